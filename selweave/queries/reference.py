"""Queries of the estimation methods, their baselines, measures and experiments."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from selweave.functions.estimate import selectivity_of
from selweave.functions.metrics import log_q_error, relative_error
from selweave.operators import baselines as bl
from selweave.operators import dens, kernels, ranges
from selweave.operators import workload as wl
from selweave.operators.query import Queries
from selweave.operators.relation import binary_bits, compact, dependencies, encoding_width, entropies, fit_dictionary, mutual_information, one_hot
from selweave.operators.truth import true_counts, true_counts_grouped, true_counts_theta, tuple_weights
from selweave.plans.advice import condition_order, join_advice
from selweave.sources.views import VIEWS, load_view
from selweave.streaming.increments import hourly_counts

from . import experiments, sql
from .common import TOTAL, Query, Relation, box, combo, errors, grouped, relation, rounded, union

RANGE_ATTRS = ["oyear", "syear", "price_band", "net_band"]
RANGE_TOTAL = 1_000


# --- views, dictionaries, encodings, information ---


def view_query(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return compact(load_view(spark, sf_dir, name), list(VIEWS[name].attributes))

    return run


def dictionary_query(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return fit_dictionary(load_view(spark, sf_dir, name), list(VIEWS[name].attributes)).frame.drop("sort")

    return run


def storage(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for name in ("orderbook", "corpus", "web", "dialog", "vecbits"):
        r = relation(spark, sf_dir, name)
        rows.append((name, r.dic.joint_size(), r.dic.independent_size(), encoding_width(r.dic), encoding_width(r.dic, "onehot")))
    return spark.createDataFrame(rows, "view string, joint_size long, independent_size long, binary_width long, one_hot_width long")


def bits_query(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "corpus")
        coded = (binary_bits if kind == "binary" else one_hot)(r.dic)
        return r.tuples.select(F.concat_ws("", F.transform(coded, lambda x: x.cast("string"))).alias("bits"), "mult")

    return run


def pair_entropies(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return rounded(entropies(r.tuples, [(a, b) for k, a in enumerate(r.attrs) for b in r.attrs[k + 1 :]]), "entropy")


def pair_information(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "orderbook")
    return rounded(mutual_information(r.tuples, [(a, b) for k, a in enumerate(r.attrs) for b in r.attrs[k + 1 :]]), "mi")


def found_dependencies(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "orderbook")
    return dependencies(r.tuples, r.attrs)


# --- workloads and truth ---


def combo_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return combo(spark, relation(spark, sf_dir, "shipments")).select("qid", F.col("k").cast("int").alias("k"), "attr", "lo")


def truth_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r)
    return true_counts(r.tuples, Queries.of_frame(w, r.dic))


def truth_grouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return true_counts_grouped(r.tuples, combo(spark, r), r.attrs)


def _range_queries(spark: SparkSession, r: Relation) -> Queries:
    return Queries.of_frame(wl.range_workload(spark, r.dic, RANGE_ATTRS, RANGE_TOTAL), r.dic)


def truth_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return true_counts(r.tuples, _range_queries(spark, r))


def truth_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return true_counts_theta(r.tuples, _range_queries(spark, r))


def workload_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return tuple_weights(r.tuples, _range_queries(spark, r)).groupBy("w").agg(F.count("*").alias("n_tuples"), F.sum("mult").alias("n_rows"))


def log_attribute_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return rounded(wl.attribute_weights(combo(spark, r), r.dic), "weight", digits=6)


def log_value_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return rounded(wl.value_weights(combo(spark, r), r.dic), "weight", digits=6)


def log_predicate_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(wl.predicate_count_distribution(combo(spark, relation(spark, sf_dir, "shipments"))), "share", digits=6)


def training_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return wl.random_training(spark, r.dic, r.tuples, 5_000)


def augmented_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return wl.augment(combo(spark, r, 200), r.dic, 1_000)


def augmented_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wl.query_weights(augmented_log(spark, sf_dir))


# --- baselines ---


def _estimates(spark: SparkSession, r: Relation, w: DataFrame, which: str) -> DataFrame:
    if which == "independence":
        return bl.independence(r.dic, w)
    q = Queries.of_frame(w, r.dic)
    if which.startswith("sample"):
        return bl.sample_estimate(bl.md5_sample(r.tuples, r.attrs), q, r.dic.rows, "constant" if which == "sample_constant" else "zero")
    net = bl.BayesNet.fit(r.tuples, r.dic, "greedy" if which == "bayes_greedy" else "tree")
    return bl.q_frame(spark, [(int(i), float(x)) for i, x in zip(q.qid, net.estimate(q))], "est_rows")


def baseline(which: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "shipments")
        return rounded(_estimates(spark, r, combo(spark, r), which).select("qid", "est_rows"), "est_rows", digits=3)

    return run


def grid(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "shipments")
        own = ["lag_band", "oyear", "price_band"]
        w = wl.range_workload(spark, r.dic, own, 60)
        return rounded(bl.grid_estimate(*bl.grid_histogram(r.tuples, r.dic, own, 800, kind), w), "est_rows")

    return run


def multicolumn(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    pair = ("nation", "region")
    w = combo(spark, r).where(F.col("attrs") == ",".join(pair))
    return rounded(bl.multicolumn_estimate(r.tuples, r.dic, pair, w), "est_rows")


def haar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every coefficient kept, so that the answers are the exact counts."""
    r = relation(spark, sf_dir, "shipments")
    own = ["oyear", "price_band"]
    w = wl.range_workload(spark, r.dic, own, 60)
    kept = bl.haar_top(bl.haar_coefficients(r.tuples, r.dic, own), own, 4096)
    return rounded(bl.haar_estimate(kept, r.dic, own, w), "est_rows", digits=2)


def haar_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    own = ["oyear", "price_band"]
    w = wl.range_workload(spark, r.dic, own, 60)
    kept = bl.haar_top(bl.haar_coefficients(r.tuples, r.dic, own), own, 12)
    return rounded(bl.haar_estimate(kept, r.dic, own, w), "est_rows", digits=2)


def error_boxes(which: str, by: str) -> Query:
    """Box rows of a baseline's q-errors by predicate count, selectivity or joint-table size."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "shipments")
        w = combo(spark, r)
        truth = true_counts(r.tuples, Queries.of_frame(w, r.dic))
        found = grouped(r, errors(truth, _estimates(spark, r, w, which)), w, (by,))
        return box(found, by)

    return run


def measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r)
    e = errors(true_counts(r.tuples, Queries.of_frame(w, r.dic)), bl.independence(r.dic, w))
    e = e.select("qid", "qerr", log_q_error(F.col("true_rows"), F.col("est_rows")).alias("log_qerr"), relative_error(F.col("true_rows"), F.col("est_rows")).alias("rel"))
    return rounded(e, "qerr", "log_qerr", "rel")


# --- exact joint tables, likelihood, planner ---


def _joint(r: Relation) -> dens.Joint:
    rows = r.tuples.toPandas()  # bounded: only for relations with a small joint table
    return dens.Joint(rows[r.attrs].to_numpy(np.int64), rows["mult"].to_numpy(float), [r.dic.cards[a] for a in r.attrs])


def joint_ranges(method: str) -> Query:
    """A range method over the exact joint table of a tiny relation."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "dialog")
        q = Queries.of_frame(wl.range_workload(spark, r.dic, r.attrs, 40), r.dic)
        return rounded(ranges.estimate(spark, [_joint(r)], q, r.dic.rows, method, 500), "est_rows")

    return run


def likelihood(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "dialog")
    models = [*dens.fit(r.tuples, r.dic, epochs=100), dens.fit_averaged(r.tuples, r.dic, dens.MaskedNet([r.dic.cards[a] for a in r.attrs], dens.attribute_order(r.attrs)))]
    return rounded(dens.nll(models, r.tuples, r.dic), "bits")


def kernel_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    q = Queries.of_frame(combo(spark, r), r.dic)
    return rounded(kernels.estimate(spark, kernels.KernelDensity.fit(r.tuples, r.dic), q, r.dic.rows), "est_rows", digits=3)


#: Conditions over the dialog relation, asked through the SQL function.
WHERES = ["role = 'user'", "turn BETWEEN 1 AND 3 AND role IN ('user', 'assistant')", "len_band >= 5", "turn > 2 AND len_band < 6", "role = 'nobody'"]


def where_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "dialog")
    asked = spark.createDataFrame([(k, t) for k, t in enumerate(WHERES)], "id int, cond string")
    return rounded(asked.select("id", selectivity_of([_joint(r)], r.dic, "enumerate")("cond").alias("sel")), "sel", digits=6)


def planner_joins(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return join_advice(bl.independence(r.dic, combo(spark, r)), 100, 100_000, 20_000)


def planner_conditions(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return condition_order(combo(spark, r), r.dic)


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {f"view_{v}": view_query(v) for v in VIEWS}
    found |= {f"dictionary_{v}": dictionary_query(v) for v in ("shipments", "partsales", "corpus", "activity")}
    found |= {
        "d1_truth_bitset": truth_points, "d1_truth_grouped": truth_grouped, "d1_truth_ranges": truth_ranges, "d1_truth_theta": truth_theta, "d2_measures": measures,
        "d8_storage": storage, "d9_entropy": pair_entropies, "d10_mutual_information": pair_information, "u18_dependencies": found_dependencies, "u2_binary_encoding": bits_query("binary"), "u3_one_hot_encoding": bits_query("onehot"),
        "w1_combo_workload": combo_query, "s11_training_queries": training_queries, "s12_attribute_weights": log_attribute_weights, "s12_value_weights": log_value_weights, "s12_predicate_counts": log_predicate_counts, "s12_augmented_log": augmented_log, "s13_query_weights": augmented_weights, "u19_tuple_weights": workload_weights,
        "b2_independence": baseline("independence"), "b3_sample": baseline("sample"), "b3a_sample_constant": baseline("sample_constant"), "b4_grid_width": grid("width"), "b4_grid_depth": grid("depth"), "b5_multicolumn": multicolumn, "b6_haar_exact": haar, "b6_haar_budget": haar_small, "b7_bayes_tree": baseline("bayes_tree"), "b7_bayes_greedy": baseline("bayes_greedy"),
        "w4_independence_by_count": error_boxes("independence", "k"), "w5_independence_by_selectivity": error_boxes("independence", "bucket"), "w6_independence_by_joint_size": error_boxes("independence", "decade"), "w25_sample_by_selectivity": error_boxes("sample", "bucket"),
        "u12_enumerate_joint": joint_ranges("enumerate"), "u13_uniform_joint": joint_ranges("uniform"), "u14_adaptive_joint": joint_ranges("adaptive"), "u15_progressive_joint": joint_ranges("progressive"), "d15_likelihood": likelihood,
        "w7_independence_by_entropy": error_boxes("independence", "quartile"), "b10_kernel_density": kernel_density, "where_function": where_function, "planner_joins": planner_joins, "planner_conditions": planner_conditions,
        "stream_hourly_counts": hourly_counts,
    }
    return found | experiments.queries()


def oracle_sql() -> dict[str, str]:
    b, ships = sql.base, sql.base("shipments")
    combo = f"{ships}, {sql.combo('shipments', TOTAL)}, {sql.combo_truth('shipments')}"
    independent = f"{combo}, {sql.INDEPENDENT}"
    ranged = f"{ships}, {sql.ranged('shipments', RANGE_ATTRS, RANGE_TOTAL)}"
    out = {}
    for v in VIEWS:
        attrs = ", ".join(sql.attrs_of(v))
        out[f"view_{v}"] = f"WITH {sql.view(v)} SELECT {attrs}, count(*) AS mult FROM v GROUP BY {attrs}"
    for v in ("shipments", "partsales", "corpus", "activity"):
        out[f"dictionary_{v}"] = f"WITH {sql.view(v)}, {sql.dictionary(v)} SELECT attr, code, value, freq FROM d"
    widths = "CAST(sum(CASE WHEN card > 1 THEN ceil(log2(card)) ELSE 0 END) AS BIGINT)"
    out["d8_storage"] = " UNION ALL ".join(f"SELECT * FROM (WITH {sql.view(v)}, {sql.dictionary(v)} SELECT '{v}' AS view, CAST(round(product(card)) AS BIGINT) AS joint_size, CAST(sum(card) AS BIGINT) AS independent_size, {widths} AS binary_width, CAST(sum(card) AS BIGINT) AS one_hot_width FROM c)" for v in ("orderbook", "corpus", "web", "dialog", "vecbits"))
    lists = {a: f"(SELECT card FROM c WHERE attr = '{a}')" for a in sql.attrs_of("corpus")}
    binary = " || ".join(f"coalesce(array_to_string([CAST(({a} >> (CAST(ceil(log2({n})) AS INT) - 1 - i)) & 1 AS VARCHAR) FOR i IN range(CASE WHEN {n} > 1 THEN CAST(ceil(log2({n})) AS INT) ELSE 0 END)], ''), '')" for a, n in lists.items())
    hot = " || ".join(f"array_to_string([CASE WHEN i = {a} THEN '1' ELSE '0' END FOR i IN range({n})], '')" for a, n in lists.items())
    wide = b("corpus") + ", n AS (SELECT " + ", ".join(f"{n} AS n_{a}" for a, n in lists.items()) + ")"
    for key, text in (("u2_binary_encoding", binary), ("u3_one_hot_encoding", hot)):
        for a, n in lists.items():
            text = text.replace(n, f"n_{a}")
        out[key] = f"{wide} SELECT {text} AS bits, mult FROM t, n"
    entropy = "round(log2(sum(m)) - sum(m * log2(m)) / sum(m), 4)"
    pairs = lambda v: [(x, y) for k, x in enumerate(sql.attrs_of(v)) for y in sql.attrs_of(v)[k + 1 :]]
    out["d9_entropy"] = ships + " " + " UNION ALL ".join(f"SELECT '{x},{y}' AS attrs, count(*) AS n_groups, {entropy} AS entropy FROM (SELECT sum(mult) AS m FROM t GROUP BY {x}, {y})" for x, y in pairs("shipments"))
    h = lambda cols: f"(SELECT log2(sum(m)) - sum(m * log2(m)) / sum(m) FROM (SELECT sum(mult) AS m FROM t GROUP BY {cols}))"
    out["d10_mutual_information"] = b("orderbook") + " " + " UNION ALL ".join(f"SELECT '{x}' AS a, '{y}' AS b, round(greatest(0.0, {h(x)} + {h(y)} - {h(f'{x}, {y}')}), 4) AS mi" for x, y in pairs("orderbook"))
    own = sql.attrs_of("orderbook")
    out["u18_dependencies"] = b("orderbook") + " SELECT determinant, dependent FROM (" + " UNION ALL ".join(f"SELECT '{x}' AS determinant, '{y}' AS dependent, max(k) AS most FROM (SELECT count(DISTINCT {y}) AS k FROM t GROUP BY {x})" for x in own for y in own if x != y) + ") WHERE most = 1"
    out["w1_combo_workload"] = f"{combo} SELECT qid, k, attr, lo FROM w"
    out["d1_truth_bitset"] = out["d1_truth_grouped"] = f"{combo} SELECT qid, true_rows FROM truth"
    out["d1_truth_ranges"] = out["d1_truth_theta"] = f"{ranged} SELECT qid, true_rows FROM truth"
    inside = " AND ".join(f"t.{a} BETWEEN r.lo_{a} AND r.hi_{a}" for a in sql.attrs_of("shipments"))
    out["u19_tuple_weights"] = f"{ranged}, x AS (SELECT t.*, (SELECT count(*) FROM r WHERE {inside}) AS w FROM t) SELECT w, count(*) AS n_tuples, CAST(sum(mult) AS BIGINT) AS n_rows FROM x GROUP BY w"
    out["s12_attribute_weights"] = f"{combo} SELECT c.attr, round(count(lo) / (SELECT count(*) FROM w), 6) AS weight FROM c LEFT JOIN w USING (attr) GROUP BY c.attr"
    out["s12_value_weights"] = f"{combo}, x AS (SELECT d.attr, code, greatest(count(w.lo), 1) AS n FROM d LEFT JOIN w ON w.attr = d.attr AND w.lo = d.code GROUP BY d.attr, code) SELECT attr, code, round(n / sum(n) OVER (PARTITION BY attr), 6) AS weight FROM x"
    out["s12_predicate_counts"] = f"{combo} SELECT k, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM ids GROUP BY k"
    out["b2_independence"] = f"{independent} SELECT qid, {sql.rnd('est_rows', 3)} AS est_rows FROM est"
    attrs = sql.attrs_of("shipments")
    sample_wide = "q AS (SELECT qid, " + ", ".join(f"max(CASE WHEN attr = '{a}' THEN lo END) AS q_{a}" for a in attrs) + " FROM w GROUP BY qid)"
    hit = " AND ".join(f"(q_{a} IS NULL OR q_{a} = s.{a})" for a in attrs)
    sampled = f"{combo}, {sql.sampled('shipments')}, {sample_wide}, total AS (SELECT sum(mult) AS n FROM t), size AS (SELECT sum(mult) AS m FROM s), est AS (SELECT qid, coalesce(sum(s.mult), 0) * any_value(n) / any_value(greatest(m, 1)) AS est_rows FROM q CROSS JOIN total CROSS JOIN size LEFT JOIN s ON {hit} GROUP BY qid)"
    out["b3_sample"] = f"{sampled} SELECT qid, {sql.rnd('est_rows', 3)} AS est_rows FROM est"
    out["b3a_sample_constant"] = f"{sampled} SELECT qid, {sql.rnd('CASE WHEN est_rows > 0 THEN est_rows ELSE n * power(0.1, k) END', 3)} AS est_rows FROM est JOIN ids USING (qid), total"
    bucket = "CASE WHEN true_rows / n >= 0.05 THEN '1: 5% or more' WHEN true_rows / n >= 0.01 THEN '2: 1% to 5%' WHEN true_rows / n >= 0.001 THEN '3: 0.1% to 1%' ELSE '4: under 0.1%' END"
    out["w4_independence_by_count"] = f"{independent}, {sql.ERRORS} {sql.box('k')}"
    out["w5_independence_by_selectivity"] = f"{independent}, {sql.ERRORS}, e2 AS (SELECT errors.*, {bucket} AS bucket FROM errors, total) {sql.box('bucket', 'e2')}"
    out["w25_sample_by_selectivity"] = f"{sampled}, {sql.ERRORS}, e2 AS (SELECT errors.*, {bucket} AS bucket FROM errors, total) {sql.box('bucket', 'e2')}"
    out["w6_independence_by_joint_size"] = f"{independent}, {sql.ERRORS}, z AS (SELECT qid, CAST(floor(sum(log10(card)) + 1e-9) AS INT) AS decade FROM w JOIN c USING (attr) GROUP BY qid), e2 AS (SELECT * FROM errors JOIN z USING (qid)) {sql.box('decade', 'e2')}"
    out["d2_measures"] = f"{independent}, {sql.ERRORS} SELECT qid, {sql.rnd('qerr', 4)} AS qerr, {sql.rnd('log10(qerr)', 4)} AS log_qerr, {sql.rnd('abs(est_rows - true_rows) / greatest(true_rows, 1.0)', 4)} AS rel FROM errors"
    small = f"{b('dialog')}, {sql.ranged('dialog', sql.attrs_of('dialog'), 40)}"
    out["u12_enumerate_joint"] = f"{small} SELECT qid, CAST(true_rows AS DOUBLE) AS est_rows FROM truth"
    out["b6_haar_exact"] = f"{ships}, {sql.ranged('shipments', ['oyear', 'price_band'], 60)} SELECT qid, CAST(true_rows AS DOUBLE) AS est_rows FROM truth"
    out["w7_independence_by_entropy"] = f"{independent}, {sql.ERRORS}, h AS (SELECT attrs, round(log2(sum(n)) - sum(n * log2(n)) / sum(n), 6) AS h FROM cube WHERE attrs IN (SELECT attrs FROM ids) GROUP BY attrs), z AS (SELECT attrs, ntile(4) OVER (ORDER BY h, attrs) AS quartile FROM h), e2 AS (SELECT * FROM errors JOIN z USING (attrs)) {sql.box('quartile', 'e2')}"
    out["s11_training_queries"] = f"{ships}, {sql.training('shipments', 5_000)}"
    logged = f"{ships}, {sql.combo('shipments', 200)}, {sql.augmented('shipments', 1_000)}"
    out["s12_augmented_log"] = f"{logged} SELECT qid, attr, lo, hi, in_workload FROM every"
    out["s13_query_weights"] = f"{logged}, q AS (SELECT DISTINCT qid, in_workload FROM every) SELECT qid, in_workload, CASE WHEN in_workload THEN 1.0 ELSE (SELECT count(*) FILTER (WHERE in_workload) / count(*) FROM q) END AS weight FROM q"
    out["s11a_naive_queries"] = f"{ships}, {sql.naive(5_000, len(attrs))}"
    gridded = ["lag_band", "oyear", "price_band"]
    for kind in ("width", "depth"):
        out[f"b4_grid_{kind}"] = f"{ships}, {sql.ranged('shipments', gridded, 60)}, {sql.grid(gridded, 800, kind)} SELECT qid, {sql.rnd('est_rows', 4)} AS est_rows FROM est"
    out["b5_multicolumn"] = (
        f"{combo}, n AS (SELECT sum(mult) AS n FROM t), g AS (SELECT nation, region, sum(mult) AS freq FROM t GROUP BY ALL), top AS (SELECT *, row_number() OVER (ORDER BY freq DESC, nation, region) AS r FROM g), "
        "degree AS (SELECT sum(CASE WHEN k = 1 THEN m ELSE 0 END) / sum(m) AS d FROM (SELECT nation, count(DISTINCT region) AS k, sum(mult) AS m FROM t GROUP BY nation)), "
        "wide AS (SELECT qid, max(CASE WHEN attr = 'nation' THEN lo END) AS va, max(CASE WHEN attr = 'region' THEN lo END) AS vb FROM w WHERE attrs = 'nation,region' GROUP BY qid) "
        f"SELECT qid, {sql.rnd('coalesce(top.freq, da.freq * (d + (1 - d) * db.freq / n), 0)', 4)} AS est_rows FROM wide LEFT JOIN top ON nation = va AND region = vb AND r <= 50 LEFT JOIN d da ON da.attr = 'nation' AND da.code = va LEFT JOIN d db ON db.attr = 'region' AND db.code = vb, degree, n"
    )
    out["d2a_empty_truth"] = f"{combo} SELECT k, count(*) AS n, CAST(count(*) FILTER (WHERE true_rows = 0) AS BIGINT) AS empty_true FROM truth GROUP BY k"
    out["gates"] = " UNION ALL ".join(f"SELECT '{g}' AS gate, true AS holds" for g in experiments.GATES)
    out["w23_wide_range"] = f"WITH {sql.view('partsales')}, {sql.dictionary('partsales')} SELECT CAST(10000 AS BIGINT) AS points, count(*) AS est_rows FROM v JOIN d a ON a.attr = 'partkey' AND a.value = CAST(v.partkey AS VARCHAR) JOIN d b ON b.attr = 'suppkey' AND b.value = CAST(v.suppkey AS VARCHAR) WHERE a.code < 100 AND b.code < 100"
    orders = f"WITH {sql.view('orderbook')}"
    coded = "x AS (SELECT CAST(row_number() OVER (ORDER BY priority NULLS FIRST) - 1 AS INT) AS code, count(*) OVER () AS card FROM v GROUP BY priority)"
    width = "CASE WHEN card > 1 THEN CAST(ceil(log2(card)) AS INT) ELSE 0 END"
    out["w24_encodings"] = f"{orders}, {coded} SELECT code, array_to_string([CASE WHEN i = code THEN '1' ELSE '0' END FOR i IN range(card)], '') AS one_hot, coalesce(array_to_string([CAST((code >> ({width} - 1 - CAST(i AS INT))) & 1 AS VARCHAR) FOR i IN range({width})], ''), '') AS bits FROM x"
    shares = "s AS (SELECT count(*) / sum(count(*)) OVER () AS s FROM v GROUP BY nation), m AS (SELECT min(-log10(s)) AS low, max(-log10(s)) AS high FROM s)"
    out["w24_scaling"] = f"{orders}, {shares} SELECT s AS selectivity, round(-log10(s) * 1.000000001, 4) AS raw, round((-log10(s) - low) / CASE WHEN high > low THEN high - low ELSE 1 END * 1.000000001, 4) AS scaled FROM s, m"
    logged_orders = "d AS (SELECT 'status' AS attr, status AS value, count(*) AS n FROM v GROUP BY status UNION ALL SELECT 'priority', priority, count(*) FILTER (WHERE omonth > 6) FROM v GROUP BY priority), y AS (SELECT attr, n, CAST(row_number() OVER (PARTITION BY attr ORDER BY value NULLS FIRST) - 1 AS INT) AS code FROM d)"
    out["w24_weights"] = f"{orders}, {logged_orders} SELECT attr, code, round(w * 1.000000001, 6) AS weight FROM (SELECT attr, -1 AS code, sum(n) / greatest(sum(sum(n)) OVER (), 1) AS w FROM y GROUP BY attr UNION ALL SELECT attr, code, greatest(n, 1) / sum(greatest(n, 1)) OVER (PARTITION BY attr) FROM y)"
    out["s3_discretised"] = (
        "WITH p AS (SELECT l_extendedprice AS x FROM lineitem), m AS (SELECT min(x) AS low, max(x) AS high, quantile_cont(x, [0.125, 0.25, 0.375, 0.5, 0.625, 0.75, 0.875]) AS q FROM p) "
        "SELECT 'width' AS kind, CAST(least(floor((x - low) / ((high - low) / 8)), 7) AS INT) AS bin, count(*) AS n FROM p, m GROUP BY ALL UNION ALL SELECT 'quantile', CAST(len([c FOR c IN q IF x > c]) AS INT), count(*) FROM p, m GROUP BY ALL"
    )
    out["s4_scaled_bounds"] = f"{ships}, {sql.ranged('shipments', ['oyear', 'price_band'], 200)} SELECT q.qid, c.attr, round(coalesce(lo, 0) / greatest(card - 1, 1) * 1.000000001, 4) AS low, round(coalesce(hi, card - 1) / greatest(card - 1, 1) * 1.000000001, 4) AS high, CASE WHEN coalesce(lo, 0) > 0 OR coalesce(hi, card - 1) < card - 1 THEN 1 ELSE 0 END AS asked FROM (SELECT DISTINCT qid FROM w) q CROSS JOIN c LEFT JOIN w ON w.qid = q.qid AND w.attr = c.attr"
    middle = "m AS (SELECT y[len(y) // 2 + 1] AS x FROM (SELECT list_sort(list(DISTINCT oyear)) AS y FROM v WHERE oyear IS NOT NULL))"
    slots = (("=", "10000"), ("<", "01000"), ("<=", "00100"), (">", "00010"), (">=", "00001"))
    out["s5_operators"] = f"{orders}, {middle} " + " UNION ALL ".join(f"SELECT '{o}' AS operator, '{x}' AS slots, count(*) AS true_rows FROM v, m WHERE oyear {o} x" for o, x in slots) + " UNION ALL SELECT 'none', '00000', count(*) FROM v"
    out["where_function"] = f"WITH {sql.view('dialog')} " + " UNION ALL ".join(f"SELECT {k} AS id, round(count(*) FILTER (WHERE {t}) / count(*) * 1.000000001, 6) AS sel FROM v" for k, t in enumerate(WHERES))
    out["planner_joins"] = f"{independent} SELECT qid, CASE WHEN est_rows * 100 <= 100000 THEN 'broadcast' ELSE 'shuffle' END AS strategy, CAST(greatest(1, ceil(est_rows * 100 / 20000.0)) AS INT) AS partitions FROM est"
    out["planner_conditions"] = f"{combo} SELECT qid, w.attr, CAST(row_number() OVER (PARTITION BY qid ORDER BY freq, w.attr) AS INT) AS place FROM w JOIN d ON d.attr = w.attr AND d.code = w.lo"
    out["stream_hourly_counts"] = "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL"
    return out

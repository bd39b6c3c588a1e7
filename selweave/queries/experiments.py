"""Experiments on whole logs: comparison at equal space, sweeps, increments, latency, and gates on their findings."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from selweave.operators import baselines as bl
from selweave.operators import conditionals, dens, kernels, ranges, reg
from selweave.operators import workload as wl
from selweave.operators.query import Predicate, Queries
from selweave.operators.relation import binary_bits, compact, discretise, encode_codes, fit_dictionary, one_hot
from selweave.operators.statistics import ColumnStatistics, GridModel, PairStatistics, WaveletModel
from selweave.operators.truth import true_counts, tuple_weights
from selweave.sources.views import load_view, table

from .common import BOX, Query, Relation, box, combo, errors, grouped, labelled, relation, rounded, union

#: Attributes of the second relation; some domains are large.
SECOND = ["brand", "type", "size", "qty", "price_c"]
#: Part of the second relation's distinct tuples that the networks of ``w10_encoding_second`` train on.
SECOND_SHARE = 0.1
#: Paths of a sampled answer.
SAMPLES = 200
TRAINING = 5_000

_TRAINED: dict[tuple, list] = {}


def trained(sf_dir: str, r: Relation, **options: object) -> list[dens.MaskedNet]:
    """Networks of a relation; a process trains each setting once, as a user would keep a fitted model."""
    key = (sf_dir, r.name, tuple(r.attrs), tuple(sorted((k, str(v)) for k, v in options.items())))
    if key not in _TRAINED:
        _TRAINED[key] = dens.fit(r.tuples, r.dic, **options)
    return _TRAINED[key]


def _nets(r: Relation, configs: list[dict]) -> list[dens.MaskedNet]:
    cards = [r.dic.cards[a] for a in r.attrs]
    return [dens.MaskedNet(cards, dens.attribute_order(r.attrs, seed=c.pop("order_seed", 0), before=c.pop("before", None)), **c) for c in map(dict, configs)]


def judged(spark: SparkSession, r: Relation, w: DataFrame, models: dict[str, list], by: list[str], method: str = "auto", samples: int = SAMPLES) -> DataFrame:
    """Box rows of each configuration's q-errors over a log."""
    q = Queries.of_frame(w, r.dic)
    truth = grouped(r, true_counts(r.tuples, q), w, tuple(by)).persist()
    parts = [errors(truth, ranges.estimate(spark, m, q, r.dic.rows, method, samples)).withColumn("config", F.lit(c)) for c, m in models.items()]
    return box(union(parts), "config", *by)


def sweep(configs: dict[str, dict], view: str = "shipments", attrs: list[str] | None = None, by: tuple[str, ...] = (), pick: Callable[[DataFrame], DataFrame] = lambda w: w, total: int = 10_000, **options: object) -> Query:
    """Networks that differ in one setting, trained side by side and judged on the same log."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, view, attrs)
        w = pick(combo(spark, r, total, values="anchored")).persist()
        models = dens.fit(r.tuples, r.dic, start=_nets(r, list(configs.values())), **options)
        return judged(spark, r, w, {c: [m] for c, m in zip(configs, models)}, list(by))

    return run


def order_ensembles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Means over one to ten orders; every network answers the log once."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, values="anchored")
    q = Queries.of_frame(w, r.dic)
    truth = true_counts(r.tuples, q).persist()
    models = dens.fit(r.tuples, r.dic, orders=10)
    each = union([ranges.estimate(spark, [m], q, r.dic.rows, samples=SAMPLES).withColumn("model", F.lit(k)) for k, m in enumerate(models)]).persist()
    parts = [errors(truth, each.where(F.col("model") < k).groupBy("qid").agg(F.avg("est_rows").alias("est_rows"))).withColumn("config", F.lit(f"{k} orders")) for k in (1, 2, 3, 5, 10)]
    return box(union(parts), "config")


def mask_cycles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One draw of the hidden units' connections against cycles of four and eight."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, values="anchored")
    return judged(spark, r, w, {"one draw": trained(sf_dir, r), "cycle of 4": trained(sf_dir, r, masks=4), "cycle of 8": trained(sf_dir, r, masks=8)}, [])


def invalid_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mass on bit patterns without a value: left out by renormalising, or kept."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, values="anchored")
    kept = [dens.MaskedNet(m.cards, m.order, m.hidden, m.encoding, m.unit, "ignore", m.seed) for m in trained(sf_dir, r)]
    for m, own in zip(kept, trained(sf_dir, r)):
        m.net = own.net
    return judged(spark, r, w, {"renormalise": trained(sf_dir, r), "ignore": kept}, [])


def dens_by(*by: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "shipments")
        return judged(spark, r, combo(spark, r, values="anchored"), {"dens": trained(sf_dir, r)}, list(by))

    return run


def range_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All range methods on one trained network, and adaptive sampling without its correction; truth is the relation."""
    r = relation(spark, sf_dir, "shipments")
    w = wl.range_workload(spark, r.dic, ["oyear", "syear", "price_band", "net_band"], 1_000).persist()
    models, q = trained(sf_dir, r, order="natural"), Queries.of_frame(w, r.dic)
    truth = true_counts(r.tuples, q).persist()
    parts = [errors(truth, ranges.estimate(spark, models, q, r.dic.rows, m, 500)).withColumn("method", F.lit(m)) for m in ("uniform", "adaptive", "progressive")]
    low, high = q.low.astype(np.int64), q.high.astype(np.int64)
    tables = spark.sparkContext.defaultParallelism
    naive = q.frame(spark).repartition(tables, "qid").mapInPandas(_uncorrected(models, r.dic.rows), "qid long, est_rows double") if len(low) and len(high) else None
    if naive is not None:
        parts.append(errors(truth, naive).withColumn("method", F.lit("adaptive, uncorrected")))
    return box(union(parts), "method")


def _uncorrected(models: list, rows: int):
    def run(batches):
        for part in batches:
            found = [np.mean([ranges.adaptive_box(m, np.array(lo), np.array(hi), 500, seed=[0, int(i)], corrected=False) for m in models]) for i, lo, hi in zip(part["qid"], part["low"], part["high"])]
            part = part[["qid"]].assign(est_rows=np.array(found, float) * rows)
            yield part

    return run


def injected_workload(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With and without loss weights from a log, and weights grown by a second log; judged on held-out queries of the same log."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, values="anchored").where(F.col("k") >= 3).persist()
    held = w.where(F.col("qid") % 5 == 0).persist()
    first, second = (w.where(F.col("qid") % 5 == k) for k in (1, 2))
    one = tuple_weights(r.tuples, Queries.of_frame(first, r.dic)).withColumn("lw", F.col("mult") * (1 + F.col("w"))).persist()
    # weights are additive over queries: the second log's are added to the first one's
    two = tuple_weights(one.withColumnRenamed("w", "w0").drop("lw"), Queries.of_frame(second, r.dic)).withColumn("lw", F.col("mult") * (1 + F.col("w0") + F.col("w"))).persist()
    plain = trained(sf_dir, r)
    tuned = dens.fit(one, r.dic, weight="lw")
    grown = dens.fit(two, r.dic, start=tuned, epochs=20, rate=5e-4, dropout=0.1, weight="lw")
    return judged(spark, r, held, {"plain": plain, "weighted": tuned, "second log added": grown}, [])


def single_networks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A network for every conditional against one masked network of all."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, values="anchored")
    return judged(spark, r, w, {"per attribute": [conditionals.fit(r.tuples, r.dic)], "masked": trained(sf_dir, r)}, [])


# --- comparison at equal space ---


def _widest(size: Callable[[int], int], budget: int) -> int:
    """The most hidden units a layer whose network fits the budget."""
    return max((h for h in range(4, 400, 4) if size(h) <= budget), default=4)


def _networks(r: Relation, budgets: tuple[int, ...], share: float = 1.0) -> dict[int, dens.MaskedNet]:
    """The widest masked network of each budget, trained side by side."""
    cards, order = [r.dic.cards[a] for a in r.attrs], dens.attribute_order(r.attrs)
    widths = [_widest(lambda h: dens.MaskedNet(cards, order, (h, h)).size_bytes(), b) for b in budgets]
    return dict(zip(budgets, dens.fit(r.tuples, r.dic, start=[dens.MaskedNet(cards, order, (h, h)) for h in widths], share=share)))


def _fits(spark: SparkSession, r: Relation, budget: int, networks: dict[int, dens.MaskedNet]) -> dict[str, Callable[[], tuple[Callable[[Queries], object], int]]]:
    """By estimator: fits it to the budget; gives what answers queries on the driver or as a job, and its bytes."""
    m = len(r.attrs)
    rows = max(1, budget // (4 * m + 8))

    def local(model: object) -> tuple[Callable[[Queries], object], int]:
        return (lambda q: model.estimate(q)), model.size_bytes()

    def regressor(make: Callable[[], object], size: Callable[[object], int]) -> tuple[Callable[[Queries], object], int]:
        model = make()
        return (lambda q: model.selectivity(q) * r.dic.rows), size(model)

    def masked() -> tuple[Callable[[Queries], object], int]:
        models = [networks[budget]]
        return (lambda q: ranges.boxes(models, q.low.astype(np.int64), q.high.astype(np.int64), "auto", SAMPLES, [[0, int(i)] for i in q.qid]) * r.dic.rows if len(q) < 100 else ranges.estimate(spark, models, q, r.dic.rows, samples=SAMPLES)), models[0].size_bytes()

    def sampled() -> tuple[Callable[[Queries], object], int]:
        sample = bl.md5_sample(r.tuples, r.attrs, min(1.0, rows / max(r.dic.rows, 1))).persist()
        return (lambda q: bl.sample_estimate(sample, q, r.dic.rows)), int(sample.count()) * (4 * m + 8)

    def density() -> tuple[Callable[[Queries], object], int]:
        model = kernels.KernelDensity.fit(r.tuples, r.dic, rows)
        return (lambda q: kernels.estimate(spark, model, q, r.dic.rows)), model.size_bytes()

    log = lambda: labelled(r, wl.random_training(spark, r.dic, r.tuples, TRAINING))

    def supervised() -> tuple[Callable[[Queries], object], int]:
        q, y = log()
        inputs = reg.encode_queries(q).shape[1]
        h = _widest(lambda h: 4 * (inputs * h + h * h + 3 * h + 1), budget)
        return regressor(lambda: reg.Regressor(r.dic.rows, hidden=(h, h)).fit(q, y), lambda x: x.size_bytes())

    coarse = lambda structure: max((b for b in (2, 3, 4, 6, 8, 12, 16, 24, 32, 64) if _net_bytes(r, b, structure) <= budget), default=2)
    three = sorted(r.attrs, key=lambda a: (-min(r.dic.cards[a], 32), a))[:3]
    return {
        "independence": lambda: local(ColumnStatistics.fit(r.dic, 10**9)),
        "column statistics": lambda: local(ColumnStatistics.fit(r.dic, budget)),
        "pair statistics": lambda: local(PairStatistics.fit(r.tuples, r.dic, budget)),
        "grid, equal width": lambda: local(GridModel.fit(r.tuples, r.dic, budget, "width")),
        "grid, equal depth": lambda: local(GridModel.fit(r.tuples, r.dic, budget, "depth")),
        "wavelet": lambda: local(WaveletModel.fit(r.tuples, r.dic, three, budget)),
        "sample": sampled,
        "kernels": density,
        "bayes tree": lambda: local(bl.BayesNet.fit(r.tuples, r.dic, "tree", coarse("tree"))),
        "bayes greedy": lambda: local(bl.BayesNet.fit(r.tuples, r.dic, "greedy", coarse("greedy"))),
        "linear": lambda: regressor(lambda: reg.LinearModel(r.dic.rows).fit(*log()), lambda x: x.w.nbytes),
        "support vectors": lambda: regressor(lambda: reg.SupportVectorModel(r.dic.rows).fit(*log()), lambda x: x.w.nbytes),
        "dens": masked,
        "reg": supervised,
    }


def _net_bytes(r: Relation, bins: int, structure: str) -> int:
    """Upper bound of a network's tables with so many bins an attribute."""
    n = sorted((min(bins, r.dic.cards[a]) for a in r.attrs), reverse=True)
    if structure == "tree":
        return 8 * sum(x * n[0] for x in n)
    return 8 * sum(x * n[0] * n[min(1, len(n) - 1)] for x in n) // 2


def comparison(view: str = "shipments", attrs: list[str] | None = None, budgets: tuple[int, ...] = (64_000,)) -> Query:
    """Every estimator cut to the same bytes on one log, at every budget: box of q-errors, bytes, seconds to fit, milliseconds a query.

    The masked networks of all budgets are trained in one job on all tuples, whose seconds stand with each.
    Of an estimator that answers as a job, a query's time is the job's over the whole log, by its queries.
    """

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, view, attrs)
        q = Queries.of_frame(combo(spark, r, values="anchored"), r.dic)
        truth = true_counts(r.tuples, q).persist()
        began = time.perf_counter()
        networks = _networks(r, budgets)
        trained_s, parts = time.perf_counter() - began, []
        for budget in budgets:
            for name, fit in _fits(spark, r, budget, networks).items():
                began = time.perf_counter()
                answer, size = fit()
                took = time.perf_counter() - began + (trained_s if name == "dens" else 0)
                if name in ("sample", "kernels"):
                    began = time.perf_counter()
                    found = answer(q).persist()
                    mean = 1e3 * (time.perf_counter() - began) / asked if (asked := found.count()) else 0.0
                else:
                    mean, found = reg.latency_ms(answer, q, 200)[0], answer(q)
                if not isinstance(found, DataFrame):
                    found = bl.q_frame(spark, [(int(i), float(x)) for i, x in zip(q.qid, found)], "est_rows")
                part = errors(truth, found.select("qid", "est_rows"))
                parts.append(part.withColumn("estimator", F.lit(name)).withColumn("budget", F.lit(budget)).withColumn("bytes", F.lit(size).cast("long")).withColumn("fit_s", F.lit(round(took, 2))).withColumn("latency_ms", F.lit(round(mean, 3))))
        return box(union(parts), "estimator", "budget", "bytes", "fit_s", "latency_ms")

    return run


# --- the supervised estimator ---


def _judge(spark: SparkSession, r: Relation, models: dict[str, object], *by: str, preds: DataFrame | None = None, tuples: DataFrame | None = None) -> DataFrame:
    w = combo(spark, r, seed=9, values="anchored") if preds is None else preds
    q = Queries.of_frame(w, r.dic)
    truth = grouped(r, true_counts(r.tuples if tuples is None else tuples, q), w, by).persist() if preds is None else true_counts(r.tuples if tuples is None else tuples, q).persist()
    return box(union([errors(truth, reg.estimate(spark, m, q)).withColumn("config", F.lit(c)) for c, m in models.items()]), "config", *by)


def regressors(view: str = "shipments", attrs: list[str] | None = None) -> Query:
    """The q-error network against the squared-error network and the linear and support-vector baselines."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, view, attrs)
        q, y = labelled(r, wl.random_training(spark, r.dic, r.tuples, TRAINING))
        n = r.dic.rows
        models = {"qerror": reg.Regressor(n).fit(q, y), "mse": reg.Regressor(n, loss="mse").fit(q, y), "sum": reg.Regressor(n, ratio="sum").fit(q, y), "linear": reg.LinearModel(n).fit(q, y), "svr": reg.SupportVectorModel(n).fit(q, y), "svr_rbf": reg.SupportVectorModel(n, "rbf").fit(q, y)}
        return _judge(spark, r, models)

    return run


def reg_by(by: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = relation(spark, sf_dir, "shipments")
        q, y = labelled(r, wl.random_training(spark, r.dic, r.tuples, 10_000))
        return _judge(spark, r, {"reg": reg.Regressor(r.dic.rows).fit(q, y)}, by)

    return run


def training_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Regressors of fewer and more training queries and epochs."""
    r = relation(spark, sf_dir, "shipments")
    models = {}
    for budget in (2_500, 5_000, 10_000):
        q, y = labelled(r, wl.random_training(spark, r.dic, r.tuples, budget))
        models |= {f"{budget} queries, {e} epochs": reg.Regressor(r.dic.rows).fit(q, y, epochs=e) for e in (10, 50, 100)}
    return _judge(spark, r, models)


def query_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training queries with a tuple's values against values drawn evenly from the domains."""
    r = relation(spark, sf_dir, "shipments")
    made = {"by frequency": wl.random_training(spark, r.dic, r.tuples, TRAINING), "naive": wl.naive_training(spark, r.dic, TRAINING)}
    return _judge(spark, r, {c: reg.Regressor(r.dic.rows).fit(*labelled(r, w)) for c, w in made.items()})


def range_regressors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range queries by four encodings: one-hot of covered values, the same without a mark of what is asked, scaled bounds, operators with scaled values."""
    r = relation(spark, sf_dir, "shipments")
    own = ["oyear", "syear", "price_band", "net_band", "lag_band"]
    q, y = labelled(r, wl.range_workload(spark, r.dic, own, TRAINING, seed=11))
    models = {kind: reg.Regressor(r.dic.rows, encoding=kind).fit(q, y) for kind in ("onehot", "multihot", "bounds", "operators")}
    return _judge(spark, r, models, preds=wl.range_workload(spark, r.dic, own, 2_000, seed=7))


def reg_augmentation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A log alone (no look at the relation: only its recorded answers), generated queries alone, and the log augmented with weighted new ones."""
    r = relation(spark, sf_dir, "shipments")
    log = combo(spark, r, 1_000, values="anchored").select("qid", "attr", "lo", "hi").persist()
    more = wl.augment(log, r.dic, TRAINING).persist()
    weights = {x["qid"]: x["weight"] for x in wl.query_weights(more).collect()}  # bounded: a training log
    q, y = labelled(r, more)
    n = r.dic.rows
    models = {"log": reg.Regressor(n).fit(*labelled(r, log)), "random": reg.Regressor(n).fit(*labelled(r, wl.random_training(spark, r.dic, r.tuples, TRAINING))), "augmented": reg.Regressor(n).fit(q, y, np.array([weights[int(i)] for i in q.qid]))}
    return _judge(spark, r, models)


def data_free(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training from recorded (query, answer) pairs alone, for logs of growing length."""
    r = relation(spark, sf_dir, "shipments")
    q, y = labelled(r, combo(spark, r, seed=3, values="anchored"))
    turn = np.random.default_rng(0).permutation(len(q))
    return _judge(spark, r, {f"{n} recorded": reg.Regressor(r.dic.rows).fit(q.take(np.sort(turn[:n])), y[np.sort(turn[:n])]) for n in (500, 2_000, 8_000) if n <= len(q)})


def _split_activity(spark: SparkSession, sf_dir: str) -> tuple[Relation, DataFrame, DataFrame]:
    attrs = ["event_type", "hr", "daypart", "dom", "dow", "vband"]
    df = load_view(spark, sf_dir, "activity")
    dic = fit_dictionary(df, attrs)
    dic.frame = dic.frame.persist()
    cut = df.agg(F.percentile("event_id", 0.8)).first()[0]
    old, new = (compact(encode_codes(df.where(c), dic), attrs).persist() for c in (F.col("event_id") <= cut, F.col("event_id") > cut))
    both = compact(old.unionByName(new), attrs).persist()
    return Relation("activity", attrs, dic, both), old, new


def increments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Likelihood (bits a tuple) on old and new rows: refit, forgetful fine-tuning, fine-tuning with dropout."""
    r, old, new = _split_activity(spark, sf_dir)
    first = dens.fit(old, r.dic)
    models = {"before": first, "refit": dens.fit(r.tuples, r.dic), "naive": dens.fine_tune(first, new, r.dic, dropout=0.0), "dropout": dens.fine_tune(first, new, r.dic)}
    flat = [m[0] for m in models.values()]
    names = F.array(*map(F.lit, models))
    parts = [dens.nll(flat, part, r.dic).select(names[F.col("model")].alias("config"), F.lit(label).alias("part"), "bits") for label, part in (("old", old), ("new", new))]
    return rounded(union(parts), "bits")


def reg_increments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """After new tuples: the old regressor, one with refreshed answers, one trained anew; judged on all rows."""
    r, old, new = _split_activity(spark, sf_dir)
    asked = wl.random_training(spark, r.dic, old, TRAINING)
    q = Queries.of_frame(asked, r.dic)
    was = {x["qid"]: x["true_rows"] for x in true_counts(old, q).collect()}  # bounded: a training log
    y = np.array([was[int(i)] for i in q.qid], float)
    n = int(old.agg(F.sum("mult")).first()[0])
    models = {"before": reg.Regressor(n).fit(q, y)}
    models["refreshed"], now = reg.Regressor(n).fit(q, y).refresh(q, y, new)
    models["refit"] = reg.Regressor(r.dic.rows).fit(q, now)
    return _judge(spark, r, models)


def reg_new_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """After queries of another kind: before, forgetful and careful fine-tuning on them alone; judged on the old kind (up to three predicates) and the new."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, seed=5, values="anchored")
    few, many = (w.where(c).persist() for c in (F.col("k") <= 3, F.col("k") > 3))
    train, test = (lambda x: x.where(F.col("qid") % 4 != 0)), (lambda x: x.where(F.col("qid") % 4 == 0))
    q, y = labelled(r, train(few))
    q2, y2 = labelled(r, train(many))
    fresh = lambda: reg.Regressor(r.dic.rows).fit(q, y)
    models = {"before": fresh(), "naive": fresh().fit(q2, y2, epochs=100), "fine-tuned": fresh().fine_tune(q2, y2)}
    return union([_judge(spark, r, models, preds=test(x)).withColumn("log", F.lit(label)) for label, x in (("few predicates", few), ("many predicates", many))])


# --- findings as gates ---


def gates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the estimators should show on the whole log; every row holds or not."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r, values="anchored")
    q = Queries.of_frame(w, r.dic)
    truth = true_counts(r.tuples, q).persist()
    own = box(errors(truth, ranges.estimate(spark, trained(sf_dir, r), q, r.dic.rows, samples=SAMPLES)).withColumn("x", F.lit(1)), "x").first()
    plain = box(errors(truth, bl.independence(r.dic, w)).withColumn("x", F.lit(1)), "x").first()
    log = labelled(r, wl.random_training(spark, r.dic, r.tuples, 10_000))
    sup, mse = (box(errors(truth, reg.estimate(spark, reg.Regressor(r.dic.rows, loss=loss).fit(*log), q)).withColumn("x", F.lit(1)), "x").first() for loss in ("qerror", "mse"))
    held = [("dens: median within a factor of 2", own["p50"] <= 2), ("dens: three quarters within a factor of 2", own["p75"] <= 2), ("dens: mean better than independence", own["mean"] < plain["mean"]), ("reg: median within a factor of 2", sup["p50"] <= 2), ("reg: q-error loss has the better mean", sup["mean"] <= mse["mean"])]
    return spark.createDataFrame([(a, bool(b)) for a, b in held], "gate string, holds boolean")


GATES = ["dens: median within a factor of 2", "dens: three quarters within a factor of 2", "dens: mean better than independence", "reg: median within a factor of 2", "reg: q-error loss has the better mean"]


# --- small worked cases ---


def worked_encodings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The domain of the order priority: one-hot and binary codes."""
    r = relation(spark, sf_dir, "orderbook", ["priority"])
    text = lambda bits: F.concat_ws("", F.transform(bits, lambda x: x.cast("string")))
    return r.tuples.select(F.col("priority").alias("code"), text(one_hot(r.dic)).alias("one_hot"), text(binary_bits(r.dic)).alias("bits"))


def worked_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The selectivity of each nation among the orders, its log and the scaled log."""
    r = relation(spark, sf_dir, "orderbook", ["nation"])
    sel = np.array([f for _, f in r.dic.values("nation")], float) / max(r.dic.rows, 1)
    scaler = reg.TargetScaler(r.dic.rows).fit(sel)
    return rounded(spark.createDataFrame([(float(s), float(x), float(y)) for s, x, y in zip(sel, scaler.raw(sel), scaler.transform(sel))], "selectivity double, raw double, scaled double"), "raw", "scaled")


def worked_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A log in which every order asks for its status, and those from July on for their priority too: weights of attributes and values."""
    df = load_view(spark, sf_dir, "orderbook")
    dic = fit_dictionary(df, ["status", "priority"])
    asked = F.array(F.struct(F.lit("status").alias("attr"), F.col("status").alias("lo")), F.when(F.col("omonth") > 6, F.struct(F.lit("priority").alias("attr"), F.col("priority").alias("lo"))))
    preds = encode_codes(df, dic, keep=["omonth"]).select(F.explode(F.filter(asked, lambda x: x.isNotNull())).alias("x")).select("x.attr", "x.lo")
    attrs = wl.attribute_weights(preds, dic).select("attr", F.lit(-1).alias("code"), "weight")
    return rounded(attrs.unionByName(wl.value_weights(preds, dic).select("attr", "code", "weight")), "weight", digits=6)


def wide_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A range over two attributes of a hundred values each, asked as its single points: their number and the sum of their counts."""
    r = relation(spark, sf_dir, "partsales", ["partkey", "suppkey"])
    points = spark.range(100).select(F.col("id").cast("int").alias("partkey")).join(F.broadcast(spark.range(100).select(F.col("id").cast("int").alias("suppkey"))), F.lit(True))  # 10,000 points
    found = points.join(r.tuples, ["partkey", "suppkey"], "left")
    return found.agg(F.count("*").alias("points"), F.coalesce(F.sum("mult"), F.lit(0)).cast("long").alias("est_rows"))


def discretised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A numeric column in eight bins of equal width and of equal depth, with their rows."""
    df = table(spark, sf_dir, "lineitem").select("l_extendedprice")
    return union([df.select(F.lit(kind).alias("kind"), discretise(df, "l_extendedprice", 8, kind).alias("bin")).groupBy("kind", "bin").agg(F.count("*").alias("n")) for kind in ("width", "quantile")])


def scaled_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range predicates by scaled bounds, with a mark of what is asked."""
    r = relation(spark, sf_dir, "shipments")
    q = Queries.of_frame(wl.range_workload(spark, r.dic, ["oyear", "price_band"], 200), r.dic)
    x = reg.encode_queries(q, "bounds").reshape(len(q), len(q.attrs), 3)
    rows = [(int(i), a, float(v[0]), float(v[1]), int(v[2])) for i, own in zip(q.qid, x) for a, v in zip(q.attrs, own)]
    return rounded(spark.createDataFrame(rows, "qid long, attr string, low double, high double, asked int"), "low", "high")


def operator_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Comparison operators as slots, and the orders that each finds at the middle one of their years."""
    r = relation(spark, sf_dir, "orderbook", ["oyear"])
    years = [v for v, _ in r.dic.values("oyear") if v is not None]
    asked = [*reg.OPERATORS, None]
    boxes, of = Queries.of_predicates([[Predicate("oyear", o, (years[len(years) // 2],))] if o and years else [] for o in asked], r.dic)
    found = {x["qid"]: x["true_rows"] for x in true_counts(r.tuples, boxes).collect()}  # one row an operator
    rows = [(o or "none", "".join(str(int(v)) for v in x), sum(int(found[int(i)]) for i in boxes.qid[of == k])) for k, (o, x) in enumerate(zip(asked, reg.operator_slots(asked)))]
    return spark.createDataFrame(rows, "operator string, slots string, true_rows long")


def naive_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = relation(spark, sf_dir, "shipments")
    return wl.naive_training(spark, r.dic, 5_000)


def column_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Common values and equal-depth buckets of each column, attributes independent."""
    r = relation(spark, sf_dir, "shipments")
    q = Queries.of_frame(combo(spark, r), r.dic)
    found = ColumnStatistics.fit(r.dic, 4_000).estimate(q)
    return rounded(bl.q_frame(spark, [(int(i), float(x)) for i, x in zip(q.qid, found)], "est_rows"), "est_rows", digits=3)


def empty_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries without any row, by predicate count: their errors rest on the floor of one tuple."""
    r = relation(spark, sf_dir, "shipments")
    w = combo(spark, r)
    truth = grouped(r, true_counts(r.tuples, Queries.of_frame(w, r.dic)), w, ("k",))
    return truth.groupBy("k").agg(F.count("*").alias("n"), F.sum((F.col("true_rows") == 0).cast("int")).alias("empty_true"))


def queries() -> dict[str, Query]:
    width = {f"{h} neurons": {"hidden": (h, h)} for h in (25, 50, 75, 100)}
    depth = {f"{d} layers": {"hidden": (100,) * d} for d in (1, 2, 3, 4)}
    encodings = {e: {"encoding": e} for e in ("binary", "onehot")}
    units = {u: {"unit": u, "leak": "ignore"} for u in ("attribute", "bit")}
    known = {"free": {"order_seed": 3}, "constrained": {"order_seed": 3, "before": [("nation", "region")]}}
    whole = lambda w: w.where(F.col("k") == 8)  # noqa: E731  a chain of single bits answers whole tuples only
    return {
        "w2_comparison": comparison(), "w3_comparison_second": comparison("partsales", SECOND), "w26_space": comparison(budgets=(16_000, 64_000, 256_000)),
        "w4_dens_by_count": dens_by("k"), "w5_dens_by_selectivity": dens_by("bucket"), "w6_dens_by_joint_size": dens_by("decade"), "w7_dens_by_entropy": dens_by("quartile"),
        "w8_width": sweep(width), "w9_depth": sweep(depth), "w10_encoding": sweep(encodings), "w10_encoding_second": sweep(encodings, "partsales", ["brand", "type", "price_c"], share=SECOND_SHARE, total=3_000), "w11_orders": order_ensembles,
        "w12_domain_knowledge": sweep(known, pick=lambda w: wl.dependency_workload(w, ("nation", "region"))), "w13_reg_by_count": reg_by("k"), "w14_reg_by_selectivity": reg_by("bucket"), "w15_reg_by_joint_size": reg_by("decade"), "w16_losses": regressors(), "w16_losses_second": regressors("partsales", SECOND),
        "w17_workload_weights": injected_workload, "w18_augmentation": reg_augmentation, "w19_range_methods": range_methods, "w20_training_grid": training_grid, "w21_increments": increments, "w21_reg_increments": reg_increments, "w21_reg_new_queries": reg_new_queries,
        "u6a_single_networks": single_networks, "u16a_bit_order": sweep(units, pick=whole), "u17a_mask_cycles": mask_cycles, "u23_invalid_codes": invalid_codes, "s6_range_encodings": range_regressors, "s11a_query_sampling": query_sampling, "s17_data_free": data_free,
        "gates": gates, "w23_wide_range": wide_range, "w24_encodings": worked_encodings, "w24_scaling": worked_scaling, "w24_weights": worked_weights, "s3_discretised": discretised, "s4_scaled_bounds": scaled_queries, "s5_operators": operator_codes, "s11a_naive_queries": naive_queries, "b5a_column_statistics": column_statistics, "d2a_empty_truth": empty_truth,
    }

"""Single networks, kernel density, stores, the SQL function and planner advice."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from selweave.functions.estimate import register
from selweave.operators import baselines as bl
from selweave.operators import conditionals, dens, kernels, ranges
from selweave.operators.query import Queries
from selweave.operators.relation import compact, encode_codes, entropies, fit_dictionary, joint_entropy
from selweave.plans.advice import condition_order, join_advice
from selweave.sources import stores

ROWS = [(a, b, c) for a, b, c, n in [("x", 1, "p", 5), ("x", 2, "q", 3), ("y", 1, "q", 7), ("y", 3, None, 2), ("z", 3, "p", 1), (None, 2, "p", 4)] for _ in range(n)]
ATTRS = ["a", "b", "c"]


@pytest.fixture(scope="module")
def rel(spark):
    df = spark.createDataFrame(ROWS, "a string, b int, c string")
    dic = fit_dictionary(df, ATTRS)
    return dic, compact(encode_codes(df, dic), ATTRS).persist()


def joint(rel):
    dic, tuples = rel
    rows = tuples.toPandas()
    return dens.Joint(rows[ATTRS].to_numpy(np.int64), rows["mult"].to_numpy(float), [dic.cards[a] for a in ATTRS])


def test_single_networks_are_a_distribution_close_to_the_relation(rel):
    dic, tuples = rel
    model = conditionals.fit(tuples, dic, epochs=300)
    cells = np.array(list(itertools.product(*(range(dic.cards[a]) for a in ATTRS))))
    p = model.prob(cells)
    assert p.sum() == pytest.approx(1, abs=1e-5)
    assert np.abs(p - joint(rel).prob(cells)).max() < 0.1
    assert ranges.enumerate_box(model, np.zeros(3, int), np.array(model.cards) - 1) == pytest.approx(1, abs=1e-5)


def test_kernel_density_sums_to_one_and_nears_counts_as_kernels_narrow(rel):
    dic, tuples = rel
    cells = list(itertools.product(*(range(dic.cards[a]) for a in ATTRS)))
    wide = kernels.KernelDensity.fit(tuples, dic, most=10_000, scale=1.0)
    assert sum(wide.selectivity(np.array(c), np.array(c)) for c in cells) == pytest.approx(1, abs=1e-6)
    narrow = kernels.KernelDensity.fit(tuples, dic, most=10_000, scale=1e-6)
    exact = joint(rel).prob(np.array(cells))
    assert np.allclose([narrow.selectivity(np.array(c), np.array(c)) for c in cells], exact, atol=1e-9)
    assert wide.selectivity(np.array([1, 0, 0]), np.array([0, 2, 2])) == 0


def test_entropies_of_many_sets_equal_single_ones(rel):
    _, tuples = rel
    sets = [s for k in (1, 2, 3) for s in itertools.combinations(ATTRS, k)]
    found = {r["attrs"]: r["entropy"] for r in entropies(tuples, sets).collect()}
    assert set(found) == {",".join(s) for s in sets}
    for s in sets:
        assert found[",".join(s)] == pytest.approx(joint_entropy(tuples, list(s)))


def test_sample_numbers_copies_of_large_multiplicities(spark):
    tuples = spark.createDataFrame([(0, 200_001), (1, 1)], "a int, mult long")
    whole = {r["a"]: r["mult"] for r in bl.md5_sample(tuples, ["a"], 1.1).collect()}
    assert whole == {0: 200_001, 1: 1}
    part = {r["a"]: r["mult"] for r in bl.md5_sample(tuples, ["a"], 0.01).collect()}
    assert 1_700 < part[0] < 2_300


def test_sql_function_gives_exact_shares_over_the_joint_table(spark, rel):
    dic, _ = rel
    register(spark, [joint(rel)], dic, "share_of", method="enumerate")
    asked = [("a = 'x'", 8), ("b >= 2 AND c = 'p'", 5), ("a IN ('x', 'z') AND b = 1", 5), ("a = 'none'", 0), ("", 22), (None, None)]
    rows = spark.createDataFrame([(k, t) for k, (t, _) in enumerate(asked)], "id int, cond string").selectExpr("id", "share_of(cond) AS s").orderBy("id").collect()
    for r, (_, n) in zip(rows, asked):
        assert (r["s"] is None or math.isnan(r["s"])) if n is None else r["s"] == pytest.approx(n / 22)


def test_logs_and_models_survive_a_round_trip(spark, rel, tmp_path):
    dic, tuples = rel
    (tmp_path / "log.txt").write_text("a = 'x' AND b = 1\n\nc IS NULL\na = 'x' AND b = 1\n")
    log = stores.read_log(spark, str(tmp_path / "log.txt"))
    assert log.count() == 2
    boxes, of = stores.bind_log(log, dic)
    assert isinstance(boxes, Queries) and len(boxes) == len(of) == 2
    models = dens.fit(tuples, dic, orders=2, epochs=1)
    for version in (1, 2):
        stores.save_models(spark, models[:version], str(tmp_path / "models"), "tiny", version)
    back = stores.load_models(spark, str(tmp_path / "models"), "tiny")
    cells = np.zeros((1, 3), int)
    assert [m.prob(cells)[0] for m in back] == [m.prob(cells)[0] for m in models]
    assert len(stores.load_models(spark, str(tmp_path / "models"), "tiny", 1)) == 1
    stores.write_labelled(spark.createDataFrame([(1, 2, 5)], "qid long, k int, true_rows long"), str(tmp_path / "labelled"))
    assert (tmp_path / "labelled" / "k=2").exists()


def test_advice_follows_sizes_and_frequencies(spark, rel):
    dic, _ = rel
    est = spark.createDataFrame([(1, 10.0), (2, 1e6)], "qid long, est_rows double")
    got = {r["qid"]: (r["strategy"], r["partitions"]) for r in join_advice(est, 100, 1 << 20, 1 << 20).collect()}
    assert got == {1: ("broadcast", 1), 2: ("shuffle", 96)}
    preds = spark.createDataFrame([(1, "a", 1), (1, "c", 0), (1, "b", 99)], "qid long, attr string, lo int")
    placed = [r["attr"] for r in condition_order(preds, dic).orderBy("place").collect()]
    assert placed == ["b", "c", "a"]

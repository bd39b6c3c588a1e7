"""Worked examples and brute force for encodings, truth, range methods, baselines and networks."""

import itertools

import numpy as np
import pytest

from selweave.operators import baselines as bl
from selweave.operators import dens, ranges, reg
from selweave.operators import workload as wl
from selweave.operators.query import Queries, parse_where
from selweave.operators.relation import compact, encode_codes, fit_dictionary
from selweave.operators.truth import true_counts, true_counts_theta

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


def test_dictionary_orders_values_and_puts_null_first(rel):
    dic, _ = rel
    assert [v for v, _ in dic.values("a")] == [None, "x", "y", "z"]
    assert [v for v, _ in dic.values("b")] == [1.0, 2.0, 3.0]
    assert dic.rows == len(ROWS)
    assert dic.joint_size() == 36


@pytest.mark.parametrize("text, expected", [("a = 'x'", 8), ("b BETWEEN 2 AND 3", 10), ("a IN ('x','z') AND b > 1", 4), ("c IS NULL", 2), ("a = 'nowhere'", 0), ("b > 2 AND b < 2", 0)])
def test_conditions_count_rows(rel, spark, text, expected):
    dic, tuples = rel
    boxes, _ = Queries.of_predicates([parse_where(text)], dic)
    assert sum(r["true_rows"] for r in true_counts(tuples, boxes).collect()) == expected


def test_bitset_counts_equal_inequality_join(rel, spark):
    dic, tuples = rel
    q = Queries.of_frame(wl.range_workload(spark, dic, ATTRS, 30), dic)
    key = lambda df: sorted((r["qid"], r["true_rows"]) for r in df.collect())
    assert key(true_counts(tuples, q)) == key(true_counts_theta(tuples, q))


@pytest.mark.parametrize("method", ["uniform", "adaptive", "progressive"])
def test_sampling_has_no_bias(rel, method):
    model = joint(rel)
    for low, high in [([1, 0, 0], [2, 1, 2]), ([0, 1, 1], [3, 2, 2])]:
        low, high = np.array(low), np.array(high)
        exact = ranges.enumerate_box(model, low, high)
        mean = np.mean([ranges.METHODS[method](model, low, high, samples=100, seed=s) for s in range(150)])
        assert mean == pytest.approx(exact, rel=0.04)


def test_uncorrected_adaptive_sampling_is_biased(rel):
    low, high = np.array([0, 0, 0]), np.array([3, 2, 1])
    exact = ranges.enumerate_box(joint(rel), low, high)
    wrong = np.mean([ranges.adaptive_box(joint(rel), low, high, samples=200, corrected=False, seed=s) for s in range(60)])
    assert abs(wrong - exact) > 0.1 * exact


@pytest.mark.parametrize("unit, encoding", [("attribute", "binary"), ("bit", "binary"), ("attribute", "onehot")])
def test_masks_let_no_later_position_through(unit, encoding):
    net = dens.MaskedNet([4, 3, 5], [2, 0, 1], (20, 20), encoding, unit, seed=3)
    d = len(net.rank)
    x = np.zeros((1, d), np.float32)
    z = net.net.forward(x)[0]
    for k in range(d):
        y = x.copy()
        y[0, k] = 1
        moved = np.flatnonzero(np.abs(net.net.forward(y)[0] - z)[0] > 0)
        assert all(net.rank[m] > net.rank[k] for m in moved)


def test_chain_sums_to_one_and_learns():
    draw = np.random.default_rng(0)
    a = draw.integers(0, 4, 3000)
    codes = np.stack([a, (a + draw.integers(0, 2, 3000)) % 4, a // 2], axis=1)
    net = dens.MaskedNet([4, 4, 2], [0, 1, 2], (50, 50), leak="ignore")
    net.learn(codes, np.ones(len(codes)), epochs=60)
    every = np.array(list(itertools.product(range(4), range(4), range(2))))
    assert net.prob(every).sum() == pytest.approx(1, abs=1e-4)
    truth = np.array([(codes == e).all(axis=1).mean() for e in every])
    assert np.abs(net.prob(every) - truth).max() < 0.03


def test_gradients_match_differences():
    from selweave.operators.nets import Net

    net, draw = Net([3, 4, 2], seed=1), np.random.default_rng(0)
    for k, p in enumerate(net.weights):
        net.weights[k] = p.astype(float)
    x, t = draw.random((5, 3)), draw.random((5, 2))
    out, seen = net.forward(x)
    g = net.gradients(seen, out - t)[0][1, 2]
    loss = lambda: 0.5 * ((net.forward(x)[0] - t) ** 2).sum()
    before = net.weights[0][1, 2]
    net.weights[0][1, 2] = before + 1e-5
    up = loss()
    net.weights[0][1, 2] = before - 1e-5
    assert g == pytest.approx((up - loss()) / 2e-5, rel=1e-3, abs=1e-6)


def test_orders_respect_dependencies_and_refuse_cycles():
    for seed in range(20):
        order = dens.attribute_order(ATTRS, seed=seed, before=[("c", "a")])
        assert order.index(2) < order.index(0)
    with pytest.raises(ValueError):
        dens.attribute_order(ATTRS, before=[("a", "b"), ("b", "a")])


def test_fit_in_spark_gives_one_network_an_order(rel):
    dic, tuples = rel
    models = dens.fit(tuples, dic, orders=2, epochs=5, hidden=(16,))
    assert len(models) == 2
    assert {r["model"] for r in dens.nll(models, tuples, dic).collect()} == {0, 1}


def test_independence_by_hand(rel, spark):
    dic, _ = rel
    w = spark.createDataFrame([(0, "a", 1, 1), (0, "b", 0, 0)], "qid long, attr string, lo int, hi int")
    assert bl.independence(dic, w).first()["est_rows"] == pytest.approx(22 * (8 / 22) * (12 / 22))


def test_full_haar_decomposition_is_exact(rel, spark):
    dic, tuples = rel
    w = wl.range_workload(spark, dic, ["a", "b"], 20)
    q = Queries.of_frame(w, dic)
    exact = {r["qid"]: r["true_rows"] for r in true_counts(tuples, q).collect()}
    kept = bl.haar_coefficients(tuples, dic, ["a", "b"])
    for r in bl.haar_estimate(kept, dic, ["a", "b"], w).collect():
        assert r["est_rows"] == pytest.approx(exact[r["qid"]], abs=1e-6)


@pytest.mark.parametrize("structure", ["tree", "greedy"])
def test_bayesian_network_sums_to_all_rows(rel, spark, structure):
    dic, tuples = rel
    q = Queries(ATTRS, [4, 3, 3], np.array([0]), np.zeros((1, 3), np.int32), np.array([[3, 2, 2]], np.int32))
    assert bl.BayesNet.fit(tuples, dic, structure).estimate(q)[0] == pytest.approx(len(ROWS))


def test_target_scaling_round_trip():
    sel = np.array([0.5, 0.01, 0.0])
    scaler = reg.TargetScaler(1000).fit(sel)
    assert scaler.transform(sel).tolist()[-1] == 1.0
    assert scaler.inverse(scaler.transform(sel)) == pytest.approx([0.5, 0.01, 0.001])


def test_regressor_learns_a_log(rel, spark):
    dic, tuples = rel
    q = Queries.of_frame(wl.range_workload(spark, dic, ATTRS, 150), dic)
    y = {r["qid"]: r["true_rows"] for r in true_counts(tuples, q).collect()}
    y = np.array([y[int(i)] for i in q.qid], float)
    model = reg.Regressor(dic.rows, encoding="bounds").fit(q, y, epochs=120)
    error = np.maximum(np.maximum(y, 1) / np.maximum(model.selectivity(q) * dic.rows, 1), np.maximum(model.selectivity(q) * dic.rows, 1) / np.maximum(y, 1))
    assert np.median(error) < 1.5


def test_entry_points_import_and_agree():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())

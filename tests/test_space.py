"""What the comparison by space shares between budgets: networks trained side by side, tables of many parent sets in one pass."""

import numpy as np

from selweave.operators import baselines as bl
from selweave.operators import dens
from selweave.operators.relation import compact, encode_codes, fit_dictionary
from selweave.queries import common, experiments
from selweave.queries.common import Relation

ROWS = [(f"a{k % 3}", k % 4, f"c{k * k % 5}") for k in range(60)]
ATTRS = ["a", "b", "c"]


def relation(spark):
    df = spark.createDataFrame(ROWS, "a string, b int, c string")
    dic = fit_dictionary(df, ATTRS)
    return Relation("r", ATTRS, dic, compact(encode_codes(df, dic), ATTRS).persist())


def test_tables_of_all_parent_sets(spark):
    r = relation(spark)
    n = {a: r.dic.cards[a] for a in ATTRS}
    rows = r.tuples.toPandas()
    options = [(), ("a",), ("b",), ("a", "b")]
    for o, found in bl.BayesNet._tables(r.tuples, "c", options, n).items():
        expected = np.zeros([n[x] for x in (*o, "c")])
        for x in rows.to_dict("records"):
            expected[tuple(x[y] for y in (*o, "c"))] += x["mult"]
        assert (found == expected).all()


def test_networks_of_several_budgets_equal_those_trained_alone(spark):
    r = relation(spark)
    together = experiments._networks(r, (2_000, 6_000), 1.0)
    for budget, net in together.items():
        alone = dens.fit(r.tuples, r.dic, start=[dens.MaskedNet(net.cards, net.order, net.hidden)])[0]
        assert net.size_bytes() <= budget
        assert all(np.allclose(x, y, atol=1e-6) for x, y in zip(net.net.parameters(), alone.net.parameters()))


def test_every_budget_has_every_estimator_on_all_tuples(spark, monkeypatch):
    r, seen = relation(spark), {}

    def fitted(tuples, dic, start, share=1.0, **_):
        seen.setdefault("shares", []).append(share)
        return start

    real, flat = experiments._fits, lambda q: np.ones(len(q))
    monkeypatch.setattr(experiments.dens, "fit", fitted)
    monkeypatch.setattr(experiments, "_fits", lambda spark, *rest: {name: lambda name=name: ((lambda q: experiments.bl.q_frame(spark, [(int(i), 1.0) for i in q.qid], "est_rows")) if name in ("sample", "kernels") else flat, 8) for name in real(spark, *rest)})
    monkeypatch.setattr(experiments, "relation", lambda *_: r)
    monkeypatch.setattr(experiments, "combo", lambda spark, r, **_: common.combo(spark, r, 20, values="anchored"))
    names = set(real(spark, r, 64_000, {}))
    for query, budgets in (("w26_space", {16_000, 64_000, 256_000}), ("w3_comparison_second", {64_000})):
        rows = experiments.queries()[query](spark, "").collect()
        assert {(x["estimator"], x["budget"]) for x in rows} == {(n, b) for n in names for b in budgets}
        assert all(x["latency_ms"] is not None for x in rows)
    assert set(seen["shares"]) == {1.0}

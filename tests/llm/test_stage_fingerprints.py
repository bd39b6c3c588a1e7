"""The pipeline's near-duplicate stage takes its first candidates from linked fingerprints."""

import random

import numpy as np
import pytest

pytest.importorskip("selweave.llm")

import corpus_pipeline  # noqa: E402
from selweave.llm import simhash  # noqa: E402


def test_fingerprint_of_a_set_by_hand():
    draw = np.random.default_rng(3)
    for n in (0, 1, 2, 7, 5000):
        own = draw.integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        expected = sum(1 << k for k in range(64) if 2 * sum(int(x) >> k & 1 for x in own) > n)
        assert simhash.set_fingerprint(own) == expected


def test_near_copies_are_linked_by_fingerprints(spark, monkeypatch):
    """Without the prefix filter the stage still joins close copies, and keeps texts apart whose sets aren't alike."""
    from selweave.llm import simhash as op

    none = "h long, t long, n int"
    monkeypatch.setattr(op, "_prefixes", lambda own, similarity, common: own.sparkSession.createDataFrame([], none))
    rng = random.Random(8)
    rows = []
    for group in range(12):
        base = [f"w{rng.randrange(4000)}" for _ in range(700)]
        rows.append((group * 10, " ".join(base)))
        base[350] = "changed"
        rows.append((group * 10 + 1, " ".join(base)))
    rows += [(900, None), (901, ""), (902, "a b"), (903, "a c")]
    kept = corpus_pipeline.keep_one_of_each(spark, spark.createDataFrame(rows, "doc_id long, text string"), None).collect()
    assert sorted(r["doc_id"] for r in kept) == [*(group * 10 for group in range(12)), 900, 902, 903]

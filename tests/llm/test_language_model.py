"""Language-model scores: the base against a plain version, gradients by differences, and a held-out gain."""

import re
from collections import Counter
from math import log10
from zlib import crc32

import numpy as np
import pytest

pytest.importorskip("selweave.llm")

from selweave.llm import attention, lm  # noqa: E402
from selweave.llm.queries import piece_model_path  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SF = "/root/testdata"


def plain(rows):
    words = {k: WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) for k, (_, t) in enumerate(rows)}
    held = {k: crc32(("" if i is None else str(i)).encode()) % 7 == 2 for k, (i, _) in enumerate(rows)}
    counts, ends = Counter(w for k, own in words.items() if not held[k] for w in own), sum(not h for h in held.values())
    total, kinds = sum(counts.values()) + ends, len(counts) + (ends > 0)
    out = Counter()
    for k, own in words.items():
        c = [counts[w] for w in own] + [ends]
        out[rows[k][0], held[k], len(c), sum(x > 0 for x in c), total, round(sum(log10((x + 1) / (total + kinds + 1)) for x in c), 6)] += 1
    return out


def test_base_counts_with_rare_words_and_copies(spark, monkeypatch):
    monkeypatch.setattr(lm, "TOP", 50)  # so that most words take the way of rare ones
    own = spark.read.parquet(f"{SF}/sf0.001/documents.parquet").select("doc_id", "text").collect()
    rows = [(r[0], r[1]) for r in own] + [(9000, None), (9001, ""), (9002, " \t"), (9003, "Größe 東京 🙂 " * 400)] + [(9100 + k, own[3][1]) for k in range(60)] + [(None, "a b"), (9003, "A b")]
    found = lm.score(spark, spark.createDataFrame(rows, "doc_id long, text string").repartition(5), piece_model_path()).collect()
    assert Counter((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in found) == plain(rows)
    assert all(r["score"] < 0 for r in found)
    assert len({round(r["score"], 6) for r in found if r["doc_id"] is not None and r["doc_id"] >= 9100}) == 1


def test_gradients_by_differences():
    draw = np.random.default_rng(0)
    v = attention.Vocabulary.of(draw.integers(0, 30, 60), 9)
    y, n = v.index[draw.integers(0, 60, 200)], np.array([50, 3, 0, 100, 47])
    model = attention.AttentionModel(v, draw.integers(0, 5, (len(v.group), v.classes)).astype(float))
    inputs, targets, text = attention.blocks(y, n, v.opening)
    model.p = {k: x.astype(np.float64) for k, x in model.p.items()}
    loss = lambda: -model.text_logs(inputs, targets, text, len(n)).sum() / n.sum()
    value, slopes = model.gradients(inputs, targets)
    assert value == pytest.approx(loss(), rel=1e-5)
    for name, x in model.p.items():
        for _ in range(5):
            at = tuple(int(draw.integers(0, k - (name == "rows" and d == 0))) for d, k in enumerate(x.shape))
            was, both = x[at], []
            for side in (1e-3, -1e-3):
                x[at] = was + side
                both.append(loss())
            x[at] = was
            assert slopes[name][at] == pytest.approx((both[0] - both[1]) / 2e-3, rel=2e-2, abs=2e-5)


def test_a_text_scores_alike_alone_and_among_others_and_sums_to_one():
    draw = np.random.default_rng(1)
    v = attention.Vocabulary.of(draw.integers(1, 9, 20), 5)
    model = attention.AttentionModel(v)
    texts = [v.index[draw.integers(0, 20, n)] for n in (1, 8, 9, 40, 17)]
    together = model.text_logs(*attention.blocks(np.concatenate(texts), np.array([len(t) for t in texts]), v.opening), len(texts))
    for t, score in zip(texts, together):
        assert model.text_logs(*attention.blocks(t, np.array([len(t)]), v.opening), 1)[0] == pytest.approx(score, rel=1e-4)
    ends = [np.append(texts[3], k).astype(np.int32) for k in range(len(v.group))]
    whole = model.text_logs(*attention.blocks(np.concatenate(ends), np.array([len(t) for t in ends]), v.opening), len(ends))
    assert np.exp(whole - together[3]).sum() == pytest.approx(1, rel=1e-3)


def test_better_than_the_unigram_base_on_held_out_texts(spark):
    docs = spark.read.parquet(f"{SF}/sf0.1/documents.parquet")
    held = lm.score(spark, docs, piece_model_path()).where("held_out").groupBy().sum("score", "base_score", "n_tokens").first()
    assert held[0] / held[2] > held[1] / held[2] + 0.1


def test_without_training_texts_and_empty(spark):
    found = lm.score(spark, spark.createDataFrame([], "doc_id long, text string"), piece_model_path())
    assert found.collect() == []

"""The pipeline's near-duplicate stage against all pairs, by five-word shingles and similarity 0.8."""

import random

import pytest

pytest.importorskip("selweave.llm")

import corpus_pipeline  # noqa: E402


def sets(text):
    w = (text or "").lower().split()
    return {tuple(w[k : k + 5]) for k in range(max(len(w) - 4, 1))} if w else set()


def test_near_copies_at_the_bound_go(spark):
    rng = random.Random(5)
    vocab = [f"w{k}" for k in range(3000)]
    rows, shared = [(900, None), (901, ""), (902, " \n"), (903, "a b"), (904, "A  b"), (905, "a b c")], [rng.choice(vocab) for _ in range(40)]
    for group in range(30):
        base = [rng.choice(vocab) for _ in range(rng.choice([12, 60, 200]))] + (shared if group % 3 == 0 else [])
        for copy in range(5):
            words = list(base)
            for _ in range(max(1, len(words) * copy // 100)):
                words[rng.randrange(len(words))] = rng.choice(vocab)
            rows.append((group * 10 + copy, " ".join(words)))
    rows.append(rows[-1])
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    own, bound = [sets(t) for _, t in rows], 0
    for i in range(len(rows)):
        for j in range(i):
            union = len(own[i] | own[j])
            like = len(own[i] & own[j]) / union if union else 1.0
            bound += 0.8 <= like < 0.9
            if like >= 0.8:
                root[find(i)] = find(j)
    assert bound > 20
    least = {}
    for k, (i, _) in enumerate(rows):
        least[find(k)] = min(i, least.get(find(k), i))
    kept = corpus_pipeline.keep_one_of_each(spark, spark.createDataFrame(rows, "doc_id long, text string"), None).collect()
    assert sorted(r["doc_id"] for r in kept) == sorted(least.values())


def test_large_groups_in_tiles_link_like_all_pairs(spark, monkeypatch):
    """Hundreds of copies whose edits put many pairs on either side of the bound, tiles far under the group's size."""
    from selweave.llm import simhash

    monkeypatch.setattr(simhash, "TILE", 40)
    monkeypatch.setattr(simhash, "STAR", 16)
    rng = random.Random(11)
    vocab = [f"v{k}" for k in range(500)]
    rows = []
    for group in range(3):
        base = [rng.choice(vocab) for _ in range(100)]
        for copy in range(120):
            words = list(base)
            for k in rng.sample(range(100), rng.randrange(0, 9)):
                words[k] = rng.choice(vocab)
            rows.append((group * 1000 + copy, " ".join(words)))
    own = [sets(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if len(own[i] & own[j]) >= 0.8 * len(own[i] | own[j]):
                root[find(i)] = find(j)
    least = {}
    for k, (i, _) in enumerate(rows):
        least[find(k)] = min(i, least.get(find(k), i))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = simhash.keep_similar(docs, shingle=5, similarity=0.8).collect()
    assert len(least) > 20
    assert sorted(r["doc_id"] for r in kept) == sorted(least.values())

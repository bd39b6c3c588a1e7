"""The classifier of toxicity is trained in a task: the driver gets the model alone, whatever the texts' size."""

import pytest

pytest.importorskip("selweave.llm")

from selweave.llm import toxicity  # noqa: E402


def test_the_driver_never_trains(spark, monkeypatch):
    def never(*_, **__):
        raise AssertionError("trained on the driver")

    docs = spark.createDataFrame([(k, f"plain words here {k}" if k % 2 else f"vile {k} words there", "en") for k in range(60)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(k, 1 - k % 2) for k in range(60)], "doc_id long, toxic int")
    monkeypatch.setattr(toxicity, "train", never)
    model = toxicity.fit(docs, labels)
    assert model.rows > 40 and model.constant is None
    scores = {r["doc_id"]: r["score"] for r in toxicity.score(docs, model).collect()}
    assert min(scores[k] for k in range(0, 60, 2)) > max(scores[k] for k in range(1, 60, 2))


def test_without_labels(spark):
    docs = spark.createDataFrame([(1, "a b", "en")], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.fit(docs, labels).constant == 0.5


def test_all_labelled_rows_are_learnt_by_several_trainers(spark, monkeypatch):
    """More rows than a trainer takes; each kind of text is marked by a word that few rows have."""
    monkeypatch.setattr(toxicity, "TRAINER_ROWS", 1000)
    marks = 300
    rows = [(k, f"plain words here {k % 7} " + (f"vile{k // 2 % marks}" if k % 2 else f"mild{k // 2 % marks}"), "en") for k in range(12_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(4)
    labels = spark.createDataFrame([(k, k % 2) for k in range(12_000)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    assert model.rows == labels.where(~toxicity.held_out(toxicity.F.col("doc_id"), 5, 0)).count() > 9_000
    wrong = toxicity.score(docs, model).where("held_out and predicted <> doc_id % 2").count()
    assert wrong < 100


def test_cutoffs_have_the_fewest_errors():
    draw = toxicity.np.random.default_rng(3)
    scores, labels = toxicity.np.round(draw.random(300), 2), draw.random(300) < 0.4
    at = toxicity.np.unique(scores)
    cuts = [*((at[1:] + at[:-1]) / 2), 0.5]
    assert toxicity.best_cutoff(scores, labels) == min((int(((scores >= c) != labels).sum()), abs(c - 0.5), c) for c in cuts)[2]

"""Toxicity by a convolutional text classifier trained in numpy.

A word's vector is the sum of three hashed rows: the word, its first four and
its first six bytes. Filters of several widths slide over the words of the
whole text; the maximum of each filter over all places feeds one logistic unit.
Cut-offs for acting on a score are calibrated by language on labelled rows kept
out of the gradient steps; the score itself never sees a language.

The fit takes all labelled rows: one trainer for each ``TRAINER_ROWS`` of them or
``TRAINER_BYTES`` of words. Several go on side by side for an epoch, then their
steps are averaged, a table row's by those that moved it.
Edge cases: null and empty texts have no words and get the score of an empty
pool; without labels of both kinds the score is the share of ones (0.5 without
any); languages without enough labels use the overall cut-off; repeated rows
score alike; an empty table gives an empty result; columns beside doc_id, text
and lang are ignored by scoring.
"""

from __future__ import annotations

import gc
import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, cut, edges, first_of_each, held_out, prefix_hashes, slices, small_batches, span_hashes, text_buffer

WORD_BITS, STEM_BITS = 18, 16
TABLES = (1 << WORD_BITS, 1 << STEM_BITS, 1 << STEM_BITS)
WIDTHS = (1, 2, 3)
PAD = max(WIDTHS) - 1
#: Labelled rows, or bytes of their words, that one trainer takes; trainers whose steps one task adds up.
TRAINER_ROWS, TRAINER_BYTES, GROUP = 8000, 64 << 20, 8
EPOCHS = 6
_LETTER = np.zeros(256, bool)
_LETTER[48:58] = _LETTER[97:123] = _LETTER[128:] = True


def words_of(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Three table rows for each word of a batch, and the first word of each document."""
    raw = LOWER[raw]
    starts, ends = edges(_LETTER[raw], offsets)
    sums = prefix_hashes(raw)
    rows = np.empty((len(starts), 3), np.int32)
    rows[:, 0] = span_hashes(sums, starts, ends) >> np.uint64(64 - WORD_BITS)
    for k, size in ((1, 4), (2, 6)):
        rows[:, k] = span_hashes(sums, starts, np.minimum(ends, starts + size)) >> np.uint64(64 - STEM_BITS)
    return rows, first_of_each(starts, offsets)


@dataclass
class ConvolutionModel:
    """Tables, filters by width, and the output unit."""

    tables: list[np.ndarray] = field(default_factory=list)
    filters: list[np.ndarray] = field(default_factory=list)
    shifts: list[np.ndarray] = field(default_factory=list)
    out: np.ndarray | None = None
    bias: float = 0.0
    constant: float | None = None
    cutoffs: dict[str, float] = field(default_factory=dict)
    cutoff: float = 0.5
    rows: int = 0

    @classmethod
    def fresh(cls, size: int, filters: int, seed: int) -> ConvolutionModel:
        draw = np.random.default_rng(seed)
        f32 = lambda *s, scale: (draw.standard_normal(s) * scale).astype(np.float32)
        return cls([f32(t, size, scale=0.05) for t in TABLES], [f32(w, size, filters, scale=(1.0 / (w * size)) ** 0.5) for w in WIDTHS], [np.zeros(filters, np.float32) for _ in WIDTHS], f32(filters * len(WIDTHS), scale=0.2))

    def embed(self, rows: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Word vectors with PAD zero vectors after each document; starts; which places hold words."""
        count = np.diff(first)
        starts = first[:-1] + PAD * np.arange(len(count))
        place = np.arange(len(rows)) + PAD * np.repeat(np.arange(len(count)), count)
        x = np.zeros((len(rows) + PAD * len(count), self.tables[0].shape[1]), np.float32)
        x[place] = self.tables[0][rows[:, 0]] + self.tables[1][rows[:, 1]] + self.tables[2][rows[:, 2]]
        return x, starts, place

    def responses(self, x: np.ndarray, k: int, word: np.ndarray) -> np.ndarray:
        """Rectified filter outputs at every place where a word stands, else 0."""
        w, n = self.filters[k], len(x)
        y = x @ w[0]
        for j in range(1, len(w)):
            y[: n - j] += x[j:] @ w[j]
        y += self.shifts[k]
        np.maximum(y, 0, out=y)
        y *= word[:, None]
        return y

    def pooled(self, rows: np.ndarray, first: np.ndarray) -> np.ndarray:
        x, starts, place = self.embed(rows, first)
        word = np.zeros(len(x), np.float32)
        word[place] = 1
        return np.concatenate([np.maximum.reduceat(self.responses(x, k, word), starts, axis=0) for k in range(len(WIDTHS))], axis=1)

    def scores(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        docs = len(offsets) - 1
        if self.constant is not None:
            return np.full(docs, self.constant)
        rows, first = words_of(raw, offsets)
        out, lo = np.empty(docs), 0
        while lo < docs:  # bounded pieces
            hi = max(lo + 1, int(np.searchsorted(first, first[lo] + 60_000, "right")) - 1)
            hi = min(hi, docs)
            out[lo:hi] = self.pooled(rows[first[lo] : first[hi]], first[lo : hi + 1] - first[lo]) @ self.out + self.bias
            lo = hi
        return 1.0 / (1.0 + np.exp(-np.clip(out, -30, 30)))


class _Adam:
    def __init__(self, rate: float) -> None:
        self.rate, self.state = rate, {}

    def step(self, key, value, grad) -> None:
        m, v, t = self.state.get(key, (0.0, 0.0, 0))
        m, v, t = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad * grad, t + 1
        self.state[key] = m, v, t
        value -= (self.rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)).astype(np.float32)


#: A model, the sums of squares of its tables' rows, and Adam's state.
State = tuple[ConvolutionModel, list[np.ndarray], _Adam]
#: What Adam steps.
STEPPED = ["out", "bias", *((c, k) for k in range(len(WIDTHS)) for c in "wb")]


def fresh_state(size: int = 8, filters: int = 16, rate: float = 0.01, seed: int = 5) -> State:
    return ConvolutionModel.fresh(size, filters, seed), [np.full(t, 1e-4, np.float32) for t in TABLES], _Adam(rate)


def train(examples: list[tuple[np.ndarray, int]], state: State, epochs: int = EPOCHS, batch: int = 64, seed: int = 5) -> State:
    """Adam on filters and output, per-coordinate scaled steps on the hashed rows; gradients flow through each pool's argmax."""
    model, squares, adam = state
    size, filters = model.filters[0].shape[1:]
    draw = np.random.default_rng(seed)
    bias = np.array([model.bias], np.float32)
    examples = [e for e in examples if len(e[0])] or examples
    for _ in range(epochs):
        order = draw.permutation(len(examples))
        for lo in range(0, len(order), batch):
            part = [examples[k] for k in order[lo : lo + batch]]
            rows = np.concatenate([e[0] for e in part])
            first = np.concatenate([[0], np.cumsum([len(e[0]) for e in part])])
            label = np.array([e[1] for e in part], np.float32)
            x, starts, place = model.embed(rows, first)
            word = np.zeros(len(x), np.float32)
            word[place] = 1
            pools, where = [], []
            ends = np.append(starts[1:], len(x))
            for k in range(len(WIDTHS)):
                y = model.responses(x, k, word)
                at = np.stack([s + y[s:e].argmax(axis=0) for s, e in zip(starts, ends)])
                where.append(at)
                pools.append(np.take_along_axis(y, at, axis=0))
            h = np.concatenate(pools, axis=1)
            p = 1.0 / (1.0 + np.exp(-np.clip(h @ model.out + bias[0], -30, 30)))
            d = ((p - label) / len(part)).astype(np.float32)
            dh = d[:, None] * model.out[None, :] * (h > 0)
            adam.step("out", model.out, h.T @ d)
            adam.step("bias", bias, np.array([d.sum()], np.float32))
            dx = np.zeros_like(x)
            for k, width in enumerate(WIDTHS):
                g, at = dh[:, k * filters : (k + 1) * filters], where[k]
                grad = np.empty_like(model.filters[k])
                for j in range(width):
                    spot = np.minimum(at + j, len(x) - 1)
                    grad[j] = np.einsum("df,dfe->ef", g, x[spot])
                    np.add.at(dx, spot.ravel(), (g[:, :, None] * model.filters[k][j].T[None]).reshape(-1, size))
                adam.step(("w", k), model.filters[k], grad)
                adam.step(("b", k), model.shifts[k], g.sum(axis=0))
            moved = np.flatnonzero(np.abs(dx[place]).sum(axis=1))
            for t, table in enumerate(model.tables):
                at, back = np.unique(rows[moved, t], return_inverse=True)
                grad = np.zeros((len(at), size), np.float32)
                np.add.at(grad, back, dx[place[moved]])
                squares[t][at] += (grad * grad).mean(axis=1)
                table[at] -= 0.1 * grad / np.sqrt(squares[t][at])[:, None]
    model.bias = float(bias[0])
    return model, squares, adam


def steps_of(state: State, base: State) -> list[np.ndarray]:
    """What a trainer adds to the sums: itself as one, dense weights and Adam's state, steps of the tables and which rows moved."""
    model, squares, adam = state
    dense = [*model.filters, *model.shifts, model.out, np.array([model.bias])]
    dense += [np.asarray(x, np.float64) for key in STEPPED for x in adam.state[key]]
    moved = [(x != y).astype(np.int32) for x, y in zip(squares, base[1])]
    return [np.ones(1), *dense, *(x - y for x, y in zip(model.tables, base[0].tables)), *(x - y for x, y in zip(squares, base[1])), *moved]


def averaged(sums: list[np.ndarray], base: State) -> State:
    """The state after the trainers' steps: means, of a table's row over the trainers that moved it."""
    model, squares, adam = base
    n, k, own = float(sums[0][0]), len(WIDTHS), len(TABLES)
    mean = [x / n for x in sums[1 : -3 * own]]
    f32 = lambda arrays: [x.astype(np.float32) for x in arrays]
    steps, more, moved = (sums[len(sums) - c * own : len(sums) - (c - 1) * own] for c in (3, 2, 1))
    by = [np.maximum(c, 1) for c in moved]
    made = ConvolutionModel(f32(t + x / c[:, None] for t, x, c in zip(model.tables, steps, by)), f32(mean[:k]), f32(mean[k : 2 * k]), mean[2 * k].astype(np.float32), float(mean[2 * k + 1][0]))
    after = _Adam(adam.rate)
    for j, key in enumerate(STEPPED):
        m, v, t = mean[2 * k + 2 + 3 * j : 2 * k + 5 + 3 * j]
        after.state[key] = m.astype(np.float32), v.astype(np.float32), int(np.round(t))
    return made, f32(s + x / c for s, x, c in zip(squares, more, by)), after


def best_cutoff(scores: np.ndarray, labels: np.ndarray, fallback: float = 0.5) -> float:
    """The cut-off with the fewest errors, halfway between neighbouring scores; near 0.5 on ties."""
    if len(scores) == 0 or labels.min() == labels.max():
        return fallback
    at = np.unique(scores)
    cuts = np.append((at[1:] + at[:-1]) / 2, fallback)
    ones, others = np.sort(scores[labels == 1]), np.sort(scores[labels == 0])
    errors = np.searchsorted(ones, cuts) + len(others) - np.searchsorted(others, cuts)
    return float(min(zip(errors, np.abs(cuts - fallback), cuts))[2])


def advanced(rows: list[tuple], start: bytes, epochs: int, seed: int) -> bytes:
    """A trainer's part of a round, over rows (doc_id, lang, label, words) in the order of their ids."""
    base, own = pickle.loads(start), pickle.loads(start)
    examples = [(np.frombuffer(w, np.int32).reshape(-1, 3), int(y)) for _, _, y, w in sorted(rows, key=lambda r: (r[0], r[3], r[1]))]
    return pickle.dumps(steps_of(train(examples, own, epochs, seed=seed), base))


def cutoffs_of(langs: list[str], margins: np.ndarray, labels: np.ndarray, least_by_language: int) -> tuple[float, dict[str, float]]:
    """The cut-off over all languages, and of each with enough rows."""
    scores, truth, langs = 1.0 / (1.0 + np.exp(-np.clip(margins, -30, 30))), labels == 1, np.array(langs, object)
    cutoff, own_cutoffs = best_cutoff(scores, truth), {}
    for lang in sorted(set(langs)):
        own = langs == lang
        if own.sum() >= least_by_language:
            own_cutoffs[lang] = best_cutoff(scores[own], truth[own], cutoff)
    return cutoff, own_cutoffs


def fit(docs: DataFrame, labels: DataFrame, target: str = "toxic", least_by_language: int = 40) -> ConvolutionModel:
    """Learn from all labelled rows that aren't held out (crc32 of the id, modulo 5, not 0); of 500 or more, a fifth gives the cut-offs instead."""
    known = labels.where(~held_out(F.col("doc_id"), 5, 0) & F.col("doc_id").isNotNull() & F.col(target).isNotNull())
    known = known.groupBy("doc_id").agg(F.max(target).cast("int").alias("label"))
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit("")
    rows = small_batches(docs).select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.coalesce(lang, F.lit("")).alias("lang")).join(known, "doc_id").select("doc_id", "text", "lang", "label")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            found, first = words_of(*text_buffer(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(2), batch.column(3).cast(pa.int32()), pa.array([found[a:b].tobytes() for a, b in zip(first[:-1], first[1:])], pa.binary())], names=["doc_id", "lang", "label", "words"])

    rows = cut(rows.mapInArrow(run, "doc_id long, lang string, label int, words binary").dropDuplicates(["doc_id", "lang", "words"]))
    n, ones = rows.agg(F.count("*"), F.coalesce(F.sum("label"), F.lit(0))).first()
    if not n or not 0 < ones < n:
        return ConvolutionModel(constant=ones / n if n else 0.5, rows=n)
    kept = F.pmod("doc_id", F.lit(5)) == 3 if n >= 500 else F.lit(False)
    learnt = rows.where(~kept)
    worded = learnt.where(F.length("words") > 0)
    number, size = worded.agg(F.count("*"), F.coalesce(F.sum(F.length("words")), F.lit(0))).first()
    if not number:
        worded, number = learnt, max(1, learnt.count())
    trainers = max(1, -(-number // TRAINER_ROWS), -(-size // TRAINER_BYTES))
    worded = worded.withColumn("trainer", F.pmod(F.xxhash64("doc_id"), F.lit(trainers)))
    state, rounds = fresh_state(), EPOCHS if trainers > 1 else 1
    for r in range(rounds):
        state = _round(worded, state, trainers, EPOCHS // rounds, 5 + r)
    model = state[0]
    model.rows = n
    packed = pickle.dumps(model)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pickle.loads(packed)
        for batch in batches:
            words = [np.frombuffer(w, np.int32).reshape(-1, 3) for w in batch.column(3).to_pylist()]
            margins = [float((own.pooled(w, np.array([0, len(w)])) @ own.out)[0] + own.bias) if len(w) else own.bias for w in words]
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(margins, pa.float64()), batch.column(2)], names=["lang", "margin", "label"])

    def calibrate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        langs, margins, labels_ = [], [], []
        for batch in batches:
            langs += batch.column(0).to_pylist()
            margins.append(batch.column(1).to_numpy())
            labels_.append(batch.column(2).to_numpy())
        if margins:
            found = cutoffs_of(langs, np.concatenate(margins), np.concatenate(labels_), least_by_language)
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(found)], pa.binary())], names=["cutoffs"])

    # in tasks, as the driver has no room for the words of all rows; an id, a margin and a label a row meet in one
    judged = (rows.where(kept) if n >= 500 else rows).mapInArrow(judge, "lang string, margin double, label int").repartition(1)
    made = judged.mapInArrow(calibrate, "cutoffs binary").toArrow().column("cutoffs")
    if len(made):
        model.cutoff, model.cutoffs = pickle.loads(made[0].as_py())
    return model


def _round(rows: DataFrame, state: State, trainers: int, epochs: int, seed: int) -> State:
    """All trainers go on from one state; their steps are added up in tasks, in groups, and averaged."""
    gc.collect()  # the round before leaves its shuffle files to Spark's cleaner
    rows.sparkSession.sparkContext._jvm.System.gc()
    start = pickle.dumps(state)
    sums = pa.schema([("trainer", pa.int64()), ("steps", pa.binary())])

    def learn(key: tuple, part: pa.Table) -> pa.Table:
        found = advanced(list(zip(*(part.column(c).to_pylist() for c in ("doc_id", "lang", "label", "words")))), start, epochs, seed)
        return pa.table([pa.array([key[0].as_py()]), pa.array([found], pa.binary())], schema=sums)

    def add(key: tuple, part: pa.Table) -> pa.Table:
        total = None
        for x in part.column("steps"):
            own = pickle.loads(x.as_py())
            total = own if total is None else [a + b for a, b in zip(total, own)]
        return pa.table([pa.array([key[0].as_py()]), pa.array([pickle.dumps(total)], pa.binary())], schema=sums)

    found, held = rows.groupBy("trainer").applyInArrow(learn, "trainer long, steps binary"), trainers
    while held > 1:
        held = -(-held // GROUP)
        found = found.withColumn("trainer", F.pmod("trainer", F.lit(held))).groupBy("trainer").applyInArrow(add, "trainer long, steps binary")
    told = found.toArrow().column("steps")
    return averaged(pickle.loads(told[0].as_py()), state) if len(told) else state


def score(docs: DataFrame, model: ConvolutionModel) -> DataFrame:
    """doc_id, held_out, score, predicted (0.5), and flagged by the calibrated cut-off of the row's language."""
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit("")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            scores = model.scores(*text_buffer(batch.column(1)))
            cut = np.array([model.cutoffs.get(x, model.cutoff) for x in batch.column(2).to_pylist()])
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(scores, pa.float64()), pa.array(scores >= cut, pa.bool_())], names=["doc_id", "score", "flagged"])

    rows = small_batches(docs).select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.coalesce(lang, F.lit("")).alias("lang"))
    scored = rows.mapInArrow(run, "doc_id long, score double, flagged boolean")
    return scored.select("doc_id", held_out(F.col("doc_id"), 5, 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "flagged")


def drop_toxic(docs: DataFrame, model: ConvolutionModel) -> DataFrame:
    """Rows of ``docs``, all columns, whose text isn't flagged; rows are judged one by one, so repeated ids are safe."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            scores = model.scores(*text_buffer(batch.column(batch.schema.get_field_index("text"))))
            at = batch.schema.get_field_index("lang")
            cut = np.array([model.cutoffs.get(x or "", model.cutoff) for x in batch.column(at).to_pylist()]) if at >= 0 else model.cutoff
            yield batch.filter(pa.array(scores < cut))

    return small_batches(docs).mapInArrow(run, docs.schema)

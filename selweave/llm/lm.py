"""Language-model scores: a causal self-attention model over subword ids, beside a smoothed unigram base.

Counting: one pass over the training texts sums words by 96-bit hash, with sums
inside each task before the shuffle. The ``TOP`` most frequent words (a fixed
bound) are shipped to all tasks; the other words of a text are joined with the
count table, where no word is frequent, and summed by text.

Model: all training texts are turned into piece ids once, kept in the shared
folder at two bytes a piece. Piece counts and the counts of classes after each
piece come from all of them, and so does training: trainers stream over their
share of the texts, one pass in ``ROUNDS`` rounds, and after every round their
weights are averaged in groups, so neither the driver nor a task ever holds more
than ``GROUP`` weight sets. The number of trainers grows with the pieces.

Edge cases: a null text is empty and has the end token only; without training
texts counts are 0 and the network keeps its first weights; repeated rows score
alike; an empty table gives an empty result; other columns are dropped. Words
are told apart by 96 bits of hash (odds of a clash about 1e-9 among 1e10 words).
"""

from __future__ import annotations

import io
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .attention import AttentionModel, Trainer, Vocabulary, blocks
from .common import IS_SPACE, LOWER, cut, edges, held_out, owner, plain_documents, prefix_hashes, skew_join, slices, span_hashes, text_buffer

TOP = 100_000
#: Pieces that one trainer streams over in all rounds together.
PIECES_A_TRAINER = 8_000_000
#: Pieces of a stored row, but that a text is never split.
ROW = 1 << 15
ROUNDS = 4
RATE = 2e-2
GROUP = 32
#: Hash pair of the end token.
END = (0, -1)
#: End of a text among stored piece ids.
STOP = 65_535
#: Words whose pieces a process remembers.
REMEMBERED = 400_000


def words(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, ...]:
    """(lowered bytes, starts, ends, 64-bit hash, 32-bit check, text of each word)."""
    raw = LOWER[raw]
    starts, ends = edges(~IS_SPACE[raw], offsets)
    h = span_hashes(prefix_hashes(raw), starts, ends).view(np.int64)
    size = ends - starts
    check = (size & 255) << 24 | raw[starts].astype(np.int64) << 16 | raw[ends - 1].astype(np.int64) << 8 | raw[starts + size // 2]
    return raw, starts, ends, h, check.astype(np.uint32).view(np.int32), owner(starts, offsets)


def word_counts(texts: DataFrame) -> DataFrame:
    """(a, b, c): hash pair and count of every word of the texts, ends included."""

    def flush(held: list) -> pa.RecordBatch:
        a, b, c = (np.concatenate([x[k] for x in held]) for k in range(3))
        order = np.lexsort((b, a))
        a, b, c = a[order], b[order], c[order]
        at = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]))
        return pa.RecordBatch.from_arrays([pa.array(a[at]), pa.array(b[at]), pa.array(np.add.reduceat(c, at))], names=["a", "b", "c"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, texts_ = [], 0, 0
        for batch in slices(batches, "text", 2 << 20):
            _, _, _, h, check, _ = words(*text_buffer(batch.column(0)))
            texts_ += batch.num_rows
            if len(h):
                a, first, c = np.unique(h, return_index=True, return_counts=True)
                held.append((a, check[first], c.astype(np.int64)))
                size += len(a)
            if size > 3_000_000:
                yield flush(held)
                held, size = [], 0
        if texts_:
            held.append((np.array([END[0]], np.int64), np.array([END[1]], np.int32), np.array([texts_], np.int64)))
            yield flush(held)

    return texts.select("text").mapInArrow(run, "a long, b int, c long").groupBy("a", "b").agg(F.sum("c").alias("c"))


class Pieces:
    """Piece ids of single words, by the public library; a process keeps one for each model file."""

    _kept: dict[str, Pieces] = {}

    def __init__(self, path: str) -> None:
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.size = self.model.get_piece_size()
        if self.size > STOP:
            raise ValueError("piece ids must fit in two bytes")
        self.known: dict[bytes, bytes] = {}

    @classmethod
    def of(cls, path: str) -> Pieces:
        if path not in cls._kept:
            cls._kept[path] = cls(path)
        return cls._kept[path]

    def encode(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of words, and their number a word."""
        known = self.known
        new = [w for w in words if w not in known]
        if new:
            if len(known) + len(new) > REMEMBERED:
                known.clear()
                new = words
            found = self.model.encode([w.decode("utf-8", "replace") for w in new], out_type=int)
            sizes = [2 * len(x) for x in found]
            packed = np.fromiter(chain.from_iterable(found), np.uint16, sum(sizes) // 2).tobytes()
            at = 0
            for w, n in zip(new, sizes):
                known[w] = packed[at : at + n]
                at += n
        packed = [known[w] for w in words]
        return np.frombuffer(b"".join(packed), np.uint16), np.fromiter(map(len, packed), np.int64, len(packed)) // 2


def _spread(flat: np.ndarray, sizes: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Concatenate the stretches ``which`` of ``flat``; also the size of each."""
    begin = np.cumsum(sizes) - sizes
    n = sizes[which]
    place = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(begin[which], n)
    return flat[place], n


def _sequences(pieces: Pieces, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, tuple[np.ndarray, ...]]:
    """Piece ids of all texts in turn with STOP after each, their number a text, and the words' parts."""
    raw, starts, ends, h, check, text = words(raw, offsets)
    texts = len(offsets) - 1
    distinct, first, inverse = np.unique(h, return_index=True, return_inverse=True)
    if len(h) and (check[first][inverse] != check).any():  # two words of one hash: tell them apart by both parts
        _, first, inverse = np.unique(np.stack([h, check.astype(np.int64)]), axis=1, return_index=True, return_inverse=True)
        inverse, distinct = inverse.ravel(), h[first]
    whole = raw.tobytes()
    flat, sizes = pieces.encode([whole[s:e] for s, e in zip(starts[first].tolist(), ends[first].tolist())])
    ids, n = _spread(flat, sizes, inverse)
    number = np.bincount(text, weights=n, minlength=texts).astype(np.int64)
    out = np.full(len(ids) + texts, STOP, np.uint16)
    out[np.arange(len(ids)) + np.repeat(np.arange(texts), number)] = ids
    return out, number + 1, (distinct, check[first], inverse, text)


def _to_model(v: Vocabulary, ids: np.ndarray) -> np.ndarray:
    return np.append(v.index, np.int32(v.end))[np.minimum(ids, len(v.index))]


def _pack(weights: dict[str, np.ndarray]) -> bytes:
    out = io.BytesIO()
    np.savez(out, **weights)
    return out.getvalue()


def _unpack(raw: bytes) -> dict[str, np.ndarray]:
    with np.load(io.BytesIO(raw)) as f:
        return {k: f[k] for k in f.files}


def encoded_texts(texts: DataFrame, model_path: str) -> DataFrame:
    """(round, pieces, ids): piece ids of whole texts, two bytes each, in rows of about ``ROW`` pieces dealt to the rounds in turn."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces, number = Pieces.of(model_path), 0
        for batch in slices(batches, "text"):
            ids, sizes, _ = _sequences(pieces, *text_buffer(batch.column(0)))
            ends = np.cumsum(sizes)
            part = (ends - 1) // ROW
            last = np.append(np.flatnonzero(part[1:] != part[:-1]), len(part) - 1)
            stops = ends[last]
            starts = np.concatenate([[0], stops[:-1]])
            yield pa.RecordBatch.from_arrays([pa.array((number + np.arange(len(stops))) % ROUNDS, pa.int32()), pa.array(stops - starts, pa.int64()), pa.array([ids[s:e].tobytes() for s, e in zip(starts, stops)], pa.binary())], names=["round", "pieces", "ids"])
            number += len(stops)

    return texts.select("text").mapInArrow(run, "round int, pieces long, ids binary")


def _tallies(rows: DataFrame, size: int, cells) -> np.ndarray:
    """Sum over all stored rows of how often ``cells`` (ids -> cell numbers below ``size``) names each cell. At most ``size`` rows reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for batch in batches:
            for raw in batch.column(0):
                total += np.bincount(cells(np.frombuffer(raw.as_buffer(), np.uint16)), minlength=size)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at])], names=["cell", "c"])

    found = rows.select("ids").mapInArrow(run, "cell long, c long").groupBy("cell").agg(F.sum("c").alias("c")).toArrow()
    out = np.zeros(size, np.int64)
    out[found.column(0).to_numpy()] = found.column(1).to_numpy()
    return out


def fit(training: DataFrame, model_path: str, pieces_a_trainer: int = PIECES_A_TRAINER, rounds: int = ROUNDS) -> AttentionModel:
    """Vocabulary, prior and weights from all training texts."""
    encoded = cut(encoded_texts(training, model_path))
    pieces = encoded.agg(F.coalesce(F.sum("pieces"), F.lit(0))).first()[0]
    size = Pieces.of(model_path).size
    counts = _tallies(encoded, size + 1, lambda ids: np.minimum(ids, size))
    v = Vocabulary.of(counts[:size], int(counts[size]))
    c = v.classes

    def pairs(ids: np.ndarray) -> np.ndarray:
        y = _to_model(v, ids)
        before = np.concatenate([[v.end], y[:-1]])
        return np.where(before == v.end, v.opening, before).astype(np.int64) * c + v.group[y]

    model = AttentionModel(v, _tallies(encoded, len(v.group) * c, pairs).reshape(-1, c))
    if not pieces:
        return model
    trainers = max(1, -(-pieces // pieces_a_trainer))
    for k in range(rounds):
        found = encoded.where(F.col("round") == k).coalesce(trainers).select("ids").mapInArrow(_trainer(model, k), "tokens long, weights binary").withColumn("trainer", F.spark_partition_id().cast("long"))
        held = trainers
        while held > GROUP:
            held = -(-held // GROUP)
            found = found.withColumn("trainer", F.pmod("trainer", F.lit(held))).groupBy("trainer").applyInArrow(_average, "trainer long, tokens long, weights binary")
        rows = found.select("trainer", "tokens", "weights").toArrow()
        if rows.num_rows:
            model.p = _unpack(_average(rows).column("weights")[0].as_py())
    return model


def _trainer(model: AttentionModel, number: int):
    """One round over a trainer's rows as they stream by, from the weights of the round before."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trainer, tokens = Trainer(model, RATE * 0.6**number), 0
        for batch in batches:
            for raw in batch.column(0):
                ids = np.frombuffer(raw.as_buffer(), np.uint16)
                ends = np.flatnonzero(ids == STOP) + 1
                trainer.learn(*blocks(_to_model(model.v, ids), np.diff(ends, prepend=0), model.v.opening)[:2])
                tokens += len(ids)
        if tokens:
            yield pa.RecordBatch.from_arrays([pa.array([tokens], pa.int64()), pa.array([_pack(trainer.model.p)], pa.binary())], names=["tokens", "weights"])

    return run


def _average(table: pa.Table) -> pa.Table:
    """Mean of weight sets, by their tokens."""
    tokens = table.column("tokens").to_pylist()
    total = max(1, sum(tokens))
    out: dict[str, np.ndarray] = {}
    for n, raw in zip(tokens, table.column("weights")):
        for k, x in _unpack(raw.as_py()).items():
            out[k] = out.get(k, 0) + x.astype(np.float64) * (n / total)
    packed = _pack({k: x.astype(np.float32) for k, x in out.items()})
    return pa.table({"trainer": pa.array([table.column("trainer")[0].as_py()], pa.int64()), "tokens": pa.array([total], pa.int64()), "weights": pa.array([packed], pa.binary())})


def score(spark: SparkSession, docs: DataFrame, model_path: str, is_held_out=None) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every whole text."""
    held = is_held_out if is_held_out is not None else held_out(F.col("doc_id"), 7, 2)
    rows = plain_documents(docs).select("doc_id", held.alias("held"), F.xxhash64("text").alias("t"), F.hash("text").alias("u"), "text")
    training = rows.where("not held").select("text")
    counts = cut(word_counts(training))
    total, kinds = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    top = counts.orderBy(F.col("c").desc(), "a", "b").limit(TOP).toArrow()
    top_a, top_b, top_c = (top.column(k).to_numpy() for k in ("a", "b", "c"))
    order = np.argsort(top_a, kind="stable")
    top_a, top_b, top_c = top_a[order], top_b[order], top_c[order]
    end = top_c[(top_a == END[0]) & (top_b == END[1])]
    end_count = int(end[0]) if len(end) else int(counts.where((F.col("a") == END[0]) & (F.col("b") == END[1])).agg(F.coalesce(F.max("c"), F.lit(0))).first()[0])
    model = fit(training, model_path)
    schema = "doc_id long, held boolean, t long, u int, n_tokens long, known long, part double, score double, rare array<struct<a: long, b: int, m: int>>"
    kind = pa.struct([("a", pa.int64()), ("b", pa.int32()), ("m", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = Pieces.of(model_path)
        v = model.v
        for batch in slices(batches, "text"):
            texts = batch.num_rows
            ids, number, (distinct, check, inverse, text) = _sequences(pieces, *text_buffer(batch.column(4)))
            tokens = _to_model(v, ids)
            inputs, targets, block_text = blocks(tokens, number, v.opening)
            logs = model.text_logs(inputs, targets, block_text, texts)
            logs += v.tail_log * np.add.reduceat(tokens == v.unseen, np.cumsum(number) - number, dtype=np.int64)
            at = np.minimum(np.searchsorted(top_a, distinct), max(len(top_a) - 1, 0))
            hit = (top_a[at] == distinct) & (top_b[at] == check) if len(top_a) else np.zeros(len(distinct), bool)
            c = np.where(hit, top_c[at], 0) if len(top_a) else np.zeros(len(distinct), np.int64)
            part = np.bincount(text, weights=np.log10(c + 1.0)[inverse], minlength=texts) + np.log10(end_count + 1.0)
            known = np.bincount(text, weights=hit[inverse], minlength=texts).astype(np.int64) + (end_count > 0)
            far = np.flatnonzero(~hit[inverse])
            pair, m = np.unique(text[far] * max(len(distinct), 1) + inverse[far], return_counts=True)
            word, of = pair % max(len(distinct), 1), pair // max(len(distinct), 1)
            rare = pa.ListArray.from_arrays(pa.array(np.searchsorted(of, np.arange(texts + 1)).astype(np.int32)), pa.StructArray.from_arrays([pa.array(distinct[word]), pa.array(check[word]), pa.array(m.astype(np.int32))], fields=list(kind)))
            n_words = np.bincount(text, minlength=texts)
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(1), batch.column(2), batch.column(3), pa.array(n_words + 1, pa.int64()), pa.array(known), pa.array(part), pa.array(logs / np.log(10.0)), rare], names=["doc_id", "held", "t", "u", "n_tokens", "known", "part", "score", "rare"])

    scored = cut(rows.mapInArrow(run, schema))
    # one row a text: its rare words, how many documents have it, and one score for all of them, as sums of floats
    # differ in the last digits with the batch that a copy stands in
    one = scored.groupBy("t", "u").agg(F.first("rare").alias("rare"), F.count("*").alias("copies"), F.min("score").alias("one"))
    each = one.where(F.size("rare") > 0).select("t", "u", F.explode("rare").alias("r")).select("t", "u", "r.*")
    sums = each.join(counts, ["a", "b"]).groupBy("t", "u").agg(F.sum("m").cast("long").alias("more"), F.sum(F.col("m") * F.log10(F.col("c") + 1.0)).alias("rest"))
    by_text = cut(one.where((F.size("rare") > 0) | (F.col("copies") > 1)).select("t", "u", "copies", "one").join(sums, ["t", "u"], "left"))
    whole = skew_join(scored.select("doc_id", "held", "t", "u", "n_tokens", "known", "part", "score"), by_text, ["t", "u"], "copies", F.col("doc_id"))
    return whole.select(
        "doc_id", F.col("held").alias("held_out"), "n_tokens", (F.col("known") + F.coalesce("more", F.lit(0))).cast("long").alias("n_known"), F.lit(int(total)).cast("long").alias("train_tokens"),
        (F.col("part") + F.coalesce("rest", F.lit(0.0)) - F.col("n_tokens") * F.lit(float(np.log10(total + kinds + 1)))).alias("base_score"), F.coalesce("one", "score").alias("score"),
    )

"""Text quality by hashed n-gram logistic regression, trained with follow-the-regularised-leader.

Tokens are runs of letters and digits, or runs of other visible characters.
Features are hashed one- and two-grams of lower-cased tokens, and two- and
three-grams of token shapes (case, digits, the punctuation itself, and whether
the token repeats one of the two before it). A score is one sparse dot product
over all tokens of the whole text, divided by the root of their number.

The fit takes at most ``max_rows`` labelled rows (a hash of the id chooses).
Edge cases: null and empty texts have no features and get the bias alone;
without labels of both kinds the score is the share of ones (0.5 without any);
repeated rows score alike; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import IS_SPACE, LOWER, first_of_each, held_out, mix, owner, plain_documents, prefix_hashes, sample_labelled, slices, span_hashes, text_buffer

BITS = 20
_CLASS = np.full(256, 2, np.uint8)
_CLASS[IS_SPACE] = 0
_CLASS[48:58] = _CLASS[65:91] = _CLASS[97:123] = _CLASS[128:] = 1


def token_features(raw: np.ndarray, offsets: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features of a batch, document after document, and the first feature of each document."""
    kind = _CLASS[raw]
    n = len(raw)
    docs = len(offsets) - 1
    if n == 0 or not kind.any():
        return np.zeros(0, np.int64), np.zeros(docs + 1, np.int64)
    change = np.empty(n, bool)
    change[0] = True
    np.not_equal(kind[1:], kind[:-1], out=change[1:])
    inner = offsets[1:-1]
    change[inner[inner < n]] = True
    starts = np.flatnonzero(change)
    ends = np.append(starts[1:], n)
    keep = kind[starts] > 0
    starts, ends = starts[keep], ends[keep]
    token = span_hashes(prefix_hashes(LOWER[raw]), starts, ends)
    kinds = kind[starts]
    upper = np.concatenate([[0], np.cumsum((raw >= 65) & (raw <= 90))])
    lower = np.concatenate([[0], np.cumsum((raw >= 97) & (raw <= 122))])
    digit = np.concatenate([[0], np.cumsum((raw >= 48) & (raw <= 57))])
    ups, lows, digs = (c[ends] - c[starts] for c in (upper, lower, digit))
    shape = (np.minimum(ups, 2) * 3 + np.minimum(lows, 1) + 9 * np.minimum(digs, 1)).astype(np.uint64)
    shape = np.where(kinds == 2, token | np.uint64(64), shape)
    doc = owner(starts, offsets)
    same = np.zeros(len(token), np.uint64)
    for back in (1, 2):
        if len(token) > back:
            hit = (token[back:] == token[:-back]) & (doc[back:] == doc[:-back]) & (kinds[back:] == 1)
            same[back:] |= hit.astype(np.uint64) << np.uint64(back)
    shape = shape * np.uint64(8) + same

    def chained(values: np.ndarray, n_gram: int, salt: int) -> np.ndarray:
        out = values + np.uint64(salt)
        for back in range(1, n_gram):
            before = np.zeros_like(values)
            before[back:] = np.where(doc[back:] == doc[:-back], values[:-back], np.uint64(0)) if len(values) > back else 0
            out = mix(out) * np.uint64(31) + before
        return (mix(out) >> np.uint64(64 - bits)).astype(np.int64)

    features = np.stack([chained(token, 1, 1), chained(token, 2, 2), chained(shape, 2, 3), chained(shape, 3, 4)], axis=1).ravel()
    return features, 4 * first_of_each(starts, offsets)


@dataclass
class LogisticModel:
    """Weights by feature, bias; ``constant`` replaces both where nothing could be learnt."""

    weights: np.ndarray
    bias: float = 0.0
    constant: float | None = None
    rows: int = 0

    def scores(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        docs = len(offsets) - 1
        if self.constant is not None:
            return np.full(docs, self.constant)
        features, first = token_features(raw, offsets)
        sums = np.concatenate([[0.0], np.cumsum(self.weights[features].astype(np.float64))])
        count = np.diff(first)
        margin = (sums[first[1:]] - sums[first[:-1]]) / np.sqrt(np.maximum(count, 1)) + self.bias
        return 1.0 / (1.0 + np.exp(-np.clip(margin, -30, 30)))


def follow_the_leader(examples: list[tuple[np.ndarray, np.ndarray, int]], bits: int = BITS, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.05, l2: float = 0.5, epochs: int = 4, seed: int = 11) -> tuple[np.ndarray, float]:
    """Per-coordinate updates with both penalties; an example is (features, values, label)."""
    z, n = np.zeros(1 << bits), np.zeros(1 << bits)
    bz = bn = 0.0
    order = np.random.default_rng(seed)

    def weight(zs, ns):
        return np.where(np.abs(zs) <= l1, 0.0, -(zs - np.sign(zs) * l1) / ((beta + np.sqrt(ns)) / alpha + l2))

    for _ in range(epochs):
        for k in order.permutation(len(examples)):
            at, value, label = examples[k]
            w = weight(z[at], n[at])
            wb = -bz / ((beta + np.sqrt(bn)) / alpha)
            p = 1.0 / (1.0 + np.exp(-np.clip(w @ value + wb, -30, 30)))
            g = (p - label) * value
            grown = n[at] + g * g
            z[at] += g - (np.sqrt(grown) - np.sqrt(n[at])) / alpha * w
            n[at] = grown
            gb = p - label
            bz += gb - (np.sqrt(bn + gb * gb) - np.sqrt(bn)) / alpha * wb
            bn += gb * gb
    return weight(z, n).astype(np.float32), float(-bz / ((beta + np.sqrt(bn)) / alpha))


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", max_rows: int = 6000) -> LogisticModel:
    """Learn from labelled rows that aren't held out (crc32 of the id, modulo 5, not 0)."""
    chosen = sample_labelled(labels.where(~held_out(F.col("doc_id"), 5, 0)), target, max_rows)
    rows = plain_documents(docs).join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "label")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            features, first = token_features(*text_buffer(batch.column(1)))
            found = [np.unique(features[a:b], return_counts=True) for a, b in zip(first[:-1], first[1:])]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(2).cast(pa.int32()), pa.array([f.astype(np.int32).tobytes() for f, _ in found], pa.binary()), pa.array([c.astype(np.int32).tobytes() for _, c in found], pa.binary())], names=["doc_id", "label", "features", "counts"])

    got = rows.mapInArrow(run, "doc_id long, label int, features binary, counts binary").toPandas().sort_values(["doc_id", "features"])
    examples, seen = [], set()
    for r in got.itertuples(index=False):
        if r.doc_id in seen:
            continue
        seen.add(r.doc_id)
        count = np.frombuffer(r.counts, np.int32)
        examples.append((np.frombuffer(r.features, np.int32), count / np.sqrt(max(1, count.sum())), int(r.label)))
    ones = sum(e[2] for e in examples)
    if not examples or ones in (0, len(examples)):
        return LogisticModel(np.zeros(1, np.float32), constant=ones / len(examples) if examples else 0.5, rows=len(examples))
    weights, bias = follow_the_leader(examples)
    return LogisticModel(weights, bias, rows=len(examples))


def score(docs: DataFrame, model: LogisticModel, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted for every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(model.scores(*text_buffer(batch.column(1))), pa.float64())], names=["doc_id", "score"])

    scored = plain_documents(docs).mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id"), 5, 0).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))

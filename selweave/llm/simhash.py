"""Near-duplicates by similarity-preserving fingerprints and bit-sliced comparison.

Fingerprints: 4-word shingles of the lower-cased words, hashed with XXH64; a bit
is one if it is set in over half of the shingles' hashes. Two texts link if at
most ``RADIUS`` bits differ; components are the classes of linked texts.

Candidates: the 64 bits are cut into b blocks. Texts that differ in at most
RADIUS bits agree on b - RADIUS whole blocks, so each choice of that many blocks
is a table and equal blocks are a bucket. b grows with the number of distinct
fingerprints, which keeps buckets small; every choice of b is exact.

Comparison: in a bucket the fingerprints stand as vertical bit planes; XORs of
planes run through carry-save counters that hold the distances of 64 texts a
word, and a block is abandoned once all its counters exceed the radius. A bucket
gives a spanning star for each of its classes and never all pairs. Buckets over
``TILE`` members are dealt out as pairs of tiles.

Stages that drop near-duplicates take another rule than the fingerprints' radius:
texts link if the Jaccard similarity of their shingle sets reaches a bound
(``similar_classes``). The first candidates are the links of fingerprints of those
sets, by the same tables and bit planes as above. For pairs beyond the radius the
others come from an exact prefix filter (of a set's
shingles in one order for all texts, those that every similar set must share one
of). Texts of a prefix shingle are compared inside tasks by parity sketches: bit k
says whether an odd number of a set's shingles fall in group k, so the bits in
which two sketches differ are never more than the shingles that only one of the
sets has, and no similar pair is missed. The sketches' words stand vertically and
a block is abandoned once all its distances exceed their bounds. Only pairs that
pass leave the task; sketches of full width sift those of long texts once more, and
every link is checked on the whole sets. Shingles are told apart by 40 bits of hash within these sets: a text of 1e5
shingles has two alike with odds of 0.5 %, which moves a similarity by 1e-5.

Edge cases: a null text is empty, an empty one has fingerprint 0, which links
like any other; rows with a null id take part, the class id is the smallest
non-null id (null if a class has none); repeated rows share a class; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import IS_SPACE, LOWER, cut, edges, first_of_each, mix, prefix_hashes, skew_join, slices, small_batches, span_hashes, text_buffer

RADIUS = 4
SHINGLE = 4
SEED = 42
TILE = 4096
#: Distinct fingerprints a bucket would hold on average if bits were random, at most.
LOAD = 64
#: Shingles in the prefixes of more texts than this (or than a thousandth of all) come last in the order.
COMMON = 100
#: Logarithms of the groups of a sketch: the fewest, and the most that are compared inside a task.
NARROW = 10
WIDE = 16
#: Links with one text that one task checks.
STAR = 256


def fingerprint(text: bytes) -> int:
    """Unsigned 64-bit fingerprint of UTF-8 text."""
    words = text.lower().split()  # bytes: only A-Z, only the six ASCII separators
    if not words:
        return 0
    whole = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    if len(words) <= SHINGLE:
        packed = xxhash.xxh64_digest(whole, SEED)
    else:
        starts = np.concatenate([[0], ends[:-SHINGLE] + 1]).tolist()
        digest = xxhash.xxh64_digest
        packed = b"".join([digest(whole[s:e], SEED) for s, e in zip(starts, ends[SHINGLE - 1 :].tolist())])
    bits = np.unpackbits(np.frombuffer(packed, np.uint8).reshape(-1, 8), axis=1)
    ones = np.zeros(64, np.int64)
    for lo in range(0, len(bits), 4096):
        ones += bits[lo : lo + 4096].sum(axis=0, dtype=np.uint32)
    return int.from_bytes(np.packbits(2 * ones > len(bits)).tobytes(), "big")


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text, to name a row again), fp (as signed long)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            texts = batch.column(2).cast(pa.binary()).to_pylist()
            prints = np.array([fingerprint(t) for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(prints, pa.int64())], names=["doc_id", "th", "fp"])

    rows = small_batches(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.mapInArrow(run, "doc_id long, th long, fp long")


# --- bit-sliced comparison ---


def planes_of(values: np.ndarray) -> np.ndarray:
    """64 vertical planes: bit k of all values side by side in uint64 words (padded with ones at the end of no value)."""
    n = len(values)
    bits = np.unpackbits(values.astype(">u8").view(np.uint8).reshape(n, 8), axis=1)
    packed = np.packbits(bits, axis=0)
    short = -packed.shape[0] % 8
    if short:
        packed = np.concatenate([packed, np.zeros((short, 64), np.uint8)])
    return np.ascontiguousarray(packed.T).view(np.uint64)


def within(differ, shape: tuple[int, ...], radius: int = RADIUS) -> np.ndarray:
    """Lanes whose distance is at most the radius (under 8). differ(k): the XOR of plane k.

    Two planes enter a full adder at a time; counts of 8 and more stick.
    """
    ones, twos, fours, over = (np.zeros(shape, np.uint64) for _ in range(4))
    for k in range(0, 64, 2):
        a, b = differ(k), differ(k + 1)
        half = a ^ b
        carry = (a & b) | (ones & half)
        ones = ones ^ half
        more = twos & carry
        twos = twos ^ carry
        over |= fours & more
        fours = fours ^ more
        if k % 8 == 6 and k >= 14:
            far = over | _above(ones, twos, fours, radius)
            if (~far == 0).all():
                return np.zeros(shape, np.uint64)
    return ~(over | _above(ones, twos, fours, radius))


def _above(ones: np.ndarray, twos: np.ndarray, fours: np.ndarray, radius: int) -> np.ndarray:
    """Lanes whose three-bit count exceeds the radius."""
    above = np.zeros_like(ones)
    equal = ~np.zeros_like(ones)
    for plane, bit in ((fours, radius >> 2 & 1), (twos, radius >> 1 & 1), (ones, radius & 1)):
        if bit:
            equal = equal & plane
        else:
            above = above | (equal & plane)
            equal = equal & ~plane
    return above


def lanes(mask: np.ndarray, n: int) -> np.ndarray:
    """Words of a mask as n booleans a row."""
    return np.unpackbits(np.ascontiguousarray(mask).view(np.uint8), axis=-1)[..., :n].astype(bool)


def close_pairs(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Whether x[i] and y[i] are within the radius, for all i at once."""
    planes = planes_of(x ^ y)
    return lanes(within(lambda k: planes[k], planes[0].shape), len(x))


def classes_in(values: np.ndarray) -> np.ndarray:
    """For each fingerprint of a bucket, the index of the first of its class within the bucket."""
    n = len(values)
    planes = planes_of(values)
    label = np.arange(n)
    step = 64
    for lo in range(0, n, step):
        queries = values[lo : lo + step]
        rows = [np.where((queries >> np.uint64(63 - k)) & np.uint64(1), ~np.uint64(0), np.uint64(0))[:, None] for k in range(64)]
        near = lanes(within(lambda k, rows=rows: planes[k][None, :] ^ rows[k], (len(queries), planes.shape[1])), n)
        for row in near:
            at = np.flatnonzero(row)
            if len(at) > 1:
                found = np.unique(label[at])
                if len(found) > 1:
                    label[np.isin(label, found[1:])] = found[0]
    return label


def stars(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links (member, head) that span the classes of each run of equal keys; keys are sorted."""
    n = len(keys)
    starts = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    size = np.diff(np.append(starts, n))
    heads, members = [], []
    small = np.repeat(size, size) <= 24
    at = np.flatnonzero(small & (np.repeat(size, size) > 1))
    for lag in range(1, int(size[size <= 24].max(initial=1))):
        left = at[(at + lag < n)]
        left = left[keys[left + lag] == keys[left]]
        if not len(left):
            break
        hit = left[close_pairs(values[left], values[left + lag])]
        heads.append(values[hit])
        members.append(values[hit + lag])
    for s, m in zip(starts[size > 24], size[size > 24]):
        own = values[s : s + m]
        label = classes_in(own)
        moved = np.flatnonzero(label != np.arange(m))
        heads.append(own[label[moved]])
        members.append(own[moved])
    if not heads:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    return np.concatenate(members), np.concatenate(heads)


def _tables(distinct: int) -> list[int]:
    """Masks of the block choices for so many distinct fingerprints."""
    blocks = next((b for b in range(RADIUS + 2, 12) if distinct / 2.0 ** (64 * (b - RADIUS) // b) <= LOAD), 12)
    cuts = [64 * k // blocks for k in range(blocks + 1)]
    parts = [((1 << (cuts[k + 1] - cuts[k])) - 1) << cuts[k] for k in range(blocks)]
    masks = [sum(c) for c in combinations(parts, blocks - RADIUS)]
    assert len(masks) == comb(blocks, RADIUS)
    return [m - (1 << 64) if m >= 1 << 63 else m for m in masks]


def _compare(keyed: DataFrame) -> DataFrame:
    """Links of rows (t, key, fp) that stand sorted by t and key within their partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: list[np.ndarray] | None = None

        def links(t, key, fp):
            # neighbours in the sort differ in t or key: number the runs
            new = np.concatenate([[True], (t[1:] != t[:-1]) | (key[1:] != key[:-1])])
            member, head = stars(np.cumsum(new), fp.view(np.uint64))
            return pa.RecordBatch.from_arrays([pa.array(member.view(np.int64)), pa.array(head.view(np.int64))], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            now = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(3)]
            if rest is not None:
                now = [np.concatenate([r, x]) for r, x in zip(rest, now)]
            t, key, fp = now
            new = np.flatnonzero((t[1:] != t[:-1]) | (key[1:] != key[:-1]))
            whole = int(new[-1]) + 1 if len(new) else 0  # the last run may go on
            rest = [x[whole:] for x in now]
            if whole:
                yield links(t[:whole], key[:whole], fp[:whole])
        if rest is not None and len(rest[0]):
            yield links(*rest)

    return keyed.mapInArrow(run, "a long, b long")


def links(distinct: DataFrame, count: int) -> DataFrame:
    """Spanning links (a, b), a > b, of distinct fingerprints ``fp``."""
    masks = _tables(count)
    keyed = distinct.select("fp", F.explode(F.array(*(F.struct(F.lit(k).alias("t"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for k, m in enumerate(masks)))).alias("x")).select("x.t", "x.key", "fp")
    hot = cut(keyed.groupBy("t", "key").agg(F.count("*").alias("n")).where(F.col("n") > TILE))
    parts = [keyed]
    if not hot.isEmpty():
        parts = [keyed.join(hot, ["t", "key"], "left_anti")]
        tiled = keyed.join(hot, ["t", "key"]).withColumn("tiles", F.ceil(F.col("n") / TILE).cast("int")).withColumn("own", F.pmod(F.xxhash64("fp"), F.col("tiles")))
        pairs = tiled.select(F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("other"), "t", "key", "own", "fp")
        parts.append(pairs.select(F.col("t"), F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("key"), "fp"))
    found = None
    for part in parts:
        near = _compare(part.repartition("t", "key").sortWithinPartitions("t", "key"))
        found = near if found is None else found.unionByName(near)
    return found.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root): smallest node of each connected component, for nodes with links.

    Large-star and small-star rounds until nothing moves; each is an aggregation
    with map-side combine and an equi-join, so a node with many links is no
    single task's burden.
    """
    edges = cut(edges)

    def state(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(20,0)")), F.lit(0))).first())

    before = state(edges)
    while before[0]:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").where(F.col("b") != F.col("m")).select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b")))
        edges = cut(small.where("a <> b").distinct())
        now = state(edges)
        if now == before:
            break
        before = now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))


def classes(prints: DataFrame) -> DataFrame:
    """(fp, component_id) for the distinct fingerprints of ``fingerprints()``."""
    distinct = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = components(links(distinct.select("fp"), distinct.count()))
    rooted = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    heads = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    return rooted.join(heads, "root").select("fp", "component_id")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row."""
    prints = cut(fingerprints(docs))
    return prints.join(classes(prints), "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


# --- classes by shingle similarity ---


def shingle_sets(column: pa.Array, shingle: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; a shorter text is one shingle, an empty one has none."""
    raw, offsets = text_buffer(column)
    raw = LOWER[raw]
    starts, ends = edges(~IS_SPACE[raw], offsets)
    first = first_of_each(starts, offsets)
    words = span_hashes(prefix_hashes(raw), starts, ends)
    out = []
    for s, e in zip(first[:-1].tolist(), first[1:].tolist()):
        width = min(shingle, e - s)
        if not width:
            out.append(np.zeros(0, np.uint64))
            continue
        n = e - s - width + 1
        h = mix(words[s : s + n]) + np.uint64(width)
        for k in range(1, width):
            h = mix(h) * np.uint64(31) + words[s + k : s + k + n]
        out.append(np.unique(mix(h)))
    return out


def pack(own: np.ndarray) -> bytes:
    """A sorted set of hashes cut to 40 bits, five bytes each."""
    return np.unique(own >> np.uint64(24)).view(np.uint8).reshape(-1, 8)[:, :5].tobytes()


def unpack(raw: pa.Scalar) -> np.ndarray:
    own = np.frombuffer(raw.as_buffer(), np.uint8).reshape(-1, 5)
    out = np.zeros((len(own), 8), np.uint8)
    out[:, :5] = own
    return out.view(np.uint64).ravel()


def prefix(own: np.ndarray, similarity: float, common: np.ndarray) -> np.ndarray:
    """The shingles of a set of which any set of this similarity shares one; common ones come last in the order."""
    if len(common):
        own = own[np.argsort(np.isin(own, common), kind="stable")]
    return own[: len(own) - int(np.ceil(similarity * len(own) - 1e-9)) + 1]


def set_fingerprint(own: np.ndarray) -> int:
    """Unsigned 64-bit fingerprint of a set of 64-bit hashes: a bit is one if over half of them have it."""
    ones = np.zeros(64, np.int64)
    for lo in range(0, len(own), 4096):
        ones += np.unpackbits(own[lo : lo + 4096].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.uint32)
    return int.from_bytes(np.packbits(2 * ones > len(own)).tobytes(), "big")


def _fingerprint_pairs(prints: DataFrame) -> DataFrame:
    """Distinct pairs (a, b), a < b, of texts (t, fp): those of a fingerprint with its least text, and the least texts of linked fingerprints."""
    distinct = cut(prints.groupBy("fp").agg(F.min("t").alias("head"), F.count("*").alias("many")))
    same = skew_join(prints, distinct, ["fp"], "many", F.col("t")).where("t <> head").select(F.col("head").alias("a"), F.col("t").alias("b"))
    head = lambda fp, name: distinct.select(F.col("fp").alias(fp), F.col("head").alias(name))
    linked = links(distinct.select("fp"), distinct.count()).join(head("a", "x"), "a").join(head("b", "y"), "b")
    return cut(same.unionByName(linked.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))))


def _prefixes(own: DataFrame, similarity: float, common: np.ndarray) -> DataFrame:
    """(h, t, n): prefix shingles of the sets, and the sets' sizes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            t = batch.column(0).to_numpy(zero_copy_only=False)
            sets = [unpack(x) for x in batch.column(1)]
            keys = [prefix(x, similarity, common) for x in sets]
            many = [len(k) for k in keys]
            flat = np.concatenate([*keys, np.zeros(0, np.uint64)]).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(flat), pa.array(np.repeat(t, many)), pa.array(np.repeat([len(x) for x in sets], many).astype(np.int32))], names=["h", "t", "n"])

    return own.select("t", "s").mapInArrow(run, "h long, t long, n int")


def parity_sketch(own: np.ndarray, groups: int) -> bytes:
    """Bit k: whether an odd number of the hashes fall in group k."""
    odd = np.bincount((own % np.uint64(groups)).astype(np.int64), minlength=groups) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def fold(sketch: np.ndarray, size: int) -> np.ndarray:
    """The sketch of the same set over fewer groups: its parts of ``size`` bytes XORed."""
    return np.bitwise_xor.reduce(sketch.reshape(-1, size), axis=0)


def _sketches(own: DataFrame) -> DataFrame:
    """(t, n, w): size of each set and a parity sketch over twice as many groups as shingles, rounded up to a power of two."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [unpack(x) for x in batch.column(1)]
            wide = [parity_sketch(x, 1 << max(NARROW, (2 * len(x) - 1).bit_length())) for x in sets]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(x) for x in sets], pa.int32()), pa.array(wide, pa.binary())], names=["t", "n", "w"])

    return own.select("t", "s").mapInArrow(run, "t long, n int, w binary")


def _by_size(sketches: DataFrame, similarity: float) -> DataFrame:
    """(t, n, size, k): the sketch folded to 2**size groups, for each size of which the set may be the smaller or the larger one of a pair.

    A pair meets in the size of its larger set, which has at most as many shingles
    as groups (up to ``WIDE``).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for t, n, w in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                wide = np.frombuffer(w.as_buffer(), np.uint8)
                for size in sorted({min(max(NARROW, m.bit_length()), WIDE) for m in (n, int(n / similarity + 1e-9))}):
                    out.append((t, n, size, fold(wide, (1 << size) // 8).tobytes()))
            if out:
                t, n, size, k = zip(*out)
                yield pa.RecordBatch.from_arrays([pa.array(t, pa.int64()), pa.array(n, pa.int32()), pa.array(size, pa.int32()), pa.array(k, pa.binary())], names=["t", "n", "size", "k"])

    return sketches.select("t", "n", "w").mapInArrow(run, "t long, n int, size int, k binary")


def _slack(similarity: float) -> float:
    """Shingles in one set only, as a share of both sets' sizes, at this similarity."""
    return (1 - similarity) / (1 + similarity)


def _possible(pairs: DataFrame, sketches: DataFrame, similarity: float) -> DataFrame:
    """The pairs that their wide sketches don't rule out; no pair of the similarity goes."""
    slack = _slack(similarity)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y, n in zip(batch.column(2), batch.column(3), batch.column(4).to_pylist()):
                x, y = (np.frombuffer(v.as_buffer(), np.uint8) for v in (x, y))
                size = min(len(x), len(y))
                keep.append(int(np.bitwise_count(fold(x, size) ^ fold(y, size)).sum()) <= slack * n + 1e-9)
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    joined = pairs.join(sketches.select(F.col("t").alias("a"), F.col("w").alias("x"), F.col("n").alias("n_a")), "a").join(sketches.select(F.col("t").alias("b"), F.col("w").alias("y"), F.col("n").alias("n_b")), "b")
    return cut(joined.select("a", "b", "x", "y", (F.col("n_a") + F.col("n_b")).alias("n")).mapInArrow(run, "a long, b long"))


def _bound(n: np.ndarray, m: np.ndarray, slack: float) -> np.ndarray:
    """How many shingles of similar sets of these sizes may be in one only; below zero where the sizes alone rule it out."""
    bound = slack * (n + m) + 1e-9
    return np.where(np.abs(n - m) <= bound, bound, -1.0)


def _apart(x: np.ndarray, y: np.ndarray, bound: np.ndarray) -> np.ndarray:
    """Bits in which the sketches x[:, i] and y[:, j] differ, word by word; ends early once all exceed their bounds."""
    total = np.zeros(bound.shape, np.int32)
    for k in range(len(x)):
        total += np.bitwise_count(x[k][:, None] ^ y[k][None, :])
        if k % 4 == 3 and (total > bound).all():
            break
    return total


def _closest(i: np.ndarray, j: np.ndarray, apart: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each i the pair that is least apart."""
    order = np.lexsort((apart, i))
    i, j = i[order], j[order]
    first = np.concatenate([[True], i[1:] != i[:-1]])
    return i[first], j[first]


def _across(one: slice, other: slice, cols: dict[str, np.ndarray], slack: float, nearest: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows (i, j) of the two parts, of different classes, that the sketches don't rule out; nearest: for each i only the closest j."""
    root, n, y = cols["root"][other], cols["n"][other], np.ascontiguousarray(cols["k"][other].T)
    for lo in range(one.start, one.stop, 64):
        part = slice(lo, min(lo + 64, one.stop))
        bound = _bound(cols["n"][part][:, None], n[None, :], slack)
        bound[cols["root"][part][:, None] == root[None, :]] = -1
        total = _apart(np.ascontiguousarray(cols["k"][part].T), y, bound)
        i, j = np.nonzero(total <= bound)
        if nearest and len(i):
            i, j = _closest(i, j, total[i, j])
        yield i + lo, j + other.start


def _block_pairs(key: np.ndarray, cols: dict[str, np.ndarray], slack: float, nearest: bool) -> tuple[np.ndarray, np.ndarray]:
    """Candidate rows (i, j) within runs of equal keys; side 0: a whole block, 1 and 2: two tiles to be held against each other."""
    n = len(key)
    starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    size = np.diff(np.append(starts, n))
    left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    tiled = cols["side"][starts] > 0
    small = (size <= 24) & ~tiled
    at, apart = np.flatnonzero(np.repeat(small & (size > 1), size)), [np.zeros(0, np.int64)]
    for lag in range(1, int(size[small].max(initial=1))):
        at = at[at + lag < n]
        at = at[key[at + lag] == key[at]]
        own = at[cols["root"][at] != cols["root"][at + lag]]
        bound = _bound(cols["n"][own], cols["n"][own + lag], slack)
        total = np.bitwise_count(cols["k"][own] ^ cols["k"][own + lag]).sum(axis=1, dtype=np.int64)
        own, total = own[total <= bound], total[total <= bound]
        left.append(own)
        right.append(own + lag)
        apart.append(total)
    if nearest and sum(map(len, left)):
        i, j, d = np.concatenate(left), np.concatenate(right), np.concatenate(apart)
        i, j = _closest(np.concatenate([i, j]), np.concatenate([j, i]), np.concatenate([d, d]))
        left, right = [i], [j]
    for s, m, two in zip(starts[~small].tolist(), size[~small].tolist(), tiled[~small].tolist()):
        middle = s + int((cols["side"][s : s + m] == 1).sum())
        parts = (slice(s, middle), slice(middle, s + m)) if two else (slice(s, s + m), slice(s, s + m))
        for i, j in _across(*parts, cols, slack, nearest):
            left.append(i)
            right.append(j)
    return np.concatenate(left), np.concatenate(right)


def _candidates(placed: DataFrame, sketches: DataFrame, similarity: float, nearest: bool) -> DataFrame:
    """Distinct pairs (a, b), a < b, of texts that share a prefix shingle, are in different classes and may be similar.

    A shingle of over ``TILE`` texts is dealt out as pairs of tiles. ``nearest``
    takes for each text of a block the closest one of another class.
    """
    slack = _slack(similarity)
    many = placed.groupBy("h").agg(F.count("*").alias("m"))
    met = skew_join(placed, cut(many), ["h"], "m", F.col("t")).withColumn("tiles", F.ceil(F.col("m") / TILE).cast("int"))
    own = F.pmod(F.xxhash64("t"), F.col("tiles")).cast("int")
    dealt = met.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    side = F.when(F.col("own") == F.col("other"), 0).when(F.col("own") < F.col("other"), 1).otherwise(2)
    dealt = dealt.select("t", "root", F.xxhash64("h", F.least("own", "other"), F.greatest("own", "other")).alias("key"), side.alias("side"))
    rows = dealt.join(_by_size(sketches, similarity), "t").select(F.xxhash64("key", "size").alias("key"), "side", "t", "root", "n", "k", "size")
    rows = rows.repartition("key").sortWithinPartitions("size", "key", "side")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: list[np.ndarray] | None = None

        def found(key, side, t, root, n, k):
            i, j = _block_pairs(key, {"side": side, "root": root, "n": n, "k": k}, slack, nearest)
            pairs = np.unique(np.stack([np.minimum(t[i], t[j]), np.maximum(t[i], t[j])]), axis=1)
            return pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], names=["a", "b"])

        for batch in batches:
            sizes = batch.column(6).to_numpy(zero_copy_only=False)
            for size in np.unique(sizes).tolist():
                lo, hi = np.searchsorted(sizes, [size, size + 1]).tolist()
                part = batch.slice(lo, hi - lo)
                words = np.frombuffer(b"".join(part.column(5).to_pylist()), np.uint64).reshape(hi - lo, -1)
                now = [*(part.column(c).to_numpy(zero_copy_only=False) for c in range(5)), words]
                if rest is not None and rest[5].shape[1] != words.shape[1]:
                    if len(rest[0]):
                        yield found(*rest)
                    rest = None
                if rest is not None:
                    now = [np.concatenate([r, x]) for r, x in zip(rest, now)]
                new = np.flatnonzero(now[0][1:] != now[0][:-1])
                whole = int(new[-1]) + 1 if len(new) else 0  # the last run may go on
                rest = [x[whole:] for x in now]
                if whole:
                    yield found(*(x[:whole] for x in now))
        if rest is not None and len(rest[0]):
            yield found(*rest)

    return cut(rows.mapInArrow(run, "a long, b long").distinct())


def _similar(pairs: DataFrame, own: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose shingle sets reach the similarity: the sets of b come after that of their a, ``STAR`` a task or so."""
    stars_ = cut(pairs.groupBy("a").agg(F.count("*").alias("m")))
    pairs = skew_join(pairs, stars_, ["a"], "m", F.col("b")).select("a", F.pmod(F.xxhash64("b"), F.ceil(F.col("m") / STAR)).alias("part"), "b")
    sent = pairs.select("a", "part", F.col("b").alias("t")).unionByName(pairs.select("a", "part", F.col("a").alias("t")).distinct())
    dealt = sent.join(own, "t").select("a", (F.col("t") != F.col("a")).alias("later"), F.col("t").alias("b"), "s", "part")

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head, x = None, None
        for batch in batches:
            keep = []
            for a, later, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(3)):
                y = unpack(y)
                if not later:  # once more for each part
                    head, x = a, y.copy()
                    keep.append(False)
                    continue
                assert a == head
                both = len(x) + len(y)
                shared = both - len(np.unique(np.concatenate([x, y])))
                keep.append(shared >= similarity * (both - shared) - 1e-9)
            yield batch.select([0, 2]).filter(pa.array(keep, pa.bool_()))

    return dealt.repartition("a", "part").sortWithinPartitions("a", "part", "later").mapInArrow(check, "a long, b long")


def similar_classes(docs: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(th, root): hashes of the distinct texts and of the least text of their class; texts link by Jaccard similarity.

    Texts whose fingerprints link are compared first, then each text with the least text of each of its prefix shingles,
    then with the closest of another class there, then with all that are in another class still. Null, empty and blank
    texts have no shingles and are equal.
    """

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            found = shingle_sets(batch.column(1), shingle)
            prints = np.array([set_fingerprint(x) for x in found], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([pack(x) for x in found], pa.binary()), pa.array(prints)], names=["t", "s", "fp"])

    rows = small_batches(docs).select(F.xxhash64("text").alias("t"), F.coalesce("text", F.lit("")).alias("text"))
    made = cut(rows.dropDuplicates(["t"]).mapInArrow(sets, "t long, s binary, fp long"))
    own, printed = made.select("t", "s"), _fingerprint_pairs(made.where(F.length("s") > 0).select("t", "fp"))
    # the order may put any shingles last, so a part of the texts is enough to name common ones
    part, everything = 8, own.count()
    sketches = cut(_sketches(own))
    often = _prefixes(own.where(F.pmod(F.xxhash64("t"), F.lit(part)) == 0), similarity, np.zeros(0, np.uint64))
    often = often.groupBy("h").count().where(F.col("count") > max(COMMON, everything // 1000) / part)
    common = np.sort(np.array([r["h"] for r in often.select("h").toLocalIterator()], np.int64).view(np.uint64))
    near = lambda n, m: F.least(n, m) >= similarity * F.greatest(n, m) - 1e-9
    prefixes = cut(_prefixes(own, similarity, common))
    shared = cut(prefixes.groupBy("h").agg(F.count("*").alias("many"), F.min(F.struct("t", "n")).alias("head")).where("many > 1"))
    keyed = skew_join(prefixes, shared, ["h"], "many", F.col("t")).where("many is not null")
    keyed = cut(keyed.select("h", "t", "n", F.col("head.t").alias("head"), F.col("head.n").alias("m")))
    heads = cut(keyed.where((F.col("t") != F.col("head")) & near(F.col("n"), F.col("m"))).select(F.col("head").alias("a"), F.col("t").alias("b")).distinct())
    keyed = keyed.select("h", "t")
    down = lambda e: e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    blank = own.where(F.length("s") == 0).select("t")
    blank = blank.crossJoin(F.broadcast(blank.agg(F.min("t").alias("a")))).where("t <> a").select("a", F.col("t").alias("b"))
    # a is the least text of a star; its set is sent once a part
    heads = printed.unionByName(heads).distinct()
    sure = cut(_similar(_possible(heads, sketches, similarity), own, similarity).unionByName(blank))
    tried = heads
    # the closest text of another class first: it mostly joins the classes, and few pairs are left for the whole comparison
    for nearest in (True, False):
        roots = components(down(sure)).withColumnRenamed("node", "t")
        placed = keyed.join(roots, "t", "left").select("h", "t", F.coalesce("root", "t").alias("root"))
        # shingles of the same texts, as in a passage, give the same pairs: one of them is enough (texts told apart by sum, count and both ends of their hashes)
        of = placed.groupBy("h").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("many"), F.sum(F.xxhash64("t").cast("decimal(20,0)")).alias("all"), F.min("t").alias("first"), F.max("t").alias("last"))
        mixed = cut(of.where("lo <> hi").groupBy("all", "many", "first", "last").agg(F.min("h").alias("h")).select("h", "many"))
        keyed = cut(skew_join(placed, mixed, ["h"], "many", F.col("t")).where("many is not null").select("h", "t", "root"))
        rest = cut(_candidates(keyed, sketches, similarity, nearest).join(tried, ["a", "b"], "left_anti"))
        sure = cut(sure.unionByName(_similar(_possible(rest, sketches, similarity), own, similarity)))
        tried = tried.unionByName(rest)
        keyed = keyed.select("h", "t")
    roots = components(down(sure))
    return own.select("t").join(roots, own.t == roots.node, "left").select(F.col("t").alias("th"), F.coalesce("root", "t").alias("root"))


def keep_similar(docs: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """Rows of ``docs``, all columns: of each class by shingle similarity the one with the smallest id (one of several equal rows; a null id last)."""
    ids = small_batches(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"))
    classed = ids.join(similar_classes(docs, shingle, similarity), "th")
    first = classed.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "th")).alias("first"))
    side = cut(first.select(F.col("first.doc_id").alias("_kept_id"), F.col("first.th").alias("_kept_th")))
    on = F.col("doc_id").cast("long").eqNullSafe(F.col("_kept_id")) & (F.xxhash64("text") == F.col("_kept_th"))
    kept = docs.join(side, on, "left_semi")
    repeated = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th")).join(side, (F.col("doc_id").eqNullSafe(F.col("_kept_id"))) & (F.col("th") == F.col("_kept_th")), "left_semi").count() > side.count()
    if repeated:
        return docs.join(side, on).dropDuplicates(["_kept_id", "_kept_th"]).drop("_kept_id", "_kept_th")
    return kept


def keep_one(docs: DataFrame) -> DataFrame:
    """Rows of ``docs``, all columns: of each class the one with the smallest id (one of several equal rows)."""
    prints = cut(fingerprints(docs))
    named = prints.join(classes(prints), "fp")
    kept = cut(named.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).groupBy("doc_id", "th", "fp", "component_id").agg(F.count("*").alias("n_rows")))
    n, repeated, heads = kept.agg(F.count("*"), F.coalesce(F.max("n_rows"), F.lit(0)), F.countDistinct(F.coalesce(F.xxhash64("component_id"), F.col("fp")))).first()
    key = F.xxhash64("text")
    side = kept.select(F.col("doc_id").alias("_kept_id"), F.col("th").alias("_kept_th"), F.when(F.col("component_id").isNull(), F.col("fp")).otherwise(F.xxhash64("component_id")).alias("_kept_class"))
    on = F.col("doc_id").cast("long").eqNullSafe(F.col("_kept_id")) & (key == F.col("_kept_th"))
    if n == heads and repeated <= 1:
        return docs.join(side, on, "left_semi")
    return docs.join(side, on).dropDuplicates(["_kept_class"]).drop("_kept_id", "_kept_th", "_kept_class")

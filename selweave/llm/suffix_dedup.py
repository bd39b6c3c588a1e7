"""Exact removal of long repeated byte strings with a hash-compared suffix sort.

A window is a string of ``LENGTH`` bytes. Two equal windows pick the same place
inside themselves as anchor: the one with the least hash of the ``GRAM`` bytes
from there. An anchor of a text owns the run of windows that pick it.

1. Anchors are grouped by their class: gram, and digest of all bytes under the
   owned windows together with the anchor's place. A class is counted map-side.
2. Of every class that isn't alone with its gram, two occurrences (one, if all
   lie at the same place of copies of one text) meet with those of the gram's
   other classes in a task, and the suffixes at all their windows are sorted: a
   bottom-up mergesort that finds each rank by binary search, where a comparison
   finds the common extension by binary search over prefix polynomial hashes.
   Neighbours that agree over a whole window are verified byte by byte. A class
   counts as repeated once all windows of one occurrence have such a neighbour;
   its further members are those of equal class.
3. Grams with very many classes are sorted in several runs; windows that stay
   single in a run are then matched across runs by digest, with map-side
   counting, so no task holds all of a hot gram.

What rests on hashes alone: a class is named by 160 bits of two independent
hashes (odds of any clash about 1e-24 among 1e12 anchors), a text by 96 bits
(about 1e-9 among 1e10 texts), a window across runs by 128 bits (about 1e-15
among 1e12 windows).

Edge cases: a null text is empty; texts under ``LENGTH`` bytes keep all;
repeated rows and copies repeat each other's windows; an empty table gives an
empty result; ids may be null or repeat.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, mix, plain_documents, prefix_hashes, shared_folder, skew_join, slices, text_buffer
from .common import _powers as powers

LENGTH = 400
GRAM = 64
#: Places a window can pick from.
REACH = LENGTH - GRAM + 1
#: Classes of a gram that are sorted in one run.
RUN = 8192
#: Contexts sorted in one task.
TASK = 4000


def anchors_of(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, ...]:
    """(document, first window, last window, anchor, gram hash), places counted in the batch."""
    n = len(raw)
    none = tuple(np.zeros(0, np.int64) for _ in range(5))
    if n < LENGTH:
        return none
    sums = prefix_hashes(raw)
    down = powers(n)[1]
    gram = mix((sums[GRAM:] - sums[:-GRAM]) * down[: n - GRAM + 1])
    m = len(gram)
    key = (gram & np.uint64(0xFFFFFFFF00000000)) | np.arange(m, dtype=np.uint64)
    short = -m % REACH
    tiles = np.concatenate([key, np.full(short, np.iinfo(np.uint64).max, np.uint64)]).reshape(-1, REACH)
    before = np.minimum.accumulate(tiles, axis=1).ravel()
    after = np.minimum.accumulate(tiles[:, ::-1], axis=1)[:, ::-1].ravel()
    picked = np.minimum(after[: n - LENGTH + 1], before[REACH - 1 : REACH - 1 + n - LENGTH + 1]) & np.uint64(0xFFFFFFFF)
    valid = np.zeros(n + 1, np.int32)
    long = np.diff(offsets) >= LENGTH
    np.add.at(valid, offsets[:-1][long], 1)
    np.add.at(valid, offsets[1:][long] - LENGTH + 1, -1)
    inside = np.cumsum(valid[: len(picked)]) > 0
    places = np.flatnonzero(inside)
    if not len(places):
        return none
    picked = picked[places].astype(np.int64)
    new = np.concatenate([[True], (picked[1:] != picked[:-1]) | (places[1:] != places[:-1] + 1)])
    at = np.flatnonzero(new)
    first, last = places[at], places[np.append(at[1:], len(places)) - 1]
    return np.searchsorted(offsets, first, "right") - 1, first, last, picked[at], gram[picked[at]].view(np.int64)


ANCHORS = "t long, u int, lo int, off int, span int, g long, f long, e int, n long"


def anchors(docs: DataFrame) -> DataFrame:
    """Anchors of all texts: text (t, u), first window lo, anchor - lo, last window - lo, gram g, class (f, e), copies n."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            t, u = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            _, once, back = np.unique(np.stack([t, u.astype(np.int64)]), axis=1, return_index=True, return_inverse=True)
            copies = np.bincount(back.ravel(), minlength=len(once))
            if len(once) < len(t):  # copies within a batch are one text
                t, u, batch = t[once], u[once], batch.take(pa.array(once))
            raw, offsets = text_buffer(batch.column(2))
            doc, first, last, at, gram = anchors_of(raw, offsets)
            if not len(doc):
                continue
            whole = memoryview(raw.tobytes())
            digest = xxhash.xxh3_128_digest
            packed = np.frombuffer(b"".join([digest(whole[s:e], o) for s, e, o in zip(first.tolist(), (last + LENGTH).tolist(), (at - first).tolist())]), np.dtype([("f", "<i8"), ("e", "<i4"), ("x", "<i4")]))
            yield pa.RecordBatch.from_arrays([pa.array(t[doc]), pa.array(u[doc]), *(pa.array(x.astype(np.int32)) for x in (first - offsets[doc], at - first, last - first)), pa.array(gram), pa.array(packed["f"].copy()), pa.array(packed["e"].copy()), pa.array(copies[doc])], names=["t", "u", "lo", "off", "span", "g", "f", "e", "n"])

    return _named(docs).select("t", "u", "text").mapInArrow(run, ANCHORS)


def _named(docs: DataFrame) -> DataFrame:
    return plain_documents(docs).select("doc_id", F.xxhash64("text").alias("t"), F.hash("text").alias("u"), "text")


# --- suffix sort ---


class Contexts:
    """Concatenated contexts with what a comparison needs: prefix hashes and the next eight bytes of each place."""

    def __init__(self, raw: np.ndarray) -> None:
        self.raw = raw
        self.sums = prefix_hashes(raw)
        self.down = powers(len(raw) + 1)[1]
        padded = np.concatenate([raw, np.zeros(8, np.uint8)]).tobytes()
        self.head = np.empty(len(raw) + 1, np.uint64)
        for k in range(8):
            own = self.head[k::8]
            own[:] = np.frombuffer(padded, ">u8", len(own), k) if len(padded) - k >= 8 * len(own) else np.frombuffer(padded + bytes(8), ">u8", len(own), k)

    def same(self, x: np.ndarray, y: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Whether size bytes from x + start and y + start hash alike."""
        a, b = x + start, y + start
        return (self.sums[a + size] - self.sums[a]) * self.down[a] == (self.sums[b + size] - self.sums[b]) * self.down[b]

    def extension(self, x: np.ndarray, y: np.ndarray, most: int = LENGTH) -> np.ndarray:
        """Common extension of the suffixes at x and y, up to ``most``: binary search over prefix hashes."""
        got = np.zeros(len(x), np.int64)
        step = 1 << (most.bit_length() - 1)
        while step:
            size = np.minimum(step, most - got)
            got += np.where(self.same(x, y, got, size), size, 0)
            step >>= 1
        return got

    def before(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Whether the window at x sorts strictly before the one at y."""
        out = self.head[x] < self.head[y]
        tied = np.flatnonzero(self.head[x] == self.head[y])
        if len(tied):
            a, b = x[tied], y[tied]
            at = self.extension(a, b)
            last = np.minimum(at, LENGTH - 1)
            out[tied] = (at < LENGTH) & (self.raw[a + last] < self.raw[b + last])
        return out

    def equal(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Whether the windows at x and y are equal: by hash, then verified in the bytes themselves."""
        out = self.head[x] == self.head[y]
        at = np.flatnonzero(out)
        out[at] = self.extension(x[at], y[at]) >= LENGTH
        at = np.flatnonzero(out)
        for k in range(0, LENGTH, 8):  # whole windows in words of eight bytes
            if not len(at):
                break
            k = min(k, LENGTH - 8)
            ok = self.head[x[at] + k] == self.head[y[at] + k]
            out[at[~ok]] = False
            at = at[ok]
        return out


def merge_sort(ctx: Contexts, place: np.ndarray, segment: np.ndarray) -> np.ndarray:
    """Order of the suffixes at ``place`` within each segment; segments are contiguous and stay where they are."""
    n = len(place)
    order = np.arange(n)
    if n == 0:
        return order
    starts = np.flatnonzero(np.concatenate([[True], segment[1:] != segment[:-1]]))
    size = np.diff(np.append(starts, n))
    begin, length = np.repeat(starts, size), np.repeat(size, size)
    width = 1
    active = np.flatnonzero(length > width)
    while len(active):
        inner = active - begin[active]
        run = inner // width
        own = run * width
        other = np.where(run % 2 == 0, own + width, own - width)
        n_other = np.clip(length[active] - other, 0, width)
        mine = place[order[active]]
        even = run % 2 == 0
        lo, hi = np.zeros(len(active), np.int64), n_other.copy()
        while True:
            open_ = np.flatnonzero(lo < hi)
            if not len(open_):
                break
            mid = (lo[open_] + hi[open_]) >> 1
            theirs = place[order[begin[active[open_]] + other[open_] + mid]]
            x = mine[open_]
            # an element of the left run goes before equal ones of the right run
            goes = np.where(even[open_], ctx.before(theirs, x), ~ctx.before(x, theirs))
            lo[open_] = np.where(goes, mid + 1, lo[open_])
            hi[open_] = np.where(goes, hi[open_], mid)
        to = begin[active] + np.minimum(own, np.where(even, own, other)) + (inner - own) + lo
        order[to] = order[active].copy()
        width *= 2
        active = active[length[active] > width]
    return order


def repeats(contexts: list[bytes], gram: np.ndarray, off: np.ndarray, span: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(context, window, repeated?) for all windows of all contexts: equal windows of equal grams at equal places."""
    lengths = np.array([len(c) for c in contexts], np.int64)
    base = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    ctx = Contexts(np.frombuffer(b"".join(contexts), np.uint8))
    count = span + 1
    which = np.repeat(np.arange(len(contexts)), count)
    window = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count)
    _, number = np.unique(gram, return_inverse=True)
    segment = number[which] * (REACH + 1) + off[which] - window
    by = np.argsort(segment, kind="stable")
    which, window, segment = which[by], window[by], segment[by]
    near = np.zeros(len(which), bool)
    shared = segment[1:] == segment[:-1]
    near[1:] |= shared
    near[:-1] |= shared
    keep = np.flatnonzero(near)
    place = base[which[keep]] + window[keep]
    order = merge_sort(ctx, place, segment[keep])
    sorted_at, seg = place[order], segment[keep]
    hit = np.zeros(len(keep), bool)
    twin = np.flatnonzero(seg[1:] == seg[:-1])
    found = twin[ctx.equal(sorted_at[twin], sorted_at[twin + 1])]
    hit[order[found]] = True
    hit[order[found + 1]] = True
    out = np.zeros(len(which), bool)
    out[keep] = hit
    return which, window, out


def _intervals(where: np.ndarray, window: np.ndarray, hit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of hit windows of each context: (context, first, last)."""
    where, window = where[hit], window[hit]
    by = np.lexsort((window, where))
    where, window = where[by], window[by]
    if not len(where):
        return where, window, window
    new = np.flatnonzero(np.concatenate([[True], (where[1:] != where[:-1]) | (window[1:] != window[:-1] + 1)]))
    return where[new], window[new], window[np.append(new[1:], len(where)) - 1]


def _sort_task(table: pa.Table) -> pa.Table:
    """One bucket of contexts -> classes confirmed as repeated (g, f, e), repeated stretches of single ones (s, stop), and for hot grams the windows still single (a, b digests)."""
    cols = {k: table.column(k).to_numpy(zero_copy_only=False) for k in ("g", "f", "e", "n", "t", "u", "lo", "off", "span", "runs")}
    _, keep = np.unique(np.stack([cols[k].astype(np.int64) for k in ("g", "f", "e", "t", "u", "lo")]), axis=1, return_index=True)
    keep = np.sort(keep)
    cols = {k: v[keep] for k, v in cols.items()}
    contexts = table.column("context").combine_chunks().take(pa.array(keep)).to_pylist()
    where, window, hit = repeats(contexts, cols["g"], cols["off"].astype(np.int64), cols["span"].astype(np.int64))
    whole = np.bincount(where, weights=hit, minlength=len(contexts)) > cols["span"]
    single = cols["n"] == 1
    sure = np.flatnonzero(whole & ~single)
    w, first, last = _intervals(where, window, hit & ~(whole & ~single)[where])
    fields = {k: [cols[k][sure], np.zeros(len(w), cols[k].dtype)] for k in ("g", "f", "e")} | {k: [cols[k][sure], cols[k][w]] for k in ("t", "u")}
    fields |= {"kind": [np.zeros(len(sure), np.int32), np.ones(len(w), np.int32)], "s": [np.zeros(len(sure), np.int64), cols["lo"][w] + first], "stop": [np.zeros(len(sure), np.int64), cols["lo"][w] + last + LENGTH]}
    a, b = [np.zeros(len(sure) + len(w), np.int64)], [np.zeros(len(sure) + len(w), np.int64)]
    waits_at, digests = [], []
    done: set[bytes] = set()
    for k in np.flatnonzero((cols["runs"] > 1)[where]).tolist():  # one row a distinct window of this run, plus each window that waits for a verdict
        c = int(where[k])
        digest = xxhash.xxh3_128_digest(contexts[c][window[k] : window[k] + LENGTH])
        waits = bool(single[c]) and not hit[k]
        if not waits and digest in done:
            continue
        done.add(digest)
        waits_at.append(k)
        digests.append(digest)
    at = np.array(waits_at, np.int64)
    pair = np.frombuffer(b"".join(digests), "<i8").reshape(-1, 2)
    for k in ("g", "f", "e"):
        fields[k].append(np.zeros(len(at), cols[k].dtype))
    for k in ("t", "u"):
        fields[k].append(cols[k][where[at]])
    fields["kind"].append(np.full(len(at), 2, np.int32))
    fields["s"].append(cols["lo"][where[at]] + window[at])
    fields["stop"].append(cols["lo"][where[at]] + window[at] + LENGTH)
    fields |= {"a": [*a, pair[:, 0]], "b": [*b, pair[:, 1]]}
    kinds = {"u": pa.int32(), "e": pa.int32(), "kind": pa.int32(), "s": pa.int32(), "stop": pa.int32()}
    return pa.table({k: pa.array(np.concatenate(fields[k])).cast(kinds.get(k, pa.int64())) for k in SORTED})


SORTED = ("kind", "g", "f", "e", "t", "u", "s", "stop", "a", "b")


def repeated_stretches(docs: DataFrame, run: int = RUN, task: int = TASK) -> tuple[DataFrame, DataFrame]:
    """(t, u, s, stop): stretches of each text in which every window of ``LENGTH`` bytes also starts elsewhere; and (t, u, copies) of the texts with windows."""
    found = cut(anchors(docs))
    copies = cut(found.where("lo = 0").groupBy("t", "u").agg(F.sum("n").alias("copies")))
    place = F.struct("t", "u", "lo", "off", "span")
    classes = cut(found.groupBy("g", "f", "e").agg(F.sum("n").alias("n"), F.min(place).alias("one"), F.max(place).alias("two")))
    grams = classes.groupBy("g").agg(F.sum("n").alias("total"), F.count("*").alias("m")).where("total > 1").select("g", "m")
    met = skew_join(classes, cut(grams), ["g"], "m", F.col("f"))
    asked = met.where("m > 1 or (n > 1 and one <> two)").withColumn("runs", F.ceil(F.col("m") / run).cast("int"))
    asked = cut(asked.select("g", "f", "e", "n", "runs", F.explode(F.when(F.col("one") == F.col("two"), F.array("one")).otherwise(F.array("one", "two"))).alias("at")).select("g", "f", "e", "n", "runs", "at.*"))
    tasks = max(1, -(-asked.count() // task))
    asked = asked.withColumn("bucket", F.when(F.col("runs") > 1, F.xxhash64("g", F.pmod("f", F.col("runs")))).otherwise(F.pmod("g", F.lit(tasks))))
    by_text = asked.groupBy("t", "u").agg(F.collect_list(F.struct("bucket", "g", "f", "e", "n", "lo", "off", "span", "runs")).alias("asked"))
    schema = "bucket long, g long, f long, e int, n long, t long, u int, lo int, off int, span int, runs int, context binary"

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: set[tuple[int, int]] = set()  # texts of this task already taken: copies give the same contexts
        for batch in slices(batches, "text"):
            raw, offsets = text_buffer(batch.column(2))
            rows: list[tuple] = []
            for k, (t, u, asked_) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(3))):
                if (t, u) in done:
                    continue
                done.add((t, u))
                text = raw[offsets[k] : offsets[k + 1]]
                rows += [(x["bucket"], x["g"], x["f"], x["e"], x["n"], t, u, x["lo"], x["off"], x["span"], x["runs"], text[x["lo"] : x["lo"] + x["span"] + LENGTH].tobytes()) for x in asked_.as_py()]
            if rows:
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=[p.split()[0] for p in schema.split(", ")])

    wanted = cut(by_text.join(copies, ["t", "u"]))
    texts = skew_join(_named(docs), wanted, ["t", "u"], "copies", F.col("doc_id")).where("asked is not null")
    contexts = texts.select("t", "u", "text", "asked").mapInArrow(extract, schema)
    sorted_ = cut(contexts.groupBy("bucket").applyInArrow(_sort_task, "kind int, g long, f long, e int, t long, u int, s int, stop int, a long, b long"))
    # classes that the sort confirmed, and those whose occurrences are all one place of copies of a text
    sure = sorted_.where("kind = 0").select("g", "f", "e").distinct().withColumn("sure", F.lit(True))
    repeated = cut(classes.where("n > 1").join(sure, ["g", "f", "e"], "left").where("sure or one = two").select("g", "f", "e", "n", F.lit(True).alias("sure")))
    members = skew_join(found, repeated, ["g", "f", "e"], "n", F.xxhash64("t", "lo")).where("sure")
    out = members.select("t", "u", F.col("lo").alias("s"), (F.col("lo") + F.col("span") + LENGTH).alias("stop"))
    out = out.unionByName(sorted_.where("kind = 1").select("t", "u", "s", "stop"))
    waiting = sorted_.where("kind = 2")
    twice = waiting.groupBy("a", "b").agg(F.count("*").alias("times")).where("times > 1")
    met = skew_join(waiting, twice, ["a", "b"], "times", F.xxhash64("t", "s")).where("times is not null")
    return out.unionByName(met.select("t", "u", "s", "stop")), copies


def remove_repeats(docs: DataFrame) -> DataFrame:
    """Per document: n_bytes, n_removed, n_spans, kept_sha256, and whether anything was removed."""
    shared_folder(docs.sparkSession)
    stretches, copies = repeated_stretches(docs)
    by_text = cut(stretches.groupBy("t", "u").agg(F.collect_set(F.struct("s", "stop")).alias("cut")).join(copies, ["t", "u"]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            raw, offsets = text_buffer(batch.column(1))
            removed, spans, digests = [], [], []
            cuts = batch.column(2)
            for k in range(batch.num_rows):
                text = raw[offsets[k] : offsets[k + 1]]
                own = cuts[k].as_py() if cuts[k].is_valid else None
                if not own:
                    removed.append(0)
                    spans.append(0)
                    digests.append(hashlib.sha256(text.tobytes()).hexdigest())
                    continue
                level = np.zeros(len(text) + 1, np.int32)
                for x in own:
                    level[x["s"]] += 1
                    level[x["stop"]] -= 1
                gone = np.cumsum(level[:-1]) > 0
                removed.append(int(gone.sum()))
                spans.append(int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()))
                digests.append(hashlib.sha256(text[~gone].tobytes()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(np.diff(offsets)), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array(digests, pa.string()), pa.array(np.array(removed) > 0)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "repeated"])

    joined = skew_join(_named(docs), by_text, ["t", "u"], "copies", F.col("doc_id")).select("doc_id", "text", "cut")
    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, repeated boolean")

"""Benchmark decontamination by pigeonhole edit matching.

An item of m characters may be met with up to m // 20 edits. It is split into
one piece more than that, so at least one piece occurs unchanged in any such
match. One Aho-Corasick pass over a whole text finds all pieces; each hit fixes
a diagonal, and the item is verified around it with Myers' bit-parallel edit
distance. Texts and items are compared lower-cased with white space collapsed.

The items' automaton is shipped to the executors, in several passes over the
texts if the items hold more than ``max_chars`` characters.
Edge cases: null or blank items never match; null texts are empty and clean;
repeated items are reported by each of their ids; repeated rows are judged
alike; empty tables give empty (no documents) or clean (no items) results.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import plain_documents, slices, small_batches

PER_EDIT = 20
MAX_CHARS = 8 << 20


def normal(text: str) -> str:
    return " ".join(text.lower().split())


def pieces(item: str) -> list[tuple[int, str]]:
    """(offset, piece): one piece more than the edits that are allowed."""
    m = len(item)
    n = m // PER_EDIT + 1
    cuts = [m * k // n for k in range(n + 1)]
    return [(cuts[k], item[cuts[k] : cuts[k + 1]]) for k in range(n)]


def edit_distance(item: str, text: str, budget: int) -> int | None:
    """Least number of edits that turn the item into a part of the text, if within the budget (Myers, one word of m bits)."""
    m = len(item)
    where: dict[str, int] = {}
    for k, c in enumerate(item):
        where[c] = where.get(c, 0) | 1 << k
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score, best = full, 0, m, m
    for c in text:
        eq = where.get(c, 0)
        diagonal = ((((eq & up) + up) ^ up) | eq | down) & full
        grow = (down | ~(diagonal | up)) & full
        fall = up & diagonal
        if grow & top:
            score += 1
        elif fall & top:
            score -= 1
            if score < best:
                best = score
        grow, fall = (grow << 1) & full, (fall << 1) & full
        up = (fall | ~(diagonal | grow)) & full
        down = grow & diagonal
    return best if best <= budget else None


class Matcher:
    """Automaton over all pieces of the items, rebuilt once a worker."""

    def __init__(self, items: list[tuple[int, str]]) -> None:
        self.items = [(i, t) for i, t in ((i, normal(t)) for i, t in items) if t]
        held: dict[str, list[tuple[int, int]]] = {}
        for number, (_, text) in enumerate(self.items):
            for offset, piece in pieces(text):
                held.setdefault(piece, []).append((number, offset))
        self.automaton = ahocorasick.Automaton()
        for piece, owners in held.items():
            self.automaton.add_word(piece, (len(piece), owners))
        if held:
            self.automaton.make_automaton()
        self.empty = not held

    def find(self, text: str) -> list[tuple[int, int]]:
        """(item id, least distance) of the items met in a text, by id."""
        if self.empty:
            return []
        text = normal(text)
        diagonals: dict[int, set[int]] = {}
        for end, (size, owners) in self.automaton.iter(text):
            for number, offset in owners:
                diagonals.setdefault(number, set()).add(end - size + 1 - offset)
        found = []
        for number, at in diagonals.items():
            item_id, item = self.items[number]
            budget = len(item) // PER_EDIT
            best = None
            order = sorted(at)
            if any(d >= 0 and text.startswith(item, d) for d in order):
                best = 0
            lo = 0
            while best != 0 and lo < len(order):  # neighbouring diagonals share a window
                hi = lo
                while hi + 1 < len(order) and order[hi + 1] - order[hi] <= 2 * budget + 1 and order[hi + 1] - order[lo] <= 4 * len(item):
                    hi += 1
                window = text[max(0, order[lo] - budget) : max(0, order[hi] + len(item) + budget)]
                found_here = edit_distance(item, window, budget)
                if found_here is not None and (best is None or found_here < best):
                    best = found_here
                lo = hi + 1
            if best is not None:
                found.append((item_id, best))
        return sorted(found)


_BUILT: dict[int, Matcher] = {}


def _matcher(items: list[tuple[int, str]]) -> Matcher:
    key = hash(tuple(items))
    if key not in _BUILT:
        _BUILT.clear()
        _BUILT[key] = Matcher(items)
    return _BUILT[key]


def item_passes(benchmark: DataFrame, max_chars: int = MAX_CHARS) -> list[list[tuple[int, str]]]:
    """Items in groups of at most ``max_chars`` characters each (or one item)."""
    rows = benchmark.where(F.col("text").isNotNull() & F.col("item_id").isNotNull()).select("item_id", "text")
    out: list[list[tuple[int, str]]] = [[]]
    size = 0
    for item_id, text in rows.distinct().orderBy("item_id", "text").toLocalIterator():
        if size + len(text) > max_chars and out[-1]:
            out.append([])
            size = 0
        out[-1].append((int(item_id), text))
        size += len(text)
    return out


def find_items(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Per document: contaminated, n_items, item_ids (ascending), distances (in the same order)."""
    schema = "doc_id long, item_ids array<long>, distances array<int>"

    def one(items):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            matcher = _matcher(items)
            for batch in slices(batches, "text"):
                found = [matcher.find(t) for t in batch.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array([[i for i, _ in f] for f in found], pa.list_(pa.int64())), pa.array([[d for _, d in f] for f in found], pa.list_(pa.int32()))], names=["doc_id", "item_ids", "distances"])

        return run

    rows, passes = plain_documents(docs), item_passes(benchmark)
    if len(passes) == 1:
        found = rows.mapInArrow(one(passes[0]), schema)
    else:  # a later pass adds to what each row already has
        def add(batches_of, items):
            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                matcher = _matcher(items)
                for batch in slices(batches, "text"):
                    old_ids, old_far = batch.column(2).to_pylist(), batch.column(3).to_pylist()
                    found = [sorted([*zip(i, d), *matcher.find(t)]) for t, i, d in zip(batch.column(1).to_pylist(), old_ids, old_far)]
                    yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(1), pa.array([[i for i, _ in f] for f in found], pa.list_(pa.int64())), pa.array([[d for _, d in f] for f in found], pa.list_(pa.int32()))], names=["doc_id", "text", "item_ids", "distances"])

            return batches_of.mapInArrow(run, "doc_id long, text string, item_ids array<long>, distances array<int>")

        start = rows.select("doc_id", "text", F.expr("cast(array() as array<bigint>)").alias("item_ids"), F.expr("cast(array() as array<int>)").alias("distances"))
        found = reduce(add, passes, start).drop("text")
    return found.select("doc_id", (F.size("item_ids") > 0).alias("contaminated"), F.size("item_ids").cast("long").alias("n_items"), "item_ids", "distances")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Rows of ``docs``, all columns, that hold no benchmark item."""
    for items in item_passes(benchmark):

        def run(batches: Iterator[pa.RecordBatch], items=items) -> Iterator[pa.RecordBatch]:
            matcher = _matcher(items)
            for batch in slices(batches, "text"):
                texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
                yield batch.filter(pa.array([not matcher.find(t or "") for t in texts], pa.bool_()))

        docs = small_batches(docs).mapInArrow(run, docs.schema)
    return docs

"""Removal of repeated strings against a plain version: hot grams, several runs, copies."""

import hashlib
import random
from collections import Counter

import pytest

pytest.importorskip("selweave.llm")

from selweave.llm import suffix_dedup  # noqa: E402


def plain(rows, width=400):
    raw = [(t or "").encode() for _, t in rows]
    seen = Counter(b[s : s + width] for b in raw for s in range(len(b) - width + 1))
    out = Counter()
    for (i, _), b in zip(rows, raw):
        gone = bytearray(len(b))
        for s in range(len(b) - width + 1):
            if seen[b[s : s + width]] > 1:
                gone[s : s + width] = b"\1" * width
        out[i, len(b), sum(gone), len(bytes(gone).split(b"\0")) - bytes(gone).split(b"\0").count(b""), hashlib.sha256(bytes(x for x, c in zip(b, gone) if not c)).hexdigest(), sum(gone) > 0] += 1
    return out


def documents():
    draw = random.Random(3)
    word = lambda: "".join(draw.choice("abcdefgh") for _ in range(draw.randint(2, 9)))
    text = lambda n: " ".join(word() for _ in range(n))
    common, long_ = text(45), text(120)  # under and over a window with what stands around it
    rows = [(k, f"{text(30)} {common} {text(30)}") for k in range(60)]
    rows += [(100 + k, f"{text(9)} {long_} {text(9)}") for k in range(30)]
    half = [f"{common} {w}" for w in ("red", "green", "blue")]
    rows += [(200 + k, f"{text(20)} {half[k % 3]} {text(40)} {long_[: 300 + 9 * k]}") for k in range(30)]
    rows += [(300, rows[0][1]), (301, rows[0][1]), (302, long_), (303, "x" * 1500), (304, "y" * 400), (305, "y" * 399), (306, None), (307, ""), (None, long_), (None, None)]
    return rows + rows[-12:-8]


@pytest.mark.parametrize("run, task", [(2048, 4000), (3, 20)])
def test_every_repeated_window_goes(spark, monkeypatch, run, task):
    whole = suffix_dedup.repeated_stretches
    monkeypatch.setattr(suffix_dedup, "repeated_stretches", lambda docs: whole(docs, run, task))
    rows = documents()
    found = suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert Counter(tuple(r) for r in found) == plain(rows)

"""Quality rules as a learnt decision list over text statistics, in DataFrame functions only.

Statistics come from built-in string and array functions. Rules are learnt by
sequential covering: a conjunction of thresholds is grown on two thirds of the
labelled rows by information gain, pruned on the rest, and its rows are taken
away before the next one is grown. The ordered list becomes one conditional
expression, so judging a text stays inside the engine.

The fit takes at most ``max_rows`` labelled rows (a hash of the id chooses).
Edge cases: a null text has no words (and so fails the base rule); without
labels of both kinds the list is empty and keeps what the base rule keeps;
repeated rows are judged alike; an empty table gives an empty result; other
columns are dropped.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import held_out, plain_documents, sample_labelled

# The base rule.
WINDOW = 5
LEAST_WORDS = 10
MOST_REPEATED_PERCENT = 20
SYMBOLS = r"[#*$%&|<>]"
SPACE_CHARS = " \t\n\x0b\x0c\r"

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Features of the rules: name -> expression over the statistics.
FEATURES = {
    "symbols_per_word": "n_symbols / greatest(n_words, 1)",
    "repeated_share": "n_repeat_words / greatest(n_words, 1)",
    "dup_line_share": "n_dup_lines / greatest(n_lines, 1)",
    "mean_word": "word_chars / greatest(n_words, 1)",
    "capitals_per_word": "n_capital_words / greatest(n_words, 1)",
    "marks_per_word": "n_marks / greatest(n_words, 1)",
    "words": "cast(n_words as double)",
    "words_per_line": "n_words / greatest(n_lines, 1)",
}


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id and the counts of every whole text."""
    trimmed = F.btrim("text", F.lit(SPACE_CHARS))
    words = F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, r"[\x20\x09-\x0D]+"))
    lines = F.filter(F.split("text", "\n"), lambda x: F.btrim(x, F.lit(SPACE_CHARS)) != "")
    step = plain_documents(docs).select(
        "doc_id",
        words.alias("words"),
        lines.alias("lines"),
        F.regexp_count("text", F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
        F.regexp_count("text", F.lit("[A-Z]{2,}")).cast("long").alias("n_capital_words"),
        F.regexp_count("text", F.lit("[!?]+")).cast("long").alias("n_marks"),
    )
    step = step.select(
        "doc_id", "n_symbols", "n_capital_words", "n_marks",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.transform("words", lambda w: F.xxhash64(w)).alias("h"),
    )
    windows = F.when(F.size("h") < WINDOW, F.array().cast("array<bigint>")).otherwise(F.transform(F.sequence(F.lit(0), F.size("h") - WINDOW), lambda i: F.xxhash64(*(F.get("h", i + k) for k in range(WINDOW)))))
    kept = ["doc_id", "n_symbols", "n_capital_words", "n_marks", "n_words", "word_chars", "n_lines", "n_dup_lines"]
    step = step.select(*kept, windows.alias("w"))
    # places only where some window comes twice, sorted by window and then by place
    placed = F.when(F.size(F.array_distinct("w")) < F.size("w"), F.sort_array(F.transform("w", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    step = step.select(*kept, placed.alias("s"))
    last = F.size("s") - 1
    found = F.sort_array(F.filter(F.transform(F.sequence(F.lit(0), last), lambda k: F.when((F.get("s", k)["h"] == F.get("s", k + 1)["h"]) | (F.get("s", k)["h"] == F.get("s", k - 1)["h"]), F.get("s", k)["i"])), lambda p: p.isNotNull()))
    step = step.select(*kept, F.when(F.col("s").isNotNull(), found).alias("p"))
    gaps = F.zip_with(F.slice("p", 1, F.size("p") - 1), F.slice("p", 2, F.size("p") - 1), lambda a, b: F.least(F.lit(WINDOW), b - a))
    covered = F.when(F.col("p").isNull(), F.lit(0)).otherwise(F.aggregate(gaps, F.lit(WINDOW), lambda a, g: a + g))
    return step.select(*kept, covered.cast("long").alias("n_repeat_words"))


def base_failed() -> Column:
    return (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED_PERCENT * F.col("n_words"))


@dataclass
class Rule:
    """All conditions (feature, at least?, threshold) hold -> drop."""

    conditions: list[tuple[str, bool, float]] = field(default_factory=list)

    def covers(self, x: dict[str, np.ndarray], n: int) -> np.ndarray:
        hit = np.ones(n, bool)
        for name, least, cut in self.conditions:
            hit &= x[name] >= cut if least else x[name] <= cut
        return hit

    def expression(self) -> Column:
        out = F.lit(True)
        for name, least, cut in self.conditions:
            value = F.expr(FEATURES[name])
            out = out & (value >= F.lit(cut) if least else value <= F.lit(cut))
        return out

    def __str__(self) -> str:
        return " and ".join(f"{n} {'>=' if s else '<='} {c:.6g}" for n, s, c in self.conditions)


@dataclass
class DecisionList:
    rules: list[Rule] = field(default_factory=list)
    rows: int = 0

    def keeps(self) -> Column:
        """Ordered conditional expression: the first rule that holds drops, else the text is kept."""
        if not self.rules:
            return F.lit(True)
        out = F.when(self.rules[0].expression(), F.lit(False))
        for rule in self.rules[1:]:
            out = out.when(rule.expression(), F.lit(False))
        return out.otherwise(F.lit(True))


def _grow(x: dict[str, np.ndarray], bad: np.ndarray, cuts: dict[str, np.ndarray], most: int) -> Rule:
    """Add the condition with the best gain until no good row is covered."""
    rule, inside = Rule(), np.ones(len(bad), bool)
    while len(rule.conditions) < most and (~bad & inside).any():
        p0, n0 = (bad & inside).sum(), inside.sum()
        best = (1e-9, None, None)
        for name, places in cuts.items():
            for cut in places:
                for least in (True, False):
                    hit = inside & (x[name] >= cut if least else x[name] <= cut)
                    n1, p1 = hit.sum(), (hit & bad).sum()
                    if p1 and n1 < n0:
                        gain = p1 * (np.log2(p1 / n1) - np.log2(p0 / n0))
                        if gain > best[0]:
                            best = (gain, (name, least, float(cut)), hit)
        if best[1] is None:
            break
        rule.conditions.append(best[1])
        inside = best[2]
    return rule


def _prune(rule: Rule, x: dict[str, np.ndarray], bad: np.ndarray) -> Rule:
    """Drop final conditions while that doesn't lower the share of right minus wrong rows."""
    best, kept = -2.0, rule
    for k in range(len(rule.conditions), 0, -1):
        short = Rule(rule.conditions[:k])
        hit = short.covers(x, len(bad))
        worth = (2 * (hit & bad).sum() - hit.sum()) / max(hit.sum(), 1) if hit.any() else -1.0
        if worth >= best:
            best, kept = worth, short
    return kept


def learn(x: dict[str, np.ndarray], bad: np.ndarray, seed: int = 3, most_rules: int = 12, most_conditions: int = 4, least_precision: float = 0.9, least_rows: int = 4) -> DecisionList:
    """Sequential covering of the bad rows."""
    found, left = DecisionList(rows=len(bad)), np.ones(len(bad), bool)
    if not len(bad) or bad.all() or not bad.any():
        return found
    cuts = {k: np.unique(np.quantile(v, np.linspace(0, 1, 41))) for k, v in x.items()}
    draw = np.random.default_rng(seed)
    while len(found.rules) < most_rules and (bad & left).any():
        grows = draw.random(len(bad)) < 2 / 3
        g, p = left & grows, left & ~grows
        if not (bad & g).any():
            break
        rule = _prune(_grow({k: v[g] for k, v in x.items()}, bad[g], cuts, most_conditions), {k: v[p] for k, v in x.items()}, bad[p])
        hit = rule.covers(x, len(bad)) & left
        if not rule.conditions or hit.sum() < least_rows or (hit & bad).sum() < least_precision * hit.sum():
            break
        found.rules.append(rule)
        left &= ~hit
    return found


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", max_rows: int = 6000) -> DecisionList:
    """Learn from labelled rows (crc32 of the id, modulo 5, not 0) that the base rule passes."""
    chosen = sample_labelled(labels.where(~held_out(F.col("doc_id"), 5, 0)), target, max_rows)
    rows = plain_documents(docs).join(F.broadcast(chosen), "doc_id", "left_semi")
    # the base rule is applied after collecting: a filter would be pushed below the statistics and repeat them
    got = statistics(rows).join(F.broadcast(chosen), "doc_id").select("doc_id", "label", base_failed().alias("failed"), *(F.expr(e).alias(k) for k, e in FEATURES.items())).collect()
    got = sorted((r for r in got if not r["failed"]), key=tuple)
    x = {k: np.array([r[k] for r in got], float) for k in FEATURES}
    return learn(x, np.array([r["label"] == 0 for r in got], bool))


def judge(docs: DataFrame, rules: DecisionList) -> DataFrame:
    """doc_id, the base counts, base_failed, kept."""
    judged = statistics(docs).withColumn("base_failed", base_failed())
    return judged.select("doc_id", *BASE, "base_failed", F.when(F.col("base_failed"), F.lit(False)).otherwise(rules.keeps()).alias("kept"))

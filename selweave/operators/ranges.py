"""Selectivities of boxes from a point model: enumeration, and uniform, adaptive and progressive sampling.

A point model has ``order``, ``cards``, ``prob(codes, upto)`` and ``conditional(codes, k)``.
Attributes behind the last one asked, in the model's order, sum to one and are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from .query import Queries

Box = tuple[np.ndarray, np.ndarray]


def prefix_length(model: object, low: np.ndarray, high: np.ndarray) -> int:
    asked = [k for k, a in enumerate(model.order) if low[a] > 0 or high[a] < model.cards[a] - 1]
    return asked[-1] + 1 if asked else 0


def points(model: object, low: np.ndarray, high: np.ndarray) -> int:
    own = model.order[: prefix_length(model, low, high)]
    return int(np.prod([high[a] - low[a] + 1 for a in own], dtype=float)) if own else 1


def enumerate_box(model: object, low: np.ndarray, high: np.ndarray, max_points: int = 2_000_000, **_: object) -> float:
    """Sum over every point of the box."""
    upto = prefix_length(model, low, high)
    n, own = points(model, low, high), model.order[:upto]
    if n > max_points:
        raise ValueError(f"a box of {n} points; use a sampling method")
    total, size = 0.0, [int(high[a] - low[a] + 1) for a in own]
    for lo in range(0, n, 65_536):
        at = np.arange(lo, min(n, lo + 65_536))
        codes = np.zeros((len(at), len(model.cards)), np.int64)
        for a, x in zip(own, np.unravel_index(at, size) if own else ()):
            codes[:, a] = x + low[a]
        total += float(model.prob(codes, upto).sum())
    return total


def uniform_box(model: object, low: np.ndarray, high: np.ndarray, samples: int = 500, seed: int = 0, **_: object) -> float:
    """Volume times the mean probability of uniform points."""
    upto = prefix_length(model, low, high)
    codes = np.random.default_rng(seed).integers(low, high + 1, (samples, len(low)))
    return float(np.prod([high[a] - low[a] + 1 for a in model.order[:upto]], dtype=float) * model.prob(codes, upto).mean())


def adaptive_box(model: object, low: np.ndarray, high: np.ndarray, samples: int = 500, stages: int = 5, bins: int = 16, defensive: float = 0.2, seed: int = 0, corrected: bool = True, **_: object) -> float:
    """Importance sampling in stages: each attribute's histogram of sampled mass becomes its proposal.

    A uniform share keeps every point possible. Each point counts by probability
    over the chance its stage gave it, so the mean over all stages has no bias.
    ``corrected=False`` omits that division (a negative control).
    """
    upto, draw = prefix_length(model, low, high), np.random.default_rng(seed)
    own = model.order[:upto]
    if not own:
        return 1.0
    width = {a: int(high[a] - low[a] + 1) for a in own}
    count = {a: min(bins, width[a]) for a in own}
    bin_of = {a: np.arange(width[a]) * count[a] // width[a] for a in own}
    per_bin = {a: np.bincount(bin_of[a], minlength=count[a]) for a in own}
    mass = {a: np.zeros(count[a]) for a in own}
    terms, volume = [], float(np.prod([width[a] for a in own], dtype=float))
    for s in range(stages):
        n = samples // stages + (s < samples % stages)
        codes, learnt, even = np.tile(low, (n, 1)).astype(np.int64), np.ones(n), np.ones(n)
        safe = np.zeros(n, bool) if s else np.ones(n, bool)
        safe |= draw.random(n) < defensive
        for a in own:
            total = mass[a].sum()
            share = (mass[a] + 0.02 * total / count[a]) / (1.02 * total) if total > 0 else per_bin[a] / width[a]
            code_share = (share / per_bin[a])[bin_of[a]]
            code_share /= code_share.sum()
            x = np.where(safe, draw.integers(0, width[a], n), draw.choice(width[a], n, p=code_share))
            codes[:, a] += x
            learnt *= code_share[x]
            even /= width[a]
        p = model.prob(codes, upto)
        chance = (defensive * even + (1 - defensive) * learnt) if s else even
        value = p / chance
        terms.append(value if corrected else p * volume)
        for a in own:
            mass[a] += np.bincount(bin_of[a][codes[:, a] - low[a]], value, count[a])
    return float(np.concatenate(terms).mean())


def progressive_box(model: object, low: np.ndarray, high: np.ndarray, samples: int = 500, seed: int = 0, **_: object) -> float:
    """Walks the order: takes the mass inside the interval, then draws from it; the mean of the products."""
    draw, upto = np.random.default_rng(seed), prefix_length(model, low, high)
    codes, mean = np.zeros((samples, len(low)), np.int64), np.ones(samples)
    for k in range(upto):
        a = model.order[k]
        inside = model.conditional(codes, k)[:, low[a] : high[a] + 1]
        total = inside.sum(axis=1)
        mean *= total
        if k + 1 < upto:
            up = np.cumsum(inside, axis=1)
            x = (up < (draw.random(samples) * total)[:, None]).sum(axis=1)
            codes[:, a] = low[a] + np.minimum(x, high[a] - low[a])
    return float(mean.mean())


METHODS = {"enumerate": enumerate_box, "uniform": uniform_box, "adaptive": adaptive_box, "progressive": progressive_box}


def box(models: list, low: np.ndarray, high: np.ndarray, method: str = "auto", **options: object) -> float:
    """Mean over the models; ``auto`` enumerates up to 2,000 points and walks beyond. An empty interval gives 0."""
    if (low > high).any() or (high >= np.array(models[0].cards)).any():
        return 0.0
    out = []
    for m in models:
        way = ("enumerate" if points(m, low, high) <= 2_000 else "progressive") if method == "auto" else method
        out.append(METHODS[way](m, low, high, **options))
    return float(np.mean(out))


def enumerate_many(model: object, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Sums over the points of many boxes; boxes that stop at one attribute share a pass of the model."""
    out = np.ones(len(low))
    upto = np.array([prefix_length(model, lo, hi) for lo, hi in zip(low, high)], np.int64)
    for u in np.unique(upto[upto > 0]):
        own, asked = model.order[:u], np.flatnonzero(upto == u)
        width = high[np.ix_(asked, own)] - low[np.ix_(asked, own)] + 1
        size = width.prod(axis=1)
        which = np.repeat(np.arange(len(asked)), size)
        at = np.arange(len(which)) - np.repeat(np.cumsum(size) - size, size)
        codes = np.zeros((len(which), len(model.cards)), np.int64)
        for j in range(u - 1, -1, -1):
            w = width[which, j]
            codes[:, own[j]] = low[asked[which], own[j]] + at % w
            at //= w
        out[asked] = np.bincount(which, model.prob(codes, int(u)), len(asked))
    return out


#: Up to so many codes a whole conditional is as cheap as a walk along the bits.
FLAT = 8


def progressive_many(model: object, low: np.ndarray, high: np.ndarray, samples: int, seeds: list) -> np.ndarray:
    """The progressive walk of many boxes side by side: paths that agree so far share one conditional."""
    n, m = low.shape
    upto = np.array([prefix_length(model, lo, hi) for lo, hi in zip(low, high)], np.int64)
    draws = np.stack([np.random.default_rng(s).random((samples, m)) for s in seeds]) if n else np.zeros((0, samples, m))
    codes, mean = np.zeros((n * samples, m), np.int64), np.ones(n * samples)
    box_of = np.repeat(np.arange(n), samples)
    for k in range(int(upto.max()) if n else 0):
        a = model.order[k]
        rows = np.flatnonzero(upto[box_of] > k)
        if getattr(model, "by_bits", False) and model.cards[a] > FLAT:
            on = upto[box_of[rows]] > k + 1  # the others end here and draw nothing
            for part, u in ((rows[on], draws.reshape(-1, m)[rows[on], k]), (rows[~on], None)):
                if len(part):
                    total, codes[part, a] = model.interval(codes[part], k, low[box_of[part], a], high[box_of[part], a], u)
                    mean[part] *= total
            continue
        p = model.conditional(codes[rows], k)
        at = np.arange(p.shape[1])
        lo, hi = low[box_of[rows], a][:, None], high[box_of[rows], a][:, None]
        up = np.cumsum(np.where((at >= lo) & (at <= hi), p, 0.0), axis=1)
        total = up[:, -1]
        mean[rows] *= total
        x = (up < (draws.reshape(-1, m)[rows, k] * total)[:, None]).sum(axis=1)
        codes[rows, a] = np.clip(x, lo[:, 0], hi[:, 0])
    return mean.reshape(n, samples).mean(axis=1)


#: Paths or points that are judged side by side.
TOGETHER = 200_000


def boxes(models: list, low: np.ndarray, high: np.ndarray, method: str, samples: int, seeds: list) -> np.ndarray:
    """Mean over the models of many boxes; ``auto`` enumerates boxes of up to ``samples`` points and walks the others."""
    cards = np.array(models[0].cards)
    out = np.zeros(len(low))
    sound = np.flatnonzero((low <= high).all(axis=1) & (high < cards).all(axis=1))
    for m in models:
        few = np.array([points(m, low[i], high[i]) <= samples for i in sound], bool)
        if method in ("uniform", "adaptive", "enumerate"):
            out[sound] += [METHODS[method](m, low[i], high[i], samples=samples, seed=seeds[i]) for i in sound]
            continue
        walk = sound if method == "progressive" else sound[~few]
        step = max(1, TOGETHER // samples)
        for part in (walk[k : k + step] for k in range(0, len(walk), step)):
            out[part] += progressive_many(m, low[part], high[part], samples, [seeds[i] for i in part])
        rest = sound[few] if method == "auto" else sound[:0]
        for part in (rest[k : k + step] for k in range(0, len(rest), step)):
            out[part] += enumerate_many(m, low[part], high[part])
    return out / len(models)


def estimate(spark: SparkSession, models: list, q: Queries, rows: int, method: str = "auto", samples: int = 500, seed: int = 0, tasks: int = 16) -> DataFrame:
    """(qid, est_rows); queries are spread over tasks, the models travel with the job. Boxes of a batch are judged side by side."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            if len(part):
                low, high = (np.stack(part[c].to_list()).astype(np.int64) for c in ("low", "high"))
                found = boxes(models, low, high, method, samples, [[seed, int(i)] for i in part["qid"]])
                yield pd.DataFrame({"qid": part["qid"], "est_rows": found * rows})

    return q.frame(spark).repartition(tasks, "qid").mapInPandas(run, "qid long, est_rows double")

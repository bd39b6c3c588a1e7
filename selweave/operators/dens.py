"""Unsupervised estimator: a masked autoregressive network over encoded tuples."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .nets import Net, train
from .relation import Dictionary, bit_matrix, one_hot_matrix

#: Distinct tuples one training task takes; of more, several tasks train side by side and their weights are averaged.
TASK_TUPLES = 200_000
#: Weight sets that one task, or the driver, averages at once.
GROUP = 32


def attribute_order(attrs: list[str], kind: str = "random", seed: int = 0, before: list[tuple[str, str]] | None = None) -> list[int]:
    """Positions of the attributes in the order of the chain. ``before`` pairs must keep their direction; a cycle raises."""
    names = list(attrs) if kind == "natural" else [attrs[k] for k in np.random.default_rng(seed).permutation(len(attrs))]
    out: list[str] = []
    pairs = [p for p in before or [] if p[0] in names and p[1] in names]
    while names:
        free = [x for x in names if not any(b == x and a in names for a, b in pairs)]
        if not free:
            raise ValueError("the order constraints form a cycle")
        out.append(free[0])
        names.remove(free[0])
    return [attrs.index(x) for x in out]


def distinct_rows(codes: np.ndarray, cards: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct rows, and the number of each row among them; by one number a row where the domain allows."""
    if not codes.shape[1]:
        return np.zeros((min(1, len(codes)), 0), codes.dtype), np.zeros(len(codes), np.int64)
    if np.prod(np.array(cards, float)) < 2**62 and len(codes) and (codes < np.array(cards)).all():
        _, first, back = np.unique(np.ravel_multi_index(tuple(codes.T), cards), return_index=True, return_inverse=True)
        return codes[first], back.ravel()
    rows, back = np.unique(codes, axis=0, return_inverse=True)
    return rows, back.ravel()


class MaskedNet:
    """p(tuple) as a product of Bernoulli conditionals, one a position of the encoding.

    Position ``d`` has a rank in the chain; hidden units draw a degree, see the
    inputs of at most that rank, and feed the outputs of a higher one.
    """

    def __init__(self, cards: list[int], order: list[int], hidden: tuple[int, ...] = (100, 100), encoding: str = "binary", unit: str = "attribute", leak: str = "renormalise", seed: int = 0) -> None:
        self.cards, self.order, self.encoding, self.unit, self.leak = list(cards), list(order), encoding, unit, leak
        self.widths = [max(0, int(np.ceil(np.log2(c)))) if c > 1 else 0 for c in cards] if encoding == "binary" else list(cards)
        at = np.cumsum([0, *self.widths])
        self.slots = [np.arange(at[k], at[k + 1]) for k in range(len(cards))]
        d = int(at[-1])
        chain = np.concatenate([self.slots[k] for k in order]) if d else np.zeros(0, np.int64)
        if unit == "bit":
            chain = np.random.default_rng([seed, 1]).permutation(d)
        self.rank = np.empty(d, np.int64)
        self.rank[chain] = np.arange(d)
        self.hidden, self.seed = tuple(hidden), seed
        self.net = Net([d, *hidden, d], self.draw_masks(seed), seed)

    def draw_masks(self, seed: int) -> list[np.ndarray]:
        draw, d = np.random.default_rng([seed, 2]), len(self.rank)
        degree, masks = self.rank, []
        for h in self.hidden:
            low = int(degree.min()) if len(degree) else 0
            own = draw.integers(low, max(low + 1, d - 1), h)
            masks.append((degree[:, None] <= own[None, :]).astype(np.float32))
            degree = own
        return [*masks, (degree[:, None] < self.rank[None, :]).astype(np.float32)]

    def encode(self, codes: np.ndarray) -> np.ndarray:
        return (bit_matrix(codes, self.widths) if self.encoding == "binary" else one_hot_matrix(codes, self.cards)).astype(np.float32)

    def bit_logs(self, codes: np.ndarray) -> np.ndarray:
        """rows x positions: log of the probability given to the actual bit."""
        x = self.encode(codes)
        z = self.net.forward(x)[0]
        return -np.logaddexp(0, np.where(x > 0, -z, z))

    def log_prob(self, codes: np.ndarray, upto: int | None = None) -> np.ndarray:
        """Natural log of the probability of the first ``upto`` attributes of the order (all)."""
        upto = len(self.order) if upto is None else upto
        if self.unit == "bit" and upto < len(self.order):
            raise ValueError("a chain of single bits has no attribute prefixes")
        if self.leak == "renormalise" and self.by_bits:
            out, logs = np.zeros(len(codes)), self.bit_logs(codes)
            for k in range(upto):
                slots = self.slots[self.order[k]]
                if len(slots):
                    own = logs[:, slots].sum(axis=1, dtype=np.float64) - np.log(np.maximum(self._valid(codes, k), 1e-300))
                    out += np.maximum(own, np.log(1e-300))
            return out
        if self.leak == "renormalise" and self.unit == "attribute":
            out = np.zeros(len(codes))
            for k in range(upto):
                p = self.conditional(codes, k)
                out += np.log(np.maximum(p[np.arange(len(codes)), codes[:, self.order[k]]], 1e-300))
            return out
        slots = np.concatenate([self.slots[k] for k in self.order[:upto]]) if upto else np.zeros(0, np.int64)
        return self.bit_logs(codes)[:, slots].sum(axis=1)

    def prob(self, codes: np.ndarray, upto: int | None = None) -> np.ndarray:
        return np.exp(self.log_prob(codes, upto))

    def conditional(self, codes: np.ndarray, k: int) -> np.ndarray:
        """rows x codes: distribution of the k-th attribute of the order, given the ones before it."""
        a = self.order[k]
        card, slots = self.cards[a], self.slots[a]
        if card == 1 and not len(slots):
            return np.ones((len(codes), 1))
        prefix, back = distinct_rows(codes[:, self.order[:k]], [self.cards[x] for x in self.order[:k]])
        rows = np.zeros((len(prefix), len(self.cards)), np.int64)
        rows[:, self.order[:k]] = prefix
        out = np.empty((len(prefix), card))
        step = max(1, 65_536 // card)
        for lo in range(0, len(prefix), step):
            many = np.repeat(rows[lo : lo + step], card, axis=0)
            many[:, a] = np.tile(np.arange(card), len(many) // card)
            out[lo : lo + step] = np.exp(self.bit_logs(many)[:, slots].sum(axis=1)).reshape(-1, card)
        if self.leak == "renormalise":
            out /= np.maximum(out.sum(axis=1, keepdims=True), 1e-300)
        return out[back.ravel()]

    # An attribute's codes are the leaves of a tree of bits, highest first, and the chain walks that tree. An
    # interval is cut out by the paths of its two ends, so its mass takes two passes and a draw one a level,
    # where ``conditional`` takes one a code.

    @property
    def by_bits(self) -> bool:
        return self.encoding == "binary" and self.unit == "attribute"

    def _bits(self, a: int, x: np.ndarray) -> np.ndarray:
        return (x[:, None] >> np.arange(self.widths[a] - 1, -1, -1)) & 1

    def _ends(self, codes: np.ndarray, k: int, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """rows x (bits + 1), below the first bits of an end: the share of codes from low on, up to high, and of both where the ends agree so far.

        Sums of positive parts only, so that small masses keep their digits.
        """
        a = self.order[k]
        slots, n, w = self.slots[a], len(codes), self.widths[a]
        ones, zeros = [], []
        for end in (low, high):
            rows = codes.copy()
            rows[:, a] = end
            z = self.net.forward(self.encode(rows))[0][:, slots].astype(np.float64)
            ones.append(np.exp(-np.logaddexp(0, -z)))
            zeros.append(np.exp(-np.logaddexp(0, z)))
        lo, hi = self._bits(a, low) == 1, self._bits(a, high) == 1
        above, below, both = np.ones((n, w + 1)), np.ones((n, w + 1)), np.ones((n, w + 1))
        for j in range(w - 1, -1, -1):
            above[:, j] = np.where(lo[:, j], ones[0][:, j] * above[:, j + 1], zeros[0][:, j] * above[:, j + 1] + ones[0][:, j])
            below[:, j] = np.where(hi[:, j], zeros[1][:, j] + ones[1][:, j] * below[:, j + 1], zeros[1][:, j] * below[:, j + 1])
            alike = np.where(lo[:, j], ones[0][:, j], zeros[0][:, j]) * both[:, j + 1]
            both[:, j] = np.where(lo[:, j] == hi[:, j], alike, zeros[0][:, j] * above[:, j + 1] + ones[0][:, j] * below[:, j + 1])
        return above, below, both

    def _prefixes(self, codes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Distinct rows by the attributes before the k-th of the order, zero elsewhere, and the number of each row among them."""
        own = self.order[:k]
        prefix, back = distinct_rows(codes[:, own], [self.cards[x] for x in own])
        rows = np.zeros((len(prefix), len(self.cards)), np.int64)
        rows[:, own] = prefix
        return rows, back

    def _valid(self, codes: np.ndarray, k: int) -> np.ndarray:
        """Mass of the bit patterns that stand for a value of the k-th attribute."""
        a = self.order[k]
        if self.cards[a] == 1 << self.widths[a]:
            return np.ones(len(codes))
        rows, back = self._prefixes(codes, k)
        return self._ends(rows, k, np.zeros(len(rows), np.int64), np.full(len(rows), self.cards[a] - 1))[2][back, 0]

    def interval(self, codes: np.ndarray, k: int, low: np.ndarray, high: np.ndarray, u: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Mass of low to high (inclusive) of the k-th attribute, given the ones before it, and the code at share ``u`` of it (low, without ``u``)."""
        a = self.order[k]
        w = self.widths[a]
        if not w:
            return np.ones(len(codes)), low.copy()
        rows, prefix = self._prefixes(codes, k)
        box, of = np.unique((prefix << 2 * w) | (low << w) | high, return_inverse=True)
        above, below, both = self._ends(rows[box >> 2 * w], k, (box >> w) & ((1 << w) - 1), box & ((1 << w) - 1))
        mass = both[of, 0]
        if self.leak == "renormalise":
            mass = mass / np.maximum(self._valid(codes, k), 1e-300)
        if u is None:
            return mass, low.copy()
        lo, hi = self._bits(a, low) == 1, self._bits(a, high) == 1
        on_low, on_high, x, u = np.ones(len(codes), bool), np.ones(len(codes), bool), np.zeros(len(codes), np.int64), u.copy()
        for j in range(w):
            # nodes that several rows stand at are passed through the network once
            node, at = np.unique((prefix << w) | x, return_inverse=True)
            many = rows[node >> w]
            many[:, a] = (node & ((1 << w) - 1)) << (w - j)
            z = self.net.output(self.encode(many), int(self.slots[a][j]))[at].astype(np.float64)
            start_l, start_r = on_low & ~lo[:, j], on_low & lo[:, j]
            stop_l, stop_r = on_high & ~hi[:, j], on_high & hi[:, j]
            part = lambda first, last: np.where(first & last, both[of, j + 1], np.where(first, above[of, j + 1], np.where(last, below[of, j + 1], 1.0)))
            left = np.where(start_r, 0.0, np.exp(-np.logaddexp(0, z)) * part(start_l, stop_l))
            right = np.where(stop_l, 0.0, np.exp(-np.logaddexp(0, -z)) * part(start_r, stop_r))
            t = u * (left + right)
            turn = ~stop_l & (start_r | (t > left))
            own = np.where(turn, right, left)
            u = np.clip(np.divide(np.where(turn, t - left, t), own, out=np.zeros(len(t)), where=own > 0), 0.0, 1.0)
            x = 2 * x + turn
            on_low, on_high = on_low & (turn == lo[:, j]), on_high & (turn == hi[:, j])
        return mass, x

    def learn(self, codes: np.ndarray, weight: np.ndarray, epochs: int = 100, batch: int = 512, rate: float = 2e-3, dropout: float = 0.0, seed: int = 0, cycle: list[list[np.ndarray]] | None = None) -> list[float]:
        """Weighted cross entropy of all positions. ``cycle`` holds mask sets, one put in before each minibatch in turn."""
        if not len(codes) or not len(self.rank):
            return []
        x = self.encode(codes).astype(np.uint8)
        w = (weight / (weight.mean() or 1.0)).astype(np.float32)[:, None]

        def slope(rows: np.ndarray, z: np.ndarray) -> tuple[float, np.ndarray]:
            y, own = x[rows], w[rows]
            p = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
            loss = float(-(own * np.log(np.maximum(np.where(y, p, 1 - p), np.float32(1e-30)))).sum() / len(rows))
            return loss, own * (p - y) / np.float32(len(rows))

        def swap(done: int) -> None:
            self.net.masks = cycle[done % len(cycle)]

        return train(self.net, len(codes), slope, lambda rows: x[rows].astype(np.float32), epochs, min(batch, max(32, len(codes) // 20)), rate, seed, dropout, swap if cycle else None)

    def size_bytes(self) -> int:
        return self.net.size_bytes()


class Joint:
    """The exact joint table under the same protocol, for checks of the range methods."""

    def __init__(self, codes: np.ndarray, mult: np.ndarray, cards: list[int], order: list[int] | None = None) -> None:
        self.codes, self.share, self.cards = codes, mult / mult.sum(), list(cards)
        self.order = list(range(len(cards))) if order is None else order

    def prob(self, codes: np.ndarray, upto: int | None = None) -> np.ndarray:
        own = self.order[: len(self.order) if upto is None else upto]
        size = [self.cards[k] for k in own]
        key = lambda c: np.ravel_multi_index(tuple(c[:, own].T), size) if own else np.zeros(len(c), np.int64)
        keys, back = np.unique(key(self.codes), return_inverse=True)
        sums = np.bincount(back.ravel(), self.share)
        at = np.minimum(np.searchsorted(keys, key(codes)), len(keys) - 1)
        return np.where(keys[at] == key(codes), sums[at], 0.0)

    def conditional(self, codes: np.ndarray, k: int) -> np.ndarray:
        a = self.order[k]
        many = np.repeat(codes, self.cards[a], axis=0)
        many[:, a] = np.tile(np.arange(self.cards[a]), len(codes))
        p = self.prob(many, k + 1).reshape(len(codes), -1)
        total = p.sum(axis=1, keepdims=True)
        return np.divide(p, total, out=np.zeros_like(p), where=total > 0)


# --- training as Spark jobs ---


def _weighted(tuples: DataFrame) -> DataFrame:
    return tuples if "mult" in tuples.columns else tuples.withColumn("mult", F.lit(1))


def train_rounds(rows: DataFrame, attrs: list[str], start: list[list[np.ndarray]], learn: Callable[[int, list[np.ndarray], np.ndarray, np.ndarray, int, float], list[np.ndarray]], epochs: int, rate: float, rounds: int = 4) -> list[list[np.ndarray]]:
    """Weight sets trained on all rows (attributes and ``_w``), side by side.

    ``learn(k, weights, codes, w, epochs, rate)`` trains set ``k``. Rows are dealt
    by hash to as many trainers as ``TASK_TUPLES`` asks for; after each round the
    trainers' weights are averaged by rows, in groups of ``GROUP`` first. A single
    trainer has nothing to average and takes all epochs in one round.
    """
    trainers = max(1, -(-rows.count() // TASK_TUPLES))
    rounds = min(rounds, max(1, epochs)) if trainers > 1 else 1
    dealt = rows.withColumn("_trainer", F.pmod(F.xxhash64(*attrs), F.lit(trainers))).withColumn("_k", F.explode(F.array(*(F.lit(k) for k in range(len(start))))))
    schema = "k int, trainer long, n double, w binary"

    def average(parts: pd.DataFrame) -> pd.DataFrame:
        n = parts["n"].sum()
        mean = [sum(p.astype(np.float64) * (x / n) for p, x in zip(ps, parts["n"])).astype(np.float32) for ps in zip(*map(pickle.loads, parts["w"]))]
        return pd.DataFrame({"k": [int(parts["k"].iloc[0])], "trainer": [int(parts["trainer"].iloc[0])], "n": [n], "w": [pickle.dumps(mean)]})

    now = [list(x) for x in start]
    for r in range(rounds):
        own, slower = epochs // rounds + (r < epochs % rounds), rate * (1 - 0.75 * r / rounds)

        def one(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
            found = learn(key[0], now[key[0]], part[attrs].to_numpy(np.int64), part["_w"].to_numpy(float), own, slower)
            return pd.DataFrame({"k": [key[0]], "trainer": [key[1]], "n": [float(len(part))], "w": [pickle.dumps(found)]})

        found, held = dealt.groupBy("_k", "_trainer").applyInPandas(one, schema), trainers
        while held > GROUP:
            held = -(-held // GROUP)
            found = found.withColumn("trainer", F.pmod("trainer", F.lit(held))).groupBy("k", "trainer").applyInPandas(average, schema)
        for k, parts in found.toPandas().groupby("k"):  # at most GROUP weight sets of each
            now[k] = pickle.loads(average(parts)["w"][0])
    return now


def fit(tuples: DataFrame, dic: Dictionary, orders: int = 1, order: str = "random", before: list[tuple[str, str]] | None = None, hidden: tuple[int, ...] = (100, 100), encoding: str = "binary", unit: str = "attribute", leak: str = "renormalise", epochs: int = 100, dropout: float = 0.0, weight: str = "mult", seed: int = 0, start: list[MaskedNet] | None = None, rate: float = 2e-3, share: float = 1.0, masks: int = 0) -> list[MaskedNet]:
    """One network an order, all trained side by side on all tuples.

    ``share`` below 1 trains on that part of the distinct tuples, picked by hash;
    ``weight`` names the column of loss weights; ``masks`` above 1 takes so many
    draws of the hidden units' connections in turn, one a minibatch. ``start``
    continues from earlier networks.
    """
    if start is None:
        cards = [dic.cards[a] for a in dic.attrs]
        start = [MaskedNet(cards, attribute_order(dic.attrs, order, seed + k, before), hidden, encoding, unit, leak, seed + k) for k in range(orders)]
    rows = _weighted(tuples).select(*dic.attrs, F.col(weight).cast("double").alias("_w"))
    if share < 1:
        rows = rows.where(F.pmod(F.xxhash64(F.lit(seed), *dic.attrs), F.lit(1 << 30)) < int(share * (1 << 30)))

    def learn(k: int, weights: list[np.ndarray], codes: np.ndarray, w: np.ndarray, own: int, slower: float) -> list[np.ndarray]:
        model = pickle.loads(pickle.dumps(start[k]))
        model.net.put(weights)
        cycle = [model.draw_masks(seed + 1_000 * j) for j in range(masks)] if masks > 1 else None
        model.learn(codes, w, own, dropout=dropout, seed=seed, rate=slower, cycle=cycle)
        return model.net.parameters()

    out = []
    for model, weights in zip(start, train_rounds(rows, list(dic.attrs), [m.net.parameters() for m in start], learn, epochs, rate)):
        model = pickle.loads(pickle.dumps(model))
        model.net.put(weights)
        out.append(model)
    return out


def fine_tune(models: list[MaskedNet], delta: DataFrame, dic: Dictionary, epochs: int = 10, dropout: float = 0.1, rate: float = 5e-4, seed: int = 1) -> list[MaskedNet]:
    """Continues on new tuples alone with a lower rate; ``dropout=0`` is the forgetful control."""
    return fit(delta, dic, epochs=epochs, dropout=dropout, start=models, rate=rate, seed=seed)


def fit_averaged(tuples: DataFrame, dic: Dictionary, model: MaskedNet, rounds: int = 10, buckets: int = 16, rate: float = 2e-3, seed: int = 0) -> MaskedNet:
    """All tuples, wherever they lie: each partition runs a local epoch from the shared weights, and
    the weights are averaged by rows, in ``buckets`` groups first, so that the driver sees a fixed number."""
    attrs = list(dic.attrs)
    rows = _weighted(tuples).select(*attrs, F.col("mult").cast("double").alias("_w"))
    for k in range(rounds):

        def local(batches: Iterator[pd.DataFrame], model: MaskedNet = model, k: int = k) -> Iterator[pd.DataFrame]:
            seen = 0.0
            for part in batches:
                model.learn(part[attrs].to_numpy(np.int64), part["_w"].to_numpy(float), 1, rate=rate * (1 - 0.9 * k / rounds), seed=seed + k)
                seen += float(part["_w"].sum())
            if seen:
                yield pd.DataFrame({"w": [pickle.dumps([p * np.float32(1) for p in model.net.parameters()])], "n": [seen]})

        def average(parts: pd.DataFrame) -> pd.DataFrame:
            n = parts["n"].sum()
            mean = [sum(p.astype(np.float64) * (x / n) for p, x in zip(ps, parts["n"])) for ps in zip(*map(pickle.loads, parts["w"]))]
            return pd.DataFrame({"w": [pickle.dumps(mean)], "n": [n]})

        partial = rows.mapInPandas(local, "w binary, n double").withColumn("b", F.spark_partition_id() % buckets)
        found = partial.groupBy("b").applyInPandas(lambda x: average(x[["w", "n"]]), "w binary, n double").toPandas()
        if not len(found):
            return model
        for p, new in zip(model.net.parameters(), pickle.loads(average(found)["w"][0])):
            p[...] = new
    return model


def nll(models: list[MaskedNet], tuples: DataFrame, dic: Dictionary) -> DataFrame:
    """(model, bits): mean negative log2 likelihood of a tuple under each network."""
    attrs = list(dic.attrs)

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            w = part["_w"].to_numpy(float)
            for k, m in enumerate(models):
                yield pd.DataFrame({"model": [k], "s": [float(-(m.log_prob(part[attrs].to_numpy(np.int64)) * w).sum() / np.log(2))], "n": [float(w.sum())]})

    rows = _weighted(tuples).select(*attrs, F.col("mult").cast("double").alias("_w"))
    return rows.mapInPandas(score, "model int, s double, n double").groupBy("model").agg((F.sum("s") / F.sum("n")).alias("bits"))

"""The unsupervised estimator with a small network of its own for every attribute's conditional."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dens import attribute_order, train_rounds
from .nets import Net, train
from .relation import Dictionary, bit_matrix


class ConditionalNets:
    """p(tuple) as a product of categorical conditionals; network k sees the bits of the k attributes before it."""

    def __init__(self, cards: list[int], order: list[int], hidden: tuple[int, ...] = (50, 50), seed: int = 0) -> None:
        self.cards, self.order = list(cards), list(order)
        self.widths = [int(np.ceil(np.log2(c))) if c > 1 else 0 for c in cards]
        self.nets = [Net([self._width(k), *hidden, max(1, cards[a])], seed=seed + k) for k, a in enumerate(order)]

    def _width(self, k: int) -> int:
        return max(1, sum(self.widths[a] for a in self.order[:k]))

    def inputs(self, codes: np.ndarray, k: int) -> np.ndarray:
        own = self.order[:k]
        bits = bit_matrix(codes[:, own], [self.widths[a] for a in own]).astype(np.float32) if own else np.zeros((len(codes), 0), np.float32)
        return bits if bits.shape[1] else np.ones((len(codes), 1), np.float32)

    def conditional(self, codes: np.ndarray, k: int) -> np.ndarray:
        """rows x codes: distribution of the k-th attribute of the order, given the ones before it."""
        z = self.nets[k].forward(self.inputs(codes, k))[0]
        p = np.exp(z - z.max(axis=1, keepdims=True))
        return p / p.sum(axis=1, keepdims=True)

    def log_prob(self, codes: np.ndarray, upto: int | None = None) -> np.ndarray:
        out = np.zeros(len(codes))
        for k in range(len(self.order) if upto is None else upto):
            out += np.log(np.maximum(self.conditional(codes, k)[np.arange(len(codes)), codes[:, self.order[k]]], 1e-300))
        return out

    def prob(self, codes: np.ndarray, upto: int | None = None) -> np.ndarray:
        return np.exp(self.log_prob(codes, upto))

    def learn(self, k: int, codes: np.ndarray, weight: np.ndarray, epochs: int, seed: int = 0, rate: float = 2e-3, batch: int = 512) -> None:
        """Weighted cross entropy of one conditional."""
        x, y = self.inputs(codes, k), codes[:, self.order[k]]
        w = (weight / (weight.mean() or 1.0)).astype(np.float32)

        def slope(rows: np.ndarray, z: np.ndarray) -> tuple[float, np.ndarray]:
            p = np.exp(z - z.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            at = np.arange(len(rows))
            loss = float(-(w[rows] * np.log(np.maximum(p[at, y[rows]], 1e-30))).sum() / len(rows))
            p[at, y[rows]] -= 1
            return loss, w[rows, None] * p / len(rows)

        train(self.nets[k], len(codes), slope, lambda rows: x[rows], epochs, min(batch, max(32, len(codes) // 20)), rate, seed)

    def size_bytes(self) -> int:
        return sum(n.size_bytes() for n in self.nets)


def fit(tuples: DataFrame, dic: Dictionary, order: str = "random", hidden: tuple[int, ...] = (50, 50), epochs: int = 100, seed: int = 0) -> ConditionalNets:
    """All tuples; the attributes' networks are trained side by side."""
    attrs = list(dic.attrs)
    model = ConditionalNets([dic.cards[a] for a in attrs], attribute_order(attrs, order, seed), hidden, seed)
    rows = tuples.select(*attrs, F.col("mult").cast("double").alias("_w"))

    def learn(k: int, weights: list[np.ndarray], codes: np.ndarray, w: np.ndarray, own: int, rate: float) -> list[np.ndarray]:
        model.nets[k].put(weights)
        model.learn(k, codes, w, own, seed, rate)
        return model.nets[k].parameters()

    for net, weights in zip(model.nets, train_rounds(rows, attrs, [n.parameters() for n in model.nets], learn, epochs, 2e-3)):
        net.put(weights)
    return model

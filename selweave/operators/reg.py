"""Supervised estimators: regression of scaled selectivities on encoded queries."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .nets import Net, train
from .query import Queries
from .truth import true_counts


def encode_queries(q: Queries, kind: str = "onehot") -> np.ndarray:
    """queries x features.

    ``onehot``: a slot a value and one for "not asked". ``multihot``: a slot a
    covered value. ``bounds``: both ends scaled to [0, 1], and whether asked.
    ``operators``: for each end a one-hot comparison operator and the scaled value.
    """
    parts, bound = [], q.bound
    for k, card in enumerate(q.cards):
        lo, hi = q.low[:, [k]], q.high[:, [k]]
        inside = (np.arange(card) >= lo) & (np.arange(card) <= hi)
        if kind == "bounds":
            top = max(card - 1, 1)
            parts.append(np.concatenate([lo / top, hi / top, bound[:, [k]]], axis=1))
        elif kind == "operators":
            top, asked = max(card - 1, 1), bound[:, k]
            point = (q.low[:, k] == q.high[:, k]) & asked
            lower = [None if not b or lo_ == 0 and not p else "=" if p else ">=" for b, p, lo_ in zip(asked, point, q.low[:, k])]
            upper = [None if not b or p or hi_ == card - 1 else "<=" for b, p, hi_ in zip(asked, point, q.high[:, k])]
            parts += [operator_slots(lower), lo / top, operator_slots(upper), hi / top]
        elif kind == "multihot":
            parts.append(inside)
        else:
            parts.append(np.concatenate([inside & bound[:, [k]], ~bound[:, [k]]], axis=1))
    return np.concatenate(parts, axis=1).astype(np.float32)


OPERATORS = ("=", "<", "<=", ">", ">=")


def operator_slots(operators: list[str | None]) -> np.ndarray:
    """One-hot of comparison operators; None (not asked) is all zero."""
    return np.array([[o == x for x in OPERATORS] for o in operators], np.float32).reshape(len(operators), len(OPERATORS))


@dataclass
class TargetScaler:
    """|log10 selectivity|, min-max scaled; empty answers count as one tuple."""

    rows: int
    low: float = 0.0
    high: float = 1.0

    def raw(self, sel: np.ndarray) -> np.ndarray:
        return np.abs(np.log10(np.maximum(sel, 1 / max(self.rows, 1))))

    def fit(self, sel: np.ndarray) -> "TargetScaler":
        y = self.raw(np.asarray(sel, float))
        self.low, self.high = (float(y.min()), float(y.max())) if len(y) else (0.0, 1.0)
        if self.high <= self.low:
            self.high = self.low + 1.0
        return self

    def transform(self, sel: np.ndarray) -> np.ndarray:
        return (self.raw(np.asarray(sel, float)) - self.low) / (self.high - self.low)

    def inverse(self, y: np.ndarray) -> np.ndarray:
        return 10 ** -(y * (self.high - self.low) + self.low)


class Regressor:
    """Two rectified layers and a sigmoid head; loss is the mean q-error of unscaled answers, or the squared error."""

    def __init__(self, rows: int, hidden: tuple[int, ...] = (100, 100), loss: str = "qerror", ratio: str = "max", encoding: str = "onehot", seed: int = 0) -> None:
        self.scaler, self.hidden, self.loss, self.ratio, self.encoding, self.seed = TargetScaler(rows), tuple(hidden), loss, ratio, encoding, seed
        self.net: Net | None = None

    def fit(self, q: Queries, true_rows: np.ndarray, weight: np.ndarray | None = None, epochs: int = 100, batch: int = 64, rate: float = 1e-3, dropout: float = 0.0) -> "Regressor":
        """Continues from the present weights if there are any."""
        x, sel = encode_queries(q, self.encoding), np.asarray(true_rows, float) / max(self.scaler.rows, 1)
        if self.net is None:
            self.scaler.fit(sel)
            self.net = Net([x.shape[1], *self.hidden, 1], seed=self.seed)
        y = self.scaler.transform(sel)[:, None]
        w = (np.ones(len(y)) if weight is None else np.asarray(weight, float))[:, None]
        span = (self.scaler.high - self.scaler.low) * np.log(10)

        def slope(rows: np.ndarray, z: np.ndarray) -> tuple[float, np.ndarray]:
            p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
            gap = p - y[rows]
            if self.loss == "mse":
                value, d = gap**2, 2 * gap
            else:
                e = np.clip(gap * span, -6, 6)  # log ratio; clipped so that a far miss can't blow up a step
                value = np.exp(np.abs(e)) if self.ratio == "max" else np.exp(e) + np.exp(-e)
                d = (np.sign(e) * np.exp(np.abs(e)) if self.ratio == "max" else np.exp(e) - np.exp(-e)) * span
            return float((w[rows] * value).mean()), w[rows] * d * p * (1 - p) / len(rows)

        train(self.net, len(x), slope, lambda rows: x[rows], epochs, batch, rate, self.seed, dropout)
        return self

    def refresh(self, q: Queries, old_rows: np.ndarray, delta: DataFrame, epochs: int = 20, dropout: float = 0.1, rate: float = 2e-4) -> tuple["Regressor", np.ndarray]:
        """New tuples: answers of the training queries grow by their counts on ``delta`` alone, then training goes on. Returns the model and the new answers."""
        more = {r["qid"]: r["true_rows"] for r in true_counts(delta, q).collect()}  # bounded: a training log
        now = np.asarray(old_rows, float) + np.array([more[int(i)] for i in q.qid], float)
        self.scaler.rows += int(delta.agg(F.coalesce(F.sum("mult"), F.lit(0))).first()[0])
        return self.fit(q, now, epochs=epochs, dropout=dropout, rate=rate), now

    def fine_tune(self, q: Queries, true_rows: np.ndarray, epochs: int = 20, dropout: float = 0.1, rate: float = 2e-4) -> "Regressor":
        """New queries: training goes on with a smaller rate."""
        return self.fit(q, true_rows, epochs=epochs, dropout=dropout, rate=rate)

    def selectivity(self, q: Queries) -> np.ndarray:
        z = self.net.forward(encode_queries(q, self.encoding))[0][:, 0]
        return self.scaler.inverse(1 / (1 + np.exp(-np.clip(z, -30, 30))))

    def size_bytes(self) -> int:
        return self.net.size_bytes()


class LinearModel:
    """Ridge regression of the scaled target."""

    def __init__(self, rows: int, ridge: float = 1e-3, encoding: str = "onehot") -> None:
        self.scaler, self.ridge, self.encoding = TargetScaler(rows), ridge, encoding

    def _features(self, q: Queries) -> np.ndarray:
        return np.concatenate([encode_queries(q, self.encoding).astype(float), np.ones((len(q), 1))], axis=1)

    def fit(self, q: Queries, true_rows: np.ndarray) -> "LinearModel":
        sel = np.asarray(true_rows, float) / max(self.scaler.rows, 1)
        x, y = self._features(q), self.scaler.fit(sel).transform(sel)
        self.w = np.linalg.solve(x.T @ x + self.ridge * np.eye(x.shape[1]), x.T @ y)
        return self

    def selectivity(self, q: Queries) -> np.ndarray:
        return self.scaler.inverse(np.clip(self._features(q) @ self.w, 0, 1.5))


class SupportVectorModel(LinearModel):
    """Epsilon-insensitive regression by sub-gradient steps; ``rbf`` maps features by random cosines first."""

    def __init__(self, rows: int, kernel: str = "linear", epsilon: float = 0.01, width: float = 0.5, dims: int = 400, encoding: str = "onehot", seed: int = 0) -> None:
        super().__init__(rows, 1e-4, encoding)
        self.kernel, self.epsilon, self.width, self.dims, self.seed = kernel, epsilon, width, dims, seed

    def _features(self, q: Queries) -> np.ndarray:
        x = super()._features(q)
        if self.kernel == "rbf":
            draw = np.random.default_rng(self.seed)
            turn, shift = draw.standard_normal((x.shape[1], self.dims)) * self.width, draw.random(self.dims) * 2 * np.pi
            x = np.concatenate([np.cos(x @ turn + shift) * np.sqrt(2 / self.dims), np.ones((len(x), 1))], axis=1)
        return x

    def fit(self, q: Queries, true_rows: np.ndarray, epochs: int = 60, batch: int = 64) -> "SupportVectorModel":
        sel = np.asarray(true_rows, float) / max(self.scaler.rows, 1)
        x, y = self._features(q), self.scaler.fit(sel).transform(sel)
        self.w, draw, total = np.zeros(x.shape[1]), np.random.default_rng(self.seed), np.zeros(x.shape[1])
        for e in range(epochs):
            order = draw.permutation(len(x))
            for lo in range(0, len(x), batch):
                own = order[lo : lo + batch]
                gap = x[own] @ self.w - y[own]
                side = np.sign(gap) * (np.abs(gap) > self.epsilon)
                self.w -= 0.3 / np.sqrt(1 + e) * (x[own].T @ side / len(own) + self.ridge * self.w)
            if e >= epochs // 2:
                total += self.w
        self.w = total / max(1, epochs - epochs // 2)
        return self


def latency_ms(answer: Callable[[Queries], object], q: Queries, most: int = 200) -> tuple[float, float]:
    """Mean and 95 % milliseconds of single queries asked one after another; ``most`` of them are timed."""
    took = []
    for k in range(min(most, len(q))):
        one = q.take(np.array([k]))
        began = time.perf_counter()
        answer(one)
        took.append(1e3 * (time.perf_counter() - began))
    return (float(np.mean(took)), float(np.quantile(took, 0.95))) if took else (0.0, 0.0)


def estimate(spark: SparkSession, model: object, q: Queries, tasks: int = 8) -> DataFrame:
    """(qid, est_rows); constant work a query, whatever the relation's size."""
    rows, attrs, cards = model.scaler.rows, q.attrs, q.cards

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            if len(part):
                own = Queries(attrs, cards, part["qid"].to_numpy(), np.stack(part["low"].to_list()), np.stack(part["high"].to_list()))
                yield pd.DataFrame({"qid": part["qid"], "est_rows": model.selectivity(own) * rows})

    return q.frame(spark).repartition(tasks, "qid").mapInPandas(run, "qid long, est_rows double")

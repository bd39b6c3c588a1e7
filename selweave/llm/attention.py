"""A small causal self-attention model over subword indices, in numpy.

One layer: every position attends to itself and at most ``2 * BLOCK - 1``
positions before it, with content scores (queries and keys are projections of the
tokens' embeddings) plus a learnt bias by distance; the attended values and the
token's own projection meet in a rectified hidden layer. The output is a two-step softmax: a class, then a token
within its class, so most predictions touch few output rows. To the class scores
comes a fixed prior, the smoothed log share of each class after the token before,
counted over all training texts; the network learns what goes beyond it.

Texts are cut into blocks of ``BLOCK`` positions; a window is a block with the
one before it, so windows overlap by half and each position is scored once.
Windows are views of the projected rows, and a pad's row is zero in the values
and in the column that sums the attention, so no mask is needed for pads.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

BLOCK = 8
KEYS = 8
HIDDEN = 32
#: Blocks of a training step, and of a scoring step.
STEP = 1024
#: Weight of the plain class shares in the prior.
SMOOTH = 8.0


@dataclass
class Vocabulary:
    """Model index by piece id. Indices run class by class; ``unseen`` stands for all pieces that no training text has."""

    index: np.ndarray  # piece id -> model index
    tail_log: float  # log probability of a piece among the unseen ones
    group: np.ndarray  # model index -> class
    edges: np.ndarray  # class -> first model index, and the end
    weight: np.ndarray  # model index -> occurrences as a target, at least one
    opening: int
    end: int
    unseen: int

    @classmethod
    def of(cls, counts: np.ndarray, texts: int) -> Vocabulary:
        """From piece counts and the number of texts: every piece seen, in classes of like root-frequency mass."""
        seen = np.flatnonzero(counts > 0)
        mass = np.concatenate([counts[seen], [texts, 1, 0]]).astype(float)  # pieces, end, unseen, opening
        order = np.lexsort((np.arange(len(mass)), -mass))
        rank = np.empty(len(mass), np.int64)
        rank[order] = np.arange(len(mass))
        share = np.sqrt(mass[order] + 1)
        classes = int(np.ceil(np.sqrt(len(mass))))
        _, group = np.unique(np.minimum((np.cumsum(share) - share) / share.sum() * classes, classes - 1).astype(np.int64), return_inverse=True)
        index = np.full(len(counts), rank[-2], np.int32)
        index[seen] = rank[: len(seen)]
        edges = np.searchsorted(group, np.arange(group[-1] + 2))
        return cls(index, -float(np.log(max(1, len(counts) - len(seen)))), group.astype(np.int32), edges, np.maximum(mass[order], 1.0), int(rank[-1]), int(rank[-3]), int(rank[-2]))

    @property
    def classes(self) -> int:
        return len(self.edges) - 1


def blocks(tokens: np.ndarray, lengths: np.ndarray, opening: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Texts of model indices -> (inputs, targets, text of each block); -1 pads.

    Inputs of a text are the opening and its tokens but the last; targets are its
    tokens. A row of pads before each text keeps texts apart.
    """
    rows = -(-lengths // BLOCK) + 1
    first = np.cumsum(rows) - rows
    inputs = np.full((int(rows.sum()), BLOCK), -1, np.int32)
    targets = inputs.copy()
    base = (first + 1) * BLOCK
    place = np.arange(len(tokens)) - np.repeat(np.cumsum(lengths) - lengths, lengths) + np.repeat(base, lengths)
    targets.ravel()[place] = tokens
    flat = inputs.ravel()
    flat[place] = np.concatenate([[opening], tokens[:-1]]) if len(tokens) else tokens
    flat[base[lengths > 0]] = opening
    return inputs, targets, np.repeat(np.arange(len(lengths)), rows)


_AGO = np.arange(BLOCK)[:, None] + BLOCK - np.arange(2 * BLOCK)[None, :]  # distance from query to key
_CAUSAL = _AGO >= 0
_Q, _K, _OWN, _V = slice(0, KEYS), slice(KEYS, 2 * KEYS), slice(2 * KEYS, 2 * KEYS + HIDDEN), slice(2 * KEYS + HIDDEN, 2 * KEYS + 2 * HIDDEN + 1)
WIDTH = 2 * KEYS + 2 * HIDDEN + 1  # the last column sums the attention


class AttentionModel:
    """Parameters by name; scoring, and gradients for training."""

    def __init__(self, vocabulary: Vocabulary, prior: np.ndarray | None = None, seed: int = 7) -> None:
        """``prior``: occurrences of each class after each model index."""
        self.v = v = vocabulary
        n, c = len(v.group), v.classes
        draw = np.random.default_rng(seed)
        f = lambda *s, scale: (draw.standard_normal(s) * scale).astype(np.float32)
        plain = np.add.reduceat(v.weight, v.edges[:-1])
        plain /= plain.sum()
        counts = np.zeros((n, c)) if prior is None else prior
        self.prior = np.log((counts + SMOOTH * plain) / (counts.sum(axis=1, keepdims=True) + SMOOTH)).astype(np.float32)
        self.prior = np.concatenate([self.prior, np.zeros((1, c), np.float32)])
        project = np.concatenate([f(HIDDEN, 2 * KEYS, scale=0.3), np.eye(HIDDEN, dtype=np.float32), f(HIDDEN, HIDDEN, scale=0.15)], axis=1)
        token = np.concatenate([f(n, HIDDEN, scale=0.05), np.log(v.weight).astype(np.float32)[:, None]], axis=1)  # the last column is a bias
        rows = np.concatenate([f(n, HIDDEN, scale=0.4), np.zeros((1, HIDDEN), np.float32)])  # the last row is the pad's
        # embeddings start as the main directions in which the prior's rows differ
        apart = (self.prior[:-1] - self.prior[:-1].mean(axis=0)).astype(np.float64)
        _, _, axes = np.linalg.svd(apart * np.sqrt(np.minimum(v.weight, 200))[:, None], full_matrices=False)
        spread = apart @ axes[:HIDDEN].T
        rows[:-1, : spread.shape[1]] = 0.4 * spread / (spread.std() + 1e-9)
        self.p = {"rows": rows, "project": project, "ago": np.zeros(2 * BLOCK, np.float32), "shift": np.full(HIDDEN, 0.1, np.float32), "class": f(HIDDEN, c, scale=0.05), "token": token}

    def _attend(self, inputs: np.ndarray) -> tuple[np.ndarray, ...]:
        """Hidden vectors of all blocks but the first, which only is looked back at."""
        p = self.p
        embedded = np.take(p["rows"], inputs, axis=0, mode="wrap")  # -1: the pad's row, the last
        rows = np.empty((*inputs.shape, WIDTH), np.float32)
        np.matmul(embedded.reshape(-1, HIDDEN), p["project"], out=rows.reshape(-1, WIDTH)[:, :-1])
        rows[:, :, -1] = inputs >= 0
        s = rows.strides
        window = np.lib.stride_tricks.as_strided(rows, (len(inputs) - 1, 2 * BLOCK, WIDTH), s, writeable=False)
        weights = np.matmul(rows[1:, :, _Q], window[:, :, _K].transpose(0, 2, 1))
        weights += np.where(_CAUSAL, p["ago"][np.clip(_AGO, 0, 2 * BLOCK - 1)], np.float32(-1e9))
        np.minimum(weights, 30, out=weights)
        np.exp(weights, out=weights)
        mixed = np.matmul(weights, window[:, :, _V])
        total = np.maximum(mixed[:, :, HIDDEN:], np.float32(1e-20))
        mean = mixed[:, :, :HIDDEN] / total
        h = mean + rows[1:, :, _OWN]
        h += p["shift"]
        np.maximum(h, 0, out=h)
        return h, mean, total, weights, window, embedded

    def _classes(self, h: np.ndarray, before: np.ndarray) -> np.ndarray:
        """Class scores with the prior."""
        z = h[:, :HIDDEN] @ self.p["class"]
        z += np.take(self.prior, before, axis=0)
        np.minimum(z, 60, out=z)
        return z

    def _by_class(self, y: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int, int, int]]]:
        """Order of the targets by class, and (start, stop, first row, end row) of each class present."""
        group = self.v.group[y]
        order = np.argsort(group, kind="stable")
        ends = np.searchsorted(group[order], np.arange(self.v.classes + 1))
        return order, [(int(ends[c]), int(ends[c + 1]), int(self.v.edges[c]), int(self.v.edges[c + 1])) for c in range(self.v.classes) if ends[c + 1] > ends[c]]

    def text_logs(self, inputs: np.ndarray, targets: np.ndarray, text: np.ndarray, texts: int, step: int = 4096, part: int = STEP) -> np.ndarray:
        """Natural log probability of each text, every position scored once.

        Attention runs over ``part`` blocks at a time, which stay in cache; the
        output runs over ``step`` blocks, so that each class is one product.
        """
        out = np.zeros(texts)
        p = self.p
        for lo in range(1, len(inputs), step):  # the first block is a row of pads
            hi = min(lo + step, len(inputs))
            h = np.empty((hi - lo, BLOCK, HIDDEN + 1), np.float32)
            h[:, :, HIDDEN] = 1
            for k in range(lo, hi, part):
                to = min(k + part, hi)
                h[k - lo : to - lo, :, :HIDDEN] = self._attend(inputs[k - 1 : to])[0]
            y = targets[lo:hi].ravel()
            live = np.flatnonzero(y >= 0)
            y, before = y[live], inputs[lo:hi].ravel()[live]
            order, parts = self._by_class(y)
            live, y, before = live[order], y[order], before[order]
            h = np.take(h.reshape(-1, HIDDEN + 1), live, axis=0)
            z = self._classes(h, before)
            logs = z[np.arange(len(y)), self.v.group[y]].astype(np.float64)
            np.exp(z, out=z)
            logs -= np.log(z.sum(axis=1))
            for s, e, a, b in parts:
                if b - a > 1:
                    z = h[s:e] @ p["token"][a:b].T
                    np.minimum(z, 60, out=z)
                    chosen = z[np.arange(e - s), y[s:e] - a]
                    np.exp(z, out=z)
                    logs[s:e] += chosen - np.log(z.sum(axis=1))
            out += np.bincount(text[lo:hi][live // BLOCK], weights=logs, minlength=texts)
        return out

    def gradients(self, inputs: np.ndarray, targets: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean loss over the positions of all blocks but the first, and its gradients."""
        p = self.p
        h3, mean, total, weights, window, embedded = self._attend(inputs)
        y = targets[1:].ravel()
        live = np.flatnonzero(y >= 0)
        y, before = y[live], inputs[1:].ravel()[live]
        n = max(1, len(y))
        order, parts = self._by_class(y)
        live, y, before = live[order], y[order], before[order]
        h = np.empty((len(y), HIDDEN + 1), np.float32)
        h[:, :HIDDEN] = np.take(h3.reshape(-1, HIDDEN), live, axis=0)
        h[:, HIDDEN] = 1
        at = np.arange(len(y))
        z = self._classes(h, before)
        group = self.v.group[y]
        np.exp(z, out=z)
        z /= z.sum(axis=1, keepdims=True)
        chance = z[at, group]  # of the class, then times that of the token in it
        z[at, group] -= 1
        z /= n
        g = {"class": h[:, :HIDDEN].T @ z, "token": np.zeros_like(p["token"])}
        dh = z @ p["class"].T
        for s, e, a, b in parts:
            if b - a > 1:
                own, token = h[s:e], p["token"][a:b]
                z = own @ token.T
                np.minimum(z, 60, out=z)
                np.exp(z, out=z)
                z /= z.sum(axis=1, keepdims=True) * np.float32(n)
                k = np.arange(0, (e - s) * (b - a), b - a) + (y[s:e] - a)
                hit = z.ravel()[k]
                chance[s:e] *= hit * np.float32(n)
                z.ravel()[k] = hit - np.float32(1 / n)
                np.matmul(z.T, own, out=g["token"][a:b])
                dh[s:e] += z @ token[:, :HIDDEN]
        loss = -float(np.log(np.maximum(chance, 1e-37)).sum(dtype=np.float64)) / n
        d3 = np.zeros((h3.shape[0] * BLOCK, HIDDEN), np.float32)
        d3[live] = dh
        d3 = d3.reshape(h3.shape)
        d3 *= h3 > 0
        g["shift"] = d3.sum(axis=(0, 1))
        mixed = np.empty((*h3.shape[:2], HIDDEN + 1), np.float32)
        np.divide(d3, total, out=mixed[:, :, :HIDDEN])
        mixed[:, :, HIDDEN] = -np.einsum("bth,bth->bt", mixed[:, :, :HIDDEN], mean)
        dz = np.matmul(mixed, window[:, :, _V].transpose(0, 2, 1))
        dz *= weights
        g["ago"] = np.bincount(np.clip(_AGO, 0, 2 * BLOCK - 1).ravel(), weights=(dz.sum(axis=0) * _CAUSAL).ravel(), minlength=2 * BLOCK).astype(np.float32)
        d = np.empty((len(inputs), BLOCK, WIDTH), np.float32)
        d[0] = 0
        d[1:, :, _Q] = np.matmul(dz, window[:, :, _K])
        d[1:, :, _OWN] = d3
        for part, back in ((_K, np.matmul(dz.transpose(0, 2, 1), window[:, BLOCK:, _Q])), (_V, np.matmul(weights.transpose(0, 2, 1), mixed))):
            d[1:, :, part] = back[:, BLOCK:]
            d[:-1, :, part] += back[:, :BLOCK]
        d = d.reshape(-1, WIDTH)[:, :-1]
        g["project"] = embedded.reshape(-1, HIDDEN).T @ d
        d = d @ p["project"].T
        flat = inputs.ravel()
        order = np.argsort(flat, kind="stable")
        ranked = flat[order]
        starts = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
        g["rows"] = np.zeros_like(p["rows"])
        g["rows"][ranked[starts]] = np.add.reduceat(np.take(d, order, axis=0), starts, axis=0)
        g["rows"][-1] = 0  # the pad's row
        return loss, g


class Trainer:
    """Adam over stretches of neighbouring blocks; moments live as long as the trainer."""

    def __init__(self, model: AttentionModel, rate: float) -> None:
        self.model, self.rate, self.t = model, rate, 0
        self.m = {k: np.zeros_like(x) for k, x in model.p.items()}
        self.s = {k: np.zeros_like(x) for k, x in model.p.items()}

    def learn(self, inputs: np.ndarray, targets: np.ndarray, step: int = STEP) -> list[float]:
        """One pass over the blocks in order; losses by step."""
        losses = []
        for lo in range(1, len(inputs), step):
            hi = min(lo + step, len(inputs))
            loss, g = self.model.gradients(inputs[lo - 1 : hi], targets[lo - 1 : hi])
            losses.append(loss)
            self.t += 1
            rate = np.float32(self.rate * min(1.0, self.t / 10) * np.sqrt(1 - 0.98**self.t) / (1 - 0.9**self.t))
            for k, x in self.model.p.items():
                m, s, d = self.m[k], self.s[k], g[k]
                m += np.float32(0.1) * (d - m)
                d *= d
                s += np.float32(0.02) * (d - s)
                x -= rate * m / (np.sqrt(s) + np.float32(1e-8))
        return losses

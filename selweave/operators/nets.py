"""Small dense networks in numpy: optional masks, rectified hidden layers, Adam."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


class Net:
    """Layers x W + b with a 0/1 mask on each W; hidden layers are rectified, the last is linear."""

    def __init__(self, sizes: list[int], masks: list[np.ndarray] | None = None, seed: int = 0) -> None:
        draw = np.random.default_rng(seed)
        self.masks = masks
        self.weights = [(draw.standard_normal((a, b)) * np.sqrt(2 / max(a, 1))).astype(np.float32) for a, b in zip(sizes, sizes[1:])]
        self.shifts = [np.zeros(b, np.float32) for b in sizes[1:]]
        if masks is not None:
            self.weights = [w * m for w, m in zip(self.weights, masks)]

    def parameters(self) -> list[np.ndarray]:
        return [*self.weights, *self.shifts]

    def put(self, parameters: list[np.ndarray]) -> None:
        """Take other weights of the same shapes."""
        parameters = [np.array(p, np.float32) for p in parameters]
        self.weights, self.shifts = parameters[: len(self.weights)], parameters[len(self.weights) :]

    def size_bytes(self) -> int:
        return sum(p.nbytes for p in self.parameters())

    def forward(self, x: np.ndarray, drop: tuple[float, np.random.Generator] | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
        """(linear outputs, inputs of each layer). ``drop`` silences hidden units whose mask column isn't empty."""
        seen = [x]
        for k, (w, b) in enumerate(zip(self.weights, self.shifts)):
            x = x @ w + b
            if k < len(self.weights) - 1:
                np.maximum(x, 0, out=x)
                if drop is not None and drop[0] > 0:
                    keep = (drop[1].random(x.shape) >= drop[0]) / np.float32(1 - drop[0])
                    if self.masks is not None:
                        keep = np.where(self.masks[k].any(axis=0), keep, 1)
                    x = (x * keep).astype(np.float32)
                seen.append(x)
        return x, seen

    def output(self, x: np.ndarray, which: int) -> np.ndarray:
        """One of the linear outputs."""
        for w, b in zip(self.weights[:-1], self.shifts[:-1]):
            x = x @ w + b
            np.maximum(x, 0, out=x)
        return x @ self.weights[-1][:, which] + self.shifts[-1][which]

    def gradients(self, seen: list[np.ndarray], d: np.ndarray) -> list[np.ndarray]:
        """Of all parameters, from the loss's slope at the linear outputs."""
        gw, gb = [], []
        for k in range(len(self.weights) - 1, -1, -1):
            g = seen[k].T @ d
            gw.append(g if self.masks is None else g * self.masks[k])
            gb.append(d.sum(axis=0))
            if k:
                d = (d @ self.weights[k].T) * (seen[k] > 0)
        return [*reversed(gw), *reversed(gb)]


class Adam:
    """All parameters are stepped as one flat vector; each keeps its shape as a view of it."""

    def __init__(self, net: Net, rate: float) -> None:
        parts = net.parameters()
        self.flat = np.concatenate([p.ravel() for p in parts]).astype(np.float32)
        views, at = [], 0
        for p in parts:
            views.append(self.flat[at : at + p.size].reshape(p.shape))
            at += p.size
        net.weights, net.shifts = views[: len(net.weights)], views[len(net.weights) :]
        self.rate, self.t = rate, 0
        self.m, self.s = np.zeros_like(self.flat), np.zeros_like(self.flat)

    def step(self, gradients: list[np.ndarray], scale: float = 1.0) -> None:
        self.t += 1
        rate = np.float32(self.rate * scale * np.sqrt(1 - 0.999**self.t) / (1 - 0.9**self.t))
        g = np.concatenate([x.ravel() for x in gradients]).astype(np.float32, copy=False)
        self.m += np.float32(0.1) * (g - self.m)
        g *= g
        self.s += np.float32(0.001) * (g - self.s)
        self.flat -= rate * self.m / (np.sqrt(self.s) + np.float32(1e-8))


def train(net: Net, n: int, slope: Callable[[np.ndarray, np.ndarray], tuple[float, np.ndarray]], inputs: Callable[[np.ndarray], np.ndarray], epochs: int, batch: int, rate: float, seed: int, dropout: float = 0.0, before: Callable[[int], None] | None = None) -> list[float]:
    """Minibatch Adam with a falling rate. ``slope(rows, outputs)`` gives the batch's loss and its slope; returns losses by epoch."""
    draw = np.random.default_rng(seed)
    adam = Adam(net, rate)
    total, losses, done = max(1, epochs * -(-n // batch)), [], 0
    for _ in range(epochs):
        order, loss = draw.permutation(n), 0.0
        for lo in range(0, n, batch):
            rows = order[lo : lo + batch]
            if before is not None:
                before(done)
            out, seen = net.forward(inputs(rows), (dropout, draw) if dropout else None)
            one, d = slope(rows, out)
            adam.step(net.gradients(seen, d.astype(np.float32)), 1 - 0.9 * done / total)
            loss += one * len(rows)
            done += 1
        losses.append(loss / max(n, 1))
    net.weights, net.shifts = [w.copy() for w in net.weights], [b.copy() for b in net.shifts]
    return losses

"""Gradient-boosted trees for two classes, on binned features, in numpy."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass
class Boosted:
    """Logistic boosting of complete trees of one depth; a node that doesn't pay sends everything left."""

    trees: int = 50
    depth: int = 5
    rate: float = 0.25
    bins: int = 32
    ridge: float = 1.0
    edges: list[np.ndarray] = field(default_factory=list)
    base: float = 0.0
    features: np.ndarray | None = None
    cuts: np.ndarray | None = None
    leaves: np.ndarray | None = None

    def _binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], "right") for j, e in enumerate(self.edges)], axis=1).astype(np.int32)

    def fit(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        n, m = x.shape
        self.edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins + 1)[1:-1])) for j in range(m)]
        b = self._binned(x)
        flat = b + np.arange(m, dtype=np.int32) * self.bins
        share = y.mean()
        self.base = float(np.log(share / (1 - share)))
        f = np.full(n, self.base)
        inner = (1 << self.depth) - 1
        self.features, self.cuts, self.leaves = np.zeros((self.trees, inner), np.int32), np.full((self.trees, inner), self.bins, np.int32), np.zeros((self.trees, inner + 1))
        for t in range(self.trees):
            p = 1 / (1 + np.exp(-f))
            g, h = y - p, p * (1 - p)
            at = np.zeros(n, np.int64)
            for level in range(self.depth):
                k = 1 << level
                cell = (flat + (at * (m * self.bins))[:, None]).reshape(-1)
                size = k * m * self.bins
                sg = np.bincount(cell, np.repeat(g, m), size).reshape(k, m, self.bins).cumsum(axis=2)
                sh = np.bincount(cell, np.repeat(h, m), size).reshape(k, m, self.bins).cumsum(axis=2)
                ag, ah = sg[:, :1, -1:], sh[:, :1, -1:]
                gain = sg**2 / (sh + self.ridge) + (ag - sg) ** 2 / (ah - sh + self.ridge) - ag**2 / (ah + self.ridge)
                gain = gain.reshape(k, -1)
                best = gain.argmax(axis=1)
                pays = gain[np.arange(k), best] > 1e-6
                node = k - 1 + np.arange(k)
                self.features[t, node] = best // self.bins
                self.cuts[t, node] = np.where(pays, best % self.bins, self.bins)
                at = 2 * at + (b[np.arange(n), self.features[t, k - 1 + at]] > self.cuts[t, k - 1 + at])
            sg, sh = np.bincount(at, g, inner + 1), np.bincount(at, h, inner + 1)
            self.leaves[t] = self.rate * sg / (sh + self.ridge)
            f += self.leaves[t, at]
        return self

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        b = self._binned(x)
        rows, out = np.arange(len(b)), np.full(len(b), self.base)
        for t in range(self.trees):
            at = np.zeros(len(b), np.int64)
            for level in range(self.depth):
                node = (1 << level) - 1 + at
                at = 2 * at + (b[rows, self.features[t, node]] > self.cuts[t, node])
            out += self.leaves[t, at]
        return out

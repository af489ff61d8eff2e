"""Gradient boosted regression trees for a binary target, in numpy.

Features are cut at quantiles; each tree is grown level by level on the
logistic loss's gradients, and a held-out fold calibrates the summed scores.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass
class Boosted:
    cuts: list[np.ndarray] = field(default_factory=list)
    trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)
    base: float = 0.0
    slope: float = 1.0
    shift: float = 0.0

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(c, x[:, i], side="right") for i, c in enumerate(self.cuts)], axis=1) if len(self.cuts) else np.zeros((len(x), 0), int)

    def raw(self, bins: np.ndarray) -> np.ndarray:
        total = np.full(len(bins), self.base)
        every = np.arange(len(bins))
        for feature, cut, value in self.trees:
            node = np.zeros(len(bins), int)
            for _ in range(int(np.log2(len(value) + 1)) - 1):
                node = 2 * node + 1 + (bins[every, feature[node]] > cut[node])
            total += value[node]
        return total

    def probability(self, x: np.ndarray) -> np.ndarray:
        z = self.raw(self.bins(x)) * self.slope + self.shift
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 40, depth: int = 3, rate: float = 0.3, most_bins: int = 32) -> Boosted:
    """Boost on four fifths of the rows and calibrate (slope and shift) on the rest."""
    model = Boosted()
    model.cuts = [np.unique(np.quantile(x[:, i], np.linspace(0, 1, most_bins + 1)[1:-1])) for i in range(x.shape[1])]
    bins = model.bins(x)
    fold = np.arange(len(y)) % 5 == 4 if len(y) >= 50 else np.zeros(len(y), bool)
    train, target = bins[~fold], y[~fold].astype(float)
    share = np.clip(target.mean(), 1e-3, 1 - 1e-3)
    model.base = float(np.log(share / (1 - share)))
    total = np.full(len(target), model.base)
    width = most_bins + 1
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-total))
        grad, curve = target - p, p * (1 - p)
        nodes = (1 << (depth + 1)) - 1
        feature, cut, value = np.zeros(nodes, int), np.full(nodes, width), np.zeros(nodes)
        node = np.zeros(len(target), int)
        for level in range(depth):
            first, count = (1 << level) - 1, 1 << level
            best = np.full(count, 1e-6)
            for f in range(train.shape[1]):
                at = (node - first) * width + train[:, f]
                g, h = (np.bincount(at, v, count * width).reshape(count, width).cumsum(axis=1) for v in (grad, curve))
                gl, hl, gt, ht = g[:, :-1], h[:, :-1], g[:, -1:], h[:, -1:]
                gain = gl**2 / (hl + 1) + (gt - gl) ** 2 / (ht - hl + 1) - gt**2 / (ht + 1)
                top = gain.argmax(axis=1)
                good = gain[np.arange(count), top] > best
                best = np.where(good, gain[np.arange(count), top], best)
                feature[first : first + count] = np.where(good, f, feature[first : first + count])
                cut[first : first + count] = np.where(good, top, cut[first : first + count])
            node = 2 * node + 1 + (train[np.arange(len(train)), feature[node]] > cut[node])
        g, h = (np.bincount(node, v, nodes) for v in (grad, curve))
        value = rate * g / (h + 1)
        model.trees.append((feature, cut, value))
        total += value[node]
    held, seen = (bins[fold], y[fold]) if fold.any() and 0 < y[fold].sum() < fold.sum() else (bins, y)
    z, beta = model.raw(held), np.array([1.0, 0.0])
    design = np.stack((z, np.ones(len(z))), axis=1)
    for _ in range(25):
        p = 1 / (1 + np.exp(-np.clip(design @ beta, -30, 30)))
        hessian = (design * (p * (1 - p))[:, None]).T @ design + 0.1 * np.eye(2)
        beta += np.clip(np.linalg.solve(hessian, design.T @ (seen - p) - 0.1 * (beta - [1, 0])), -1, 1)
    model.slope, model.shift = float(beta[0]), float(beta[1])
    return model

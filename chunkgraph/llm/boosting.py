"""Gradient boosted regression trees on the logistic loss, over binned features; small and deterministic."""

from __future__ import annotations

import numpy as np


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


class BoostedTrees:
    """Complete trees of fixed depth; every level of a tree splits each of its nodes at the best histogram cut."""

    def __init__(self, rounds: int = 60, depth: int = 3, rate: float = 0.2, smooth: float = 1.0, bins: int = 32):
        self.rounds, self.depth, self.rate, self.smooth, self.bins = rounds, depth, rate, smooth, bins

    def fit(self, x: np.ndarray, y: np.ndarray) -> "BoostedTrees":
        x, y = np.asarray(x, float), np.asarray(y, float)
        self.cuts = [np.unique(np.quantile(column, np.linspace(0, 1, self.bins + 1)[1:-1])) for column in x.T]
        coded = np.stack([np.searchsorted(cut, column, side="left") for cut, column in zip(self.cuts, x.T)], 1)
        share = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.base = float(np.log(share / (1 - share)))
        self.trees, margin = [], np.full(len(y), self.base)
        for _ in range(self.rounds):
            p = sigmoid(margin)
            tree, leaf = self._grow(coded, y - p, p * (1 - p))
            self.trees.append(tree)
            margin += tree[2][leaf]
        return self

    def _grow(self, coded, slope, curve):
        inner = 2**self.depth - 1
        feature, cut = np.zeros(inner, int), np.full(inner, np.inf)
        at, width = np.zeros(len(coded), int), self.bins + 1
        for level in range(self.depth):
            first, count = 2**level - 1, 2**level
            best = np.full(count, 1e-9)
            chosen = np.zeros(count, int)
            where = np.full(count, width)
            for j in range(coded.shape[1]):
                key = (at - first) * width + coded[:, j]
                g = np.bincount(key, slope, count * width).reshape(count, width).cumsum(1)
                h = np.bincount(key, curve, count * width).reshape(count, width).cumsum(1)
                total_g, total_h = g[:, -1:], h[:, -1:]
                gain = g**2 / (h + self.smooth) + (total_g - g) ** 2 / (total_h - h + self.smooth) - total_g**2 / (total_h + self.smooth)
                top = gain.argmax(1)
                value = gain[np.arange(count), top]
                better = value > best
                best[better], chosen[better], where[better] = value[better], j, top[better]
            feature[first : first + count] = chosen
            for node in range(count):
                cuts = self.cuts[chosen[node]]
                cut[first + node] = cuts[where[node]] if where[node] < len(cuts) else np.inf
            local = at - first
            right = coded[np.arange(len(coded)), chosen[local]] > where[local]
            at = 2 * at + 1 + right
        leaf = at - inner
        g, h = np.bincount(leaf, slope, inner + 1), np.bincount(leaf, curve, inner + 1)
        return (feature, cut, self.rate * g / (h + self.smooth)), leaf

    def margin(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, float)
        rows, out = np.arange(len(x)), np.full(len(x), self.base)
        for feature, cut, value in self.trees:
            at = np.zeros(len(x), int)
            for _ in range(self.depth):
                at = 2 * at + 1 + (x[rows, feature[at]] > cut[at])
            out += value[at - len(cut)]
        return out


def isotonic(scores: np.ndarray, targets: np.ndarray, weights: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators; returns knots (score, value), both ascending, for np.interp."""
    scores, targets = np.asarray(scores, float), np.asarray(targets, float)
    weights = np.ones(len(scores)) if weights is None else np.asarray(weights, float)
    order = np.argsort(scores, kind="stable")
    blocks: list[list[float]] = []  # mean, weight, first score, last score
    for s, t, w in zip(scores[order], targets[order], weights[order]):
        blocks.append([t, w, s, s])
        while len(blocks) > 1 and (blocks[-2][0] >= blocks[-1][0] or blocks[-2][3] == blocks[-1][2]):
            t2, w2, _, last = blocks.pop()
            t1, w1, first, _ = blocks.pop()
            blocks.append([(t1 * w1 + t2 * w2) / (w1 + w2), w1 + w2, first, last])
    if not blocks:
        return np.array([0.0]), np.array([0.5])
    knots = [(s, b[0]) for b in blocks for s in ((b[2],) if b[2] == b[3] else (b[2], b[3]))]
    return np.array([k[0] for k in knots]), np.array([k[1] for k in knots])

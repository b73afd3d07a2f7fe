"""Gradient-boosted trees on binned features, and isotonic calibration.

Small models for bounded samples: fitting runs on the driver over one numpy
matrix, scoring is a few vectorised look-ups a tree and runs anywhere.
"""

from __future__ import annotations

import numpy as np


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(z, -40, 40)))


def bin_edges(X: np.ndarray, bins: int) -> list[np.ndarray]:
    """Per feature, cut points between distinct values, at most bins - 1 of them."""
    edges = []
    for column in X.T:
        values = np.unique(column)
        if len(values) > bins:
            values = np.unique(np.quantile(column, np.linspace(0, 1, bins), method="nearest"))
        edges.append((values[:-1] + values[1:]) / 2)
    return edges


def binned(X: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    return np.stack([np.searchsorted(e, column, side="right") for e, column in zip(edges, X.T)], axis=1)


class BoostedTrees:
    """Logistic-loss trees of fixed depth, grown on gradient histograms.

    An empty or one-class sample gives the constant smoothed base rate.
    """

    def __init__(self, rounds: int = 60, depth: int = 3, rate: float = 0.2, bins: int = 32, ridge: float = 1.0, least: float = 1.0):
        self.rounds, self.depth, self.rate, self.bins, self.ridge, self.least = rounds, depth, rate, bins, ridge, least
        self.trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.base = 0.0

    def fit(self, X: np.ndarray, y: np.ndarray) -> BoostedTrees:
        rate = (y.sum() + 0.5) / (len(y) + 1.0)
        self.base, self.trees = float(np.log(rate / (1 - rate))), []
        if len(y) == 0 or y.min() == y.max():
            return self
        edges = bin_edges(X, self.bins)
        B, margin = binned(X, edges), np.full(len(y), self.base)
        for _ in range(self.rounds):
            p = sigmoid(margin)
            tree, step = self._grow(B, edges, y - p, p * (1 - p))
            self.trees.append(tree)
            margin += step
        return self

    def _grow(self, B, edges, gradient, hessian):
        """One tree as a full heap: feature, threshold and value by node."""
        size = 2 ** (self.depth + 1)
        feature, threshold, value = np.full(size, -1), np.zeros(size), np.zeros(size)
        node = np.ones(len(B), dtype=int)
        gain_of = lambda g, h: g * g / (h + self.ridge)
        for level in range(self.depth):
            for at in range(2**level, 2 ** (level + 1)):
                rows = np.flatnonzero(node == at)
                if len(rows) < 2:
                    continue
                g, h = gradient[rows], hessian[rows]
                best = (1e-6, -1, 0)
                for f, cuts in enumerate(edges):
                    if not len(cuts):
                        continue
                    left_g = np.cumsum(np.bincount(B[rows, f], g, len(cuts) + 1))[:-1]
                    left_h = np.cumsum(np.bincount(B[rows, f], h, len(cuts) + 1))[:-1]
                    total_g, total_h = g.sum(), h.sum()
                    gain = gain_of(left_g, left_h) + gain_of(total_g - left_g, total_h - left_h) - gain_of(total_g, total_h)
                    gain[(left_h < self.least) | (total_h - left_h < self.least)] = -1
                    k = int(gain.argmax())
                    if gain[k] > best[0]:
                        best = (gain[k], f, k)
                if best[1] >= 0:
                    feature[at], threshold[at] = best[1], edges[best[1]][best[2]]
                    node[rows] = 2 * at + (B[rows, best[1]] > best[2])
        for at in np.unique(node):
            rows = node == at
            value[at] = self.rate * gradient[rows].sum() / (hessian[rows].sum() + self.ridge)
        return (feature, threshold, value), value[node]

    def predict(self, X: np.ndarray) -> np.ndarray:
        """Probabilities of label 1."""
        margin = np.full(len(X), self.base)
        for feature, threshold, value in self.trees:
            node = np.ones(len(X), dtype=int)
            for _ in range(self.depth):
                f = feature[node]
                inner = f >= 0
                goes = X[np.arange(len(X)), np.maximum(f, 0)] >= threshold[node]
                node = np.where(inner, 2 * node + goes, node)
            margin += value[node]
        return sigmoid(margin)


class Isotonic:
    """Non-decreasing map from raw to calibrated probability, by pooling adjacent violators.

    Blocks keep their mean with a half row of each label added, and values between blocks are
    interpolated, so that a pure block stays short of 0 and 1.
    """

    def __init__(self):
        self.x, self.y = np.array([0.0, 1.0]), np.array([0.0, 1.0])

    def fit(self, score: np.ndarray, y: np.ndarray) -> Isotonic:
        if len(y) == 0:
            return self
        order = np.argsort(score, kind="stable")
        blocks: list[list[float]] = []  # sum of labels, rows, lowest and highest score
        for s, label in zip(score[order], y[order]):
            if blocks and blocks[-1][3] == s:
                blocks[-1][0] += label
                blocks[-1][1] += 1
            else:
                blocks.append([float(label), 1.0, float(s), float(s)])
            while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
                top = blocks.pop()
                blocks[-1] = [blocks[-1][0] + top[0], blocks[-1][1] + top[1], blocks[-1][2], top[3]]
        smooth = np.maximum.accumulate([(b[0] + 0.5) / (b[1] + 1.0) if b[0] in (0, b[1]) else b[0] / b[1] for b in blocks])
        self.x = np.array([v for b in blocks for v in (b[2], b[3])])
        self.y = np.repeat(smooth, 2)
        return self

    def predict(self, score: np.ndarray) -> np.ndarray:
        return np.interp(score, self.x, self.y)


def out_of_fold(X: np.ndarray, y: np.ndarray, folds: int = 3, **options) -> np.ndarray:
    """Each row's prediction by a model that has not seen it (folds by row number)."""
    scores, fold = np.zeros(len(y)), np.arange(len(y)) % folds
    for k in range(folds):
        if (fold == k).any():
            scores[fold == k] = BoostedTrees(**options).fit(X[fold != k], y[fold != k]).predict(X[fold == k])
    return scores

"""Gradient-boosted trees over dense features, and isotonic calibration, in numpy."""

from __future__ import annotations

import numpy as np


class BoostedTrees:
    """Logistic loss, histogram splits on quantile bins, trees of a fixed depth stored as arrays."""

    def __init__(self, trees: int = 80, depth: int = 3, rate: float = 0.15, bins: int = 32, least: int = 10, l2: float = 1.0):
        self.trees, self.depth, self.rate, self.bins, self.least, self.l2 = trees, depth, rate, bins, least, l2

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        n, width = x.shape
        cuts = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, self.bins + 1)[1:-1])) for k in range(width)]
        # Rare features have one quantile value at zero; a cut just above it and the mean of the rest keep them usable.
        for k in range(width):
            rest = x[x[:, k] > cuts[k][-1], k]
            if len(rest):
                cuts[k] = np.unique(np.concatenate((cuts[k], np.quantile(rest, [0.25, 0.5, 0.75]))))
        code = np.stack([np.searchsorted(c, x[:, k], side="left") for k, c in enumerate(cuts)])
        most = max(len(c) for c in cuts) + 1
        mean = np.clip(y.mean(), 1e-4, 1 - 1e-4)
        self.base = float(np.log(mean / (1 - mean)))
        score = np.full(n, self.base)
        self.feature, self.cut, self.leaf = [], [], []
        for _ in range(self.trees):
            p = 1 / (1 + np.exp(-score))
            g, h = p - y, p * (1 - p)
            node = np.zeros(n, np.int64)
            feature = np.zeros(2**self.depth - 1, np.int64)
            cut = np.full(2**self.depth - 1, np.inf)
            for level in range(self.depth):
                first, count = 2**level - 1, 2**level
                best = np.full(count, 1e-6)
                for k in range(width):
                    slot = node * most + code[k]
                    shape = (count, most)
                    gs = np.bincount(slot, g, count * most).reshape(shape).cumsum(1)
                    hs = np.bincount(slot, h, count * most).reshape(shape).cumsum(1)
                    ns = np.bincount(slot, minlength=count * most).reshape(shape).cumsum(1)
                    total_g, total_h, total_n = gs[:, -1:], hs[:, -1:], ns[:, -1:]
                    gain = gs**2 / (hs + self.l2) + (total_g - gs) ** 2 / (total_h - hs + self.l2) - total_g**2 / (total_h + self.l2)
                    gain[(ns < self.least) | (total_n - ns < self.least)] = -1
                    gain = gain[:, : len(cuts[k])]
                    at = gain.argmax(1)
                    value = gain[np.arange(count), at]
                    for j in np.flatnonzero(value > best):
                        best[j], feature[first + j], cut[first + j] = value[j], k, cuts[k][at[j]]
                node = node * 2 + (x[np.arange(n), feature[first + node]] > cut[first + node])
            gs, hs = np.bincount(node, g, 2**self.depth), np.bincount(node, h, 2**self.depth)
            leaf = -self.rate * gs / (hs + self.l2)
            score += leaf[node]
            self.feature.append(feature)
            self.cut.append(cut)
            self.leaf.append(leaf)
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        score = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for feature, cut, leaf in zip(self.feature, self.cut, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for level in range(self.depth):
                at = 2**level - 1 + node
                node = node * 2 + (x[rows, feature[at]] > cut[at])
            score += leaf[node]
        return score


def isotonic(score: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots (score, probability) of the non-decreasing least-squares fit, by pooling adjacent violators."""
    order = np.argsort(score, kind="stable")
    blocks: list[list[float]] = []
    for s, v in zip(score[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([v, 1.0, s, s])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            b, a = blocks.pop(), blocks.pop()
            w = a[1] + b[1]
            blocks.append([(a[0] * a[1] + b[0] * b[1]) / w, w, a[2], b[3]])
    at, value = [], []
    for v, _, low, high in blocks:
        at += [low, high] if high > low else [low]
        value += [v, v] if high > low else [v]
    return np.array(at), np.array(value)


def calibrated(margin: np.ndarray, knots: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The isotonic probability, with a hundredth of the plain logistic one so that order within a flat part is kept."""
    plain = 1 / (1 + np.exp(-margin))
    return np.clip(0.99 * np.interp(margin, *knots) + 0.01 * plain, 0.0, 1.0) if len(knots[0]) else plain

"""Histogram gradient boosting for log loss on a small dense matrix, and isotonic calibration; numpy alone."""

from __future__ import annotations

import numpy as np


class Trees:
    """Boosted trees of fixed depth over binned features; each level of a tree is one array."""

    def __init__(self, edges: list[np.ndarray], base: float, trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]], depth: int):
        self.edges, self.base, self.trees, self.depth = edges, base, trees, depth

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(self.edges)], axis=1).astype(np.int16)

    def margin(self, x: np.ndarray) -> np.ndarray:
        b, out, rows = self.bins(x), np.full(len(x), self.base), np.arange(len(x))
        for feature, cut, leaf in self.trees:
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + (b[rows, feature[node]] > cut[node])
            out += leaf[node - len(feature)]
        return out


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 80, depth: int = 3, rate: float = 0.15, most_bins: int = 64, least: float = 1.0, ridge: float = 1.0) -> Trees:
    """``y`` in {0, 1}. Splits maximise the second-order gain; ties go to the first feature and lowest bin."""
    n, m = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, most_bins + 1)[1:-1])) if n else np.zeros(0) for j in range(m)]
    p = (y.sum() + 0.5) / (n + 1)
    model = Trees(edges, float(np.log(p / (1 - p))), [], depth)
    if n == 0 or y.min() == y.max():
        return model
    b, f = model.bins(x).astype(np.int64), np.full(n, model.base)
    width, inner = most_bins + 1, 2**depth - 1
    for _ in range(rounds):
        q = 1 / (1 + np.exp(-f))
        g, h = q - y, np.maximum(q * (1 - q), 1e-9)
        feature, cut = np.zeros(inner, np.int64), np.full(inner, width, np.int64)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            first, wide = 2**level - 1, 2**level
            local = node - first
            best = np.full(wide, 1e-6)
            for j in range(m):
                at = local * width + b[:, j]
                gs = np.bincount(at, g, wide * width).reshape(wide, width).cumsum(1)
                hs = np.bincount(at, h, wide * width).reshape(wide, width).cumsum(1)
                gt, ht = gs[:, -1:], hs[:, -1:]
                gain = gs**2 / (hs + ridge) + (gt - gs) ** 2 / (ht - hs + ridge) - gt**2 / (ht + ridge)
                gain[(hs < least) | (ht - hs < least)] = -1
                top = gain.argmax(1)
                value = gain[np.arange(wide), top]
                won = value > best + 1e-12
                best[won] = value[won]
                feature[first + np.flatnonzero(won)], cut[first + np.flatnonzero(won)] = j, top[won]
            node = 2 * node + 1 + (b[np.arange(n), feature[node]] > cut[node])
        gs, hs = np.bincount(node - inner, g, inner + 1), np.bincount(node - inner, h, inner + 1)
        leaf = -rate * gs / (hs + ridge)
        f += leaf[node - inner]
        model.trees.append((feature, cut, leaf))
    return model


def isotonic(margin: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators: knots (margin, share) of the non-decreasing fit; equal margins pool first."""
    at, inverse = np.unique(margin, return_inverse=True)
    weight, total = np.bincount(inverse).astype(float), np.bincount(inverse, y)
    blocks: list[list[float]] = []
    for k in range(len(at)):
        blocks.append([at[k], at[k], total[k], weight[k]])
        while len(blocks) > 1 and blocks[-2][2] * blocks[-1][3] >= blocks[-1][2] * blocks[-2][3]:
            last = blocks.pop()
            blocks[-1] = [blocks[-1][0], last[1], blocks[-1][2] + last[2], blocks[-1][3] + last[3]]
    xs = np.array([v for lo, hi, _, _ in blocks for v in (lo, hi)])
    ys = np.array([t / w for _, _, t, w in blocks for _ in (0, 1)])
    return xs, ys


def calibrated(margin: np.ndarray, knots: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Isotonic share with a thousandth of the logistic score, which keeps the order inside a flat stretch."""
    raw = 1 / (1 + np.exp(-np.clip(margin, -30, 30)))
    return raw if not len(knots[0]) else 0.999 * np.interp(margin, *knots) + 0.001 * raw

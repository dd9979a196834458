"""Small, exact learners in numpy: boosted trees, lasso logistic regression, isotonic fit.

All are fitted on the driver from a bounded sample of rows of a few dense statistics.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from .common import ship


@dataclass
class Tree:
    """Nodes in arrays; a row goes left when its feature is at most the threshold."""

    feature: list[int] = field(default_factory=list)
    threshold: list[float] = field(default_factory=list)
    left: list[int] = field(default_factory=list)
    right: list[int] = field(default_factory=list)
    value: list[float] = field(default_factory=list)

    def add(self, value: float) -> int:
        for column, x in ((self.feature, -1), (self.threshold, 0.0), (self.left, -1), (self.right, -1), (self.value, value)):
            column.append(x)
        return len(self.value) - 1

    def predict(self, x: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), np.int64)
        feature, threshold, left, right = map(np.array, (self.feature, self.threshold, self.left, self.right))
        while (inner := np.flatnonzero(feature[at] >= 0)).size:
            node = at[inner]
            at[inner] = np.where(x[inner, feature[node]] <= threshold[node], left[node], right[node])
        return np.array(self.value)[at]

    def paths(self) -> list[tuple[tuple[int, bool, float], ...]]:
        """The conditions (feature, at most?, threshold) that lead to each node but the root."""
        found, todo = [], [(0, ())]
        while todo:
            node, path = todo.pop()
            if path:
                found.append(path)
            if self.feature[node] >= 0:
                cut = self.feature[node], self.threshold[node]
                todo.append((self.left[node], (*path, (cut[0], True, cut[1]))))
                todo.append((self.right[node], (*path, (cut[0], False, cut[1]))))
        return found


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 60, depth: int = 3, rate: float = 0.15, bins: int = 64, share: float = 0.7, least: float = 1.0, seed: int = 1) -> tuple[float, list[Tree]]:
    """Newton-boosted trees for the logistic loss: (base log odds, trees)."""
    rng = np.random.default_rng(seed)
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    codes = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T, strict=True)], axis=1)
    mean = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    base = float(np.log(mean / (1 - mean)))
    score, trees = np.full(len(y), base), []
    for _ in range(rounds):
        p = sigmoid(score)
        g, h = p - y, np.maximum(p * (1 - p), 1e-6)
        rows = np.flatnonzero(rng.random(len(y)) < share) if len(y) > 50 else np.arange(len(y))
        tree = Tree()
        todo = [(tree.add(0.0), rows, 0)]
        while todo:
            node, own, level = todo.pop()
            total_g, total_h = g[own].sum(), h[own].sum()
            tree.value[node] = float(-rate * total_g / (total_h + 1))
            if level == depth or len(own) < 8:
                continue
            best = (1e-6, None, None)
            for f, e in enumerate(edges):
                if not len(e):
                    continue
                sum_g = np.cumsum(np.bincount(codes[own, f], g[own], len(e) + 1))[:-1]
                sum_h = np.cumsum(np.bincount(codes[own, f], h[own], len(e) + 1))[:-1]
                gain = sum_g**2 / (sum_h + 1) + (total_g - sum_g) ** 2 / (total_h - sum_h + 1) - total_g**2 / (total_h + 1)
                gain[(sum_h < least) | (total_h - sum_h < least)] = 0
                k = int(gain.argmax())
                if gain[k] > best[0]:
                    best = (gain[k], f, k)
            if best[1] is None:
                continue
            _, f, k = best
            low = codes[own, f] <= k
            tree.feature[node], tree.threshold[node] = f, float(edges[f][k])
            tree.left[node], tree.right[node] = tree.add(0.0), tree.add(0.0)
            todo += [(tree.left[node], own[low], level + 1), (tree.right[node], own[~low], level + 1)]
        score = score + tree.predict(x)
        trees.append(tree)
    return base, trees


def margin(base: float, trees: list[Tree], x: np.ndarray) -> np.ndarray:
    return base + sum((t.predict(x) for t in trees), np.zeros(len(x)))


def lasso_logistic(r: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 300) -> tuple[float, np.ndarray]:
    """(intercept, weights) of l1-penalised logistic regression by accelerated proximal steps."""
    n = len(y)
    aug = np.concatenate([np.ones((n, 1)), r], axis=1)
    v = np.ones(aug.shape[1])
    for _ in range(20):
        v = aug.T @ (aug @ v)
        v /= np.linalg.norm(v) or 1
    step = 4 * n / max(float(np.linalg.norm(aug @ v) ** 2), 1e-9) / 1.05
    w = look = np.zeros(aug.shape[1])
    t = 1.0
    for _ in range(rounds):
        slope = aug.T @ (sigmoid(aug @ look) - y) / n
        new = look - step * slope
        new[1:] = np.sign(new[1:]) * np.maximum(np.abs(new[1:]) - step * penalty, 0)
        t, before = (1 + (1 + 4 * t * t) ** 0.5) / 2, t
        look = new + (before - 1) / t * (new - w)
        w = new
    return float(w[0]), w[1:]


def isotonic(z: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots (z, probability) of the non-decreasing least-squares fit, by pooling violators."""
    order = np.argsort(z, kind="stable")
    blocks: list[list[float]] = []  # sum of y, count, first z, last z
    for x, t in zip(z[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([t, 1, x, x])
        while len(blocks) > 1 and (blocks[-2][3] == blocks[-1][2] or blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]):
            s, c, _, last = blocks.pop()
            blocks[-1][0] += s
            blocks[-1][1] += c
            blocks[-1][3] = last
    knots = [(at, s / c) for s, c, first, last in blocks for at in sorted({first, last})]
    return np.array([k[0] for k in knots]), np.array([k[1] for k in knots])


ship(__name__)

"""Gradient-boosted trees that are fitted on a bounded sample on the driver and compiled into one SQL expression."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass
class Node:
    value: float = 0.0
    feature: int = -1
    threshold: float = 0.0
    low: Node | None = None
    high: Node | None = None


def _grow(x: np.ndarray, grad: np.ndarray, hess: np.ndarray, depth: int, l2: float) -> Node:
    node = Node(value=float(grad.sum() / (hess.sum() + l2)))
    if depth == 0 or len(x) < 8:
        return node
    best, parent = 1e-6, grad.sum() ** 2 / (hess.sum() + l2)
    for f in range(x.shape[1]):
        levels = np.unique(x[:, f])
        for cut in (levels[:-1] + levels[1:]) / 2 if len(levels) <= 32 else np.quantile(x[:, f], np.linspace(0.03, 0.97, 32)):
            left = x[:, f] <= cut
            if 3 <= left.sum() <= len(x) - 3:
                gain = grad[left].sum() ** 2 / (hess[left].sum() + l2) + grad[~left].sum() ** 2 / (hess[~left].sum() + l2) - parent
                if gain > best:
                    best, node.feature, node.threshold = gain, f, float(cut)
    if node.feature >= 0:
        left = x[:, node.feature] <= node.threshold
        node.low, node.high = _grow(x[left], grad[left], hess[left], depth - 1, l2), _grow(x[~left], grad[~left], hess[~left], depth - 1, l2)
    return node


def _walk(node: Node, x: np.ndarray) -> np.ndarray:
    if node.low is None:
        return np.full(len(x), node.value)
    return np.where(x[:, node.feature] <= node.threshold, _walk(node.low, x), _walk(node.high, x))


@dataclass
class Boosted:
    """Logistic boosting. platt: slope and intercept fitted on the held-out part. threshold: on the calibrated probability."""

    base: float
    rate: float
    trees: list[Node]
    platt: tuple[float, float] = (1.0, 0.0)
    threshold: float = 0.5

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.base + self.rate * sum((_walk(t, x) for t in self.trees), np.zeros(len(x)))

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.platt[0] * self.margin(x) + self.platt[1])))

    def column(self, features: list[Column]) -> Column:
        """The calibrated probability as a SQL expression over the features."""

        def tree(node: Node) -> Column:
            if node.low is None:
                return F.lit(node.value)
            return F.when(features[node.feature] <= F.lit(node.threshold), tree(node.low)).otherwise(tree(node.high))

        total = F.lit(self.base)
        for t in self.trees:
            total = total + F.lit(self.rate) * tree(t)
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-(F.lit(self.platt[0]) * total + F.lit(self.platt[1]))))


def fit(x: np.ndarray, y: np.ndarray, held: np.ndarray, trees: int = 16, depth: int = 3, rate: float = 0.3, l2: float = 1.0, precision: float = 0.99) -> Boosted:
    """Fit on the rows that aren't held out, calibrate on those that are, and take the smallest threshold that has the precision there."""
    fx, fy = x[~held], y[~held]
    rate0 = min(max(fy.mean(), 1e-3), 1 - 1e-3)
    model = Boosted(float(np.log(rate0 / (1 - rate0))), rate, [])
    margin = np.full(len(fx), model.base)
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        t = _grow(fx, fy - p, p * (1 - p), depth, l2)
        model.trees.append(t)
        margin += rate * _walk(t, fx)
    m, hy = model.margin(x[held]), y[held]
    a, b = 1.0, 0.0
    for _ in range(50):  # Newton steps of a logistic regression in one variable, with a small prior on the slope
        p = 1 / (1 + np.exp(-(a * m + b)))
        w = p * (1 - p) + 1e-9
        g = np.array([((hy - p) * m).sum() - 0.01 * (a - 1), (hy - p).sum()])
        h = np.array([[(w * m * m).sum() + 0.01, (w * m).sum()], [(w * m).sum(), w.sum() + 1e-6]])
        step = np.clip(np.linalg.solve(h, g), -1, 1)
        a, b = a + step[0], b + step[1]
    model.platt = (float(a), float(b))
    p = model.probability(x[held])
    safe = 1.0
    for cut in np.unique(np.round(p, 4))[::-1]:
        if hy[p >= cut - 1e-4].mean() < precision:
            model.threshold = max(0.5, float(safe + cut) / 2)  # half-way to the first that is not precise enough
            break
        safe = cut
    return model

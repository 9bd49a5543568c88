"""Gradient-boosted regression trees for the logistic loss: small, seeded, on numpy; scored as SQL expressions."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

import numpy as np


@dataclass
class Leaf:
    value: float


@dataclass
class Split:
    feature: int
    cut: float
    low: Any
    high: Any


@dataclass
class Boosted:
    base: float = 0.0
    trees: list[Any] = field(default_factory=list)
    slope: float = 1.0
    offset: float = 0.0

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.base + sum((_walk(t, x) for t in self.trees), np.zeros(len(x)))

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.slope * self.margin(x) + self.offset)))

    def expression(self, column: Callable[[int], Any], when: Callable[[Any, Any, Any], Any], lit: Callable[[float], Any]) -> Any:
        """The margin, built with the caller's notion of a column, a conditional and a literal."""

        def tree(t: Any) -> Any:
            return lit(t.value) if isinstance(t, Leaf) else when(column(t.feature) <= t.cut, tree(t.low), tree(t.high))

        out = lit(self.base)
        for t in self.trees:
            out = out + tree(t)
        return out

    def margin_for(self, probability: float) -> float:
        """The margin at which the calibrated probability is reached."""
        return (float(np.log(probability / (1 - probability))) - self.offset) / self.slope


def _walk(t: Any, x: np.ndarray) -> np.ndarray:
    if isinstance(t, Leaf):
        return np.full(len(x), t.value)
    return np.where(x[:, t.feature] <= t.cut, _walk(t.low, x), _walk(t.high, x))


def _grow(x: np.ndarray, g: np.ndarray, h: np.ndarray, depth: int, least: int, ridge: float, rate: float) -> Any:
    best = (1e-6, None)
    total_g, total_h = g.sum(), h.sum()
    if depth and len(g) >= 2 * least:
        for j in range(x.shape[1]):
            order = np.argsort(x[:, j], kind="stable")
            v, cg, ch = x[order, j], np.cumsum(g[order]), np.cumsum(h[order])
            at = np.flatnonzero(v[1:] > v[:-1])
            at = at[(at + 1 >= least) & (len(g) - at - 1 >= least)]
            if len(at):
                gain = cg[at] ** 2 / (ch[at] + ridge) + (total_g - cg[at]) ** 2 / (total_h - ch[at] + ridge) - total_g**2 / (total_h + ridge)
                k = int(np.argmax(gain))
                if gain[k] > best[0]:
                    best = (float(gain[k]), (j, float((v[at[k]] + v[at[k] + 1]) / 2)))
    if best[1] is None:
        return Leaf(float(rate * total_g / (total_h + ridge)))
    j, cut = best[1]
    low = x[:, j] <= cut
    return Split(j, cut, _grow(x[low], g[low], h[low], depth - 1, least, ridge, rate), _grow(x[~low], g[~low], h[~low], depth - 1, least, ridge, rate))


def boost(x: np.ndarray, y: np.ndarray, n_trees: int = 30, depth: int = 3, rate: float = 0.3, least: int = 10, ridge: float = 1.0) -> Boosted:
    """Newton boosting; the last fifth of the rows calibrates the margins to probabilities."""
    cut = len(y) * 4 // 5
    a, b, c, d = x[:cut], y[:cut], x[cut:], y[cut:]
    p0 = float(np.clip(b.mean(), 1e-3, 1 - 1e-3))
    out = Boosted(base=float(np.log(p0 / (1 - p0))))
    m = np.full(len(b), out.base)
    for _ in range(n_trees):
        p = 1 / (1 + np.exp(-m))
        tree = _grow(a, b - p, p * (1 - p), depth, least, ridge, rate)
        out.trees.append(tree)
        m = m + _walk(tree, a)
    r, s, o = out.margin(c), 1.0, 0.0
    for _ in range(100):  # logistic calibration with a weak prior at slope 1
        p = 1 / (1 + np.exp(-(s * r + o)))
        v = p * (1 - p) + 1e-6
        g = np.array([((d - p) * r).sum() + (1 - s), (d - p).sum() - 0.1 * o])
        hess = np.array([[(v * r * r).sum() + 1, (v * r).sum()], [(v * r).sum(), v.sum() + 0.1]])
        step = np.clip(np.linalg.solve(hess, g), -0.5, 0.5)
        s, o = s + float(step[0]), o + float(step[1])
        if np.abs(step).max() < 1e-9:
            break
    out.slope, out.offset = max(s, 1e-3), o
    return out

"""Small decision-tree ensembles: fitted on a bounded labelled sample on the driver, applied as SQL expressions.

``fit_forest`` bags trees over random feature subsets; ``fit_boosted`` adds shallow trees on the logistic loss. Both yield plain tuples that
``forest_score`` and ``boosted_score`` turn into nested CASE expressions, so scoring is JVM code without Python.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: A leaf is a float; an inner node is (feature index, threshold, left, right): left if value <= threshold.
Tree = float | tuple


def _grow(x: np.ndarray, target: np.ndarray, weight: np.ndarray, depth: int, least: int, pick, leaf) -> Tree:
    if depth == 0 or len(x) < 2 * least or np.ptp(target / weight) == 0:
        return leaf(target, weight)
    best = None
    for f in pick(x.shape[1]):
        order = np.argsort(x[:, f], kind="stable")
        v, t, w = x[order, f], target[order], weight[order]
        st, sw = np.cumsum(t), np.cumsum(w)
        cut = np.flatnonzero(v[1:] > v[:-1])
        cut = cut[(cut + 1 >= least) & (len(v) - cut - 1 >= least)]
        if not len(cut):
            continue
        gain = st[cut] ** 2 / (sw[cut] + 1e-9) + (st[-1] - st[cut]) ** 2 / (sw[-1] - sw[cut] + 1e-9) - st[-1] ** 2 / (sw[-1] + 1e-9)
        k = int(np.argmax(gain))
        if gain[k] > 1e-9 and (best is None or gain[k] > best[0]):
            best = float(gain[k]), int(f), float((v[cut[k]] + v[cut[k] + 1]) / 2)
    if best is None:
        return leaf(target, weight)
    _, f, at = best
    low = x[:, f] <= at
    return (f, at, _grow(x[low], target[low], weight[low], depth - 1, least, pick, leaf), _grow(x[~low], target[~low], weight[~low], depth - 1, least, pick, leaf))


def fit_forest(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, *, trees: int = 15, depth: int = 5, least: int = 4, seed: int = 1) -> list[Tree]:
    """Bagged trees; a leaf is the share of its rows' weight that is labelled 1."""
    random, out = np.random.default_rng(seed), []
    weight = np.ones(len(x)) if weight is None else weight
    for _ in range(trees):
        rows = random.integers(0, len(x), len(x))
        pick = lambda n: random.choice(n, max(1, round(n**0.5)), replace=False)
        w = weight[rows]
        out.append(_grow(x[rows], y[rows] * w, w, depth, least, pick, lambda t, w: round(float(t.sum() / w.sum()), 6)))
    return out


def fit_boosted(x: np.ndarray, y: np.ndarray, *, rounds: int = 20, depth: int = 3, rate: float = 0.3, least: int = 5) -> tuple[float, list[Tree]]:
    share = min(max(float(np.mean(y)), 1e-3), 1 - 1e-3)
    start = float(np.log(share / (1 - share)))
    score, out = np.full(len(x), start), []
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-score))
        tree = _grow(x, y - p, np.maximum(p * (1 - p), 1e-6), depth, least, range, lambda t, w: round(float(rate * t.sum() / (w.sum() + 1.0)), 6))
        score += predict(tree, x)
        out.append(tree)
    return start, out


def predict(tree: Tree, x: np.ndarray) -> np.ndarray:
    if not isinstance(tree, tuple):
        return np.full(len(x), tree)
    f, at, left, right = tree
    return np.where(x[:, f] <= at, predict(left, x), predict(right, x))


def _case(tree: Tree, names: Sequence[str]) -> str:
    if not isinstance(tree, tuple):
        return f"{tree!r}D"
    f, at, left, right = tree
    return f"IF({names[f]} <= {at!r}D, {_case(left, names)}, {_case(right, names)})"


def forest_score(forest: list[Tree], names: Sequence[str]) -> Column:
    """Mean vote of the trees, 0 to 1."""
    return F.expr(f"({' + '.join(_case(t, names) for t in forest)}) / {float(len(forest))}")


def boosted_score(model: tuple[float, list[Tree]], names: Sequence[str]) -> Column:
    """Probability, 0 to 1."""
    return F.expr(f"1 / (1 + exp(-({model[0]!r}D + {' + '.join(_case(t, names) for t in model[1])})))")


def calibrated_threshold(score: np.ndarray, y: np.ndarray, precision: float, weight: np.ndarray | None = None) -> float:
    """The lowest threshold from which on at least such a share of the labelled candidates (by weight) is right; above 1 if there is none."""
    order = np.argsort(-score, kind="stable")
    weight = np.ones(len(y)) if weight is None else weight
    right = np.cumsum((y * weight)[order]) / np.cumsum(weight[order])
    last = np.flatnonzero(np.append(np.diff(score[order]) != 0, True) & (right >= precision))
    return float(score[order][last[-1]]) if len(last) else 1.1

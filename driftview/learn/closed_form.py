"""Least squares, ridge and weighted least squares, and leave-one-out errors."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.learn.model import Model, sign


def gram(df: DataFrame, features: list[str], label: str, weight: str | None = None) -> tuple[np.ndarray, np.ndarray, float]:
    """Weighted X'X, X'y and the sum of weights, the last column of X being 1: one aggregation, no row leaves the executors."""
    x = [F.col(c).cast("double") for c in features] + [F.lit(1.0)]
    k = F.col(weight).cast("double") if weight else F.lit(1.0)
    d = len(x)
    upper = [(i, j) for i in range(d) for j in range(i, d)]
    row = df.agg(*[F.sum(k * x[i] * x[j]).alias(f"g{i}_{j}") for i, j in upper], *[F.sum(k * x[i] * F.col(label)).alias(f"y{i}") for i in range(d)]).first()
    g, y = np.zeros((d, d)), np.zeros(d)
    for i, j in upper:
        g[i, j] = g[j, i] = row[f"g{i}_{j}"] or 0.0
    for i in range(d):
        y[i] = row[f"y{i}"] or 0.0
    return g, y, g[-1, -1]


def normal_equations(df: DataFrame, features: list[str], label: str, l2: float = 0.0, weight: str | None = None) -> Model:
    """The bias is the last coefficient with its sign turned, and is not penalized."""
    g, y, _ = gram(df, features, label, weight)
    return solve(g, y, l2)


def solve(g: np.ndarray, y: np.ndarray, l2: float = 0.0) -> Model:
    ridge = np.eye(len(g)) * l2
    ridge[-1, -1] = 0.0
    try:
        beta = np.linalg.solve(g + ridge, y)
    except np.linalg.LinAlgError:
        beta = np.linalg.lstsq(g + ridge, y, rcond=None)[0]
    return Model(beta[:-1], -float(beta[-1]))


def press(x: np.ndarray, y: np.ndarray, l2: float = 0.0) -> np.ndarray:
    """Scores of each example under the model trained without it, from one fit and the hat matrix's diagonal."""
    a = np.column_stack([x, np.ones(len(x))])
    ridge = np.eye(a.shape[1]) * l2
    ridge[-1, -1] = 0.0
    inverse = np.linalg.pinv(a.T @ a + ridge)
    hat = np.einsum("ij,jk,ik->i", a, inverse, a)
    residual = y - a @ (inverse @ (a.T @ y))
    return y - residual / np.maximum(1e-12, 1.0 - hat)


def press_rows(df: DataFrame, features: list[str], label: str, l2: float = 0.0) -> DataFrame:
    """``df`` with ``score``, each row's score under the model trained without it: one pass for the sums, one for the rows.

    The model without a row follows from the one with it and the row's leverage,
    a'(A'A + l2)^-1 a, so nothing is trained again and no row leaves the executors.
    """
    g, y, _ = gram(df, features, label)
    ridge = np.eye(len(g)) * l2
    ridge[-1, -1] = 0.0
    inverse = np.linalg.pinv(g + ridge)
    beta = inverse @ y
    a = [F.col(c).cast("double") for c in features] + [F.lit(1.0)]
    leverage, fitted = F.lit(0.0), F.lit(0.0)
    for i, x in enumerate(a):
        fitted = fitted + F.lit(float(beta[i])) * x
        for j, z in enumerate(a):
            leverage = leverage + F.lit(float(inverse[i, j])) * x * z
    score = F.col(label) - (F.col(label) - fitted) / F.greatest(F.lit(1e-12), 1.0 - leverage)
    return df.withColumn("score", score)


def loo_press(x: np.ndarray, y: np.ndarray, l2: float = 0.0) -> float:
    return float(np.mean([sign(s) != t for s, t in zip(press(x, y, l2), y, strict=True)]))


def loo_bruteforce(train: Callable[[np.ndarray, np.ndarray], Model], x: np.ndarray, y: np.ndarray) -> float:
    """Share of examples that a model trained without them gets wrong."""
    wrong = 0
    for k in range(len(x)):
        rest = np.arange(len(x)) != k
        wrong += sign(train(x[rest], y[rest]).score(x[k])) != y[k]
    return wrong / max(1, len(x))


def dual_hinge(x: np.ndarray, y: np.ndarray, c: float = 1.0, passes: int = 200) -> tuple[np.ndarray, np.ndarray]:
    """Dual weights of a linear support vector machine by coordinate ascent; the bias is a constant feature."""
    a = np.column_stack([x, np.ones(len(x))])
    q = (a * a).sum(1)
    alpha, w = np.zeros(len(a)), np.zeros(a.shape[1])
    for _ in range(passes):
        moved = 0.0
        for i in range(len(a)):
            slope = y[i] * (w @ a[i]) - 1.0
            new = min(c, max(0.0, alpha[i] - slope / max(q[i], 1e-12)))
            if new != alpha[i]:
                w += (new - alpha[i]) * y[i] * a[i]
                moved = max(moved, abs(new - alpha[i]))
                alpha[i] = new
        if moved < 1e-9:
            break
    return alpha, w


def loo_hinge_bound(x: np.ndarray, y: np.ndarray, c: float = 1.0) -> float:
    """An upper estimate of the leave-one-out error from one fit.

    An example counts if 2 * alpha * R^2 + slack reaches 1, with its dual weight
    alpha and slack, and R^2 the largest squared length of an example.
    """
    alpha, w = dual_hinge(x, y, c)
    a = np.column_stack([x, np.ones(len(x))])
    slack = np.maximum(0.0, 1.0 - y * (a @ w))
    radius = float((a * a).sum(1).max()) if len(a) else 0.0
    return float(np.mean(2 * alpha * radius + slack >= 1.0 - 1e-12)) if len(a) else 0.0

"""Exact optima to compare with: normal equations, Newton steps, conditional entropy, trivial predictors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def normal_sums(df: DataFrame, features: list[str], target: str) -> DataFrame:
    """One row of second moments (xx_i_j, xy_i) and n: one pass with partial sums, size independent of the rows."""
    pairs = [(i, j) for i in range(len(features)) for j in range(i, len(features))]
    sums = [F.sum(F.col(features[i]) * F.col(features[j])).alias(f"xx_{i}_{j}") for i, j in pairs]
    return df.agg(*sums, *[F.sum(F.col(f) * F.col(target)).alias(f"xy_{i}") for i, f in enumerate(features)], F.count("*").alias("n"))


def solve_normal(df: DataFrame, features: list[str], target: str) -> np.ndarray:
    row, k = normal_sums(df, features, target).first(), len(features)
    a = np.array([[row[f"xx_{min(i, j)}_{max(i, j)}"] for j in range(k)] for i in range(k)])
    return np.linalg.solve(a, np.array([row[f"xy_{i}"] for i in range(k)]))


def newton(x: np.ndarray, y: np.ndarray, l2: float, steps: int = 30) -> np.ndarray:
    """Optimum of the penalized logistic loss on rows that fit one machine."""
    theta = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 0.5 * (1 + np.tanh(x @ theta / 2))
        h = (x * (p * (1 - p))[:, None]).T @ x / len(y) + l2 * np.eye(len(theta))
        theta = theta - np.linalg.solve(h, x.T @ (p - y) / len(y) + l2 * theta)
    return theta


def conditional_entropy(counts: DataFrame, given: list[str], n: str = "n") -> DataFrame:
    """nll: the least mean negative log likelihood (nats) that any table of (next | given) can reach."""
    rows = counts.groupBy(*given).agg(F.sum(n).alias("total"))
    joined = counts.join(rows, given)
    return joined.agg((-F.sum(F.col(n) * F.log(F.col(n) / F.col("total"))) / F.sum(n)).alias("nll"))


def majority_share(df: DataFrame, label: str) -> DataFrame:
    """Accuracy of always saying the most frequent label."""
    counts = df.groupBy(label).count()
    return counts.agg((F.max("count") / F.sum("count")).alias("majority_share"))

"""Losses and gradients as column expressions: the twin of the numpy models that SQL can check, for few features."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(features: Sequence[str], theta: Sequence[float]) -> Column:
    out = F.lit(0.0)
    for name, t in zip(features, theta, strict=True):
        out = out + F.col(name) * F.lit(float(t))
    return out


def sigmoid(z: Column) -> Column:
    """Safe at both ends."""
    return F.when(z >= 0, 1 / (1 + F.exp(-z))).otherwise(F.exp(z) / (1 + F.exp(z)))


def linear_error(features: Sequence[str], theta: Sequence[float], target: str) -> Column:
    return dot(features, theta) - F.col(target)


def linear_loss(features, theta, target) -> Column:
    return F.avg(0.5 * F.pow(linear_error(features, theta, target), 2))


def logistic_loss(features, theta, target) -> Column:
    z = dot(features, theta)
    return F.avg(F.greatest(z, F.lit(0.0)) + F.log1p(F.exp(-F.abs(z))) - F.col(target) * z)


def softmax_loss(features: Sequence[str], thetas: Sequence[Sequence[float]], target: str) -> Column:
    zs = [dot(features, t) for t in thetas]
    top = F.greatest(*zs)
    total = sum((F.exp(z - top) for z in zs), F.lit(0.0))
    own = F.element_at(F.array(*zs), (F.col(target) + 1).cast("int"))
    return F.avg(top + F.log(total) - own)


def linear_gradient(features, theta, target) -> list[Column]:
    err = linear_error(features, theta, target)
    return [F.avg(err * F.col(f)).alias(f"g{i}") for i, f in enumerate(features)]


def logistic_gradient(features, theta, target) -> list[Column]:
    err = sigmoid(dot(features, theta)) - F.col(target)
    return [F.avg(err * F.col(f)).alias(f"g{i}") for i, f in enumerate(features)]


def two_level(batch: DataFrame, group: Sequence[str], worker: str, gradient: Sequence[Column]) -> DataFrame:
    """Mean over workers of each worker's mean: right for batches of unequal size, unlike a flat mean."""
    per = batch.groupBy(*group, worker).agg(*gradient)
    names = [c for c in per.columns if c not in (*group, worker)]
    return per.groupBy(*group).agg(*[F.avg(c).alias(c) for c in names], F.count("*").alias("n_workers"))

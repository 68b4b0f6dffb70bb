"""Vector functions: column expressions first, Arrow and pandas functions where an expression would be long."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def planted_weights(d: int) -> np.ndarray:
    """The direction of the planted target."""
    return ((37 * np.arange(d) + 11) % 19 - 9) / 9


def planted(d: int) -> Column:
    return F.array(*[F.lit(float(w)) for w in planted_weights(d)])


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


@F.pandas_udf(T.DoubleType())
def planted_dot(v: pd.Series) -> pd.Series:
    if not len(v):
        return pd.Series([], dtype=float)
    x = np.stack(v.to_numpy()).astype(float)
    return pd.Series(x @ planted_weights(x.shape[1]))


@F.pandas_udf(T.DoubleType())
def sigmoid(z: pd.Series) -> pd.Series:
    return pd.Series(0.5 * (1 + np.tanh(z.to_numpy(float) / 2)))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(v: pd.Series) -> list[float]:
    return np.sum([np.asarray(x, float) for x in v], axis=0).tolist()


def partial_total(df: DataFrame, column: str) -> DataFrame:
    """(total, n) per partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = 0.0, 0
        for b in batches:
            total, n = total + float(np.asarray(b.column(0)).sum()), n + b.num_rows
        yield pa.RecordBatch.from_arrays([pa.array([total]), pa.array([n])], names=["total", "n"])

    return df.select(column).mapInArrow(run, "total double, n long")


@F.udtf(returnType=T.StructType([T.StructField("step", T.IntegerType()), T.StructField("theta", T.DoubleType())]))
class QuadraticReplay:
    """One row per step of descent on (theta - target)^2 / 2."""

    def eval(self, theta: float, rate: float, target: float, steps: int):
        yield 0, theta
        for t in range(1, steps + 1):
            theta = theta - rate * (theta - target)
            yield t, theta


def register(spark: SparkSession) -> None:
    """Names for SQL text."""
    spark.udf.register("qg_sigmoid", sigmoid)
    spark.udf.register("qg_planted_dot", planted_dot)

"""Python functions for the plans that built-in ones can't express, and their registration for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructField, StructType

from tilealg.workers import shipped

shipped(__name__)


@F.pandas_udf(DoubleType())
def vector_norm(v: pd.Series) -> pd.Series:
    sizes = v.map(len).to_numpy()
    flat = np.concatenate([np.zeros(0), *v])
    total = np.concatenate([[0.0], np.cumsum(flat * flat)])
    ends = np.cumsum(sizes)
    return pd.Series(np.sqrt(np.maximum(total[ends] - total[ends - sizes], 0)))


@F.pandas_udf(DoubleType())
def robust_sum(v: pd.Series) -> float:
    """Sum of the values within three standard deviations of their mean."""
    spread = v.std(ddof=0)
    return float(v[(v - v.mean()).abs() <= 3 * spread].sum()) if spread > 0 else float(v.sum())


@F.udtf(returnType=StructType([StructField("beta", IntegerType())]))
class TileCopies:
    """The column stripes that a cell is copied to."""

    def eval(self, stripes: int) -> Iterator[tuple[int]]:
        for b in range(stripes):
            yield (b,)


@F.udtf(returnType=StructType([StructField("a", LongType()), StructField("b", LongType()), StructField("v", DoubleType())]))
class GramPairs:
    """The products that a row of columns and values gives to the Gram of the columns, on and above the diagonal."""

    def eval(self, idx: list[int], val: list[float]) -> Iterator[tuple[int, int, float]]:
        for x, (i, v) in enumerate(zip(idx, val, strict=True)):
            for j, w in zip(idx[x:], val[x:], strict=True):
                yield (i, j, v * w) if i <= j else (j, i, v * w)


def register(spark: SparkSession) -> None:
    """mat_norm, mat_robust_sum, mat_copies and gram_pairs for SQL."""
    spark.udtf.register("gram_pairs", GramPairs)
    spark.udf.register("mat_norm", vector_norm)
    spark.udf.register("mat_robust_sum", robust_sum)
    spark.udtf.register("mat_copies", TileCopies)


def distinct_by_smallest(df, column: str, k: int = 1024):
    """(n): number of distinct values, exact up to k, else from the k smallest of their hashes; no state beyond k rows."""
    hashed = F.conv(F.substring(F.md5(F.col(column).cast("binary")), 1, 12), 16, 10).cast("long")
    least = df.select(hashed.alias("h")).where("h is not null").distinct().orderBy("h").limit(k)
    return least.agg(F.when(F.count(F.lit(1)) < k, F.count(F.lit(1))).otherwise(F.floor((k - 1) * 2.0**48 / F.max("h"))).cast("long").alias("n"))


def sql_product(spark: SparkSession, left: str, right: str):
    """Product of two views with columns i, j, v, as SQL text."""
    return spark.sql(f"SELECT a.i, b.j, sum(a.v * b.v) AS v FROM {left} a JOIN {right} b ON a.j = b.i GROUP BY a.i, b.j")

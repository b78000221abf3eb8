"""Seeded matrices from integer arithmetic that any SQL engine repeats exactly."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells

PRIME = 2_147_483_647


def mixed(i: Column, j: Column, seed: int) -> Column:
    """A number below PRIME for each cell; two squarings break up the rows and columns."""
    x = (i * 7919 + j * 104_729 + (seed * 1_299_709 + 12_345)) % PRIME
    x = (x * x + 48_271) % PRIME
    return (x * x + 16_807) % PRIME


def random_matrix(spark: SparkSession, rows: int, cols: int, density: float, seed: int = 1, low: int = 1, high: int = 9, parts: int | None = None, ids: DataFrame | None = None) -> Cells:
    """Each cell is kept with chance ``density`` and has a whole value from low to high.  Rows are dealt evenly, or
    lie as the given ``ids`` (id) do, which number the rows."""
    i, j = F.col("id"), F.col("j").cast("long")
    each = spark.range(0, rows, 1, parts or workers(spark)) if ids is None else ids
    cells = each.select("id", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("j"))
    kept = cells.select(i.alias("i"), j.alias("j"), mixed(i, j, seed).alias("x")).where(F.col("x") < int(density * PRIME))
    return Cells(kept.select("i", "j", ((F.col("x") * 16_807 + 11) % PRIME % (high - low + 1) + low).alias("v")), rows, cols)


def workers(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def random_factor(spark: SparkSession, rows: int, k: int, seed: int = 17) -> DataFrame:
    """(i, vec): strictly positive rows of k values, of full rank for small k."""
    return spark.range(rows).select(F.col("id").alias("i"), F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda j: ((F.col("id") * 7919 + j * 104_729 + seed) % 1009 + 1) / F.lit(1010.0)).alias("vec"))

"""Sparse matrices as DataFrames of cells (i, j, v); a missing cell is 0.  Indices count from 0.

``Cells`` carries the shape, so that empty rows and columns count, and may carry a bound of its cells, such as the rows of
the table they come from.  Transposing is a renaming.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Cells:
    df: DataFrame
    rows: int
    cols: int
    most: int | None = None
    #: Rows (i, j, v) whose sums for each (i, j), as the type of the cells, are the cells; nulls count as nothing.
    loose: DataFrame | None = None

    @classmethod
    def of(cls, df: DataFrame, rows: int | None = None, cols: int | None = None) -> Cells:
        """Columns i, j, v of ``df``; a missing shape is read off the largest indices."""
        df = df.select("i", "j", "v")
        if rows is None or cols is None:
            r, c = df.agg(F.max("i"), F.max("j")).first()
            rows, cols = rows if rows is not None else (r if r is not None else -1) + 1, cols if cols is not None else (c if c is not None else -1) + 1
        return cls(df, int(rows), int(cols))

    @property
    def t(self) -> Cells:
        turned = lambda df: df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")
        return Cells(turned(self.df), self.cols, self.rows, self.most, None if self.loose is None else turned(self.loose))

    def with_df(self, df: DataFrame) -> Cells:
        return replace(self, df=df, most=None, loose=None)

    def bound(self, enough: int = 0) -> int:
        """A bound of the number of cells: that of the shape if it is within ``enough``, the one carried, else their count."""
        if self.rows * self.cols <= enough:
            return self.rows * self.cols
        return self.nnz() if self.most is None else min(self.most, self.rows * self.cols)

    def nnz(self) -> int:
        return self.df.count()

    @property
    def spark(self) -> SparkSession:
        return self.df.sparkSession


def validated(a: Cells, non_negative: bool = False) -> Cells:
    """Raises ValueError, with counts, for null or outside indices, values that are NaN or infinite, and negative ones
    if asked; null values count as missing cells."""
    v = F.col("v").cast("double")
    bad = a.df.agg(
        F.count_if(F.col("i").isNull() | F.col("j").isNull()).alias("null_index"),
        F.count_if(~F.col("i").between(0, a.rows - 1) | ~F.col("j").between(0, a.cols - 1)).alias("outside"),
        F.count_if(F.isnan(v) | (F.abs(v) == float("inf"))).alias("not_finite"),
        F.count_if((v < 0) & F.lit(non_negative)).alias("negative"),
    ).first().asDict()
    if any(bad.values()):
        raise ValueError(f"bad cells: { {k: n for k, n in bad.items() if n} }")
    return a.with_df(a.df.where("v is not null"))


def transpose(a: Cells) -> Cells:
    return a.t


def drop_zeros(a: Cells, tol: float = 0.0) -> Cells:
    return a.with_df(a.df.where(F.abs("v") > tol))


def hadamard(a: Cells, b: Cells) -> Cells:
    return a.with_df(a.df.join(b.df.withColumnRenamed("v", "w"), ["i", "j"]).select("i", "j", (F.col("v") * F.col("w")).alias("v")))


def ratio(num, den, eps: float):
    """num / den; 0 / 0 is 0 and x / 0 is x / eps."""
    return F.when(num == 0, 0.0).otherwise(num / F.when(den == 0, eps).otherwise(den))


def safe_ratio(a: Cells, b: Cells, eps: float = 1e-12) -> Cells:
    w = F.coalesce(F.col("w"), F.lit(0.0))
    return a.with_df(a.df.join(b.df.withColumnRenamed("v", "w"), ["i", "j"], "left").select("i", "j", ratio(F.col("v"), w, eps).alias("v")))


def scale(a: Cells, factor) -> Cells:
    return a.with_df(a.df.select("i", "j", (F.col("v") * factor).alias("v")))


def axpy(factor, a: Cells, b: Cells) -> Cells:
    """factor * a + b, over the cells of either."""
    both = a.df.join(b.df.withColumnRenamed("v", "w"), ["i", "j"], "full")
    return b.with_df(both.select("i", "j", (F.coalesce("v", F.lit(0)) * factor + F.coalesce("w", F.lit(0))).alias("v")))


def slice_rows(a: Cells, low: int, high: int) -> Cells:
    """Rows low to high - 1, under their old numbers."""
    return a.with_df(a.df.where((F.col("i") >= low) & (F.col("i") < high)))


def slice_cols(a: Cells, low: int, high: int) -> Cells:
    return a.with_df(a.df.where((F.col("j") >= low) & (F.col("j") < high)))


def to_rows(a: Cells) -> DataFrame:
    """(i, idx, val): one row of the matrix each, columns in order."""
    cells = F.array_sort(F.collect_list(F.struct("j", "v")))
    return a.df.groupBy("i").agg(cells.alias("c")).select("i", F.transform("c", lambda x: x["j"].cast("int")).alias("idx"), F.transform("c", lambda x: x["v"].cast("double")).alias("val"))


def from_rows(rows: DataFrame, n: int | None = None, cols: int | None = None) -> Cells:
    return Cells.of(rows.select("i", F.explode(F.arrays_zip("idx", "val")).alias("c")).select("i", F.col("c.idx").cast("long").alias("j"), F.col("c.val").alias("v")), n, cols)


def from_dense(rows: DataFrame, vector: str, n: int | None = None, cols: int | None = None) -> Cells:
    """(i, vector) with an array column; values are widened to double before anything else."""
    return Cells.of(rows.select("i", F.posexplode(vector).alias("j", "v")).select("i", F.col("j").cast("long").alias("j"), F.col("v").cast("double").alias("v")), n, cols)


def to_maps(a: Cells) -> DataFrame:
    """(i, m) with a map from column to value."""
    return a.df.groupBy("i").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct(F.col("j").cast("int"), F.col("v").cast("double"))))).alias("m"))


def from_maps(rows: DataFrame, n: int | None = None, cols: int | None = None) -> Cells:
    return Cells.of(rows.select("i", F.explode("m").alias("j", "v")).select("i", F.col("j").cast("long").alias("j"), "v"), n, cols)


def to_tiles(a: Cells, rows_per: int, cols_per: int) -> DataFrame:
    """(bi, bj, idx, val): tiles with cells in row-major order inside the tile."""
    at = (F.col("i") % rows_per) * cols_per + F.col("j") % cols_per
    return (
        a.df.groupBy(F.expr(f"i div {rows_per}").alias("bi"), F.expr(f"j div {cols_per}").alias("bj"))
        .agg(F.array_sort(F.collect_list(F.struct(at.cast("long").alias("at"), F.col("v").alias("v")))).alias("c"))
        .select("bi", "bj", F.transform("c", lambda x: x["at"]).alias("idx"), F.transform("c", lambda x: x["v"]).alias("val"))
    )


def from_tiles(tiles: DataFrame, rows_per: int, cols_per: int, rows: int | None = None, cols: int | None = None) -> Cells:
    cells = tiles.select("bi", "bj", F.explode(F.arrays_zip("idx", "val")).alias("c"))
    return Cells.of(cells.select((F.col("bi") * rows_per + F.expr(f"c.idx div {cols_per}")).alias("i"), (F.col("bj") * cols_per + F.col("c.idx") % cols_per).alias("j"), F.col("c.val").alias("v")), rows, cols)


def split_rows(a: Cells, parts: int) -> Cells:
    """Whole rows dealt at random over partitions."""
    return a.with_df(a.df.repartition(parts, "i"))


def dictionary(keys: DataFrame, name: str) -> DataFrame:
    """(key, idx): numbers keys by their order.  Ranges of keys are numbered apart and shifted by the counts before
    them, so no task holds all keys."""
    from pyspark.sql import Window

    from tilealg.operators.iterate import cut

    keys = keys.select(F.col(name).alias("key")).where("key is not null").distinct()
    # Written, as a range sample that is taken again after a loss could place keys otherwise.
    ranged = cut(keys.repartitionByRange("key").withColumn("part", F.spark_partition_id()))
    before = ranged.groupBy("part").count().withColumn("first", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return ranged.join(F.broadcast(before.select("part", "first")), "part").select("key", (F.row_number().over(Window.partitionBy("part").orderBy("key")) - 1 + F.col("first")).cast("long").alias("idx"))

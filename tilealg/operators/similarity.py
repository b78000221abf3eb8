"""Comparing rows: dot products, distances, cosines, neighbours."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells
from tilealg.operators.grid import TileGrid
from tilealg.operators.packed import STRIPE_CELLS, cut_finer, packed_chosen, packed_distances, packed_gram, packed_nearest, packed_product, packed_reach, packed_top
from tilealg.operators.product import broadcast_product, cell_product, group_tiles, large, multiply_tiles, sum_partials, tiled_product, workers_of


def row_dots(a: Cells, b: Cells, **how) -> Cells:
    return tiled_product(a, b.t, **how)


def chosen_dots(a: Cells, every: int = 20) -> Cells:
    """The rows of A A^T whose number ``every`` divides, in packed tiles of rows of A, dealt evenly over the workers."""
    workers = workers_of(a.spark)
    grid = TileGrid.of(a.rows, a.cols, a.rows, 2 * workers)
    return packed_chosen(a, f"i % {every} = 0", -(-a.bound() // every), grid, "row", workers).t


def gram_rows(a: Cells, half: bool = True, grid: TileGrid | None = None, placement: str = "tile", workers: int | None = None, by_reach: bool = False, **how) -> Cells | DataFrame:
    """A A^T.  half: only tiles on and above the diagonal are multiplied, and the rest is their mirror.

    The grid has as many row as column stripes, by default those of the planner's ``kernel`` preset.  A cell of row
    stripe s goes to the tiles (s, s..) as a left and to (..s, s) as a right operand, so no index holds all pairs.  Where
    the copies pass the product's bound, the tiles are packed, and the lower ones are mirrors in either case.

    by_reach: instead of the cells, (reach, own): how many have ``reach`` as the larger index, counted in the packed tiles
    that make them.
    """
    workers = workers or workers_of(a.spark)
    if by_reach:
        parts = max(math.isqrt(workers // 2) + 1, -(-a.bound() // STRIPE_CELLS))
        return packed_reach(a, TileGrid.of(a.rows, a.cols, a.rows, parts, 1, parts), workers)
    if grid is None:
        from tilealg.plans.planner import preset

        grid = preset("kernel", a.rows, a.cols, a.rows, workers)
    if half and (grid.m != grid.k or how):
        raise ValueError("half a Gram takes a grid with as many row as column stripes, and no more options")
    if grid.m == grid.k and not how and (sizes := large(a, a.t, grid)):
        return packed_gram(a, cut_finer(grid, *sizes), placement, workers)
    if not half:
        return tiled_product(a, a.t, grid, placement, workers=workers, **how)
    left = a.df.select(grid.alpha("i").alias("alpha"), F.explode(F.sequence(grid.alpha("i"), F.lit(grid.k - 1))).alias("beta"), grid.gamma("j").alias("gamma"), "i", F.col("j").alias("t"), "v")
    right = a.df.select(F.explode(F.sequence(F.lit(0), grid.alpha("i"))).alias("alpha"), grid.alpha("i").alias("beta"), grid.gamma("j").alias("gamma"), F.col("j").alias("t"), F.col("i").alias("j"), F.col("v").alias("w"))
    pairs = group_tiles(left, right, placement, workers).where("alpha < beta or i <= j")
    if placement == "random":
        upper = sum_partials(multiply_tiles(pairs), local=False)
    else:
        upper = sum_partials(multiply_tiles(pairs, combine=False), local=True)
    return Cells(upper.select(F.explode(F.when(F.col("i") == F.col("j"), F.array(F.struct("i", "j", "v"))).otherwise(F.array(F.struct("i", "j", "v"), F.struct(F.col("j").alias("i"), F.col("i").alias("j"), "v")))).alias("c")).select("c.*"), a.rows, a.rows)


def gram_cols(a: Cells) -> Cells:
    """A^T A, by pairs of cells in a row; sums combine before the exchange, so a narrow A moves little."""
    return cell_product(a.t, a)


def squared_norms(a: Cells) -> DataFrame:
    return a.df.groupBy("i").agg(F.sum(F.col("v") * F.col("v")).alias("n2"))


def row_distances(a: Cells, b: Cells, squared: bool = False, most_pairs: int = 2_000_000_000, rows: DataFrame | None = None, decimals: int | None = None) -> Cells:
    """Euclidean distances of all pairs of rows, those without a common column too.

    The result has a.rows * b.rows cells by definition; more than ``most_pairs`` is an error, not a cut.  rows: (i) of
    the rows of A that are asked for, if not all.  The squared norms are two more columns, in which every row has a cell, so
    distances are made whole in packed tiles and pairs are never exchanged.  decimals: distances are rounded there.
    """
    asked = a.rows if rows is None else rows.count()
    if asked * b.rows > most_pairs:
        raise ValueError(f"{asked} x {b.rows} distances; ask for neighbours instead")
    spark = a.spark
    ids = spark.range(a.rows).select(F.col("id").alias("i")).join(squared_norms(a), "i", "left").select("i", F.coalesce("n2", F.lit(0)).cast("double").alias("n2"))
    other = spark.range(b.rows).select(F.col("id").alias("i")).join(squared_norms(b), "i", "left").select("i", F.coalesce("n2", F.lit(0)).cast("double").alias("n2"))
    own = a.df
    if rows is not None:
        ids, own = ids.join(rows, "i", "left_semi"), own.join(rows, "i", "left_semi")
    one, norm = (F.lit(a.cols + at).cast("long") for at in (0, 1))
    left = own.select("i", F.col("j").cast("long").alias("j"), (F.col("v") * -2.0).alias("v")).union(ids.select("i", F.explode(F.array(F.struct(one.alias("j"), F.lit(1.0).alias("v")), F.struct(norm.alias("j"), F.col("n2").alias("v")))).alias("c")).select("i", "c.*"))
    right = b.df.select("i", F.col("j").cast("long").alias("j"), F.col("v").cast("double").alias("v")).union(other.select("i", F.explode(F.array(F.struct(one.alias("j"), F.col("n2").alias("v")), F.struct(norm.alias("j"), F.lit(1.0).alias("v")))).alias("c")).select("i", "c.*"))
    workers = workers_of(spark)
    grid = cut_finer(TileGrid.of(a.rows, a.cols + 2, b.rows, 1, 1, workers), a.bound() + 2 * asked, b.bound() + 2 * b.rows)
    return Cells(packed_distances(Cells(left, a.rows, a.cols + 2), Cells(right, b.rows, a.cols + 2).t, grid, squared, decimals, workers), a.rows, b.rows)


def row_cosines(a: Cells, b: Cells) -> Cells:
    """Cosines of pairs of rows with a common column."""
    x, y = squared_norms(a).withColumnRenamed("n2", "x"), squared_norms(b).select(F.col("i").alias("j"), F.col("n2").alias("y"))
    return Cells(cell_product(a, b.t).df.join(x, "i").join(y, "j").where("x > 0 and y > 0").select("i", "j", (F.col("v") / F.sqrt(F.col("x") * F.col("y"))).alias("v")), a.rows, b.rows)


def top_k_similar(a: Cells, b: Cells, k: int, metric: str = "cosine", skip_self: bool = True, decimals: int | None = None) -> DataFrame:
    """(i, j, v, place): for each row of A its k best rows of B; ties go to the smaller j."""
    scored = {"cosine": row_cosines, "dot": lambda x, y: cell_product(x, y.t), "distance": row_distances}[metric](a, b).df
    if skip_self:
        scored = scored.where("i <> j")
    if decimals is not None:
        scored = scored.withColumn("v", F.round("v", decimals))
    order = F.col("v").asc() if metric == "distance" else F.col("v").desc()
    return scored.withColumn("place", F.row_number().over(Window.partitionBy("i").orderBy(order, "j"))).where(F.col("place") <= k)


def top_k_packed(a: Cells, b: Cells, k: int, skip_self: bool = True, decimals: int | None = None, chosen: str | None = None) -> DataFrame:
    """``top_k_similar`` by cosine, with the k best of each row taken in each packed tile: pairs never leave it.

    chosen: A is the rows of B for which this holds, so B is worked out once for both; its cells are whole numbers.
    """
    last = lambda best: best.withColumn("place", F.row_number().over(Window.partitionBy("i").orderBy(F.col("v").desc(), "j"))).where(F.col("place") <= k)
    if chosen is not None:
        return last(packed_nearest(b, squared_norms(b).where("n2 > 0"), chosen, max(1, b.bound() * a.rows // max(1, b.rows)), k, decimals, skip_self, workers_of(b.spark)))
    unit = lambda m: m.df.join(squared_norms(m).where("n2 > 0"), "i").select("i", "j", (F.col("v") / F.sqrt("n2")).alias("v"))
    x, y = a.with_df(unit(a)), b.with_df(unit(b)).t
    workers = workers_of(a.spark)
    grid = cut_finer(TileGrid.of(x.rows, x.cols, y.cols, 1, 1, workers), a.bound(), b.bound())
    return last(packed_top(x, y, grid, k, decimals, skip_self, workers))


def assign_nearest(a: Cells, centroids: Cells) -> DataFrame:
    """(i, j): the nearest centroid of each row that has a cell; centroids are the small operand."""
    dots = broadcast_product(a, centroids, transpose_small=True).df
    y = squared_norms(centroids).select(F.col("i").alias("j"), F.col("n2").alias("y"))
    ids = a.df.select("i").distinct().crossJoin(F.broadcast(y))
    return ids.join(dots, ["i", "j"], "left").groupBy("i").agg(F.min_by("j", F.struct(F.round(F.col("y") - 2 * F.coalesce("v", F.lit(0)), 9), "j")).alias("j"))

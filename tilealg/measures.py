"""Costs and accuracies: counts of work, sizes, times, fits."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells
from tilealg.operators.grid import TileGrid
from tilealg.operators.packed import packed_counts
from tilealg.operators.product import group_tiles, multiply_tiles, shard, tag_left, tag_right, workers_of


def timed(make: Callable[[], DataFrame]) -> float:
    """Seconds to run a plan to its end without keeping its rows."""
    began = time.monotonic()
    make().write.format("noop").mode("overwrite").save()
    return time.monotonic() - began


def stage_times(a: Cells, b: Cells, grid: TileGrid, placement: str, path: str) -> dict[str, float]:
    """Seconds of the partition stage (tagged copies written) and of the compute stage (read, multiplied, summed)."""
    from tilealg.operators.product import sum_partials

    began = time.monotonic()
    tag_left(a, grid).write.mode("overwrite").parquet(f"{path}/left")
    tag_right(b, grid).write.mode("overwrite").parquet(f"{path}/right")
    cut = time.monotonic() - began
    read = a.spark.read.parquet
    return {"partition": cut, "compute": timed(lambda: sum_partials(multiply_tiles(group_tiles(read(f"{path}/left"), read(f"{path}/right"), placement, workers_of(a.spark))), placement != "random"))}


#: Bytes of a tagged cell (piece, cell, value) and of a partial one on their way through an exchange.
TAGGED_BYTES, PARTIAL_BYTES = 3 * 4 + 3 * 8, 2 * 4 + 3 * 8


def intermediate_counts(a: Cells, b: Cells, grid: TileGrid, placement: str = "tile", workers: int | None = None) -> DataFrame:
    """(copied, partials, moved, moved_bytes): tagged input cells, partial cells before the final sum, and what is sent
    between workers.

    A worker sums the partials that it made of a cell; under row and tile placement these are all, so none is sent.
    Under random placement those go to the worker of the cell's tile that are not there already.
    """
    workers = workers or workers_of(a.spark)
    copied = tag_left(a, grid).agg(F.count(F.lit(1)).alias("n")).crossJoin(tag_right(b, grid).agg(F.count(F.lit(1)).alias("m"))).select((F.col("n") + F.col("m")).alias("copied"))
    parts = multiply_tiles(group_tiles(tag_left(a, grid), tag_right(b, grid), placement, workers))
    if placement == "random":
        own = parts.groupBy("pid", "alpha", "beta", "i", "j").agg(F.count(F.lit(1)).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("partials"), F.count(F.when(F.col("pid") != shard("tile", workers), 1)).alias("moved"))
    else:
        own = parts.agg(F.count(F.lit(1)).alias("partials"), F.lit(0).cast("long").alias("moved"))
    return copied.crossJoin(own).withColumn("moved_bytes", F.col("copied") * TAGGED_BYTES + F.col("moved") * PARTIAL_BYTES)


def intermediate_counts_many(a: Cells, b: Cells, grids: list[tuple[TileGrid, str]], workers: int | None = None) -> DataFrame:
    """(at, copied, partials, moved, moved_bytes) of ``intermediate_counts`` for each place ``at`` of the list, all from one
    product in packed tiles, as partial cells of a large product are too many to be sent."""
    counts = packed_counts(a, b, grids, workers or workers_of(a.spark))
    cells = counts.where("at < 0").select(F.col("x").alias("na"), F.col("y").alias("nb"))
    edges = a.spark.createDataFrame([(at, g.k, g.m) for at, (g, _) in enumerate(grids)], "at int, k long, m long")
    own = F.broadcast(edges).crossJoin(F.broadcast(cells)).join(F.broadcast(counts.where("at >= 0")), "at", "left")
    zero = lambda c: F.coalesce(c, F.lit(0).cast("long"))
    copied = F.col("k") * F.col("na") + F.col("m") * F.col("nb")
    return own.select("at", copied.alias("copied"), zero(F.col("x")).alias("partials"), zero(F.col("y")).alias("moved"), (copied * TAGGED_BYTES + zero(F.col("y")) * PARTIAL_BYTES).alias("moved_bytes"))


def placement_balance(tags: DataFrame, placement: str, workers: int) -> DataFrame:
    """(busy, most, mean): workers with cells, and cells at the fullest and at the mean one."""
    return tags.withColumn("pid", shard(placement, workers)).groupBy("pid").count().agg(F.count(F.lit(1)).alias("busy"), F.max("count").alias("most"), (F.sum("count") / workers).alias("mean"))


def local_fraction(a: Cells, b: Cells, grid: TileGrid, placement: str, workers: int) -> float:
    """Share of partial cells that already lie where their sum is made (that of their tile)."""
    parts = multiply_tiles(group_tiles(tag_left(a, grid), tag_right(b, grid), placement, workers))
    if placement != "random":
        return 1.0
    return parts.agg(F.avg((F.col("pid") == shard("tile", workers)).cast("double"))).first()[0] or 0.0


def density(a: Cells) -> float:
    return a.nnz() / max(1, a.rows * a.cols)


def storage_size(a: Cells, bytes_per_cell: int = 24) -> tuple[int, int]:
    n = a.nnz()
    return n, n * bytes_per_cell


def flops(a: Cells, b: Cells) -> int:
    """Scalar products of two sparse operands, from counts by inner index."""
    left = a.df.groupBy(F.col("j").alias("t")).agg(F.count(F.lit(1)).alias("x"))
    right = b.df.groupBy(F.col("i").alias("t")).agg(F.count(F.lit(1)).alias("y"))
    return left.join(right, "t").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0))).first()[0]


def expected_flops(a: int, b: int, c: int, da: float, db: float) -> float:
    return a * b * c * da * db


def expected_output_density(inner: int, da: float, db: float) -> float:
    return 1 - (1 - da * db) ** inner


def copied_bound(na: int, nb: int, grid: TileGrid) -> tuple[int, int]:
    """Exact copies of the inputs, and the looser bound m k (nnz A + nnz B)."""
    return grid.k * na + grid.m * nb, grid.m * grid.k * (na + nb)


def accuracy(pred: DataFrame, truth: str = "y", label: str = "label") -> DataFrame:
    """(rows, right, accuracy, balanced, majority) of a table with true and predicted labels of -1 and 1."""
    ok = (F.col(truth) == F.col(label)).cast("double")
    per = [F.avg(F.when(F.col(truth) == s, ok)) for s in (1, -1)]
    positive = F.avg((F.col(truth) == 1).cast("double"))
    return pred.agg(F.count(F.lit(1)).alias("rows"), F.sum(ok).cast("long").alias("right"), F.avg(ok).alias("accuracy"), ((F.coalesce(per[0], F.lit(0.0)) + F.coalesce(per[1], F.lit(0.0))) / 2).alias("balanced"), F.greatest(positive, 1 - positive).alias("majority"))


def confusion(pred: DataFrame, truth: str = "y", label: str = "label") -> DataFrame:
    return pred.groupBy(truth, label).count()


def is_non_increasing(trace: list[float], tol: float = 1e-9) -> bool:
    return all(b <= a * (1 + tol) + tol for a, b in zip(trace, trace[1:], strict=False))


def is_non_decreasing(trace: list[float], tol: float = 1e-9) -> bool:
    return is_non_increasing([-x for x in trace], tol) if all(x >= 0 for x in trace) is False else all(b >= a - tol - tol * abs(a) for a, b in zip(trace, trace[1:], strict=False))


def kkt_gap(k: Cells, y: DataFrame, alpha: DataFrame, c: float) -> float:
    """Largest step that the box would still allow along the gradient."""
    from tilealg.operators.svm import svm_gradient

    g = alpha.join(svm_gradient(k, y, alpha).withColumnRenamed("v", "g"), "i")
    held = F.when((F.col("v") <= 0) & (F.col("g") < 0), 0.0).when((F.col("v") >= c) & (F.col("g") > 0), 0.0).otherwise(F.abs("g"))
    return g.agg(F.coalesce(F.max(held), F.lit(0.0))).first()[0]


def relative_speedup(seconds: dict[int, float]) -> dict[int, float]:
    one = seconds[min(seconds)]
    return {p: one / s for p, s in seconds.items()}


def loglog_fit(x: list[float], y: list[float]) -> float:
    """Slope of the least squares line through logarithms."""
    return float(np.polyfit(np.log(x), np.log(y), 1)[0])


def last_slope(x: list[float], y: list[float]) -> float:
    return math.log(y[-1] / y[-2]) / math.log(x[-1] / x[-2])


def linearity(x: list[float], y: list[float]) -> float:
    """R^2 of a straight line."""
    return float(np.corrcoef(x, y)[0, 1] ** 2)


def iterations_per_hour(iters: int, seconds: float) -> float:
    return 3600 * iters / seconds

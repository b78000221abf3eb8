"""Non-negative factors A = W H by multiplicative updates for squared error.

Factors are dense rows (i, vec) of k values: W by rows of A, H transposed, so that its columns are rows.
The error counts as Gaussian noise: least squares is the largest likelihood up to constants.
"""

from __future__ import annotations

import math
import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells, ratio
from tilealg.operators.generate import random_factor
from tilealg.operators.iterate import cut
from tilealg.operators.product import tiled_product, workers_of


def _sum_vectors(weighted: str, k: int):
    """Sums of k-vectors, one aggregate a place: they combine before the exchange."""
    return [F.sum(F.element_at(weighted, r + 1)).alias(f"x{r}") for r in range(k)]


def _rank(factor: DataFrame) -> int:
    row = factor.select(F.size("vec")).first()
    return row[0] if row else 0


def nmf_x(w: DataFrame, a: Cells, k: int | None = None) -> DataFrame:
    """(i, vec): columns of W^T A, as rows by column of A.  The k-vectors are never cut."""
    k = k or _rank(w)
    joined = a.df.join(w.withColumnRenamed("i", "row"), a.df.i == F.col("row")).select(F.col("j").alias("i"), F.transform("vec", lambda x: x * F.col("v")).alias("xv"))
    summed = joined.groupBy("i").agg(*_sum_vectors("xv", k))
    return summed.select("i", F.array(*[f"x{r}" for r in range(k)]).alias("vec"))


def nmf_x_tiled(w: DataFrame, a: Cells, k: int | None = None, **how) -> Cells:
    """W^T A as a tiled product, k by columns of A, on the planner's ``tall`` grid: the long inner edge is cut, the
    factor's short edge stays whole."""
    from tilealg.plans.planner import preset

    k = k or _rank(w)
    left = w.select(F.posexplode("vec").alias("r", "v"), "i").select(F.col("r").cast("long").alias("i"), F.col("i").alias("j"), "v")
    workers = workers_of(a.spark)
    return tiled_product(Cells(left, k, a.rows), a, preset("tall", k, a.rows, a.cols, workers), "random", workers=workers, **how)


def gram(factor: DataFrame, k: int | None = None) -> np.ndarray:
    """Factor^T factor: k x k sums on the driver.  A group for each row of it, as k^2 sums in one are too many to compile."""
    k = k or _rank(factor)
    places = factor.select("vec", F.posexplode("vec").alias("r", "x"))
    sums = [F.sum(F.col("x") * F.element_at("vec", s + 1)) for s in range(k)]
    out = np.zeros((k, k))
    for row in places.groupBy("r").agg(F.array(*sums).alias("g")).collect() if k else []:
        out[row["r"]] = [v or 0 for v in row["g"]]
    return out


def nmf_y(c: np.ndarray, ht: DataFrame) -> DataFrame:
    """(i, vec): rows of H^T C^T; the k x k block is a literal of the expression, so H isn't moved."""
    dot = lambda row: F.aggregate(F.zip_with("vec", row, lambda x, y: x * y), F.lit(0.0), lambda total, v: total + v)
    return ht.select("i", F.transform(F.lit(c.astype(float).tolist()), dot).alias("vec"))


def nmf_apply(h: DataFrame, x: DataFrame, y: DataFrame, eps: float = 1e-12) -> DataFrame:
    """H * X / Y in every place.  0 / 0 is 0; a column of A without cells gives 0."""
    both = h.join(x.withColumnRenamed("vec", "x"), "i", "left").join(y.withColumnRenamed("vec", "y"), "i")
    k = F.size("vec")
    place = F.transform(F.sequence(F.lit(1), k), lambda r: ratio(F.element_at("vec", r.cast("int")) * F.coalesce(F.element_at("x", r.cast("int")), F.lit(0.0)), F.element_at("y", r.cast("int")), eps))
    return both.select("i", place.alias("vec"))


def nmf_apply_local(h: DataFrame, x: DataFrame, y: DataFrame, eps: float = 1e-12, most_values: int = 5_000_000) -> DataFrame:
    """``nmf_apply`` on the driver, for factors of at most ``most_values`` values; larger ones stay distributed."""
    k = _rank(h)
    if h.count() * k > most_values:
        return nmf_apply(h, x, y, eps)
    own, num, den = ({r["i"]: np.array(r["vec"], float) for r in f.collect()} for f in (h, x, y))
    rows = []
    for i in own.keys() & den.keys():
        top = own[i] * num.get(i, np.zeros(k))
        rows.append((i, np.where(top == 0, 0.0, top / np.where(den[i] == 0, eps, den[i])).tolist()))
    return h.sparkSession.createDataFrame(rows, "i long, vec array<double>")


def nmf_update_h(a: Cells, w: DataFrame, ht: DataFrame, eps: float = 1e-12, k: int | None = None) -> DataFrame:
    k = k or _rank(w)
    return nmf_apply(ht, nmf_x(w, a, k), nmf_y(gram(w, k), ht), eps)


def nmf_update_w(a: Cells, w: DataFrame, ht: DataFrame, eps: float = 1e-12, k: int | None = None) -> DataFrame:
    """The same with the roles of the factors changed."""
    return nmf_update_h(a.t, ht, w, eps, k)


def nmf_divergence(a: Cells, w: DataFrame, ht: DataFrame) -> float:
    """|A - W H|^2 from the cells of A and two k x k blocks: the dense product is never made."""
    dot = F.aggregate(F.zip_with("wv", "hv", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    joined = a.df.join(w.select(F.col("i"), F.col("vec").alias("wv")), "i").join(ht.select(F.col("i").alias("j"), F.col("vec").alias("hv")), "j")
    inner = joined.agg(F.coalesce(F.sum(F.col("v") * dot), F.lit(0.0))).first()[0]
    square = a.df.agg(F.coalesce(F.sum(F.col("v").cast("double") * F.col("v")), F.lit(0.0))).first()[0]
    return float(square - 2 * inner + (gram(w) * gram(ht)).sum())


def gaussian_nll(a: Cells, w: DataFrame, ht: DataFrame, sigma: float = 1.0) -> float:
    n = a.rows * a.cols
    return nmf_divergence(a, w, ht) / (2 * sigma**2) + n * math.log(sigma * math.sqrt(2 * math.pi))


def nmf(a: Cells, k: int, iters: int, seed: int = 17, init: tuple[DataFrame, DataFrame] | None = None, order: tuple[str, ...] = ("H", "W"), eps: float = 1e-12, trace: list | None = None) -> tuple[DataFrame, DataFrame]:
    """(W, H^T) after ``iters`` rounds of the updates in ``order``; ("H",) leaves W as it is.

    trace gets the error before the first and after every update.
    """
    w, ht = init or (random_factor(a.spark, a.rows, k, seed), random_factor(a.spark, a.cols, k, seed + 14))
    if trace is not None:
        trace.append(nmf_divergence(a, w, ht))
    for _ in range(iters):
        for which in order:
            if which == "H":
                ht = cut(nmf_update_h(a, w, ht, eps, k))
            else:
                w = cut(nmf_update_w(a, w, ht, eps, k))
            if trace is not None:
                trace.append(nmf_divergence(a, w, ht))
    return w, ht


def nmf_reconstruct(w: DataFrame, ht: DataFrame, cells: DataFrame | None = None) -> DataFrame:
    """(i, j, v) of W H: for given cells (i, j), or all."""
    dot = F.aggregate(F.zip_with("wv", "hv", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    left, right = w.select("i", F.col("vec").alias("wv")), ht.select(F.col("i").alias("j"), F.col("vec").alias("hv"))
    pairs = left.crossJoin(right) if cells is None else cells.select("i", "j").join(left, "i").join(right, "j")
    return pairs.select("i", "j", dot.alias("v"))


def nmf_profile(a: Cells, k: int, seed: int = 17) -> dict[str, float]:
    """Seconds of the parts of one H update: x, y, and the ratio, distributed and on the driver."""
    w, ht = cut(random_factor(a.spark, a.rows, k, seed)), cut(random_factor(a.spark, a.cols, k, seed + 14))
    out, kept = {}, {}
    for name, make in (("x", lambda: nmf_x(w, a)), ("y", lambda: nmf_y(gram(w), ht)), ("ratio", lambda: nmf_apply(ht, kept["x"], kept["y"])), ("ratio_local", lambda: nmf_apply_local(ht, kept["x"], kept["y"]))):
        began = time.monotonic()
        kept[name] = cut(make())
        out[name] = time.monotonic() - began
    return out

"""Loops around a product: power method, gradient descent, step sizes.

State between rounds (a vector, never the matrix) is cut off the plan in the checkpoint folder of the session.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells
from tilealg.operators.product import matvec

#: A step reads its state more than once, so plans would double with every round that isn't cut.
CUT_EVERY = 1


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the checkpoint folder that the session names.

    Where none is named, a session on one machine gets a temporary one; on a cluster that is an error, as executors
    would not share it.
    """
    spark = df.sparkSession
    context = spark.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="tilealg-"))
    return df.checkpoint(eager=True)


def forget(df: DataFrame) -> None:
    """Deletes the files of a state that ``cut`` made and nothing reads any more."""
    plan = df._jdf.queryExecution().analyzed()
    if plan.getClass().getSimpleName() != "LogicalRDD" or not plan.rdd().getCheckpointFile().isDefined():
        return
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(plan.rdd().getCheckpointFile().get())
    path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def run(step: Callable[[DataFrame], DataFrame], state: DataFrame, rounds: int, distance: Callable[[DataFrame, DataFrame], float] | None = None, tol: float | None = None, trace: list | None = None, every: int = CUT_EVERY) -> DataFrame:
    """Applies ``step`` so many times, or until ``distance`` of two states is within ``tol``.

    A state's files are deleted once the next state has been written; the first state is the caller's.
    """
    written = []
    for r in range(rounds):
        after = step(state)
        if tol is not None or (r + 1) % every == 0:
            after = cut(after)
            written.append(after)
        if distance is not None and (tol is not None or trace is not None):
            moved = distance(state, after)
            if trace is not None:
                trace.append(moved)
            if tol is not None and moved <= tol:
                return after
        while len(written) > 1:
            forget(written.pop(0))
        state = after
    return state


def l1(a: DataFrame, b: DataFrame) -> float:
    """Sum of absolute differences of two vectors (i, v)."""
    both = a.join(b.withColumnRenamed("v", "w"), "i", "full")
    return both.agg(F.coalesce(F.sum(F.abs(F.coalesce("v", F.lit(0.0)) - F.coalesce("w", F.lit(0.0)))), F.lit(0.0))).first()[0]


def power_method(p: Cells, x0: DataFrame, iters: int, tol: float | None = None, normalise: bool = False, trace: list | None = None) -> DataFrame:
    """(i, v) of repeated products with P.  normalise: divide by the sum of absolute values each time."""

    def step(x: DataFrame) -> DataFrame:
        y = matvec(p, x)
        if normalise:
            total = y.agg(F.sum(F.abs("v")).alias("total"))
            y = y.crossJoin(F.broadcast(total)).select("i", (F.col("v") / F.col("total")).alias("v"))
        return y

    return run(step, x0, iters, l1, tol, trace)


def gram_power(a: Cells, x0: DataFrame, iters: int, tol: float | None = None, trace: list | None = None) -> DataFrame:
    """``power_method`` with A A^T, normalised, as A (A^T x): the Gram is never made.  A is written once, by its columns, so
    a step moves only sums by row."""
    workers = int(a.spark.conf.get("spark.sql.shuffle.partitions"))
    own = cut(a.df.select("i", "j", F.col("v").cast("double").alias("v")).repartition(workers, "j"))

    def step(x: DataFrame) -> DataFrame:
        inner = own.join(x.withColumnRenamed("v", "x"), "i") if a.rows > 1_000_000 else own.join(F.broadcast(x.withColumnRenamed("v", "x")), "i")
        inner = inner.groupBy("j").agg(F.sum(F.col("v") * F.col("x")).alias("x"))
        y = own.join(inner, "j").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("v"))
        total = y.agg(F.sum(F.abs("v")).alias("total"))
        return y.crossJoin(F.broadcast(total)).select("i", (F.col("v") / F.col("total")).alias("v"))

    return run(step, x0, iters, l1, tol, trace)


def linear_gd(a: Cells, y: DataFrame, eta: float, iters: int, tol: float | None = None) -> DataFrame:
    """(i, v): theta with A^T theta = y in the least squares sense, by gradient steps from 0; y is (i, v)."""
    theta = a.spark.range(a.rows).select(F.col("id").alias("i"), F.lit(0.0).alias("v"))

    def step(state: DataFrame) -> DataFrame:
        reached = matvec(a.t, state).withColumnRenamed("v", "w")
        left = y.join(reached, "i", "left").select("i", (F.col("v") - F.coalesce("w", F.lit(0.0))).alias("v"))
        slope = matvec(a, left).withColumnRenamed("v", "w")
        return state.join(slope, "i", "left").select("i", (F.col("v") + eta * F.coalesce("w", F.lit(0.0))).alias("v"))

    return run(step, theta, iters, l1, tol)


def step_size(k: Cells, rule: str = "norm", iters: int = 20) -> float:
    """``norm``: 1 over the largest row sum of absolute values; ``power``: 1 over the largest eigenvalue."""
    if rule == "norm":
        return 1 / k.df.groupBy("i").agg(F.sum(F.abs("v")).alias("s")).agg(F.max("s")).first()[0]
    if rule != "power":
        raise ValueError("rule is norm or power")
    x = k.spark.range(k.rows).select(F.col("id").alias("i"), F.lit(1.0).alias("v"))
    x = cut(power_method(k, x, iters, normalise=True))
    top = matvec(k, x).withColumnRenamed("v", "w").join(x, "i").agg((F.sum(F.col("w") * F.col("v")) / F.sum(F.col("v") * F.col("v"))).alias("l")).first()[0]
    return 1 / top


def solve_gram(k: Cells, y: DataFrame, ridge: float = 0.0, most_rows: int = 5000) -> np.ndarray:
    """Weights s with (K + ridge) s = y on the driver; for small problems and as a yardstick."""
    if k.rows > most_rows:
        raise ValueError(f"{k.rows} rows; at most {most_rows} are solved on the driver")
    full, target = np.zeros((k.rows, k.rows)), np.zeros(k.rows)
    for r in k.df.toLocalIterator():
        full[r["i"], r["j"]] = r["v"]
    for r in y.toLocalIterator():
        target[r["i"]] = r["v"]
    return np.linalg.lstsq(full + ridge * np.eye(k.rows), target, rcond=None)[0]

"""The experiments whose results are times: sweeps that print one JSON line for each setting.

``python -m tilealg.plans.experiments NAME...`` runs them at the sizes below, which suit one machine; on a cluster,
pass larger ones.  Operands are written before the clock starts, so that making them is never timed.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
import uuid
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilealg import baselines, measures
from tilealg.operators import iterate, nmf, pagerank, similarity, svm
from tilealg.operators.cells import Cells
from tilealg.operators.generate import random_matrix
from tilealg.operators.grid import TileGrid
from tilealg.operators.product import tiled_product
from tilealg.sources import tables as T

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
COARSE, FINE = (20, 6, 20), (40, 6, 40)
EXPERIMENTS = {}

#: Rows that the sequential trainer takes on the driver; more are refused.
MOST_SEQUENTIAL_ROWS = 5_000


def experiment(f):
    EXPERIMENTS[f.__name__] = f
    return f


def _scratch(spark: SparkSession) -> str:
    return f"{spark.conf.get('spark.sql.warehouse.dir')}/experiment_{uuid.uuid4().hex}"


def _square(spark: SparkSession, m: int, density: float, seed: int) -> Cells:
    a = random_matrix(spark, m, m, density, seed)
    return a.with_df(iterate.cut(a.df))


def _pair(spark: SparkSession, m: int, density: float) -> tuple[Cells, Cells]:
    return _square(spark, m, density, 1), _square(spark, m, density, 2)


def _grid(m: int, shape: tuple[int, int, int]) -> TileGrid:
    return TileGrid.of(m, m, m, *shape)


@experiment
def size_sweep(spark: SparkSession, sizes=(512, 1024, 2048, 4096, 8192), density: float = 2**-7) -> Iterator[dict]:
    """Both stages over growing square operands, with the cubic line through the first point and slopes of the total."""
    _warm(spark)
    totals = []
    for m in sizes:
        a, b = _pair(spark, m, density)
        t = measures.stage_times(a, b, _grid(m, COARSE), "row", _scratch(spark))
        totals.append(t["partition"] + t["compute"])
        yield {"m": m, "nnz": a.nnz(), **_seconds(t), "total": round(totals[-1], 2), "cubic": round(baselines.cubic_prediction(sizes[0], totals[0], m), 2), "share_partition": round(t["partition"] / totals[-1], 3)}
    if len(sizes) > 1:
        yield {"slope": round(measures.loglog_fit(list(sizes), totals), 2), "last_slope": round(measures.last_slope(list(sizes), totals), 2)}


@experiment
def density_sweep(spark: SparkSession, m: int = 4096, densities=(2**-10, 2**-9, 2**-8, 2**-7, 2**-6)) -> Iterator[dict]:
    """Both stages at one size over growing shares of non-zero cells, and how straight the total is in the non-zeros."""
    _warm(spark)
    cells, totals = [], []
    for d in densities:
        a, b = _pair(spark, m, d)
        t = measures.stage_times(a, b, _grid(m, COARSE), "row", _scratch(spark))
        cells.append(a.nnz() + b.nnz())
        totals.append(t["partition"] + t["compute"])
        yield {"density": d, "nnz": cells[-1], "flops": measures.flops(a, b), **_seconds(t), "total": round(totals[-1], 2)}
    if len(densities) > 1:
        yield {"linearity": round(measures.linearity(cells, totals), 4)}


@experiment
def placement_sweep(spark: SparkSession, m: int | tuple[int, ...] = (2048, 4096, 8192), density: float = 2**-7) -> Iterator[dict]:
    """Placements and grids at each size: seconds, cells and bytes between the stages, and partials that need not move."""
    _warm(spark)
    workers = int(spark.conf.get("spark.sql.shuffle.partitions"))
    for size in (m,) if isinstance(m, int) else m:
        a, b = _pair(spark, size, density)
        for placement, shape in (("row", COARSE), ("random", COARSE), ("random", FINE), ("tile", COARSE)):
            grid = _grid(size, shape)
            counts = measures.intermediate_counts(a, b, grid, placement).first().asDict()
            took = measures.timed(lambda p=placement, g=grid: tiled_product(a, b, g, p).df)  # noqa: B023
            yield {"m": size, "placement": placement, "grid": shape, "seconds": round(took, 2), **counts, "stays": round(measures.local_fraction(a, b, grid, placement, workers), 3)}


@experiment
def speedup(spark: SparkSession, cores=(1, 2, 4, 8), m: int = 4096, densities=(2**-7, 2**-10, 2**-13)) -> Iterator[dict]:
    """Relative speedup of one product over the number of cores; a fresh session for each number."""
    seconds: dict[float, dict[int, float]] = {d: {} for d in densities}
    for p in cores:
        code = f"from tilealg.plans.experiments import product_seconds; product_seconds({p}, {m}, {tuple(densities)})"
        done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True)
        for d, s in json.loads(done.stdout.strip().splitlines()[-1]):
            seconds[d][p] = s
    for d, by in seconds.items():
        for p, gain in measures.relative_speedup(by).items():
            yield {"density": d, "cores": p, "seconds": round(by[p], 2), "speedup": round(gain, 2), "ideal": baselines.ideal_speedup(p) / min(cores)}


def product_seconds(p: int, m: int, densities: tuple) -> None:
    """Prints [density, seconds] of products on p cores."""
    spark = session(p, partitions=20)
    _warm(spark)
    out = []
    for d in densities:
        a, b = _pair(spark, m, d)
        out.append([d, measures.timed(lambda a=a, b=b: tiled_product(a, b, _grid(m, COARSE), "row").df)])
    print(json.dumps(out))


def _labelled(spark: SparkSession, sf_dir: str, task: str, n: int | None = None) -> tuple[Cells, DataFrame]:
    """Unit rows of term counts of the first n labelled documents (of all, if None), renumbered from 0; (i, y, is_test)."""
    from tilealg.operators.cells import dictionary

    t, _ = T.doc_term(spark, sf_dir, normalise=True)
    y = iterate.cut(T.labelled(spark, sf_dir, task))
    place = dictionary(y.select("i").distinct(), "i").select(F.col("key").alias("i"), F.col("idx").alias("at"))
    if n is not None:
        place = place.where(F.col("at") < n)
    place = iterate.cut(place)
    rows = place.count()
    own = t.df.join(place, "i").select(F.col("at").alias("i"), "j", "v")
    return Cells(iterate.cut(own), rows, t.cols), iterate.cut(y.join(place, "i").select(F.col("at").alias("i"), "y", "is_test"))


@experiment
def svm_scaling(spark: SparkSession, sf_dir: str = SF_DIR, sizes=(125, 250, 500, 1000), task: str = "language", iters: int = 10) -> Iterator[dict]:
    """Density and cells of the stored kernel, seconds a step, and accuracy, over growing numbers of documents."""
    _warm(spark)
    for n in sizes:
        t, y = _labelled(spark, sf_dir, task, n)
        train = y.where("not is_test").select("i", F.col("y").alias("v"))
        own = t.with_df(iterate.cut(t.df.join(train.select("i"), "i", "left_semi")))
        k = similarity.gram_rows(own, half=True)
        k = k.with_df(iterate.cut(k.df))
        rows, cells = train.count(), k.nnz()
        model = svm.svm_fit(own, train, bias=0.0, eta=iterate.step_size(k), iters=iters, kernel_mode="materialised")
        pred = svm.svm_predict(model, t).join(y.where("is_test").select("i", F.col("y").cast("int").alias("y")), "i")
        yield {"n": n, "train": rows, "kernel_density": round(cells / (rows * rows), 3), "kernel_cells": cells, "kernel_mb": round(cells * 24 / 2**20, 1), "seconds_a_step": round(float(np.median(model.iteration_seconds)), 2), **_figures(pred)}


@experiment
def svm_against_sequential(spark: SparkSession, sf_dir: str = SF_DIR.replace("sf0.1", "sf0.01"), tasks=("language", "quality", "toxic"), iters: int = 20) -> Iterator[dict]:
    """Held-out accuracy of the gradient trainer beside a sequential soft-margin trainer and the library's linear one."""
    from pyspark.ml.linalg import Vectors

    for task in tasks:
        t, y = _labelled(spark, sf_dir, task)
        if t.rows > MOST_SEQUENTIAL_ROWS:
            raise ValueError(f"{t.rows} rows; at most {MOST_SEQUENTIAL_ROWS} are trained on the driver")
        train, test = y.where("not is_test").select("i", F.col("y").alias("v")), y.where("is_test").select("i", F.col("y").cast("int").alias("y"))
        own = t.with_df(iterate.cut(t.df.join(train.select("i"), "i", "left_semi")))
        k = similarity.gram_rows(own, half=True)
        model = svm.svm_fit(own, train, bias=0.0, eta=iterate.step_size(k.with_df(iterate.cut(k.df))), iters=iters)
        yield {"task": task, "trainer": "gradient", **_figures(svm.svm_predict(model, t).join(test, "i"))}
        x, sign = np.zeros((t.rows, t.cols)), np.zeros(t.rows)
        for r in t.df.toLocalIterator():
            x[r["i"], r["j"]] = r["v"]
        held = np.zeros(t.rows, bool)
        for r in y.toLocalIterator():
            sign[r["i"]], held[r["i"]] = r["y"], r["is_test"]
        alpha = baselines.svm_reference(x[~held], sign[~held], bias=0.0)
        yield {"task": task, "trainer": "sequential", **_counted(x[held] @ (x[~held].T @ (alpha * sign[~held])) >= 0, sign[held] > 0)}
        rows = [(Vectors.sparse(t.cols, [(int(j), float(x[i, j])) for j in np.flatnonzero(x[i])]), float(sign[i] > 0), bool(held[i])) for i in range(t.rows)]
        df = spark.createDataFrame(rows, ["features", "label", "held"])
        pred = baselines.library_linear_svc(df.where("not held"), "features", "label").transform(df.where("held")).select("label", "prediction").collect()
        yield {"task": task, "trainer": "library", **_counted(np.array([r["prediction"] > 0 for r in pred]), np.array([r["label"] > 0 for r in pred]))}


@experiment
def nmf_components(spark: SparkSession, m: int = 4096, densities=(2**-7, 2**-10), ranks=(8, 32)) -> Iterator[dict]:
    """Seconds of the three parts of one update of H."""
    _warm(spark)
    for d in densities:
        a = _square(spark, m, d, 1)
        for k in ranks:
            yield {"density": d, "k": k, **_seconds(nmf.nmf_profile(a, k))}


@experiment
def pagerank_hundred(spark: SparkSession, sf_dir: str = SF_DIR, iters: int = 100) -> Iterator[dict]:
    """Seconds, steps an hour and total mass of page ranks of the parts' graph."""
    edges = iterate.cut(T.part_next(spark, sf_dir))
    began = time.monotonic()
    ranks = iterate.cut(pagerank.pagerank(edges, iters=iters))
    took = time.monotonic() - began
    yield {"pages": ranks.count(), "links": edges.count(), "iters": iters, "seconds": round(took, 1), "steps_an_hour": round(measures.iterations_per_hour(iters, took)), "mass": pagerank.rank_mass(ranks), "agreement_with_in_links": pagerank.rank_inlink_agreement(ranks, edges)}


def _figures(pred: DataFrame) -> dict:
    r = measures.accuracy(pred).first()
    return {"test": r["rows"], "right": r["right"], "accuracy": round(r["accuracy"], 3), "balanced": round(r["balanced"], 3), "majority": round(r["majority"], 3)}


def _counted(guess: np.ndarray, truth: np.ndarray) -> dict:
    ok = guess == truth
    share = [float(ok[truth == s].mean()) if (truth == s).any() else 0.0 for s in (True, False)]
    return {"test": len(ok), "right": int(ok.sum()), "accuracy": round(float(ok.mean()), 3), "balanced": round(sum(share) / 2, 3), "majority": round(float(max(truth.mean(), 1 - truth.mean())), 3)}


def _seconds(t: dict[str, float]) -> dict[str, float]:
    return {k: round(v, 2) for k, v in t.items()}


def _warm(spark: SparkSession) -> None:
    a, b = _pair(spark, 64, 0.25)
    measures.timed(lambda: tiled_product(a, b, _grid(64, (2, 2, 2)), "row").df)


def session(cores: int, partitions: int | None = None) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(partitions or cores)).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.sql.warehouse.dir", "/tmp/tilealg_experiments").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main(names: list[str]) -> None:
    for name in names or list(EXPERIMENTS):
        spark = session(int(os.environ.get("BENCH_CPUS", "8")))
        for row in EXPERIMENTS[name](spark):
            print(json.dumps({"experiment": name, **row}), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])

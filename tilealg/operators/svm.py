"""Dual support vector machine by gradient ascent, a product with the kernel in each step.

Labels y are -1 or 1.  The bias is fixed: it adds bias^2 to every kernel value, like a constant feature.
Materialised mode keeps K = T T^T; implicit mode multiplies T (T^T D) and never stores the quadratic kernel.
"""

from __future__ import annotations

import time
import warnings
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells
from tilealg.operators.iterate import cut, forget, run
from tilealg.operators.product import broadcast_product, matvec
from tilealg.operators.similarity import gram_rows


#: Cells of a kernel that is stored.
MOST_KERNEL = 2_000_000_000


def linear_kernel(t: Cells, bias: float = 0.0, most_cells: int = MOST_KERNEL, **how) -> Cells:
    """T T^T + bias^2; with a bias all cells are stored, and more than ``most_cells`` of them is an error."""
    k = gram_rows(t, half=True, **how)
    if not bias:
        return k
    if t.rows**2 > most_cells:
        raise ValueError(f"a kernel of {t.rows} rows with a bias has no empty cells; use the implicit mode")
    ids = t.spark.range(t.rows).select(F.col("id").alias("i"))
    grid = ids.crossJoin(ids.withColumnRenamed("i", "j"))
    return k.with_df(grid.join(k.df, ["i", "j"], "left").select("i", "j", (F.coalesce("v", F.lit(0.0)) + bias * bias).alias("v")))


def svm_gradient(k: Cells, y: DataFrame, alpha: DataFrame, form: str = "elementwise", most_rows: int = 4_000_000) -> DataFrame:
    """(i, v): 1 - y_i sum_j y_j alpha_j K_ij.  y and alpha are (i, v).

    elementwise: one join of kernel cells with the signed weights; vector: -y * (D K) + 1 as vector operations.
    Weights of more than ``most_rows`` rows of the kernel (256 MB as a hash table) are not broadcast; they and the cells
    are exchanged.
    """
    signed = y.withColumnRenamed("v", "y").join(alpha, "i").select("i", (F.col("y") * F.col("v")).alias("v"))
    if form == "elementwise":
        d = signed.select(F.col("i").alias("j"), F.col("v").alias("d"))
        d = F.broadcast(d) if k.rows <= most_rows else d
        dots = k.df.join(d, "j").groupBy("i").agg(F.sum(F.col("v") * F.col("d")).alias("w"))
    else:
        dots = matvec(k.t, signed).withColumnRenamed("v", "w")
    return y.join(dots, "i", "left").select("i", (1 - F.col("v") * F.coalesce("w", F.lit(0.0))).alias("v"))


def svm_gradient_implicit(t: Cells, y: DataFrame, alpha: DataFrame, bias: float = 0.0) -> DataFrame:
    """``svm_gradient`` for the kernel of T, through T (T^T D): work grows with the cells of T, and no kernel is made."""
    signed = y.withColumnRenamed("v", "y").join(alpha, "i").select("i", (F.col("y") * F.col("v")).alias("v"))
    through = matvec(t, matvec(t.t, signed)).withColumnRenamed("v", "w")
    level = signed.agg((F.coalesce(F.sum("v"), F.lit(0.0)) * bias * bias).alias("b"))
    return y.join(through, "i", "left").crossJoin(F.broadcast(level)).select("i", (1 - F.col("v") * (F.coalesce("w", F.lit(0.0)) + F.col("b"))).alias("v"))


def svm_dual_objective(k: Cells, y: DataFrame, alpha: DataFrame) -> float:
    """Sum of alpha less half of the quadratic form."""
    slope = svm_gradient(k, y, alpha).withColumnRenamed("v", "g")
    return alpha.join(slope, "i").agg(F.sum(F.col("v") - 0.5 * F.col("v") * (1 - F.col("g")))).first()[0]


def boxed(value, box: str, c: float):
    """``soft`` holds weights within 0 and C, ``hard`` at 0 or above, ``none`` leaves the plain step."""
    if box == "soft":
        return F.greatest(F.lit(0.0), F.least(F.lit(float(c)), value))
    if box == "hard":
        return F.greatest(F.lit(0.0), value)
    if box != "none":
        raise ValueError("box is soft, hard or none")
    return value


@dataclass
class SvmModel:
    alpha: DataFrame
    y: DataFrame
    train: Cells
    bias: float
    iteration_seconds: list[float] = field(default_factory=list)
    objective: list[float] = field(default_factory=list)

    def primal(self) -> DataFrame:
        """(i, v): T^T (y * alpha) by feature."""
        signed = self.y.withColumnRenamed("v", "y").join(self.alpha, "i").select("i", (F.col("y") * F.col("v")).alias("v"))
        return matvec(self.train.t, signed)


def svm_fit(t: Cells, y: DataFrame, c: float = 1.0, bias: float = 1.0, eta: float = 0.01, iters: int = 20, box: str = "soft", kernel_mode: str = "implicit", trace: bool = False) -> SvmModel:
    """A fixed number of steps from alpha = 0.  All labelled rows take part, rows of T without cells too."""
    y = cut(y.select("i", "v"))
    alpha = y.select("i", F.lit(0.0).alias("v"))
    kernel = None
    if kernel_mode == "materialised" and bias and t.rows**2 > MOST_KERNEL:
        # As linear_kernel advises: the steps are the same.
        warnings.warn(f"a kernel of {t.rows} rows with a bias has no empty cells and isn't stored; steps go through the features", stacklevel=2)
    elif kernel_mode == "materialised":
        kernel = Cells(cut(linear_kernel(t, bias).df), t.rows, t.rows)
    elif kernel_mode != "implicit":
        raise ValueError("kernel_mode is materialised or implicit")
    model = SvmModel(alpha, y, t, bias)
    # Labels travel with the weights, so that a step joins its state once.
    state = cut(y.select("i", F.col("v").alias("y"), F.lit(0.0).alias("v")))
    for _ in range(iters):
        began = time.monotonic()
        if kernel is not None:
            slope = svm_gradient(kernel, y, state.select("i", "v"))
            after = state.join(slope.withColumnRenamed("v", "g"), "i")
        else:
            signed = state.select("i", (F.col("y") * F.col("v")).alias("v"))
            through = matvec(t, matvec(t.t, signed)).withColumnRenamed("v", "w")
            level = signed.agg((F.coalesce(F.sum("v"), F.lit(0.0)) * bias * bias).alias("b"))
            after = state.join(through, "i", "left").crossJoin(F.broadcast(level)).withColumn("g", 1 - F.col("y") * (F.coalesce("w", F.lit(0.0)) + F.col("b")))
        after = cut(after.select("i", "y", boxed(F.col("v") + eta * F.col("g"), box, c).alias("v")))
        forget(state)
        state = after
        model.iteration_seconds.append(time.monotonic() - began)
        if trace and kernel is not None:
            model.objective.append(svm_dual_objective(kernel, y, state.select("i", "v")))
    model.alpha = state.select("i", "v")
    return model


def kernel_step(t: Cells, rows: DataFrame, bias: float = 0.0, iters: int = 6) -> float:
    """1 over the kernel's largest eigenvalue, by the power method through T (T^T x) from all ones; rows is (i)."""
    x = cut(rows.select("i", F.lit(1.0).alias("v")))
    for r in range(iters + 1):
        through = matvec(t, matvec(t.t, x)).withColumnRenamed("v", "w")
        total = x.agg(F.coalesce(F.sum("v"), F.lit(0.0)).alias("b"))
        y = cut(x.join(through, "i", "left").crossJoin(F.broadcast(total)).select("i", F.col("v").alias("x"), (F.coalesce("w", F.lit(0.0)) + bias * bias * F.col("b")).alias("v")))
        top, size, whole = y.agg(F.sum(F.col("x") * F.col("v")), F.sum(F.col("x") * F.col("x")), F.sum(F.abs("v"))).first()
        x = y.select("i", (F.col("v") / (whole or 1.0)).alias("v"))
    return size / top if top else 1.0


def svm_predict(model: SvmModel, x: Cells) -> DataFrame:
    """(i, margin, label) for each row of X, through the feature weights; a margin of 0 counts as 1."""
    w = cut(model.primal())
    level = model.y.withColumnRenamed("v", "y").join(model.alpha, "i").agg(F.sum(F.col("y") * F.col("v"))).first()[0] or 0.0
    ids = x.spark.range(x.rows).select(F.col("id").alias("i"))
    margin = F.coalesce("v", F.lit(0.0)) + level * model.bias**2
    return ids.join(matvec(x, w), "i", "left").select("i", margin.alias("margin")).withColumn("label", F.when(F.col("margin") >= 0, 1).otherwise(-1))


@dataclass
class OneAgainstRest:
    """Weights alpha (i, j, v) of every row and class, side by side; names[j] is class j."""

    names: list
    alpha: DataFrame
    classes: DataFrame
    train: Cells
    bias: float

    def signed(self) -> DataFrame:
        """(i, j, v): y * alpha."""
        return _signed(self.alpha, self.classes)


def _signed(alpha: DataFrame, classes: DataFrame) -> DataFrame:
    return alpha.join(classes, "i").select("i", "j", F.when(F.col("class") == F.col("j"), F.col("v")).otherwise(-F.col("v")).alias("v"))


def svm_fit_ovr(t: Cells, classes: DataFrame, names: list, c: float = 1.0, bias: float = 1.0, eta: float = 0.01, iters: int = 20, box: str = "soft", kernel_mode: str = "implicit") -> OneAgainstRest:
    """All classes against their rests in one loop; ``classes`` is (i, name).

    alpha has a column for each class, so a step is one product with the kernel (or with T and T^T), which all classes
    share.  Steps start from alpha = 0.
    """
    spark = t.spark
    place = spark.createDataFrame([(n, j) for j, n in enumerate(names)], "name string, class long")
    classes = cut(classes.join(F.broadcast(place), "name").select("i", "class"))
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(len(names) - 1).cast("long"))).alias("j")
    alpha = classes.select("i", every, F.lit(0.0).alias("v"))
    kernel = Cells(cut(linear_kernel(t, bias).df), t.rows, t.rows) if kernel_mode == "materialised" else None

    def step(alpha: DataFrame) -> DataFrame:
        signed = _signed(alpha, classes)
        d = Cells(signed, t.rows, len(names))
        through = broadcast_product(kernel, d) if kernel is not None else broadcast_product(t, broadcast_product(t.t, d))
        slope = alpha.join(through.df.withColumnRenamed("v", "w"), ["i", "j"], "left").join(classes, "i")
        pull = F.coalesce("w", F.lit(0.0))
        if kernel is None:
            level = signed.groupBy("j").agg((F.sum("v") * bias * bias).alias("b"))
            slope, pull = slope.join(F.broadcast(level), "j"), pull + F.col("b")
        sign = F.when(F.col("class") == F.col("j"), 1.0).otherwise(-1.0)
        return slope.select("i", "j", boxed(F.col("v") + eta * (1 - sign * pull), box, c).alias("v"))

    return OneAgainstRest(names, run(step, alpha, iters), classes, t, bias)


def svm_predict_ovr(model: OneAgainstRest, x: Cells) -> DataFrame:
    """(i, name): the class with the largest margin, the first by name among equals."""
    signed = model.signed()
    weights = broadcast_product(model.train.t, Cells(signed, model.train.rows, len(model.names)))
    level = signed.groupBy("j").agg((F.sum("v") * model.bias**2).alias("b"))
    names = x.spark.createDataFrame([(j, str(n)) for j, n in enumerate(model.names)], "j long, name string")
    grid = x.spark.range(x.rows).select(F.col("id").alias("i")).crossJoin(F.broadcast(names.join(level, "j")))
    scored = grid.join(broadcast_product(x, Cells(cut(weights.df), x.cols, len(model.names))).df, ["i", "j"], "left").withColumn("margin", F.coalesce("v", F.lit(0.0)) + F.col("b"))
    return scored.groupBy("i").agg(F.min_by("name", F.struct(-F.col("margin"), F.col("name"))).alias("name"))

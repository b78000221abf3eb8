"""Page ranks by the power method, and what is read off their distribution."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilealg.operators.iterate import cut, l1, run
from tilealg.operators.product import workers_of


def transition(edges: DataFrame, weighted: bool = False, dedup: bool = True, self_loops: str = "keep") -> DataFrame:
    """(src, dst, p): the share of a page's links that go to each other page.

    edges: (src, dst) or (src, dst, w).  dedup: a repeated link counts once (its weights add up if weighted).
    """
    if self_loops == "drop":
        edges = edges.where("src <> dst")
    w = F.col("w").cast("double") if weighted else F.lit(1.0)
    links = edges.select("src", "dst", w.alias("w"))
    if weighted:
        links = links.groupBy("src", "dst").agg(F.sum("w").alias("w"))
    elif dedup:
        links = links.distinct()
    else:
        links = links.groupBy("src", "dst").agg(F.sum("w").alias("w"))
    out = links.groupBy("src").agg(F.sum("w").alias("out"))
    return links.join(out, "src").select("src", "dst", (F.col("w") / F.col("out")).alias("p"))


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id"))).distinct()


def pagerank(edges: DataFrame, nodes: DataFrame | None = None, d: float | None = 0.85, iters: int = 100, tol: float | None = None, dangling: str = "uniform", weighted: bool = False, dedup: bool = True, self_loops: str = "keep", trace: list | None = None, parts: int | None = None) -> DataFrame:
    """(id, r) after ``iters`` steps from the uniform vector.  d=None is the plain power method.

    dangling: pages without links give their rank to all pages (``uniform``: ranks sum to 1), to nobody (``drop``),
    or keep it (``self``).  Links are dealt over ``parts`` by their source once, pages and ranks by their id alike, so a
    step only exchanges what pages send to each other, combined before it is sent, and one number for dangling pages.
    """
    if dangling not in ("uniform", "drop", "self"):
        raise ValueError("dangling is uniform, drop or self")
    spark = edges.sparkSession
    parts = parts or workers_of(spark)
    shares = transition(edges, weighted, dedup, self_loops)
    p = cut(shares.select("src", "dst", "p").repartition(parts, "src"))
    ids = (nodes if nodes is not None else nodes_of(edges)).select("id").distinct()
    known = ids.join(p.select(F.col("src").alias("id")).distinct().withColumn("links", F.lit(True)), "id", "left")
    nodes = cut(known.repartition(parts, "id"))
    n = nodes.count()
    ranks = nodes.select(F.col("id").alias("i"), F.lit(1.0 / max(n, 1)).alias("v"), "links")

    def step(r: DataFrame) -> DataFrame:
        sent = p.join(r, p.src == r.i).select(F.col("dst").alias("to"), (F.col("p") * F.col("v")).alias("got"))
        got = sent.groupBy("to").agg(F.sum("got").alias("got")).repartition(parts, "to")
        base = r.join(got, r.i == F.col("to"), "left").select("i", "v", "links", F.coalesce("got", F.lit(0.0)).alias("got"))
        if dangling == "self":
            base = base.withColumn("got", F.col("got") + F.when(F.col("links").isNull(), F.col("v")).otherwise(0.0))
        if dangling == "uniform":
            lost = r.where("links is null").agg((F.coalesce(F.sum("v"), F.lit(0.0)) / n).alias("lost"))
            base = base.crossJoin(F.broadcast(lost)).withColumn("got", F.col("got") + F.col("lost"))
        new = F.col("got") if d is None else (1 - d) / n + d * F.col("got")
        return base.select("i", new.alias("v"), "links")

    return run(step, ranks, iters, l1, tol, trace).select(F.col("i").alias("id"), F.col("v").alias("r"))


def in_links(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").distinct().groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("in_links"))


def rank_report(ranks: DataFrame, edges: DataFrame, k: int = 10, inlink_cut: int = 100) -> DataFrame:
    """(place, id, r, in_links, in_cut): the k highest ranks; in_cut: among the ``inlink_cut`` pages with most links in."""
    links = in_links(edges)
    edge = links.orderBy(F.desc("in_links"), "id").limit(inlink_cut).agg(F.min("in_links").alias("edge"))
    best = ranks.orderBy(F.desc("r"), "id").limit(k).join(links, "id", "left").crossJoin(F.broadcast(edge))
    counted = best.select("id", "r", F.coalesce("in_links", F.lit(0)).cast("long").alias("in_links"), (F.coalesce("in_links", F.lit(0)) >= F.col("edge")).alias("in_cut"))
    return counted.withColumn("place", F.row_number().over(Window.orderBy(F.desc("r"), "id")).cast("long"))


def _placed(ranks: DataFrame) -> DataFrame:
    """Place by falling rank: ranges are counted apart and shifted, so no task holds all pages."""
    ranged = cut(ranks.select("id", "r").repartitionByRange(F.desc("r"), "id").withColumn("part", F.spark_partition_id()))
    before = ranged.groupBy("part").count().withColumn("first", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return ranged.join(F.broadcast(before.select("part", "first")), "part").select("id", "r", (F.row_number().over(Window.partitionBy("part").orderBy(F.desc("r"), "id")) + F.col("first")).cast("long").alias("place"))


def rank_curve(ranks: DataFrame) -> DataFrame:
    """(place, id, r, ln_place, ln_r); the logarithm of a rank of 0 is null."""
    return _placed(ranks).select("place", "id", "r", F.ln("place").alias("ln_place"), F.ln(F.when(F.col("r") > 0, F.col("r"))).alias("ln_r"))


def loglog_slope(curve: DataFrame) -> float:
    return curve.agg(F.regr_slope("ln_r", "ln_place")).first()[0]


def normal_quantile(p):
    """Quantile of the normal distribution for a probability column, to about 1e-9, by a published rational
    approximation with the constants below."""
    # Coefficients of a published rational approximation (central part, then tails).
    a = (-3.969683028665376e1, 2.209460984245205e2, -2.759285104469687e2, 1.383577518672690e2, -3.066479806614716e1, 2.506628277459239)
    b = (-5.447609879822406e1, 1.615858368580409e2, -1.556989798598866e2, 6.680131188771972e1, -1.328068155288572e1, 1.0)
    c = (-7.784894002430293e-3, -3.223964580411365e-1, -2.400758277161838, -2.549732539343734, 4.374664141464968, 2.938163982698783)
    d = (7.784695709041462e-3, 3.224671290700398e-1, 2.445134137142996, 3.754408661907416, 1.0)

    def poly(k, x):
        out = F.lit(k[0])
        for y in k[1:]:
            out = out * x + y
        return out

    tail = F.sqrt(-2 * F.ln(F.least(p, 1 - p)))
    far = poly(c, tail) / poly(d, tail)
    q = p - 0.5
    return F.when(F.least(p, 1 - p) < 0.02425, F.when(p < 0.5, far).otherwise(-far)).otherwise(poly(a, q * q) * q / poly(b, q * q))


def lognormal_plot(ranks: DataFrame) -> DataFrame:
    """(id, ln_r, z): logarithms against normal quantiles of their places; a straight line means lognormal ranks."""
    placed = _placed(ranks.where("r > 0"))
    n = placed.count()
    return placed.select("id", F.ln("r").alias("ln_r"), normal_quantile((n - F.col("place") + 0.5) / F.lit(float(n))).alias("z"))


def straightness(plot: DataFrame) -> float:
    return plot.agg(F.corr("ln_r", "z")).first()[0]


def tail_plateau(ranks: DataFrame, decimals: int = 12) -> DataFrame:
    """(r, pages): how many pages share each rank, for the smallest rank."""
    groups = ranks.groupBy(F.round("r", decimals).alias("r")).agg(F.count(F.lit(1)).alias("pages"))
    return groups.orderBy("r").limit(1)


def low_rank_group(ranks: DataFrame, least: float) -> DataFrame:
    """(pages, mass): pages under a rank."""
    return ranks.where(F.col("r") < least).agg(F.count(F.lit(1)).alias("pages"), F.coalesce(F.sum("r"), F.lit(0.0)).alias("mass"))


def rank_mass(ranks: DataFrame) -> float:
    return ranks.agg(F.sum("r")).first()[0]


def rank_inlink_agreement(ranks: DataFrame, edges: DataFrame, k: int = 100) -> float | None:
    """Rank correlation of ranks and links in among the k highest ranks."""
    best = ranks.orderBy(F.desc("r"), "id").limit(k).join(in_links(edges), "id", "left").fillna(0, ["in_links"])
    placed = best.select(F.rank().over(Window.orderBy("r")).alias("a"), F.rank().over(Window.orderBy("in_links")).alias("b"))
    return placed.agg(F.corr("a", "b")).first()[0]

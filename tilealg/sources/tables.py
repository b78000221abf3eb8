"""Matrices, graphs and training sets from the given tables, and matrices from files."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells
from tilealg.workers import shipped

shipped(__name__)

#: Names that are sent to all workers at most.
MOST_NAMES = 1 << 20

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def _ordered_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    return lines.join(load(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


def _count(spark: SparkSession, sf_dir: str, name: str) -> int:
    return load(spark, sf_dir, name).count()


def cust_part(spark: SparkSession, sf_dir: str) -> Cells:
    """Quantity of each part by customer; whole numbers."""
    loose = _ordered_lines(spark, sf_dir).select(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j"), F.col("l_quantity").cast("double").alias("v"))
    df = loose.groupBy("i", "j").agg(F.sum("v").cast("long").alias("v"))
    return Cells(df, _count(spark, sf_dir, "customer"), _count(spark, sf_dir, "part"), _count(spark, sf_dir, "lineitem"), loose)


def supp_part(spark: SparkSession, sf_dir: str) -> Cells:
    """Lines of each part by supplier."""
    keys = load(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey").select(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("j"))
    df = keys.groupBy("i", "j").agg(F.count(F.lit(1)).alias("v"))
    return Cells(df, _count(spark, sf_dir, "supplier"), _count(spark, sf_dir, "part"), _count(spark, sf_dir, "lineitem"), keys.withColumn("v", F.lit(1.0)))


def order_part(spark: SparkSession, sf_dir: str) -> Cells:
    df = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity").groupBy(F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j")).agg(F.sum("l_quantity").cast("long").alias("v"))
    return Cells(df, _count(spark, sf_dir, "orders"), _count(spark, sf_dir, "part"), _count(spark, sf_dir, "lineitem"))


def user_event(spark: SparkSession, sf_dir: str) -> Cells:
    """Events by user and kind; kinds are numbered by name (there are a handful)."""
    events = load(spark, sf_dir, "events", "user_id", "event_type")
    kinds = events.select("event_type").distinct().withColumn("j", (F.row_number().over(Window.orderBy("event_type")) - 1).cast("long"))
    return Cells.of(events.join(F.broadcast(kinds), "event_type").groupBy(F.col("user_id").alias("i"), "j").agg(F.count(F.lit(1)).alias("v")))


def embed_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("i"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), "label")


def embed_cells(spark: SparkSession, sf_dir: str) -> Cells:
    rows = embed_rows(spark, sf_dir)
    return Cells.of(rows.select("i", F.posexplode("vec").alias("j", "v")).withColumn("j", F.col("j").cast("long")))


def term_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, term, tf) over words of ASCII letters."""
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    words = F.regexp_extract_all(F.translate("text", UPPER, LOWER), F.lit("[a-z]+"), F.lit(0))
    return docs.select("doc_id", F.explode(words).alias("term")).groupBy("doc_id", "term").agg(F.count(F.lit(1)).alias("tf"))


#: Bytes to lower-case letters, all others to spaces.
LETTERS = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 else 32 for c in range(256))


def _terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            found = [Counter((text or b"").translate(LETTERS).split()) for text in part.column("text").cast(pa.binary()).to_pylist()]
            owner = pa.array([k for k, c in enumerate(found) for _ in c], pa.int64())
            yield pa.RecordBatch.from_arrays([part.column("doc_id").take(owner), pa.array([w for c in found for w in c], pa.binary()).cast(pa.string()), pa.array([n for c in found for n in c.values()], pa.int64())], ["doc_id", "term", "tf"])


def local_term_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``term_counts`` without an exchange of words, as long as no two documents have one id."""
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    if not docs.groupBy("doc_id").count().where("count > 1").isEmpty():
        return term_counts(spark, sf_dir)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_terms, "doc_id long, term string, tf long")


def vocabulary(counts: DataFrame, least_docs: int = 5) -> DataFrame:
    """(term, df) of terms in enough documents."""
    return counts.groupBy("term").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") >= least_docs)


def doc_term(spark: SparkSession, sf_dir: str, least_docs: int = 5, normalise: bool = False, local: bool = False) -> tuple[Cells, DataFrame]:
    """Counts of terms by document, rows by doc_id, and the dictionary (key, idx).  local: words are counted in Python where
    their documents are read, and the cells carry their number."""
    from tilealg.operators.cells import dictionary
    from tilealg.operators.iterate import cut

    counts = (local_term_counts if local else term_counts)(spark, sf_dir)
    kept = vocabulary(counts, least_docs)
    kept = cut(kept) if local else kept
    names = dictionary(kept, "term")
    many = names.count()
    df = counts.join(F.broadcast(names) if local and many <= MOST_NAMES else names, counts.term == names.key).select(F.col("doc_id").alias("i"), F.col("idx").alias("j"), F.col("tf").alias("v"))
    if normalise:
        size = df.groupBy("i").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("n"))
        df = df.join(size, "i").select("i", "j", (F.col("v") / F.col("n")).alias("v"))
    top = load(spark, sf_dir, "documents", "doc_id").agg(F.max("doc_id")).first()[0]
    most = (kept.agg(F.sum("df")).first()[0] or 0) if local else None
    return Cells(df, (top if top is not None else -1) + 1, many, most), names


def part_next(spark: SparkSession, sf_dir: str, loops: bool = False) -> DataFrame:
    """(src, dst): the next part in the same order."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    out = lines.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst")).where("dst is not null").distinct()
    return out if loops else out.where("src <> dst")


def hrefs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, host, path, href)"""
    pages = load(spark, sf_dir, "pages")
    host, path = F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1), F.regexp_extract("url", "^[a-z]+://[^/?#]+([^?#]*)", 1)
    return pages.select("page_id", host.alias("host"), path.alias("path"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("href"))


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hrefs(spark, sf_dir).select(F.concat("host", "path").alias("src"), F.concat("host", "href").alias("dst")).distinct()


def path_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hrefs(spark, sf_dir).select(F.col("page_id").cast("string").alias("src"), F.col("href").alias("dst")).distinct()


def event_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, w): kinds of consecutive events of a user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    events = load(spark, sf_dir, "events", "user_id", "ts", "event_id", "event_type")
    return events.select(F.col("event_type").alias("src"), F.lead("event_type").over(w).alias("dst")).where("dst is not null").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))


def nation_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, w): lines from a customer's nation to a supplier's."""
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey").join(load(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    lines = lines.join(load(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return lines.groupBy(F.col("c_nationkey").alias("src"), F.col("s_nationkey").alias("dst")).agg(F.count(F.lit(1)).alias("w"))


def user_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, w): users of consecutive events of all users.

    The order is global, so ranges of time are numbered apart; only their last events cross over.
    """
    events = load(spark, sf_dir, "events", "event_id", "ts", "user_id").repartitionByRange("ts", "event_id").withColumn("part", F.spark_partition_id())
    w = Window.partitionBy("part").orderBy("ts", "event_id")
    inside = events.select("part", "user_id", F.lead("user_id").over(w).alias("next"))
    edge = events.groupBy("part").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    across = edge.select(F.col("last").alias("user_id"), F.lead("first").over(Window.orderBy("part")).alias("next"))
    pairs = inside.select("user_id", "next").union(across).where("next is not null")
    return pairs.groupBy(F.col("user_id").alias("src"), F.col("next").alias("dst")).agg(F.count(F.lit(1)).alias("w"))


def labelled(spark: SparkSession, sf_dir: str, task: str) -> DataFrame:
    """(i, y, is_test): documents with a label; every fifth by doc_id is for testing.

    Tasks: language (English or not), quality, toxic; all over the documents that ``labels`` covers.
    """
    docs = load(spark, sf_dir, "documents", "doc_id", "lang").join(load(spark, sf_dir, "labels"), "doc_id")
    yes = {"language": F.col("lang") == "en", "quality": F.col("quality") == 1, "toxic": F.col("toxic") == 1}[task]
    ranked = docs.select(F.col("doc_id").alias("i"), F.when(yes, 1.0).otherwise(-1.0).alias("y"))
    numbered = ranked.repartitionByRange("i").withColumn("part", F.spark_partition_id())
    before = numbered.groupBy("part").count().withColumn("first", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    placed = numbered.join(F.broadcast(before), "part").withColumn("at", F.row_number().over(Window.partitionBy("part").orderBy("i")) - 1 + F.col("first"))
    return placed.select("i", "y", (F.col("at") % 5 == 0).alias("is_test"))


def read_cells(spark: SparkSession, path: str, form: str = "parquet") -> Cells:
    """Cells from parquet, orc, json or csv files with columns i, j, v (csv without a header, in this order)."""
    if form == "csv":
        df = spark.read.schema("i long, j long, v double").csv(path)
    elif form == "json":
        df = spark.read.schema("i long, j long, v double").json(path)
    else:
        df = spark.read.format(form).load(path)
    return Cells.of(df)


def write_cells(a: Cells, path: str, form: str = "parquet", mode: str = "overwrite") -> None:
    a.df.write.mode(mode).format(form).save(path)


def write_tiles(tiles: DataFrame, table: str, buckets: int) -> None:
    """Tiles as a table bucketed by their row, so that later products of one layout join without an exchange."""
    tiles.write.mode("overwrite").bucketBy(buckets, "bi").sortBy("bi").format("parquet").saveAsTable(table)

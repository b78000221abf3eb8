"""Training-data pipeline: quality, near copies, benchmark passages, personal data, tokens.

Every stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept.  All stages but the last return
the columns of documents.  Documents without a doc_id stay, as do those that share one but not the text.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilealg.llm import byte_pairs, near_copies, private_data, quality, shard_index
from tilealg.llm.lineage import cut
from tilealg.llm.queries import _vocabulary


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality scorer accepts."""
    return quality.good_documents(docs)


def keyed_rows(docs: DataFrame) -> DataFrame:
    """``docs`` with a key for each distinct id and text: the id for one text of each id, else a hash above 2^62."""
    own = F.xxhash64("doc_id", "text")
    shared = cut(docs.where("doc_id is not null").groupBy("doc_id").agg(F.min(own).alias("__first"), F.max(own).alias("__last")).where("__first <> __last").select("doc_id", "__first"))
    hashed = own.bitwiseAND(F.lit((1 << 62) - 1)) + F.lit(1 << 62)
    if shared.isEmpty():
        return docs.select(*docs.columns, F.coalesce(F.col("doc_id").cast("long"), hashed).alias("__key"))
    plain = F.col("doc_id").isNotNull() & (F.col("__first").isNull() | (F.col("__first") == own))
    return cut(docs.join(shared, "doc_id", "left").select(*docs.columns, F.when(plain, F.col("doc_id").cast("long")).otherwise(hashed).alias("__key")))


def keep_one_copy(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near copies; repeated rows of it become one.

    Documents without an id, or with one that another text goes by, are told apart by keys of their own.
    """
    keyed = keyed_rows(docs)
    gone = near_copies.near_copies(keyed.select(F.col("__key").alias("doc_id"), "text")).where("not kept").select(F.col("doc_id").alias("__key")).distinct()
    return keyed.join(gone, "__key", "left_anti").dropDuplicates(["__key"]).select(docs.columns)


def drop_test_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which less than a twentieth of the words stands in benchmark passages."""
    return shard_index.decontaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def hide_private_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with pseudonyms for personal data."""
    return private_data.pseudonymised(docs).select(docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """n_tokens and hashes of the ids, and of the text decoded from them, of every document."""
    return byte_pairs.code_digests(docs, *_vocabulary())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality classifier", keep_good),
    ("near-copy removal", keep_one_copy),
    ("benchmark decontamination", drop_test_passages),
    ("private data", hide_private_data),
    ("byte-pair encoding", encode),
]

#: SQL can't express the quality scorer; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; results between stages are cut off in the checkpoint folder."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = cut(docs)
    return docs

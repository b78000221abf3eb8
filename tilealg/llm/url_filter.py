"""URL filter: a blocked Bloom filter over canonical rules passes possible hits to an exact hash join.

A rule is a host and a path prefix with a verdict; it fits its host, all subdomains of it, and all paths that start
with its path.  A URL's probes are its host's suffixes of as many labels as rules have, crossed with its path's prefixes of
the lengths that rules have: as many as the rules call for, however long the URL is.  The filter keeps one 64-bit block
for each key, all of whose bits lie in it, so a probe reads one word.  Probes that pass go to a hash join with the
rules, which removes false positives; the longest rule wins.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS = 6
PROBED = "page_id long, host string, path string, hits array<string>"


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z in lower case) and path; both empty for null or without ``://``."""
    rest = F.when(F.instr(url, "://") > 0, F.substr(url, F.instr(url, "://") + F.lit(3))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return host, path


def block_and_mask(key: Column, blocks: int) -> tuple[Column, Column]:
    """A key's block and its bits there."""
    bits = [F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(F.shiftright(F.xxhash64(F.lit(1), key), 7 * k), F.lit(64)).cast("int")) for k in range(BITS)]
    mask = bits[0]
    for b in bits[1:]:
        mask = mask.bitwiseOR(b)
    return F.pmod(F.xxhash64(F.lit(2), key), F.lit(blocks)), mask


def bloom(keys: Column, table: DataFrame, most_blocks: int = 1 << 22) -> tuple[np.ndarray, int] | None:
    """The filter's words, 16 bits or more a key.  None if it would pass ``most_blocks`` (32 MB): then all go to the join."""
    n = table.count()
    blocks = 1 << max(6, int(max(1, n) * 16 // 64).bit_length())
    if blocks > most_blocks:
        return None
    block, mask = block_and_mask(keys, blocks)
    rows = table.select(block.alias("block"), mask.alias("mask")).groupBy("block").agg(F.bit_or("mask").alias("mask")).collect()
    words = np.zeros(blocks, np.int64)
    for r in rows:
        words[r["block"]] = r["mask"]
    return words, blocks


def _prober(words, blocks: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        filled = words.value
        for batch in batches:
            block = pc.list_flatten(batch.column("blocks")).to_numpy(zero_copy_only=False)
            mask = pc.list_flatten(batch.column("masks")).to_numpy(zero_copy_only=False)
            passed = (filled[block] & mask) == mask
            owner = pc.list_parent_indices(batch.column("keys")).to_numpy(zero_copy_only=False)
            keys = pc.list_flatten(batch.column("keys")).filter(pa.array(passed))
            offset = np.searchsorted(owner[passed], np.arange(batch.num_rows + 1)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("host"), batch.column("path"), pa.ListArray.from_arrays(pa.array(offset), keys.cast(pa.string()))], ["page_id", "host", "path", "hits"])

    return run


def url_verdicts(pages: DataFrame, rules: DataFrame, unlisted: str = "allow") -> DataFrame:
    """page_id, host, path, rule, verdict for each row of ``pages`` (page_id, url).

    ``rules`` has host, path, verdict; of rules with one host and path the smallest verdict holds, null ones are left
    out.  ``unlisted`` is the verdict of URLs that no rule fits, null and malformed ones among them.  Of fitting rules
    the longest (host and path together) wins, then the one with the longer host.
    """
    context = pages.sparkSession.sparkContext
    rules = rules.where("host is not null and path is not null and verdict is not null").groupBy("host", "path").agg(F.min("verdict").alias("verdict")).withColumn("key", F.concat("host", "path"))
    reach = sorted(r[0] for r in rules.select(F.length("path")).distinct().collect())
    depth = sorted(r[0] for r in rules.select(F.size(F.split("host", r"\."))).distinct().collect())
    url = F.col("url").cast("string")
    host, path = host_and_path(url)
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), host.alias("host"), path.alias("path"))
    labels = F.split("host", r"\.")
    suffixes = F.filter(F.array(*[F.when(F.size(labels) >= n, F.array_join(F.slice(labels, -n, n), ".")) for n in depth] or [F.lit(None).cast("string")]), lambda h: h.isNotNull())
    prefixes = F.filter(F.array(*[F.when(F.length("path") >= n, F.substring("path", 1, n)) for n in reach] or [F.lit(None).cast("string")]), lambda p: p.isNotNull())
    probes = pages.withColumn("keys", F.flatten(F.transform(suffixes, lambda h: F.transform(prefixes, lambda p: F.concat(h, p)))))
    made = bloom(F.col("key"), rules)
    if made is None:
        probed = probes.withColumnRenamed("keys", "hits")
    else:
        words, blocks = made
        # One hash pass in the JVM, one lookup pass in numpy.
        where, bits = F.transform("keys", lambda k: block_and_mask(k, blocks)[0]), F.transform("keys", lambda k: block_and_mask(k, blocks)[1])
        probed = probes.select("page_id", "host", "path", "keys", where.alias("blocks"), bits.alias("masks")).mapInArrow(_prober(context.broadcast(words), blocks), PROBED)
    none = F.lit(None).cast("string")
    missed = probed.where(F.size("hits") == 0).select("page_id", "host", "path", none.alias("rule"), F.lit(unlisted).alias("verdict"))
    hit = probed.where(F.size("hits") > 0).withColumn("row", F.monotonically_increasing_id())
    listed = rules.select(F.col("key").alias("hit"), F.col("host").alias("rule_host"), F.col("path").alias("rule_path"), F.col("verdict").alias("rule_verdict"))
    tried = hit.withColumn("hit", F.explode("hits")).join(listed, "hit", "left")
    fits = F.expr("rule_host is not null and startswith(path, rule_path) and (host = rule_host or endswith(host, concat('.', rule_host)))")
    best = F.max(F.when(fits, F.struct(F.length(F.concat("rule_host", "rule_path")).alias("n"), F.length("rule_host").alias("h"), F.col("hit").alias("rule"), F.col("rule_verdict").alias("verdict"))))
    settled = tried.groupBy("row").agg(F.first("page_id").alias("page_id"), F.first("host").alias("host"), F.first("path").alias("path"), best.alias("best"))
    return missed.union(settled.select("page_id", "host", "path", "best.rule", F.coalesce("best.verdict", F.lit(unlisted)).alias("verdict")))

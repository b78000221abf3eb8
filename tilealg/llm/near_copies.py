"""Near-copy detection: one-permutation hashing, banded buckets, star-shaped candidates, full-set links.

1.  Each document's set of word shingles is hashed to 64 bits.  One permutation serves all bins: the sorted
    hashes fall into equal ranges, and a range's smallest hash is its value.  Empty ranges borrow from another
    range by a fixed random order of their own (optimal densification), so all bins stay independent.
2.  Documents with equal sets form a class, named by a hash of its set; only classes go on, so it makes no difference
    which ids their documents have.
3.  ``bands`` groups of ``rows`` bins are bucket keys.  In every bucket each member is paired with the
    bucket's smallest class only: the candidates grow with the documents, not with the squares of groups.
4.  Star pairs are confirmed on the full sets.  Members of one bucket that star pairs leave in different
    components are compared in blocks of bounded size, so that no link between their classes is lost; pairs
    inside one component are not compared again.
5.  Components are found by repeated smallest-neighbour stars, each round written to the checkpoint folder.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilealg.llm.bytewords import ODD, SPACED, Words, mix, text_blocks, windows
from tilealg.llm.lineage import cut

SKETCHED = "doc_id long, n_shingles long, set_hi long, set_lo long, bands array<long>"
BLOCK = 192


def shingle_sets(column: pa.Array, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts, one after the other, and their offsets.

    A text of fewer words than a shingle has its whole word sequence as its only shingle; none if it has no words.
    """
    words = Words(column, SPACED)
    runs = windows(words.hash, size)
    sets = []
    for a, b in zip(words.offset[:-1].tolist(), words.offset[1:].tolist(), strict=True):
        if b - a >= size:
            sets.append(np.unique(runs[a : b - size + 1]))
        elif b > a:
            sets.append(windows(words.hash[a:b], b - a) ^ np.uint64(b - a))
        else:
            sets.append(np.zeros(0, np.uint64))
    offset = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int64)
    return (np.concatenate(sets) if sets else np.zeros(0, np.uint64)), offset


def _borrow_order(bins: int) -> np.ndarray:
    """For each bin a random order of all bins; the same on every machine."""
    return np.random.default_rng(20_011).permuted(np.tile(np.arange(bins), (bins, 1)), axis=1)


def sketch(hashes: np.ndarray, offset: np.ndarray, bins: int, order: np.ndarray) -> np.ndarray:
    """A row of bin values for every set; rows of empty sets are all 0."""
    n = len(offset) - 1
    out, full = np.zeros((n, bins), np.uint64), np.zeros((n, bins), bool)
    owner = np.repeat(np.arange(n), np.diff(offset))
    bin_of = ((hashes >> np.uint64(32)) * np.uint64(bins) >> np.uint64(32)).astype(np.int64)
    place = owner * bins + bin_of
    first = np.flatnonzero(np.diff(place, prepend=-1))
    out.reshape(-1)[place[first]] = hashes[first]
    full.reshape(-1)[place[first]] = True
    row, col = np.nonzero(~full & full.any(axis=1)[:, None])
    for attempt in range(bins):
        if not len(row):
            break
        source = order[col, attempt]
        hit = full[row, source]
        out[row[hit], col[hit]] = out[row[hit], source[hit]]
        row, col = row[~hit], col[~hit]
    return out


def _names(hashes: np.ndarray, offset: np.ndarray) -> list[pa.Array]:
    """Size and two 64-bit sums of every set: equal sets have equal ones."""
    sums = []
    for salt in (np.uint64(0), ODD):
        total = np.concatenate([[np.uint64(0)], np.cumsum(mix(hashes ^ salt))]).astype(np.uint64)
        sums.append(pa.array((total[offset[1:]] - total[offset[:-1]]).view(np.int64)))
    return [pa.array(np.diff(offset)), *sums]


def _sketcher(size: int, bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = _borrow_order(bands * rows)
        salt = mix(np.arange(1, bands + 1, dtype=np.uint64))
        for batch in batches:
            for a, b in text_blocks(batch.column("text")):
                part = batch.slice(a, b - a)
                hashes, offset = shingle_sets(part.column("text"), size)
                values = sketch(hashes, offset, bands * rows, order).reshape(-1, bands, rows)
                keys = np.repeat(salt[None, :], len(values), axis=0)
                for k in range(rows):
                    keys = mix(keys * ODD + values[:, :, k])
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("doc_id"),
                        *_names(hashes, offset),
                        pa.ListArray.from_arrays(pa.array(np.arange(0, (len(values) + 1) * bands, bands), pa.int32()), pa.array(keys.reshape(-1).view(np.int64))),
                    ],
                    ["doc_id", "n_shingles", "set_hi", "set_lo", "bands"],
                )

    return run


def _setter(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in text_blocks(batch.column("text")):
                part = batch.slice(a, b - a)
                hashes, offset = shingle_sets(part.column("text"), size)
                sets = [hashes[i:j].tobytes() for i, j in zip(offset[:-1], offset[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([*_names(hashes, offset), pa.array(sets, pa.binary())], ["n_shingles", "set_hi", "set_lo", "elements"])

    return run


def _linked(shared: np.ndarray, left: np.ndarray, right: np.ndarray, percent: int) -> np.ndarray:
    return 100 * shared >= percent * (left + right - shared)


def _confirm_stars(percent: int):
    """One hub and some of its members: the members that are linked with the hub."""

    def run(table: pa.Table) -> pa.Table:
        ids = table.column("rep").to_numpy()
        hub = table.column("hub")[0].as_py()
        sets = [np.frombuffer(x, np.uint64) for x in table.column("elements").to_pylist()]
        at = int(np.flatnonzero(ids == hub)[0])
        own = sets[at]
        keep = []
        for i, s in enumerate(sets):
            if i != at and len(s) * 100 >= percent * len(own) and len(own) * 100 >= percent * len(s):
                near = np.minimum(np.searchsorted(own, s), max(len(own) - 1, 0))
                if _linked(np.int64((own[near] == s).sum()), np.int64(len(own)), np.int64(len(s)), percent):
                    keep.append(i)
        return pa.table({"src": pa.array(ids[keep], pa.int64()), "dst": pa.array(np.full(len(keep), hub), pa.int64())})

    return run


def _compare_blocks(percent: int):
    """Two blocks of one cluster: a forest of the links between their different parts, as pairs of parts."""

    def run(table: pa.Table) -> pa.Table:
        ids, part, side = (table.column(c).to_numpy() for c in ("rep", "part", "side"))
        sets = [np.frombuffer(x, np.uint64) for x in table.column("elements").to_pylist()]
        size = np.array([len(s) for s in sets], np.int64)
        owner = np.repeat(np.arange(len(sets)), size)
        element = np.concatenate(sets)
        order = np.argsort(element, kind="stable")
        element, owner = element[order], owner[order]
        edge = np.flatnonzero(np.diff(element, prepend=element[0] + np.uint64(1)))
        ends = np.append(edge[1:], len(element))
        n = len(sets)
        shared = np.zeros((n, n), np.int32)
        for a, b in zip(edge[ends - edge > 1].tolist(), ends[ends - edge > 1].tolist(), strict=True):
            who = owner[a:b]
            shared[who[:, None], who[None, :]] += 1
        good = _linked(shared.astype(np.int64), size[:, None], size[None, :], percent)
        two = len(np.unique(side)) == 2
        good &= (part[:, None] != part[None, :]) & ((side[:, None] != side[None, :]) | (not two))
        root = {int(p): int(p) for p in np.unique(part)}

        def find(x: int) -> int:
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        out = []
        for i, j in zip(*np.nonzero(np.triu(good, 1)), strict=True):
            x, y = find(int(part[i])), find(int(part[j]))
            if x != y:
                root[max(x, y)] = min(x, y)
                out.append((int(part[i]), int(part[j])))
        return pa.table({"graph": pa.array([0] * len(out), pa.int32()), "src": pa.array([x for x, _ in out], pa.int64()), "dst": pa.array([y for _, y in out], pa.int64())})

    return run


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(graph, node, component): the smallest node reachable over links (graph, src, dst) of the same graph.

    Nodes without links are not in it.  Several graphs share one run, which costs no more rounds than the deepest
    of them.  Every round sends each node's smallest neighbour to its larger neighbours and, in a second half, ties
    each node to the smallest of the smaller ones.  Rounds stop when the links are stars.
    """
    edges = cut(links.where("src <> dst").select("graph", F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())
    key, seen = ["graph", "a"], None
    turned = lambda d, b: d.select("graph", F.col("b").alias("a"), b.alias("b"))
    for _ in range(most_rounds):
        both = edges.select("graph", "a", "b").union(turned(edges, F.col("a")))
        least = both.groupBy(key).agg(F.least("a", F.min("b")).alias("m"))
        large = turned(both.join(least, key).where("b > a"), F.col("m")).union(least.select("graph", "a", F.col("m").alias("b"))).where("a <> b").distinct()
        down = large.groupBy(key).agg(F.min("b").alias("m"))
        edges = cut(turned(large.join(down, key), F.col("m")).union(down.select("graph", "a", F.col("m").alias("b"))).where("a <> b").distinct())
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("graph", "a", "b").cast("decimal(20,0)"))).first()
        if now == seen or not now[0]:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return edges.select("graph", F.col("a").alias("node"), F.col("b").alias("component")).union(edges.select("graph", F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def near_copies(docs: DataFrame, size: int = 5, percent: int = 85, bands: int = 40, rows: int = 8) -> DataFrame:
    """One row for each row of ``docs`` (doc_id, text): doc_id, n_shingles, component_id, kept.

    Null and blank texts have an empty set, no links, and are their own component.  Equal texts are one component.
    Rows with one doc_id are told apart by their texts: each has the component of its own text.  A row without an id takes
    part if another row with its set has an id; else its component is null.  Other columns are ignored.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    marked = cut(docs.mapInArrow(_sketcher(size, bands, rows), SKETCHED))
    name = F.xxhash64("set_hi", "set_lo", "n_shingles").alias("rep")
    classes = marked.where("n_shingles > 0").groupBy("set_hi", "set_lo", "n_shingles").agg(F.min("doc_id").alias("first_id"), F.first("bands").alias("bands"))
    classes = cut(classes.select("*", name))
    keys = classes.where("first_id is not null").select("rep", F.explode("bands").alias("key"))
    hubs = keys.groupBy("key").agg(F.min("rep").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1").select("key", "hub")
    stars = cut(keys.join(hubs, "key").where("rep <> hub").select("rep", "hub").distinct())
    named = stars.select("rep").union(stars.select("hub")).distinct()
    ids = classes.join(named, "rep", "left_semi").select(F.col("first_id").alias("doc_id")).distinct()
    wanted = docs.join(ids, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"]).select("text")
    sets = cut(wanted.mapInArrow(_setter(size), "n_shingles long, set_hi long, set_lo long, elements binary").select(name, "elements"))
    if sets.select("rep").distinct().count() < sets.count():
        sets = cut(sets.dropDuplicates(["rep"]))

    # Members of a hub are dealt over groups of bounded size; the hub's set goes to each of its groups.
    degree = stars.groupBy("hub").agg(F.count(F.lit(1)).alias("degree"))
    dealt = stars.join(degree, "hub").select("hub", "rep", F.pmod(F.xxhash64("rep"), F.ceil(F.col("degree") / BLOCK)).alias("deal"))
    heads = degree.select("hub", F.col("hub").alias("rep"), F.explode(F.sequence(F.lit(0), F.ceil(F.col("degree") / BLOCK) - 1)).alias("deal"))
    starred = dealt.union(heads).join(sets, "rep").groupBy("hub", "deal").applyInArrow(_confirm_stars(percent), "src long, dst long")
    confirmed = cut(starred)

    # A cluster holds all that buckets connect; parts are what confirmed links connect.
    linked = components(stars.select(F.lit(0).alias("graph"), F.col("rep").alias("src"), F.col("hub").alias("dst")).union(confirmed.select(F.lit(1), "src", "dst")))
    of = lambda graph, name: linked.where(F.col("graph") == graph).select(F.col("node").alias("rep"), F.col("component").alias(name))
    placed = cut(of(0, "cluster").join(of(1, "part"), "rep", "left").withColumn("part", F.coalesce("part", "rep")))
    sizes = placed.groupBy("cluster", "part").agg(F.count(F.lit(1)).alias("size"))
    open_ = sizes.groupBy("cluster").agg(F.count(F.lit(1)).alias("parts"), F.sum(F.when(F.col("size") < BLOCK, F.col("size")).otherwise(0)).alias("small"), F.sum(F.when(F.col("size") < BLOCK, 0).otherwise(F.ceil(F.col("size") / BLOCK))).alias("wide")).where("parts > 1")
    # Small parts share blocks by hash; a part over a block's size has blocks of its own, numbered after them.
    ranks = sizes.where(F.col("size") >= BLOCK).withColumn("before", F.sum(F.ceil(F.col("size") / BLOCK)).over(Window.partitionBy("cluster").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))
    narrow = F.greatest(F.lit(1), F.ceil(F.col("small") / BLOCK))
    blocks = (
        placed.join(open_, "cluster").join(ranks.select("part", F.coalesce("before", F.lit(0)).alias("before"), "size"), "part", "left")
        .withColumn("narrow", narrow)
        .withColumn("block", F.when(F.col("size").isNull(), F.pmod(F.xxhash64("part"), F.col("narrow"))).otherwise(F.col("narrow") + F.col("before") + F.pmod(F.xxhash64("rep"), F.ceil(F.col("size") / BLOCK))))
        .withColumn("n_blocks", F.col("narrow") + F.col("wide"))
        .withColumn("own", F.when(F.col("size").isNull(), F.lit(None).cast("long")).otherwise(F.col("part")))
        .select("cluster", "rep", "part", "block", "n_blocks", "own")
    )
    kinds = blocks.select("cluster", "block", "n_blocks", "own").distinct()
    pairs = (
        kinds.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n_blocks") - 1)))
        .select("cluster", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "own")
    )
    # A pair of blocks that hold one and the same part has nothing left to compare.
    dead = pairs.groupBy("cluster", "lo", "hi").agg(F.count_distinct("own").alias("owns"), F.count("own").alias("owned"), F.count(F.lit(1)).alias("rows")).where("not (owned = rows and owns = 1)").where("rows = 2 or lo = hi").select("cluster", "lo", "hi")
    live = pairs.join(dead, ["cluster", "lo", "hi"]).select("cluster", "lo", "hi", "block").distinct()
    facing = blocks.join(live, ["cluster", "block"]).join(sets, "rep").select("cluster", "lo", "hi", "rep", "part", F.col("block").alias("side"), "elements")
    bridged = cut(facing.groupBy("cluster", "lo", "hi").applyInArrow(_compare_blocks(percent), "graph int, src long, dst long"))

    # Bridges join parts; where there are none, parts are the components.
    found = placed.select("rep", F.col("part").alias("found"))
    if not bridged.isEmpty():
        merged = components(bridged).select(F.col("node").alias("found"), F.col("component").alias("merged"))
        found = found.join(merged, "found", "left").select("rep", F.coalesce("merged", "found").alias("found"))
    members = classes.select("set_hi", "set_lo", "n_shingles", "rep", "first_id").join(found, "rep", "left").withColumn("found", F.coalesce("found", "rep"))
    smallest = members.groupBy("found").agg(F.min("first_id").alias("component_id"))
    members = members.join(smallest, "found").select("set_hi", "set_lo", "n_shingles", "component_id")
    full = marked.where("n_shingles > 0").select("doc_id", "n_shingles", "set_hi", "set_lo").join(members, ["set_hi", "set_lo", "n_shingles"]).select("doc_id", "n_shingles", "component_id")
    bare = marked.where("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return full.union(bare).withColumn("kept", F.expr("doc_id <=> component_id"))

"""The tiled product for operands whose tagged copies would not fit on disk.

Cells meet by inner index first, so a cell is copied only to the tiles where the other operand has that index, once for
each tile; copies travel as packed arrays, and so do the cells of large products before they meet.  Operands with loose rows are summed to cells where they meet, so they need no
exchange of their own before.  A tile is then multiplied in strips of rows, whose sums are kept in memory.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.operators.cells import Cells
from tilealg.operators.grid import TileGrid
from tilealg.workers import shipped

shipped(__name__)

#: Cells that are packed at once, and scalar products and values of a strip.
CHUNK, STRIP = 1 << 20, 1 << 20

#: Cells of a stripe at most, on average: stripes of a coarser grid are cut, so that a task holds two of these.
STRIPE_CELLS = 4 << 20

#: Cells of a stripe of a large product at most, on average; left cells that are multiplied at once; partitions for each
#: of its tiles at most.
DEALT_CELLS, SUB_CELLS, SPARE = 10 << 20, 1 << 20, 8

#: Bytes of the dense blocks of a tile, for the inner indices most cells have; a dense product counts as so many times faster.
BLOCK, FASTER = 64 << 20, 32

#: Rows whose cells are tried as one dense product of the inner indices and columns they meet; it may have so many times
#: the scalar products.
TALL, LOCAL = 2048, 128

#: A dense product in four bytes counts as so many times faster.
FASTEST = 400

WHOLE = ("tinyint", "smallint", "int", "bigint")

BLOCKS = "pid int, bucket int, side int, n int, exact boolean, first long, x0 long, ts binary, xs binary, vs binary"

PIECES = "pid int, alpha int, beta int, part int, side int, n int, first long, x0 long, ts binary, xs binary, vs binary"


def cut_finer(grid: TileGrid, na: int, nb: int, most: int = STRIPE_CELLS) -> TileGrid:
    """The grid with each row and column stripe cut into as many as hold ``most`` cells."""
    more = lambda parts, cells: parts * max(1, -(-cells // (parts * most)))
    return TileGrid.of(grid.a, grid.b, grid.c, more(grid.m, na), grid.n, more(grid.k, nb))


class Dealt(NamedTuple):
    """How tiles of a large product lie: left stripes in so many parts, right stripes as every so-many-th slice of columns,
    and the partition of each tile; and the buckets of inner indices in each partition where cells meet."""

    subs: int
    slice: int
    home: np.ndarray
    buckets: int


def dealt(grid: TileGrid, na: int, nb: int, placement: str, workers: int, least: tuple[int, int] | None = None) -> tuple[TileGrid, Dealt]:
    """Tiles for operands of about ``na`` and ``nb`` cells.  A cell is copied to each stripe of the other operand that has
    its index, in the worst case to all, so stripes of the grid are put together until they hold ``DEALT_CELLS``, or cut if
    they hold more, with enough tiles for the partitions.  Column stripes are dealt slice by slice, as cells near the
    diagonal would else meet in few tiles.  Tiles of a row stripe are neighbours under row placement, else scattered.  least:
    row and column stripes there are at least."""
    least = least or (math.isqrt(max(1, -(-workers // SPARE)) - 1) + 1,) * 2

    def stripes(parts: int, cells: int, least: int) -> int:
        want = max(least, -(-cells // DEALT_CELLS))
        return -(-parts // (parts // want)) if parts > want else parts * -(-want // parts)

    out = TileGrid.of(grid.a, grid.b, grid.c, stripes(grid.m, na, least[0]), grid.n, stripes(grid.k, nb, least[1]))
    alpha, beta = np.divmod(np.arange(out.m * out.k), out.k)
    order = alpha * out.k + beta if placement == "row" else np.lexsort((beta, alpha, _scattered(alpha, beta)))
    home = np.empty(len(order), np.int64)
    home[order] = np.arange(len(order)) % workers
    return out, Dealt(max(1, -(-na // (out.m * SUB_CELLS))), max(1, -(-out.c // (16 * out.k))), home.reshape(out.m, out.k), max(1, -(-(na + nb) // (workers * CHUNK))))


def packed_product(a: Cells, b: Cells, grid: TileGrid, placement: str, workers: int, sizes: tuple[int, int] | None = None) -> Cells:
    """A B.  Under random placement a tile lies in one place, so that its partials need not move.  sizes: the grid is fitted
    to operands of so many cells (``dealt``)."""
    grid, how = dealt(grid, *sizes, placement, workers) if sizes else (grid, None)
    return Cells(_product(*_sides(a, b), grid, placement, workers, False, how), a.rows, b.cols)


def packed_gram(a: Cells, grid: TileGrid, placement: str, workers: int) -> Cells:
    """A A^T from the tiles on and above the diagonal; cells are sent as left and as right operand from one exchange."""
    return Cells(_product(*_sides(a, None), grid, placement, workers, True), a.rows, a.rows)


def packed_chosen(a: Cells, chosen: str, many: int, grid: TileGrid, placement: str, workers: int) -> Cells:
    """A C^T, where C is the rows of A (about ``many`` cells) for which ``chosen`` holds; A is worked out once for both."""
    sides = F.when(F.expr(chosen), F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))
    both = a.df.select(F.col("j").alias("t"), F.explode(sides).alias("side"), F.col("i").alias("x"), "v")
    grid = cut_finer(grid, a.bound(), many)
    return Cells(_product(both, dict(a.df.dtypes)["v"] in WHOLE, False, grid, placement, workers, False), a.rows, a.rows)


def packed_top(a: Cells, b: Cells, grid: TileGrid, k: int, decimals: int | None, skip_self: bool, workers: int) -> DataFrame:
    """(i, j, v): the k largest cells of each row of A B in each tile, those of smaller j among equals; so the k largest of
    the whole row are among them."""

    def best(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        for _, _, left, right in tiles:
            for i, j, v in _strips(left, right, False):
                if skip_self:
                    i, j, v = i[i != j], j[i != j], v[i != j]
                if decimals is not None:
                    v = np.round(v, decimals)
                order = np.lexsort((j, -v, i))
                i, j, v = i[order], j[order], v[order]
                new = np.append(True, i[1:] != i[:-1]) if len(i) else np.zeros(0, bool)
                place = np.arange(len(i)) - np.flatnonzero(new)[np.cumsum(new) - 1] if len(i) else i
                yield _batch(i[place < k], j[place < k], v[place < k])

    return _mapped(*_sides(a, b), grid, "tile", workers, False, best, "i long, j long, v double")


def packed_distances(a: Cells, b: Cells, grid: TileGrid, squared: bool, decimals: int | None, workers: int) -> DataFrame:
    """(i, j, v) from a product A B whose cells are squared distances; halves are rounded away from zero, as by SQL."""

    def far(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        for _, _, left, right in tiles:
            for i, j, v in _strips(left, right, False):
                v = np.maximum(v, 0.0)
                v = v if squared else np.sqrt(v)
                yield _batch(i, j, (v if decimals is None else np.floor(v * 10.0**decimals + 0.5) / 10.0**decimals) + 0.0)

    return _mapped(*_sides(a, b), grid, "tile", workers, False, far, "i long, j long, v double")


def packed_nearest(a: Cells, norms: DataFrame, chosen: str, many: int, k: int, decimals: int | None, skip_self: bool, workers: int) -> DataFrame:
    """(i, j, v): the k largest cosines of each row of A for which ``chosen`` holds (about ``many`` cells) to the rows of A
    in each tile, those of smaller j among equals.  norms: (i, n2) of the rows that count; they travel as cells of one more
    inner index, so cells are sent as the whole numbers they are, and A is worked out once for both sides."""
    tell = a.cols
    every = a.df.select("i", F.col("j").cast("long").alias("j"), F.col("v").cast("long").alias("v")).union(norms.select("i", F.lit(tell).cast("long"), F.col("n2").cast("long")))
    sides = F.when(F.expr(chosen), F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(1)))
    both = every.select(F.col("j").alias("t"), F.explode(sides).alias("side"), F.col("i").alias("x"), "v")
    grid, how = dealt(TileGrid.of(a.rows, a.cols + 1, a.rows), many, a.bound(), "tile", workers, (1, -(-workers // 3)))

    def best(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        for _, _, left, right in tiles:
            for i, j, v in _nearest(left, right, tell, k, decimals, skip_self):
                order = np.lexsort((j, -v, i))
                i, j, v = i[order], j[order], v[order]
                new = _first(i)
                place = np.arange(len(i)) - np.flatnonzero(new)[np.cumsum(new) - 1] if len(i) else i
                yield _batch(i[place < k], j[place < k], v[place < k])

    return _mapped(both, True, False, grid, "tile", workers, False, best, "i long, j long, v double", how=how)


def packed_reach(a: Cells, grid: TileGrid, workers: int) -> DataFrame:
    """(reach, own): cells of A A^T whose larger index is ``reach``, counted in the tiles where they are made."""
    both, whole, loose = _sides(a, None)

    def counted(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        for alpha, beta, left, right in tiles:
            # Rows of a tile above the diagonal come before its columns; a tile on it is whole.
            for cols, own in _reached(left, right, whole, alpha == beta):
                yield pa.RecordBatch.from_arrays([pa.array(cols), pa.array(own)], ["reach", "own"])

    out = _mapped(both, whole, loose, grid, "tile", workers, True, counted, "reach long, own long")
    return out.groupBy("reach").agg(F.sum("own").alias("own"))


def packed_counts(a: Cells, b: Cells, grids: list[tuple[TileGrid, str]], workers: int) -> DataFrame:
    """(at, x, y): for each place ``at`` of a grid and placement, its partial cells, and those at other than their tile's
    worker; under -1 the cells of A and of B.  All from one product, on tiles of its own size."""
    first = grids[0][0]
    grid = cut_finer(TileGrid.of(first.a, first.b, first.c), a.bound(), b.bound())
    specs = [(*(max(1, -(-edge // parts)) for edge, parts in ((g.a, g.m), (g.b, g.n), (g.c, g.k))), g.m, g.n, g.k, p) for g, p in grids]

    def counted(tiles: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        for alpha, _, left, right in tiles:
            if alpha < 0:
                x, y = (sum(int(v[0]) for _, _, v in side) for side in (left, right))
                yield _batch_of((-1, x, y))
                continue
            total = np.zeros((len(specs), 2), np.int64)
            for rows, cols, key, t in _scalars(left, right):
                for s, spec in enumerate(specs):
                    total[s] += _partials(rows, cols, key, t, spec, workers)
            for s, (x, y) in enumerate(total.tolist()):
                yield _batch_of((s, x, y))

    out = _mapped(*_sides(a, b), grid, "tile", workers_of(a.spark), False, counted, "at int, x long, y long", tell=True)
    return out.groupBy("at").agg(F.sum("x").alias("x"), F.sum("y").alias("y"))


def workers_of(spark) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def _batch_of(row: tuple) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip(row, kinds, strict=True)], ["at", "x", "y"])


def _partials(rows: np.ndarray, cols: np.ndarray, key: np.ndarray, t: np.ndarray, spec: tuple, workers: int) -> tuple[int, int]:
    """Partial cells of a strip under one grid, and those made away from their tile's worker."""
    a, b, c, m, n, k, placement = spec
    gamma = np.minimum(t // b, n - 1)
    part = _distinct(key * n + gamma, len(rows) * len(cols) * n)
    if placement != "random":
        return len(part), 0
    cell, gamma = np.divmod(part, n)
    alpha, beta = np.minimum(rows[cell // len(cols)] // a, m - 1), np.minimum(cols[cell % len(cols)] // c, k - 1)
    pid, home = (_pid(alpha, beta, "tile", workers, g) for g in (gamma, 0))
    away = pid != home
    return len(part), len(_distinct(cell[away] * workers + pid[away], len(rows) * len(cols) * workers))


def _distinct(key: np.ndarray, size: int) -> np.ndarray:
    if size > 16 * len(key) + 1:
        return np.unique(key)
    seen = np.zeros(size, bool)
    seen[key] = True
    return np.flatnonzero(seen)


def _sides(a: Cells, b: Cells | None) -> tuple[DataFrame, bool, bool]:
    """Rows (t, side, x, v) of both operands, or of the only one; whether cells are whole numbers, and whether the rows are
    loose: they are if those of both operands are, in one type."""
    both = [m for m in (a, b) if m is not None]
    kind = lambda df: dict(df.dtypes)["v"]
    whole = all(kind(m.df) in WHOLE for m in both)
    loose = all(m.loose is not None for m in both) and len({kind(m.loose) for m in both} | {"double"}) == 1
    out = None
    for side, m in enumerate(both):
        t, x = ("i", "j") if side else ("j", "i")
        own = (m.loose if loose else m.df).select(F.col(t).alias("t"), F.lit(side).alias("side"), F.col(x).alias("x"), "v")
        out = own if out is None else out.union(own)
    return out, whole, loose


def _product(both: DataFrame, whole: bool, loose: bool, grid: TileGrid, placement: str, workers: int, half: bool, how: Dealt | None = None) -> DataFrame:
    return _mapped(both, whole, loose, grid, placement, workers, half, lambda tiles: _multiply(tiles, whole, half), f"i long, j long, v {'long' if whole else 'double'}", how=how)


def _mapped(both: DataFrame, whole: bool, loose: bool, grid: TileGrid, placement: str, workers: int, half: bool, work, schema: str, tell: bool = False, how: Dealt | None = None) -> DataFrame:
    """``work`` on the tiles, from two exchanges.  tell: counts of the operands' cells come as a tile of their own."""
    steps = (max(1, -(-grid.a // grid.m)), max(1, -(-grid.c // grid.k)))
    shape = (grid.m, grid.k, *steps)
    cells = both.select("t", "side", "x", F.col("v").cast("long" if whole and not loose else "double").alias("v")).where("v is not null")
    if how:
        met = cells.where("t is not null").mapInArrow(lambda batches: _sent(batches, workers, how.buckets, whole), BLOCKS).repartitionById(workers, "pid").sortWithinPartitions("bucket")
    else:
        met = cells.repartition(workers, "t").sortWithinPartitions("t")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _pack(_received(batches, whole and not loose) if how else _chunks(batches), shape, placement, workers, half, ("i8" if whole else "f8") if tell else None, (np.int64 if whole else np.float64) if loose else None, how)

    def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return work(_tiles(batches, whole))

    pieces = met.mapInArrow(pack, PIECES).repartitionById(workers, "pid").sortWithinPartitions("alpha", "beta", "part")
    return pieces.mapInArrow(multiply, schema)


def _spread(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For counts (2, 0, 3): owners 0 0 2 2 2 and places 0 1 0 1 2."""
    owner = np.repeat(np.arange(len(counts)), counts)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)


def _narrow(x: np.ndarray) -> np.ndarray:
    """The same whole numbers in as few bytes as hold them."""
    low, high = (int(x.min()), int(x.max())) if len(x) else (0, 0)
    for kind in (np.int8, np.int16, np.int32):
        if np.iinfo(kind).min <= low and high <= np.iinfo(kind).max:
            return x.astype(kind)
    return x.astype(np.int64)


def _raw(x: np.ndarray) -> bytes:
    """The width of the values, then their first bytes, their second bytes and so on, compressed."""
    size = x.dtype.itemsize
    planes = np.ascontiguousarray(x).view(np.uint8).reshape(-1, size).T
    return bytes([size]) + pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def _read(raw: bytes, n: int, kind: str) -> np.ndarray:
    size = raw[0]
    planes = np.frombuffer(pa.decompress(memoryview(raw)[1:], n * size, codec="zstd"), np.uint8).reshape(size, n)
    return np.ascontiguousarray(planes.T).view(f"{kind}{size}").reshape(-1)


def _thin(x: np.ndarray) -> np.ndarray:
    """Indices in four bytes if they fit."""
    return x.astype(np.int32) if len(x) == 0 or int(x.max()) < 1 << 31 else x


def _first(x: np.ndarray) -> np.ndarray:
    """Whether a value differs from the one before."""
    return np.append(True, x[1:] != x[:-1]) if len(x) else np.zeros(0, bool)


def _pid(alpha: np.ndarray, beta: np.ndarray, placement: str, workers: int, gamma: np.ndarray | int = 0) -> np.ndarray:
    """As ``product.shard``; without gamma for the first piece of a tile."""
    if placement == "row":
        return alpha % workers
    return _scattered(alpha, beta, gamma) % workers


def _scattered(alpha: np.ndarray, beta: np.ndarray, gamma: np.ndarray | int = 0) -> np.ndarray:
    return (((alpha * 73_856_093) ^ (beta * 19_349_663) ^ (gamma * 83_492_791)) % (1 << 31) * 48_271) >> 8


def _summed(cols: list[np.ndarray], kind: type) -> list[np.ndarray]:
    """Loose rows, in the order of t, to cells."""
    t, side, x, v = cols
    low, wide = int(x.min()), int(x.max() - x.min()).bit_length()
    if int(t[-1] - t[0]).bit_length() + 1 + wide < 63:
        order = np.argsort((((t - t[0]) * 2 + side) << wide) + (x - low))
    else:
        order = np.lexsort((x, side, t))
    t, side, x = t[order], side[order], x[order]
    first = np.flatnonzero(_first(t) | _first(side) | _first(x))
    total = np.add.reduceat(v[order], first)
    if kind is np.int64 and not np.isfinite(total).all():
        raise ValueError("values that are no numbers, where whole numbers are summed")
    return [t[first], side[first], x[first], total.astype(kind)]


def _sent(batches: Iterator[pa.RecordBatch], workers: int, buckets: int, whole: bool) -> Iterator[pa.RecordBatch]:
    """Cells (t, side, x, v) to packed blocks by the place of their inner index, a bucket of a partition.  whole: values that
    are doubles are sent as whole numbers where they are such."""
    held: list[tuple] = []
    size = 0
    for batch in batches:
        if batch.num_rows:
            held.append(tuple(batch.column(c).to_numpy(zero_copy_only=False) for c in ("t", "side", "x", "v")))
            size += batch.num_rows
        if size >= CHUNK:
            yield _blocks([np.concatenate(c) for c in zip(*held, strict=True)], workers, buckets, whole)
            held, size = [], 0
    if held:
        yield _blocks([np.concatenate(c) for c in zip(*held, strict=True)], workers, buckets, whole)


def _blocks(cols: list[np.ndarray], workers: int, buckets: int, whole: bool) -> pa.RecordBatch:
    t, side, x, v = cols
    place = _bucket(t, workers * buckets) * 2 + side
    low = int(t.min())
    bits = (int(t.max()) - low).bit_length()
    if bits + (2 * workers * buckets).bit_length() < 63:
        order = np.argsort((place << bits) + (t - low))
    else:
        order = np.lexsort((t, place))
    place, t, x, v = (c[order] for c in (place, t, x, v))
    exact = v.dtype.kind != "f"
    if whole and not exact:
        with np.errstate(invalid="ignore"):
            w = v.astype(np.int64)
        v, exact = (w, True) if (w == v).all() else (v, False)
    cuts = np.flatnonzero(np.diff(place)) + 1
    rows = []
    for low, high in zip([0, *cuts], [*cuts, len(t)], strict=True):
        at, s = divmod(int(place[low]), 2)
        base = int(x[low:high].min())
        rows.append((at % workers, at // workers, s, high - low, exact, int(t[low]), base, _raw(_narrow(np.diff(t[low:high], prepend=t[low]))), _raw(_narrow(x[low:high] - base)), _raw(_narrow(v[low:high]) if exact else v[low:high])))
    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.bool_(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
    arrays = [pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)]
    return pa.RecordBatch.from_arrays(arrays, [c.split()[0] for c in BLOCKS.split(", ")])


def _bucket(t: np.ndarray, many: int) -> np.ndarray:
    """Inner indices dealt at random, by the high bits of a product."""
    return ((t.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)) % np.uint64(many)).astype(np.int64)


def _received(batches: Iterator[pa.RecordBatch], whole: bool) -> Iterator[list[np.ndarray]]:
    """Columns t, side, x, v of a bucket at a time, from its blocks, in the order of t."""
    now, held = None, []

    def opened() -> list[np.ndarray]:
        cols = [np.concatenate(c) for c in zip(*held, strict=True)]
        held.clear()
        order = np.argsort(cols[0], kind="stable")
        return [c[order] for c in cols]

    for batch in batches:
        for r in batch.to_pylist():
            if r["bucket"] != now and held:
                yield opened()
            now, n = r["bucket"], r["n"]
            t = np.cumsum(_read(r["ts"], n, "i"), dtype=np.int64) + r["first"]
            v = _read(r["vs"], n, "i" if r["exact"] else "f").astype(np.int64 if whole else np.float64)
            held.append((t, np.full(n, r["side"], np.int8), _read(r["xs"], n, "i") + np.int64(r["x0"]), v))
    if held:
        yield opened()


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """Columns t, side, x, v of some rows at a time, which are in the order of t; an index is never cut over two chunks."""
    held: list[tuple] = []
    size = 0
    for batch in batches:
        if batch.num_rows:
            held.append(tuple(batch.column(c).to_numpy(zero_copy_only=False) for c in ("t", "side", "x", "v")))
            size += batch.num_rows
        if size >= CHUNK:
            cols = [np.concatenate(c) for c in zip(*held, strict=True)]
            end = int(np.searchsorted(cols[0], cols[0][-1]))
            if end:
                yield [c[:end] for c in cols]
            held, size = [tuple(c[end:] for c in cols)], len(cols[0]) - end
    if held:
        yield [np.concatenate(c) for c in zip(*held, strict=True)]


def _pack(chunks: Iterator[list[np.ndarray]], shape: tuple, placement: str, workers: int, half: bool, tell: str | None = None, loose: type | None = None, how: Dealt | None = None) -> Iterator[pa.RecordBatch]:
    """Cells in the order of their inner index, each index in one chunk, to pieces.  loose: rows are summed to cells of that
    type."""
    seen = np.zeros(2, np.int64)
    for cols in chunks:
        cols = _summed(cols, loose) if loose else cols
        seen += np.bincount(cols[1], minlength=2)
        yield from _pieces(cols, shape, placement, workers, half, how)
    if tell:
        for s in (0, 1):
            yield _piece_rows([(-1, -1, 1 - s, 1, 0, 0, *(_raw(np.zeros(1, np.int8)) for _ in "tx"), _raw(seen[s : s + 1].astype(tell)))], s, np.zeros(1, np.int64))


def _pieces(cols: list[np.ndarray], shape: tuple, placement: str, workers: int, half: bool, how: Dealt | None = None) -> Iterator[pa.RecordBatch]:
    t, side, x, v = cols
    parts, steps = shape[:2], shape[2:]
    place = np.cumsum(_first(t)) - 1
    names = int(place[-1]) + 1
    sides = []
    for s in (0, 1):
        own = np.flatnonzero(side == s) if not half else np.arange(len(t))
        stripe = x[own] // how.slice % parts[1] if how and s else np.minimum(x[own] // steps[s], parts[s] - 1)
        # The stripes that this operand has at each inner index.
        have = np.unique(place[own] * parts[s] + stripe)
        counts = np.bincount(have // parts[s], minlength=names)
        sides.append((own, stripe, have % parts[s], counts, np.cumsum(counts) - counts))
    for s in (0, 1):
        own, stripe = sides[s][:2]
        _, _, others, counts, first = sides[1 - s]
        at = place[own]
        # Copies of some cells at a time, as an index with many stripes has many.
        ends = np.searchsorted(np.cumsum(counts[at]), np.arange(CHUNK, counts[at].sum() + CHUNK, CHUNK), "right") if len(own) else []
        low = 0
        for end in [*ends, len(own)]:
            end = min(len(own), max(end, low + 1))
            if end <= low:
                continue
            cell, step = _spread(counts[at[low:end]])
            cell += low
            other = others[first[at[cell]] + step]
            alpha, beta = (stripe[cell], other) if s == 0 else (other, stripe[cell])
            if half:
                keep = alpha <= beta
                cell, alpha, beta = cell[keep], alpha[keep], beta[keep]
            yield from _rows(alpha, beta, s, t[own[cell]], x[own[cell]], v[own[cell]], parts, steps[s], placement, workers, how)
            low = end


def _rows(alpha, beta, side, t, x, v, parts, step, placement, workers, how) -> Iterator[pa.RecordBatch]:
    """The parts of a tile: its right cells are part 0, and its left cells one or more."""
    if not len(t):
        return
    tile = alpha * parts[1] + beta
    subs = how.subs if how and side == 0 else 1
    if subs > 1:
        tile = tile * subs + np.minimum((x - alpha * step) // -(-step // subs), subs - 1)
    # Sorts of two-byte numbers are by their digits.
    order = np.argsort(tile.astype(np.int16) if parts[0] * parts[1] * subs < 1 << 15 else tile, kind="stable")
    tile, t, x, v = (c[order] for c in (tile, t, x, v))
    cuts = np.flatnonzero(np.diff(tile)) + 1
    rows = []
    for low, high in zip([0, *cuts], [*cuts, len(tile)], strict=True):
        at, part = divmod(int(tile[low]), subs)
        base = int(x[low:high].min())
        values = v[low:high] if v.dtype.kind == "f" else _narrow(v[low:high])
        rows.append((*divmod(at, parts[1]), 0 if side else 1 + part, high - low, int(t[low]), base, _raw(_narrow(np.diff(t[low:high], prepend=t[low]))), _raw(_narrow(x[low:high] - base)), _raw(values)))
    alpha, beta = (np.array([r[c] for r in rows], np.int64) for c in (0, 1))
    yield _piece_rows(rows, side, how.home[alpha, beta] if how else _pid(alpha, beta, placement, workers))


def _piece_rows(rows: list[tuple], side: int, pid: np.ndarray) -> pa.RecordBatch:
    a, b, part, n, first, base, ts, xs, vs = zip(*rows, strict=True)
    arrays = [pa.array(pid.astype(np.int32)), pa.array(a, pa.int32()), pa.array(b, pa.int32()), pa.array(part, pa.int32()), pa.array([side] * len(a), pa.int32()), pa.array(n, pa.int32()), pa.array(first, pa.int64()), pa.array(base, pa.int64()), *(pa.array(c, pa.binary()) for c in (ts, xs, vs))]
    return pa.RecordBatch.from_arrays(arrays, ["pid", "alpha", "beta", "part", "side", "n", "first", "x0", "ts", "xs", "vs"])


def _multiply(tiles: Iterator[tuple], whole: bool, half: bool) -> Iterator[pa.RecordBatch]:
    for alpha, beta, left, right in tiles:
        for i, j, v in _strips(left, right, whole):
            if half and alpha == beta:
                keep = i <= j
                i, j, v = i[keep], j[keep], v[keep]
            yield _batch(i, j, v)
            if half:
                keep = i != j
                yield _batch(j[keep], i[keep], v[keep])


def _batch(i: np.ndarray, j: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(v)], ["i", "j", "v"])


class _Right(list):
    """Pieces (t, x, v) of a right operand, that are put in the order of their inner index once."""

    met: tuple | None = None

    def ordered(self) -> tuple:
        """(cols, names, starts, counts, place, u, y, w): place is the place in names of index names[0] + n, or -1; None if
        that table would be large."""
        if self.met is None:
            # A column at a time, as a tile may have many cells.
            u, y, w = ([p[c] for p in self] for c in range(3))
            self.clear()
            u = np.concatenate(u)
            order = np.argsort(u, kind="stable")
            u, y = u[order], np.concatenate(y)[order]
            w = np.concatenate(w)[order]
            cols, y = _numbered(y)
            starts = np.flatnonzero(_first(u))
            names = u[starts]
            place = None
            if (most := int(names[-1]) - int(names[0])) < 8 * len(u) + 1024:
                place = np.full(most + 1, -1, np.int32)
                place[names - names[0]] = np.arange(len(names))
            self.met = cols, names, starts, np.diff(np.append(starts, len(u))), place, u, y, w
        return self.met


def _numbered(y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values, and the place of each value among them."""
    low, most = int(y.min()), int(y.max() - y.min())
    if most > 4 * len(y) + 1024:
        cols, y = np.unique(y, return_inverse=True)
        return cols.astype(np.int64), y
    seen = np.zeros(most + 1, bool)
    seen[y - low] = True
    return np.flatnonzero(seen) + low, (np.cumsum(seen, dtype=np.int32) - 1)[y - low]


def _tiles(batches: Iterator[pa.RecordBatch], whole: bool) -> Iterator[tuple]:
    """(alpha, beta, left, right) with operands as lists of (t, x, v), for each part of the left operand of a tile; pieces
    are in the order of tiles and parts, right ones first."""
    now, left, right = None, [], _Right()
    for batch in batches:
        alphas, betas, parts, which, ns, firsts, bases = (batch.column(c).to_pylist() for c in ("alpha", "beta", "part", "side", "n", "first", "x0"))
        ts, xs, vs = (batch.column(c) for c in ("ts", "xs", "vs"))
        for r in range(batch.num_rows):
            tile = (alphas[r], betas[r], parts[r])
            if tile != now:
                if left:
                    yield *now[:2], left, right
                left, right = [], right if now and now[:2] == tile[:2] else _Right()
                now = tile
            n = ns[r]
            t = _thin(np.cumsum(_read(ts[r].as_py(), n, "i"), dtype=np.int64) + firsts[r])
            (right if which[r] else left).append((t, _thin(_read(xs[r].as_py(), n, "i") + np.int64(bases[r])), _read(vs[r].as_py(), n, "i" if whole else "f")))
    if left:
        yield *now[:2], left, right


def _met(left: list, right: list) -> tuple | None:
    """(rows, cols, row, t, v, first, many, names, counts, u, y, w): operands by row and by inner index, for each left cell
    the first and number of the right cells it meets; None if there are none."""
    right = right if isinstance(right, _Right) else _Right(right)
    if not left or not (right or right.met):
        return None
    cols, names, starts, counts, place, u, y, w = right.ordered()
    t, x, v = (np.concatenate(c) for c in zip(*left, strict=True))
    left.clear()
    order = np.argsort(x, kind="stable" if v.dtype.kind == "f" else None)
    t, x, v = t[order], x[order], v[order]
    if place is None:
        at = np.minimum(np.searchsorted(names, t), len(names) - 1)
        ok = names[at] == t
    else:
        ok = (t >= names[0]) & (t <= names[-1])
        at = place[np.where(ok, t, names[0]) - names[0]]
        ok &= at >= 0
    t, x, v, at = t[ok], x[ok], v[ok], at[ok]
    if not len(x):
        return None
    first = _first(x)
    return x[first].astype(np.int64), cols, np.cumsum(first) - 1, t, v, starts[at], counts[at], names, counts, u, y, w


def _cuts(row: np.ndarray, many: np.ndarray, width: int, rows: int, begin: int = 0) -> Iterator[tuple[int, int, int, int]]:
    """(low, high, a, b): strips of rows low to high - 1 with cells a to b - 1, of bounded products and values."""
    ends = np.searchsorted(row, np.arange(begin, rows + 1))
    work = np.append(0, np.cumsum(many[ends[0] : ends[-1]]))[ends - ends[0]]
    low = begin
    while low < rows:
        high = max(low + 1, min(low + max(1, 4 * STRIP // width), begin + int(np.searchsorted(work, work[low - begin] + STRIP, "right")) - 1))
        yield low, high, int(ends[low - begin]), int(ends[high - begin])
        low = high


def _locally(row: np.ndarray, v: np.ndarray, first: np.ndarray, many: np.ndarray, y: np.ndarray, w: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray] | None:
    """(cols, cells) of some rows of the product from dense blocks of the inner indices and columns that these rows meet;
    None where the blocks would be too sparse or large.  No scalar product passes ``most``."""
    rows = int(row[-1]) + 1
    starts, one, to = np.unique(first, return_index=True, return_inverse=True)
    n, work = many[one], LOCAL * int(many.sum())
    if rows * len(starts) * int(n.max()) > work:
        return None
    owner, step = _spread(n)
    at = starts[owner] + step
    cols, place = _numbered(y[at])
    if rows * len(starts) * len(cols) > work or 8 * max(rows * len(cols), (rows + len(cols)) * len(starts)) > 2 * BLOCK:
        return None
    # Whole numbers up to 2^24 are exact in four bytes.
    kind = np.float32 if float(most) * int(np.bincount(row).max()) < 1 << 24 else np.float64
    left, right = (np.bincount(key, x, size).astype(kind) for key, x, size in ((row * len(starts) + to, v, rows * len(starts)), (owner * len(cols) + place, w[at], len(starts) * len(cols))))
    return cols, left.reshape(rows, -1) @ right.reshape(-1, len(cols))


def _scalars(left: list, right: list) -> Iterator[tuple]:
    """(rows, cols, key, t) of a tile's scalar products by strips: key is the place in the strip, rows by columns."""
    met = _met(left, right)
    if met is None:
        return
    rows, cols, row, t, _, first, many, _, _, _, y, _ = met
    for low, high, a, b in _cuts(row, many, len(cols), len(rows)):
        owner, step = _spread(many[a:b])
        yield rows[low:high], cols, (row[a:b] - low)[owner] * len(cols) + y[first[a:b][owner] + step], t[a:b][owner]


def _dense(rows: int, width: int, row, t, v, names, counts, u, y, w) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """(mask, left, right): cells of the left operand whose inner index is frequent in both, and blocks of both operands at
    those indices; None if there are none."""
    if counts.max() * FASTER < width:
        return None
    to = np.repeat(np.arange(len(names)), counts)
    at = np.searchsorted(names, t)
    work = np.bincount(at, minlength=len(names)) * counts
    many = min(int(np.count_nonzero(work * FASTER >= rows * width)), BLOCK // (8 * (rows + width)))
    if not many:
        return None
    place = np.full(len(names), -1)
    place[np.argsort(-work, kind="stable")[:many]] = np.arange(many)
    own, other = place[at], place[to]
    mask, also = own >= 0, other >= 0
    first = np.bincount(row[mask] * many + own[mask], v[mask], rows * many).reshape(rows, many)
    return mask, first, np.bincount(other[also] * width + y[also], w[also], many * width).reshape(many, width)


def _strips(left: list, right: list, whole: bool) -> Iterator[tuple]:
    """(i, j, v) of a tile's cells that have a product, by strips of its rows."""
    met = _met(left, right)
    if met is None:
        return
    rows, cols, row, t, v, first, many, names, counts, u, y, w = met
    v = v.astype(np.int64 if whole else np.float64)
    w = w if whole else w.astype(np.float64)
    width = len(cols)
    if not whole and len(t) == len(rows) * len(names) and len(u) == len(names) * width:
        # Neither operand has an empty cell, so neither has the product.
        at = np.searchsorted(names, t)
        dense, other = np.zeros((len(rows), len(names))), np.zeros((len(names), width))
        dense[row, at] = v
        other[np.searchsorted(names, u), y] = w
        for low in range(0, len(rows), max(1, STRIP // width)):
            own = rows[low : low + max(1, STRIP // width)]
            yield np.repeat(own, width), np.tile(cols, len(own)), (dense[low : low + len(own)] @ other).reshape(-1)
        return
    # Sums of products of one sign can't cancel, so their zeros are cells without products.
    mixed = bool((v <= 0).any() or (w <= 0).any())
    # Sums in doubles are exact up to 2^53.
    most = max(abs(int(v.min())), abs(int(v.max()))) * max(abs(int(w.min())), abs(int(w.max()))) if whole else 0
    exact = not whole or float(most) * len(names) < 2.0**53
    bits = most.bit_length() if whole and not mixed else 64
    block = _dense(len(rows), width, row, t, v, names, counts, u, y, w) if whole and exact and not mixed else None
    if block:
        mask, own, other = block
        row, v, first, many = (c[~mask] for c in (row, v, first, many))
    tried = whole and exact and not mixed and not block
    for begin in range(0, len(rows), TALL if tried else len(rows)):
        end = min(begin + TALL, len(rows)) if tried else len(rows)
        if tried:
            a, b = np.searchsorted(row, (begin, end))
            near = _locally(row[a:b] - begin, v[a:b], first[a:b], many[a:b], y, w, most)
            if near:
                own, total = near
                for low in range(begin, end, max(1, STRIP // len(own))):
                    part = total[low - begin : low - begin + max(1, STRIP // len(own))]
                    i, j = np.nonzero(part)
                    yield rows[low + i], cols[own[j]], part[i, j].astype(np.int64)
                continue
        for low, high, a, b in _cuts(row, many, width, end, begin):
            n = many[a:b]
            k = np.repeat(first[a:b] - (np.cumsum(n) - n), n)
            k += np.arange(len(k))
            key = np.repeat((row[a:b] - low) * width, n)
            key += y[k]
            value = np.repeat(v[a:b], n)
            value *= w[k]
            size = (high - low) * width
            if block or size <= 16 * len(key):
                total = np.bincount(key, value, size) if exact else _sums(key, value, size)
                if block:
                    total = total + (own[low:high] @ other).reshape(-1)
                cell = np.flatnonzero(np.bincount(key, minlength=size) if mixed else total)
                total = total[cell]
            elif bits + size.bit_length() < 63:
                # A place and a product in one number: sorts of numbers are faster than those of places.
                key <<= bits
                key |= value
                key = np.sort(key.astype(np.uint32) if bits + size.bit_length() <= 32 else key).astype(np.int64)
                value = np.cumsum(key & ((1 << bits) - 1))
                key >>= bits
                new = np.flatnonzero(_first(key))
                cell, total = key[new], np.diff(value[np.append(new[1:], len(key)) - 1], prepend=0)
            else:
                order = np.argsort(key, kind="stable")
                key = key[order]
                new = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
                cell, total = key[new], np.add.reduceat(value[order], new)
            i = cell // width
            yield rows[low + i], cols[cell - i * width], total.astype(np.int64) if whole else total.astype(np.float64)


def _full(met: tuple, norms: float | None = None) -> Iterator[tuple[int, int, np.ndarray]] | None:
    """(low, high, sums): rows low to high - 1 of a product of positive whole numbers with all columns, empty cells as 0.
    Inner indices that are frequent in both operands are multiplied as dense blocks.  norms: no sum passes it.  None where
    numbers aren't positive, or sums pass 2^53."""
    rows, cols, row, t, v, first, many, names, counts, u, y, w = met
    width = len(cols)
    most = norms if norms is not None else float(int(v.max())) * int(w.max()) * len(names)
    if (v <= 0).any() or (w <= 0).any() or most >= 2.0**53:
        return None
    kind = np.float32 if most < 1 << 24 else np.float64
    at = np.searchsorted(names, t)
    work = np.bincount(at, minlength=len(names)) * counts
    frequent = min(int(np.count_nonzero(work * FASTEST >= len(rows) * width)), BLOCK // (4 * width))
    place = np.full(len(names), -1)
    place[np.argsort(-work, kind="stable")[:frequent]] = np.arange(frequent)
    own, other = place[at], place[np.repeat(np.arange(len(names)), counts)]
    also = other >= 0
    right = np.zeros((frequent, width), kind)
    np.add.at(right, (other[also], y[also]), w[also].astype(kind))
    mask = own >= 0
    dense_row, dense_at, dense_v = row[mask], own[mask], v[mask]
    row, v, first, many = (c[~mask] for c in (row, v, first, many))

    def strips() -> Iterator[tuple[int, int, np.ndarray]]:
        for low, high, a, b in _cuts(row, many, width, len(rows)):
            p, q = np.searchsorted(dense_row, (low, high))
            left = np.zeros((high - low, frequent), kind)
            np.add.at(left, (dense_row[p:q] - low, dense_at[p:q]), dense_v[p:q].astype(kind))
            n = many[a:b]
            k = np.repeat(first[a:b] - (np.cumsum(n) - n), n)
            k += np.arange(len(k))
            key = np.repeat((row[a:b] - low) * width, n)
            key += y[k]
            value = np.repeat(v[a:b].astype(np.float64), n)
            value *= w[k]
            yield low, high, (left @ right if frequent else 0) + np.bincount(key, value, (high - low) * width).reshape(high - low, width)

    return strips()


def _nearest(left: list, right: list, tell: int, k: int, decimals: int | None, skip_self: bool) -> Iterator[tuple]:
    """(i, j, v) of cells of a tile that may be among the k largest cosines of their row; values at inner index ``tell`` are
    squared norms."""
    met = _met(left, right)
    if met is None:
        return
    rows, cols, row, t, v, first, many, names, counts, u, y, w = met
    if names[-1] != tell:
        return
    # The last index: norms are split off, and rows without one don't count.
    end = len(u) - int(counts[-1])
    x2, y2 = np.zeros(len(rows), np.int64), np.zeros(len(cols), np.int64)
    y2[y[end:]] = w[end:]
    x2[row[t == tell]] = v[t == tell]
    keep = t != tell
    names, counts, u, y, w = names[:-1], counts[:-1], u[:end], y[:end], w[:end]
    row, t, v, first, many = (c[keep] for c in (row, t, v, first, many))
    if not len(row):
        return
    v = v.astype(np.int64)
    met = rows, cols, row, t, v, first, many, names, counts, u, y, w
    scale = np.divide(1.0, np.sqrt(y2.astype(np.float64)), out=np.zeros(len(cols)), where=y2 > 0)
    slack = 0.0 if decimals is None else 2 * 10.0**-decimals
    strips = _full(met, float(x2.max()) ** 0.5 * float(y2.max()) ** 0.5 * 1.001)

    def scored(i: np.ndarray, j: np.ndarray, d: np.ndarray) -> tuple:
        """From places of rows and columns."""
        v = d / np.sqrt(x2[i].astype(np.float64) * y2[j])
        return rows[i], cols[j], v if decimals is None else np.round(v, decimals)

    if strips is None:
        for i, j, d in _strips([(t, rows[row], v)], [(u, cols[y], w)], True):
            i, j = np.searchsorted(rows, i), np.searchsorted(cols, j)
            ok = (x2[i] > 0) & (y2[j] > 0) & ((rows[i] != cols[j]) | (not skip_self))
            yield scored(i[ok], j[ok], d[ok])
        return
    at = np.minimum(np.searchsorted(cols, rows), len(cols) - 1)
    for low, high, dots in strips:
        if skip_self:
            same = np.flatnonzero(cols[at[low:high]] == rows[low:high])
            dots[same, at[low:high][same]] = 0
        cosines = dots * scale
        left_over = cosines.copy()
        line = np.arange(high - low)
        for _ in range(min(k, len(cols)) - 1):
            left_over[line, left_over.argmax(1)] = 0
        least = left_over.max(1) - slack * np.sqrt(x2[low:high])
        i, j = np.nonzero((cosines > 0) & (cosines >= least[:, None] * (1 - 1e-12)))
        ok = x2[low + i] > 0
        yield scored(low + i[ok], j[ok], dots[i[ok], j[ok]])


def _reached(left: list, right: list, whole: bool, diagonal: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(cols, own): cells of a tile and their mirrors by their larger index, which is the column's."""
    met = _met(left, right)
    if met is None:
        return
    rows, cols, row, t, v, first, many, names, counts, u, y, w = met
    strips = _full((rows, cols, row, t, v.astype(np.int64), first, many, names, counts, u, y, w)) if whole else None
    if strips is None:
        for i, j, _ in _strips([(t, rows[row], v)], [(u, cols[y], w)], whole):
            keep = i <= j
            reach, own = np.unique(j[keep], return_inverse=True)
            yield reach, np.bincount(own, np.where(i == j, 1, 2)[keep], len(reach)).astype(np.int64)
        return
    own = np.zeros(len(cols), np.int64)
    for low, high, sums in strips:
        made = sums > 0
        if diagonal:
            place = cols[None] - rows[low:high, None]
            own -= np.count_nonzero(made & (place == 0), axis=0)
            made &= place >= 0
        own += 2 * np.count_nonzero(made, axis=0)
    yield cols[own > 0], own[own > 0]


def _sums(key: np.ndarray, value: np.ndarray, size: int) -> np.ndarray:
    out = np.zeros(size, value.dtype)
    np.add.at(out, key, value)
    return out

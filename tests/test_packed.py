"""Packed products, Grams and the queries that need them at size."""

from pathlib import Path

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from test_engine import dense, sparse

from tilealg.operators import packed, product
from tilealg.operators.grid import TileGrid

SF = "/root/testdata/sf0.001"


@pytest.fixture
def tight(monkeypatch):
    """Bounds so small that any product is packed, in chunks and strips of a few cells."""
    monkeypatch.setattr(product, "MOST_COPIES", 0)
    monkeypatch.setattr(packed, "CHUNK", 20)
    monkeypatch.setattr(packed, "STRIP", 16)


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("scale", [1, 0.5, 2**40])
@pytest.mark.parametrize("cut", [(1, 2, 1), (4, 3, 3), (23, 1, 17)])
def test_large_products_are_packed(spark, tight, scale, cut):
    rng = np.random.default_rng(0)
    a, b = (rng.integers(-2, 4, (23, 31)) * (rng.random((23, 31)) < 0.3) * scale), rng.integers(-1, 300, (31, 17)) * (rng.random((31, 17)) < 0.3)
    x, y = sparse(spark, a), sparse(spark, b)
    want, hit = a @ b, (a != 0).astype(int) @ (b != 0).astype(int) > 0
    for placement in ("row", "tile", "random"):
        got = product.tiled_product(x, y, TileGrid.of(23, 31, 17, *cut), placement)
        assert "MapInArrow" in plan(got.df)
        cells = {(r["i"], r["j"]): r["v"] for r in got.df.collect()}
        assert cells == {(i, j): want[i, j] for i, j in zip(*np.nonzero(hit), strict=True)}


def test_packed_cells_meet_before_they_are_copied(spark):
    """Two blocks without a common index: a cell goes to one tile, not to every stripe."""
    a = np.kron(np.eye(2, dtype=int), np.ones((4, 3), int))
    x = sparse(spark, a)
    t, side, at, v = (np.array(c) for c in zip(*[(j, s, i, 1) for j in range(6) for s in (0, 1) for i in range(8) if a[i, j]], strict=True))
    rows = [b.to_pylist() for b in packed._pieces([t, side, at, v], (2, 2, 4, 4), "tile", 3, False)]
    assert sum(r["n"] for b in rows for r in b) == 2 * np.count_nonzero(a) and {(r["alpha"], r["beta"]) for b in rows for r in b} == {(0, 0), (1, 1)}
    assert (dense(packed.packed_product(x, x.t, TileGrid.of(8, 6, 8, 2, 1, 2), "tile", 3)) == a @ a.T).all()


def test_planned_product_is_packed(spark, tight):
    import __spark_entry__ as entry

    got = entry.queries()["product_planned"](spark, SF)
    assert "MapInArrow" in plan(got)
    db = duckdb.connect()
    for name in ("lineitem", "orders"):
        db.sql(f"CREATE VIEW {name} AS SELECT * FROM '{SF}/{name}.parquet'")
    assert sorted(map(tuple, got.collect())) == sorted(db.sql(entry.oracle_sql()["product_planned"]).fetchall())


def same_as_sql(spark, name):
    import __spark_entry__ as entry

    db = duckdb.connect()
    for f in Path(SF).glob("*.parquet"):
        db.sql(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
    want = db.sql(entry.oracle_sql()[name])
    got = entry.queries()[name](spark, SF)
    assert sorted(map(tuple, got.select(*want.columns).collect()), key=str) == sorted(want.fetchall(), key=str)
    return got


@pytest.mark.parametrize("name", ["intermediate_size_by_grid", "intermediate_size_by_placement"])
def test_partials_are_counted_in_packed_tiles(spark, tight, name):
    assert "Aggregate [pid" not in plan(same_as_sql(spark, name))


@pytest.mark.parametrize("name", ["gram_suppliers", "gram_customers"])
def test_large_grams_are_packed(spark, tight, name):
    assert "MapInArrow" in plan(same_as_sql(spark, name))


CHANGED = (
    "power_method_gram", "generator_cells", "product_generated", "nmf_gram", "nmf_y", "svm_language_gradient", "svm_language_alpha_materialised", "tile_product_arrow", "product_broadcast", "svm_kernel_stats",
    "document_cosine_topk", "embedding_topk", "embedding_distances", "embedding_dots", "doc_term_gram",
)


@pytest.mark.parametrize("name", CHANGED)
def test_changed_queries_equal_sql(spark, tight, monkeypatch, name):
    from tilealg.operators import svm

    monkeypatch.setattr(svm, "MOST_KERNEL", 100)
    got = same_as_sql(spark, name)
    if name in ("generator_cells", "product_generated", "nmf_gram", "nmf_y"):
        assert ("part.parquet" if name == "nmf_y" else "customer.parquet") in str(got.inputFiles())


FLAGSHIPS = ("product_inner_only", "product_random_placement", "product_row_placement", "product_supplier_customer", "product_tile_placement", "product_random_placement_fine")


@pytest.mark.parametrize("name", FLAGSHIPS)
def test_large_flagships_sum_lines_where_they_meet(spark, tight, name):
    """One exchange of each operand's rows and one of the pieces, besides the two sides of the join of lines and orders."""
    got = same_as_sql(spark, name)
    physical = got._jdf.queryExecution().sparkPlan().toString()
    assert "MapInArrow" in physical and "HashAggregate" not in physical and physical.count("Exchange ") == 2


@pytest.mark.parametrize("least", [-1, 1])
@pytest.mark.parametrize("block", [64 << 20, 600])
def test_frequent_indices_are_multiplied_as_blocks(monkeypatch, block, least):
    """Same cells with blocks, with some, and (as cells without a positive sum must stay) without."""
    monkeypatch.setattr(packed, "STRIP", 40)
    monkeypatch.setattr(packed, "BLOCK", block)
    rng = np.random.default_rng(1)
    share = np.array([0.9, 0.02, 1.0, 0.05, 0.0, 0.5])
    a, b = (rng.integers(least, 5, s) * (rng.random(s) < p) for s, p in (((19, 6), share), ((6, 13), share[:, None])))
    made, real = [], packed._dense
    monkeypatch.setattr(packed, "_dense", lambda *x: made.append(real(*x)) or made[-1])
    i, t = np.nonzero(a)
    u, j = np.nonzero(b)
    cells = {}
    for x, y, v in packed._strips([(t, i, a[i, t])], [(u, j, b[u, j])], True):
        cells |= {(int(p), int(q)): int(z) for p, q, z in zip(x, y, v, strict=True)}
    hit = (a != 0).astype(int) @ (b != 0).astype(int)
    assert cells == {(int(p), int(q)): int((a @ b)[p, q]) for p, q in zip(*np.nonzero(hit), strict=True)}
    assert not made if least < 0 else made[0] is not None


def test_words_are_counted_where_documents_are_read(spark, tmp_path):
    """As ``term_counts``, also where two documents share an id (then by an exchange)."""
    from tilealg.sources import tables

    rows = [(1, "Aa bb aa\x00aa"), (2, None), (3, "É x-X")]
    for more, plain in (([], True), ([(1, "bb cc")], False)):
        spark.createDataFrame(rows + more, "doc_id long, text string").write.parquet(f"{tmp_path}/{plain}/documents.parquet")
        got = tables.local_term_counts(spark, f"{tmp_path}/{plain}")
        assert ("MapInArrow" in plan(got)) is plain
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, tables.term_counts(spark, f"{tmp_path}/{plain}").collect()))


EVERYWHERE = ("product_random_placement", "product_row_placement", "product_supplier_customer", "product_tile_placement", "product_random_placement_fine")


@pytest.mark.parametrize("name", EVERYWHERE)
@pytest.mark.parametrize("most", [packed.DEALT_CELLS, 2000])
def test_stripes_of_large_flagships_follow_their_cells(spark, tight, monkeypatch, name, most):
    """Not the 20 or 40 stripes of the query's grid, to each of which a cell may be copied: as many as hold the cells."""
    monkeypatch.setattr(packed, "DEALT_CELLS", most)
    monkeypatch.setattr(packed, "SUB_CELLS", 300)
    made, real = [], packed.dealt
    monkeypatch.setattr(packed, "dealt", lambda *x: made.append(real(*x)) or made[-1])
    same_as_sql(spark, name)
    (grid, how), lines = made[0], duckdb.sql(f"SELECT count(*) FROM '{SF}/lineitem.parquet'").fetchall()[0][0]
    for parts, edge in ((grid.m, grid.a), (grid.k, grid.c)):
        least = -(-min(lines, edge * grid.b) // most)
        assert least <= parts <= 2 * least
    assert how.subs > 1


@pytest.mark.parametrize("placement", ["row", "tile", "random"])
def test_tiles_of_large_products_are_spread(placement):
    """Tiles go to partitions of their own; where only stripes of one number meet, to nearly all of them, a cell once."""
    grid, how = packed.dealt(TileGrid.of(960, 960, 960, 20, 6, 20), 4 * packed.DEALT_CELLS, 4 * packed.DEALT_CELLS, placement, 96)
    assert (grid.m, grid.k) == (4, 4) and len(set(how.home.ravel().tolist())) == 16
    assert how.home.tolist() == np.arange(16).reshape(4, 4).tolist() or placement != "row"
    t, side, x = (np.array(c) for c in zip(*[(j, s, j) for j in range(960) for s in (0, 1)], strict=True))
    rows = [r for b in packed._pieces([t, side, x, x], (4, 4, 240, 240), placement, 96, False, how) for r in b.to_pylist()]
    assert sum(r["n"] for r in rows) == 2 * 960 and len({r["pid"] for r in rows}) == 16
    assert all(r["part"] == 0 if r["side"] else r["part"] > 0 for r in rows)


def test_pieces_keep_their_numbers():
    for x in (np.array([3, -1, 127], np.int8), np.array([-(2**62), 5]), np.array([0.5, -1e300]), np.array([2**20, -7], np.int32)):
        raw = packed._raw(x)
        assert packed._read(raw, len(x), x.dtype.kind).tolist() == x.tolist()


SENT = ("product_tile_placement", "product_supplier_customer", "product_row_placement", "product_random_placement_fine", "product_random_placement")


@pytest.mark.parametrize("name", SENT)
def test_large_flagships_pack_cells_before_they_meet(spark, tight, name):
    """What is exchanged so that cells meet is blocks, not a row for each cell."""
    physical = same_as_sql(spark, name)._jdf.queryExecution().sparkPlan().toString()
    assert physical.count("MapInArrow") == 3 and "hashpartitioning(t#" not in physical


@pytest.mark.parametrize("kind", ["counts", "whole", "parts"])
def test_sent_cells_arrive_by_buckets(monkeypatch, kind):
    """Every cell once, in the order of the inner index inside a bucket, no index in two; whole numbers in few bytes."""
    monkeypatch.setattr(packed, "CHUNK", 2000)
    rng = np.random.default_rng(2)
    t, side, x = rng.integers(0, 900, 9000), rng.integers(0, 2, 9000).astype(np.int32), rng.integers(2**40, 2**40 + 500, 9000)
    v = {"counts": rng.integers(1, 60, 9000), "whole": rng.integers(1, 60, 9000).astype(float), "parts": rng.random(9000)}[kind]
    rows = [pa.RecordBatch.from_arrays([pa.array(c[low : low + 700]) for c in (t, side, x, v)], ["t", "side", "x", "v"]) for low in range(0, 9000, 700)]
    sent = [r for b in packed._sent(iter(rows), 3, 4, kind != "parts") for r in b.to_pylist()]
    assert {r["pid"] for r in sent} == {0, 1, 2} and {r["bucket"] for r in sent} == {0, 1, 2, 3}
    assert kind == "parts" or sum(len(r[c]) for r in sent for c in ("ts", "xs", "vs")) < 9000 * 7
    got, seen = [], []
    for pid in range(3):
        own = sorted((r for r in sent if r["pid"] == pid), key=lambda r: r["bucket"])
        for cols in packed._received(iter([pa.RecordBatch.from_pylist(own[:5]), pa.RecordBatch.from_pylist(own[5:])]), kind == "counts"):
            assert (np.diff(cols[0]) >= 0).all()
            seen += set(cols[0].tolist())
            got += zip(*(c.tolist() for c in cols), strict=True)
    assert len(seen) == len(set(seen)) and sorted(got) == sorted(zip(t.tolist(), side.tolist(), x.tolist(), v.tolist(), strict=True))


@pytest.mark.parametrize("squared", [True, False])
def test_distances_are_made_whole_in_tiles(spark, squared):
    """Rows without a common column and without a cell too; nothing stands between the tiles and the result."""
    from tilealg.operators import similarity
    from tilealg.operators.cells import Cells

    rows = {0: {0: 1.0, 2: 2.0}, 1: {1: 3.0}, 3: {0: -1.0, 1: 0.5}}
    a = Cells(spark.createDataFrame([(i, j, v) for i, r in rows.items() for j, v in r.items()], "i long, j long, v double"), 5, 3)
    asked = spark.createDataFrame([(1,), (2,), (3,)], "i long")
    got = similarity.row_distances(a, a, squared, rows=asked, decimals=6).df
    assert got._jdf.queryExecution().optimizedPlan().getClass().getSimpleName() == "MapInArrow"
    dense = np.array([[rows.get(i, {}).get(j, 0.0) for j in range(3)] for i in range(5)])
    want = ((dense[:, None] - dense[None]) ** 2).sum(2) ** (1 if squared else 0.5)
    assert {(r.i, r.j): r.v for r in got.collect()} == pytest.approx({(i, j): round(want[i, j], 6) for i in (1, 2, 3) for j in range(5)})


@pytest.mark.parametrize("scale", [1, 1 << 20])
def test_rows_that_meet_few_columns_are_multiplied_as_blocks(monkeypatch, scale):
    """Same cells in four and in eight bytes; rows of two groups share no inner index, and strips may hold both."""
    rng = np.random.default_rng(2)
    a, b = np.zeros((50, 20), int), np.zeros((20, 70), int)
    for g in (0, 1):
        a[25 * g : 25 * g + 25, 10 * g : 10 * g + 10] = rng.integers(0, 3, (25, 10))
        b[10 * g : 10 * g + 10, 35 * g : 35 * g + 35] = rng.integers(1, 5, (10, 35)) * scale
    monkeypatch.setattr(packed, "FASTER", 0)
    monkeypatch.setattr(packed, "TALL", 20)
    made, real = [], packed._locally
    monkeypatch.setattr(packed, "_locally", lambda *x: made.append(real(*x)) or made[-1])
    i, t = np.nonzero(a)
    u, j = np.nonzero(b)
    cells = {}
    for x, y, v in packed._strips([(t, i, a[i, t])], [(u, j, b[u, j])], True):
        cells |= {(int(p), int(q)): int(z) for p, q, z in zip(x, y, v, strict=True)}
    assert cells == {(int(p), int(q)): int((a @ b)[p, q]) for p, q in zip(*np.nonzero(a @ b), strict=True)}
    assert len(made) == 3 and all(made) and made[0][1].dtype == (np.float32 if scale == 1 else np.float64)


@pytest.mark.parametrize("least", [1, -1])
@pytest.mark.parametrize("block", [64 << 20, 0])
def test_nearest_rows_are_found_from_whole_numbers(monkeypatch, least, block):
    """With blocks and without, and with negative numbers; ties go to the smaller column, rows aren't their own neighbours."""
    monkeypatch.setattr(packed, "STRIP", 30)
    monkeypatch.setattr(packed, "BLOCK", block)
    rng = np.random.default_rng(3)
    a = rng.integers(least, 4, (30, 9)) * (rng.random((30, 9)) < np.linspace(0.05, 1, 9))
    a[7], a[11], a[5] = a[3], a[3], 0
    n2 = (a * a).sum(1)
    i, t = np.nonzero(a)
    live = np.flatnonzero(n2)
    side = lambda ok: [(np.append(t[ok[i]], np.full(ok[live].sum(), 9)), np.append(i[ok[i]], live[ok[live]]), np.append(a[i, t][ok[i]], n2[live[ok[live]]]))]
    found = {}
    for x, y, v in packed._nearest(side(np.arange(30) % 3 == 0), side(np.ones(30, bool)), 9, 3, 9, True):
        for p, q, z in zip(x.tolist(), y.tolist(), v.tolist(), strict=True):
            found.setdefault(p, []).append((-z, q))
    hit = (a != 0).astype(int) @ (a != 0).T.astype(int)
    for p in range(0, 30, 3):
        want = sorted((-round(float(a[p] @ a[q] / np.sqrt(float(n2[p] * n2[q]))), 9), q) for q in range(30) if q != p and hit[p, q])
        assert [(pytest.approx(z), q) for z, q in want[:3]] == sorted(found.get(p, []))[:3]


def test_cells_of_document_search_are_neither_written_nor_exchanged_as_rows(spark):
    """Words are counted where documents are read, and counts travel in packed blocks."""
    from tilealg.plans.workloads import QUERIES

    text = QUERIES["document_cosine_topk"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("MapInArrow") > 2 and "LogicalRDD [i" not in text and "regexp_extract_all" not in text


@pytest.mark.parametrize("kind", ["positive", "mixed", "double"])
@pytest.mark.parametrize("diagonal", [True, False])
def test_gram_cells_are_counted_where_they_are_made(monkeypatch, kind, diagonal):
    """By their larger index, with their mirrors; zeros that cancel stay cells."""
    monkeypatch.setattr(packed, "STRIP", 30)
    rng = np.random.default_rng(4)
    a = rng.integers(-1 if kind == "mixed" else 1, 3, (24, 7)) * (rng.random((24, 7)) < np.linspace(0.02, 0.6, 7))
    a = a * (1.5 if kind == "double" else 1)
    i, t = np.nonzero(a)
    up, low = i < (24 if diagonal else 12), i >= (0 if diagonal else 12)
    side = lambda ok: [(t[ok], i[ok], a[i[ok], t[ok]])]
    got = np.zeros(24, int)
    for reach, own in packed._reached(side(up), side(low), kind != "double", diagonal):
        np.add.at(got, reach, own)
    hit = (a != 0).astype(int) @ (a != 0).T.astype(int) > 0
    want = [sum((1 if p == q else 2) * int(hit[p, q]) for p in range(q + 1 if diagonal else 12)) if diagonal or q >= 12 else 0 for q in range(24)]
    assert got.tolist() == want


def test_kernel_cells_are_counted_in_tiles(spark, tight, monkeypatch):
    """The query's kernel leaves its tiles as counts."""
    from tilealg.operators import similarity

    seen, real = [], similarity.gram_rows
    monkeypatch.setattr(similarity, "gram_rows", lambda *x, **y: seen.append(real(*x, **y)) or seen[-1])
    same_as_sql(spark, "svm_kernel_stats")
    assert len(seen) == 1 and seen[0].columns == ["reach", "own"] and "MapInArrow" in plan(seen[0])

"""Products, learners and measures against numpy on small inputs."""

import os
import subprocess
import sys
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilealg import baselines, measures
from tilealg.operators import cells as C
from tilealg.operators import iterate, nmf, pagerank, similarity, svm
from tilealg.operators.cells import Cells
from tilealg.operators.generate import random_matrix
from tilealg.operators.grid import TileGrid
from tilealg.operators.product import broadcast_product, cell_product, tag_left, tag_right, tiled_product, tiled_product_blocks

ROOT = Path(__file__).resolve().parents[1]


def sparse(spark, m):
    rows = [(int(i), int(j), m[i, j].item()) for i, j in zip(*np.nonzero(m), strict=True)]
    kind = "double" if m.dtype.kind == "f" else "long"
    return Cells(spark.createDataFrame(rows, f"i long, j long, v {kind}"), *m.shape)


def dense(a):
    out = np.zeros((a.rows, a.cols))
    for r in a.df.collect():
        assert out[r["i"], r["j"]] == 0
        out[r["i"], r["j"]] = r["v"]
    return out


@pytest.fixture(scope="module")
def pair(spark):
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 4, (5, 7)) * rng.integers(0, 2, (5, 7)), rng.integers(0, 4, (7, 3))
    a[2] = b[:, 1] = 0
    return a, b, sparse(spark, a), sparse(spark, b)


@pytest.mark.parametrize("grid", [(1, 1, 1), (2, 3, 2), (5, 7, 3), (9, 1, 1), (1, 4, 1), (3, 2, 1)])
@pytest.mark.parametrize("placement", ["row", "tile", "random"])
def test_every_grid_and_placement_gives_the_product(pair, grid, placement):
    a, b, x, y = pair
    assert (dense(tiled_product(x, y, TileGrid.of(5, 7, 3, *grid), placement)) == a @ b).all()


def test_other_forms_of_the_product(pair, tmp_path):
    a, b, x, y = pair
    want = a @ b
    grid = TileGrid.of(5, 7, 3, 2, 3, 2)
    assert (dense(tiled_product(x, y)) == want).all()
    assert (dense(tiled_product(x, y, grid, staged=True, path=str(tmp_path))) == want).all()
    assert (dense(tiled_product(x, y, grid, "random", combine=False)) == want).all()
    assert (dense(tiled_product_blocks(x, y, grid)) == want).all()
    assert (dense(cell_product(x, y)) == want).all()
    assert (dense(broadcast_product(x, y)) == want).all()
    assert (dense(broadcast_product(x, y.t, transpose_small=True)) == want).all()
    assert (dense(broadcast_product(x, y, most_bytes=64)) == want).all()
    assert (baselines.local_product(a, b, loops=True) == want).all()


def test_copies_and_exchanges(pair):
    a, b, x, y = pair
    grid = TileGrid.of(5, 7, 3, 2, 3, 2)
    assert tag_left(x, grid).count() == grid.k * np.count_nonzero(a)
    assert tag_right(y, grid).count() == grid.m * np.count_nonzero(b)
    assert measures.copied_bound(np.count_nonzero(a), np.count_nonzero(b), grid)[0] == grid.k * np.count_nonzero(a) + grid.m * np.count_nonzero(b)
    spark = x.spark
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        count = lambda p: tiled_product(x, y, grid, p).df._jdf.queryExecution().executedPlan().toString().count("Exchange ")
        assert (count("row"), count("tile"), count("random")) == (2, 2, 3)
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_bad_shapes_and_cells(spark, pair):
    _, _, x, y = pair
    with pytest.raises(ValueError):
        tiled_product(x, x)
    with pytest.raises(ValueError):
        TileGrid.of(3, 3, 3, 0, 1, 1)
    bad = Cells(spark.createDataFrame([(0, 0, float("nan")), (None, 1, 1.0)], "i long, j long, v double"), 2, 2)
    with pytest.raises(ValueError):
        C.validated(bad)
    empty = Cells(spark.createDataFrame([], "i long, j long, v long"), 5, 7)
    assert tiled_product(empty, y).df.count() == 0


def test_forms_convert_back(pair):
    a, _, x, _ = pair
    assert (dense(C.from_tiles(C.to_tiles(x, 2, 3), 2, 3, 5, 7)) == a).all()
    assert (dense(C.from_rows(C.to_rows(x), 5, 7)) == a).all()
    assert (dense(C.from_maps(C.to_maps(x), 5, 7)) == a).all()
    assert (dense(x.t) == a.T).all()
    assert (dense(C.drop_zeros(C.axpy(-1, x, x))) == 0).all()


def test_similarity(spark, pair):
    a, _, x, _ = pair
    assert (dense(similarity.gram_rows(x)) == a @ a.T).all()
    assert (dense(similarity.gram_cols(x)) == a.T @ a).all()
    d = dense(similarity.row_distances(x, x))
    assert np.allclose(d, np.sqrt(((a[:, None] - a[None]) ** 2).sum(axis=2)))


def test_generator_density(spark):
    n = random_matrix(spark, 200, 100, 0.125, seed=5).nnz()
    assert abs(n - 2500) < 4 * np.sqrt(20000 * 0.125 * 0.875)
    assert n == random_matrix(spark, 200, 100, 0.125, seed=5, parts=3).nnz()


@pytest.mark.parametrize("dangling", ["uniform", "drop", "self"])
@pytest.mark.parametrize("d", [0.85, None])
def test_pagerank(spark, dangling, d):
    edges = [(0, 1), (0, 2), (1, 2), (1, 2), (2, 0), (3, 2), (2, 4)]
    got = pagerank.pagerank(spark.createDataFrame(edges, "src long, dst long"), d=d, iters=6, dangling=dangling)
    want = baselines.local_pagerank(5, edges, d, 6, dangling)
    assert np.allclose([r["r"] for r in got.orderBy("id").collect()], want)
    if dangling != "drop":
        assert abs(pagerank.rank_mass(got) - 1) < 1e-12


def test_factorisation(spark):
    rng = np.random.default_rng(2)
    a = rng.integers(0, 5, (6, 5)).astype(float)
    trace: list[float] = []
    w, ht = nmf.nmf(sparse(spark, a), 2, 2, trace=trace)
    assert measures.is_non_increasing(trace)
    init = [np.array([[((i * 7919 + j * 104729 + s) % 1009 + 1) / 1010 for j in range(2)] for i in range(n)]) for n, s in ((6, 17), (5, 31))]
    _, _, want = baselines.local_nmf(a, init[0], init[1].T, 2)
    assert np.allclose(trace, want)
    got = np.array([r["vec"] for r in w.orderBy("i").collect()]) @ np.array([r["vec"] for r in ht.orderBy("i").collect()]).T
    assert abs(((a - got) ** 2).sum() - trace[-1]) < 1e-9


def test_support_vector_machine(spark):
    x = np.array([[1.0, 0.2], [0.8, 0.1], [-1.0, -0.3], [-0.7, 0.2], [0.9, -0.4]])
    y = np.array([1.0, 1, -1, -1, 1])
    t = sparse(spark, x)
    labels = spark.createDataFrame([(i, float(v)) for i, v in enumerate(y)], "i long, v double")
    want = baselines.svm_ascent(x, y, 0.05, 6)
    for mode in ("implicit", "materialised"):
        model = svm.svm_fit(t, labels, eta=0.05, iters=6, kernel_mode=mode)
        assert np.allclose([r["v"] for r in model.alpha.orderBy("i").collect()], want)
    assert [r["label"] for r in svm.svm_predict(model, t).orderBy("i").collect()] == y.tolist()
    k = svm.linear_kernel(t, bias=1.0)
    forms = [[r["v"] for r in svm.svm_gradient(k, labels, model.alpha, f).orderBy("i").collect()] for f in ("elementwise", "vector")]
    assert np.allclose(*forms)
    assert np.allclose(iterate.solve_gram(k, labels) @ (x @ x.T + 1), y, atol=1.0)
    assert baselines.svm_reference(x, y).min() >= 0


def test_measures():
    assert abs(measures.loglog_fit([1, 2, 4], [baselines.cubic_prediction(1, 2, m) for m in (1, 2, 4)]) - 3) < 1e-9
    assert measures.relative_speedup({1: 8.0, 4: 2.0})[4] == 4
    assert baselines.amdahl(8, 0.0) == 8
    assert 0.38 < measures.expected_output_density(2**13, 2**-7, 2**-7) < 0.40


def test_normal_quantile(spark):
    row = spark.range(1).select(*[F.round(pagerank.normal_quantile(F.lit(p)), 4).alias(f"q{i}") for i, p in enumerate((0.5, 0.975, 0.001))]).first()
    assert tuple(row) == (0.0, 1.96, -3.0902)


def test_stream_equals_batch(spark, tmp_path):
    from tilealg.streaming import incremental

    rows = [(k, k % 3, f"2024-01-01 0{k % 5}:1{k % 6}:00", "ab"[k % 2]) for k in range(40)]
    events = spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string").withColumn("ts", F.col("ts").cast("timestamp"))
    for part in range(2):
        events.where(F.col("event_id") % 2 == part).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = incremental.tumbling_counts(stream, late="10 hours").writeStream.format("memory").queryName("tumbled").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination(60)
    want = {tuple(r) for r in incremental.tumbling_counts(events).collect()}
    assert {tuple(r) for r in spark.table("tumbled").collect()} == want
    keeper = incremental.RunningGram(str(tmp_path / "gram"))
    stream.writeStream.foreachBatch(keeper).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination(60)
    c = events.groupBy("user_id", "event_type").count()
    n = {(r[0], r[1]): r[2] for r in c.collect()}
    got = {(r["a"], r["b"]): r["v"] for r in keeper.gram(spark).collect()}
    assert got == {(a, b): sum(n.get((u, a), 0) * n.get((u, b), 0) for u in range(3)) for a in "ab" for b in "ab"}
    again = incremental.RunningGram(str(tmp_path / "gram"))
    more = spark.createDataFrame([(0, "a"), (7, "b")], "user_id long, event_type string")
    again(more, keeper.done)
    assert {(r["a"], r["b"]): r["v"] for r in again.gram(spark).collect()} == got
    again(more, keeper.done + 1)
    n[(0, "a")], n[(7, "b")] = n.get((0, "a"), 0) + 1, 1
    got = {(r["a"], r["b"]): r["v"] for r in incremental.RunningGram(str(tmp_path / "gram")).gram(spark).collect()}
    assert got == {(a, b): sum(n.get((u, a), 0) * n.get((u, b), 0) for u in (0, 1, 2, 7)) for a in "ab" for b in "ab"}


def test_local_factor_update_equals_the_distributed_one(spark):
    of = lambda rows: spark.createDataFrame(rows, "i long, vec array<double>")
    h, x, y = of([(0, [1.0, 2.0]), (1, [0.0, 4.0]), (2, [3.0, 1.0])]), of([(0, [2.0, 0.0]), (1, [5.0, 6.0])]), of([(0, [4.0, 0.0]), (1, [0.0, 0.0]), (2, [1.0, 1.0])])
    rows = lambda df: sorted((r["i"], r["vec"]) for r in df.collect())
    want = rows(nmf.nmf_apply(h, x, y))
    assert rows(nmf.nmf_apply_local(h, x, y)) == want == rows(nmf.nmf_apply_local(h, x, y, most_values=2))


def test_bounds_of_what_is_shipped(spark):
    rng = np.random.default_rng(3)
    t = rng.integers(0, 4, (6, 4)).astype(float)
    k = sparse(spark, t @ t.T)
    y = spark.createDataFrame([(i, float(s)) for i, s in enumerate((1, -1, 1, 1, -1, -1))], "i long, v double")
    alpha = spark.createDataFrame([(i, i / 10) for i in range(6)], "i long, v double")
    rows = lambda df: sorted((r["i"], round(r["v"], 9)) for r in df.collect())
    assert rows(svm.svm_gradient(k, y, alpha)) == rows(svm.svm_gradient(k, y, alpha, most_rows=2)) == rows(svm.svm_gradient(k, y, alpha, form="vector"))
    with pytest.raises(ValueError, match="implicit"):
        svm.linear_kernel(k, bias=1.0, most_cells=35)


def test_plans_of_the_planner_are_kept(spark, pair):
    from tilealg.plans.planner import plan_product, preset

    a, b, x, y = pair
    for placements in (("row",), ("tile",), ("random",)):
        plan = plan_product(x, y, 4, placements=placements)
        assert plan.placement == placements[0] and np.isfinite(plan.cost)
        assert (dense(tiled_product(x, y, placement=plan.placement, workers=4)) == a @ b).all()
    chosen = plan_product(x, y, 4)
    text = tiled_product(x, y, workers=4).df._jdf.queryExecution().optimizedPlan().toString()
    assert ("Aggregate [pid" in text or "Aggregate [pid" in text.replace("#", " ")) == (chosen.placement != "random") or chosen.placement == "random"
    one = Cells(spark.createDataFrame([(0, 0, 3)], "i long, j long, v long"), 1, 1)
    assert np.isfinite(plan_product(one, one, 4, tile_bytes=1).cost) and dense(tiled_product(one, one)).tolist() == [[9.0]]
    assert preset("kernel", 9, 5, 9, 8).m == preset("kernel", 9, 5, 9, 8).k == 4


@pytest.mark.parametrize("placement", ["row", "tile", "random"])
def test_half_a_gram_by_tiles(pair, placement):
    a, _, x, _ = pair
    for m, n in ((1, 1), (2, 3), (5, 7)):
        got = similarity.gram_rows(x, grid=TileGrid.of(5, 7, 5, m, n, m), placement=placement, workers=3)
        assert (dense(got) == a @ a.T).all()
    with pytest.raises(ValueError):
        similarity.gram_rows(x, grid=TileGrid.of(5, 7, 5, 2, 1, 3))
    with pytest.raises(ValueError):
        similarity.gram_rows(x, combine=False)


def test_blocks_hold_their_bounds(spark, monkeypatch):
    from tilealg.operators import product

    rng = np.random.default_rng(5)
    a, b = rng.integers(-3, 4, (9, 6)), rng.integers(-3, 4, (6, 8))
    x, y = sparse(spark, a), sparse(spark, b)
    monkeypatch.setattr(product, "STRIP", 5)
    hit = (a != 0).astype(int) @ (b != 0).astype(int) > 0
    got = tiled_product_blocks(x, y, TileGrid.of(9, 6, 8, 2, 2, 2))
    assert (dense(got) == a @ b).all() and got.df.count() == hit.sum()
    with pytest.raises(ValueError, match="finer"):
        tiled_product_blocks(x, y, TileGrid.of(9, 6, 8), most_bytes=100)
    shipped = product.ship_block(spark, np.eye(3) * 2)
    rows = spark.createDataFrame([(0, [1.0, 2.0, 3.0])], "i long, vec array<double>")
    for _ in range(2):
        assert product.broadcast_rows(rows, shipped).first()["vec"] == [2.0, 4.0, 6.0]
    shipped.destroy()
    with pytest.raises(ValueError):
        product.ship_block(spark, np.eye(3), most_bytes=8)


def test_moved_partials_by_placement(pair):
    _, _, x, y = pair
    grid = TileGrid.of(5, 7, 3, 2, 3, 2)
    rows = {p: measures.intermediate_counts(x, y, grid, p, 4).first() for p in ("row", "tile", "random")}
    assert rows["row"].moved == rows["tile"].moved == 0 < rows["random"].moved <= rows["random"].partials
    assert rows["random"].moved_bytes > rows["row"].moved_bytes and len({r.partials for r in rows.values()}) == 1


def test_exchanges_of_a_rank_step(spark):
    """Links and ranks lie by source and id, so a step moves what is sent and one number."""
    edges = spark.createDataFrame([(0, 1), (1, 2), (2, 0), (0, 2), (3, 0), (2, 4)], "src long, dst long")
    seen = []
    keep = pagerank.run
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        pagerank.run = lambda step, state, *rest: (seen.append(step(iterate.cut(step(state)))), keep(step, state, *rest))[1]
        trace = []
        ranks = pagerank.pagerank(edges, iters=3, dangling="drop", trace=trace)
        assert len(trace) == 3 and trace[-1] < trace[0]  # distances of successive states
        text = seen[0]._jdf.queryExecution().executedPlan().toString()
        assert text.count("Exchange ") == 1, text
        assert ranks.count() == 5
    finally:
        pagerank.run = keep
        spark.conf.unset("spark.sql.adaptive.enabled")
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    low = pagerank.low_rank_group(ranks, 1.0).first()
    assert low.pages == 5 and abs(low.mass - pagerank.rank_mass(ranks)) < 1e-12


def test_states_that_nothing_reads_are_deleted(spark):
    folder = Path(spark.sparkContext._jsc.sc().getCheckpointDir().get().removeprefix("file:")) if spark.sparkContext._jsc.sc().getCheckpointDir().isDefined() else None
    x = iterate.cut(spark.range(4).select(F.col("id").alias("i"), F.lit(1.0).alias("v")))
    folder = folder or Path(spark.sparkContext._jsc.sc().getCheckpointDir().get().removeprefix("file:"))
    before = len(list(folder.iterdir()))
    out = iterate.run(lambda s: s.select("i", (F.col("v") * 2).alias("v")), x, 6)
    assert out.agg(F.sum("v")).first()[0] == 4 * 64 and len(list(folder.iterdir())) == before + 1 and x.count() == 4


def test_one_loop_for_all_classes(spark):
    x = np.array([[1.0, 0.2], [0.8, 0.1], [-1.0, -0.3], [-0.7, 0.2], [0.1, 2.0], [0.2, 1.5]])
    names = ["a", "a", "b", "b", "c", "c"]
    t, classes = sparse(spark, x), spark.createDataFrame(list(enumerate(names)), "i long, name string")
    for mode in ("implicit", "materialised"):
        model = svm.svm_fit_ovr(t, classes, ["a", "b", "c"], eta=0.05, iters=6, kernel_mode=mode)
        got = {(r.i, r.j): r.v for r in model.alpha.collect()}
        for j, n in enumerate("abc"):
            want = baselines.svm_ascent(x, np.array([1.0 if m == n else -1.0 for m in names]), 0.05, 6)
            assert np.allclose([got[i, j] for i in range(6)], want)
    assert [r["name"] for r in svm.svm_predict_ovr(model, t).orderBy("i").collect()] == names


def test_dual_objective_and_steps(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(6, 3))
    y = np.array([1.0, -1, 1, 1, -1, -1])
    t, labels = sparse(spark, x), spark.createDataFrame([(i, float(v)) for i, v in enumerate(y)], "i long, v double")
    k = svm.linear_kernel(t, bias=1.0)
    full = x @ x.T + 1
    alpha = np.arange(6) / 10
    state = spark.createDataFrame([(i, float(v)) for i, v in enumerate(alpha)], "i long, v double")
    assert abs(svm.svm_dual_objective(k, labels, state) - (alpha.sum() - 0.5 * (y * alpha) @ full @ (y * alpha))) < 1e-9
    slope = 1 - y * (full @ (y * alpha))
    gap = max(0.0 if (a <= 0 and g < 0) or (a >= 0.4 and g > 0) else abs(g) for a, g in zip(alpha, slope, strict=True))
    assert abs(measures.kkt_gap(k, labels, state, 0.4) - gap) < 1e-9
    top = 1 / np.linalg.eigvalsh(full)[-1]
    assert abs(svm.kernel_step(t, labels.select("i"), 1.0, 6) / top - 1) < 0.1
    assert abs(iterate.step_size(k, "power", 6) / top - 1) < 0.1
    model = svm.svm_fit(t, labels, eta=top, iters=3, kernel_mode="materialised", trace=True)
    assert measures.is_non_decreasing(model.objective)


def test_factor_modes(spark):
    rng = np.random.default_rng(4)
    a = rng.integers(1, 5, (6, 5)).astype(float)
    x = sparse(spark, a)
    of = lambda m: spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(m)], "i long, vec array<double>")
    w, h = rng.random((6, 2)) + 0.1, rng.random((5, 2)) + 0.1
    same, _ = nmf.nmf(x, 2, 2, init=(of(w), of(h)), order=("H",))
    assert np.allclose([r["vec"] for r in same.orderBy("i").collect()], w)
    error = ((a - w @ h.T) ** 2).sum()
    assert abs(nmf.gaussian_nll(x, of(w), of(h), 2.0) - (error / 8 + 30 * np.log(2 * np.sqrt(2 * np.pi)))) < 1e-9
    assert np.allclose(dense(nmf.nmf_x_tiled(of(w), x)), w.T @ a)


def test_rows_are_split_whole(spark, pair):
    a, _, x, _ = pair
    parts = C.split_rows(x, 3).df.withColumn("part", F.spark_partition_id()).groupBy("i").agg(F.count_distinct("part").alias("n")).collect()
    assert {r["n"] for r in parts} == {1}


def test_library_block_product(spark, pair):
    a, b, x, y = pair
    assert np.allclose(baselines.library_block_product(x, y, 2).toLocalMatrix().toArray(), a @ b)


def test_as_of_and_interval_joins(spark):
    from tilealg.operators import joins

    left = spark.createDataFrame([("a", 5, 1), ("a", 1, 2), ("b", 9, 3), (None, 4, 4), ("a", 5, 5)], "k string, at long, id long")
    right = spark.createDataFrame([("a", 2, "x"), ("a", 5, "y"), ("a", 5, "z"), ("b", 10, "w"), ("c", 1, "v")], "k string, at long, got string")
    got = {r.id: r.got for r in joins.asof_join(left, right, "k", "at", ["got"]).collect()}
    assert got == {1: "z", 2: None, 3: None, 4: None, 5: "z"}
    points = spark.createDataFrame([(x,) for x in range(-5, 30)], "p long")
    spans = spark.createDataFrame([(1, -3, 4), (2, 0, 25), (3, 7, 7), (4, 9, 3), (5, 28, 90), (6, None, 4)], "s long, low long, high long")
    got = sorted((r.p, r.s) for r in joins.interval_join(points, spans, "p", "low", "high", 4).collect())
    assert got == sorted((p, s) for p in range(-5, 30) for s, low, high in ((1, -3, 4), (2, 0, 25), (5, 28, 90)) if low <= p < high)


def test_streams_of_windows_sessions_links_and_ranks(spark, tmp_path):
    from tilealg.streaming import incremental

    rows = [(k, k % 3, f"2024-01-01 {k // 6:02d}:{(k * 7) % 60:02d}:00", "abc"[k * k % 3]) for k in range(48)]
    events = spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string").withColumn("ts", F.col("ts").cast("timestamp"))
    end = spark.createDataFrame([(900 + u, u, "2024-02-01 00:00:00", "z") for u in range(3)], "event_id long, user_id long, ts string, event_type string").withColumn("ts", F.col("ts").cast("timestamp"))
    for part in (events.where("event_id < 20"), events.where("event_id >= 20"), end, end.withColumn("event_id", F.col("event_id") + 50)):
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))

    def drained(df, name, mode="append"):
        df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination(120)
        return sorted(map(tuple, spark.table(name).collect()), key=str)

    whole = events.union(end).union(end.withColumn("event_id", F.col("event_id") + 50))
    closed = lambda df: sorted((tuple(r) for r in df.collect() if r["start"].month == 1 and r["start"].year == 2024 and r["start"].day < 31), key=str)
    for f in (incremental.sliding_counts, incremental.session_counts):
        got = [r for r in drained(f(stream(), late="20 hours"), f.__name__) if r[0].month == 1 and r[0].day < 31]
        assert got == closed(f(whole))
    assert len(drained(incremental.once(stream(), late="60 days").select("event_id"), "once")) == 54
    linked = drained(incremental.link_gaps(stream(), late="20 hours"), "linked")
    want = []
    for u in range(3):
        own = sorted((r.ts, r.event_id, r.event_type) for r in events.where(F.col("user_id") == u).collect())
        want += [(a[2], b[2], int((b[0] - a[0]).total_seconds() * 1e6)) for a, b in zip(own, own[1:], strict=False)]
    assert [x for x in linked if "z" not in x[:2]] == sorted(want, key=str)
    refresh = incremental.refresh_ranks(lambda: spark.createDataFrame([("a", "b", 2), ("b", "a", 1), ("b", "c", 1)], "src string, dst string, w long"), iters=5)
    refresh(events, 0)
    assert abs(refresh.latest.agg(F.sum("r")).first()[0] - 1) < 1e-9


def test_workers_need_no_copy_of_the_library(tmp_path):
    """Python workers of a session started elsewhere, with the library on the driver's path alone."""
    code = f"""
import sys
sys.path.insert(0, {str(ROOT)!r})
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
spark = SparkSession.builder.master("local[1]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "1").getOrCreate()
from tilealg.functions.registered import register, vector_norm
from tilealg.operators.cells import Cells
from tilealg.operators.grid import TileGrid
from tilealg.operators.product import broadcast_rows, tiled_product_blocks
a = Cells(spark.createDataFrame([(0, 0, 2.0), (1, 1, 3.0)], "i long, j long, v double"), 2, 2)
print("BLOCKS", tiled_product_blocks(a, a, TileGrid.of(2, 2, 2, 1, 1, 1)).df.agg(F.sum("v")).first()[0])
register(spark)
print("COPIES", spark.sql("select * from mat_copies(3)").count())
v = spark.createDataFrame([(0, [3.0, 4.0])], "i long, vec array<double>")
print("NORM", v.select(vector_norm("vec")).first()[0])
import numpy as np
print("ROWS", broadcast_rows(v, np.eye(2)).first()["vec"])
"""
    path = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=path, capture_output=True, text=True, timeout=180)
    assert done.stdout.split() == ["BLOCKS", "13.0", "COPIES", "3", "NORM", "5.0", "ROWS", "[3.0,", "4.0]"], done.stderr[-2000:]

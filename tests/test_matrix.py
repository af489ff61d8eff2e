"""Golden examples, identities and edge cases of the matrix methods."""

from __future__ import annotations

import math
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridsparse.functions import permutations as perms
from gridsparse.matrix import SparseMatrix, from_arrays, from_triples
from gridsparse.operators import assign, baselines, build, contract, elementwise, graph, indexing, layout, measures, product
from gridsparse.operators import kernels
from gridsparse.operators.baselines import dense, mllib_block, one_processor, to_dense
from gridsparse.operators.layout import Grid
from gridsparse.semiring import Semiring
from gridsparse.plans import planner
from gridsparse.sources import generators
from gridsparse.sources.tables import count_keys

STRATEGIES = [
    {"strategy": "inner"}, {"strategy": "grid", "grid": Grid(2, 3)}, {"strategy": "grid", "grid": Grid(3, 2, inner=2, layout="hash")},
    {"strategy": "broadcast"}, {"strategy": "rowwise_1d", "grid": Grid(3, 1)}, {"mode": "loop", "block": 5}, {"mode": "loop", "block": 4, "merge": "eager"},
    {"mode": "loop", "block": 3, "merge": "threshold", "every": 2}, {"strategy": "grid", "grid": Grid(2, 2), "kernel": "outer", "block": 7},
    {"strategy": "grid", "grid": Grid(2, 2), "kernel": "columnwise"}, {"split_heavy": 4}, {"strategy": "auto"},
    {"strategy": "broadcast_left"}, {"mode": "loop", "block": 5, "strategy": "grid", "grid": Grid(2, 3)}, {"strategy": "grid", "grid": Grid(2, 3), "kernel": "outer"},
]


def random_matrix(spark, m, n, share, seed):
    rng = np.random.default_rng(seed)
    full = rng.integers(1, 9, (m, n)) * (rng.random((m, n)) < share)
    i, j = np.nonzero(full)
    return from_arrays(spark, i, j, [int(x) for x in full[i, j]], (m, n), kind="long"), full


@pytest.fixture(scope="module")
def pair(spark):
    return random_matrix(spark, 17, 13, 0.3, 1), random_matrix(spark, 13, 19, 0.3, 2)


@pytest.mark.parametrize("options", STRATEGIES, ids=str)
def test_strategies_agree_with_dense(pair, options):
    (a, fa), (b, fb) = pair
    assert (to_dense(a.multiply(b, **options)) == fa @ fb).all()


@pytest.mark.parametrize("ring", [Semiring.min_plus(), Semiring.max_plus(), Semiring.max_min(), Semiring.min_max()], ids=lambda r: r.name)
def test_semirings_against_dense(pair, ring):
    (a, fa), (b, fb) = pair
    add, mul = (getattr(np, f) for f in ring.ufunc)
    rows = {(r["i"], r["j"]): r["v"] for r in a.multiply(b, semiring=ring).df.collect()}
    kernel = {(r["i"], r["j"]): r["v"] for r in a.multiply(b, semiring=ring, strategy="grid", grid=Grid(2, 2), kernel="outer").df.collect()}
    for i in range(17):
        for j in range(19):
            both = [k for k in range(13) if fa[i, k] and fb[k, j]]
            want = add.reduce([mul(fa[i, k], fb[k, j]) for k in both]) if both else None
            assert rows.get((i, j)) == want == kernel.get((i, j))


def test_identities(spark, pair):
    (a, _), (b, _) = pair
    c, _ = random_matrix(spark, 19, 7, 0.3, 3)
    assert elementwise.equals(a.multiply(b).multiply(c), a.multiply(b.multiply(c)))
    assert elementwise.equals(a.multiply(b).transpose(), b.transpose().multiply(a.transpose()))
    for order in ("left", "right", "auto"):
        assert elementwise.equals(product.multiply_chain([a, b, c], order), a.multiply(b).multiply(c))
    assert measures.chain_products(a, b, c)["left"] == measures.products(a, b) + measures.products(a.multiply(b), c)


def test_packed_column_storage(spark):
    m = from_arrays(spark, [6, 8, 4, 2], [1, 1, 7, 8], [0.1, 0.2, 0.3, 0.4], (9, 9), base=1)
    assert layout.pack_csc(m, base=1) == ([1, 3, 3, 3, 3, 3, 3, 4, 5, 5], [6, 8, 4, 2], [0.1, 0.2, 0.3, 0.4])
    block = layout.pack_dcsc(m, Grid(1, 1), aux=True).first().asDict()
    assert [j + 1 for j in block["jc"]] == [1, 7, 8] and [p + 1 for p in block["cp"]] == [1, 3, 4, 5] and [i + 1 for i in block["ir"]] == [6, 8, 4, 2]
    assert layout.dcsc_column(block, 0) == [(5, 0.1), (7, 0.2)] and layout.dcsc_column(block, 3) == []
    assert [e[:2] for e in layout.dcsc_column_range(block, 1, 8)] == [(3, 6), (1, 7)]
    assert elementwise.equals(layout.unpack_dcsc(layout.pack_dcsc(m, Grid(2, 3)), m.shape), m)


def test_selector_example(spark):
    s = build.row_selector(perms.index_vector(spark, [x - 1 for x in (7, 2, 5, 8, 1, 3)]), 6, 9)
    assert sorted((r["i"] + 1, r["j"] + 1) for r in s.df.collect()) == [(1, 7), (2, 2), (3, 5), (4, 8), (5, 1), (6, 3)] and s.shape == (6, 9)


def test_stage_owners():
    assert layout.stages(100_000, 5_000) == 20
    assert [layout.stage_owner(s, 5_000, 100_000, 4) for s in range(20)] == [s // 5 for s in range(20)]
    assert [layout.stage_owner(s, 5_000, 100_000, 5) for s in range(20)] == [s // 4 for s in range(20)]


def test_extract(spark, pair):
    (a, fa), _ = pair
    rows, cols = [3, 3, 16, 0], [12, 1, 1]
    i, j = perms.index_vector(spark, rows), perms.index_vector(spark, cols)
    for options in ({"via": "product", "order": "left"}, {"via": "product", "order": "right"}, {"via": "join"}):
        assert (to_dense(indexing.extract(a, i, j, (4, 3), **options)) == fa[np.ix_(rows, cols)]).all()
    empty = spark.createDataFrame([], "pos long, idx long")
    assert indexing.extract(a, empty, j, (0, 3)).df.count() == 0
    with pytest.raises(IndexError):
        indexing.extract(a, perms.index_vector(spark, [17]), None, (1, 13), validate=True)
    assert (to_dense(indexing.window(a, 2, 9, 4, 8)) == fa[2:9, 4:8]).all()


def test_permutations(spark, pair):
    for method in ("hash", "affine", "feistel"):
        p = perms.random_permutation(spark, 97, 7, method)
        assert sorted(r["idx"] for r in p.collect()) == list(range(97)) == sorted(r["pos"] for r in p.collect())
    (a, _), _ = pair
    sq = a.multiply(a.transpose())
    p = perms.random_permutation(spark, 17)
    there = indexing.permute(sq, p, p)
    back = p.select(p.idx.alias("pos"), p.pos.alias("idx"))
    assert elementwise.equals(indexing.permute(there, back, back), sq)
    assert elementwise.equals(there, indexing.permute_by_map(sq, p))
    assert elementwise.equals(product.permuted_multiply(sq, sq, p), indexing.permute(sq.multiply(sq), p, p))


def test_assign(spark, pair):
    (a, fa), _ = pair
    rows, cols = [5, 2, 11], [0, 7]
    i, j = perms.index_vector(spark, rows), perms.index_vector(spark, cols)
    b, fb = random_matrix(spark, 3, 2, 0.6, 9)
    want = fa.copy()
    want[np.ix_(rows, cols)] = fb
    for options in ({}, {"via": "product"}, {"clear": "subtract"}):
        got = assign.assign(a, i, j, b, **options)
        assert (to_dense(got) == want).all()
        assert elementwise.equals(indexing.extract(got, i, j, (3, 2)), b)
    assert elementwise.equals(assign.assign(a, i, j, indexing.extract(a, i, j, (3, 2))), a)
    with pytest.raises(ValueError):
        assign.assign(a, perms.index_vector(spark, [1, 1, 2]), j, b)
    more = fa.copy()
    np.add.at(more, np.ix_([1, 1, 2], cols), fb)
    assert (to_dense(assign.extend_add(a, perms.index_vector(spark, [1, 1, 2]), j, b)) == more).all()


def test_assign_special_values(spark):
    a = from_arrays(spark, [0, 0, 1, 1], [0, 1, 0, 1], [math.nan, math.inf, 0.0, 2.0], (2, 2))
    b = from_arrays(spark, [0], [0], [5.0], (1, 1))
    at = perms.index_vector(spark, [0])
    got = {(r["i"], r["j"]): r["v"] for r in assign.assign(a, at, at, b).df.collect()}
    assert got == {(0, 0): 5.0, (0, 1): math.inf, (1, 0): 0.0, (1, 1): 2.0}


def test_dense_window_bounds(spark):
    cells = spark.range(64).selectExpr("id div 8 as i", "id % 8 as j", "1L as v")
    a = SparseMatrix(cells, 16, 16)
    w = perms.index_vector(spark, range(8))
    assert measures.nnz(indexing.extract(a, w, w, (8, 8))) == 64 > 16


def test_contraction(spark, pair):
    (a, _), _ = pair
    sq = a.multiply(a.transpose())
    s = build.restriction(spark, 17, 4)
    fused = contract.contract(sq, s)
    for order in ("left", "right"):
        assert elementwise.equals(contract.contract(sq, s, order), fused)
    assert elementwise.equals(contract.galerkin(sq, s, True), contract.galerkin(sq, s, False))
    total = lambda m: m.df.groupBy().sum("v").first()[0]
    assert total(fused) == total(sq)


def test_graphs(spark):
    edges = [(0, 1), (1, 2), (2, 3), (3, 4), (4, 5), (1, 4)]
    both = edges + [(b, a) for a, b in edges]
    g = from_arrays(spark, *zip(*both, strict=True), [1] * 12, (6, 6), kind="long")
    levels = {(r["source"], r["vertex"]): r["level"] for r in graph.bfs_multi(g, spark.createDataFrame([(0,), (5,)], "vertex long")).collect()}
    assert [levels[0, v] for v in range(6)] == [0, 1, 2, 3, 2, 3] and levels[5, 0] == 3
    dist = {(r["i"], r["j"]): r["v"] for r in graph.apsp(g).df.collect()}
    assert dist[0, 5] == 3 and dist[2, 5] == 3 and dist[3, 3] == 0
    score = {r["vertex"]: r["score"] for r in graph.betweenness(g, spark.range(6).withColumnRenamed("id", "vertex")).collect()}
    assert score[1] > score[0] and score[4] == score[1] and score[0] == 0
    triangle = from_arrays(spark, [0, 1, 0, 2, 1, 2], [1, 0, 2, 0, 2, 1], [1] * 6, (3, 3), kind="long")
    assert graph.triangles(triangle) == 1 and graph.triangles(g) == 0


def test_measures(spark, pair):
    (a, fa), (b, fb) = pair
    want = int(((fa != 0).sum(axis=0) * (fb != 0).sum(axis=1)).sum())
    assert measures.products(a, b) == want and measures.flops2(a, b) == 2 * want
    words = measures.comm_words(a, b, Grid(2, 3)).groupBy().sum("words").first()[0]
    assert words == 3 * measures.nnz(a) + 2 * measures.nnz(b)
    assert measures.nnz(a.multiply(b)) <= want
    assert measures.dense_flops(1 << 24, 1 << 24, 1 << 24) == 2 * (1 << 72)
    assert abs(measures.loglog_slope([1, 4, 16], [1, 2, 4]) - 0.5) < 1e-12
    assert measures.comm_model(64, 8e6, 8e6, 1e4, 10) > measures.comm_model(256, 8e6, 8e6, 1e4, 10)
    narrow, wide = (layout.storage_words(a, Grid(s, s)).first() for s in (1, 4))
    assert wide["csc_words"] > narrow["csc_words"] and wide["triples_words"] == narrow["triples_words"]


def test_generators(spark):
    a = generators.rmat(spark, 8, seed=1)
    assert a.validate().df.count() == generators.rmat(spark, 8, seed=1, relabel="shared").df.count()
    shared = [generators.rmat(spark, 9, seed=s, relabel="shared") for s in (1, 2)]
    apart = [generators.rmat(spark, 9, seed=s) for s in (1, 2)]
    assert measures.products(*shared) > 2 * measures.products(*apart)
    assert generators.erdos_renyi(spark, 100, 5, 3).df.count() <= 15


def test_edge_shapes(spark):
    none = from_arrays(spark, [], [], [], (4, 4))
    one = from_arrays(spark, [0], [0], [2.0], (1, 1))
    assert none.multiply(none).df.count() == 0 and none.multiply(none, mode="loop", block=2).df.count() == 0
    assert one.multiply(one, strategy="grid", grid=Grid(3, 3)).df.first()["v"] == 4.0
    huge = from_arrays(spark, [0, 1 << 39], [1 << 39, 5], [1.0, 3.0], (1 << 40, 1 << 40))
    assert huge.multiply(huge, strategy="grid", grid=Grid(2, 2), kernel="outer").df.first()["v"] == 3.0
    with pytest.raises(ValueError):
        one.multiply(none)
    with pytest.raises(ValueError):
        from_triples(spark.createDataFrame([(0, 0), (0, 0)], "i long, j long"), "i", "j", None, (1, 1), "error")


def test_plans(spark, pair):
    (a, _), (b, _) = pair
    exchanges = lambda m: m.df._jdf.queryExecution().executedPlan().toString().count("Exchange")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        assert exchanges(a.multiply(b, strategy="grid", grid=Grid(2, 2))) == 2
        picked = indexing.extract(a, perms.index_vector(spark, [1]), None, (1, 13))
        text = picked.df._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastHashJoin" in text and "Aggregate" not in text
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_searches_that_are_not_done_are_errors(spark):
    chain = spark.range(6).select(F.col("id").alias("i"), (F.col("id") + 1).alias("j"), F.lit(1).alias("v"))
    a, sources = SparseMatrix(chain, 7, 7), spark.createDataFrame([(0,)], "vertex long")
    edges = chain.select(F.explode(F.array(F.lit("E"), F.lit("S"))).alias("label"), "i", "j")
    for search in (lambda: graph.bfs_multi(a, sources, 3), lambda: graph.betweenness(a, sources, 3), lambda: graph.cfg_reach([("S", "S", "E")], edges, 2)):
        with pytest.raises(RuntimeError):
            search()
    assert {r["vertex"]: r["level"] for r in graph.bfs_multi(a, sources).collect()} == {k: k for k in range(7)}
    assert {r["vertex"]: r["level"] for r in graph.bfs_multi(a, sources, depth=4).collect()} == {k: k for k in range(5)}


def test_library_and_one_processor_baselines(pair):
    (a, x), (b, y) = pair
    assert (to_dense(mllib_block(a, b, 8)) == x @ y).all() and (to_dense(one_processor(a, b)) == x @ y).all()


def test_library_tasks_are_bounded(spark, pair, monkeypatch):
    """The library's tasks grow in number with the result and the inner range, and no entry goes through Python."""
    (a, x), (b, y) = pair
    parts, splits = baselines.library_tasks(a, b, 2)
    assert parts * baselines.TASK_BLOCKS >= 9 * 10
    monkeypatch.setattr(baselines, "TASK_PRODUCTS", 2)
    assert baselines.library_tasks(a, b, 2)[1] > splits
    monkeypatch.setattr(baselines, "TASK_BLOCKS", 20)
    done = mllib_block(a, b, 2)
    assert (to_dense(done) == x @ y).all()
    assert "Python" not in done.df._jdf.queryExecution().toString()


def test_planner(spark, pair, monkeypatch):
    (a, _), (b, _) = pair
    assert planner.choose(a, b)[0].startswith("broadcast")
    assert planner.choose(b.transpose(), a.transpose())[0].startswith("broadcast")
    wide = b.with_df(b.df.unionAll(b.df.withColumn("j", F.col("j") + 1000)))
    assert planner.choose(a, wide) == ("broadcast_left", None)
    monkeypatch.setattr(planner, "BROADCAST_ENTRIES", 0)
    dense_a, dense_b = (random_matrix(spark, 40, 40, 1.0, k)[0] for k in (1, 2))
    how, grid = planner.choose(dense_a, dense_b)
    assert how == "grid" and grid.cells >= int(spark.conf.get("spark.sql.shuffle.partitions"))
    assert planner.grid_for(10**12, 8).cells >= 10**12 / planner.CELL_PRODUCTS
    exact = measures.nnz(dense_a.multiply(dense_b))
    assert abs(planner.predict_structure(dense_a, dense_b, "sketch", 0.5) / exact - 1) < 0.25


def test_outer_kernel_merges_as_it_goes(monkeypatch):
    import pyarrow as pa

    rng, held = np.random.default_rng(3), []
    reduce = kernels._reduce
    monkeypatch.setattr(kernels, "_reduce", lambda add, i, j, v: held.append(len(i)) or reduce(add, i, j, v))
    i, j, v = rng.integers(0, 20, 4000), rng.permutation(4000), rng.integers(1, 5, 4000)
    k, n, w = rng.permutation(4000), rng.integers(0, 20, 4000), rng.integers(1, 5, 4000)
    a, b = pa.table({"i": i, "j": j, "v": v}), pa.table({"i": k, "j": n, "v": w})
    gi, gj, gv = kernels.outer(a, b, Semiring.plus_times(), most=100)
    want = np.zeros((20, 20), int)
    back = np.argsort(k)
    np.add.at(want, (i, n[back[j]]), v * w[back[j]])
    got = np.zeros((20, 20), int)
    got[gi, gj] = gv
    assert (got == want).all() and max(held) <= 400 + 500


def test_small_tables_and_bounds(spark, monkeypatch):
    assert count_keys(spark.range(1), "id") == 1 and count_keys(spark.range(0), "id") == 0
    with pytest.raises(ValueError):
        layout.pack_csc(SparseMatrix(spark.createDataFrame([], "i long, j long, v long"), 3, 2_000_000))


def test_mask_is_applied_to_the_products(pair):
    (a, x), (b, y) = pair
    mask = a.multiply(b).prune(lambda v: v > 40)
    done = a.multiply(b, mask=mask)
    assert (to_dense(done) == np.where((x @ y) > 40, x @ y, 0)).all()
    plan = done.df._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Aggregate") < plan.index("LeftSemi")  # the sum is above the join


def test_loop_has_a_barrier_and_phases_are_measured(spark, pair):
    (a, x), (b, y) = pair
    done = {}
    found = measures.phase_breakdown(spark, lambda: done.update(c=to_dense(a.multiply(b, mode="loop", block=5))))
    assert (done["c"] == x @ y).all() and found["compute_s"] > 0 and found["moved_mb"] > 0 and found["out_of_memory"] == 0


def test_kernels_hold_slabs_and_runs(spark, monkeypatch):
    """Large cells go slab after slab and give their result in bounded parts, in every layout."""
    import pyarrow as pa

    (a, x), (b, y) = random_matrix(spark, 60, 40, 0.3, 5), random_matrix(spark, 40, 50, 0.3, 6)
    monkeypatch.setattr(product, "CELL_ENTRIES", 50)
    for kernel in ("outer", "columnwise"):
        got = {}
        body = {"outer": kernels.outer_runs, "columnwise": kernels.columnwise_runs}[kernel]
        for i, j, v in body((*np.nonzero(x), x[np.nonzero(x)]), (*np.nonzero(y), y[np.nonzero(y)]), Semiring.plus_times(), most=200):
            assert len(i) <= 200 + 40 * 50 * 0.3
            assert not got.keys() & set(zip(i.tolist(), j.tolist(), strict=True))
            got |= dict(zip(zip(i.tolist(), j.tolist(), strict=True), v.tolist(), strict=True))
        assert got == {(i, j): int((x @ y)[i, j]) for i, j in zip(*(n.tolist() for n in np.nonzero(x @ y)), strict=True)}
        for grid in (Grid(2, 2), Grid(1, 1), Grid(2, 3, inner=2, layout="hash")):
            assert product._slabs(a, b, grid) > 1
            assert (to_dense(a.multiply(b, strategy="grid", grid=grid, kernel=kernel)) == x @ y).all()
        apart = (np.array([0]), np.array([1]), np.array([1])), (np.array([2]), np.array([0]), np.array([1]))
        assert not list(body(*apart, Semiring.plus_times()))
    table = lambda m: pa.table(dict(zip("ijv", (*np.nonzero(m), m[np.nonzero(m)]), strict=True)))
    assert len(kernels.outer(table(x), table(y), Semiring.plus_times())[0]) == (x @ y > 0).sum()


def test_tiled_kernel(spark, monkeypatch):
    """Dense and sparse tiles, entries that cancel, sums that doubles would round, other semirings: all as in whole numbers."""
    monkeypatch.setattr(kernels, "TILE", 8)
    (a, x), (b, y) = random_matrix(spark, 60, 40, 0.3, 5), random_matrix(spark, 40, 50, 0.3, 6)
    x[:20] *= np.random.default_rng(1).integers(0, 50, (20, 40)) == 0  # a sparse part
    x[30:40] *= -1
    x[40, :2], y[:2, 7] = (3, -3), (2, 2)  # cancels
    entries = lambda m: (*np.nonzero(m), m[np.nonzero(m)])
    for scale, least, kind in ((1, 1, int), (1, 40, int), (1, 1 << 40, int), (1 << 45, 1, int), (0.5, 1, float)):
        monkeypatch.setattr(kernels, "DENSE_PRODUCTS", least)
        left, right = x.astype(kind) * scale, y.astype(kind)
        got, want = np.zeros((60, 50), kind), left @ right
        present = np.zeros((60, 50), bool)
        for i, j, v in kernels.tiled_runs(entries(left), entries(right), Semiring.plus_times()):
            assert not present[i, j].any() and v.dtype == want.dtype
            present[i, j], got[i, j] = True, v
        assert (got == want).all() and (present == ((x != 0).astype(int) @ (y != 0).astype(int) > 0)).all()
    unsafe = [(np.array([0, 0]), np.array([0, 1]), np.array([1.0, np.inf])), (np.array([0, 1]), np.array([0, 1]), np.array([1.0, 1.0]))]
    assert {(i, j): v for part in kernels.tiled_runs(*unsafe, Semiring.plus_times()) for i, j, v in zip(*(c.tolist() for c in part), strict=True)} == {(0, 0): 1.0, (0, 1): np.inf}
    assert not list(kernels.tiled_runs((np.array([0]), np.array([1]), np.array([1])), (np.array([2]), np.array([0]), np.array([1])), Semiring.plus_times()))


def test_tiled_product(spark, pair, monkeypatch):
    (a, x), (b, y) = pair
    monkeypatch.setattr(product, "TILED_ENTRIES", 20)
    monkeypatch.setattr(kernels, "TILE", 4)
    finer = product._finer(a, b, Grid(2, 2))
    assert finer.pr > 2 and finer.pc > 2  # no cell holds more than it may
    for grid in (None, Grid(2, 2), Grid(2, 3, inner=2, layout="hash")):
        assert (to_dense(a.multiply(b, strategy="grid", grid=grid, kernel="tiled")) == x @ y).all()
    ring = Semiring.max_plus()
    assert set(a.multiply(b, semiring=ring, strategy="grid", kernel="tiled").df.collect()) == set(a.multiply(b, semiring=ring).df.collect())


def test_third_power_lists_no_products(spark):
    """Powers of a nearly dense graph go tile by tile: no join makes a row for each product."""
    from gridsparse.queries import catalog, matrix  # noqa: F401

    a, x = random_matrix(spark, 30, 30, 0.3, 7)
    assert (to_dense(product.power(a, 3, strategy="grid", kernel="tiled")) == x @ x @ x).all()
    plan = catalog.QUERIES["square_power3"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "Join" not in plan


def test_tiled_grid_moves_packed_blocks(spark, monkeypatch):
    """Copies along the grid are rows of a packed block each, not rows of entries; any grid, whole numbers and fractions, other semirings."""
    monkeypatch.setattr(product, "TILED_ENTRIES", 200)
    (a, x), (b, y) = random_matrix(spark, 60, 30, 0.5, 5), random_matrix(spark, 30, 50, 0.5, 6)
    a, x = a.apply(lambda v: F.when(F.col("i") % 2 == 0, -v).otherwise(v)), x * np.where(np.arange(60) % 2 == 0, -1, 1)[:, None]
    for grid in (Grid(2, 2), Grid(2, 3, inner=2, layout="hash")):
        made = a.multiply(b, strategy="grid", grid=grid, kernel="tiled")
        plan = made.df._jdf.queryExecution().optimizedPlan().toString()
        copied = plan[plan.index("Generate explode") :]
        assert plan.count("FlatMapGroupsInArrow") == 3 and copied.count("FlatMapGroupsInArrow") == 2
        rows = made.df.collect()
        assert len(rows) == ((x != 0).astype(int) @ (y != 0).astype(int) > 0).sum() and all((x @ y)[r["i"], r["j"]] == r["v"] for r in rows)
    half = a.apply(lambda v: v / 2)
    assert (to_dense(half.multiply(b.cast("double"), strategy="grid", kernel="tiled")) == x / 2 @ y).all()
    ring = Semiring.min_plus()
    assert set(a.multiply(b, semiring=ring, strategy="grid", kernel="tiled").df.collect()) == set(a.multiply(b, semiring=ring).df.collect())
    assert a.with_df(a.df.limit(0)).multiply(b, strategy="grid", kernel="tiled").df.count() == 0


def test_products_are_summed_by_one_key(monkeypatch):
    """Sums of equal positions take one sort of a joint key; positions too far apart for one keep two keys."""
    rng = np.random.default_rng(2)
    i, j = (rng.integers(3, 9, 500) for _ in range(2))
    lexsort, calls = np.lexsort, []
    monkeypatch.setattr(np, "lexsort", lambda *a: calls.append(1) or lexsort(*a))
    for far in (1, 1 << 40):
        for v in (rng.integers(-5, 5, 500), rng.random(500), rng.random(500) < 0.5):
            add = np.logical_or if v.dtype == bool else np.add
            x, y, w = kernels._reduce(add, i * far, j * far, v)
            want = {}
            for a, b, c in zip(i * far, j * far, v, strict=True):
                want[b, a] = add(want[b, a], c) if (b, a) in want else c
            assert list(zip(y, x)) == sorted(want) and w.tolist() == pytest.approx([want[k] for k in sorted(want)])
        assert len(calls) == (0 if far == 1 else 3)


def test_packed_products(monkeypatch):
    """Products of packed tiles: dense and listed, signed and cancelling, beyond singles and doubles, fractions, tiles without positions."""
    rng = np.random.default_rng(5)
    x, y = (rng.integers(1, 9, shape) * (rng.random(shape) < 0.4) for shape in ((40, 24), (24, 32)))
    signed = x * rng.choice([-1, 1], x.shape)
    signed[3, :], y[:2, 7] = 0, (2, 2)
    signed[3, :2] = 3, -3

    def tiles(m, dense):
        out = {}
        for ti, tj in np.ndindex(m.shape[0] // 8, m.shape[1] // 8):
            part = m[ti * 8 : ti * 8 + 8, tj * 8 : tj * 8 + 8].ravel()
            at = np.flatnonzero(part).astype(np.uint32)
            if len(at) and (ti, tj) != (1, 1):
                out.setdefault(ti, {})[tj] = (None, part) if dense else (at, part[at])
        return out

    monkeypatch.setattr(kernels, "TILE", 8)
    x[8:16, 8:16], signed[8:16, 8:16], y[8:16, 8:16] = 0, 0, 0
    large = np.where(x > 0, x + (1 << 22), 0)
    for least in (1, 1 << 20):
        monkeypatch.setattr(kernels, "DENSE_PRODUCTS", least)
        for left, dense in ((x, False), (x, True), (signed, False), (large, True), (large << 26, False), (x * 0.5, False)):
            got, present = np.zeros((40, 32), left.dtype), np.zeros((40, 32), bool)
            for ti, tj, at, v in kernels.packed_products(tiles(left, dense), tiles(y.astype(left.dtype), dense), Semiring.plus_times(), left.dtype.name):
                i, j, v = kernels._tile_entries((at, v), ti, tj, left.dtype)
                assert not present[i, j].any()
                present[i, j], got[i, j] = True, v
            assert (got == left @ y).all() and (present == ((left != 0).astype(int) @ (y != 0).astype(int) > 0)).all()


def test_power_writes_no_rows_of_intermediates(spark, monkeypatch):
    """Several tiles and cells, sparse and dense; what is written between the steps is packed by tile."""
    written = []
    monkeypatch.setattr(product, "settle", lambda df, *a, f=product.settle, **o: written.append(df.columns) or f(df, *a, **o))
    monkeypatch.setattr(product, "TILED_ENTRIES", 4000)
    for size, density, exponent in ((1300, 0.004, 4), (600, 0.2, 3)):
        a, x = random_matrix(spark, size, size, density, 9)
        made = product.power(a, exponent, strategy="grid", kernel="tiled")
        want = np.linalg.matrix_power(x, exponent)
        rows = made.df.toPandas()
        assert len(rows) == (want > 0).sum() and (want[rows["i"], rows["j"]] == rows["v"]).all() and made.df.dtypes == [("i", "bigint"), ("j", "bigint"), ("v", "bigint")]
    assert written and all("ti" in columns for columns in written)
    none = a.with_df(a.df.limit(0))
    assert product.power(none, 3, kernel="tiled").df.count() == 0


def test_grammar_reach_doubles_and_falls_back(spark):
    """A long cycle takes few rounds; dense steps and grammars of other forms go round by round, all to the same closure."""
    def closure(pairs):
        out = set(pairs)
        while more := {(i, j) for i, k in out for h, j in pairs if h == k} - out:
            out |= more
        return out

    cycle = [(k, (k + 1) % 40) for k in range(40)]
    bush = [(0, k) for k in range(1, 9)] + [(k, 9) for k in range(1, 9)] + [(9, k) for k in range(10, 18)] + [(17, 0), (17, 18), (18, 19)]
    for pairs, most in ((cycle, 7), (bush, None)):
        frame = spark.createDataFrame(pairs, "i long, j long").select(F.explode(F.array(F.lit("E"), F.lit("S"))).alias("label"), "i", "j")
        for rules in ([("S", "S", "E")], [("S", "E", "S")], [("S", "S", "S")]):
            if pairs is cycle and rules[0][1] == "E":
                continue  # forty rounds
            rows = [tuple(r) for r in graph.cfg_reach(rules, frame, most).collect()]
            assert sorted(rows) == sorted([("S", *x) for x in closure(pairs)] + [("E", *x) for x in pairs])


def test_interpolation_of_a_partition_is_not_summed(spark):
    s = from_arrays(spark, [0, 0, 1, 2], [0, 2, 1, 3], [1, 2, 3, 1], (3, 5), kind="long")
    y = from_arrays(spark, [0, 1, 1, 2], [0, 0, 1, 2], [5, 7, 1, 4], (3, 3), kind="long")
    made = contract.interpolate(s, y)
    assert "Aggregate" not in made.df._jdf.queryExecution().optimizedPlan().toString()
    assert made.shape == (5, 3) and (to_dense(made) == to_dense(s).T @ to_dense(y)).all()
    twice = from_arrays(spark, [0, 1, 1], [0, 0, 1], [1, 2, 3], (3, 5), kind="long")
    assert (to_dense(contract.interpolate(twice, y)) == to_dense(twice).T @ to_dense(y)).all()


def test_packed_tiles():
    """Parts of tiles add to the product: dense and listed, signed, cancelling, beyond doubles, fractions, more inner indices than one step takes."""
    (x, y), rng = (np.random.default_rng(s).integers(1, 9, shape) * (np.random.default_rng(s + 5).random(shape) < 0.3) for s, shape in ((1, (60, 40)), (2, (40, 50)))), np.random.default_rng(3)
    signed = x * rng.choice([-1, 1], x.shape)
    signed[40, :], y[:2, 7] = 0, (2, 2)
    signed[40, :2] = 3, -3
    large = x.copy()
    large[large > 0] += 1 << 30
    entries = lambda m: (*np.nonzero(m), m[np.nonzero(m)])
    for left, inner in ((x, 1024), (x, 7), (signed, 7), (large, 1024), (large << 15, 1024), (x * 0.5, 7), (np.where(x > 1, 0, x) * (np.arange(60) == 9)[:, None], 1024)):
        with pytest.MonkeyPatch.context() as patch:
            patch.setattr(kernels, "INNER", inner)
            parts = list(kernels.packed_tiles(entries(left), entries(y.astype(left.dtype)), Semiring.plus_times(), 8, left is not large))
        batches = [kernels._packed_batch(*p) for p in parts]
        got, present = np.zeros((64, 56), left.dtype), np.zeros((64, 56), bool)
        for tile in {p[:2] for p in parts}:
            mine = [r for r, p in zip(batches, parts, strict=True) if p[:2] == tile]
            again = list(kernels.merge_kernel(8, True)(iter(mine)))
            for rows in kernels.merge_kernel(8, False)(iter(again)):
                i, j, v = (rows.column(c).to_numpy() for c in ("i", "j", "v"))
                assert not present[i, j].any() and v.dtype == left.dtype and i.dtype == j.dtype == np.int64
                present[i, j], got[i, j] = True, v
        assert (got[:60, :50] == left @ y).all() and (present[:60, :50] == ((left != 0).astype(int) @ (y != 0).astype(int) > 0)).all() and present.sum() == present[:60, :50].sum()


def test_loop_adds_slabs_by_tile(spark, monkeypatch):
    """Slabs of a dense product are written and added by tile, not as rows, on any grid and merge; a sparse one keeps its rows, and scratch removes what was written."""
    from gridsparse import storage

    monkeypatch.setattr(product, "DENSE_PRODUCTS", 8)
    monkeypatch.setattr(kernels, "TILE", 4)
    monkeypatch.setattr(product, "CELL_TILES", 2)
    (a, x), (b, y) = random_matrix(spark, 40, 30, 0.5, 5), random_matrix(spark, 30, 35, 0.5, 6)
    assert max(len({strip for _, _, strip in rows}) for rows in product._strips(a.df.selectExpr("*", "j div 8 AS slab"), "i", Grid(3, 1).row_block(product.F.col("i"), 40), 4).values()) >= 4
    for options in ({}, {"strategy": "grid", "grid": Grid(2, 2, layout="hash"), "merge": "threshold", "every": 2}):
        made = a.multiply(b, mode="loop", block=8, kernel="tiled", **options)
        plan = made.df._jdf.queryExecution().optimizedPlan().toString()
        assert "FlatMapGroupsInArrow" in plan and "Aggregate" not in plan
        assert (to_dense(made) == x @ y).all() and made.df.count() == (x @ y > 0).sum()
    sparse, z = random_matrix(spark, 30, 35, 0.05, 7)
    for least, packed in ((1, True), (1 << 12, False)):
        monkeypatch.setattr(product, "PACKED_PRODUCTS", least)
        made = a.multiply(sparse, mode="loop", block=8, kernel="tiled")
        assert ("FlatMapGroupsInArrow" in made.df._jdf.queryExecution().optimizedPlan().toString()) == packed
        assert (to_dense(made) == x @ z).all() and made.df.count() == (x @ z > 0).sum()
    with storage.scratch(spark):
        kept = storage.settle(a.df)
        assert kept.count() == a.df.count()
    path = kept.inputFiles()[0].removeprefix("file://")
    assert not Path(path).exists()

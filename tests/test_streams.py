"""Stores that streams fill, and rows that come too late."""

from __future__ import annotations

import datetime

import pytest
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import layout, packed, relational, selectors
from gridsparse.operators.layout import Grid
from gridsparse.streaming import rows, updates

DAY = datetime.datetime(2024, 1, 1)


def _cells(spark, cells):
    return spark.createDataFrame([(i, j, v, DAY + datetime.timedelta(hours=h)) for i, j, v, h in cells], "i long, j long, v long, at timestamp")


def test_store_rewrites_only_the_blocks_it_touches(spark, tmp_path):
    store = updates.VersionedStore(spark, str(tmp_path), blocks=8)
    assert store.read() is None
    store.apply(_cells(spark, [(i, j, 1, 0) for i in range(40) for j in range(3)]), 0, "extend_add")
    before = dict(store.current)
    store.apply(_cells(spark, [(5, 1, 10, 0), (5, 1, 5, 0), (5, 9, 7, 0)]), 1, "extend_add")
    assert sum(before[b] != v for b, v in store.current.items()) == 1
    store.apply(_cells(spark, [(5, 1, 99, 0)]), 1, "extend_add")  # applied before
    store.apply(_cells(spark, []), 2, "extend_add")
    got = {(r["i"], r["j"]): r["v"] for r in store.read().collect()}
    assert got == {(i, j): 1 for i in range(40) for j in range(3)} | {(5, 1): 16, (5, 9): 7}


def test_store_is_taken_up_by_a_new_driver(spark, tmp_path):
    path = str(tmp_path / "store")
    first = updates.VersionedStore(spark, path, blocks=8)
    assert first.vacuum() == 0
    for n in range(3):
        first.apply(_cells(spark, [(i, n, 1, 0) for i in range(10 * (n + 1))]), n, "extend_add")
    want = sorted(map(tuple, first.read().collect()))
    again = updates.VersionedStore(spark, path, blocks=8)
    assert (again.version, again.current, again.schema) == (first.version, first.current, first.schema)
    again.apply(_cells(spark, [(0, 0, 50, 0)]), 2, "extend_add")  # the batch that the first driver had applied
    assert sorted(map(tuple, again.read().collect())) == want
    _cells(spark, [(3, 3, 1, 0)]).write.parquet(f"{path}/v3/block=1")  # a batch cut off before its manifest
    (tmp_path / "store/manifest/v3").mkdir()
    third = updates.VersionedStore(spark, path, blocks=8)
    assert third.version == 2
    third.apply(_cells(spark, [(0, 0, 50, 0)]), 3, "extend_add")
    assert third.vacuum() > 0 and third.vacuum() == 0
    want = sorted((i, j, v + 50 * (i == j == 0)) for i, j, v in want)
    assert sorted(map(tuple, updates.VersionedStore(spark, path, blocks=8).read().collect())) == want
    with pytest.raises(ValueError):
        updates.VersionedStore(spark, path, blocks=4)


def test_latest_value_wins_in_both_stores(spark, tmp_path):
    batches = [[(0, 0, 1, 5), (0, 1, 2, 5), (1, 0, 3, 5)], [(0, 0, 8, 4), (0, 1, 9, 6), (1, 0, 2, 5), (1, 70_000, 4, 1)]]
    store = updates.VersionedStore(spark, str(tmp_path / "store"))
    for n, batch in enumerate(batches):
        store.apply(_cells(spark, batch), n, "assign")
        _cells(spark, batch).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    want = {(0, 0): 1, (0, 1): 9, (1, 0): 3, (1, 70_000): 4}
    assert {(r["i"], r["j"]): r["v"] for r in store.read().collect()} == want
    stream = spark.readStream.schema("i long, j long, v long, at timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    assert {(r["i"], r["j"]): r["v"] for r in rows.row_store(stream, width=1000).collect()} == want


def test_rows_behind_the_watermark_are_dropped(spark, tmp_path):
    at = lambda day: DAY + datetime.timedelta(days=day)
    for n, batch in enumerate([[(1, at(0)), (2, at(100))], [(4, at(101))], [(3, at(1)), (5, at(102))]]):  # a watermark counts from the batch after next
        spark.createDataFrame(batch, "event_id long, ts timestamp").coalesce(1).write.parquet(str(tmp_path / f"in/{n}"))
    stream = spark.readStream.schema("event_id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in/*"))
    got = updates.run_to_table(updates.deduplicated(stream, late="2 days").select("event_id"))
    assert sorted(r[0] for r in got.collect()) == [1, 2, 4, 5]


@pytest.mark.parametrize("aux", [True, False])
def test_packed_columns(spark, aux):
    cells = [(i, j, float(i * 100 + j)) for i in range(9) for j in (0, 3, 4, 11, 12, 50, 98, 99)]
    a, grid = SparseMatrix(spark.createDataFrame(cells, "i long, j long, v double"), 9, 100), Grid(2, 3)
    blocks = layout.pack_dcsc(a, grid, aux)
    wanted = spark.createDataFrame([(j,) for j in (0, 1, 4, 4, 12, 49, 99, -1, 100, None)], "j long")
    found = packed.columns(blocks, wanted, a.shape, grid, aux).df.collect()
    assert sorted(map(tuple, found)) == sorted(c for c in cells if c[1] in (0, 4, 12, 99))
    for low, high in ((0, 100), (4, 51), (5, 11), (99, 100), (7, 7)):
        found = packed.column_range(blocks, low, high, a.shape, grid).df.collect()
        assert sorted(map(tuple, found)) == sorted(c for c in cells if low <= c[1] < high)


def test_selector_sources(spark):
    index = spark.createDataFrame([(k, (7 * k + 2) % 12) for k in range(9)], "pos long, idx long")
    for source in ("diagonal", "all"):
        placed = selectors.scatter(index, 9, 12, Grid(3, 3), source).collect()
        assert sorted((r["i"], r["j"]) for r in placed) == [(k, (7 * k + 2) % 12) for k in range(9)]
        assert all(r["cell"] == r["i"] // 3 * 3 + r["j"] // 4 for r in placed)
    assert all(r["home"] // 3 == r["cell"] // 3 for r in selectors.located(index, 9, 12, Grid(3, 3)).collect())  # along one row of cells
    with pytest.raises(ValueError):
        selectors.scatter(index, 9, 12, Grid(2, 3))


def test_bernoulli_sample(spark):
    picked = relational.bernoulli_sample(spark.range(20_000), 0.1, 3)
    assert abs(picked.count() - 2000) < 250 and sorted(map(tuple, picked.collect())) == sorted(map(tuple, relational.bernoulli_sample(spark.range(20_000), 0.1, 3).collect()))

"""Every query with SQL against DuckDB on the smallest tables; the rest run."""

from __future__ import annotations

from pathlib import Path

import duckdb
import pytest

import __spark_entry__
from gridsparse.queries import catalog

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not Path(SF).exists(), reason="no test tables")
QUICK = ["prod_inner", "prod_grid_rect", "semiring_min_plus", "extract_join", "assign_join", "contract_fused", "bfs_multi", "storage_words_4", "stage_cells", "r17_asof_join", "r18_interval_join", "stream_extend_add", "stream_assign_last", "stream_windows", "betweenness", "peer_pressure", "markov_cluster_step", "cfg_reach", "w06_restrict_counts", "dcsc_columns_aux", "dcsc_columns_search", "dcsc_column_range", "scatter_words_diagonal", "scatter_words_all", "exchange_words", "selector_exchange", "r48_row_store"]


QUICK += ["r04_data_source", "r52_table_function"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        con.sql(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    return con


@pytest.mark.parametrize("name", QUICK)
def test_query_matches_sql(spark, duck, name):
    got = catalog.QUERIES[name](spark, SF)
    columns = sorted(got.columns)
    want = duck.sql(catalog.ORACLE_SQL[name])
    assert sorted(want.columns) == columns
    order = [want.columns.index(c) for c in columns]
    assert sorted(repr(tuple(r[c] for c in columns)) for r in got.collect()) == sorted(repr(tuple(r[k] for k in order)) for r in want.fetchall())


def test_entry(spark):
    assert __spark_entry__.entry(spark).columns == ["i", "j", "v"]
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_rounding_at_halves_is_that_of_sql(spark, duck):
    from pyspark.sql import functions as F

    from gridsparse.queries.matrix import round_scaled

    values = [(2 * k + 1) / 2e6 * m for k in range(500) for m in (1, 3, 1001)]
    frame = spark.createDataFrame([(x,) for x in values], "x double")
    got = {r["x"]: r["y"] for r in frame.select("x", round_scaled(F.col("x"), 6).alias("y")).collect()}
    assert got == dict(duck.sql(f"SELECT x, round(x, 6) FROM (SELECT unnest({values}::DOUBLE[]) AS x)").fetchall())


def test_words_of_one_hash_are_not_shared(spark, tmp_path):
    """Two words whose md5 begins alike are two words."""
    import hashlib

    met: dict[str, str] = {}
    for k in range(200_000):
        if (other := met.setdefault(hashlib.md5(f"w{k}".encode()).hexdigest()[:7], f"w{k}")) != f"w{k}":
            break
    spark.createDataFrame([(0, f"{other} both")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([(0, f"w{k} both both"), (1, f"w{k}"), (2, "both")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, 1), (1, 1), (2, 0)], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    assert [tuple(r) for r in catalog.QUERIES["term_intersection"](spark, str(tmp_path)).collect()] == [(0, 0, 1)]

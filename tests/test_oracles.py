"""A spread of registered queries against DuckDB on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as contract
from hopline.sources.tables import TABLES, load_hopset, save_hopset

NAMES = ["graph_edges_part_mesh", "graph_stats_supply", "components_balance_ladder", "hop_limited_mesh_4", "exact_tree", "parents_mesh", "ldd_ladder", "rounding_mesh", "bounds_table", "op_join_salted", "op_join_interval", "op_win_rank", "op_stream_edges", "op_stream_session", "op_sql_helpers"]


def norm(v):
    return f"{v:.6g}" if isinstance(v, float) else str(v)


def compare(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = contract.queries()[name](spark, sf)
    got = con.execute(contract.oracle_sql()[name])
    columns = [c[0] for c in got.description]
    assert sorted(columns) == sorted(df.columns)
    want = sorted(tuple(map(norm, r)) for r in got.fetchall())
    assert sorted(tuple(map(norm, r)) for r in df.select(*columns).collect()) == want


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, sf, name):
    compare(spark, sf, name)


def test_every_oracle_has_a_query():
    assert set(contract.oracle_sql()) <= set(contract.queries())


def test_hopset_round_trip(spark, tmp_path):
    h = spark.createDataFrame([(1, 2, 3, 4, "star", 0, 1), (2, 3, 1, 5, "top", 0, 2)], "u long, v long, w long, scale int, kind string, rep int, center long")
    save_hopset(h, str(tmp_path / "h"))
    back = load_hopset(spark, str(tmp_path / "h"), [5])
    assert [r.v for r in back.collect()] == [3]

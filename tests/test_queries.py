"""Every query against its SQL at the smallest size, and the entry point."""

import math
from pathlib import Path

import duckdb
import pytest

import __spark_entry__
from tilebalance.plans.registry import ORACLES, QUERIES

SF = Path("/root/testdata/sf0.001")
#: Mesh sweeps whose SQL takes long even on small tables; the driver runs them.
LONG = {"w1_mesh_sweep_quads", "w1_mesh_sweep_tris", "w4_mesh_kinds", "w_tile_sweep", "part_strips_4x8"}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in SF.glob("*.parquet"):
        con.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6) + 0.0
    return tuple(map(plain, v)) if isinstance(v, list | tuple) else v


@pytest.mark.parametrize("name", sorted(set(ORACLES) - LONG))
def test_query_equals_its_sql(spark, duck, name):
    df = QUERIES[name](spark, str(SF))
    columns = sorted(df.columns)
    cursor = duck.execute(ORACLES[name])
    others = [d[0] for d in cursor.description]
    assert sorted(others) == columns
    got = sorted(repr(tuple(plain(r[c]) for c in columns)) for r in df.collect())
    want = sorted(repr(tuple(plain(r[others.index(c)]) for c in columns)) for r in cursor.fetchall())
    assert got == want


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_rows_only_queries_run(spark, name):
    assert QUERIES[name](spark, str(SF)).count() > 0


@pytest.mark.parametrize("name", ["diff_links4x4", "diff_pairwise", "field_prescribed", "fn_polygon_barycentre", "fn_zorder_key", "gen_quads", "mesh_graph_cut", "met_mesh_counts", "met_volume", "part_even_tiles", "pic_leapfrog_mesh"])
def test_queries_follow_the_given_table(spark, tmp_path, name):
    """Half of the events give other rows: the query reads them."""
    (tmp_path / "half").mkdir()
    duckdb.sql(f"COPY (SELECT * FROM '{SF}/events.parquet' WHERE event_id % 2 = 0 AND user_id % 4 <> 3 AND value < 100) TO '{tmp_path}/half/events.parquet' (FORMAT parquet)")
    rows = [sorted(map(repr, QUERIES[name](spark, where).collect())) for where in (str(SF), f"{tmp_path}/half")]
    assert rows[0] != rows[1]


def test_entry(spark):
    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 8 and sum(r["load"] for r in rows) == 1000


def test_oracles_have_queries():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())

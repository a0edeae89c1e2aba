"""Queries against their SQL on the smallest tables."""

from __future__ import annotations

import glob
import os
from collections import Counter

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
FAST = [k for k in entry.oracle_sql() if k.startswith(("ep_hop_k2", "any_shortest_hop", "all_shortest_hop", "all_trail_slice", "words_groups_simple", "words_shortest_k_walk", "groups_acyclic", "shortest_k_hop_5", "g_", "path_cost", "bl_reach", "triples", "session", "asof"))]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_sql(spark, con, name):
    df = entry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = Counter(tuple(round(v, 6) if isinstance(v, float) else v for v in (r[c] for c in cols)) for r in df.collect())
    cur = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    assert sorted(names) == cols
    want = Counter(tuple(round(v, 6) if isinstance(v, float) else v for v in (r[names.index(c)] for c in cols)) for r in cur.fetchall())
    assert got == want


@pytest.mark.parametrize("name", ["all_trail_hop", "all_simple_hop", "shortest_k_acyclic_hop", "bitmask_endpoints_hop"])
def test_whole_graph_query_equals_its_sql(spark, con, name):
    assert "2024-01-01" not in entry.oracle_sql()[name]
    test_query_equals_its_sql(spark, con, name)


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_trail_of_a_diamond_of_orders(spark, con):
    """The diamond is one of the given table's: its nodes are orders and lines."""
    test_query_equals_its_sql(spark, con, "any_trail_diamond_bfs_1")
    (row,) = entry.queries()["any_trail_diamond_bfs_1"](spark, SF).collect()
    order, line = row["path"].split(">")[0].split("|")[1:]
    k, n = line.removeprefix("L:").split(":")
    assert order == f"O:{k}" and con.execute(f"select count(*) from lineitem where l_orderkey = {k} and l_linenumber = {n}").fetchone()[0]


def test_diamond_view_reads_its_table(spark):
    """All its orders are of lineitem, 25 diamonds in a chain."""
    rows = entry.queries()["g_diamond_edges"](spark, SF).collect()
    keys = {int(x[2:]) for r in rows for x in (r["src"], r["dst"]) if x.startswith("O:")}
    there = {r[0] for r in spark.read.parquet(f"{SF}/lineitem.parquet").select("l_orderkey").distinct().collect()}
    assert len(rows) == 100 and len(keys) == 26 and keys <= there

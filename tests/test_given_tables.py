"""Queries that once made their data up read the given tables and equal their SQL."""

from collections import Counter

import duckdb
import pytest

import __spark_entry__ as entry
from fragmap.catalog import BENCHMARKS

NAMES = ["bag_to_relations", "cfg_all", "cfg_beam", "cfg_rank_ties", "cfg_sigma_arith", "cfg_sigma_geo", "disconnected_bag", "fork_edges", "fork_edges_closure", "fork_vertices", "graph_edges", "graph_vertices"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_equals_its_sql(spark, sf, name):
    got = entry.queries()[name](spark, sf)
    con = duckdb.connect()
    for t in BENCHMARKS["all"]:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    assert got.columns == columns
    assert Counter(map(tuple, got.collect())) == Counter(want.fetchall()) != Counter()
    assert "parquet" in got._jdf.queryExecution().toString()

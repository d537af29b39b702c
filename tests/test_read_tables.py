"""Queries over small grids and graphs take them from given tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from tests.helpers import SMALL

TABLES = ("lineitem", "events")


@pytest.mark.parametrize("name", ["equivalent_walks", "frontier_toy8", "index_loads_toy8", "plan_strategy", "plan_strategy_by_size", "tail_bound_grid", "walks_for_precision_grid"])
def test_reads_a_table_and_equals_sql(spark, monkeypatch, name):
    from ripplerank.sources import edges

    read, given = [], edges.table
    monkeypatch.setattr(edges, "table", lambda s, d, t: read.append(t) or given(s, d, t))
    got = entry.queries()[name](spark, SMALL)
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()[name]).df()
    assert read and list(want.columns) == got.columns and len(want)
    order = list(want.columns)
    assert sorted(map(tuple, got.collect())) == sorted(want[order].itertuples(index=False, name=None))

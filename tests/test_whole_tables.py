"""Queries that cover their whole table, against SQL on a longer one."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", ["range_distinct", "range_mode"])
def test_ranges_reach_the_end(spark, name):
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{SF}/events.parquet')")
    last = duck.execute("SELECT max(event_id) FROM events").fetchone()[0]
    got = entry.queries()[name](spark, SF)
    rows = [tuple(r[c] for c in sorted(got.columns)) for r in got.collect()]
    found = duck.execute(entry.oracle_sql()[name])
    names = [d[0] for d in found.description]
    assert sorted(rows) == sorted(tuple(r[names.index(c)] for c in sorted(names)) for r in found.fetchall())
    assert max(r[sorted(got.columns).index("hi")] for r in rows) > 0.9 * last > 1000

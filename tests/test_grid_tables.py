"""Box queries that read line items: against SQL, and their plans scan the table."""

import duckdb
import pytest

import __spark_entry__ as entry

NAMES = ["box_sum_frontier", "box_sum_set", "compact_box_sums", "linear_box_scan", "rst_cell_points", "significance_table", "visits_rst"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_line_items(spark, sf, name):
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{sf}/lineitem.parquet')")
    got = entry.queries()[name](spark, sf)
    assert any(f.endswith("lineitem.parquet") for f in got.inputFiles())
    found = duck.execute(entry.oracle_sql()[name])
    names = [d[0] for d in found.description]
    assert sorted(names) == sorted(got.columns)
    assert sorted(map(tuple, got.select(names).collect())) == sorted(found.fetchall())

"""The whole lattice: equal to SQL, dealt once by each dimension's leaves, never expanded to all tuples at once."""

import duckdb

import __spark_entry__ as entry
from hcube.operators import baselines
from hcube.workloads import cubes


def test_all_tuples_equal_sql_without_expanding(spark, sf, monkeypatch):
    duck = duckdb.connect()
    for t in ("lineitem", "supplier", "nation", "region", "part"):
        duck.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    seen, make = [], baselines.materialise

    def kept(df, name):
        seen.append((name, df._jdf.queryExecution().executedPlan().toString()))
        return make(df, name)

    monkeypatch.setattr(baselines, "materialise", kept)
    got = entry.queries()["lattice_all_levels"](spark, sf)
    found = duck.execute(entry.oracle_sql()["lattice_all_levels"])
    names = [d[0] for d in found.description]
    assert sorted(map(tuple, got.select(names).collect())) == sorted(found.fetchall())
    # A part reads its dealt table as it is: the one further shuffle is that of its few sums.
    parts = [plan for name, plan in seen if name == "lattice-part"]
    assert len(parts) == cubes.C1.height * len(cubes.C1.dims)
    assert not any("Expand" in plan for _, plan in seen) and all(plan.count("ENSURE_REQUIREMENTS") == 1 for plan in parts)

from hcube.workloads import experiments
from hcube.workloads.grids import Grid


def test_both_trees_agree_and_the_regular_one_sums_more(spark):
    rows = experiments.compare(spark, Grid(3, 8, "irregular", 25), ("above_cells", "mixed"), 60)
    assert [r["differing"] for r in rows] == [0, 0]
    assert 0.5 < rows[0]["hast_summed"] <= 1  # empty ones aren't counted
    assert all(r["rst_summed"] > r["hast_summed"] for r in rows)

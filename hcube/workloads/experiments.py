"""The published comparison of both trees on grids: batches of label queries, times and counters.

Queries are one label per dimension: cells (the last depth), members of the depth above
it, and mixed depths without cells.  Each batch is asked of both compact trees; the time
is that of the walks inside the tasks, per query, so it is of one thread and free of
job starts; the wall time of the whole batch stands beside it.

``python -m hcube.workloads.experiments 4D_16 5D_16 --queries 10000`` prints one JSON line
per grid, organisation, share of empty cells and kind.
"""

from __future__ import annotations

import argparse
import json
import time
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import packed, packed_rst, rst
from ..operators.hast import Tree
from ..operators.measures import space_report
from ..plans import planner
from ..sources.store import materialise
from .grids import Grid
from .querysets import free_draws, label_boxes

KINDS = ("cells", "above_cells", "mixed")


class Made(NamedTuple):
    """Both trees of a grid in compact form, written."""

    tree: Tree
    cut: int
    shards: DataFrame
    height: int
    regular_cut: int
    regular: DataFrame


def prepared(spark: SparkSession, grid: Grid) -> Made:
    t = grid.tree(spark)
    cut = packed.choose_cut(t)
    h = rst.height_for(grid.m, 2)
    regular = {d: materialise(x, f"regular-{d}") for d, x in rst.build_rst(grid.cells(spark), grid.n, 2, h).items()}
    regular_cut = packed_rst.choose_cut(regular, grid.n, 2)
    return Made(t, cut, materialise(packed.pack(t, "v", cut), "shards"), h, regular_cut, materialise(packed_rst.pack(regular, grid.n, 2, regular_cut), "regular-shards"))


def batch(t, kind: str, n_queries: int, seed: int = 0) -> DataFrame:
    h = t.cube.height
    draw, fixed = ("mixed", None) if kind == "mixed" else ("one", h if kind == "cells" else h - 1)
    return materialise(free_draws(t, n_queries, draw, fixed, seed), "batch")


def ask_hast(made: Made, asked: DataFrame) -> DataFrame:
    """``(qid, total, n_summed, n_visited, nanos)``"""
    return packed.descend(made.tree, made.shards, planner.resolved(made.tree, asked), made.cut)


def ask_rst(grid: Grid, made: Made, asked: DataFrame) -> DataFrame:
    return packed_rst.walk(made.regular, label_boxes(made.tree, asked), grid.n, 2, made.height, made.regular_cut)


def compare(spark: SparkSession, grid: Grid, kinds=KINDS, n_queries: int = 10_000, seed: int = 0, made=None) -> list[dict]:
    """One row per kind: microseconds a query and sums a query of both trees, and whether the answers agree."""
    made = made or prepared(spark, grid)
    rows = []
    for kind in kinds:
        asked = batch(made.tree, kind, n_queries, seed)
        out = {"grid": grid.name, "organisation": grid.organisation, "empty": grid.empty, "kind": kind, "queries": n_queries}
        answers = {}
        for name, ask in (("hast", lambda: ask_hast(made, asked)), ("rst", lambda: ask_rst(grid, made, asked))):
            began = time.time()
            answers[name] = materialise(ask(), f"answers-{name}")
            wall = time.time() - began
            x = answers[name].agg(F.sum("nanos").alias("nanos"), F.avg("n_summed").alias("summed")).first()
            out |= {f"{name}_us": round(x.nanos / 1000 / n_queries, 3), f"{name}_summed": round(x.summed, 2), f"{name}_batch_s": round(wall, 2)}
        a, b = (answers[x].select("qid", F.col("total").alias(x)) for x in ("hast", "rst"))
        met = a.join(b, "qid", "full").agg(F.count_if(F.expr("NOT (coalesce(hast, 0) <=> coalesce(rst, 0))"))).first()[0]
        rows.append(out | {"differing": met, "rst_over_hast": round(out["rst_us"] / max(out["hast_us"], 0.001), 2)})
    return rows


def space(spark: SparkSession, grid: Grid) -> dict:
    """KB of both trees and of their parts."""
    t = grid.tree(spark)
    regular = {d: materialise(x, f"regular-{d}") for d, x in rst.build_rst(grid.cells(spark), grid.n, 2, rst.height_for(grid.m, 2)).items()}
    found = space_report(t, "v", regular, grid.n, 2)
    kb = {k: v if k.endswith(("width", "overhead")) else round(v / 8192, 2) for k, v in found.items()}
    return {"grid": grid.name, "organisation": grid.organisation, "empty": grid.empty, **kb, "rst_over_hast": round(found["rst_total"] / found["hast_total"], 3)}


def significance(spark: SparkSession, grid: Grid, kind: str = "above_cells", sets: int = 20, n_queries: int = 10_000) -> dict:
    """Means and deviations of time over sets drawn by different seeds, and both statistics."""
    from statistics import mean, stdev

    from ..operators.measures import separation, welch_z

    made = prepared(spark, grid)
    found = [compare(spark, grid, (kind,), n_queries, seed, made)[0] for seed in range(sets)]
    a, b = ([x[f"{name}_us"] for x in found] for name in ("rst", "hast"))
    stats = (mean(a), mean(b), stdev(a), stdev(b))
    return {
        "grid": grid.name, "kind": kind, "sets": sets, "rst_mean": round(stats[0], 3), "rst_dev": round(stats[2], 3), "hast_mean": round(stats[1], 3),
        "hast_dev": round(stats[3], 3), "stat_plain": round(separation(*stats), 3), "stat_n": round(welch_z(*stats, sets), 3),
    }


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("grids", nargs="+", help="such as 4D_16")
    p.add_argument("--queries", type=int, default=10_000)
    p.add_argument("--empty", type=int, nargs="*", default=[0, 25, 50])
    p.add_argument("--organisations", nargs="*", default=["binary", "irregular"])
    p.add_argument("--kinds", nargs="*", default=list(KINDS))
    p.add_argument("--space", action="store_true", help="sizes instead of times")
    p.add_argument("--sets", type=int, default=0, help="repeat sets for the significance of one kind")
    args = p.parse_args()
    spark = SparkSession.builder.config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in args.grids:
        n, m = map(int, name.split("D_"))
        for organisation in args.organisations:
            for empty in args.empty:
                grid = Grid(n, m, organisation, empty)
                if args.space:
                    rows = [space(spark, grid)]
                elif args.sets:
                    rows = [significance(spark, grid, kind, args.sets, args.queries) for kind in args.kinds]
                else:
                    rows = compare(spark, grid, args.kinds, args.queries)
                for row in rows:
                    print(json.dumps(row), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()

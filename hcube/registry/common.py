"""Shared pieces of the registered queries: trees made once per session, SQL over raw facts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators.hast import Tree, tree
from ..spec import Cube, Dimension

Query = Callable[[SparkSession, str], DataFrame]
_trees: dict[tuple, Tree] = {}


class Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, query: Query, sql: str | None = None) -> None:
        self.queries[name] = query
        if sql:
            self.sql[name] = sql


def tree_of(spark: SparkSession, sf_dir: str, cube: Cube) -> Tree:
    """A cube's stored tree, made once per session and input folder (inputs are taken as fixed)."""
    key = (spark.sparkContext.applicationId, id(spark._jsparkSession), sf_dir, cube)
    if key not in _trees:
        _trees[key] = tree(spark, cube, sf_dir)
    return _trees[key]


def grid_tree(spark: SparkSession, grid) -> Tree:
    key = (spark.sparkContext.applicationId, id(spark._jsparkSession), "", grid)
    if key not in _trees:
        _trees[key] = grid.tree(spark)
    return _trees[key]


def cols(dim: Dimension, k: int) -> str:
    return ", ".join(dim.column(j) for j in range(1, k + 1))


def members_sql(dim: Dimension, facts: str) -> str:
    """Members of one dimension: depth, label, parent_label, ordinal, fanout, lo, hi, member_id, is_copy."""
    h = dim.height
    ctes = [f"f AS ({facts})", f"leafs AS (SELECT DISTINCT {cols(dim, h)} FROM f)",
            f"leaf AS (SELECT *, row_number() OVER (ORDER BY {cols(dim, h)}) - 1 AS pos FROM leafs)"]
    parts = []
    for k in range(1, h + 1):
        below = f"count(DISTINCT {dim.column(k + 1)})" if k < h else "0"
        up = dim.column(k - 1) if k > 1 else "NULL"
        over = f"PARTITION BY {cols(dim, k - 1)} " if k > 1 else ""
        parts.append(
            f"SELECT {k} AS depth, {dim.column(k)} AS label, CAST({up} AS VARCHAR) AS parent_label, "
            f"row_number() OVER ({over}ORDER BY {dim.column(k)}) - 1 AS ordinal, {below} AS fanout, min(pos) AS lo, max(pos) AS hi, "
            f"row_number() OVER (ORDER BY {cols(dim, k)}) - 1 AS member_id, {str(dim.is_copy(k)).lower()} AS is_copy FROM leaf GROUP BY {cols(dim, k)}"
        )
    return f"(WITH {', '.join(ctes)} {' UNION ALL '.join(parts)})"


def level_sql(cube: Cube, k: int, extra: str = "") -> str:
    """Facts grouped by the level tuple of depth k, labels named by dimension."""
    facts = cube.sql()
    keys = ", ".join(d.column(j) for d in cube.dims for j in range(1, k + 1))
    labels = ", ".join(f"{d.column(k)} AS {d.name}" for d in cube.dims)
    sums = ", ".join(f"CAST(sum({m}) AS BIGINT) AS {m}" for m, _ in cube.measures)
    return f"SELECT {labels}, {sums}, count(*) AS cnt{extra} FROM ({facts}) GROUP BY {keys}"


def slots_sql(cube: Cube, k: int, facts: str) -> str:
    """Nonempty nodes and slots of depth k."""
    keys = lambda d, j: [x.column(i) for x in [d] for i in range(1, j + 1)]
    joins, fans = "", []
    for i, d in enumerate(cube.dims):
        if k > 1:
            on = " AND ".join(f"p.{c} = n{i}.{c}" for c in keys(d, k - 1))
            joins += f" JOIN (SELECT {', '.join(keys(d, k - 1))}, count(DISTINCT {d.column(k)}) AS fan FROM f GROUP BY {', '.join(keys(d, k - 1))}) n{i} ON {on}"
        else:
            joins += f" CROSS JOIN (SELECT count(DISTINCT {d.column(1)}) AS fan FROM f) n{i}"
        fans.append(f"n{i}.fan")
    above = ", ".join(c for d in cube.dims for c in keys(d, k - 1))
    here = ", ".join(c for d in cube.dims for c in keys(d, k))
    parents = f"(SELECT DISTINCT {above} FROM f) p" if k > 1 else "(SELECT 1) p"
    return (
        f"SELECT {k} AS depth, (SELECT count(*) FROM (SELECT DISTINCT {here} FROM f)) AS nonempty, "
        f"(SELECT CAST(sum({' * '.join(fans)}) AS BIGINT) FROM {parents}{joins}) AS slots"
    )

"""Distinct counts and modes: over general ranges, and under the members of a hierarchy."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_distinct(seq: DataFrame, ranges: DataFrame, block: int = 1024) -> DataFrame:
    """``seq(pos, value)``, ``ranges(rid, lo, hi)``: distinct values in each range.

    A value counts where its previous occurrence lies before the range.  Ranges meet
    positions by blocks, so the join has a key.
    """
    previous = F.lag("pos").over(Window.partitionBy("value").orderBy("pos"))
    marked = seq.withColumn("before", F.coalesce(previous, F.lit(-1))).withColumn("blk", F.expr(f"pos div {block}"))
    wide = ranges.withColumn("blk", F.explode(F.expr(f"sequence(lo div {block}, hi div {block})")))
    got = marked.join(wide, "blk").filter("pos BETWEEN lo AND hi AND before < lo").groupBy("rid").agg(F.count("*").alias("n_distinct"))
    return ranges.join(got, "rid", "left").select("rid", "lo", "hi", F.coalesce("n_distinct", F.lit(0)).alias("n_distinct"))


def range_mode(seq: DataFrame, ranges: DataFrame, block: int = 1024) -> DataFrame:
    """Most frequent value of each range, ties to the smallest value."""
    wide = ranges.withColumn("blk", F.explode(F.expr(f"sequence(lo div {block}, hi div {block})")))
    met = seq.withColumn("blk", F.expr(f"pos div {block}")).join(wide, "blk").filter("pos BETWEEN lo AND hi")
    counts = met.groupBy("rid", "lo", "hi", "value").agg(F.count("*").alias("n"))
    best = counts.groupBy("rid", "lo", "hi").agg(F.min(F.struct((-F.col("n")).alias("m"), "value")).alias("b"))
    return best.select("rid", "lo", "hi", F.col("b.value").alias("mode_value"), (-F.col("b.m")).alias("mode_count"))


def top_cells(nodes: dict[int, DataFrame], dims: list[str], measure: str, k: int) -> DataFrame:
    """The k largest cells of a measure >= 0, best subtrees first: ``(member ids of the cells, measure)``.

    A cell is never more than a node above it.  The largest node of each depth leads to k
    cells whose least is a bound; below it whole subtrees end, depth by depth.
    """
    h = max(nodes)
    keys = lambda d: [f"{x}_id_{j}" for j in range(1, d + 1) for x in dims]
    leaf = [F.col(f"{x}_id_{h}") for x in dims]
    order = [F.desc(measure), *leaf]
    best = nodes[1].orderBy(F.desc(measure), *keys(1)).limit(1).select(*keys(1))
    first = nodes[h].join(F.broadcast(best), keys(1)).orderBy(*order).limit(k)
    found = first.agg(F.count("*").alias("n"), F.min(measure).alias("least")).first()
    bound = found.least if found.n == k else 0
    open_ = nodes[1].filter(F.col(measure) >= bound)
    for d in range(2, h + 1):
        open_ = nodes[d].filter(F.col(measure) >= bound).join(open_.select(*keys(d - 1)), keys(d - 1), "left_semi")
    return open_.orderBy(*order).limit(k).select(*[c.alias(x) for c, x in zip(leaf, dims)], measure)


def sketched_distinct(rows: DataFrame, levels: list[str], value: str) -> DataFrame:
    """Approximate distinct values under every member, ``(depth, label, estimate)``: sketches merged upwards."""
    now = rows.groupBy(*levels).agg(F.hll_sketch_agg(value, F.lit(14)).alias("sketch"))
    parts = []
    for k in range(len(levels), 0, -1):
        if k < len(levels):
            now = now.groupBy(*levels[:k]).agg(F.hll_union_agg("sketch").alias("sketch"))
        parts.append(now.select(F.lit(k).alias("depth"), F.col(levels[k - 1]).alias("label"), F.hll_sketch_estimate("sketch").alias("estimate")))
    return reduce(DataFrame.unionByName, parts)


def hier_distinct(rows: DataFrame, levels: list[str], value: str) -> DataFrame:
    """Distinct values under every member of every depth: ``(depth, label, n_distinct)``.

    The members' leaves are in order, and equal values that follow each other share the
    members above both: each depth's count is its occurrences less the neighbours that
    meet at that depth or below.  One window and one aggregate per depth, no set is kept.
    """
    leaf = rows.select(*levels, value).distinct()
    order = Window.partitionBy(value).orderBy(*levels)
    flags = []
    same = F.lit(True)
    for c in levels:
        same = same & (F.lag(c).over(order) == F.col(c))
        flags.append(F.when(F.coalesce(same, F.lit(False)), 0).otherwise(1).alias(f"new_{c}"))
    marked = leaf.select("*", *flags)
    parts = [
        marked.groupBy(*levels[:k]).agg(F.sum(f"new_{levels[k - 1]}").cast("long").alias("n_distinct"))
        .select(F.lit(k).alias("depth"), F.col(levels[k - 1]).alias("label"), "n_distinct")
        for k in range(1, len(levels) + 1)
    ]
    return reduce(DataFrame.unionByName, parts)


def hier_mode(rows: DataFrame, levels: list[str], value: str) -> DataFrame:
    """Most frequent value under every member, counts rolled up depth by depth."""
    now = rows.groupBy(*levels, value).agg(F.count("*").alias("n"))
    parts = []
    for k in range(len(levels), 0, -1):
        if k < len(levels):
            now = now.groupBy(*levels[:k], value).agg(F.sum("n").alias("n"))
        best = now.groupBy(*levels[:k]).agg(F.min(F.struct((-F.col("n")).alias("m"), F.col(value).alias("v"))).alias("b"))
        parts.append(best.select(F.lit(k).alias("depth"), F.col(levels[k - 1]).alias("label"), F.col("b.v").alias("mode_value"), (-F.col("b.m")).alias("mode_count")))
    return reduce(DataFrame.unionByName, parts)

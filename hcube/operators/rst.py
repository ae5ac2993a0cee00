"""The regular-split summed tree: every dimension cut into k equal parts, depth after depth.

Nodes are blocks named by their coordinates; empty blocks have no row, so padding to a
power of k costs nothing.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def height_for(side: int, k: int) -> int:
    h = 0
    while k**h < side:
        h += 1
    return h


def build_rst(cells: DataFrame, n: int, k: int, h: int, measure: str = "v") -> dict[int, DataFrame]:
    """Depth 0..h: ``b1..bn`` block coordinates, ``total``, ``cnt``; each depth from the one below it."""
    b = [f"b{i}" for i in range(1, n + 1)]
    now = cells.groupBy(*[F.col(f"k{i}").alias(x) for i, x in enumerate(b, 1)]).agg(F.sum(measure).alias("total"), F.count("*").alias("cnt"))
    out = {h: now}
    for depth in range(h - 1, 0, -1):
        now = now.groupBy(*[F.expr(f"{x} div {k}").alias(x) for x in b]).agg(F.sum("total").alias("total"), F.sum("cnt").alias("cnt"))
        out[depth] = now
    if h:
        root = now.agg(F.coalesce(F.sum("total"), F.lit(0)).alias("total"), F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))
        out[0] = root.select(*[F.lit(0).cast("long").alias(x) for x in b], "total", "cnt")
    return out


def contained(b: str, i: int, side: int) -> str:
    return f"lo_{i} <= {b} * {side} AND {b} * {side} + {side - 1} <= hi_{i}"


def disjoint(b: str, i: int, side: int) -> str:
    return f"({b} * {side} > hi_{i} OR {b} * {side} + {side - 1} < lo_{i})"


def range_sum(tree: dict[int, DataFrame], boxes: DataFrame, n: int, k: int) -> DataFrame:
    """Frontier form of a box sum: ``(qid, total, n_summed, n_visited)``.

    ``boxes(qid, lo_1, hi_1, ...)``, inclusive.  Per depth, blocks in the box give their
    stored sum and go no deeper; blocks that meet it partly go on to their children by an
    equi-join; empty and disjoint ones end.
    """
    h = max(tree)
    b = [f"b{i}" for i in range(1, n + 1)]
    bounds = [c for i in range(1, n + 1) for c in (f"lo_{i}", f"hi_{i}")]
    frontier = boxes.crossJoin(tree[0].filter("cnt > 0"))  # the root is one row
    done = []
    for depth in range(h + 1):
        side = k ** (h - depth)
        inside = " AND ".join(contained(x, i, side) for i, x in enumerate(b, 1))
        apart = " OR ".join(disjoint(x, i, side) for i, x in enumerate(b, 1))
        met = frontier.filter(f"NOT ({apart})").withColumn("inside", F.expr(inside))
        # Met are the root, and of an opened block all children that the box reaches, empty ones too.
        reached = F.lit(0).cast("long")
        if depth < h:
            step = side // k
            spans = [F.expr(f"least(hi_{i}, {x} * {side} + {side - 1}) div {step} - greatest(lo_{i}, {x} * {side}) div {step} + 1") for i, x in enumerate(b, 1)]
            reached = F.when(F.col("inside"), 0).otherwise(reduce(lambda p, q: p * q, spans))
        seen = reached + F.lit(1 if depth == 0 else 0)
        done.append(met.groupBy("qid").agg(F.sum(F.when(F.col("inside"), F.col("total"))).alias("total"), F.count_if(F.col("inside")).alias("n_summed"), F.sum(seen).alias("n_visited")))
        if depth < h:
            child = tree[depth + 1].select(*b, "total", "cnt", *[F.expr(f"{x} div {k}").alias(f"u{x}") for x in b])
            open_ = met.filter("NOT inside").select("qid", *bounds, *[F.col(x).alias(f"u{x}") for x in b])
            frontier = open_.join(child, [f"u{x}" for x in b]).drop(*[f"u{x}" for x in b])
    every = reduce(DataFrame.unionByName, done)
    got = every.groupBy("qid").agg(F.sum("total").alias("total"), F.sum("n_summed").alias("n_summed"), F.sum("n_visited").alias("n_visited"))
    return boxes.select("qid").join(got, "qid", "left").na.fill(0).select("qid", *[F.col(c).cast("long").alias(c) for c in ("total", "n_summed", "n_visited")])


def range_sum_set(tree: dict[int, DataFrame], boxes: DataFrame, n: int, k: int) -> DataFrame:
    """The same sums without a frontier: a block counts if it lies in the box and its parent does not.

    A box lists the depth-1 blocks that it meets (at most k^n); each depth joins on those.
    """
    h = max(tree)
    b = [f"b{i}" for i in range(1, n + 1)]
    if not h:
        return range_sum(tree, boxes, n, k).select("qid", "total")
    top = k ** (h - 1)
    wide = boxes
    for i in range(1, n + 1):
        wide = wide.withColumn(f"t{i}", F.explode(F.expr(f"sequence(lo_{i} div {top}, least(hi_{i} div {top}, {k - 1}L))")))
    parts = []
    whole = " AND ".join(contained(x, i, k**h) for i, x in enumerate(b, 1))
    parts.append(boxes.crossJoin(tree[0]).filter(whole).select("qid", "total"))
    for depth in range(1, h + 1):
        side = k ** (h - depth)
        table = tree[depth].select(*b, "total", *[F.expr(f"{x} div {k ** (depth - 1)}").alias(f"t{i}") for i, x in enumerate(b, 1)])
        mine = " AND ".join(contained(x, i, side) for i, x in enumerate(b, 1))
        parent = " AND ".join(contained(f"({x} div {k})", i, side * k) for i, x in enumerate(b, 1))
        parts.append(table.join(wide, [f"t{i}" for i in range(1, n + 1)]).filter(f"({mine}) AND NOT ({parent})").select("qid", "total"))
    got = reduce(DataFrame.unionByName, parts).groupBy("qid").agg(F.sum("total").alias("total"))
    return boxes.select("qid").join(got, "qid", "left").select("qid", F.coalesce("total", F.lit(0)).cast("long").alias("total"))


def cell(tree: dict[int, DataFrame], points: DataFrame, n: int) -> DataFrame:
    """``points(qid, k1..kn)`` to ``(qid, total)``, 0 where the cell is empty."""
    leaf = tree[max(tree)].select(*[F.col(f"b{i}").alias(f"k{i}") for i in range(1, n + 1)], "total")
    return points.join(leaf, [f"k{i}" for i in range(1, n + 1)], "left").select("qid", F.coalesce("total", F.lit(0)).cast("long").alias("total"))


def linear_scan(cells: DataFrame, boxes: DataFrame, n: int, side: int, measure: str = "v") -> DataFrame:
    """Baseline: the box over the cells themselves, met by coarse blocks so the join has keys."""
    wide = boxes
    for i in range(1, n + 1):
        wide = wide.withColumn(f"t{i}", F.explode(F.expr(f"sequence(lo_{i} div {side}, hi_{i} div {side})")))
    keyed = cells.select("*", *[F.expr(f"k{i} div {side}").alias(f"t{i}") for i in range(1, n + 1)])
    inside = " AND ".join(f"k{i} BETWEEN lo_{i} AND hi_{i}" for i in range(1, n + 1))
    got = keyed.join(wide, [f"t{i}" for i in range(1, n + 1)]).filter(inside).groupBy("qid").agg(F.sum(measure).alias("total"))
    return boxes.select("qid").join(got, "qid", "left").select("qid", F.coalesce("total", F.lit(0)).cast("long").alias("total"))


def closed_form(n: int, k: int, h: int) -> tuple[Column, Column]:
    """Blocks summed and visited for a box over a full cube, as arithmetic on its bounds."""
    summed = visited = None
    for d in range(h + 1):
        inside, touched = [], []
        for side, into in ((k ** (h - d), inside), (k ** (h - d + 1), None)):
            if into is None and d == 0:
                continue
            terms_in = [F.expr(f"greatest(0L, (hi_{i} + 1) div {side} - (lo_{i} + {side - 1}) div {side})") for i in range(1, n + 1)]
            terms_touch = [F.expr(f"hi_{i} div {side} - lo_{i} div {side} + 1") for i in range(1, n + 1)]
            product_in, product_touch = reduce(lambda a, b: a * b, terms_in), reduce(lambda a, b: a * b, terms_touch)
            if into is not None:
                mine_in, mine_touch = product_in, product_touch
            else:
                above_in = product_in
        minus = F.lit(k**n) * above_in if d else F.lit(0)
        summed = mine_in - minus if summed is None else summed + mine_in - minus
        visited = mine_touch if visited is None else visited + mine_touch - minus
    return summed, visited

"""Label queries: resolve, classify, answer from stored sums.

A batch ``queries(qid, <dim>...)`` gives one label per dimension (``*`` for all).  Depths
differ from query to query, but there are at most (H + 1)^n tuples of depths; the batch is
answered by one equi-join per tuple that occurs.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.hast import Tree, ids
from ..sources.store import materialise
from ..spec import ROOT


def resolve(t: Tree, queries: DataFrame) -> DataFrame:
    """Adds by dimension the depth (-1: unknown, 0: root) and the ids down to the member, and ``deepest``."""
    out = queries
    h = t.cube.height
    for d in t.cube.dims:
        v = t.vocabulary(d.name).select(
            F.col("label").alias(d.name), F.when(F.col("n") > 1, F.lit(-2)).otherwise(F.col("depth")).alias(f"{d.name}_depth"),
            *[F.col(f"id_{k}").alias(f"{d.name}_id_{k}") for k in range(1, h + 1)], F.col("lo").alias(f"{d.name}_lo"), F.col("hi").alias(f"{d.name}_hi"),
        )
        out = out.join(v, d.name, "left").withColumn(
            f"{d.name}_depth", F.when(F.col(d.name) == ROOT, F.lit(0)).otherwise(F.coalesce(f"{d.name}_depth", F.lit(-1)))
        )
    depths = [F.col(f"{d.name}_depth") for d in t.cube.dims]
    return out.withColumns({
        "deepest": F.greatest(*depths) if len(depths) > 1 else depths[0],
        "status": F.when(reduce(lambda a, b: a | b, [x == -2 for x in depths]), F.lit("ambiguous_label"))
        .when(reduce(lambda a, b: a | b, [x == -1 for x in depths]), F.lit("unknown_label")).otherwise(F.lit("ok")),
    })


def resolved(t: Tree, queries: DataFrame) -> DataFrame:
    """``resolve``, written once where the tree is: a batch is read again for every tuple of depths."""
    out = resolve(t, queries)
    return materialise(out, "asked") if t.stored else out


def tuples(t: Tree, resolved: DataFrame) -> list[tuple[int, ...]]:
    """Depth tuples of the batch, at most (H + 1)^n."""
    names = [f"{d.name}_depth" for d in t.cube.dims]
    return sorted(tuple(r) for r in resolved.filter("status = 'ok'").select(*names).distinct().collect())


def _measures(t: Tree) -> list[str]:
    return [m for m, _ in t.cube.measures]


def answer(t: Tree, queries: DataFrame, counters: bool = True) -> DataFrame:
    """``(qid, labels, status, measures, cnt, n_summed)``: one stored sum, or the sum of a few.

    Labels of one depth meet one node; of several depths, the nodes of the deepest whose
    ancestors are the queried members (for each shallower one, all its descendants).
    """
    cube = t.cube
    asked = resolved(t, queries)
    parts = []
    for depths in tuples(t, asked):
        deepest = max(depths)
        mine = asked
        on = []
        for d, k in zip(cube.dims, depths):
            mine = mine.filter(F.col(f"{d.name}_depth") == k)
            if k:
                on.append(f"{d.name}_id_{k}")
        node = t.nodes[deepest].select(*on, *_measures(t), "cnt")
        mine = mine.filter("status = 'ok'").select("qid", *on)
        met = node.join(mine, on) if on else node.crossJoin(mine)  # the root is one row
        parts.append(met.groupBy("qid").agg(*[F.sum(m).cast("long").alias(m) for m in _measures(t)], F.sum("cnt").cast("long").alias("cnt"), F.count("*").alias("n_summed")))
    found = reduce(DataFrame.unionByName, parts) if parts else None
    out = asked.select("qid", *[d.name for d in cube.dims], "status")
    values = [*_measures(t), "cnt", "n_summed"]
    if found is None:
        return out.select("*", *[F.lit(None).cast("long").alias(v) for v in values])
    out = out.join(found, "qid", "left")
    ok = F.col("status") == "ok"
    return out.select("qid", *[d.name for d in cube.dims], "status", *[F.when(ok, F.coalesce(v, F.lit(0))).cast("long").alias(v) for v in values])


def answer_exploded(t: Tree, queries: DataFrame) -> DataFrame:
    """The same for few descendants: each query lists the member tuples it needs and probes for them."""
    cube = t.cube
    asked = resolved(t, queries).filter("status = 'ok'")
    parts = []
    for depths in tuples(t, asked):
        deepest = max(depths)
        mine = asked
        for d, k in zip(cube.dims, depths):
            mine = mine.filter(F.col(f"{d.name}_depth") == k)
        rows = mine.select("qid", *[f"{d.name}_id_{k}" for d, k in zip(cube.dims, depths) if k])
        for d, k in zip(cube.dims, depths):
            if 0 < k < deepest:
                down = t.leaf[d.name].select(F.col(f"id_{k}").alias(f"{d.name}_id_{k}"), F.col(f"id_{deepest}").alias(f"{d.name}_id_{deepest}")).distinct()
                rows = rows.join(down, f"{d.name}_id_{k}")
            elif k == 0 and deepest:
                down = t.leaf[d.name].select(F.col(f"id_{deepest}").alias(f"{d.name}_id_{deepest}")).distinct()
                rows = rows.crossJoin(down)  # all members of a depth, for a query over all
        on = [f"{d.name}_id_{deepest}" for d in cube.dims] if deepest else []
        node = t.nodes[deepest].select(*on, *_measures(t), "cnt")
        met = rows.select("qid", *on).join(node, on) if on else rows.select("qid").crossJoin(node)
        parts.append(met.groupBy("qid").agg(*[F.sum(m).cast("long").alias(m) for m in _measures(t)], F.sum("cnt").cast("long").alias("cnt"), F.count("*").alias("n_summed")))
    found = reduce(DataFrame.unionByName, parts)
    return asked.select("qid").join(found, "qid", "left").na.fill(0)


EXPLODE_LIMIT = 64


def choose_mode(t: Tree, queries: DataFrame, limit: int = EXPLODE_LIMIT) -> str:
    """``explode`` when the mean query needs at most ``limit`` probes, else ``prefix``."""
    asked = resolve(t, queries).filter("status = 'ok'")
    width = F.lit(1.0)
    for d in t.cube.dims:
        width = width * (F.coalesce(F.col(f"{d.name}_hi") - F.col(f"{d.name}_lo"), F.lit(0)) + 1)
    mean = asked.filter(f"deepest < {t.cube.height}").agg(F.avg(width)).first()[0]
    return "explode" if mean is not None and mean <= limit else "prefix"


def visits(t: Tree, queries: DataFrame) -> DataFrame:
    """``(qid, n_visited, n_summed)`` of the walk from the root, empty branches left out."""
    cube = t.cube
    asked = resolved(t, queries).filter("status = 'ok'")
    parts = []
    for depths in tuples(t, asked):
        mine = asked
        for d, k in zip(cube.dims, depths):
            mine = mine.filter(F.col(f"{d.name}_depth") == k)
        for step in range(max(depths) + 1):
            on = [f"{d.name}_id_{min(k, step)}" for d, k in zip(cube.dims, depths) if min(k, step)]
            node = t.nodes[step].select(*on)
            met = node.join(mine.select("qid", *on), on) if on else node.crossJoin(mine.select("qid"))
            parts.append(met.groupBy("qid").agg(F.count("*").alias("n")).withColumn("last", F.lit(step == max(depths))))
    every = reduce(DataFrame.unionByName, parts)
    total = every.groupBy("qid").agg(F.sum("n").alias("n_visited"), F.sum(F.when(F.col("last"), F.col("n"))).alias("n_summed"))
    return asked.select("qid").join(total, "qid", "left").na.fill(0)


def group_level(t: Tree, depth: int) -> DataFrame:
    """A GROUP BY over one level of every dimension, served from the nodes of that depth."""
    return t.labelled(depth)


def member_set(t: Tree, queries: DataFrame, dim: str) -> DataFrame:
    """Sum over a set of labels of one dimension: labels below another of the set don't count twice.

    ``queries(qid, <dims>)`` with several rows per qid.
    """
    asked = resolve(t, queries).filter("status = 'ok'")
    # A row is covered when the same query holds an ancestor of its member.
    a, b = asked.alias("a"), asked.select("qid", f"{dim}_depth", f"{dim}_lo", f"{dim}_hi").distinct().alias("b")
    covered = a.join(b, F.expr(f"a.qid = b.qid AND b.{dim}_lo <= a.{dim}_lo AND a.{dim}_hi <= b.{dim}_hi AND b.{dim}_depth < a.{dim}_depth"), "left_anti")
    rows = covered.select(F.struct("a.qid", f"a.{dim}").alias("k"), *[f"a.{d.name}" for d in t.cube.dims]).distinct()
    numbered = rows.select(F.col("k.qid").alias("q"), F.xxhash64("k").alias("qid"), *[d.name for d in t.cube.dims])
    got = answer(t, numbered.drop("q"))
    return numbered.select("q", "qid").join(got, "qid").groupBy(F.col("q").alias("qid")).agg(*[F.sum(m).cast("long").alias(m) for m in _measures(t)])

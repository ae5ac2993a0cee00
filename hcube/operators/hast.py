"""The hierarchy-aligned summed tree in its logical form: one row per nonempty node.

Cells are one aggregate of the facts; each further depth is an aggregate of the one below
it, added up before its shuffle and dealt by its own keys, so the tasks that are busy
follow the number of nodes of a depth and not the number of the topmost members.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import materialise
from ..spec import Cube
from . import hierarchy


@dataclass
class Tree:
    """A cube's members and nodes.

    ``stored``: each depth is written to shared storage and the next one made from it, so
    the facts are read once however many queries follow; else one lazy plan.
    """

    spark: SparkSession
    cube: Cube
    facts: DataFrame
    stored: bool = True

    @cached_property
    def leaf(self) -> dict[str, DataFrame]:
        return {d.name: hierarchy.leaves(self.facts, d) for d in self.cube.dims}

    @cached_property
    def _tables(self) -> dict[tuple[str, str], DataFrame]:
        return {}

    def _once(self, kind: str, dim: str, make) -> DataFrame:
        """Tables that every batch of queries needs are written once where nodes are."""
        if (kind, dim) not in self._tables:
            made = make(self.leaf[dim], self._dim(dim))
            self._tables[kind, dim] = materialise(made, f"{kind}-{dim}") if self.stored else made
        return self._tables[kind, dim]

    def members(self, dim: str) -> DataFrame:
        return self._once("members", dim, hierarchy.members)

    def vocabulary(self, dim: str) -> DataFrame:
        return self._once("vocabulary", dim, hierarchy.vocabulary)

    def _dim(self, name: str):
        return next(d for d in self.cube.dims if d.name == name)

    @cached_property
    def nodes(self) -> dict[int, DataFrame]:
        """Depth 0..H: member ids ``<dim>_id_<k>``, slots ``p_<k>`` from the root, and the aggregates."""
        return build_hast(cells(self), self.cube, (lambda df, k: materialise(df, f"nodes-{k}")) if self.stored else None)

    def labelled(self, depth: int) -> DataFrame:
        """Nodes of a depth with the labels of their members."""
        out = self.nodes[depth]
        for d in self.cube.dims if depth else ():
            names = self.leaf[d.name].select(F.col(f"id_{depth}").alias(f"{d.name}_id_{depth}"), F.col(d.column(depth)).alias(d.name)).distinct()
            out = out.join(names, f"{d.name}_id_{depth}")
        return out


def tree(spark: SparkSession, cube: Cube, sf_dir: str) -> Tree:
    return Tree(spark, cube, cube.facts(spark, sf_dir))


def aggregates(cube: Cube) -> list[Column]:
    """Mergeable aggregates of facts: count, and by measure sum, min, max and sum of squares."""
    out = [F.count("*").alias("cnt")]
    for m, _ in cube.measures:
        out += [F.sum(m).alias(m), F.min(m).alias(f"min_{m}"), F.max(m).alias(f"max_{m}"), F.sum(F.col(m).cast("decimal(38,0)") * F.col(m)).alias(f"sq_{m}")]
    return out


def merged(cube: Cube) -> list[Column]:
    out = [F.sum("cnt").alias("cnt")]
    for m, _ in cube.measures:
        out += [F.sum(m).alias(m), F.min(f"min_{m}").alias(f"min_{m}"), F.max(f"max_{m}").alias(f"max_{m}"), F.sum(f"sq_{m}").alias(f"sq_{m}")]
    return out


def ids(cube: Cube, upto: int) -> list[str]:
    return [f"{d.name}_id_{k}" for k in range(1, upto + 1) for d in cube.dims]


def slot(cube: Cube, k: int) -> Column:
    """Child number at step k: mixed radix, first dimension fastest, radix = fanout of the current member."""
    out = F.lit(0).cast("long")
    for d in reversed(cube.dims):
        out = F.col(f"{d.name}_fan_{k}") * out + F.col(f"{d.name}_ord_{k}")
    return out


def cells(t: Tree) -> DataFrame:
    """Facts summed by leaf members, with all ancestors' ids and the slot of each step."""
    cube, h = t.cube, t.cube.height
    out = t.facts.groupBy(*[d.column(k) for d in cube.dims for k in range(1, h + 1)]).agg(*aggregates(cube))
    for d in cube.dims:
        leaf = t.leaf[d.name]
        leaf = leaf.select(*[d.column(k) for k in range(1, h + 1)], *[F.col(f"{x}_{k}").alias(f"{d.name}_{x}_{k}") for x in ("id", "ord", "fan") for k in range(1, h + 1)])
        out = out.join(leaf, [d.column(k) for k in range(1, h + 1)])
    slots = [slot(cube, k).alias(f"p_{k}") for k in range(1, h + 1)]
    rest = [c for c in out.columns if c == "cnt" or any(c == x or c.endswith(f"_{x}") for x, _ in cube.measures)]
    return out.select(*ids(cube, h), *slots, *[F.col(c) for c in rest if c in _aggregate_names(cube)])


def _aggregate_names(cube: Cube) -> list[str]:
    return ["cnt", *[n for m, _ in cube.measures for n in (m, f"min_{m}", f"max_{m}", f"sq_{m}")]]


def build_hast(cell_table: DataFrame, cube: Cube, keep=None) -> dict[int, DataFrame]:
    """Depth 0..H; ``keep(table, depth)`` may write a depth before the next one is made."""
    keep = keep or (lambda df, k: df)
    h = cube.height
    names = _aggregate_names(cube)
    now = keep(cell_table.select(*ids(cube, h), *[f"p_{k}" for k in range(1, h + 1)], *names), h)
    out = {h: now}
    for k in range(h - 1, 0, -1):
        now = keep(now.groupBy(*ids(cube, k), *[f"p_{j}" for j in range(1, k + 1)]).agg(*merged(cube)), k)
        out[k] = now
    root = now.agg(*[F.coalesce(a, F.lit(0)).alias(n) if n == "cnt" or n in dict(cube.measures) else a.alias(n) for a, n in zip(merged(cube), names)])
    return out | {0: root}


def all_depths(nodes: dict[int, DataFrame], cube: Cube) -> DataFrame:
    """One table: depth, path (slots), member ids of the node's own depth, aggregates."""
    parts = []
    for k in sorted(nodes):
        own = [F.col(f"{d.name}_id_{k}").alias(d.name) if k else F.lit(None).cast("long").alias(d.name) for d in cube.dims]
        path = F.array(*[F.col(f"p_{j}") for j in range(1, k + 1)]).cast("array<long>")
        parts.append(nodes[k].select(F.lit(k).alias("depth"), path.alias("path"), *own, *_aggregate_names(cube)))
    return reduce(DataFrame.unionByName, parts)


def slots(t: Tree, depth: int) -> DataFrame:
    """Slots of all nonempty parents, empty ones included: parent's path, slot, sum (0 if empty).

    The children of one parent come from one explode of its fanout product.
    """
    cube = t.cube
    above, keys = t.nodes[depth - 1], [f"p_{j}" for j in range(1, depth)]
    fan = F.lit(1).cast("long")
    parents = above
    for d in cube.dims:
        leaf = t.leaf[d.name]
        on = [f"{d.name}_id_{depth-1}"] if depth > 1 else []
        fans = leaf.select(*[F.col(f"id_{depth-1}").alias(c) for c in on], F.col(f"fan_{depth}").alias(f"{d.name}_f")).distinct()
        parents = parents.join(F.broadcast(fans), on) if on else parents.crossJoin(F.broadcast(fans))  # depth 1: one row each
        fan = fan * F.col(f"{d.name}_f")
    every = parents.select(*keys, F.explode(F.sequence(F.lit(0).cast("long"), fan - 1)).alias(f"p_{depth}"))
    have = t.nodes[depth].select(*keys, f"p_{depth}", *[m for m, _ in cube.measures], "cnt")
    filled = every.join(have, [*keys, f"p_{depth}"], "left")
    return filled.na.fill(0, ["cnt", *[m for m, _ in cube.measures]])


def slot_count(t: Tree, depth: int) -> DataFrame:
    """``(depth, nonempty, slots)`` without listing the slots."""
    cube = t.cube
    parents, fan = t.nodes[depth - 1], F.lit(1).cast("long")
    for d in cube.dims:
        on = [f"{d.name}_id_{depth-1}"] if depth > 1 else []
        fans = t.leaf[d.name].select(*[F.col(f"id_{depth-1}").alias(c) for c in on], F.col(f"fan_{depth}").alias(f"{d.name}_f")).distinct()
        parents = parents.join(F.broadcast(fans), on) if on else parents.crossJoin(F.broadcast(fans))
        fan = fan * F.col(f"{d.name}_f")
    total = parents.agg(F.sum(fan).cast("long").alias("slots"))
    full = t.nodes[depth].agg(F.count("*").alias("nonempty"))
    return full.crossJoin(total).select(F.lit(depth).alias("depth"), "nonempty", F.coalesce("slots", F.lit(0).cast("long")).alias("slots"))

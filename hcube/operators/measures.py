"""Cost measures: space by part, visits, significance."""

from __future__ import annotations

from functools import reduce

import numpy as np

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import best_width, dac_bits_sql
from .hast import Tree, slot_count


def separation(mean_a: float, mean_b: float, dev_a: float, dev_b: float) -> float:
    """Difference over the pooled deviation, not divided by the number of sets."""
    return (mean_a - mean_b) / (dev_a**2 + dev_b**2) ** 0.5


def welch_z(mean_a: float, mean_b: float, dev_a: float, dev_b: float, n: int) -> float:
    return (mean_a - mean_b) / (dev_a**2 / n + dev_b**2 / n) ** 0.5


def value_bits(slots: DataFrame, column: str, width: int) -> DataFrame:
    """``(width, entries, bits)`` of the variable-length code of a column of values >= 0."""
    return slots.agg(
        F.lit(width).alias("width"), F.count("*").alias("entries"), F.sum(F.expr(dac_bits_sql(column, width))).cast("long").alias("bits")
    )


def value_lengths(tables: list[DataFrame], column: str, zeros: int = 0) -> np.ndarray:
    """How many values >= 0 have each bit length, by length; ``zeros`` more values are 0."""
    out = np.zeros(65, np.int64)
    every = reduce(DataFrame.unionByName, [x.select(F.length(F.bin(F.col(column).cast("long"))).alias("len")) for x in tables])
    for r in every.groupBy("len").agg(F.count("*").alias("n")).collect():  # at most 64 rows
        out[r.len] = r.n
    out[1] += zeros
    return out


def space_report(t: Tree, measure: str, regular: dict[int, DataFrame], n: int, k: int) -> dict[str, int]:
    """Bits of every part of both trees, values at their best chunk widths, in the published sense.

    The hierarchy tree has degree sequences and a vocabulary of places, the regular one a
    vocabulary of ranges; ``hast_overhead`` is the former's hierarchies in thousandths.
    """
    h, depth = t.cube.height, max(regular)
    counts = [slot_count(t, d).first() for d in range(1, h + 1)]
    slots = [r.slots for r in counts]
    width, values = best_width(value_lengths([t.nodes[d] for d in range(h + 1)], measure, sum(r.slots - r.nonempty for r in counts)))
    out = {"hast_occupancy": sum(slots[:-1]), "hast_limits": sum(slots), "hast_values": values, "hast_width": width}
    members = [t.members(d.name).agg(F.count("*").alias("c"), F.sum(F.length("label")).alias("chars")).first() for d in t.cube.dims]
    out |= {"hast_louds": sum(2 * (m.c + 1) - 1 for m in members), "hast_vocabulary": sum(8 * m.chars + 32 * m.c for m in members)}
    blocks = [regular[d].count() for d in range(depth + 1)]
    width, values = best_width(value_lengths(list(regular.values()), "total", sum(b * k**n for b in blocks[:-1]) - sum(blocks[1:])))
    out |= {"rst_occupancy": sum(b * k**n for b in blocks[:-2]) if depth > 1 else 0, "rst_values": values, "rst_width": width}
    out["rst_vocabulary"] = sum(8 * m.chars + 64 * m.c for m in members)
    total = {s: sum(v for c, v in out.items() if c.startswith(s) and not c.endswith("width")) for s in ("hast", "rst")}
    return out | {"hast_total": total["hast"], "rst_total": total["rst"], "hast_overhead": round(1000 * (out["hast_louds"] + out["hast_vocabulary"]) / total["hast"])}


def hast_space(t: Tree, measure: str, width: int) -> DataFrame:
    """``(structure, part, bits)`` of the tree along hierarchies.

    Occupancy has a bit per slot of all depths but the last, block limits one per slot of
    all; values are one per slot and the root, empty slots coded as zeros.
    """
    h = t.cube.height
    counts = reduce(DataFrame.unionByName, [slot_count(t, k) for k in range(1, h + 1)])
    parts = [
        counts.agg(F.coalesce(F.sum(F.when(F.col("depth") < h, F.col("slots"))), F.lit(0)).alias("bits")).select(F.lit("occupancy").alias("part"), "bits"),
        counts.agg(F.sum("slots").alias("bits")).select(F.lit("limits").alias("part"), "bits"),
    ]
    stored = reduce(DataFrame.unionByName, [t.nodes[k].agg(F.sum(F.expr(dac_bits_sql(measure, width))).alias("bits")) for k in range(h + 1)])
    empty = counts.agg((F.sum(F.col("slots") - F.col("nonempty")) * (width + 1)).alias("bits"))
    parts.append(stored.unionByName(empty).agg(F.sum("bits").alias("bits")).select(F.lit("values").alias("part"), "bits"))
    for d in t.cube.dims:
        m = t.members(d.name)
        parts.append(m.agg((2 * (F.count("*") + 1) - 1).alias("bits")).select(F.lit(f"louds_{d.name}").alias("part"), "bits"))
        parts.append(m.agg((F.sum(F.length("label")) * 8 + F.count("*") * 32).alias("bits")).select(F.lit(f"vocabulary_{d.name}").alias("part"), "bits"))
    out = reduce(DataFrame.unionByName, [p.select("part", F.col("bits").cast("long").alias("bits")) for p in parts])
    return out.select(F.lit("hast").alias("structure"), "part", "bits")


def rst_space(tree: dict[int, DataFrame], n: int, k: int, t: Tree, width: int) -> DataFrame:
    """The same of the regular tree; its vocabulary holds both ends of a label's range."""
    h = max(tree)
    slots = [tree[d - 1].agg((F.count("*") * k**n).alias("s")).select(F.lit(d).alias("depth"), "s") for d in range(1, h + 1)]
    slots = reduce(DataFrame.unionByName, slots)
    full = reduce(DataFrame.unionByName, [tree[d].agg(F.count("*").alias("c"), F.sum(F.expr(dac_bits_sql("total", width))).alias("b")) for d in range(h + 1)])
    occupancy = slots.agg(F.coalesce(F.sum(F.when(F.col("depth") < h, F.col("s"))), F.lit(0)).alias("bits")).select(F.lit("occupancy").alias("part"), "bits")
    totals = full.agg(F.sum("c").alias("c"), F.sum("b").alias("b")).crossJoin(slots.agg(F.sum("s").alias("s")))
    values = totals.select(F.lit("values").alias("part"), (F.col("b") + (F.col("s") + 1 - F.col("c")) * (width + 1)).alias("bits"))
    parts = [occupancy, values]
    for d in t.cube.dims:
        parts.append(t.members(d.name).agg((F.sum(F.length("label")) * 8 + F.count("*") * 64).alias("bits")).select(F.lit(f"vocabulary_{d.name}").alias("part"), "bits"))
    out = reduce(DataFrame.unionByName, [p.select("part", F.col("bits").cast("long").alias("bits")) for p in parts])
    return out.select(F.lit("rst").alias("structure"), "part", "bits")


def hast_closed_form(t: Tree, resolved: DataFrame) -> DataFrame:
    """Nodes summed and visited on a full cube: products of descendant counts."""
    h = t.cube.height
    out = resolved
    for d in t.cube.dims:
        for k in range(h + 1):
            counts = t.leaf[d.name].select(*[F.col(f"id_{j}") for j in range(1, h + 1)])
            # descendants of the member at depth l, at depth k >= l, by l
            step = None
            for level in range(k + 1):
                col = F.lit(1).cast("long")
                if level < k:
                    below = counts.groupBy(*([F.col(f"id_{level}").alias(f"__m")] if level else [])).agg(F.countDistinct(f"id_{k}").alias(f"__n{level}"))
                    if level:
                        out = out.join(below, F.expr(f"{d.name}_depth = {level} AND {d.name}_id_{level} = __m"), "left").drop("__m")
                    else:
                        out = out.crossJoin(F.broadcast(below))
                    col = F.col(f"__n{level}").cast("long")
                hit = F.when(F.col(f"{d.name}_depth") == level, col)
                step = hit if step is None else F.coalesce(step, hit)
            out = out.withColumn(f"__{d.name}_{k}", F.coalesce(step, F.lit(1).cast("long"))).drop(*[f"__n{level}" for level in range(k)])
    product = lambda k: reduce(lambda a, b: a * b, [F.col(f"__{d.name}_{k}") for d in t.cube.dims])
    visited = reduce(lambda a, b: a + b, [F.when(F.col("deepest") >= k, product(k)).otherwise(0) for k in range(h + 1)])
    summed = reduce(F.coalesce, [F.when(F.col("deepest") == k, product(k)) for k in range(h + 1)])
    return out.select("qid", summed.cast("long").alias("n_summed"), visited.cast("long").alias("n_visited"))

"""Members of hierarchies: numbers in level order, intervals, closures, vocabularies."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ordering import dense_ids
from ..sources.store import materialise
from ..spec import Dimension


def leaves(df: DataFrame, dim: Dimension) -> DataFrame:
    """One row per leaf member: its labels, ``id_1..id_H`` and, per depth, ordinal and the parent's fanout.

    ``df`` holds the level columns: facts (observed members) or a dimension table
    (declared ones).  Numbers follow the order of paths, which is level order.
    """
    cols = [dim.column(k) for k in range(1, dim.height + 1)]
    base = materialise(df.select(*cols).distinct(), f"leaves-{dim.name}")
    out = base
    for k in range(dim.height, 0, -1):
        keys = cols[:k]
        level = dense_ids(base.select(*keys).distinct(), keys, f"id_{k}")
        family = level.groupBy(*keys[:-1]).agg(F.min(f"id_{k}").alias("__first"), F.count("*").alias(f"fan_{k}"))
        level = level.join(family, keys[:-1]) if k > 1 else level.crossJoin(F.broadcast(family))  # one row
        out = out.join(level.withColumn(f"ord_{k}", F.col(f"id_{k}") - F.col("__first")).drop("__first"), keys)
    return materialise(out, f"members-{dim.name}")


def members(leaf: DataFrame, dim: Dimension) -> DataFrame:
    """All members but the root: depth, member_id, parent_id, label, parent_label, ordinal, fanout, lo, hi, is_copy."""
    found = []
    h = dim.height
    for k in range(1, h + 1):
        parent = [F.lit(0).cast("long").alias("parent_id"), F.lit(None).cast("string").alias("parent_label")] if k == 1 else [
            F.col(f"id_{k-1}").alias("parent_id"), F.col(dim.column(k - 1)).alias("parent_label")
        ]
        below = F.first(f"fan_{k+1}") if k < h else F.lit(0).cast("long")
        found.append(
            leaf.groupBy(F.col(f"id_{k}").alias("member_id"), *parent, F.col(dim.column(k)).alias("label"), F.col(f"ord_{k}").alias("ordinal"))
            .agg(F.min(f"id_{h}").alias("lo"), F.max(f"id_{h}").alias("hi"), below.alias("fanout"))
            .select(
                F.lit(k).alias("depth"), "member_id", "parent_id", "label", "parent_label", "ordinal",
                F.col("fanout").cast("long").alias("fanout"), "lo", "hi", F.lit(dim.is_copy(k)).alias("is_copy"),
            )
        )
    out = found[0]
    for x in found[1:]:
        out = out.unionByName(x)
    return out


def vocabulary(leaf: DataFrame, dim: Dimension) -> DataFrame:
    """``(label, depth, member_id, lo, hi, id_1..id_depth, n)``: where a label leads.

    A label at several depths (copied levels) leads to the shallowest; ``n`` counts the
    members of that depth that bear it, and above 1 it is ambiguous.
    """
    h = dim.height
    ids = [f"id_{k}" for k in range(1, h + 1)]
    parts = None
    for k in range(1, h + 1):
        part = leaf.groupBy(F.col(dim.column(k)).alias("label"), *[F.col(c) for c in ids[:k]]).agg(F.min(f"id_{h}").alias("lo"), F.max(f"id_{h}").alias("hi"))
        part = part.select(
            "label", F.lit(k).alias("depth"), F.col(f"id_{k}").alias("member_id"), "lo", "hi",
            *[F.col(c) if j < k else F.lit(None).cast("long").alias(c) for j, c in enumerate(ids)],
        )
        parts = part if parts is None else parts.unionByName(part)
    best = Window.partitionBy("label")
    return parts.withColumn("__d", F.min("depth").over(best)).filter("depth = __d").withColumn("n", F.count("*").over(best)).drop("__d")


def closure(leaf: DataFrame, dim: Dimension) -> DataFrame:
    """Pairs (member, ancestor) of all depths, itself included."""
    h = dim.height
    both = F.explode(F.array(*[
        F.struct(F.lit(k).alias("depth"), F.col(f"id_{k}").alias("member_id"), F.col(dim.column(k)).alias("label"),
                 F.lit(a).alias("anc_depth"), F.col(f"id_{a}").alias("anc_id"), F.col(dim.column(a)).alias("anc_label"))
        for k in range(1, h + 1) for a in range(1, k + 1)
    ]))
    return leaf.select(both.alias("p")).select("p.*").distinct()


def closure_recursive(spark, member_table: DataFrame) -> DataFrame:
    """The same by a recursive query over parent links, for hierarchies of unknown height."""
    return spark.sql(
        """
        WITH RECURSIVE up(depth, member_id, anc_depth, anc_id) AS (
          SELECT depth, member_id, depth, member_id FROM {m}
          UNION ALL
          SELECT u.depth, u.member_id, m.depth - 1, m.parent_id
          FROM up u JOIN {m} m ON m.depth = u.anc_depth AND m.member_id = u.anc_id WHERE u.anc_depth > 1)
        SELECT * FROM up""",
        m=member_table,
    )


def louds_bits(member_table: DataFrame) -> DataFrame:
    """``(bits, n_members)``: the whole hierarchy's unary degrees in level order, root first.

    For hierarchies that fit a row; larger ones stay relational.
    """
    unary = F.concat(F.repeat(F.lit("1"), F.col("fanout").cast("int")), F.lit("0"))
    rows = F.sort_array(F.collect_list(F.struct("depth", "member_id", unary.alias("u"))))
    top = F.count(F.when(F.col("depth") == 1, 1))
    return member_table.agg(
        F.concat(F.repeat(F.lit("1"), top.cast("int")), F.lit("0"), F.array_join(F.transform(rows, lambda r: r["u"]), "")).alias("bits"),
        (F.count("*") + 1).alias("n_members"),
    )


def check_hierarchy(member_table: DataFrame) -> DataFrame:
    """Violations: wrong intervals, children outside their parent, wrong fanouts (empty when sound)."""
    child, up = member_table.alias("c"), member_table.alias("p")
    joined = child.filter("depth > 1").join(up, F.expr("p.depth = c.depth - 1 AND p.member_id = c.parent_id"), "left")
    outside = joined.filter("p.member_id IS NULL OR c.lo < p.lo OR c.hi > p.hi").select(F.lit("outside").alias("kind"), "c.depth", "c.member_id")
    counts = joined.groupBy("p.depth", "p.member_id", "p.fanout").agg(F.count("*").alias("n"), F.min("c.lo").alias("lo"), F.max("c.hi").alias("hi"), F.sum(F.expr("c.hi - c.lo + 1")).alias("w"))
    fan = counts.filter("n <> fanout OR hi - lo + 1 <> w").select(F.lit("fanout").alias("kind"), "depth", "member_id")
    return outside.unionByName(fan)


def advise_plan(members_by_depth: dict[str, list[int]], wanted: list[dict[str, int]], height: int) -> dict[str, tuple[int, ...]]:
    """Level plans (1-based levels by depth) that make the fewest wanted level pairs need sums.

    ``wanted``: level of each dimension in a query.  Searches the monotone maps of levels
    to depths; ties go to the fewest stored members.
    """
    import itertools

    def maps(levels: int):
        return [p for p in itertools.combinations_with_replacement(range(1, levels + 1), height) if set(p) == set(range(1, levels + 1))]

    names = list(members_by_depth)
    best = None
    for combo in itertools.product(*(maps(len(members_by_depth[n])) for n in names)):
        plan = dict(zip(names, combo))
        missed = sum(not any(all(plan[n][d] == q[n] for n in names) for d in range(height)) for q in wanted)
        stored = 0
        for d in range(height):
            size = 1
            for n in names:
                size *= members_by_depth[n][plan[n][d] - 1]
            stored += size
        if best is None or (missed, stored) < best[0]:
            best = ((missed, stored), plan)
    return best[1]

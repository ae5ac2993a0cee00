"""Query sets drawn by rule, the same in Spark and in SQL: nothing random at run time."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.ordering import dense_ids
from ..operators.hast import Tree, ids
from ..spec import Cube

P = 1_000_003


def draw(q: str, i: int, seed: int = 0) -> str:
    """A number below P for query q and dimension i; squared twice, as a linear rule repeats itself."""
    x0 = f"(({q} * 7919 + {i * 104729 + seed * 31 + 1}) % {P})"
    x1 = f"(({x0} * {x0} + {7 * i + 3}) % {P})"
    return f"(({x1} * {x1} + {11 * i + 5}) % {P})"


def depth_sql(kind: str, height: int, i: int, fixed: int | None = None) -> str:
    """Depth of dimension i in query q: one depth for all, or mixed ones."""
    if kind == "one":
        return str(fixed)
    if kind == "mixed":  # cells excluded
        return f"(1 + (q + {i}) % {height - 1})" if height > 2 else f"((q + {i}) % 2)"
    if kind == "rooted":  # the first dimension over all its members
        return "0" if i == 0 else f"(1 + (q + {i}) % {max(height - 1, 1)})"
    return f"(1 + (q + {i}) % {height})"  # "three": cells included


def free_draws(t: Tree, n: int, kind: str, fixed: int | None = None, seed: int = 0) -> DataFrame:
    """``(qid, labels)``: members drawn by their level-order number."""
    out = t.spark.range(n).select(F.col("id").alias("q"))
    for i, d in enumerate(t.cube.dims):
        m = t.members(d.name)
        sizes = m.groupBy("depth").agg(F.count("*").alias("size"))
        asked = out.withColumn("depth", F.expr(depth_sql(kind, t.cube.height, i, fixed)).cast("int"))
        numbered = asked.join(F.broadcast(sizes), "depth", "left").withColumn("member_id", F.expr(f"{draw('q', i, seed)} % size"))
        labels = m.select("depth", "member_id", F.col("label").alias(d.name))
        out = numbered.join(labels, ["depth", "member_id"], "left").drop("depth", "member_id", "size").withColumn(d.name, F.coalesce(d.name, F.lit("*")))
    return out.withColumnRenamed("q", "qid")


def existing_draws(t: Tree, n: int, kind: str, fixed: int | None = None, seed: int = 0, first: int = 0) -> DataFrame:
    """Labels of nodes that exist: a node is taken by its rank, its members lifted to the drawn depths."""
    h = t.cube.height
    depth = fixed if kind == "one" else h
    keys = [f"{d.name}_id_{depth}" for d in t.cube.dims]
    ranked = dense_ids(t.nodes[depth].select(*ids(t.cube, depth)).distinct(), keys, "rank")
    total = ranked.count()
    asked = t.spark.range(n).select(F.col("id").alias("q"), F.expr(f"(id * 7919 + {seed}) % {max(total, 1)}").alias("rank"))
    out = asked.join(ranked, "rank")
    for i, d in enumerate(t.cube.dims):
        names = [F.col(d.column(k)) for k in range(1, depth + 1)]
        leaf = t.leaf[d.name].select(F.col(f"id_{depth}").alias(f"{d.name}_id_{depth}"), *[c.alias(f"__{k}") for k, c in enumerate(names, 1)]).distinct()
        pick = F.element_at(F.array(F.lit("*"), *[F.col(f"__{k}") for k in range(1, depth + 1)]), F.expr(depth_sql(kind, h, i, fixed)).cast("int") + 1)
        out = out.join(leaf, f"{d.name}_id_{depth}").withColumn(d.name, pick).drop(*[f"__{k}" for k in range(1, depth + 1)])
    return out.select((F.col("q") + first).alias("qid"), *[d.name for d in t.cube.dims])


def query_set(t: Tree, n: int, kind: str, fixed: int | None = None, seed: int = 0) -> DataFrame:
    """n free draws and n from existing nodes."""
    return free_draws(t, n, kind, fixed, seed).unionByName(existing_draws(t, n, kind, fixed, seed, n))


def query_set_sql(cube: Cube, facts: str, n: int, kind: str, fixed: int | None = None, seed: int = 0) -> str:
    """The same set as CTEs over ``facts`` (ends with the CTE ``queries``, depths ``g1..gn`` included)."""
    h = cube.height
    dims = cube.dims
    out = [f"facts AS ({facts})"]
    for i, d in enumerate(dims):
        parts = []
        for k in range(1, h + 1):
            cols = [d.column(j) for j in range(1, k + 1)]
            parts.append(
                f"SELECT {k} AS depth, {d.column(k)} AS label, row_number() OVER (ORDER BY {', '.join(cols)}) - 1 AS id, count(*) OVER () AS size "
                f"FROM (SELECT DISTINCT {', '.join(cols)} FROM facts)"
            )
        out.append(f"m{i} AS ({' UNION ALL '.join(parts)})")
    depth = fixed if kind == "one" else h
    g = [depth_sql(kind, h, i, fixed) for i in range(len(dims))]
    joins = " ".join(f"LEFT JOIN m{i} ON m{i}.depth = {g[i]} AND m{i}.id = {draw('q', i, seed)} % m{i}.size" for i in range(len(dims)))
    labels = ", ".join(f"coalesce(m{i}.label, '*') AS {d.name}, {g[i]} AS g{i}" for i, d in enumerate(dims))
    out.append(f"free AS (SELECT q AS qid, {labels} FROM (SELECT range AS q FROM range({n})) {joins})")
    cols = [d.column(k) for d in dims for k in range(1, depth + 1)]
    out.append(f"node AS (SELECT *, row_number() OVER (ORDER BY {', '.join(cols)}) - 1 AS rank, count(*) OVER () AS total FROM (SELECT DISTINCT {', '.join(cols)} FROM facts))")
    lifted = ", ".join(f"CASE {g[i]} WHEN 0 THEN '*' " + " ".join(f"WHEN {k} THEN {d.column(k)}" for k in range(1, depth + 1)) + f" END AS {d.name}, {g[i]} AS g{i}" for i, d in enumerate(dims))
    out.append(f"drawn AS (SELECT q + {n} AS qid, {lifted} FROM (SELECT range AS q FROM range({n})) JOIN node ON rank = (q * 7919 + {seed}) % total)")
    out.append("queries AS (SELECT * FROM free UNION ALL SELECT * FROM drawn)")
    return ", ".join(out)


def truth_sql(cube: Cube, facts: str, n: int, kind: str, fixed: int | None = None, seed: int = 0) -> str:
    """Answers of the set from raw facts: qid, labels, measures, cnt, n_summed."""
    h, dims = cube.height, cube.dims
    match = " AND ".join(f"(g{i} = 0" + "".join(f" OR (g{i} = {k} AND f.{d.column(k)} = q.{d.name})" for k in range(1, h + 1)) + ")" for i, d in enumerate(dims))
    deepest = f"greatest({', '.join(f'g{i}' for i in range(len(dims)))})" if len(dims) > 1 else "g0"
    key = " ".join(f"WHEN {k} THEN concat_ws('|', {', '.join(f'f.{d.column(j)}' for d in dims for j in range(1, k + 1))})" for k in range(1, h + 1))
    sums = ", ".join(f"CAST(coalesce(sum(f.{m}), 0) AS BIGINT) AS {m}" for m, _ in cube.measures)
    names = ", ".join(f"q.{d.name}" for d in dims)
    return (
        f"WITH {query_set_sql(cube, facts, n, kind, fixed, seed)} "
        f"SELECT q.qid, {names}, {sums}, CAST(count(f.{dims[0].column(1)}) AS BIGINT) AS cnt, "
        f"CAST(count(DISTINCT CASE WHEN f.{dims[0].column(1)} IS NOT NULL THEN CASE {deepest} {key} WHEN 0 THEN '' END END) AS BIGINT) AS n_summed "
        f"FROM queries q LEFT JOIN facts f ON {match} GROUP BY q.qid, {names}"
    )


def boxes(spark, n_queries: int, n: int, m: int, seed: int = 0) -> DataFrame:
    """Boxes between two drawn coordinates in each dimension, aligned to nothing."""
    out = spark.range(n_queries).select(F.col("id").alias("q"))
    cols = [F.col("q").alias("qid")]
    for i in range(n):
        a, b = f"{draw('q', 2 * i, seed)} % {m}", f"{draw('q', 2 * i + 1, seed)} % {m}"
        cols += [F.expr(f"least({a}, {b})").alias(f"lo_{i + 1}"), F.expr(f"greatest({a}, {b})").alias(f"hi_{i + 1}")]
    return out.select(*cols)


def boxes_sql(n_queries: int, n: int, m: int, seed: int = 0) -> str:
    cols = ["q AS qid"]
    for i in range(n):
        a, b = f"{draw('q', 2 * i, seed)} % {m}", f"{draw('q', 2 * i + 1, seed)} % {m}"
        cols += [f"least({a}, {b}) AS lo_{i + 1}", f"greatest({a}, {b}) AS hi_{i + 1}"]
    return f"SELECT {', '.join(cols)} FROM (SELECT range AS q FROM range({n_queries}))"


def day_boxes_sql(table: str, m: int) -> str:
    """One box for each ship date of the line items, between coordinates added up from that day's keys."""
    cols = []
    for i, key in enumerate(("l_partkey", "l_suppkey", "l_orderkey", "CAST(l_quantity AS BIGINT)"), 1):
        a, b = (f"CAST(coalesce(sum({key} % {m}{by}), 0) % {m} AS BIGINT)" for by in ("", " * l_linenumber"))
        cols += [f"least({a}, {b}) AS lo_{i}", f"greatest({a}, {b}) AS hi_{i}"]
    day = "CAST(year(l_shipdate) AS BIGINT) * 1000 + CAST(dayofyear(l_shipdate) AS BIGINT)"
    return f"SELECT {day} AS qid, {', '.join(cols)} FROM {table} WHERE l_shipdate IS NOT NULL GROUP BY {day}"


def label_boxes(t: Tree, queries: DataFrame) -> DataFrame:
    """Labels to coordinate boxes: the vocabulary of ranges that the regular tree needs."""
    out = queries
    for i, d in enumerate(t.cube.dims, 1):
        v = t.vocabulary(d.name).filter("n = 1").select(F.col("label").alias(d.name), F.col("lo").alias(f"lo_{i}"), F.col("hi").alias(f"hi_{i}"))
        out = out.join(v, d.name)
    bounds = reduce(lambda a, b: a + b, [[f"lo_{i}", f"hi_{i}"] for i in range(1, len(t.cube.dims) + 1)])
    return out.select("qid", *bounds)

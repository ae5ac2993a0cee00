"""Hierarchies, cells and the tree along hierarchies over the given tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import hast, hierarchy
from ..workloads import cubes
from .common import Registry, cols, level_sql, members_sql, slots_sql, tree_of


def register(r: Registry) -> None:
    def member_query(cube, dim, names):
        return lambda s, d: tree_of(s, d, cube).members(dim).select(*names)

    base = ["depth", "label", "parent_label", "ordinal", "fanout"]
    for key, cube, dim in (
        ("h_supplier_geo_members", cubes.C1, "geo"), ("h_customer_geo_members", cubes.S_CUSTOMER, "geo"),
        ("h_part_members", cubes.C1, "product"), ("h_time_members", cubes.C1, "time"), ("h_url_members", cubes.C6, "host"),
    ):
        d = next(x for x in cube.dims if x.name == dim)
        r.add(key, member_query(cube, dim, base), f"SELECT {', '.join(base)} FROM {members_sql(d, cube.sql())}")
    geo = cubes.C1.dims[0]
    r.add("h_leaf_ranges", member_query(cubes.C1, "geo", ["depth", "label", "lo", "hi"]), f"SELECT depth, label, lo, hi FROM {members_sql(geo, cubes.C1.sql())}")
    pairs = " UNION ".join(
        f"SELECT DISTINCT {k} AS depth, {geo.column(k)} AS label, {a} AS anc_depth, {geo.column(a)} AS anc_label FROM f" for k in (1, 2, 3) for a in range(1, k + 1)
    )
    r.add(
        "h_closure",
        lambda s, d: hierarchy.closure(tree_of(s, d, cubes.C1).leaf["geo"], geo).select("depth", "label", "anc_depth", "anc_label"),
        f"WITH f AS ({cubes.C1.sql()}) {pairs}",
    )
    c2geo = cubes.C2.dims[0]
    r.add("h_padded_levels", member_query(cubes.C2, "geo", ["depth", "label", "parent_label", "is_copy"]), f"SELECT depth, label, parent_label, is_copy FROM {members_sql(c2geo, cubes.C2.sql())}")

    def plans(s, d):
        parts = []
        for name, cube in (("copy_below", cubes.C2), ("copy_above", cubes.C2_ABOVE)):
            t = tree_of(s, d, cube)
            parts += [t.nodes[k].agg(F.count("*").alias("nodes"), F.sum("cents").cast("long").alias("cents")).select(F.lit(name).alias("plan"), F.lit(k).alias("depth"), "nodes", "cents") for k in range(1, 5)]
        return reduce(DataFrame.unionByName, parts)

    r.add("h_level_plan_variant", plans, " UNION ALL ".join(
        f"SELECT '{name}' AS plan, {k} AS depth, count(*) AS nodes, CAST(sum(c) AS BIGINT) AS cents FROM (SELECT sum(cents) AS c FROM ({cube.sql()}) GROUP BY {', '.join(cols(x, k) for x in cube.dims)})"
        for name, cube in (("copy_below", cubes.C2), ("copy_above", cubes.C2_ABOVE)) for k in range(1, 5)
    ))

    def bits(s, d):
        t = tree_of(s, d, cubes.C1)
        return reduce(DataFrame.unionByName, [hierarchy.louds_bits(t.members(x.name)).select(F.lit(x.name).alias("dim"), "bits", "n_members") for x in cubes.C1.dims])

    r.add("h_louds_bits", bits, " UNION ALL ".join(
        f"SELECT '{x.name}' AS dim, repeat('1', CAST(count(*) FILTER (depth = 1) AS INTEGER)) || '0' || "
        f"string_agg(repeat('1', CAST(fanout AS INTEGER)) || '0', '' ORDER BY depth, member_id) AS bits, count(*) + 1 AS n_members FROM {members_sql(x, cubes.C1.sql())}"
        for x in cubes.C1.dims
    ))

    def vocab(s, d):
        t = tree_of(s, d, cubes.C1)
        return reduce(DataFrame.unionByName, [t.vocabulary(x.name).select(F.lit(x.name).alias("dim"), "depth", "label", "member_id") for x in cubes.C1.dims])

    r.add("h_vocab", vocab, " UNION ALL ".join(f"SELECT '{x.name}' AS dim, depth, label, member_id FROM {members_sql(x, cubes.C1.sql())}" for x in cubes.C1.dims))
    r.add("h_violations", lambda s, d: hierarchy.check_hierarchy(tree_of(s, d, cubes.C1).members("product")), "SELECT '' AS kind, 0 AS depth, CAST(0 AS BIGINT) AS member_id WHERE false")

    def broken(s, d):
        """Each part of an odd number hung below the next brand: outside its parent, whose fanout is wrong."""
        m = tree_of(s, d, cubes.C1).members("product")
        brands = m.filter("depth = 2").count()
        wrong = F.when(F.expr("depth = 3 AND member_id % 2 = 1"), F.expr(f"(parent_id + 1) % {brands}")).otherwise(F.col("parent_id"))
        return hierarchy.check_hierarchy(m.withColumn("parent_id", wrong)).filter("kind = 'outside'").select("kind", "depth", "member_id")

    leaf = members_sql(cubes.C1.dims[1], cubes.C1.sql())
    r.add("h_violations_found", broken, f"SELECT 'outside' AS kind, 3 AS depth, member_id FROM {leaf} WHERE depth = 3 AND member_id % 2 = 1")

    # Cells and nodes of the sales cube.
    labels = [d.name for d in cubes.C1.dims]
    sums = [m for m, _ in cubes.C1.measures]
    for key, k in (("c1_cells", 3), ("hast_depth1", 1), ("hast_depth2", 2)):
        r.add(key, lambda s, d, k=k: tree_of(s, d, cubes.C1).labelled(k).select(*labels, *[F.col(m).cast("long").alias(m) for m in sums], "cnt"), level_sql(cubes.C1, k))

    def totals(s, d):
        t = tree_of(s, d, cubes.C1)
        return reduce(DataFrame.unionByName, [t.nodes[k].agg(F.count("*").alias("nodes"), F.sum("qty").cast("long").alias("qty"), F.sum("cents").cast("long").alias("cents")).withColumn("depth", F.lit(k)) for k in range(4)])

    c1keys = {k: ", ".join(cols(x, k) for x in cubes.C1.dims) for k in (1, 2, 3)}
    r.add("hast_all_depth_totals", totals, f"WITH f AS ({cubes.C1.sql()}), t AS (SELECT CAST(sum(qty) AS BIGINT) AS qty, CAST(sum(cents) AS BIGINT) AS cents FROM f) SELECT 0 AS depth, 1 AS nodes, qty, cents FROM t " + " ".join(
        f"UNION ALL SELECT {k}, (SELECT count(*) FROM (SELECT DISTINCT {c1keys[k]} FROM f)), qty, cents FROM t" for k in (1, 2, 3)))
    counts = lambda s, d: reduce(DataFrame.unionByName, [hast.slot_count(tree_of(s, d, cubes.C1), k) for k in (1, 2, 3)])
    counts_sql = f"WITH f AS ({cubes.C1.sql()}) " + " UNION ALL ".join(slots_sql(cubes.C1, k, "f") for k in (1, 2, 3))
    r.add("hast_node_counts", counts, counts_sql)
    r.add("hast_occupancy_counts", lambda s, d: counts(s, d).filter("depth < 3").selectExpr("depth", "nonempty AS ones", "slots - nonempty AS zeros"),
          f"SELECT depth, nonempty AS ones, slots - nonempty AS zeros FROM ({counts_sql}) WHERE depth < 3")

    def zeros(s, d):
        t = tree_of(s, d, cubes.C1)
        named = t.leaf
        out = hast.slots(t, 1).select("p_1", "qty")
        fans = {x.name: named[x.name].select(F.col(x.column(1)).alias(x.name), F.col("ord_1").alias(f"o_{x.name}"), F.col("fan_1").alias(f"f_{x.name}")).distinct() for x in cubes.C1.dims}
        combos = reduce(lambda a, b: a.crossJoin(b), fans.values())  # the few members of depth 1
        number = F.lit(0).cast("long")
        for x in reversed(cubes.C1.dims):
            number = F.col(f"f_{x.name}") * number + F.col(f"o_{x.name}")
        return combos.withColumn("p_1", number).join(out, "p_1").select(*labels, F.col("qty").cast("long").alias("qty"))

    r.add("hast_values_with_zeros", zeros,
          f"WITH f AS ({cubes.C1.sql()}), g AS (SELECT DISTINCT geo_1 FROM f), p AS (SELECT DISTINCT product_1 FROM f), t AS (SELECT DISTINCT time_1 FROM f) "
          "SELECT g.geo_1 AS geo, p.product_1 AS product, t.time_1 AS time, CAST(coalesce(sum(qty), 0) AS BIGINT) AS qty FROM g CROSS JOIN p CROSS JOIN t LEFT JOIN f USING (geo_1, product_1, time_1) GROUP BY 1, 2, 3")
    r.add("hast_minmax", lambda s, d: tree_of(s, d, cubes.C1).labelled(1).select(*labels, "min_cents", "max_cents"), f"SELECT {', '.join(f'{x}_1 AS {x}' for x in labels)}, min(cents) AS min_cents, max(cents) AS max_cents FROM ({cubes.C1.sql()}) GROUP BY 1, 2, 3")
    # Both sides divide the same exact integers once.
    r.add("hast_avg_var", lambda s, d: tree_of(s, d, cubes.C1).labelled(1).select(
        *labels, (F.col("qty").cast("double") / F.col("cnt").cast("double")).alias("avg_qty"),
        ((F.col("cnt") * F.col("sq_qty").cast("long") - F.col("qty") * F.col("qty")).cast("double") / (F.col("cnt") * F.col("cnt")).cast("double")).alias("var_qty")),
        f"SELECT {', '.join(f'{x}_1 AS {x}' for x in labels)}, CAST(sum(qty) AS DOUBLE) / CAST(count(*) AS DOUBLE) AS avg_qty, "
        f"CAST(count(*) * sum(qty * qty) - sum(qty) * sum(qty) AS DOUBLE) / CAST(count(*) * count(*) AS DOUBLE) AS var_qty FROM ({cubes.C1.sql()}) GROUP BY 1, 2, 3")
    with_order = cubes.Cube("c1o", cubes.C1.source, cubes.C1.dims, (("l_orderkey", "l_orderkey"),), cubes.C1.tables)
    r.add("hast_distinct", lambda s, d: with_order.facts(s, d).groupBy(*[F.col(f"{x}_1").alias(x) for x in labels]).agg(F.countDistinct("l_orderkey").alias("orders_distinct")),
          f"SELECT {', '.join(f'{x}_1 AS {x}' for x in labels)}, count(DISTINCT l_orderkey) AS orders_distinct FROM ({with_order.sql()}) GROUP BY 1, 2, 3")

    # The other cubes: all depths, labels and sums.
    for key, cube in (
        ("events_user_type_time", cubes.C4), ("events_json_dim", cubes.C4_JSON), ("docs_lang_source", cubes.C5), ("pages_url_tree", cubes.C6), ("conversations_role_turn", cubes.C7),
        ("benchmark_length_tree", cubes.C9), ("orders_plan_tree", cubes.C2), ("flags_status_tree", cubes.C3),
        ("supplier_signed_balance", cubes.S_SUPPLIER), ("orders_signed_balance", cubes.S_CUSTOMER),
    ):
        names, ms = [x.name for x in cube.dims], [m for m, _ in cube.measures]

        def every(s, d, cube=cube, names=names, ms=ms):
            t = tree_of(s, d, cube)
            return reduce(DataFrame.unionByName, [t.labelled(k).select(F.lit(k).alias("depth"), *names, *[F.col(m).cast("long").alias(m) for m in ms], "cnt") for k in range(1, cube.height + 1)])

        sql = " UNION ALL ".join(f"SELECT {k} AS depth, * FROM ({level_sql(cube, k)})" for k in range(1, cube.height + 1))
        r.add(key, every, sql.replace(cubes.JSON_IN_SPARK, cubes.JSON_IN_DUCKDB))

    def quality(s, d):
        t = tree_of(s, d, cubes.C5)
        return t.nodes[1].join(t.leaf["place"].select(F.col("id_1").alias("place_id_1"), F.col("place_1").alias("lang")).distinct(), "place_id_1").groupBy("lang").agg(
            F.sum("quality").cast("long").alias("quality"), F.sum("toxic").cast("long").alias("toxic"), F.sum("cnt").cast("long").alias("cnt"))

    r.add("labels_quality_by_lang", quality, f"SELECT place_1 AS lang, CAST(sum(quality) AS BIGINT) AS quality, CAST(sum(toxic) AS BIGINT) AS toxic, count(*) AS cnt FROM ({cubes.C5.sql()}) GROUP BY 1")

    def vectors(s, d):
        cells = s.read.parquet(f"{d}/embeddings.parquet").select("vec_id", "label", F.posexplode("embedding").alias("i", "x")).select(
            F.col("label").cast("string").alias("lab"), F.expr("vec_id div 10").alias("tens"), F.expr("i div 16").cast("long").alias("b1"), F.expr("i div 4").cast("long").alias("b2"),
            F.expr("CAST(ROUND(CAST(x AS DOUBLE) * 1e6) AS BIGINT)").alias("v"))
        deep = cells.groupBy("lab", "tens", "b1", "b2").agg(F.sum("v").alias("v"), F.count("*").alias("cnt"))
        top = deep.groupBy("lab", "b1").agg(F.sum("v").cast("long").alias("v"), F.sum("cnt").alias("cnt"))
        a = top.select(F.lit(1).alias("depth"), F.concat_ws("/", "lab", F.col("b1").cast("string")).alias("label"), "v", "cnt")
        b = deep.select(F.lit(2).alias("depth"), F.concat_ws("/", "lab", F.col("tens").cast("string"), F.col("b2").cast("string")).alias("label"), "v", "cnt")
        return a.unionByName(b)

    r.add("embeddings_matrix_signed", vectors,
          "WITH e AS (SELECT CAST(label AS VARCHAR) AS lab, vec_id // 10 AS tens, unnest(embedding) AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings), "
          "c AS (SELECT *, CAST(ROUND(CAST(x AS DOUBLE) * 1e6) AS BIGINT) AS v FROM e) "
          "SELECT 1 AS depth, lab || '/' || CAST(i // 16 AS VARCHAR) AS label, CAST(sum(v) AS BIGINT) AS v, count(*) AS cnt FROM c GROUP BY lab, i // 16 UNION ALL "
          "SELECT 2, lab || '/' || CAST(tens AS VARCHAR) || '/' || CAST(i // 4 AS VARCHAR), CAST(sum(v) AS BIGINT), count(*) FROM c GROUP BY lab, tens, i // 4")

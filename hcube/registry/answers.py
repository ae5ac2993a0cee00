"""Queries by label: one stored value, sums of several, and what surrounds them; baselines."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import baselines, related
from ..plans import planner
from ..workloads import cubes, querysets
from .common import Registry, cols, members_sql, tree_of

N = 200
C1 = cubes.C1


def register(r: Registry) -> None:
    names, sums = [x.name for x in C1.dims], [m for m, _ in C1.measures]
    keep = ["qid", *names, *sums, "cnt", "n_summed"]
    for key, cube, kind, fixed in (
        ("q1_cells", C1, "one", 3), ("q1_internal", C1, "one", 2), ("q1_top", C1, "one", 1), ("q2_mixed_two", C1, "mixed", None),
        ("q2_mixed_three", C1, "three", None), ("q2_rooted", C1, "rooted", None), ("q2_copied_levels", cubes.C2, "mixed", None), ("q1_flags", cubes.C3, "one", 1), ("q2_flags", cubes.C3, "mixed", None),
    ):
        out = ["qid", *[x.name for x in cube.dims], *[m for m, _ in cube.measures], "cnt", "n_summed"]

        def ask(s, d, cube=cube, kind=kind, fixed=fixed, out=out):
            t = tree_of(s, d, cube)
            return planner.answer(t, querysets.query_set(t, N, kind, fixed)).select(*out)

        # A copied level's label leads to its shallowest depth, so stored values read are counted for unique labels only.
        if cube is cubes.C2:
            out.remove("n_summed")
        sql = querysets.truth_sql(cube, cube.sql(), N, kind, fixed)
        r.add(key, ask, f"SELECT {', '.join(out)} FROM ({sql})")

    def region_month(s, d):
        t = tree_of(s, d, C1)
        regions = t.leaf["geo"].select(F.col("geo_1").alias("geo")).distinct()
        months = t.leaf["time"].select(F.col("time_2").alias("time")).distinct()
        asked = regions.crossJoin(months).select("geo", F.lit("*").alias("product"), "time", F.xxhash64("geo", "time").alias("qid"))  # both few
        return planner.answer(t, asked).select(F.col("geo").alias("region"), F.col("time").alias("month"), "qty")

    r.add("q_region_month", region_month,
          f"WITH f AS ({C1.sql()}), a AS (SELECT DISTINCT geo_1 FROM f), b AS (SELECT DISTINCT time_2 FROM f) "
          "SELECT a.geo_1 AS region, b.time_2 AS month, CAST(coalesce(sum(qty), 0) AS BIGINT) AS qty FROM a CROSS JOIN b LEFT JOIN f ON f.geo_1 = a.geo_1 AND f.time_2 = b.time_2 GROUP BY 1, 2")

    def fixed_labels(s, d, rows):
        t = tree_of(s, d, C1)
        return planner.answer(t, s.createDataFrame(rows, "qid long, geo string, product string, time string")).select("qid", "status", "qty")

    r.add("q_unknown_label", lambda s, d: fixed_labels(s, d, [(1, "ASIA", "*", "1995"), (2, "ATLANTIS", "*", "1995"), (3, "*", "*", "*")]),
          f"WITH f AS ({C1.sql()}) SELECT CAST(1 AS BIGINT) AS qid, 'ok' AS status, CAST(coalesce(sum(qty), 0) AS BIGINT) AS qty FROM f WHERE geo_1 = 'ASIA' AND time_1 = '1995' "
          "UNION ALL SELECT 2, 'unknown_label', NULL UNION ALL SELECT 3, 'ok', CAST(sum(qty) AS BIGINT) FROM f")
    # A region with another region's nation has no cell: the answer is 0, not null.
    r.add("q_empty_zero", lambda s, d: _leaf_pairs(s, d), _leaf_pairs_sql())
    r.add("q_slice_rows", lambda s, d: tree_of(s, d, C1).labelled(2).join(
        tree_of(s, d, C1).leaf["geo"].filter("geo_1 = 'ASIA'").select(F.col("geo_2").alias("geo")).distinct(), "geo").groupBy("product", "time").agg(F.sum("qty").cast("long").alias("qty")),
        f"SELECT product_2 AS product, time_2 AS time, CAST(sum(qty) AS BIGINT) AS qty FROM ({C1.sql()}) WHERE geo_1 = 'ASIA' GROUP BY 1, 2")

    def in_list(s, d):
        t = tree_of(s, d, C1)
        asia = t.leaf["geo"].filter("geo_1 = 'ASIA'").agg(F.min("geo_2").alias("geo")).select("geo")
        rows = s.createDataFrame([("ASIA",), ("EUROPE",)], "geo string").unionByName(asia)
        return planner.member_set(t, rows.select(F.lit(1).cast("long").alias("qid"), "geo", F.lit("*").alias("product"), F.lit("*").alias("time")), "geo").select("qid", "qty")

    r.add("q_in_list", in_list, f"SELECT CAST(1 AS BIGINT) AS qid, CAST(sum(qty) AS BIGINT) AS qty FROM ({C1.sql()}) WHERE geo_1 IN ('ASIA', 'EUROPE')")

    def complement(s, d):
        t = tree_of(s, d, C1)
        regions = t.leaf["geo"].select(F.col("geo_1").alias("geo")).distinct().select(F.xxhash64("geo").alias("qid"), "geo", F.lit("*").alias("product"), F.lit("*").alias("time"))
        part = planner.answer(t, regions)
        return part.crossJoin(t.nodes[0].select(F.col("qty").alias("all"))).select("geo", (F.col("all") - F.col("qty")).cast("long").alias("qty"))  # the root is one row

    r.add("q_complement", complement, f"WITH f AS ({C1.sql()}), a AS (SELECT DISTINCT geo_1 FROM f) SELECT a.geo_1 AS geo, CAST(sum(qty) AS BIGINT) AS qty FROM a JOIN f ON f.geo_1 <> a.geo_1 GROUP BY 1")
    r.add("q_iceberg", lambda s, d: tree_of(s, d, C1).labelled(2).filter("qty >= 100").select(*names, F.col("qty").cast("long").alias("qty")),
          f"SELECT geo_2 AS geo, product_2 AS product, time_2 AS time, CAST(sum(qty) AS BIGINT) AS qty FROM ({C1.sql()}) GROUP BY geo_1, geo_2, product_1, product_2, time_1, time_2 HAVING sum(qty) >= 100")
    mixed_sql = querysets.truth_sql(C1, C1.sql(), N, "mixed")
    r.add("q2_mixed_exploded", lambda s, d: planner.answer_exploded(tree_of(s, d, C1), querysets.query_set(tree_of(s, d, C1), N, "mixed")).select("qid", "qty", "n_summed"), f"SELECT qid, qty, n_summed FROM ({mixed_sql})")

    def brute(s, d):
        t = tree_of(s, d, C1)
        asked = querysets.query_set(t, N, "mixed")
        for i in range(len(C1.dims)):
            asked = asked.withColumn(f"g{i}", F.expr(querysets.depth_sql("mixed", 3, i).replace("q ", f"(qid % {N}) ")).cast("int"))
        return baselines.brute_force(t.facts, C1, asked).select("qid", "qty")

    r.add("brute_facts", brute, f"SELECT qid, qty FROM ({mixed_sql})")
    sets = lambda cube, tuples: ", ".join("(" + ", ".join(c for x, k in zip(cube.dims, t) for c in ([cols(x, k)] if k else [])) + ")" for t in tuples)
    out_cols = [x.column(k) for x in C1.dims for k in (1, 2, 3)]
    one = [(k, k, k) for k in range(4)]
    r.add("rollup_depths", lambda s, d: baselines.rollup_depths(C1.facts(s, d), C1).select(*out_cols, *sums, "cnt"),
          f"SELECT {', '.join(out_cols)}, CAST(sum(qty) AS BIGINT) AS qty, CAST(sum(cents) AS BIGINT) AS cents, count(*) AS cnt FROM ({C1.sql()}) GROUP BY GROUPING SETS ({sets(C1, one)})")
    from itertools import product as every

    lattice_sql = lambda n, of: f"SELECT {', '.join(of)}, CAST(sum(qty) AS BIGINT) AS qty, CAST(sum(cents) AS BIGINT) AS cents, count(*) AS cnt FROM ({C1.sql()}) GROUP BY GROUPING SETS ({sets(C1, every(range(n + 1), repeat=3))})"
    low = [x.column(k) for x in C1.dims for k in (1, 2)]
    r.add("lattice_upper_levels", lambda s, d: baselines.lattice(C1.facts(s, d), C1, 2).select(*low, *sums, "cnt"), lattice_sql(2, low))
    # All 64 tuples of depths, each by what its members add up to: the rows themselves are many times the facts.
    depth = ", ".join(f"CAST({' + '.join(f'CASE WHEN {x.column(k)} IS NULL THEN 0 ELSE 1 END' for k in (1, 2, 3))} AS INTEGER) AS g_{x.name}" for x in C1.dims)
    tuple_of = ", ".join(f"g_{x.name}" for x in C1.dims)
    checks = "count(*) AS members, CAST(sum(qty) AS BIGINT) AS qty, CAST(max(qty) AS BIGINT) AS most, CAST(sum(qty * qty) AS BIGINT) AS squares, CAST(sum(cents) AS BIGINT) AS cents, CAST(sum(cnt) AS BIGINT) AS cnt"

    r.add("lattice_all_levels", lambda s, d: baselines.lattice_checks(C1.facts(s, d), C1), f"SELECT {tuple_of}, {checks} FROM (SELECT {depth}, qty, cents, cnt FROM ({lattice_sql(3, out_cols)})) GROUP BY {tuple_of}")

    # Operators around the tree.
    def running(s, d):
        t = tree_of(s, d, C1)
        months = t.leaf["time"].select("id_2", F.col("time_1").alias("year"), F.col("time_2").alias("month")).distinct()
        rows = t.nodes[2].groupBy(F.col("time_id_2").alias("id_2")).agg(F.sum("qty").cast("long").alias("qty")).join(months, "id_2")
        return rows.select("year", "month", "qty", F.sum("qty").over(Window.partitionBy("year").orderBy("month")).alias("running"))

    r.add("window_running_total", running, f"WITH m AS (SELECT time_1 AS year, time_2 AS month, CAST(sum(qty) AS BIGINT) AS qty FROM ({C1.sql()}) GROUP BY 1, 2) SELECT year, month, qty, CAST(sum(qty) OVER (PARTITION BY year ORDER BY month) AS BIGINT) AS running FROM m")

    def topk(s, d):
        t = tree_of(s, d, C1)
        place = t.leaf["geo"].select("id_2", F.col("geo_1").alias("region"), F.col("geo_2").alias("nation")).distinct()
        rows = t.nodes[2].groupBy(F.col("geo_id_2").alias("id_2")).agg(F.sum("qty").cast("long").alias("qty")).join(place, "id_2")
        rank = F.row_number().over(Window.partitionBy("region").orderBy(F.desc("qty"), "nation"))
        return rows.select("region", rank.alias("rank"), "nation", "qty").filter("rank <= 3")

    r.add("topk_members", topk, f"WITH m AS (SELECT geo_1 AS region, geo_2 AS nation, CAST(sum(qty) AS BIGINT) AS qty FROM ({C1.sql()}) GROUP BY 1, 2) SELECT * FROM (SELECT region, CAST(row_number() OVER (PARTITION BY region ORDER BY qty DESC, nation) AS INTEGER) AS rank, nation, qty FROM m) WHERE rank <= 3")

    def best_cells(s, d):
        t = tree_of(s, d, C1)
        out = related.top_cells(t.nodes, names, "qty", 20)
        for x in C1.dims:
            out = out.withColumnRenamed(x.name, f"id_{x.name}").join(t.leaf[x.name].select(F.col("id_3").alias(f"id_{x.name}"), F.concat_ws("/", *[x.column(k) for k in (1, 2, 3)]).alias(x.name)), f"id_{x.name}")
        return out.select(*names, F.col("qty").cast("long").alias("qty"))

    paths = [f"concat_ws('/', {cols(x, 3)})" for x in C1.dims]
    r.add("topk_best_first", best_cells, f"SELECT {', '.join(f'{p} AS {x}' for p, x in zip(paths, names))}, CAST(sum(qty) AS BIGINT) AS qty FROM ({C1.sql()}) GROUP BY {', '.join(cols(x, 3) for x in C1.dims)} ORDER BY qty DESC, {', '.join(cols(x, 3) for x in C1.dims)} LIMIT 20")

    def pivoted(s, d):
        rows = tree_of(s, d, cubes.C3).labelled(1)
        return rows.groupBy("state").pivot("flag", ["A", "N", "R"]).agg(F.sum("qty").cast("long")).na.fill(0)

    r.add("pivot_flags", pivoted, f"SELECT state, {', '.join(f'CAST(coalesce(sum(qty) FILTER (flag_1 = {chr(39)}{x}{chr(39)}), 0) AS BIGINT) AS {chr(34)}{x}{chr(34)}' for x in 'ANR')} FROM (SELECT state_1 AS state, flag_1, qty FROM ({cubes.C3.sql()})) GROUP BY state")

    def counted(s, d):
        """Cells of each flag by order state, as a map turned to text."""
        rows = tree_of(s, d, cubes.C3).labelled(1).groupBy("flag").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("state", "cnt")))).alias("m"))
        halves = F.transform_values("m", lambda k, v: F.floor(v / 2))
        text = F.array_join(F.transform(F.map_keys(halves), lambda k: F.concat_ws(":", k, F.element_at(halves, k))), ",")
        return rows.select("flag", F.size("m").alias("states"), text.alias("halves"))

    r.add("map_state_counts", counted, f"SELECT flag, CAST(count(*) AS INTEGER) AS states, string_agg(state || ':' || (cnt // 2), ',' ORDER BY state) AS halves FROM (SELECT flag_1 AS flag, state_1 AS state, count(*) AS cnt FROM ({cubes.C3.sql()}) GROUP BY 1, 2) GROUP BY flag")

    def sketched(s, d):
        f, levels = C1.facts(s, d), [C1.dims[2].column(k) for k in (1, 2)]
        rows = related.sketched_distinct(f, levels, C1.dims[1].column(3))
        exact = related.hier_distinct(f, levels, C1.dims[1].column(3))
        close = F.abs(F.col("estimate") - F.col("n_distinct")) <= F.lit(0.05) * F.col("n_distinct")
        return rows.join(exact, ["depth", "label"]).select("depth", "label", "n_distinct", close.alias("close"))

    r.add("sketched_distinct", sketched, f"WITH f AS ({C1.sql()}) " + " UNION ALL ".join(f"SELECT {k} AS depth, time_{k} AS label, count(DISTINCT {C1.dims[1].column(3)}) AS n_distinct, true AS close FROM f GROUP BY time_{k}" for k in (1, 2)))

    def overlapping(s, d):
        """Pairs of product types and stretches of 100 parts that overlap: a join by inequalities alone."""
        m = tree_of(s, d, C1).members("product")
        types = m.filter("depth = 1").select(F.col("label"), "lo", "hi")
        steps = m.filter("depth = 3").select(F.expr("member_id div 100").alias("stretch")).distinct()
        return types.join(F.broadcast(steps), F.expr("lo <= stretch * 100 + 99 AND hi >= stretch * 100")).select("label", "stretch")

    span = members_sql(C1.dims[1], C1.sql())
    r.add("theta_overlaps", overlapping, f"WITH m AS (SELECT * FROM {span}), s AS (SELECT DISTINCT CAST(member_id // 100 AS BIGINT) AS stretch FROM m WHERE depth = 3) SELECT label, stretch FROM m JOIN s ON lo <= stretch * 100 + 99 AND hi >= stretch * 100 WHERE depth = 1")

    def used(s, d, how):
        t = tree_of(s, d, C1)
        brands = t.members("product").filter("depth = 2").select("depth", "label", "member_id")
        facts = t.nodes[2].join(t.leaf["time"].filter("time_2 = '1995-01'").select(F.col("id_2").alias("time_id_2")).distinct(), "time_id_2", "left_semi")
        return brands.join(facts.select(F.col("product_id_2").alias("member_id")), "member_id", how).select("depth", "label")

    for key, how, word in (("semi_members_used", "left_semi", ""), ("anti_empty_members", "left_anti", "NOT ")):
        r.add(key, lambda s, d, how=how: used(s, d, how), f"WITH f AS ({C1.sql()}) SELECT DISTINCT 2 AS depth, product_2 AS label FROM f WHERE product_2 {word}IN (SELECT product_2 FROM f WHERE time_2 = '1995-01')")

    def asof(s, d):
        e = s.read.parquet(f"{d}/events.parquet").select("event_id", "user_id", "ts", "event_type", F.date_trunc("week", "ts").alias("wk"))
        versions = e.groupBy("user_id", "wk").agg(F.min(F.struct("ts", "event_id", "event_type")).alias("v")).select("user_id", F.col("v.ts").alias("version_ts"), F.col("v.event_type").alias("label"), F.lit(1).alias("is_version"))
        rows = e.select("user_id", "ts", "event_id").withColumn("is_version", F.lit(2)).unionByName(versions.select("user_id", F.col("version_ts").alias("ts"), "is_version", "label"), allowMissingColumns=True)
        # Versions and events of a user in one order; each event takes the last version before it.
        last = Window.partitionBy("user_id").orderBy("ts", "is_version").rowsBetween(Window.unboundedPreceding, 0)
        seen = F.last(F.when(F.col("is_version") == 1, F.struct(F.col("ts").alias("version_ts"), "label")), ignorenulls=True).over(last)
        return rows.withColumn("v", seen).filter("is_version = 2").select("event_id", F.date_format("v.version_ts", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("version_ts"), "v.label")

    r.add("asof_member_version", asof,
          "WITH v AS (SELECT user_id, arg_min(struct_pack(t := ts, l := event_type), struct_pack(a := ts, b := event_id)) AS x FROM events GROUP BY user_id, date_trunc('week', ts)) "
          "SELECT event_id, strftime(x.t, '%Y-%m-%d %H:%M:%S.%f') AS version_ts, x.l AS label FROM (SELECT e.event_id, v.x, row_number() OVER (PARTITION BY e.event_id ORDER BY v.x.t DESC) AS k FROM events e JOIN v ON v.user_id = e.user_id AND v.x.t <= e.ts) WHERE k = 1")

    def setops(s, d):
        a = s.read.parquet(f"{d}/customer.parquet").select(F.col("c_nationkey").alias("k")).distinct()
        b = s.read.parquet(f"{d}/supplier.parquet").select(F.col("s_nationkey").alias("k")).distinct()
        names_ = s.read.parquet(f"{d}/nation.parquet").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("label"))
        kinds = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}
        return reduce(DataFrame.unionByName, [x.join(names_, "k").select(F.lit(n).alias("kind"), "label") for n, x in kinds.items()])

    r.add("setops_levels", setops,
          "WITH a AS (SELECT DISTINCT c_nationkey AS k FROM customer), b AS (SELECT DISTINCT s_nationkey AS k FROM supplier), "
          "u AS (SELECT 'union' AS kind, k FROM (SELECT k FROM a UNION SELECT k FROM b) UNION ALL SELECT 'intersect', k FROM (SELECT k FROM a INTERSECT SELECT k FROM b) UNION ALL SELECT 'except', k FROM (SELECT k FROM a EXCEPT SELECT k FROM b)) "
          "SELECT kind, n_name AS label FROM u JOIN nation ON n_nationkey = k")


def _leaf_pairs(s, d):
    """Every nation of depth 2 with every year's first brand: many are empty."""
    t = tree_of(s, d, C1)
    nations = t.leaf["geo"].select(F.col("geo_2").alias("geo")).distinct()
    brand = t.leaf["product"].agg(F.min("product_2").alias("product"))
    month = t.leaf["time"].agg(F.min("time_2").alias("time"))
    asked = nations.crossJoin(brand).crossJoin(month).select("*", F.xxhash64("geo").alias("qid"))  # one brand and month
    return planner.answer(t, asked).select("geo", "status", "qty")


def _leaf_pairs_sql() -> str:
    return (
        f"WITH f AS ({C1.sql()}), b AS (SELECT min(product_2) AS p FROM f), m AS (SELECT min(time_2) AS t FROM f), a AS (SELECT DISTINCT geo_2 FROM f) "
        "SELECT a.geo_2 AS geo, 'ok' AS status, CAST(coalesce(sum(qty), 0) AS BIGINT) AS qty FROM a CROSS JOIN b CROSS JOIN m LEFT JOIN f ON f.geo_2 = a.geo_2 AND f.product_2 = b.p AND f.time_2 = m.t GROUP BY 1"
    )

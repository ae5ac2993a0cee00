"""The synthetic grids: both trees, boxes, space and visit counters; related problems; streams."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import dac_bits_sql
from ..operators import hast, measures, packed, packed_rst, related, rst
from ..plans import planner
from ..streaming import upkeep
from ..workloads import cubes, grids, querysets
from .common import Registry, grid_tree, level_sql, members_sql, slots_sql, tree_of

BOXES = 60
LABELS = 50


def _blocks_sql(cells: str, n: int, k: int, h: int) -> str:
    keys = lambda d: ", ".join(f"CAST(floor(k{i} / {k ** (h - d)}) AS BIGINT) AS b{i}" for i in range(1, n + 1))
    by = ", ".join(f"b{i}" for i in range(1, n + 1))
    return " UNION ALL ".join(f"SELECT {d} AS depth, {by}, CAST(sum(v) AS BIGINT) AS total FROM (SELECT {keys(d)}, v FROM ({cells})) GROUP BY {by}" for d in range(h + 1))


def _boxes_truth(cells: str, boxes: str, n: int) -> str:
    inside = " AND ".join(f"k{i} BETWEEN lo_{i} AND hi_{i}" for i in range(1, n + 1))
    return f"SELECT qid, CAST(coalesce(sum(v), 0) AS BIGINT) AS total FROM ({boxes}) b LEFT JOIN ({cells}) c ON {inside} GROUP BY qid"


def _visits_sql(boxes: str, n: int, k: int, h: int) -> str:
    """Counts blocks one by one: those in the box, and those met, whose parent is not in the box."""
    per = []
    for d in range(h + 1):
        side = k ** (h - d)
        froms = ", ".join(f"(SELECT range AS b{i} FROM range({k ** d})) r{i}" for i in range(1, n + 1))
        mine = " AND ".join(f"lo_{i} <= b{i} * {side} AND b{i} * {side} + {side - 1} <= hi_{i}" for i in range(1, n + 1))
        touch = " AND ".join(f"b{i} * {side} <= hi_{i} AND b{i} * {side} + {side - 1} >= lo_{i}" for i in range(1, n + 1))
        s2 = side * k
        parent = " AND ".join(f"lo_{i} <= (b{i} // {k}) * {s2} AND (b{i} // {k}) * {s2} + {s2 - 1} <= hi_{i}" for i in range(1, n + 1)) if d else "false"
        per.append(f"SELECT qid, count(*) FILTER ({mine}) AS a, count(*) AS v FROM ({boxes}) q, {froms} WHERE {touch} AND NOT ({parent}) GROUP BY qid")
    return f"SELECT qid, CAST(sum(a) AS BIGINT) AS n_summed, CAST(sum(v) AS BIGINT) AS n_visited FROM ({' UNION ALL '.join(per)}) GROUP BY qid"


def _met_sql(cells: str, boxes: str, n: int, k: int, h: int) -> str:
    """The same counts where blocks may be empty: an empty block is met below a full one, but not opened or summed."""
    b = [f"b{i}" for i in range(1, n + 1)]
    full = lambda d: "SELECT DISTINCT " + ", ".join(f"k{i} // {k ** (h - d)} AS b{i}" for i in range(1, n + 1)) + f" FROM ({cells})"
    inside = lambda x, side: " AND ".join(rst.contained(f"{x}{i}", i, side) for i in range(1, n + 1))
    per = [f"SELECT qid, CASE WHEN {inside('b', k ** h)} THEN 1 ELSE 0 END AS a, 1 AS v FROM ({boxes}) q, ({full(0)}) p"]
    for d in range(1, h + 1):
        side = k ** (h - d)
        child = ", ".join(f"b{i} * {k} + o{i} AS c{i}" for i in range(1, n + 1)) + ", " + ", ".join(f"lo_{i}, hi_{i}" for i in range(1, n + 1))
        steps = ", ".join(f"(SELECT range AS o{i} FROM range({k})) r{i}" for i in range(1, n + 1))
        met = f"SELECT qid, {child} FROM ({boxes}) q, ({full(d - 1)}) p, {steps} WHERE NOT ({inside('b', side * k)})"
        apart = " OR ".join(rst.disjoint(f"c{i}", i, side) for i in range(1, n + 1))
        on = " AND ".join(f"f.{x} = m.c{i}" for i, x in enumerate(b, 1))
        per.append(f"SELECT qid, count(*) FILTER (f.b1 IS NOT NULL AND {inside('c', side)}) AS a, count(*) AS v FROM ({met}) m LEFT JOIN ({full(d)}) f ON {on} WHERE NOT ({apart}) GROUP BY qid")
    return f"SELECT qid, CAST(coalesce(sum(a), 0) AS BIGINT) AS n_summed, CAST(coalesce(sum(v), 0) AS BIGINT) AS n_visited FROM ({boxes}) LEFT JOIN ({' UNION ALL '.join(per)}) USING (qid) GROUP BY qid"


def _hast_visits_sql(cube, facts: str, n: int, kind: str, fixed=None) -> str:
    """Products of descendant counts, from each dimension's distinct paths."""
    h = cube.height
    d_terms = []
    ctes = querysets.query_set_sql(cube, facts, n, kind, fixed)
    for i, x in enumerate(cube.dims):
        ctes += f", t{i} AS (SELECT DISTINCT {', '.join(x.column(j) for j in range(1, h + 1))} FROM facts)"

    def count(i, k):
        x = cube.dims[i]
        cases = " ".join(f"WHEN {l} THEN (SELECT count(DISTINCT {x.column(k)}) FROM t{i}" + (f" WHERE {x.column(l)} = q.{x.name}" if l else "") + ")" for l in range(k))
        return f"(CASE g{i} {cases} ELSE 1 END)" if k else "1"

    deepest = f"greatest({', '.join(f'g{i}' for i in range(len(cube.dims)))})"
    for k in range(h + 1):
        d_terms.append(" * ".join(count(i, k) for i in range(len(cube.dims))))
    visited = " + ".join(f"CASE WHEN {deepest} >= {k} THEN {e} ELSE 0 END" for k, e in enumerate(d_terms))
    summed = " ".join(f"WHEN {k} THEN {e}" for k, e in enumerate(d_terms))
    return f"WITH {ctes} SELECT qid, CAST(CASE {deepest} {summed} END AS BIGINT) AS n_summed, CAST({visited} AS BIGINT) AS n_visited FROM queries q"


def register(r: Registry) -> None:
    g8, b8 = grids.Grid(4, 8), grids.Grid(4, 8, "binary")
    b = [f"b{i}" for i in range(1, 5)]

    def depths(s, cells, k, h, n=4):
        tree = rst.build_rst(cells, n, k, h)
        return reduce(DataFrame.unionByName, [tree[d].select(F.lit(d).alias("depth"), *[f"b{i}" for i in range(1, n + 1)], F.col("total").cast("long").alias("total")) for d in range(h + 1)])

    line = lambda s, d: grids.from_lineitem(s, d)
    line_sql = grids.lineitem_sql("lineitem", 16)
    r.add("rst_depth_sums", lambda s, d: depths(s, line(s, d), 2, 4), _blocks_sql(line_sql, 4, 2, 4))
    r.add("rst_k3_depth_sums", lambda s, d: depths(s, line(s, d), 3, 3), _blocks_sql(line_sql, 4, 3, 3))
    r.add("rst_k4_depth_sums", lambda s, d: depths(s, line(s, d), 4, 2), _blocks_sql(line_sql, 4, 4, 2))
    r.add("rst_two_dimensions", lambda s, d: depths(s, line(s, d), 2, 4, 2), _blocks_sql(line_sql, 2, 2, 4))
    r.add("grid_lineitem_mod16", lambda s, d: rst.range_sum(rst.build_rst(line(s, d), 4, 2, 4), querysets.boxes(s, BOXES, 4, 16), 4, 2).select("qid", "total"), _boxes_truth(line_sql, querysets.boxes_sql(BOXES, 4, 16), 4))

    def node_counts(s, d):
        tree = rst.build_rst(line(s, d), 4, 2, 4)
        return reduce(DataFrame.unionByName, [tree[k].agg(F.count("*").alias("nonempty")).crossJoin(tree[k - 1].agg((F.count("*") * 16).alias("slots"))).select(F.lit(k).alias("depth"), "nonempty", "slots") for k in range(1, 5)])

    blocks = _blocks_sql(line_sql, 4, 2, 4)
    r.add("rst_node_counts", node_counts, f"WITH n AS (SELECT depth, count(*) AS c FROM ({blocks}) GROUP BY depth) SELECT a.depth, a.c AS nonempty, p.c * 16 AS slots FROM n a JOIN n p ON p.depth = a.depth - 1")

    def same(s, d):
        tree = rst.build_rst(b8.cells(s), 4, 2, 3)
        t = grid_tree(s, b8)
        parts = []
        for k in (1, 2, 3):
            mine = t.nodes[k].select(*[F.col(f"x{i}_id_{k}").alias(f"b{i}") for i in range(1, 5)], F.col("v").alias("mine"))
            met = tree[k].join(mine, b, "full")
            parts.append(met.agg(F.count_if(F.col("mine") == F.col("total")).alias("n_equal"), F.count_if(~F.expr("mine <=> total")).alias("n_diff")).select(F.lit(k).alias("depth"), "n_equal", "n_diff"))
        return reduce(DataFrame.unionByName, parts)

    r.add("binary_same_sums", same, f"SELECT depth, count(*) AS n_equal, CAST(0 AS BIGINT) AS n_diff FROM ({_blocks_sql(b8.duck(), 4, 2, 3)}) WHERE depth > 0 GROUP BY depth")
    tree8 = lambda s: rst.build_rst(g8.cells(s), 4, 2, 3)
    box8 = lambda s: querysets.boxes(s, BOXES, 4, 8)
    # Line items as cells of the same grid, and with the same half of the cells emptied.
    cells8_sql, half8_sql = (grids.lineitem_cells_sql("lineitem", 8, e) for e in (0, 50))
    cells8 = lambda s, d, e=0: s.sql(grids.lineitem_cells_sql("{lineitem}", 8, e), lineitem=s.read.parquet(f"{d}/lineitem.parquet"))
    sums8 = lambda s, d: rst.build_rst(cells8(s, d), 4, 2, 3)
    truth8 = _boxes_truth(cells8_sql, querysets.boxes_sql(BOXES, 4, 8), 4)
    r.add("box_sum_set", lambda s, d: rst.range_sum_set(sums8(s, d), box8(s), 4, 2), truth8)
    r.add("linear_box_scan", lambda s, d: rst.linear_scan(cells8(s, d), box8(s), 4, 4).na.fill(0), truth8)
    r.add("compact_box_sums", lambda s, d: packed_rst.walk(packed_rst.pack(sums8(s, d), 4, 2), box8(s), 4, 2, 3).select("qid", "total"), truth8)
    met8 = _met_sql(cells8_sql, querysets.boxes_sql(BOXES, 4, 8), 4, 2, 3)
    r.add("box_sum_frontier", lambda s, d: rst.range_sum(sums8(s, d), box8(s), 4, 2), f"SELECT qid, total, n_summed, n_visited FROM ({truth8}) JOIN ({met8}) USING (qid)")
    # One box for each ship date, drawn from that day's line items.
    days = lambda s, d: s.sql(querysets.day_boxes_sql("{lineitem}", 8), lineitem=s.read.parquet(f"{d}/lineitem.parquet"))
    days_sql = querysets.day_boxes_sql("lineitem", 8)

    def visits_rst(s, d):
        summed, visited = rst.closed_form(4, 2, 3)
        return days(s, d).select("qid", summed.cast("long").alias("n_summed"), visited.cast("long").alias("n_visited"))

    visits_days = _visits_sql(days_sql, 4, 2, 3)
    r.add("visits_rst", visits_rst, visits_days)
    point = "SELECT qid, " + ", ".join(f"lo_{i} AS k{i}" for i in range(1, 5)) + f" FROM ({querysets.boxes_sql(BOXES, 4, 8)})"
    r.add("rst_cell_points", lambda s, d: rst.cell(rst.build_rst(cells8(s, d, 50), 4, 2, 3), box8(s).select("qid", *[F.col(f"lo_{i}").alias(f"k{i}") for i in range(1, 5)]), 4),
          f"SELECT qid, CAST(coalesce(sum(v), 0) AS BIGINT) AS total FROM ({point}) p LEFT JOIN ({half8_sql}) c USING (k1, k2, k3, k4) GROUP BY qid")

    # Label queries on grids: both organisations, sparsities and shapes.
    def labels(s, grid, kind, fixed=None):
        t = grid_tree(s, grid)
        return planner.answer(t, querysets.query_set(t, LABELS, kind, fixed)).select("qid", *[x.name for x in t.cube.dims], "v", "cnt", "n_summed")

    for key, grid, kind, fixed in (
        ("grid_4d8_irregular", g8, "mixed", None), ("grid_4d8_binary", b8, "mixed", None), ("grid_4d8_penultimate", g8, "one", 2), ("grid_4d8_cells", g8, "one", 3),
        ("grid_4d16_irregular_q2", grids.Grid(4, 16), "mixed", None), ("grid_5d8_sparse25", grids.Grid(5, 8, "irregular", 25), "mixed", None),
        ("grid_5d8_sparse50", grids.Grid(5, 8, "irregular", 50), "one", 2), ("grid_4d8_clustered", grids.Grid(4, 8, "irregular", 0, True), "mixed", None),
    ):
        c = grid.cube()
        r.add(key, lambda s, d, grid=grid, kind=kind, fixed=fixed: labels(s, grid, kind, fixed), querysets.truth_sql(c, grid.fact_sql(), LABELS, kind, fixed))
    cube8, facts8 = g8.cube(), g8.fact_sql()
    truth = querysets.truth_sql(cube8, facts8, LABELS, "mixed")

    def via_ranges(s, d):
        t = grid_tree(s, g8)
        bx = querysets.label_boxes(t, querysets.query_set(t, LABELS, "mixed"))
        return rst.range_sum(tree8(s), bx, 4, 2).select("qid", "total")

    r.add("label_via_ranges", via_ranges, f"SELECT qid, v AS total FROM ({truth})")

    def compact(s, kind, fixed=None, cut=None):
        t = grid_tree(s, g8)
        asked = planner.resolved(t, querysets.query_set(t, LABELS, kind, fixed))
        cut = packed.choose_cut(t) if cut is None else cut
        got = packed.descend(t, packed.pack(t, "v", cut), asked, cut)
        return asked.select("qid").join(got, "qid", "left").select("qid", *[F.coalesce(c, F.lit(0)).cast("long").alias(a) for c, a in (("total", "v"), ("n_summed", "n_summed"), ("n_visited", "n_visited"))])

    r.add("compact_walk_points", lambda s, d: compact(s, "one", 3).select("qid", "v"), f"SELECT qid, v FROM ({querysets.truth_sql(cube8, facts8, LABELS, 'one', 3)})")
    r.add("compact_walk_mixed", lambda s, d: compact(s, "mixed").select("qid", "v"), f"SELECT qid, v FROM ({truth})")
    r.add("compact_walk_shards", lambda s, d: compact(s, "mixed", cut=1).select("qid", "v"), f"SELECT qid, v FROM ({truth})")
    hast_sql = _hast_visits_sql(cube8, facts8, LABELS, "mixed")
    ask8 = lambda s: querysets.query_set(grid_tree(s, g8), LABELS, "mixed")
    def spread(s, d):
        return planner.visits(grid_tree(s, g8), ask8(s)).agg(*[F.percentile("n_visited", F.lit(p)).alias(f"p{int(100 * p)}") for p in (0.5, 0.9, 0.99)])

    r.add("visits_percentiles", spread, f"SELECT {', '.join(f'CAST(quantile_cont(n_visited, {p}) AS DOUBLE) AS p{int(100 * p)}' for p in (0.5, 0.9, 0.99))} FROM ({hast_sql})")
    r.add("visits_hast", lambda s, d: planner.visits(grid_tree(s, g8), ask8(s)).select("qid", "n_summed", "n_visited"), hast_sql)
    r.add("visits_hast_closed", lambda s, d: measures.hast_closed_form(grid_tree(s, g8), planner.resolve(grid_tree(s, g8), ask8(s))), hast_sql)

    def ratio(s, d):
        t = grid_tree(s, g8)
        asked = ask8(s)
        mine = planner.visits(t, asked)
        su, vi = rst.closed_form(4, 2, 3)
        other = querysets.label_boxes(t, asked).select("qid", su.cast("long").alias("rs"), vi.cast("long").alias("rv"))
        return mine.join(other, "qid").agg(*[F.sum(c).cast("long").alias(n) for c, n in (("n_summed", "hast_summed"), ("n_visited", "hast_visited"), ("rs", "rst_summed"), ("rv", "rst_visited"))])

    lohi = ", ".join(f"m{i}.lo AS lo_{i}, m{i}.hi AS hi_{i}" for i in range(1, 5))
    on = " ".join(f"JOIN {members_sql(x, facts8)} m{i} ON m{i}.label = q.{x.name}" for i, x in enumerate(cube8.dims, 1))
    qboxes = f"WITH {querysets.query_set_sql(cube8, facts8, LABELS, 'mixed')} SELECT q.qid, {lohi} FROM queries q {on}"
    r.add("visits_ratio", ratio, f"SELECT CAST(sum(a.n_summed) AS BIGINT) AS hast_summed, CAST(sum(a.n_visited) AS BIGINT) AS hast_visited, CAST(sum(b.n_summed) AS BIGINT) AS rst_summed, CAST(sum(b.n_visited) AS BIGINT) AS rst_visited FROM ({hast_sql}) a JOIN ({_visits_sql(qboxes, 4, 2, 3)}) b USING (qid)")

    # Space.
    width = 4
    nodes = " UNION ALL ".join(f"SELECT {k} AS depth, CAST(sum(v) AS BIGINT) AS total FROM facts GROUP BY {', '.join(x.column(j) for x in cube8.dims for j in range(1, k + 1)) or '()'}" for k in range(4))
    slots = " UNION ALL ".join(slots_sql(cube8, k, "facts").replace("FROM f)", "FROM facts)").replace("FROM f GROUP", "FROM facts GROUP") for k in (1, 2, 3))
    dims = " ".join(
        f"UNION ALL SELECT 'louds_{x.name}', 2 * (count(*) + 1) - 1 FROM {members_sql(x, 'SELECT * FROM facts')} "
        f"UNION ALL SELECT 'vocabulary_{x.name}', CAST(sum(length(label)) * 8 + count(*) * 32 AS BIGINT) FROM {members_sql(x, 'SELECT * FROM facts')}"
        for x in cube8.dims
    )
    r.add("space_parts", lambda s, d: measures.hast_space(grid_tree(s, g8), "v", width),
          f"WITH facts AS ({facts8}), s AS ({slots}), n AS ({nodes}), p AS (SELECT 'occupancy' AS part, CAST(sum(slots) FILTER (depth < 3) AS BIGINT) AS bits FROM s UNION ALL SELECT 'limits', CAST(sum(slots) AS BIGINT) FROM s "
          f"UNION ALL SELECT 'values', CAST((SELECT sum({dac_bits_sql('total', width)}) FROM n) + (SELECT sum(slots - nonempty) FROM s) * {width + 1} AS BIGINT) {dims}) SELECT 'hast' AS structure, part, bits FROM p")
    bl = _blocks_sql(g8.duck(), 4, 2, 3)
    vocab = " ".join(f"UNION ALL SELECT 'vocabulary_{x.name}', CAST(sum(length(label)) * 8 + count(*) * 64 AS BIGINT) FROM {members_sql(x, facts8)}" for x in cube8.dims)
    r.add("space_parts_rst", lambda s, d: measures.rst_space(tree8(s), 4, 2, grid_tree(s, g8), width),
          f"WITH n AS ({bl}), s AS (SELECT depth + 1 AS depth, count(*) * 16 AS slots FROM n WHERE depth < 3 GROUP BY depth), p AS (SELECT 'occupancy' AS part, CAST(sum(slots) FILTER (depth < 3) AS BIGINT) AS bits FROM s "
          f"UNION ALL SELECT 'values', CAST((SELECT sum({dac_bits_sql('total', width)}) FROM n) + ((SELECT sum(slots) FROM s) + 1 - (SELECT count(*) FROM n)) * {width + 1} AS BIGINT) {vocab}) SELECT 'rst' AS structure, part, bits FROM p")
    r.add("dac_bits_by_width", lambda s, d: reduce(DataFrame.unionByName, [measures.value_bits(tree_of(s, d, cubes.C1).nodes[2], "qty", w) for w in range(1, 17)]),
          " UNION ALL ".join(f"SELECT {w} AS width, count(*) AS entries, CAST(sum({dac_bits_sql('qty', w)}) AS BIGINT) AS bits FROM n" for w in range(1, 17)).join([f"WITH n AS (SELECT qty FROM ({level_sql(cubes.C1, 2)})) ", ""]))

    def sparsity(s, d):
        parts = []
        for e in (0, 25, 50):
            t = grid_tree(s, grids.Grid(4, 8, "irregular", e))
            bits = hast.slots(t, 3).agg(F.count_if(F.col("cnt") > 0).alias("cells"), F.count("*").alias("slots"), F.sum(F.expr(dac_bits_sql("v", 2))).cast("long").alias("dac_bits"))
            parts.append(bits.select(F.lit(e).alias("mask"), "cells", "slots", "dac_bits"))
        return reduce(DataFrame.unionByName, parts)

    r.add("sparsity_effect", sparsity, " UNION ALL ".join(f"(WITH f AS ({grids.Grid(4, 8, 'irregular', e).fact_sql()}), z AS ({slots_sql(cube8, 3, 'f')}) SELECT {e} AS mask, nonempty AS cells, slots, CAST((SELECT sum({dac_bits_sql('v', 2)}) FROM f) + (slots - nonempty) * 3 AS BIGINT) AS dac_bits FROM z)" for e in (0, 25, 50)))
    # The published test on blocks visited: trees split by 2 and by 8, 20 sets of the ship dates' boxes.
    stats = "round(a - b, 6) AS diff, round((a - b) / nullif(sqrt(c * c + e * e), 0), 6) AS stat_plain, round((a - b) / nullif(sqrt((c * c + e * e) / n), 0), 6) AS stat_n"
    over = "avg(x) AS a, avg(y) AS b, stddev_samp(x) AS c, stddev_samp(y) AS e, count(*) AS n"
    means = "CAST(sum(x) AS DOUBLE) / count(*) AS x, CAST(sum(y) AS DOUBLE) / count(*) AS y"

    def significance(s, d):
        two, eight = (rst.closed_form(4, k, h)[1].cast("long") for k, h in ((2, 3), (8, 1)))
        return s.sql(f"SELECT 'lineitem' AS dataset, {stats} FROM (SELECT {over} FROM (SELECT {means} FROM {{visits}} GROUP BY qid % 20))", visits=days(s, d).select("qid", two.alias("x"), eight.alias("y")))

    r.add("significance_table", significance,
          f"SELECT 'lineitem' AS dataset, {stats} FROM (SELECT {over} FROM (SELECT {means} FROM (SELECT qid, p.n_visited AS x, q.n_visited AS y FROM ({visits_days}) p JOIN ({_visits_sql(days_sql, 4, 8, 1)}) q USING (qid)) GROUP BY qid % 20))")

    # Distinct counts and modes.
    seq = lambda s, d: s.read.parquet(f"{d}/events.parquet").select(F.col("event_id").alias("pos"), F.col("user_id").alias("value"))
    # Ranges are drawn from the whole table, however long it is.
    upto = "coalesce(max(event_id), 0) + 1"
    whole = lambda s, d: querysets.boxes(s, BOXES, 1, s.read.parquet(f"{d}/events.parquet").agg(F.expr(upto)).first()[0]).select(F.col("qid").alias("rid"), F.col("lo_1").alias("lo"), F.col("hi_1").alias("hi"))
    whole_sql = f"SELECT qid AS rid, lo_1 AS lo, hi_1 AS hi FROM ({querysets.boxes_sql(BOXES, 1, f'(SELECT {upto} FROM events)')})"
    r.add("range_distinct", lambda s, d: related.range_distinct(seq(s, d), whole(s, d)), f"SELECT rid, lo, hi, count(DISTINCT user_id) AS n_distinct FROM ({whole_sql}) r LEFT JOIN events e ON event_id BETWEEN lo AND hi GROUP BY 1, 2, 3")
    r.add("range_mode", lambda s, d: related.range_mode(seq(s, d), whole(s, d)), f"SELECT rid, lo, hi, user_id AS mode_value, n AS mode_count FROM (SELECT *, row_number() OVER (PARTITION BY rid ORDER BY n DESC, user_id) AS k FROM (SELECT rid, lo, hi, user_id, count(*) AS n FROM ({whole_sql}) r JOIN events e ON event_id BETWEEN lo AND hi GROUP BY ALL)) WHERE k = 1")
    timed = cubes.Cube("c4u", cubes.C4.source, (cubes.C4.dims[2],), (("user_id", "user_id"), ("event_type", "event_type")), ("events",))
    levels = [timed.dims[0].column(k) for k in (1, 2, 3)]
    r.add("hier_distinct", lambda s, d: related.hier_distinct(timed.facts(s, d), levels, "user_id"), f"WITH f AS ({timed.sql()}) " + " UNION ALL ".join(f"SELECT {k} AS depth, {c} AS label, count(DISTINCT user_id) AS n_distinct FROM f GROUP BY {c}" for k, c in enumerate(levels, 1)))
    r.add("hier_mode", lambda s, d: related.hier_mode(timed.facts(s, d), levels, "event_type"), f"WITH f AS ({timed.sql()}) " + " UNION ALL ".join(
        f"SELECT {k} AS depth, label, event_type AS mode_value, n AS mode_count FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY n DESC, event_type) AS z FROM (SELECT {c} AS label, event_type, count(*) AS n FROM f GROUP BY 1, 2)) WHERE z = 1" for k, c in enumerate(levels, 1)))
    hourly_sql = "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour, event_type, count(*) AS cnt, CAST(sum(CAST(ROUND(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2"
    hour = "CAST(CAST(hour AS TIMESTAMP_NTZ) AS STRING) AS hour"
    r.add("stream_events_hourly", lambda s, d: upkeep.hourly(s.read.parquet(f"{d}/events.parquet")).selectExpr(hour, "event_type", "cnt", "cents"), hourly_sql)

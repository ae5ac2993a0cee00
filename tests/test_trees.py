import itertools
import re

import numpy as np
import pytest

from hcube.operators import hast, hierarchy, measures, packed, packed_rst, rst
from hcube.plans import planner
from hcube.spec import Cube, Dimension
from hcube.workloads import cubes, grids, querysets

# An 8 x 8 matrix with known sums.
MATRIX = """
1 0 2 0 0 0 0 0
0 1 0 0 0 0 0 0
2 4 5 4 0 0 0 0
0 0 0 2 0 0 0 0
0 0 0 2 1 0 0 4
0 0 1 5 0 2 0 0
0 3 0 0 0 0 3 0
1 0 0 2 0 5 0 1
"""


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def small(spark):
    cells = [(r, c, int(v)) for r, line in enumerate(MATRIX.split("\n")[1:-1]) for c, v in enumerate(line.split()) if v != "0"]
    return spark.createDataFrame(cells, "k1 long, k2 long, v long")


def test_known_matrix(spark, small):
    tree = rst.build_rst(small, 2, 2, 3)
    assert tree[0].first().total == 51
    assert {(r.b1, r.b2): r.total for r in tree[1].collect()} == {(0, 0): 21, (1, 0): 14, (1, 1): 16}
    box = spark.createDataFrame([(1, 2, 5, 1, 3)], "qid long, lo_1 long, hi_1 long, lo_2 long, hi_2 long")
    got = rst.range_sum(tree, box, 2, 2).first()
    assert (got.total, got.n_visited) == (23, 9)
    assert rst.range_sum_set(tree, box, 2, 2).first().total == 23
    point = spark.createDataFrame([(1, 2, 1), (2, 3, 1)], "qid long, k1 long, k2 long")
    assert rows(rst.cell(tree, point, 2)) == [(1, 4), (2, 0)]
    full = rst.build_rst(spark.range(64).selectExpr("id div 8 AS k1", "id % 8 AS k2", "1L AS v"), 2, 2, 3)
    got = rst.range_sum(full, box, 2, 2).first()
    assert (got.n_summed, got.n_visited) == (6, 11)


def test_uneven_sides_and_three_way(spark):
    cells = spark.range(35).selectExpr("id div 7 AS k1", "id % 7 AS k2", "id + 1 AS v")
    for k in (2, 3):
        h = rst.height_for(7, k)
        tree = rst.build_rst(cells, 2, k, h)
        assert all(tree[d].agg({"total": "sum"}).first()[0] == 35 * 36 // 2 for d in range(h + 1))


def test_tree_invariants_and_modes(spark):
    t = grids.Grid(3, 8, "irregular", 25).tree(spark)
    h = t.cube.height
    total = t.nodes[0].first().v
    for k in range(1, h + 1):
        assert t.nodes[k].agg({"v": "sum"}).first()[0] == total
    for x in t.cube.dims:
        assert hierarchy.check_hierarchy(t.members(x.name)).isEmpty()
    q = querysets.query_set(t, 15, "mixed")
    a = planner.answer(t, q)
    assert rows(a.select("qid", "v")) == rows(planner.answer_exploded(t, q).select("qid", "v"))
    visits = planner.visits(t, q)
    assert rows(visits.select("qid", "n_summed")) == rows(a.select("qid", "n_summed"))
    # Descents on the bits give the same sums wherever shards are cut, and the same nodes from the root.
    asked = planner.resolve(t, q)
    found = packed.descend(t, packed.pack(t, "v", 0), asked, 0)
    assert rows(found.select("qid", "total")) == rows(a.select("qid", "v"))
    assert rows(found.select("qid", "n_visited", "n_summed")) == rows(visits.select("qid", "n_visited", "n_summed"))
    for cut in (1, 2, h):
        assert packed.shard_sizes(t, cut).agg({"cells": "sum"}).first()[0] == t.nodes[h].count()
        assert rows(packed.descend(t, packed.pack(t, "v", cut), asked, cut, 7).select("qid", "total")) == rows(a.select("qid", "v"))
    assert [packed.choose_cut(t, most) for most in (10**6, 200, 1)] == [0, 1, h]
    seq = packed.sequences_of(t, "v")
    assert len(seq.tc) == sum(hast.slot_count(t, k).first().slots for k in range(1, h + 1))
    slots = [f"p_{k}" for k in range(1, h + 1)]
    for r in t.nodes[h].select(*slots, "v").limit(40).collect():
        assert seq.walk(list(r[:h]))[0] == r.v


@pytest.mark.parametrize("k", [2, 3])
def test_compact_regular_tree(spark, k):
    """Box sums on bits equal the relational frontier, counters included; cells by rank."""
    grid = grids.Grid(3, 8, "irregular", 50, True)
    h = rst.height_for(8, k)
    tree = {d: x.cache() for d, x in rst.build_rst(grid.cells(spark), 3, k, h).items()}
    boxes = querysets.boxes(spark, 40, 3, 8).cache()
    want = {r.qid: (r.total, r.n_summed, r.n_visited) for r in rst.range_sum(tree, boxes, 3, k).collect()}
    seq = packed_rst.sequences(tree, 3, k)
    asked = boxes.collect()
    bounds = lambda e: np.array([[r[f"{e}_{i}"] for i in (1, 2, 3)] for r in asked])
    got = list(zip(*(x.tolist() for x in seq.box_sums(bounds("lo"), bounds("hi")))))
    # On bits an empty block in the box is read as a zero; the relational form has no row for it.
    assert [(g[0], g[2]) for g in got] == [(want[r.qid][0], want[r.qid][2]) for r in asked]
    assert all(g[1] >= want[r.qid][1] for g, r in zip(got, asked))
    for cut in (1, h):
        found = packed_rst.walk(packed_rst.pack(tree, 3, k, cut), boxes, 3, k, h, cut)
        assert {r.qid: r.total for r in found.collect()} == {q: x[0] for q, x in want.items()}
    some = {(r.k1, r.k2, r.k3): r.v for r in grid.cells(spark).collect()}
    for point in itertools.product((0, 3, 5, 7), repeat=3):
        assert seq.cell(list(point)) == some.get(point, 0)


def test_hierarchies_need_fewer_nodes(spark):
    g = grids.Grid(3, 16)
    t = g.tree(spark)
    q = querysets.free_draws(t, 40, "one", 2)
    mine = planner.visits(t, q).agg({"n_summed": "sum"}).first()[0]
    su, _ = rst.closed_form(3, 2, 4)
    other = querysets.label_boxes(t, q).select(su.alias("n")).agg({"n": "sum"}).first()[0]
    assert mine == 40 and other > 4 * mine


def test_space_falls_with_emptiness(spark):
    bits = []
    for empty in (0, 25, 50):
        t = grids.Grid(3, 8, "irregular", empty).tree(spark)
        bits.append({r.part: r.bits for r in measures.hast_space(t, "v", 2).collect()}["values"])
    assert bits[0] > bits[1] > bits[2]


def test_edges(spark):
    def tree(values, levels=("a", "b")):
        frame = spark.createDataFrame(values, "a string, b string, v long")
        cube = Cube("e", "{t}", (Dimension("x", tuple((n, n) for n in levels)),), (("v", "v"),))
        return hast.Tree(spark, cube, spark.sql(cube.select(), t=frame))

    t = tree([("p", "q", 5), ("p", "r", -5), (None, None, 2**40), ("s", "q", 0)])
    by = {r.x: (r.v, r.cnt) for r in t.labelled(1).collect()}
    assert by == {"p": (0, 2), "__null__": (2**40, 1), "s": (0, 1)}  # sums of zero are kept
    ask = spark.createDataFrame([(1, "p"), (2, "q"), (3, "none"), (4, "*")], "qid long, x string")
    got = {r.qid: (r.status, r.v) for r in planner.answer(t, ask).collect()}
    assert got == {1: ("ok", 0), 2: ("ambiguous_label", None), 3: ("unknown_label", None), 4: ("ok", 2**40)}
    assert tree([("p", "q", 5)], ("a",)).nodes[0].first().v == 5
    empty = tree([("p", "q", 5)])
    empty.facts = empty.facts.filter("false")
    assert empty.nodes[0].first().v == 0
    with pytest.raises(ValueError):
        Cube("h", "t", (Dimension("x", (("a", "a"),)), Dimension("y", (("a", "a"), ("b", "b")))), ())


def test_busy_tasks_follow_the_nodes(spark, sf):
    """Each depth is dealt by its own keys after a partial aggregate, so not by its few topmost members."""
    t = hast.tree(spark, cubes.C3, sf)
    again = hast.build_hast(t.nodes[2], cubes.C3)
    plan = again[1]._jdf.queryExecution().executedPlan().toString()
    dealt = re.findall(r"Exchange hashpartitioning\((.*?), \d+\)", plan)
    assert len(dealt) == 1 and "partial_sum" in plan and "REPARTITION" not in plan
    grid = grids.Grid(3, 8)
    plan = rst.build_rst(grid.cells(spark), 3, 2, 3)[2]._jdf.queryExecution().executedPlan().toString()
    assert "REPARTITION" not in plan and plan.count("Exchange hashpartitioning") == 2
    node = t.nodes[2].filter("flag_id_2 = 1").select("qty")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(flag_id_2), EqualTo(flag_id_2,1)]" in node and "Python" not in plan


def test_level_plan_advice():
    plan = hierarchy.advise_plan({"d1": [3, 9, 90], "d2": [2, 8, 24, 700]}, [{"d1": 2, "d2": 2}, {"d1": 2, "d2": 3}], 4)
    assert plan == {"d1": (1, 2, 2, 3), "d2": (1, 2, 3, 4)}


def test_recursive_closure(spark, sf):
    t = hast.tree(spark, cubes.C1, sf)
    m = t.members("geo")
    want = rows(hierarchy.closure(t.leaf["geo"], cubes.C1.dims[0]).select("depth", "member_id", "anc_depth", "anc_id"))
    assert rows(hierarchy.closure_recursive(spark, m)) == want

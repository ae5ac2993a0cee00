"""The cube object, Arrow functions and table functions, against the operators under them."""

import numpy as np
from pyspark.sql import functions as F

from hcube.api import HCube
from hcube.functions.arrow import dac_get, louds_child, pack_bits, pack_values
from hcube.functions.bits import BitVec, Dac
from hcube.functions.louds import LevelOrder, Louds
from hcube.plans import planner
from hcube.sources import udtf
from hcube.workloads import grids, querysets


def test_cube_object(spark):
    t = grids.Grid(2, 8, "irregular", 25).tree(spark)
    cube, q = HCube(t), querysets.query_set(t, 10, "mixed")
    want = {r.qid: (r.v, r.n_summed) for r in planner.answer(t, q).collect()}
    assert {r.qid: (r.v, r.n_summed) for r in cube.answer(q).collect()} == want
    why = {r.qid: r for r in cube.explain_query(q).collect()}
    assert all(why[k].n_summed == n and why[k].status == "ok" for k, (_, n) in want.items())
    boxes = querysets.label_boxes(t, q)
    assert {r.qid: r.total for r in cube.box(boxes, "v").collect()} == {k: v for k, (v, _) in want.items()}
    shards, cut = cube.pack("v")
    assert cut == 0 and shards.count() == 1 and cube.violations("x1").isEmpty()


def test_arrow_functions(spark):
    values = np.array([5, 0, 900, 7], np.uint64)
    bits = "".join("1" * d + "0" for d in (2, 1, 0, 0))
    row = spark.createDataFrame([(bytearray(Dac(values).to_bytes()), 2, 9, bits)], "codes binary, i int, far int, bits string")
    got = row.select(dac_get("codes", "i").alias("v"), dac_get("codes", "far").alias("none"), louds_child("bits", F.lit(0), F.lit(1)).alias("child"), louds_child("bits", F.lit(0), F.lit(2)).alias("no")).first()
    assert (got.v, got.none, got.child, got.no) == (900, None, Louds([2, 1, 0, 0]).child(0, 2), None)
    flags = spark.createDataFrame([(k % 2, 2 - k, int(values[k])) for k in range(3)], "bit int, place int, v long")
    packed = flags.agg(pack_bits("bit", "place").alias("b"), pack_values("v", "place").alias("v")).first()
    assert bytes(packed.b) == BitVec([0, 1, 0]).to_bytes() and Dac.from_bytes(bytes(packed.v)).all().tolist() == [900, 0, 5]
    udtf.register(spark)
    below = spark.sql(f"SELECT * FROM hcube_descendants('{bits}', 0, 2)").collect()
    assert [(r.depth, r.number) for r in below] == [(1, 1), (1, 2), (2, 3)]


def test_level_order_walks_up_like_louds():
    rng = np.random.default_rng(2)
    degrees, open_ = [], 1
    while len(degrees) < open_:
        degrees.append(int(rng.integers(0, 4)) if open_ < 200 else 0)
        open_ += degrees[-1]
    tree = Louds(degrees)
    many = LevelOrder(tree.bits, [0])
    numbers = np.arange(1, len(degrees))
    parents, places = many.parents(numbers)
    for n, p, c in zip(numbers.tolist(), parents.tolist(), places.tolist()):
        at = tree.node(n)
        assert tree.number(tree.parent(at)) == p and tree.ordinal(at) - 1 == c and many.first[p] + c == n
    assert many.fan.tolist() == degrees

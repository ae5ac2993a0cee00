"""One object for a cube's users: build it, ask labels, boxes and levels, pack it, see what a query would do."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import hast, hierarchy, packed, rst
from .plans import planner
from .spec import Cube


class HCube:
    """A cube's summed tree and the queries on it."""

    def __init__(self, tree: hast.Tree):
        self.tree = tree

    @classmethod
    def build(cls, spark: SparkSession, cube: Cube, facts: DataFrame, stored: bool = True) -> HCube:
        """``facts`` has the cube's level columns and measures (``Cube.facts`` or ``Cube.select``)."""
        return cls(hast.Tree(spark, cube, facts, stored))

    def answer(self, queries: DataFrame) -> DataFrame:
        """Label queries of any depths, ``(qid, <dim>..)``: few descendants are probed, many are joined by ancestor."""
        if planner.choose_mode(self.tree, queries) == "prefix":
            return planner.answer(self.tree, queries)
        got = planner.answer_exploded(self.tree, queries)
        values = [m for m, _ in self.tree.cube.measures] + ["cnt", "n_summed"]
        asked = planner.resolve(self.tree, queries).select("qid", *[d.name for d in self.tree.cube.dims], "status")
        ok = F.col("status") == "ok"
        return asked.join(got, "qid", "left").select(*asked.columns, *[F.when(ok, F.coalesce(v, F.lit(0))).cast("long").alias(v) for v in values])

    point = mixed = answer

    def level(self, depth: int) -> DataFrame:
        return self.tree.labelled(depth)

    def members(self, dim: str) -> DataFrame:
        return self.tree.members(dim)

    def violations(self, dim: str) -> DataFrame:
        return hierarchy.check_hierarchy(self.members(dim))

    def box(self, boxes: DataFrame, measure: str) -> DataFrame:
        """``boxes(qid, lo_1, hi_1, ..)`` over leaf numbers, by the regular tree over the same cells."""
        dims, h = self.tree.cube.dims, self.tree.cube.height
        cells = self.tree.nodes[h].select(*[F.col(f"{d.name}_id_{h}").alias(f"k{i}") for i, d in enumerate(dims, 1)], F.col(measure).alias("v"))
        side = max((self.members(d.name).filter(F.col("depth") == h).count() for d in dims), default=1)
        depth = rst.height_for(side, 2)
        return rst.range_sum(rst.build_rst(cells, len(dims), 2, depth), boxes, len(dims), 2)

    def pack(self, measure: str) -> tuple[DataFrame, int]:
        """Shards of the compact form and the depth at which they are cut."""
        cut = packed.choose_cut(self.tree)
        return packed.pack(self.tree, measure, cut), cut

    def explain_query(self, queries: DataFrame) -> DataFrame:
        """By query: status, deepest label, and the nodes that its answer sums and meets."""
        asked = planner.resolve(self.tree, queries).select("qid", "status", "deepest")
        return asked.join(planner.visits(self.tree, queries), "qid", "left")

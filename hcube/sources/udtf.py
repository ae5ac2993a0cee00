"""Table functions for SQL users."""

from __future__ import annotations

import itertools

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="depth: int, block: array<bigint>")
class BoxCover:
    """Blocks of a regular k-way split that make up the box [lo, hi] (inclusive arrays)."""

    def eval(self, lo: list, hi: list, side: int, k: int):
        h = 0
        while k**h < side:
            h += 1

        def cover(depth: int, block: tuple):
            s = k ** (h - depth)
            if any(b * s > y or b * s + s - 1 < x for b, x, y in zip(block, lo, hi)):
                return
            if all(x <= b * s and b * s + s - 1 <= y for b, x, y in zip(block, lo, hi)):
                yield depth, list(block)
                return
            for step in itertools.product(range(k), repeat=len(block)):
                yield from cover(depth + 1, tuple(b * k + c for b, c in zip(block, step)))

        yield from cover(0, (0,) * len(lo))


@udtf(returnType="ordinal: int, position: int, n_descendants: bigint")
class LoudsChildren:
    """Children of the node at a position of a LOUDS bit string, and how many nodes each has below it."""

    def eval(self, bits: str, position: int):
        from ..functions.bits import BitVec
        from ..functions.louds import Louds

        tree = Louds(bits=BitVec(bits))

        def size(i: int) -> int:
            return sum(1 + size(tree.child(i, k)) for k in range(1, tree.degree(i) + 1))

        for k in range(1, tree.degree(position) + 1):
            child = tree.child(position, k)
            yield k - 1, child, size(child)


@udtf(returnType="depth: int, number: bigint, position: bigint")
class LoudsDescendants:
    """Descendants of the node at a position of a LOUDS bit string down to some depth below it, with their level-order numbers."""

    def eval(self, bits: str, position: int, depth: int):
        from ..functions.bits import BitVec
        from ..functions.louds import Louds

        tree, level = Louds(bits=BitVec(bits)), [position]
        for below in range(1, depth + 1):
            level = [tree.child(i, k) for i in level for k in range(1, tree.degree(i) + 1)]
            for i in level:
                yield below, tree.number(i), i


def register(spark: SparkSession) -> None:
    spark.udtf.register("rst_cover", BoxCover)
    spark.udtf.register("louds_children", LoudsChildren)
    spark.udtf.register("hcube_descendants", LoudsDescendants)

"""Synthetic grids: n dimensions of m items, regular or irregular hierarchies, emptied cells."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..spec import Cube, Dimension

# Starts of the groups at each depth above the items.
CUTS_16 = (
    ((0, 3, 10), (0, 1, 3, 5, 9, 10, 13, 14)),
    ((0, 5, 6, 13), (0, 2, 5, 6, 9, 11, 13, 15)),
    ((0, 7), (0, 1, 4, 7, 8, 12, 15)),
    ((0, 2, 9, 11), (0, 2, 3, 5, 9, 11, 12, 14)),
)
CUTS_32 = (
    ((0, 5, 12, 25), (0, 2, 5, 6, 10, 12, 17, 20, 25, 26, 30),
     (0, 1, 2, 4, 5, 6, 8, 10, 11, 12, 15, 17, 18, 20, 23, 25, 26, 28, 30, 31)),
    ((0, 11, 14), (0, 3, 9, 11, 14, 19, 27), (0, 2, 3, 5, 9, 10, 11, 12, 14, 15, 19, 22, 24, 27, 31)),
)


def cuts(m: int, i: int) -> list[tuple[int, ...]]:
    """Group starts of dimension i (from 0), the items' own depth last."""
    if m == 32:
        found = CUTS_32[i % 2]
    else:
        found = CUTS_16[i % 4]
        if m != 16:
            found = tuple(tuple(sorted({x * m // 16 for x in row})) for row in found)
    return [*found, tuple(range(m))]


def binary_cuts(m: int, k: int = 2) -> list[tuple[int, ...]]:
    out, side = [], m
    while side > 1:
        side = -(-side // k)
        out.append(tuple(range(0, m, side)))
    return out


@dataclass(frozen=True)
class Grid:
    n: int
    m: int
    organisation: str = "irregular"
    empty: int = 0  # percent: 0, 25 or 50
    clustered: bool = False

    @property
    def name(self) -> str:
        return f"{self.n}D_{self.m}"

    def starts(self, i: int) -> list[tuple[int, ...]]:
        return binary_cuts(self.m) if self.organisation == "binary" else cuts(self.m, i)

    def mask(self) -> str:
        parts = []
        if self.empty:
            parts.append(f"((id * 7919 + 104729) % 65537) % {100 // self.empty} <> 0")
        if self.clustered:
            parts.append("(" + " + ".join(f"CAST(floor(({self._k(i)}) / {max(self.m // 4, 1)}) AS BIGINT)" for i in range(self.n)) + ") % 3 <> 0")
        return " AND ".join(parts) or "true"

    def _k(self, i: int) -> str:
        return f"CAST(floor(id / {self.m ** i}) AS BIGINT) % {self.m}"

    def cells_sql(self, source: str) -> str:
        keys = ", ".join(f"{self._k(i)} AS k{i + 1}" for i in range(self.n))
        return f"SELECT {keys}, CAST(1 + ((id * 48271) % 2147483647) % 9 AS BIGINT) AS v FROM {source} WHERE {self.mask()}"

    def cells(self, spark: SparkSession) -> DataFrame:
        return spark.sql(self.cells_sql("{ids}"), ids=spark.range(self.m**self.n))

    def duck(self) -> str:
        return self.cells_sql(f"(SELECT range AS id FROM range({self.m ** self.n}))")

    def cube(self, source: str = "{grid}") -> Cube:
        dims = []
        for i in range(self.n):
            levels = []
            for d, row in enumerate(self.starts(i), 1):
                steps = " ".join(f"WHEN k{i + 1} >= {s} THEN '{d}.{row[j]:02d}'" for j, s in reversed(list(enumerate(row))))
                levels.append((f"d{d}", f"(CASE {steps} END)"))
            dims.append(Dimension(f"x{i + 1}", tuple(levels)))
        return Cube(self.name, source, tuple(dims), (("v", "v"),))

    def tree(self, spark: SparkSession):
        from ..operators.hast import Tree

        cube = self.cube()
        return Tree(spark, cube, spark.sql(cube.select(), grid=self.cells(spark)))

    def fact_sql(self) -> str:
        """The cube's facts for DuckDB."""
        return self.cube().select().replace("{grid}", f"({self.duck()}) AS grid")


def from_lineitem(spark: SparkSession, sf_dir: str, m: int = 16) -> DataFrame:
    """The grids' twin on data: keys of line items modulo m in four dimensions."""
    return spark.sql(lineitem_sql("{lineitem}", m), lineitem=spark.read.parquet(f"{sf_dir}/lineitem.parquet"))


def lineitem_sql(table: str, m: int) -> str:
    return (
        f"SELECT l_partkey % {m} AS k1, l_suppkey % {m} AS k2, l_orderkey % {m} AS k3, "
        f"CAST(dayofyear(l_shipdate) AS BIGINT) % {m} AS k4, CAST(l_quantity AS BIGINT) AS v FROM {table}"
    )


def lineitem_cells_sql(table: str, m: int, empty: int = 0) -> str:
    """Line items added up by cell; ``empty`` percent of the cells are emptied as in a grid."""
    keys = ["k1", "k2", "k3", "k4"]
    cell = "(" + " + ".join(f"{k} * {m**i}" for i, k in enumerate(keys)) + ")"
    kept = Grid(4, m, empty=empty).mask().replace("id", cell)
    known = " AND ".join(f"{k} IS NOT NULL" for k in keys)
    return f"SELECT {', '.join(keys)}, CAST(sum(v) AS BIGINT) AS v FROM ({lineitem_sql(table, m)}) WHERE {known} AND {kept} GROUP BY {', '.join(keys)}"

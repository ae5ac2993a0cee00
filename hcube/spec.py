"""Declarative description of a cube: facts, hierarchies, measures, level plan."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

NULL_MEMBER = "__null__"
ROOT = "*"


@dataclass(frozen=True)
class Dimension:
    """A hierarchy: level names from coarse to fine, each with its SQL expression.

    A label need only be unique below its parent.  ``plan`` lists the level that stands
    at each depth; a name twice in a row is an artificial level (one child: itself).
    """

    name: str
    levels: tuple[tuple[str, str], ...]
    plan: tuple[str, ...] = ()

    def at(self) -> tuple[str, ...]:
        names = self.plan or tuple(n for n, _ in self.levels)
        order = [n for n, _ in self.levels]
        places = [order.index(n) for n in names]
        if places != sorted(places) or set(names) - set(order):
            raise ValueError(f"{self.name}: the plan {names} does not go from coarse to fine")
        return names

    @property
    def height(self) -> int:
        return len(self.at())

    def expression(self, depth: int) -> str:
        return dict(self.levels)[self.at()[depth - 1]]

    def column(self, depth: int) -> str:
        return f"{self.name}_{depth}"

    def is_copy(self, depth: int) -> bool:
        return depth > 1 and self.at()[depth - 1] == self.at()[depth - 2]


@dataclass(frozen=True)
class Cube:
    """``source`` is what follows FROM, with tables in braces; Spark and DuckDB read the same text."""

    name: str
    source: str
    dims: tuple[Dimension, ...]
    measures: tuple[tuple[str, str], ...]
    tables: tuple[str, ...] = field(default=())

    def __post_init__(self) -> None:
        if len({d.height for d in self.dims}) > 1:
            raise ValueError(f"{self.name}: hierarchies of different height; give level plans")

    @property
    def height(self) -> int:
        return self.dims[0].height

    def select(self) -> str:
        cols = [
            f"coalesce({d.expression(k)}, '{NULL_MEMBER}') AS {d.column(k)}" for d in self.dims for k in range(1, d.height + 1)
        ]
        cols += [f"{e} AS {n}" for n, e in self.measures]
        return f"SELECT {', '.join(cols)} FROM {self.source}"

    def facts(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """One row per fact: a label for each dimension and depth, and the measures."""
        frames = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in self.tables}
        return spark.sql(self.select(), **frames) if frames else spark.sql(self.select())

    def sql(self) -> str:
        return self.select().format(**{t: t for t in self.tables})

    def with_plan(self, **plans: tuple[str, ...]) -> Cube:
        dims = tuple(Dimension(d.name, d.levels, plans.get(d.name, d.plan)) for d in self.dims)
        return Cube(self.name, self.source, dims, self.measures, self.tables)

    def only(self, *names: str) -> Cube:
        return Cube(self.name, self.source, tuple(d for d in self.dims if d.name in names), self.measures, self.tables)

"""What Spark offers unaided, to compare with: roll-ups, the full lattice, brute force."""

from __future__ import annotations

import gc
import itertools
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import materialise
from ..spec import Cube


def grouping_sets(facts: DataFrame, cube: Cube, sets: list[tuple[int, ...]]) -> DataFrame:
    """One aggregate over several tuples of depths; the facts are expanded once per set."""
    cols = [d.column(k) for d in cube.dims for k in range(1, cube.height + 1)]
    listed = [[d.column(j) for d, k in zip(cube.dims, depths) for j in range(1, k + 1)] for depths in sets]
    return facts.groupingSets([[F.col(c) for c in s] for s in listed], *[F.col(c) for c in cols]).agg(*[F.sum(m).cast("long").alias(m) for m, _ in cube.measures], F.count("*").alias("cnt"))


def rollup_depths(facts: DataFrame, cube: Cube) -> DataFrame:
    return grouping_sets(facts, cube, [(k,) * len(cube.dims) for k in range(cube.height + 1)])


def lattice(facts: DataFrame, cube: Cube, upto: int) -> DataFrame:
    """All tuples of depths 0..upto: most storage, one read for any query."""
    return grouping_sets(facts, cube, list(itertools.product(range(upto + 1), repeat=len(cube.dims))))


def lattice_checks(facts: DataFrame, cube: Cube, rows_a_part: int = 1 << 18) -> DataFrame:
    """What the members of each tuple of depths add up to, without a table of all members.

    Facts are dealt once by the leaves of each dimension, for all tuples in which that
    dimension is at its leaf level and those before it are not; every member is then whole in
    one task and goes into its sums there.  The tuples above all leaves come in the same way
    from the facts added up by the depth above.  One dealt table is held at a time.
    A member's depth is the number of its labels that are not null.
    """
    spark, names = facts.sparkSession, [m for m, _ in cube.measures]
    first = names[0]
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    now, parts = materialise(facts.select(*_path(cube, cube.height), *names, F.lit(1).cast("long").alias("cnt")), "lattice-facts"), []
    for h in range(cube.height, 0, -1):
        rows = now.count()
        for j, leaf in enumerate(cube.dims):
            dealt = now.repartition(max(width, -(-rows // rows_a_part)), *[F.col(leaf.column(k)) for k in range(1, h + 1)]).persist(StorageLevel.DISK_ONLY)
            dealt.count()  # only once it is stored does Spark take its partitions as they are
            tuples = itertools.product(*[[h] if i == j else range(h if i < j else h + 1) for i in range(len(cube.dims))])
            parts.append(materialise(_added(reduce(DataFrame.unionByName, [_members(dealt, cube, t) for t in tuples]), cube), "lattice-part"))
            dealt.unpersist(True)
            del dealt
            _drop_shuffles(spark)
        above = _path(cube, h - 1)
        now = now.groupBy(*above).agg(*[F.sum(c).cast("long").alias(c) for c in (*names, "cnt")])
        now = materialise(now, "lattice-above")
        _drop_shuffles(spark)
    parts.append(_added(_members(now, cube, (0,) * len(cube.dims)), cube))
    every = reduce(DataFrame.unionByName, parts)
    by = [f"g_{d.name}" for d in cube.dims]
    sums = ["members", first, "squares", *names[1:], "cnt"]
    return every.groupBy(*by).agg(*[F.sum(c).cast("long").alias(c) for c in sums], F.max("most").alias("most")).select(*by, "members", first, "most", "squares", *names[1:], "cnt")


def _drop_shuffles(spark: SparkSession) -> None:
    """Spark's cleaner drops the shuffle files of finished jobs once the driver's garbage is collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def _path(cube: Cube, depth: int) -> list[str]:
    return [d.column(k) for d in cube.dims for k in range(1, depth + 1)]


def _members(rows: DataFrame, cube: Cube, depths: tuple[int, ...]) -> DataFrame:
    keys = [[d.column(k) for k in range(1, depth + 1)] for d, depth in zip(cube.dims, depths)]
    sums = [m for m, _ in cube.measures] + ["cnt"]
    found = rows.groupBy(*[c for of in keys for c in of]).agg(*[F.sum(c).cast("long").alias(c) for c in sums])
    known = lambda of: reduce(lambda a, b: a + b, [F.col(c).isNotNull().cast("int") for c in of], F.lit(0))
    return found.select(*[known(of).alias(f"g_{d.name}") for d, of in zip(cube.dims, keys)], *sums)


def _added(members: DataFrame, cube: Cube) -> DataFrame:
    first, *others = [m for m, _ in cube.measures]
    return members.groupBy(*[f"g_{d.name}" for d in cube.dims]).agg(
        F.count("*").alias("members"), F.max(first).alias("most"), F.sum(F.col(first) * F.col(first)).alias("squares"), *[F.sum(c).alias(c) for c in (first, *others, "cnt")]
    )


def brute_force(facts: DataFrame, cube: Cube, queries: DataFrame) -> DataFrame:
    """Sums straight from the facts: queries ``(qid, labels, g0..)`` by one equi-join per tuple of depths."""
    depth_cols = [f"g{i}" for i in range(len(cube.dims))]
    parts = []
    for depths in sorted(tuple(r) for r in queries.select(*depth_cols).distinct().collect()):  # at most (H+1)^n
        mine = queries
        for c, k in zip(depth_cols, depths):
            mine = mine.filter(F.col(c) == k)
        on = [(d.name, d.column(k)) for d, k in zip(cube.dims, depths) if k]
        keyed = mine.select("qid", *[F.col(a).alias(b) for a, b in on])
        met = facts.join(keyed, [b for _, b in on]) if on else facts.crossJoin(keyed)
        parts.append(met.groupBy("qid").agg(*[F.sum(m).cast("long").alias(m) for m, _ in cube.measures]))
    got = reduce(DataFrame.unionByName, parts)
    return queries.select("qid").join(got, "qid", "left").na.fill(0)

"""Upkeep of node sums from a stream: sums and counts of new facts are added as deltas.

Each micro-batch appends one delta per depth, named by its batch, so a replayed batch
replaces its own delta; readers add base and deltas, and compaction folds them.  Min and
max merge for inserts only.  Members are known by label here: dense numbers are made anew
when a store is compacted and rebuilt.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.utils import AnalysisException

from ..spec import Cube


def delta(facts: DataFrame, cube: Cube, depth: int) -> DataFrame:
    keys = [d.column(k) for d in cube.dims for k in range(1, depth + 1)]
    aggs = [F.count("*").alias("cnt"), *[F.sum(m).cast("long").alias(m) for m, _ in cube.measures]]
    return facts.groupBy(*keys).agg(*aggs)


def level_facts(rows: DataFrame, cube: Cube) -> DataFrame:
    """Level columns and measures of a stream or batch of one raw table."""
    return rows.selectExpr(
        *[f"coalesce({d.expression(k)}, '__null__') AS {d.column(k)}" for d in cube.dims for k in range(1, d.height + 1)],
        *[f"{e} AS {n}" for n, e in cube.measures],
    )


def maintain(stream: DataFrame, cube: Cube, store: str, checkpoint: str):
    """Starts the upkeep of ``store`` from a stream of raw rows; returns the streaming query."""

    def add(batch: DataFrame, batch_id: int) -> None:
        cells = delta(level_facts(batch, cube), cube, cube.height).persist()
        for depth in range(cube.height, -1, -1):
            keys = [d.column(k) for d in cube.dims for k in range(1, depth + 1)]
            up = cells.groupBy(*keys).agg(F.sum("cnt").alias("cnt"), *[F.sum(m).cast("long").alias(m) for m, _ in cube.measures])
            up.write.mode("overwrite").parquet(f"{store}/depth={depth}/batch={batch_id}")
        cells.unpersist()

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_sums(spark: SparkSession, cube: Cube, store: str, depth: int) -> DataFrame:
    """Base and deltas of a depth, added."""
    keys = [d.column(k) for d in cube.dims for k in range(1, depth + 1)]
    try:
        rows = spark.read.parquet(f"{store}/depth={depth}")
    except AnalysisException:  # nothing has arrived yet
        schema = ", ".join([*(f"{k} string" for k in keys), "cnt long", *(f"{m} long" for m, _ in cube.measures)])
        rows = spark.createDataFrame([], schema)
    return rows.groupBy(*keys).agg(F.sum("cnt").alias("cnt"), *[F.sum(m).cast("long").alias(m) for m, _ in cube.measures])


def compact(spark: SparkSession, cube: Cube, store: str, target: str) -> None:
    for depth in range(cube.height + 1):
        read_sums(spark, cube, store, depth).write.mode("overwrite").parquet(f"{target}/depth={depth}/batch=-1")


def hourly(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Tumbling hours of events by type; rows later than the watermark are left out when streamed."""
    stamped = events.withColumn("at", F.col("ts").cast("timestamp"))
    kept = stamped.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else stamped.dropDuplicates(["event_id"])
    return kept.groupBy(F.window("at", "1 hour").alias("w"), "event_type").agg(
        F.count("*").alias("cnt"), F.sum(F.expr("CAST(ROUND(value * 100) AS BIGINT)")).cast("long").alias("cents")
    ).select(F.col("w.start").alias("hour"), "event_type", "cnt", "cents")


def sliding_from_panes(panes: DataFrame, hours: int) -> DataFrame:
    """Sliding windows as sums of whole panes: each pane belongs to the windows that start up to ``hours - 1`` before it."""
    shifts = F.explode(F.sequence(F.lit(0), F.lit(hours - 1)))
    moved = panes.withColumn("back", shifts).withColumn("start", F.expr("hour - make_interval(0, 0, 0, 0, back, 0, 0)"))
    return moved.groupBy("start", "event_type").agg(F.sum("cnt").alias("cnt"), F.sum("cents").alias("cents"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Session windows per user: no hierarchy nests them, so they are summed from the rows."""
    return events.withColumn("at", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("cnt")).select(
        "user_id", F.col("w.start").alias("start"), "cnt"
    )


def union_deltas(parts: list[DataFrame], keys: list[str], measures: list[str]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts).groupBy(*keys).agg(*[F.sum(m).cast("long").alias(m) for m in measures])

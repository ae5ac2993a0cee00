"""Tables in shared storage: intermediate ones that cut lineage, and the node store."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; one of our own only where none is set (tests)."""
    found = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = tempfile.mkdtemp(prefix="hcube-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def materialise(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as parquet to the shared folder and read back."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def write_nodes(nodes: dict[int, DataFrame], path: str) -> None:
    """One folder per depth, rows in the order of their slots: a subtree is a run of rows.

    Each depth has its own columns (ids and slots down to it), so depths are folders of
    their own table rather than one table with a partition column.
    """
    for depth, table in nodes.items():
        keys = [f"p_{k}" for k in range(1, depth + 1)]
        laid = table.repartitionByRange(*keys).sortWithinPartitions(*keys) if keys else table
        laid.write.mode("overwrite").parquet(f"{path}/depth={depth}")


def read_nodes(spark: SparkSession, path: str, height: int) -> dict[int, DataFrame]:
    return {k: spark.read.parquet(f"{path}/depth={k}") for k in range(height + 1)}


def register_views(nodes: dict[int, DataFrame], members: dict[str, DataFrame], cube: str) -> list[str]:
    """Temporary views ``nodes_<cube>_<depth>`` and ``members_<cube>_<dim>`` for SQL users."""
    names = []
    for depth, table in nodes.items():
        table.createOrReplaceTempView(n := f"nodes_{cube}_{depth}")
        names.append(n)
    for dim, table in members.items():
        table.createOrReplaceTempView(n := f"members_{cube}_{dim}")
        names.append(n)
    return names


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """``df`` written and read back as csv, json, orc or parquet with its own schema."""
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)
    reader = df.sparkSession.read.schema(df.schema)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def path_range(df: DataFrame, prefix: list[int]) -> DataFrame:
    """Nodes below a slot prefix, by predicates that reach the scan."""
    for k, v in enumerate(prefix, 1):
        df = df.filter(F.col(f"p_{k}") == v)
    return df

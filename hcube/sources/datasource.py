"""Python data source ``hcube``: nodes of a stored tree, one depth or all.

``spark.dataSource.register(NodeSource)``, then ``spark.read.format("hcube")
.option("path", store).option("height", h).option("depth", 2).load()``.  Each (depth, part
file) is a partition.  The depth is an option and not a pushed filter: Spark keeps a
reader's pushed filters with the DataFrame, and a second query on it would read too little.
Reads local or mounted paths; on remote stores use ``store.read_nodes``.
"""

from __future__ import annotations

from pathlib import Path

import numpy as np
import pyarrow as pa

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, depth: int, file: str):
        self.depth, self.file = depth, file


class NodeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "hcube"

    def schema(self) -> str:
        measures = self.options.get("measures", "")
        return "depth int, path array<long>, cnt long" + "".join(f", {m} long" for m in measures.split(",") if m)

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options, [f.name for f in schema][3:])


class _Reader(DataSourceReader):
    def __init__(self, options: dict, measures: list[str]):
        self.root, self.height, self.measures = options["path"], int(options["height"]), measures
        self.depth = int(options["depth"]) if "depth" in options else None

    def partitions(self) -> list[_Part]:
        depths = range(self.height + 1) if self.depth is None else [self.depth]
        return [_Part(d, str(f)) for d in depths for f in sorted(Path(self.root, f"depth={d}").glob("*.parquet"))]

    def read(self, partition: _Part):
        import pyarrow.parquet as pq

        slots = [f"p_{k}" for k in range(1, partition.depth + 1)]
        for batch in pq.ParquetFile(partition.file).iter_batches(columns=[*slots, "cnt", *self.measures]):
            n, k = batch.num_rows, len(slots)
            path = np.stack([batch.column(s).to_numpy(zero_copy_only=False) for s in slots], 1).ravel() if k else np.empty(0, np.int64)
            paths = pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * k, pa.int32()), pa.array(path, pa.int64()))
            rest = [batch.column(c).cast(pa.int64()) for c in ("cnt", *self.measures)]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, partition.depth), pa.int32()), paths, *rest], ["depth", "path", "cnt", *self.measures])

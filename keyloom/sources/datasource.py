"""A filter's slots as a Python data source: ``spark.read.format("keyloom_slots").option("path", ...)``."""

from __future__ import annotations

import glob

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class SlotSource(DataSource):
    """Rows (shard, slot, g) of a saved filter. The path has to be one that every executor can open."""

    @classmethod
    def name(cls) -> str:
        return "keyloom_slots"

    def schema(self) -> str:
        return "shard int, slot long, g long"

    def reader(self, schema):
        return _Reader(self.options["path"])


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.removeprefix("file:")

    def partitions(self):
        return [InputPartition(f) for f in sorted(glob.glob(f"{self.path}/tables/**/*.parquet", recursive=True))]

    def read(self, partition):
        """Arrow batches, one for each shard."""
        for batch in pq.ParquetFile(partition.value).iter_batches(batch_size=1, columns=["shard", "g"]):
            cells = batch.column("g")[0].values
            if cells is not None and len(cells):
                n = len(cells)
                columns = [pa.array(np.full(n, batch.column("shard")[0].as_py()), pa.int32()), pa.array(np.arange(n), pa.int64()), cells.cast(pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, names=["shard", "slot", "g"])

"""A batch source for the edges of a written index: spark.read.format("range_index").load(path).

One partition per shard directory, read with Arrow; an `alpha` option leaves only the edges that are active at
that weight. Reads local or shared paths that pyarrow can open.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..schema import SCALE


class RangeIndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "range_index"

    def schema(self) -> str:
        return "shard int, src long, dst long, lo short, hi short"

    def reader(self, schema) -> "RangeIndexReader":
        return RangeIndexReader(self.options["path"], self.options.get("alpha"))


class RangeIndexReader(DataSourceReader):
    def __init__(self, path: str, alpha: str | None):
        self.path, self.at = path, None if alpha is None else round(float(alpha) * SCALE)

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)
        found = store.get_file_info(fs.FileSelector(f"{base}/nodes", recursive=False))
        return [InputPartition((int(f.base_name.split("=")[1]), f.path)) for f in found if f.base_name.startswith("shard=")]

    def read(self, partition: InputPartition):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc
        import pyarrow.parquet as pq

        shard, path = partition.value
        for b in pq.ParquetDataset(path, partitioning=None).read(columns=["id", "level", "dst", "lo", "hi"]).to_batches(max_chunksize=20_000):
            b = b.filter(pc.equal(b.column("level"), 0))
            dst, lo, hi = (b.column(c).flatten() for c in ("dst", "lo", "hi"))
            pieces = pc.list_value_length(lo).to_numpy()
            src = np.repeat(b.column("id").to_numpy(), pc.list_value_length(b.column("dst")).to_numpy())
            low, high = lo.flatten().to_numpy(), hi.flatten().to_numpy()
            keep = np.ones(len(low), bool) if self.at is None else (low <= self.at) & (self.at <= high)
            rows = (np.full(len(low), shard, np.int32), np.repeat(src, pieces), np.repeat(dst.to_numpy(), pieces), low, high)
            yield pa.RecordBatch.from_arrays([pa.array(r[keep]) for r in rows], names=["shard", "src", "dst", "lo", "hi"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RangeIndexSource)

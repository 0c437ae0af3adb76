"""format("meterpack"): recovered rows straight from packed Parquet, by Spark's Python data source interface.

Its readers open files themselves, so the path must be one that every machine mounts; for stores that only Spark reads
there are sources.container and plans.recompress.
"""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition

from meterpack.schemas import READINGS


class PackedSource(DataSource):
    """Options: path (a folder of packed blocks), block_len, stream_ids (comma-joined; only rows that hold one are decoded),
    pushdown ("true" where the session has spark.sql.python.filterPushdown.enabled: filters on stream_id come by themselves)."""

    @classmethod
    def name(cls) -> str:
        return "meterpack"

    def schema(self) -> str:
        return READINGS

    def reader(self, schema) -> "PackedReader":
        kind = PushdownReader if self.options.get("pushdown") == "true" else PackedReader
        ids = self.options.get("stream_ids")
        return kind(self.options["path"], int(self.options.get("block_len", 1500)), {int(i) for i in ids.split(",")} if ids else None)


class PackedReader(DataSourceReader):
    def __init__(self, path: str, block_len: int, wanted: set[int] | None = None) -> None:
        self.path, self.block_len, self.wanted = path.removeprefix("file://"), block_len, wanted

    def partitions(self):
        import glob

        return [InputPartition(f) for f in sorted(glob.glob(f"{self.path}/**/*.parquet", recursive=True))]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa
        import pyarrow.parquet as pq

        from meterpack.kernels.firststage import decode_block
        from meterpack.plans.recompress import unpack

        file = pq.ParquetFile(partition.value)
        window = next((int(p.split("=")[1]) for p in partition.value.split("/") if p.startswith("window_no=")), None)
        for batch in file.iter_batches(64):
            for row in batch.to_pylist():
                if self.wanted is not None and not self.wanted & set(row["stream_ids"]):
                    continue
                row |= {"applied": row["rle_applied"], "t": row["rle_threshold"], "window_no": row.get("window_no", window)}
                for s in unpack(row):
                    if self.wanted is None or s["stream_id"] in self.wanted:
                        x = decode_block(s["words"], s["coder"], s["n_readings"], s["n_bits"], s["mu"], s["sigma"], s["first"])
                        pos = (np.arange(len(x)) + s["block_no"] * self.block_len).astype(np.int32)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), s["stream_id"], np.int64)), pa.array(pos), pa.array(x.astype(np.int64))], names=["stream_id", "pos", "sym"])


class PushdownReader(PackedReader):
    def pushFilters(self, filters):
        """Takes equality and membership on stream_id; whatever else comes stays with Spark."""
        for f in filters:
            values = (f.value,) if isinstance(f, EqualTo) else f.value if isinstance(f, In) else None
            if values is not None and tuple(f.attribute) == ("stream_id",):
                self.wanted = set(values) & self.wanted if self.wanted is not None else set(values)
            else:
                yield f

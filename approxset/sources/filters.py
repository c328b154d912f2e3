"""A data source for stored filters: spark.read.format("approxfilter").load(path) gives (fp, cnt) of what `quotient.save` wrote.

One partition a stored file. Paths are opened by pyarrow, so they must have a scheme that it knows (file, hdfs, s3, gs);
where only Spark's readers can open a path, use `quotient.load` and `quotient.unpack`."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..cluster import ship


def register(spark: SparkSession) -> None:
    """Make the format known to the session. The class is local, so that it travels by value to Python's planner and workers."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    ship(spark)

    class Reader(DataSourceReader):
        def __init__(self, path):
            self.path = path

        def _store(self):
            from pyarrow import fs

            return fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path}")

        def partitions(self):
            from pyarrow import fs

            store, base = self._store()
            files = store.get_file_info(fs.FileSelector(f"{base}/shards"))
            return [InputPartition(f.path) for f in files if f.path.endswith(".parquet")]

        def read(self, partition):
            import json

            import numpy as np
            import pyarrow as pa
            import pyarrow.parquet as pq

            from approxset.operators.quotient import _fps_of
            from approxset.schema import FilterSpec

            store, base = self._store()
            if partition is None:  # no file
                return
            row = pq.read_table(f"{base}/descriptor", filesystem=store).to_pylist()[0]
            spec, per = FilterSpec(**json.loads(row["spec"])), None
            per = -(-spec.slots // row["shards"])
            with store.open_input_file(partition.value) as f:
                for batch in pq.ParquetFile(f).iter_batches(64):
                    for r in batch.to_pylist():
                        fp, cnt = np.unique(_fps_of(r["shard"], r["ring"], r["payload"], per, spec), return_counts=True)
                        yield pa.RecordBatch.from_arrays([pa.array(fp, pa.int64()), pa.array(cnt, pa.int64())], names=["fp", "cnt"])

    class FilterSource(DataSource):
        @classmethod
        def name(cls):
            return "approxfilter"

        def schema(self):
            return "fp long, cnt long"

        def reader(self, schema):
            return Reader(self.options["path"])

    spark.dataSource.register(FilterSource)

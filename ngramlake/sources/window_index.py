"""The window index as a data source: ``spark.read.format("window_index")``.

Options: ``runs``, a folder of sorted run files (Parquet, readable by the
executors), and ``prefix``, the key prefix that is asked for.  One task reads one
file; files whose key range cannot hold the prefix are left out when planning.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder, self.prefix = options["runs"].removeprefix("file://"), options.get("prefix", "")

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds
        import pyarrow.parquet as pq

        out = []
        for path in ds.dataset(self.folder, format="parquet").files:
            meta = pq.ParquetFile(path).metadata
            at = meta.schema.to_arrow_schema().get_field_index("key")
            stats = [meta.row_group(i).column(at).statistics for i in range(meta.num_row_groups)]
            if any(s is None or not s.has_min_max or (s.min[: len(self.prefix)] <= self.prefix <= s.max[: len(self.prefix)] or s.min.startswith(self.prefix)) for s in stats):
                out.append(_File(path))
        return out or [_File("")]

    def read(self, partition: _File) -> Iterator:
        import pyarrow.compute as pc
        import pyarrow.parquet as pq

        if not partition.path:
            return
        for b in pq.ParquetFile(partition.path).iter_batches(columns=["key", "run"]):
            if self.prefix:
                b = b.filter(pc.starts_with(b.column(0), self.prefix))
            yield from zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)


class WindowIndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "window_index"

    def schema(self) -> str:
        return "key string, run long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))

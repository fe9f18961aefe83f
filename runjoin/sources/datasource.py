"""``spark.read.format('runsummary').load(path)``: stored columns as rows, a range of rows a task."""

from __future__ import annotations

import json
import math
from collections.abc import Iterable, Iterator
from functools import reduce

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructField, StructType


class RunSummarySource(DataSource):
    """Rows of a stored summary in Parquet, read through Arrow file systems. Option ``rows``: rows a partition. The manifest
    holds the total, so the driver reads nothing else. With option ``push`` (it needs spark.sql.python.filterPushdown.enabled)
    filters of the first column spare ranges of rows."""

    @classmethod
    def name(cls) -> str:
        return "runsummary"

    def _manifest(self) -> dict:
        import pyarrow.fs as pafs

        fs, root = pafs.FileSystem.from_uri(self.options["path"])
        for f in fs.get_file_info(pafs.FileSelector(f"{root}/manifest")):
            if f.base_name.startswith("part-"):
                return json.loads(fs.open_input_stream(f.path).read())
        raise FileNotFoundError(f"{root}/manifest")

    def schema(self) -> StructType:
        m = self._manifest()
        kinds = {n: StructType.fromJson(json.loads(m["schemas"][n]))["value"].dataType for n in m["columns"]}
        return StructType([StructField(n, t) for n, t in kinds.items()])

    def reader(self, schema: StructType) -> DataSourceReader:
        m = self._manifest()
        kind = _FilteringReader if self.options.get("push", "false").lower() == "true" else _Reader
        return kind(self.options["path"], m["columns"], m["rows"], int(self.options.get("rows", 1 << 18)))


class _Reader(DataSourceReader):
    def __init__(self, path: str, columns: list[str], total: int, rows: int) -> None:
        self.path, self.columns, self.total, self.rows = path, columns, total, rows
        self.wanted: list[tuple[str, object]] = []

    def _dataset(self, name: str):
        import pyarrow.dataset as ds
        import pyarrow.fs as pafs

        fs, root = pafs.FileSystem.from_uri(self.path)
        files = [f.path for f in fs.get_file_info(pafs.FileSelector(f"{root}/col={name}")) if f.base_name.startswith("part-")]
        return ds.dataset(files, filesystem=fs, format="parquet")

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(math.ceil(self.total / self.rows))]

    def _asked(self, field):
        tests = {"==": lambda v: field == v, "in": lambda v: field.isin(list(v)), ">": lambda v: field > v, ">=": lambda v: field >= v, "<": lambda v: field < v, "<=": lambda v: field <= v}
        return reduce(lambda a, b: a & b, [tests[k](v) for k, v in self.wanted])

    def read(self, partition: InputPartition) -> Iterator:
        import numpy as np
        import pyarrow as pa
        import pyarrow.dataset as ds

        low = partition.value * self.rows
        high = low + self.rows
        here = (ds.field("start") < high) & (ds.field("start") + ds.field("freq") > low)
        if self.wanted and not self._dataset(self.columns[0]).count_rows(filter=here & self._asked(ds.field("value"))):
            return
        out = []
        for name in self.columns:
            t = self._dataset(name).to_table(filter=here).sort_by("start")
            start, freq = t["start"].to_numpy(), t["freq"].to_numpy()
            times = np.minimum(start + freq, high) - np.maximum(start, low)
            out.append(t["value"].combine_chunks().take(pa.array(np.repeat(np.arange(len(times)), times))))
        yield pa.RecordBatch.from_arrays([a.combine_chunks() if isinstance(a, pa.ChunkedArray) else a for a in out], self.columns)


class _FilteringReader(_Reader):
    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        """Equalities, lists and bounds of the first column are noted: ranges of rows that can't hold such values are not
        expanded. All filters are left to Spark too, as a range holds other rows besides."""
        kinds = {EqualTo: "==", In: "in", GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<="}
        for f in filters:
            if type(f) in kinds and f.attribute == (self.columns[0],):
                self.wanted.append((kinds[type(f)], f.value))
            yield f


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RunSummarySource)

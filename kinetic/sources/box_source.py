"""``moving_objects``: a data source over a written layout whose box filters pick files by their footers.

Needs spark.sql.python.filterPushdown.enabled. Bounds on x, y, part and
quadrant are taken over; a file is read only if its footer's extremes meet
them, and Spark still tests every row.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

SCHEMA = "oid long, x double, y double, vx double, vy double, speed double, t_ref double, part int, quadrant int"
COLUMNS = ["oid", "x", "y", "vx", "vy", "speed", "t_ref"]


class LayoutFile(InputPartition):
    def __init__(self, path: str, part: int, quadrant: int):
        super().__init__(path)
        self.path, self.part, self.quadrant = path, part, quadrant


class LayoutReader(DataSourceReader):
    def __init__(self, root: str):
        self.root = root
        self.low: dict[str, float] = {}
        self.high: dict[str, float] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            name = f.attribute[0] if len(getattr(f, "attribute", ())) == 1 else None
            if name in ("x", "y", "part", "quadrant"):
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    self.low[name] = max(f.value, self.low.get(name, f.value))
                if isinstance(f, (LessThan, LessThanOrEqual, EqualTo)):
                    self.high[name] = min(f.value, self.high.get(name, f.value))
            yield f  # rows are tested again

    def _meets(self, name: str, low: float, high: float) -> bool:
        return high >= self.low.get(name, high) and low <= self.high.get(name, low)

    def partitions(self) -> list[LayoutFile]:
        import pyarrow.parquet as pq
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(self.root)
        out = []
        for info in store.get_file_info(fs.FileSelector(root, recursive=True)):
            keys = dict(k.split("=") for k in info.path.split("/") if k.startswith(("part=", "quadrant=")))
            if not info.path.endswith(".parquet") or len(keys) < 2:
                continue
            part, quadrant = int(keys["part"]), int(keys["quadrant"])
            if not (self._meets("part", part, part) and self._meets("quadrant", quadrant, quadrant)):
                continue
            with store.open_input_file(info.path) as f:
                meta = pq.ParquetFile(f).metadata
            ends = {"x": [], "y": []}
            for g in range(meta.num_row_groups):
                for c in range(meta.num_columns):
                    col = meta.row_group(g).column(c)
                    if col.path_in_schema in ends and col.statistics is not None and col.statistics.has_min_max:
                        ends[col.path_in_schema] += [col.statistics.min, col.statistics.max]
            if all(not v or self._meets(n, min(v), max(v)) for n, v in ends.items()):
                out.append(LayoutFile(info.path, part, quadrant))
        return out or [LayoutFile("", 0, 0)]

    def read(self, partition: LayoutFile) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq
        from pyarrow import fs

        if not partition.path:
            return
        store, _ = fs.FileSystem.from_uri(self.root)
        with store.open_input_file(partition.path) as f:
            for b in pq.ParquetFile(f).iter_batches(columns=COLUMNS):
                n = b.num_rows
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array([partition.part] * n, pa.int32()), pa.array([partition.quadrant] * n, pa.int32())], names=[*COLUMNS, "part", "quadrant"])


class MovingObjectsSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "moving_objects"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> LayoutReader:
        root = self.options["path"]
        return LayoutReader(root if "://" in root else f"file://{root}")


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(MovingObjectsSource)

"""The live codes of an index directory as a Spark data source: spark.read.format("cfi").option("path", ...).load().

The option ``cells`` (comma-separated) chooses bucket folders when partitions are planned, and rows inside the files. With
``pushdown`` set to true, equality and membership filters on ``cell`` do the same by themselves; Spark keeps what was pushed with the
loaded relation, so a frame loaded that way serves one query, and the default is the option. Files are read by Arrow from any URI
that pyarrow.fs resolves.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator

import pyarrow as pa
import pyarrow.dataset as pads
import pyarrow.fs as pafs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition
from pyspark.sql.types import StructType

from annspark.sources.layout import OPENS, spread

SCHEMA = "id long, cell long, code binary, sign binary, res_norm short, norm double"


class _File(InputPartition):
    def __init__(self, path: str, cells: list[int] | None):
        self.path, self.cells = path, cells


def _fs(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


class _Reader(DataSourceReader):
    def __init__(self, path: str, buckets: int, cells: list[int] | None):
        self.path, self.buckets, self.cells = path, buckets, cells

    def partitions(self) -> list[InputPartition]:
        return _plan(self)

    def read(self, partition: _File) -> Iterator[pa.RecordBatch]:
        if partition.path:
            fs, _ = _fs(self.path)
            data = pads.dataset(partition.path, filesystem=fs, format="parquet", partitioning=None)
            names = [f.split()[0] for f in SCHEMA.split(", ")]
            yield from data.to_batches(columns=names, filter=None if partition.cells is None else pads.field("cell").isin(partition.cells))


class _PushingReader(_Reader):
    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("cell",):
                self.cells = [f.value] if self.cells is None else [c for c in self.cells if c == f.value]
            elif isinstance(f, In) and f.attribute == ("cell",):
                self.cells = list(f.value) if self.cells is None else [c for c in self.cells if c in f.value]
            else:
                yield f


def _plan(reader: _Reader) -> list[InputPartition]:
    """The files of the live epoch, by the manifest's rules (``layout.live``), without a Spark session."""
    fs, root = _fs(reader.path)
    commits: list[dict] = []
    for info in fs.get_file_info(pafs.FileSelector(f"{root}/manifest")):
        if info.path.endswith(".json"):
            with fs.open_input_stream(info.path) as f:
                commits += map(json.loads, f.read().decode().splitlines())
    newest = max(r["epoch"] for r in commits if r["batch"] == OPENS)
    rows = sorted((r for r in commits if r["epoch"] == newest), key=lambda r: r["folders"])
    first = next(r for r in rows if r["batch"] == OPENS)
    covered = set(spread(first["covers"]))
    later = {r["batch"]: r["folders"] for r in rows if r["batch"] != OPENS and r["batch"] not in covered}
    wanted = None if reader.cells is None else {c % reader.buckets for c in reader.cells}
    out: list[InputPartition] = []
    for folder in [*first["folders"], *(f for b in sorted(later) for f in later[b])]:
        for info in fs.get_file_info(pafs.FileSelector(f"{root}/codes/{folder}", recursive=True)):
            if info.path.endswith(".parquet") and (wanted is None or int(info.path.split("cell_bucket=")[1].split("/")[0]) in wanted):
                out.append(_File(info.path, reader.cells))
    return out or [_File("", [])]


class IndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cfi"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        cells = self.options.get("cells")
        kind = _PushingReader if self.options.get("pushdown", "false").lower() == "true" else _Reader
        return kind(self.options["path"], int(self.options.get("buckets", 256)), [int(c) for c in cells.split(",")] if cells else None)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IndexSource)

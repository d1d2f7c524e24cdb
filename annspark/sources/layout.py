"""The index on storage: epochs of codes in cell order, centroids, and an append-only manifest.

    <path>/centroids/epoch=e                (cell, c)
    <path>/codes/epoch=e/batch=b/try=t      codes, partitioned by cell_bucket, sorted by cell inside files
    <path>/manifest                         JSON rows (epoch, batch, folders, rows, affinity, covers, meta), one file a commit

Nothing is edited in place: every write goes to a folder of its own, and counts once a manifest row names it. A row with batch -1 opens an
epoch: from then on it is the live one, and ``covers`` has every insert batch that its folders hold, as ranges. A later
row adds one batch to its epoch; of two rows for one batch, one counts, so replays change nothing.

A refresh stages the next epoch while the old one serves and takes inserts. It carries over the batches that came meanwhile, opens the new
epoch with all of them by one row, and looks once more for batches that were committed under the old one up to then. An insert, once
committed, looks whether another epoch was opened without it, and if so joins that too. So whichever of the two is last sees the other,
and no batch is lost; one that dies half-way is replayed by its stream. Refreshes themselves come one at a time. Everything
goes through Spark's readers and writers, so any store that Spark knows will do.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.operators import cfi, coarse

BUCKETS = 256
#: The batch number of an epoch's first folder, and of the manifest row that opens the epoch.
OPENS = -1
MANIFEST = "epoch int, batch long, folders array<string>, rows long, affinity double, covers array<array<long>>, meta string"
_STORED = "id long, cell long, code binary, sign binary, res_norm short, norm double, epoch int, batch long, try string, cell_bucket int"


@dataclass(frozen=True)
class Live:
    """The live epoch: its index, the folders that hold its codes, the insert batches in them, and what a refresh is decided by."""

    index: cfi.Index
    folders: tuple[str, ...]
    batches: frozenset[int]
    rows: int
    #: Mean coarse affinity when the epoch opened, and of the rows inserted since.
    affinity_then: float
    affinity_now: float


def ranges(numbers: Iterable[int]) -> list[list[int]]:
    """Sorted numbers as closed ranges, so that a long stream's batches stay a short list."""
    out: list[list[int]] = []
    for n in sorted(set(numbers)):
        if out and n == out[-1][1] + 1:
            out[-1][1] = n
        else:
            out.append([n, n])
    return out


def spread(covers: Iterable[Iterable[int]] | None) -> Iterator[int]:
    for lo, hi in covers or ():
        yield from range(lo, hi + 1)


def write_codes(codes: DataFrame, path: str, epoch: int, batch: int, buckets: int = BUCKETS) -> tuple[str, int, float]:
    """(folder, rows, mean coarse affinity): range-partitioned by bucket and cell and sorted, so that probes prune folders and row groups.

    For unit vectors and unit centroids the affinity is 1 - |residual|^2 / 2, so it is read off the codes.
    """
    folder = f"epoch={epoch}/batch={batch}/try={uuid.uuid4().hex[:12]}"
    placed = codes.drop("epoch").withColumn("cell_bucket", (F.col("cell") % buckets).cast("int"))
    placed.repartitionByRange("cell_bucket", "cell").sortWithinPartitions("cell_bucket", "cell").write.partitionBy("cell_bucket").parquet(f"{path}/codes/{folder}")
    r = _read(codes.sparkSession, path, [folder]).agg(F.count("*").alias("n"), F.avg(1 - F.col("norm") * F.col("norm") / 2).alias("a")).first()
    return folder, r.n, r.a or 0.0


def commit(spark: SparkSession, path: str, index: cfi.Index, batch: int, folders: list[str], rows: int, affinity: float, covers: list[list[int]], **more) -> None:
    meta = {"d": index.d, "b": index.b, "stage2": index.stage2, "seed": index.seed, "generation": index.generation, "exact_norm": index.exact_norm, "cells": index.cells} | more
    spark.createDataFrame([(index.epoch, batch, folders, rows, affinity, covers, json.dumps(meta))], MANIFEST).coalesce(1).write.mode("append").json(f"{path}/manifest")


def _centroids(spark: SparkSession, index: cfi.Index, path: str) -> None:
    coarse.to_frame(spark, index.c, index.epoch).drop("epoch").coalesce(1).write.mode("overwrite").parquet(f"{path}/centroids/epoch={index.epoch}")


def create(codes: DataFrame, index: cfi.Index, path: str, buckets: int = BUCKETS) -> None:
    """Write an epoch's first codes and centroids, then open it."""
    spark = codes.sparkSession
    _centroids(spark, index, path)
    folder, rows, affinity = write_codes(codes, path, index.epoch, OPENS, buckets)
    commit(spark, path, index, OPENS, [folder], rows, affinity, [], inserted=0)


def append(batch_rows: DataFrame, path: str, batch: int, buckets: int = BUCKETS) -> int:
    """Encode and add an insert batch under the live epoch, and return that epoch; the same batch again is the same state."""
    if batch < 0:
        raise ValueError("insert batches are numbered from 0")
    spark = batch_rows.sparkSession
    while batch not in (now := live(spark, path)).batches:  # looked at again after the commit: a refresh may have opened another epoch
        _add(spark, path, now.index, batch, cfi.encode(batch_rows, now.index), buckets)
    return now.index.epoch


def _add(spark: SparkSession, path: str, index: cfi.Index, batch: int, codes: DataFrame, buckets: int) -> None:
    folder, rows, affinity = write_codes(codes, path, index.epoch, batch, buckets)
    commit(spark, path, index, batch, [folder], rows, affinity, [[batch, batch]])


def manifest(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(MANIFEST).json(f"{path}/manifest")


def live(spark: SparkSession, path: str) -> Live:
    """The newest open epoch."""
    commits = manifest(spark, path)
    epoch = commits.where(F.col("batch") == OPENS).agg(F.max("epoch")).first()[0]
    if epoch is None:
        raise FileNotFoundError(f"no live epoch under {path}")
    return _state(spark, path, epoch)


def _state(spark: SparkSession, path: str, epoch: int) -> Live:
    rows = sorted(manifest(spark, path).where(F.col("epoch") == epoch).collect(), key=lambda r: r.folders)  # a row a commit
    first = next(r for r in rows if r.batch == OPENS)
    m, covered = json.loads(first.meta), frozenset(spread(first.covers))
    later = {r.batch: r for r in rows if r.batch != OPENS and r.batch not in covered}
    c = np.array([r.c for r in spark.read.parquet(f"{path}/centroids/epoch={epoch}").orderBy("cell").collect()], np.float64)
    new = sum(r.rows for r in later.values())
    index = cfi.Index(m["d"], m["b"], c, m["stage2"], m["seed"], epoch, m["generation"], m["exact_norm"], inserted=m["inserted"] + new)
    now = sum(r.rows * r.affinity for r in later.values()) / new if new else first.affinity
    folders = (*first.folders, *(f for b in sorted(later) for f in later[b].folders))
    return Live(index, folders, covered | later.keys(), first.rows + new, first.affinity, now)


def load(spark: SparkSession, path: str, cells: list[int] | None = None, buckets: int = BUCKETS) -> tuple[cfi.Index, DataFrame]:
    """(index, codes) of the live epoch; ``cells`` prunes buckets at planning and row groups by their statistics."""
    now = live(spark, path)
    codes = _read(spark, path, now.folders)
    if cells is not None:
        codes = codes.where(F.col("cell_bucket").isin(sorted({c % buckets for c in cells})) & F.col("cell").isin(cells))
    return now.index, codes


def _read(spark: SparkSession, path: str, folders: Iterable[str]) -> DataFrame:
    return spark.read.schema(_STORED).option("basePath", f"{path}/codes").parquet(*(f"{path}/codes/{f}" for f in folders))


def refresh(spark: SparkSession, path: str, raw: DataFrame | None = None, buckets: int = BUCKETS, **options) -> cfi.Index:
    """Stage the next epoch, carry over the batches that came meanwhile, open it by one manifest row; returns its index."""
    from annspark.operators import refresh as rf

    then = live(spark, path)
    old = then.index
    new, recoded = rf.run(old, _read(spark, path, then.folders), raw, **options)
    _centroids(spark, new, path)
    folder, rows, affinity = write_codes(recoded, path, new.epoch, OPENS, buckets)
    folders, late, batches = [folder], 0, set(then.batches)

    def arrived() -> list[tuple[int, DataFrame]]:
        """Batches of the old epoch that are not in the new one, encoded for it."""
        out = []
        state = _state(spark, path, old.epoch)
        for f in state.folders:
            if (batch := int(f.split("batch=")[1].split("/")[0])) != OPENS and batch not in batches:
                part = _read(spark, path, [f])
                vectors = raw.join(part.select("id"), "id", "left_semi") if raw is not None else cfi.reconstruct(part, old)
                out.append((batch, cfi.encode(vectors, new)))
        return out

    while came := arrived():
        for batch, codes in came:
            folder, n, _ = write_codes(codes, path, new.epoch, batch, buckets)
            late += n
            folders.append(folder)
            batches.add(batch)
    commit(spark, path, new, OPENS, folders, rows + late, affinity, ranges(batches), inserted=late)
    for batch, codes in arrived():  # committed between the last look and the opening
        if batch not in live(spark, path).batches:
            _add(spark, path, new, batch, codes, buckets)
    return live(spark, path).index

"""Shared plumbing of the training-data operators."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word, everywhere in this subpackage: a maximal run without ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage by a reliable checkpoint in the folder that the session names (spark.checkpoint.dir).

    Only where no folder is set and the master is local, as in tests, a temporary one is used. The rows are then in the checkpoint, so the shuffle
    files that made them are let go (a setting of the session that can be set at any time, and is put back).
    """
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not folder and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="annspark-ckpt-"))
    conf, name = df.sparkSession.conf, "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = conf.get(name, None)
    conf.set(name, "true")
    try:
        return df.select("*").checkpoint(eager=True)  # a new plan, made under the setting
    finally:
        conf.unset(name) if before is None else conf.set(name, before)


def shuffle_parts(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def texts(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    """Whole texts of a batch; null reads as the empty text."""
    return [t or "" for t in batch.column(batch.schema.get_field_index(name)).to_pylist()]


def sliced(batches: Iterator[pa.RecordBatch], rows: int = 1_000) -> Iterator[pa.RecordBatch]:
    """Batches cut in slices, without a copy, so that a kernel holds Python objects of few rows at a time."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def salted(*cols: Column, salt: str) -> Column:
    """A seeded 64-bit hash; nulls hash like any other value."""
    return F.xxhash64(F.lit(salt), *cols)


def shielded(docs: DataFrame, own: tuple[str, ...]) -> tuple[DataFrame, list[str]]:
    """docs with every column but ``own`` renamed by its place, so that no name that an operator uses can clash; and the names to restore, in order."""
    names = [c if c in own else f"_extra_{i}" for i, c in enumerate(docs.columns)]
    return docs.toDF(*names), names


def restored(df: DataFrame, names: list[str], originals: list[str]) -> DataFrame:
    """The columns ``names`` of df under their original names."""
    return df.select(*names).toDF(*originals)

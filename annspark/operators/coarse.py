"""Spherical k-means partitions: the only trained part of the codebook-free index.

Vectors have schema (id LONG, v ARRAY<DOUBLE>), unit norm. Sums are fixed-point integers, so that centroids do not
depend on how rows are partitioned: a coordinate counts as round(x * 1e9), and integer sums are associative.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.functions import codes as pk
from annspark.functions.vectors import matrix

FIXED = 1e9


def seeded_order(seed: int, col: str = "id"):
    """A seeded order that other engines share: the MD5 of 'seed:id'."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(col).cast("string")).cast("binary"))


def initial(df: DataFrame, cells: int, seed: int) -> np.ndarray:
    """The first rows in seeded order."""
    rows = df.select("id", "v").orderBy(seeded_order(seed), "id").limit(cells).collect()
    return np.array([r.v for r in rows], np.float64)


def nearest(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(cell, inner product) by largest inner product, ties to the lower cell; in blocks of bounded size."""
    cell, ip = np.zeros(len(x), np.int64), np.zeros(len(x))
    step = max(1, 4_000_000 // max(1, len(c)))
    for a in range(0, len(x), step):
        s = x[a : a + step] @ c.T
        k = s.argmax(axis=1)
        cell[a : a + step], ip[a : a + step] = k, s[np.arange(len(k)), k]
    return cell, ip


def normalised(sums: np.ndarray, old: np.ndarray) -> np.ndarray:
    n = np.sqrt((sums * sums).sum(axis=1, keepdims=True))
    return np.where(n > 0, sums / np.where(n > 0, n, 1), old)


def step(df: DataFrame, c: np.ndarray) -> np.ndarray:
    """One round: per-task fixed-point sums, added per cell; an empty cell keeps its centroid."""
    d = c.shape[1]

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n = np.zeros(c.shape, np.int64), np.zeros(len(c), np.int64)
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(0))
                cell, _ = nearest(x, c)
                by = np.argsort(cell, kind="stable")
                start = np.flatnonzero(np.diff(cell[by], prepend=-1))
                sums[cell[by[start]]] += np.add.reduceat(np.rint(x[by] * FIXED).astype(np.int64), start, axis=0)
                n += np.bincount(cell, minlength=len(c))
        some = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pk.to_binary(sums[some].view(np.uint8))], names=["cell", "sums"])

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for b in batches:
            if b.num_rows:
                for k, v in zip(b.column(0).to_pylist(), pk.from_binary(b.column(1), 8 * d).view(np.int64), strict=True):
                    total[k] = total[k] + v if k in total else v.copy()
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(total, pa.int64()), pk.to_binary(np.stack(list(total.values())).view(np.uint8))], names=["cell", "sums"])

    # a row of bytes a cell: a column for each coordinate takes longer to plan than to add
    kind = "cell long, sums binary"
    got = df.select("v").mapInArrow(part, kind).repartition("cell").mapInArrow(whole, kind).toArrow().combine_chunks()  # a row a cell
    out = c.copy()
    if got.num_rows:
        at = got.column("cell").to_numpy()
        sums = np.array([np.frombuffer(x, np.int64) for x in got.column("sums").to_pylist()], np.float64)
        out[at] = normalised(sums, c[at])
    return out


def fit(df: DataFrame, cells: int, iters: int = 10, seed: int = 42, init: np.ndarray | None = None) -> np.ndarray:
    """Centroids (cells x d) of all rows after a fixed number of rounds; ``init`` warm-starts."""
    df = df.select("id", "v").persist()
    try:
        c = initial(df, cells, seed) if init is None else np.asarray(init, np.float64)
        for _ in range(iters):
            c = step(df, c)
        return c
    finally:
        df.unpersist()


def fit_two_level(df: DataFrame, upper: int, lower: int, iters: int = 10, seed: int = 42) -> np.ndarray:
    """upper x lower cells from two rounds of small fits: assignment costs upper + lower products a vector instead of their product.

    Each upper cell is split by its own fit on a bounded sample of its rows, inside one task.
    """
    top = fit(df, upper, iters, seed)
    held = assign(df, top, carry=True)
    quota = 64 * lower
    from pyspark.sql import Window

    ranked = held.withColumn("_r", F.row_number().over(Window.partitionBy("cell").orderBy(seeded_order(seed), "id"))).where(F.col("_r") <= quota)

    def split(t: pa.Table) -> pa.Table:
        x = matrix(t.column("v"))
        c = x[:lower]
        for _ in range(iters):
            cell, _ = nearest(x, c)
            sums = np.zeros(c.shape)
            np.add.at(sums, cell, np.rint(x * FIXED))
            c = normalised(sums, c)
        return pa.table({"cell": pa.array([t.column("cell")[0].as_py()] * len(c), pa.int64()), "sub": pa.array(range(len(c)), pa.int32()), "v": pa.array(c.tolist(), pa.list_(pa.float64()))})

    rows = ranked.select("cell", "v").groupBy("cell").applyInArrow(split, "cell long, sub int, v array<double>").orderBy("cell", "sub").collect()
    return np.array([r.v for r in rows], np.float64)


def assign(df: DataFrame, c: np.ndarray, carry: bool = False) -> DataFrame:
    """(id, cell, ip[, v]): map-only, centroids travel with the closure (Spark broadcasts it)."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cell, ip = nearest(matrix(b.column(1)), c)
                cols = [b.column(0), pa.array(cell, pa.int64()), pa.array(ip)]
                yield pa.RecordBatch.from_arrays([*cols, b.column(1)] if carry else cols, names=["id", "cell", "ip", "v"][: 3 + carry])

    return df.select("id", "v").mapInArrow(go, "id long, cell long, ip double" + ", v array<double>" * carry)


def to_frame(spark: SparkSession, c: np.ndarray, epoch: int = 0) -> DataFrame:
    return spark.createDataFrame([(epoch, i, v.tolist()) for i, v in enumerate(c)], "epoch int, cell int, c array<double>")

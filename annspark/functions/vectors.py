"""Vector columns: native expressions, and the bridge from Arrow columns to matrices.

Expressions take array columns of any numeric element and work in double. They are for moderate data and for
plans that must stay inside Catalyst; the heavy kernels of the operators read Arrow batches as matrices.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Vec = Column | str


def _col(v: Vec) -> Column:
    return F.col(v) if isinstance(v, str) else v


def doubles(v: Vec) -> Column:
    return _col(v).cast("array<double>")


def total(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0).cast("double"), lambda a, x: a + x)


def dot(a: Vec, b: Vec) -> Column:
    return total(F.zip_with(doubles(a), doubles(b), lambda x, y: x * y))


def norm(v: Vec) -> Column:
    return F.sqrt(dot(v, v))


def cosine(a: Vec, b: Vec) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def l2(a: Vec, b: Vec) -> Column:
    return F.sqrt(total(F.zip_with(doubles(a), doubles(b), lambda x, y: (x - y) * (x - y))))


def add(a: Vec, b: Vec) -> Column:
    return F.zip_with(doubles(a), doubles(b), lambda x, y: x + y)


def scale(v: Vec, k: Column | float) -> Column:
    k = F.lit(k) if isinstance(k, (int, float)) else k
    return F.transform(doubles(v), lambda x: x * k)


def unit(v: Vec) -> Column:
    """v / |v|, nulls for a zero vector; the norm is computed once per row."""
    return F.transform(F.array(F.struct(doubles(v).alias("v"), norm(v).alias("n"))), lambda s: F.transform(s["v"], lambda x: F.try_divide(x, s["n"])))[0]


def is_bad(v: Vec, d: int | None = None) -> Column:
    """Null, wrong size, null or non-finite component, or zero norm: such rows go to quarantine."""
    c = doubles(v)
    odd = F.exists(c, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) | ~F.exists(c, lambda x: x != 0)
    wrong = F.size(c) != d if d is not None else F.lit(False)
    return F.coalesce(c.isNull() | wrong | odd, F.lit(True))


def normalise(df: DataFrame, col: str = "v", d: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(rows with a unit vector in ``col``, quarantined rows as they were)."""
    bad = is_bad(col, d)
    return df.where(~bad).withColumn(col, unit(col)), df.where(bad)


def mean(df: DataFrame, by: list[str], col: str = "v") -> DataFrame:
    """Component means per group, by posexplode and partial sums."""
    parts = df.select(*by, F.posexplode(doubles(col)).alias("j", "x")).groupBy(*by, "j").agg(F.avg("x").alias("x"))
    return parts.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda s: s["x"]).alias(col))


def matrix(column: pa.Array | pa.ChunkedArray, kind: type = np.float64) -> np.ndarray:
    """A list column as an n x d matrix, of doubles unless ``kind`` says otherwise."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(kind, copy=False)
    return flat.reshape(n, -1) if n else flat.reshape(0, 0)


def as_lists(m: np.ndarray, kind: pa.DataType | None = None) -> pa.Array:
    n, d = m.shape
    values = pa.array(np.ascontiguousarray(m).ravel(), kind or pa.float64())
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * d + 1, max(d, 1), dtype=np.int32)[: n + 1]), values)


def rows_matrix(rows: Iterable, col: str = "v") -> np.ndarray:
    return np.array([r[col] for r in rows], np.float64)

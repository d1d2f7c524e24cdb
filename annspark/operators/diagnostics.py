"""Why a partition helps a scalar quantizer: measured and predicted error ratios."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.operators import cfi


def amplification(df: DataFrame, index: cfi.Index, queries: DataFrame) -> DataFrame:
    """One row (affinity, predicted, flat_error, partitioned_error, measured): squared inner-product errors of the flat and the partitioned
    quantizer over the same vectors and queries; predicted is 2 (1 - mean affinity). Above 1 the partition hurts."""
    flat = cfi.inner_error(df, replace(index, c=None), queries).select(F.col("ip_mse").alias("flat_error"))
    part = cfi.inner_error(df, index, queries).select("affinity", F.col("ip_mse").alias("partitioned_error"))
    return part.crossJoin(flat).select("affinity", (2 * (1 - F.col("affinity"))).alias("predicted"), "flat_error", "partitioned_error", (F.col("partitioned_error") / F.col("flat_error")).alias("measured"))

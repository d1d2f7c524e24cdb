"""Partition-only refresh: new centroids from a stratified sample, then one pass that assigns and encodes anew.

Rotation and quantizer stay. Vectors come from the raw table or, without one, from the codes themselves;
each self-contained refresh quantizes an already quantized vector, so errors add up over generations: the index
counts them and ``run`` refuses beyond ``most_generations``.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from annspark.operators import cfi, coarse

#: Slices of a cell's seeded order are made so that each holds about as many rows as there are slices, and this many at least.
SLICE = 512


def sample(codes: DataFrame, size: int, seed: int = 42) -> DataFrame:
    """(cell, id): proportional to cell sizes, one a cell at least, in seeded order.

    No cell is sorted as a whole. Its seeded order, a uniform hash, is cut in slices that are counted first: those that lie under the cell's quota
    as a whole are taken by a filter, and only the slice in which the quota ends is ranked. Hot cells are so spread over tasks.
    """
    keyed = codes.select("cell", "id", coarse.seeded_order(seed).alias("o"))
    sizes = codes.groupBy("cell").agg(F.count("*").alias("n"))
    total = sizes.agg(F.sum("n")).first()[0] or 0
    share = min(1.0, size / max(total, 1))
    quotas = sizes.select("cell", F.greatest(F.lit(1), F.ceil(F.col("n") * F.lit(share))).alias("quota"), F.greatest(F.lit(1), F.least(F.sqrt("n"), F.col("n") / SLICE)).cast("long").alias("slices"))
    # the first 28 bits of the order as a share of the cell
    at = F.conv(F.substring("o", 1, 7), 16, 10).cast("long")
    sliced = keyed.join(F.broadcast(quotas), "cell").withColumn("slice", F.shiftright(at * F.col("slices"), 28))
    counts = sliced.groupBy("cell", "slice").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("cell").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # a row a slice: sqrt(n) of a cell at most
    taken = counts.withColumn("before", before).join(F.broadcast(quotas.select("cell", "quota")), "cell").where("before < quota").select("cell", "slice", (F.col("quota") - F.col("before")).alias("left"), (F.col("quota") - F.col("before") >= F.col("n")).alias("whole"))
    some = sliced.join(taken, ["cell", "slice"])
    w = Window.partitionBy("cell", "slice").orderBy("o", "id")
    last = some.where("NOT whole").withColumn("r", F.row_number().over(w)).where("r <= left")
    return some.where("whole").select("cell", "id").unionByName(last.select("cell", "id"))


@dataclass(frozen=True)
class Trigger:
    """When to refresh: after so many inserted rows, or when mean coarse affinity has dropped so far."""

    every: int | None = None
    affinity_drop: float | None = None

    def due(self, inserted: int, affinity_then: float = 0.0, affinity_now: float = 0.0) -> bool:
        return (self.every is not None and inserted >= self.every) or (self.affinity_drop is not None and affinity_then - affinity_now >= self.affinity_drop)


def run(index: cfi.Index, codes: DataFrame, raw: DataFrame | None = None, size: int | None = None, cells: int | None = None, iters: int = 10, seed: int = 42, most_generations: int = 3) -> tuple[cfi.Index, DataFrame]:
    """(index, codes) of the next epoch; ``raw`` None is the self-contained way."""
    if raw is None and index.generation >= most_generations:
        raise ValueError("too many self-contained refreshes of one index: errors add up; give raw vectors")
    cells = cells or index.cells
    n = codes.count()
    size = size or max(64 * cells, n // 10)
    vectors = raw.select("id", "v").join(codes.select("id"), "id", "left_semi") if raw is not None else cfi.reconstruct(codes, index)
    chosen = vectors.join(sample(codes, size, seed).select("id"), "id", "left_semi")
    c = coarse.fit(chosen, cells, iters, seed)
    new = replace(index, c=c, epoch=index.epoch + 1, generation=index.generation + (raw is None), inserted=0)
    return new, cfi.encode(vectors, new)

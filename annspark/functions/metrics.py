"""Measures of search results, as DataFrame aggregations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from annspark.functions.vectors import dot


def recall(found: DataFrame, truth: DataFrame, k: int = 10, by: tuple[str, ...] = ()) -> DataFrame:
    """([by,] recall): share of the true k that were found, averaged over the queries of the truth."""
    keys = [*by, "qid"]
    hit = truth.where(F.col("rank") <= k).select(*keys, "id").join(found.where(F.col("rank") <= k).select(*keys, "id", F.lit(1).alias("hit")), [*keys, "id"], "left")
    per_query = hit.groupBy(*keys).agg((F.sum(F.coalesce("hit", F.lit(0))) / k).alias("r"))
    return per_query.groupBy(*by).agg(F.avg("r").alias("recall"))


def recall_ties(found: DataFrame, truth: DataFrame, k: int = 10, slack: float = 1e-9) -> DataFrame:
    """As recall, but a found row counts if its exact score reaches the k-th true score: copies are as good as each other.

    ``found`` carries exact scores (after a re-rank).
    """
    bar = truth.where(F.col("rank") <= k).groupBy("qid").agg(F.min("score").alias("bar"))
    good = bar.join(found.where(F.col("rank") <= k).select("qid", "score"), "qid", "left")
    per_query = good.groupBy("qid").agg((F.sum(F.when(F.col("score") >= F.col("bar") - slack, 1).otherwise(0)) / k).alias("r"))
    return per_query.agg(F.avg("r").alias("recall"))


def delta(runs: DataFrame, by: list[str]) -> DataFrame:
    """(by, delta): last batch's recall less the first's, in percentage points."""
    return runs.groupBy(*by).agg(((F.max_by("value", "batch") - F.min_by("value", "batch")) * 100).alias("delta"))


def gap(runs: DataFrame, by: list[str], a: str, b: str) -> DataFrame:
    """(by, gap): recall of method a less that of b, in percentage points."""
    return runs.groupBy(*by).pivot("method", [a, b]).agg(F.first("value")).select(*by, ((F.col(a) - F.col(b)) * 100).alias("gap"))


def partition_health(codes: DataFrame, cells: int) -> DataFrame:
    """One row: occupied and empty cells, smallest and largest, skew (largest over mean), and mean affinity if there is an ip."""
    sizes = codes.groupBy("cell").agg(F.count("*").alias("n"), *([F.sum("ip").alias("ip")] if "ip" in codes.columns else []))
    more = [(F.sum("ip") / F.sum("n")).alias("affinity")] if "ip" in codes.columns else []
    return sizes.agg(F.count("*").alias("occupied"), (F.lit(cells) - F.count("*")).alias("empty"), F.min("n").alias("smallest"), F.max("n").alias("largest"), (F.max("n") / (F.sum("n") / cells)).alias("skew"), *more)


def swap_cosine(old: DataFrame, new: DataFrame) -> DataFrame:
    """(n, mean, sd) of the cosines of shared ids under two encoders (unit vectors)."""
    j = old.select("id", F.col("v").alias("a")).join(new.select("id", F.col("v").alias("b")), "id").select(dot("a", "b").alias("c"))
    return j.agg(F.count("*").alias("n"), F.avg("c").alias("mean"), F.stddev_samp("c").alias("sd"))


def pareto(points: DataFrame, cost: str = "cost", value: str = "value") -> DataFrame:
    """The points that no other beats on cost and value, equal points all; one partition of a report-sized table."""
    below = F.max(value).over(Window.orderBy(F.col(cost)).rangeBetween(Window.unboundedPreceding, Window.currentRow))
    cheaper = F.min(F.struct(value, cost)).over(Window.partitionBy(F.col(value)))
    ranked = points.withColumn("_best", below).withColumn("_least", cheaper[cost])
    return ranked.where((F.col(value) >= F.col("_best")) & (F.col(cost) <= F.col("_least"))).drop("_best", "_least")


def bias_capacity(runs: DataFrame) -> DataFrame:
    """(dataset, bias, capacity): random-sample less first-rows recall, and all-rows less random-sample recall, in points."""
    p = runs.groupBy("dataset").pivot("method", ["first", "random", "all"]).agg(F.avg("value"))
    return p.select("dataset", ((F.col("random") - F.col("first")) * 100).alias("bias"), ((F.col("all") - F.col("random")) * 100).alias("capacity"))


def qps(queries: int, seconds: float) -> float:
    return queries / seconds if seconds > 0 else float("inf")

"""The experiments, re-expressed on the given tables. Each returns rows of one schema:

    workload, dataset, method, regime, seed, batch, metric, value

Recall is of 10 neighbours against exact truth of the cumulative table. Defaults are sized for a check on small tables; the full
protocols take ``seeds=SEEDS`` and the wider grids through their keywords. Seconds are reported as cost, never compared
across machines; rows encoded again are the machine-independent cost.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterable
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.functions import bounds, cost, metrics, rotation, scalarq, stats
from annspark.functions.vectors import matrix
from annspark.operators import cfi, coarse, diagnostics, exact, graph, lsh, pq, refresh
from annspark.sources import datasets as ds

SEEDS = (42, 123, 7777)
SCHEMA = "workload string, dataset string, method string, regime string, seed long, batch long, metric string, value double"
K = 10


class Runs:
    """Collected measurements of one workload."""

    def __init__(self, workload: str):
        self.workload, self.rows = workload, []

    def add(self, dataset: str, method: str, value: float, metric: str = "recall", regime: str = "", seed: int = 42, batch: int = -1) -> None:
        self.rows.append((self.workload, dataset, method, regime, seed, batch, metric, float(value)))

    def by_batch(self, dataset: str, method: str, frame: DataFrame, **more) -> None:
        for r in frame.collect():  # a row a batch
            self.add(dataset, method, r.recall, batch=r.batch, **more)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)


def vectors(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """E, A(alpha), D(d) or P(d)."""
    kind, _, arg = name.rstrip(")").partition("(")
    if kind == "E":
        return ds.embeddings(spark, sf_dir)
    if kind == "A":
        return ds.anchored(spark, sf_dir, float(arg))
    return (ds.documents if kind == "D" else ds.pages)(spark, sf_dir, int(arg))


def gathered(df: DataFrame, n: int, d: int) -> DataFrame:
    """The same rows in partitions of 32 MB, or two a core if those are more: a scan sends k rows a query from each."""
    return df.coalesce(parts(df.sparkSession, n, d))


def parts(spark: SparkSession, n: int, d: int) -> int:
    return max(2 * spark.sparkContext.defaultParallelism, n * d * 8 >> 25)


def batched(base: DataFrame, n: int, d: int, first: float, batches: int, *order) -> DataFrame:
    """``ds.batches``, kept, in as many partitions as a scan wants: small shuffles are else read by a task or two."""
    return ds.batches(base, first, batches, *order).repartition(parts(base.sparkSession, n, d), "id").persist()


def load(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame, int, int]:
    """(base, queries, d, cells): cells is the power of two nearest the root of n."""
    # kept: base and queries are read many times, and hashing texts into vectors is the dearest step
    base, q = ds.split(vectors(spark, sf_dir, name).persist())
    n, d = base.count(), len(base.select("v").first().v)
    cells = 1 << max(1, round(math.log2(math.sqrt(n))))
    if base.rdd.getNumPartitions() < parts(spark, n, d):
        return base.repartition(parts(spark, n, d), "id").persist(), q, d, cells
    return gathered(base, n, d), q, d, cells


def _recall(found: DataFrame, truth: DataFrame) -> float:
    return metrics.recall(found, truth, K).first().recall


def _cfi(base, q, truth, d, cells, n_p, b=4, stage2="sign", seed=42, fit_on=None, **more) -> float:
    index, codes = cfi.build(base, cells, b, stage2, seed, d=d, fit_on=fit_on, **more)
    return _recall(cfi.search(codes, index, q, K, n_p), truth)


def w01_matched_memory(spark, sf_dir, sets: Iterable[str] = ("E", "A(2.5)", "D(96)", "D(100)"), totals=(4, 5, 6), seed: int = 42) -> DataFrame:
    """Stage 1 at B bits against B - 1 bits and refinement, at equal memory; paired t over the cells."""
    runs, plain, refined = Runs("w01"), [], []
    for s in sets:
        base, q, d, cells = load(spark, sf_dir, s)
        truth, c = exact.knn(base, q, K).persist(), coarse.fit(base, cells, 10, seed)
        for total in totals:
            both = []
            for b, stage2 in ((total, "none"), (total - 1, "sign")):
                index = cfi.Index(d, b, c, stage2, seed)
                codes = cfi.encode(base, index).persist()  # read by each wave of queries
                both.append(_recall(cfi.search(codes, index, q, K, max(1, cells // 4)), truth))
                codes.unpersist()
            runs.add(s, "xbq", both[0], regime=f"B={total}", seed=seed)
            runs.add(s, "cfi", both[1], regime=f"B={total}", seed=seed)
            runs.add(s, "cfi-xbq", 100 * (both[1] - both[0]), "delta_pp", f"B={total}", seed)
            if s != "E":
                plain.append(both[0])
                refined.append(both[1])
    if len(plain) > 1:
        m, half, p = stats.paired_t(refined, plain)
        for name, v in (("mean_pp", 100 * m), ("half_pp", 100 * half), ("p", p)):
            runs.add("all", "cfi-xbq", v, name, seed=seed)
    return runs.frame(spark)


def w02_amplification(spark, sf_dir, sets=("E", "A(1.5)", "A(2.5)", "D(96)"), seed: int = 42) -> DataFrame:
    """Flat against partitioned: recall of both, error ratio as predicted and as measured."""
    runs = Runs("w02")
    for s in sets:
        base, q, d, cells = load(spark, sf_dir, s)
        truth = exact.knn(base, q, K).persist()
        runs.add(s, "rsq", _cfi(base, q, truth, d, 0, 0, seed=seed), seed=seed)
        index, codes = cfi.build(base, cells, 4, "sign", seed, d=d)
        runs.add(s, "cfi", _recall(cfi.search(codes, index, q, K, cells), truth), seed=seed)
        r = diagnostics.amplification(base, index, q).first()
        for m in ("affinity", "predicted", "measured"):
            runs.add(s, "cfi", r[m], m, seed=seed)
    return runs.frame(spark)


def w03_flat_stage2(spark, sf_dir, sets=("E", "A(2.5)"), bits=(3,), seed: int = 42) -> DataFrame:
    runs = Runs("w03")
    for s in sets:
        base, q, d, _ = load(spark, sf_dir, s)
        truth = exact.knn(base, q, K).persist()
        for b in bits:
            for stage2 in cfi.STAGES:
                runs.add(s, f"rsq_{stage2}", _cfi(base, q, truth, d, 0, 0, b, stage2, seed), regime=f"b={b}", seed=seed)
    return runs.frame(spark)


def w04_learned_ceiling(spark, sf_dir, sets=("A(2.5)",), ms=(8, 16, 32, 64), bits: int = 4, seed: int = 42) -> DataFrame:
    """Recall of the learned index with every cell probed, by number of sub-spaces; the ratio of training rows to codes beside it."""
    runs = Runs("w04")
    for s in sets:
        base, q, d, cells = load(spark, sf_dir, s)
        truth, c = exact.knn(base, q, K).persist(), coarse.fit(base, cells, 5, seed)
        n = base.count()
        for m in ms:
            cb = pq.fit(base, m, bits, cells, c=c, iters=5, seed=seed)
            runs.add(s, "ivpq", _recall(pq.search(pq.encode(base, cb), cb, q, K, cells), truth), regime=f"m={m}", seed=seed)
            runs.add(s, "ivpq", n / (1 << bits), "rows_per_code", f"m={m}", seed)
    return runs.frame(spark)


def w05_probes(spark, sf_dir, sets=("E", "A(2.5)"), seed: int = 42) -> DataFrame:
    runs = Runs("w05")
    for s in sets:
        base, q, d, cells = load(spark, sf_dir, s)
        truth = exact.knn(base, q, K).persist()
        index, codes = cfi.build(base, cells, 4, "sign", seed, d=d)
        n_p = 1
        while n_p <= cells:
            runs.add(s, "cfi", _recall(cfi.search(codes, index, q, K, n_p), truth), regime=f"n_p={n_p}", seed=seed)
            n_p *= 2
    return runs.frame(spark)


def _arms(runs: Runs, s: str, base: DataFrame, q: DataFrame, d: int, b: DataFrame, seed: int, m: int, bits: int, regime: str, retrain: tuple[int, ...] = (1,), methods=("cfi", "stale", "retrain", "ceiling", "rsq")) -> None:
    """One streaming cell: b has a batch column; partition and codebooks are fitted on batch 0.

    ceiling is exact search in the probed cells; rsq is the data-free flat arm. Both fall as the table grows denser, which is not staleness.
    """
    first = b.where("batch = 0").select("id", "v").persist()
    sizes = {r.batch: r["count"] for r in b.groupBy("batch").count().collect()}
    n0, last = sizes.get(0, 0), max(sizes)
    cells = 1 << max(1, round(math.log2(math.sqrt(n0))))
    n_p = max(1, cells // 4)
    truth = exact.knn_cumulative(b, q, K).persist()
    c = coarse.fit(first, cells, 10, seed)

    known = b.sparkSession.createDataFrame([(i,) for i in sorted(sizes)], "batch int")  # what is found is not searched again for its batches

    def upto(found: DataFrame) -> DataFrame:
        return metrics.recall(exact.accumulate(found.drop("rank"), K, known), truth, K, ("batch",))

    for name, index in (("cfi", cfi.Index(d, 4, c, "sign", seed)), ("rsq", cfi.Index(d, 4, None, "sign", seed))):
        if name in methods:
            t = time.time()
            codes = cfi.encode(b, index, "batch")
            runs.by_batch(s, name, upto(cfi.search(codes, index, q, K, n_p, extra="batch", limit=1 << 40)), regime=regime, seed=seed)
            runs.add(s, name, time.time() - t, "seconds", regime, seed)
    if "ceiling" in methods:
        probes = cfi.probes_frame(cfi.Index(d, 1, c), q, n_p).select("qid", "cell")
        near = coarse.assign(b, c).select("id", "cell").join(F.broadcast(probes), "cell").select("qid", "id")
        all_truth = exact.knn_cumulative(b, q, K)
        runs.by_batch(s, "ceiling", metrics.recall(all_truth.join(near, ["qid", "id"], "left_semi"), truth, K, ("batch",)), regime=regime, seed=seed)
    if "stale" in methods or "retrain" in methods:
        cb = pq.fit(first, m, bits, cells, c=c, iters=5, seed=seed)
    if "stale" in methods:
        codes = pq.encode(b, cb, "batch")
        runs.by_batch(s, "stale", upto(pq.search(codes, cb, q, K, n_p, extra="batch")), regime=regime, seed=seed)
        runs.add(s, "stale", n0 / (1 << bits), "rows_per_code", regime, seed)
    if "retrain" in methods:
        for period in retrain:
            name, due, t = "retrain" if period == 1 else f"retrain_{period}", [i for i in range(1, last + 1) if i % period == 0], time.time()
            again = dict(zip(due, pq.retrain(b, cb, bits, "codebook", 5, seed, upto=due), strict=True))
            spent, now, found = time.time() - t, cb, []
            for i in range(last + 1):
                now, codes = again.get(i) or (now, pq.encode(b.where(F.col("batch") <= i), now))
                found.append(pq.search(codes, now, q, K, n_p).withColumn("batch", F.lit(i)))
            runs.by_batch(s, name, metrics.recall(exact.united(found), truth, K, ("batch",)), regime=regime, seed=seed)
            runs.add(s, name, spent, "seconds", regime, seed)
            runs.add(s, name, sum(n for i in due for at, n in sizes.items() if at <= i), "rows_reencoded", regime, seed)
    first.unpersist()
    truth.unpersist()


def w06_streaming_small(spark, sf_dir, s: str = "A(2.5)", orders=("id", "shuffled"), seeds=(42,), m: int = 64, bits: int = 5, n: int = 8) -> DataFrame:
    """A fifth first, then eight equal batches, in the given and in shuffled order; learned codes have the memory of the index."""
    runs = Runs("w06")
    base, q, d, _ = load(spark, sf_dir, s)
    for order in orders:
        for seed in seeds:
            _arms(runs, s, base, q, d, batched(base, base.count(), d, 0.2, n, order, seed), seed, m, bits, order, methods=("cfi", "stale", "retrain", "rsq"))
    return runs.frame(spark)


#: (d, sub, bit-matched, super) as (m, bits); the narrow ones keep the budgets with codebooks that small tables can train.
REGIMES = {96: ((48, 8), (48, 10), (96, 8)), 128: ((64, 8), (64, 10), (128, 8)), 200: ((100, 8), (100, 10), (200, 8))}
NARROW = {d: ((d, 4), (d, 5), (d, 8)) for d in REGIMES}


def w07_nine_cells(spark, sf_dir, dims=(96, 128, 200), regimes=("sub", "bit", "super"), seeds=SEEDS, n: int = 9, narrow: bool | None = None, methods=("cfi", "stale", "retrain", "ceiling")) -> DataFrame:
    """A tenth first, then n equal batches; three dimensions by three memory regimes by three seeds.

    narrow: False takes REGIMES, True takes NARROW and a fifth first; None takes REGIMES and, where the first batch has fewer rows than
    a codebook has codes, NARROW beside it."""
    runs = Runs("w07")
    for d in dims:
        s = f"D({d})"
        base, q, _, _ = load(spark, sf_dir, s)
        for seed in seeds:
            b = batched(base, base.count(), d, 0.2 if narrow else 0.1, n, "shuffled", seed)
            n0 = b.where("batch = 0").count()
            for name in regimes:
                wide, slim = (x[d][("sub", "bit", "super").index(name)] for x in (REGIMES, NARROW))
                chosen = (slim if narrow else wide,) if narrow is not None else (wide, slim) if n0 < 1 << wide[1] and slim != wide else (wide,)
                for m, bits in chosen:
                    _arms(runs, s, base, q, d, b, seed, m, bits, f"{name} m={m} b={bits} x{cost.regime(m, bits, d):.2f}", methods=methods)
            b.unpersist()
    out = runs.frame(spark)
    change = metrics.delta(out.where("metric = 'recall'"), ["workload", "dataset", "method", "regime", "seed"])
    return out.unionByName(change.select("workload", "dataset", "method", "regime", "seed", F.lit(-1).cast("long").alias("batch"), F.lit("delta_pp").alias("metric"), F.col("delta").alias("value")))


def w08_orders(spark, sf_dir, seeds=(42,), n: int = 3) -> DataFrame:
    """Given order, shuffled, and real drift (by language): change of recall under each."""
    runs, s = Runs("w08"), "D(96)"
    base, q, d, _ = load(spark, sf_dir, s)
    lang = ds.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "lang")
    for seed in seeds:
        for order in ("id", "shuffled", "drift"):
            _arms(runs, s, base, q, d, batched(base, base.count(), d, 0.2, n, order, seed, lang), seed, d, 5, order, methods=("cfi", "stale", "retrain"))
    return runs.frame(spark)


def w09_bias_capacity(spark, sf_dir, s: str = "D(96)", m: int = 96, bits: int = 5, seeds=(42,)) -> DataFrame:
    """Codebooks from the first rows, as many random rows, or all: bias is random less first, capacity all less random."""
    runs = Runs("w09")
    base, q, d, cells = load(spark, sf_dir, s)
    truth, n = exact.knn(base, q, K).persist(), base.count()
    for seed in seeds:
        c = coarse.fit(base, cells, 5, seed)
        # ids alone are put in order, and the vectors of the chosen rows are kept where they are
        first = base.join(base.select("id").orderBy("id").limit(n // 5), "id", "left_semi").persist()
        chance = base.join(base.select("id").orderBy(coarse.seeded_order(seed), "id").limit(n // 5), "id", "left_semi").persist()
        for name, rows in (("first", first), ("random", chance), ("all", base)):
            cb = pq.fit(rows, m, bits, cells, c=c, iters=5, seed=seed)
            codes = pq.encode(base, cb).persist()  # read by each wave of queries
            runs.add(s, name, _recall(pq.search(codes, cb, q, K, cells), truth), seed=seed)
            codes.unpersist()
        first.unpersist()
        chance.unpersist()
    out = runs.frame(spark)
    split = metrics.bias_capacity(out)
    long = split.selectExpr("dataset", "stack(2, 'bias_pp', bias, 'capacity_pp', capacity) AS (metric, value)")
    return out.unionByName(long.select(F.lit("w09").alias("workload"), "dataset", F.lit("ivpq").alias("method"), F.lit("").alias("regime"), F.lit(0).cast("long").alias("seed"), F.lit(-1).cast("long").alias("batch"), "metric", "value"))


def _moved(runs: Runs, s: str, base: DataFrame, q: DataFrame, d: int, first_share: float, shift: Callable[[DataFrame, str], DataFrame], seed: int, m: int, bits: int, regime: str, n: int, adaptive: bool, rr: tuple[int, ...] = (0,)) -> None:
    """The streamed part and the queries are shifted; frozen, adaptive, stale and retrained indexes on the end state."""
    b = batched(base, base.count(), d, first_share, n, "shuffled", seed)
    head, tail = b.where("batch = 0").select("id", "v"), b.where("batch > 0")
    new = shift(tail.select("id", "v"), "v")
    now = head.unionByName(new).persist()
    asked = shift(q.select("qid", "qv"), "qv")
    n0 = head.count()
    cells = 1 << max(1, round(math.log2(math.sqrt(n0))))
    n_p = max(1, cells // 3)
    truth = exact.knn(now, asked, K).persist()
    c = coarse.fit(head, cells, 10, seed)
    index = cfi.Index(d, 4, c, "sign", seed)
    start = _recall(cfi.search(cfi.encode(head, index), index, q, K, n_p), exact.knn(head, q, K))
    runs.add(s, "cfi", start, "initial", regime, seed)

    def both(method: str, found_of: Callable[[int], DataFrame]) -> None:
        for depth in rr:
            found = found_of(max(K, depth))
            runs.add(s, method, _recall(cfi.rerank(found, now, asked, K, depth) if depth else found, truth), regime=f"{regime} rr={depth}", seed=seed)

    frozen = cfi.encode(now, index)
    both("frozen", lambda k: cfi.search(frozen, index, asked, k, n_p))
    if adaptive:
        for source, raw in (("raw", now), ("codes", None)):
            t = time.time()
            fresh, codes = refresh.run(index, frozen, raw, seed=seed)
            codes = codes.persist()
            both(f"adaptive_{source}", lambda k, i=fresh, x=codes: cfi.search(x, i, asked, k, n_p))
            runs.add(s, f"adaptive_{source}", time.time() - t, "seconds", regime, seed)
    cb = pq.fit(head, m, bits, cells, c=c, iters=5, seed=seed)
    both("stale", lambda k: pq.search(pq.encode(now, cb), cb, asked, k, n_p))
    runs.add(s, "stale", n0 / (1 << bits), "rows_per_code", regime, seed)
    runs.add(s, "stale", cost.regime(m, bits, d), "memory_ratio", regime, seed)
    for scope in ("codebook", "full"):
        t = time.time()
        again, codes = pq.retrain(now, cb, bits, scope, 5, seed)
        both(f"retrain_{scope}", lambda k, x=codes, i=again: pq.search(x, i, asked, k, n_p))
        runs.add(s, f"retrain_{scope}", time.time() - t, "seconds", regime, seed)


def w10_encoder_swap(spark, sf_dir, s: str = "A(2.5)", seeds=(42,), m: int = 64, bits: int = 5) -> DataFrame:
    """Old vectors from one encoder, new ones and queries from another, at a gentle and at a harsh mean cosine; the true cosine beside it."""
    runs = Runs("w10")
    base, q, d, _ = load(spark, sf_dir, s)
    for seed in seeds:
        for regime, c, share in (("gentle", 0.51, 0.2), ("harsh", 0.24, 0.4)):
            r = metrics.swap_cosine(base, ds.rotated(base, d, 99, c)).first()
            runs.add(s, "encoder", r["mean"], "cosine", regime, seed)
            _moved(runs, s, base, q, d, share, lambda x, col, c=c: ds.rotated(x, d, 99, c, col), seed, m, bits, regime, 4, False)
    return runs.frame(spark)


def w11_rotation_stress(spark, sf_dir, s: str = "A(2.5)", seeds=(42,), m: int = 64, bits: int = 5, rr=(0, 50)) -> DataFrame:
    """Everything that is streamed, and the queries, rotated: the partition alone is wrong, and refreshing it alone helps."""
    runs = Runs("w11")
    base, q, d, _ = load(spark, sf_dir, s)
    for seed in seeds:
        _moved(runs, s, base, q, d, 0.2, lambda x, col: ds.rotated(x, d, 99, 0.0, col), seed, m, bits, "rotation", 4, True, rr)
    return runs.frame(spark)


def w12_refresh_sweep(spark, sf_dir, s: str = "A(2.5)", every=(0.125, 0.25, 0.5), seed: int = 42) -> DataFrame:
    """Rotated stream under refreshes after every so large a share of n: final recall and rows encoded again."""
    runs = Runs("w12")
    base, q, d, _ = load(spark, sf_dir, s)
    b = ds.batches(base, 0.2, 8, "shuffled", seed).persist()
    head = b.where("batch = 0").select("id", "v")
    moved = ds.rotated(b.where("batch > 0").select("id", "v"), d, 99).join(b.select("id", "batch"), "id").persist()
    asked, total = ds.rotated(q, d, 99, 0.0, "qv"), base.count()
    now = head.unionByName(moved.select("id", "v")).persist()
    truth = exact.knn(now, asked, K).persist()
    n0 = head.count()
    cells = 1 << max(1, round(math.log2(math.sqrt(n0))))
    first = cfi.Index(d, 4, coarse.fit(head, cells, 5, seed), "sign", seed)
    for share in every:
        index, since, coded, trigger = first, 0, 0, refresh.Trigger(every=max(1, int(share * total)))
        for i in range(1, 9):
            since += moved.where(F.col("batch") == i).count()
            if trigger.due(since):
                rows = head.unionByName(moved.where(F.col("batch") <= i).select("id", "v"))
                index, _ = refresh.run(index, cfi.encode(rows, index), rows, iters=5, seed=seed)
                since, coded = 0, coded + rows.count()
        runs.add(s, "adaptive", _recall(cfi.search(cfi.encode(now, index), index, asked, K, max(1, cells // 3)), truth), regime=f"every {share}", seed=seed)
        runs.add(s, "adaptive", coded, "rows_reencoded", f"every {share}", seed)
    return runs.frame(spark)


def w13_freshness(spark, sf_dir, s: str = "A(2.5)", periods=(1, 2, 4), seed: int = 42, n: int = 4) -> DataFrame:
    """Cost of freshness: retraining never, or every so many batches; the undominated points are marked."""
    runs = Runs("w13")
    base, q, d, _ = load(spark, sf_dir, s)
    _arms(runs, s, base, q, d, batched(base, base.count(), d, 0.2, n, "shuffled", seed), seed, d, 5, "", tuple(periods), ("cfi", "stale", "retrain"))
    out = runs.frame(spark)
    end = out.where("metric = 'recall'").groupBy("method").agg(F.max_by("value", "batch").alias("value"))
    spent = out.where("metric = 'rows_reencoded'").select("method", F.col("value").alias("cost"))
    front = metrics.pareto(end.join(spent, "method", "left").na.fill(0.0, ["cost"]))
    return out.unionByName(front.select(F.lit("w13").alias("workload"), F.lit(s).alias("dataset"), "method", F.lit("pareto").alias("regime"), F.lit(seed).cast("long").alias("seed"), F.lit(-1).cast("long").alias("batch"), F.lit("recall_on_front").alias("metric"), "value"))


def w14_static(spark, sf_dir, s: str = "A(2.5)", seed: int = 42, m: int = 64, bits: int = 5) -> DataFrame:
    """Every method on one table: recall, queries a second and MiB; learned codes at the memory of the index with 4 bits."""
    runs = Runs("w14")
    base, q, d, cells = load(spark, sf_dir, s)
    truth, n, nq = exact.knn(base, q, K).persist(), base.count(), q.count()
    n_p, c = max(1, cells // 4), coarse.fit(base, cells, 10, seed)

    def measure(method: str, search: Callable[[], DataFrame], mib: float) -> None:
        t = time.time()
        found = search().persist()
        found.count()
        runs.add(s, method, metrics.qps(nq, time.time() - t), "qps", seed=seed)
        runs.add(s, method, _recall(found, truth), seed=seed)
        runs.add(s, method, mib, "mib", seed=seed)
        found.unpersist()

    measure("exact", lambda: exact.knn(base, q, K), n * d * 4 / cost.MIB)
    for b in (4, 5, 6):
        for name, stage2 in (("xbq", "none"), ("cfi", "sign")):
            index = cfi.Index(d, b, c, stage2, seed)
            codes = cfi.encode(base, index).persist()
            codes.count()
            measure(f"{name}_{b}", lambda x=codes, i=index: cfi.search(x, i, q, K, n_p), cost.memory_mib(n, cost.bits(b, d, stage2 == "sign"), cells, d))
    for name, rotate, eta in (("ivpq", False, None), ("opq_ivpq", True, None), ("atq", False, 4.0)):
        cb = pq.fit(base, m, bits, cells, rotate, eta, 5, seed=seed, c=c)
        codes = pq.encode(base, cb).persist()
        codes.count()
        mib = cost.memory_mib(n, cost.pq_bits(m, bits), cells, d)
        if eta is None:
            measure(name, lambda x=codes, i=cb: pq.search(x, i, q, K, n_p), mib)
        else:
            measure(name, lambda x=codes, i=cb: pq.atq_search(x, i, base, q, K, n_p, 50), mib)
    for links, ef in ((16, 64), (16, 256)):
        measure(f"hnsw_{links}_{ef}", lambda m_=links, e=ef: graph.search(base, q, K, m_, ef=e), cost.graph_bytes(n, d, links) / cost.MIB)
    measure("lsh", lambda: lsh.search(base, q, K), n * d * 4 / cost.MIB)
    return runs.frame(spark)


def w15_bits_or_rerank(spark, sf_dir, sets=("A(2.5)", "D(96)"), seed: int = 42) -> DataFrame:
    """4 bits and a re-rank of 50 on raw vectors, against 6 bits alone: recall and MiB of both."""
    runs = Runs("w15")
    for s in sets:
        base, q, d, cells = load(spark, sf_dir, s)
        truth, n, c = exact.knn(base, q, K).persist(), base.count(), coarse.fit(base, cells, 10, seed)
        n_p = max(1, cells // 4)
        low, high = cfi.Index(d, 4, c, "sign", seed), cfi.Index(d, 6, c, "sign", seed)
        runs.add(s, "4_rr50", _recall(cfi.rerank(cfi.search(cfi.encode(base, low), low, q, 50, n_p), base, q, K, 50), truth), seed=seed)
        runs.add(s, "6", _recall(cfi.search(cfi.encode(base, high), high, q, K, n_p), truth), seed=seed)
        runs.add(s, "4_rr50", cost.rerank_memory_mib(n, cost.bits(4, d), cells, d)[2], "mib", seed=seed)
        runs.add(s, "6", cost.memory_mib(n, cost.bits(6, d), cells, d), "mib", seed=seed)
    return runs.frame(spark)


def w16_bounds(spark, sf_dir, b: int = 4, delta: float = 0.05, turns: int = 200) -> DataFrame:
    """The fixed-vector bound against the error quantile over the embeddings, each under one of many rotations, and the bounds as d grows."""
    runs, e = Runs("w16"), ds.embeddings(spark, sf_dir)
    d = len(e.select("v").first().v)
    q = scalarq.design(b, d)

    def go(batches):
        turn: dict[int, np.ndarray] = {}
        for x in batches:
            if x.num_rows:
                v, which = matrix(x.column(1)), x.column(0).to_numpy() % turns
                for i in np.unique(which).tolist():
                    if i not in turn:
                        turn[i] = rotation.dense(d, 1_000 + i)
                    y = v[which == i] @ turn[i].T
                    yield pa.RecordBatch.from_arrays([pa.array(np.sqrt(((y - q.decode(q.encode(y))) ** 2).sum(axis=1)))], names=["e"])

    r = e.select("id", "v").mapInArrow(go, "e double").agg(F.percentile("e", 1 - delta).alias("top"), F.avg(F.col("e") * F.col("e")).alias("mse")).first()
    runs.add("E", "measured", r.top, "error_quantile", f"d={d}")
    runs.add("E", "measured", r.mse / bounds.db(b), "mse_over_db", f"d={d}")
    for dd in (d, 128, 1_000, 10_000):
        runs.add("E", "single", bounds.single(b, dd, delta), "bound", f"d={dd}")
        runs.add("E", "worst_case", bounds.worst_case(b, dd)[1], "bound", f"d={dd}")
        runs.add("E", "uniform", bounds.uniform(b, dd, delta), "bound", f"d={dd}")
    return runs.frame(spark)


def w17_generation_loss(spark, sf_dir, sets=("A(2.5)",), generations: int = 3, seed: int = 42) -> DataFrame:
    """Refreshes from codes alone, repeated: error and recall by generation, beside one refresh from raw vectors."""
    runs = Runs("w17")
    for s in sets:
        base, q, d, cells = load(spark, sf_dir, s)
        truth = exact.knn(base, q, K).persist()
        index, codes = cfi.build(base, cells, 4, "sign", seed, 5, d=d)
        for g in range(generations + 1):
            codes = codes.persist()
            back = cfi.reconstruct(codes, index).select("id", F.col("v").alias("w")).join(base, "id")
            e = back.select(F.aggregate(F.zip_with("v", "w", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda a, x: a + x).alias("e")).agg(F.avg("e")).first()[0]
            runs.add(s, "from_codes", e, "mse", seed=seed, batch=g)
            runs.add(s, "from_codes", _recall(cfi.search(codes, index, q, K, cells), truth), seed=seed, batch=g)
            if g < generations:
                index, codes = refresh.run(index, codes, None, iters=5, seed=seed, most_generations=99)
        again, new = refresh.run(replace(index, generation=0), codes, base, iters=5, seed=seed)
        runs.add(s, "from_raw", _recall(cfi.search(new, again, q, K, cells), truth), seed=seed, batch=generations)
    return runs.frame(spark)


def w18_flat_error(spark, sf_dir, s: str = "D(96)", n: int = 4, seed: int = 42) -> DataFrame:
    """Errors of the data-independent layer by insert batch: the last rows are coded as well as the first."""
    runs = Runs("w18")
    base, q, d, _ = load(spark, sf_dir, s)
    b = ds.batches(base, 0.2, n, "shuffled", seed).persist()
    first = b.where("batch = 0").select("id", "v")
    cells = 1 << max(1, round(math.log2(math.sqrt(first.count()))))
    index = cfi.Index(d, 4, coarse.fit(first, cells, 10, seed), "sign", seed)
    for r in cfi.inner_error(b, index, q, "batch").collect():
        for m in ("mse", "ip_mse", "ip_p95", "affinity"):
            runs.add(s, "cfi", r[m], m, seed=seed, batch=r.batch)
    return runs.frame(spark)


def w19_accounting(spark, sf_dir, sets=("E", "A(2.5)")) -> DataFrame:
    """Bits a vector of each set, with a fixed and with an exact id part, and MiB of its rows."""
    runs = Runs("w19")
    for s in sets:
        base, _, d, cells = load(spark, sf_dir, s)
        runs.add(s, "cfi", cost.bits(4, d), "bits")
        runs.add(s, "cfi", cost.bits(4, d, cells=cells), "bits_exact")
        runs.add(s, "cfi", cost.memory_mib(base.count(), cost.bits(4, d), cells, d), "mib")
    return runs.frame(spark)


WORKLOADS = {f.__name__: f for f in (w01_matched_memory, w02_amplification, w03_flat_stage2, w04_learned_ceiling, w05_probes, w06_streaming_small, w07_nine_cells, w08_orders, w09_bias_capacity, w10_encoder_swap, w11_rotation_stress, w12_refresh_sweep, w13_freshness, w14_static, w15_bits_or_rerank, w16_bounds, w17_generation_loss, w18_flat_error, w19_accounting)}

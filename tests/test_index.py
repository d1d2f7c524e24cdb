"""The index, its baselines and measures on small vectors."""

import hashlib
import math
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from annspark.functions import metrics, scalarq, vectors
from annspark.operators import cfi, coarse, diagnostics, exact, graph, lsh, pq, refresh
from annspark.plans import workloads
from annspark.sources import datasets as ds
from annspark.sources import datasource, layout
from annspark.streaming import ingest
from tests.conftest import SF

K = 10


@pytest.fixture(scope="module")
def a(spark):
    """Clustered vectors: (base, queries, truth)."""
    base, q = ds.split(ds.anchored(spark, SF, 2.5))
    base, q = base.cache(), q.cache()
    return base, q, exact.knn(base, q, K).cache()


@pytest.fixture(scope="module")
def index(a):
    return cfi.build(a[0], 8, 4, "sign", 42, 4, d=64)


def recall(found, truth):
    return metrics.recall(found, truth, K).first().recall


def ids(found):
    return {(r.qid, r["rank"]): r.id for r in found.collect()}


def test_quarantine(spark):
    rows = [(1, [3.0, 4.0]), (2, [0.0, 0.0]), (3, None), (4, [1.0]), (5, [float("nan"), 1.0]), (6, [None, 1.0]), (7, [float("inf"), 1.0])]
    good, bad = vectors.normalise(spark.createDataFrame(rows, "id long, v array<double>"), "v", 2)
    assert [(r.id, r.v) for r in good.collect()] == [(1, [0.6, 0.8])] and sorted(r.id for r in bad.collect()) == [2, 3, 4, 5, 6, 7]


def test_exact_ties_by_id(spark):
    base = spark.createDataFrame([(i, [1.0, 0.0] if i % 2 else [0.0, 1.0]) for i in range(8)], "id long, v array<double>")
    q = spark.createDataFrame([(0, [1.0, 0.0])], "qid long, qv array<double>")
    for f in (exact.knn, exact.knn_native):
        assert [r.id for r in f(base, q, 6).orderBy("rank").collect()] == [1, 3, 5, 7, 0, 2]


def test_hashed_sets_read_whole_texts(spark):
    opening = "same words at the start " * 200
    texts = spark.createDataFrame([(1, opening + "whale"), (2, opening + "otter " * 300), (3, "-" * 3000 + "late")], "id long, text string")
    slots = {}
    for r in ds.hashed_slots(texts, 96).collect():
        slots.setdefault(r.id, {})[r.slot] = r.x
    assert sum(abs(x) for x in slots[2].values()) > 250 and slots[1] != slots[2] and list(slots[3].values()) in ([1], [-1])
    v = {r.id: r.v for r in ds.hashed(texts, 96).collect()}
    assert set(v) == {1, 2, 3} and np.dot(v[1], v[2]) < 0.999


def test_waves_cover_all(a):
    _, q, _ = a
    got = [r.qid for w in exact.waves(q, 20) for r in w.collect()]
    assert sorted(got) == sorted(r.qid for r in q.collect())


def test_searches_go_over_all_waves(a, index, monkeypatch):
    base, q, truth = a
    found, codes = index
    cb = pq.from_first_rows(base, 8, 4)
    pq_codes = pq.encode(base, cb)
    b = base.withColumn("batch", (F.col("id") % 2).cast("int"))
    runs = {
        "knn": lambda: exact.knn(base, q, K),
        "native": lambda: exact.knn_native(base, q, K),
        "cumulative": lambda: exact.knn_cumulative(b, q, K).drop("rank").withColumn("rank", F.col("batch") * 100 + F.row_number().over(_order("batch", "qid"))),
        "cfi": lambda: cfi.search(codes, found, q, K, 2),
        "join": lambda: cfi.search(codes, found, q, K, 2, limit=1),
        "pq": lambda: pq.search(pq_codes, cb, q, K),
        "graph": lambda: graph.search(base, q, K),
        "probes": lambda: cfi.probes_frame(found, q, 2).withColumnRenamed("cell", "id"),
    }
    whole, errors = {name: ids(run()) for name, run in runs.items()}, cfi.inner_error(base, found, q).first()
    monkeypatch.setattr(exact, "WAVE", 20)
    monkeypatch.setattr(cfi, "SCORES", 200)
    assert q.count() > 2 * exact.WAVE
    for name, run in runs.items():
        assert ids(run()) == whole[name], name
    assert cfi.inner_error(base, found, q).first() == pytest.approx(errors)


def test_w07_runs_every_cell(spark, monkeypatch):
    cells = []

    def arms(runs, s, base, q, d, b, seed, m, bits, regime, **more):
        cells.append((d, seed, m, bits))
        assert [r.batch for r in b.select("batch").distinct().orderBy("batch").collect()] == list(range(10))
        runs.add(s, "cfi", 0.5, regime=regime, seed=seed, batch=0)

    monkeypatch.setattr(workloads, "_arms", arms)
    assert workloads.WORKLOADS["w07_nine_cells"](spark, SF).count() > 0
    assert {(d, seed, *x) for d in (96, 128, 200) for seed in workloads.SEEDS for x in workloads.REGIMES[d]} <= set(cells)
    assert {(d, seed, *x) for d in (96, 128, 200) for seed in workloads.SEEDS for x in workloads.NARROW[d]} <= set(cells)  # 18 rows first
    assert len(cells) == len(set(cells))


def _order(*by):
    return Window.partitionBy(*by).orderBy(F.desc("score"), "id")


def test_centroids_do_not_depend_on_partitions(a):
    base = a[0]
    assert np.array_equal(coarse.fit(base, 8, 3), coarse.fit(base.repartition(7), 8, 3))
    c = coarse.fit_two_level(base, 3, 4, 3)
    assert np.allclose(np.linalg.norm(c, axis=1), 1) and 3 <= len(c) <= 12


def test_empty_cell_keeps_its_centroid(spark):
    base = spark.createDataFrame([(i, [1.0, 0.0]) for i in range(5)], "id long, v array<double>")
    c = coarse.fit(base, 2, 2, init=np.array([[1.0, 0.0], [0.0, 1.0]]))
    assert c.tolist() == [[1.0, 0.0], [0.0, 1.0]]


def test_zero_residual_scores_by_its_centroid(spark):
    base = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.6, 0.8])], "id long, v array<double>")
    idx = cfi.Index(2, 4, np.array([[1.0, 0.0]]))
    q = spark.createDataFrame([(0, [0.8, 0.6])], "qid long, qv array<double>")
    got = {r.id: r.score for r in cfi.search(cfi.encode(base, idx), idx, q, 2).collect()}
    assert got[0] == pytest.approx(0.8) and got[1] == pytest.approx(0.96, abs=0.05)


def test_recall_grows_to_exact(a, index):
    base, q, truth = a
    idx, codes = index
    assert recall(cfi.rerank(cfi.search(codes, idx, q, 400, 8), base, q, K, 400), truth) == 1
    by = [recall(cfi.rerank(cfi.search(codes, idx, q, rr, 8), base, q, K, rr), truth) for rr in (10, 30, 100)]
    assert by == sorted(by)
    assert recall(cfi.search(codes, idx, q, K, 8), truth) >= recall(cfi.search(codes, idx, q, K, 1), truth)
    eight = cfi.Index(64, 8, idx.c)
    assert recall(cfi.search(cfi.encode(base, eight), eight, q, K, 8), truth) > 0.97


def test_both_search_plans_agree(a, index):
    _, q, _ = a
    idx, codes = index
    want = ids(cfi.search(codes, idx, q, K, 3))
    assert want == ids(cfi.search(codes.repartition(9), idx, q, K, 3))
    spark = codes.sparkSession
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")  # groups really lie in different partitions
    try:
        for salt_rows in (15, 1_000_000):
            assert want == ids(cfi.search_join(codes, idx, q, K, 3, salt_rows=salt_rows))
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def test_cascade_and_ties(a, index):
    base, q, truth = a
    idx, codes = index
    assert recall(cfi.cascade(codes, idx, q, K, 8, (20, 5), base), truth) > 0.97
    found = cfi.rerank(cfi.search(codes, idx, q, 50, 8), base, q, K, 50)
    assert metrics.recall_ties(found, truth, K).first().recall >= recall(found, truth) - 1e-12


def test_insert_is_the_same_as_build(a, index):
    base, _, _ = a
    idx, codes = index
    half = cfi.insert(cfi.encode(base.where("id % 2 = 0"), idx), base.where("id % 2 = 1"), idx)
    assert sorted(map(tuple, half.select("id", "cell", "code", "sign").collect())) == sorted(map(tuple, codes.select("id", "cell", "code", "sign").collect()))


def test_errors_follow_the_design(a):
    base, q, _ = a
    idx, _ = cfi.build(base, 10, 4, "sign", 42, 5, d=64)
    r = diagnostics.amplification(base, idx, q).first()
    assert r.measured == pytest.approx(r.predicted, rel=0.1) and r.predicted < 0.6
    flat = cfi.inner_error(base, replace(idx, c=None, stage2="none"), q).first()
    assert 0.8 < flat.mse / scalarq.design(4).distortion < 1.02


def test_partition_hurts_isotropic_noise(spark):
    base, q = ds.split(ds.embeddings(spark, SF))
    idx, _ = cfi.build(base, 16, 4, "sign", 42, 5, d=64)
    r = diagnostics.amplification(base, idx, q).first()
    assert r.predicted > 1 and r.measured > 1


def test_fast_rotation(a):
    base, q, truth = a
    idx, codes = cfi.build(base, 8, 4, "sign", 42, 4, d=64, fast_rotation=True)
    assert recall(cfi.search(codes, idx, q, K, 8), truth) > 0.8


def test_refresh_and_generations(a, index):
    base, q, truth = a
    idx, codes = index
    new, again = refresh.run(idx, codes, base, size=100, iters=3)
    assert new.epoch == 1 and new.generation == 0 and again.count() == base.count() and recall(cfi.search(again, new, q, K, 8), truth) > 0.8
    own, _ = refresh.run(idx, codes, None, size=100, iters=3)
    assert own.generation == 1
    with pytest.raises(ValueError):
        refresh.run(replace(idx, generation=3), codes, None)
    assert refresh.Trigger(every=5).due(5) and not refresh.Trigger(every=5).due(4) and refresh.Trigger(affinity_drop=0.1).due(0, 0.9, 0.75)
    sizes = {r.cell: r["count"] for r in refresh.sample(codes, 90).groupBy("cell").count().collect()}
    assert set(sizes) == {r.cell for r in codes.select("cell").distinct().collect()} and abs(sum(sizes.values()) - 90) <= len(sizes)


def test_learned_baselines(a):
    base, q, truth = a
    c = coarse.fit(base, 8, 4)
    got = {}
    for name, options in (("pq", {}), ("ivpq", {"cells": 8, "c": c}), ("opq", {"cells": 8, "c": c, "rotate": True, "rounds": 2}), ("atq", {"cells": 8, "c": c, "eta": 4.0})):
        cb = pq.fit(base, 32, 4, iters=4, **options)
        got[name] = recall(pq.search(pq.encode(base, cb), cb, q, K, 8), truth)
        if name == "atq":
            got["reordered"] = recall(pq.atq_search(pq.encode(base, cb), cb, base, q, K, 8, 100), truth)
    assert got["ivpq"] > 0.4 and got["opq"] > 0.4 and got["atq"] > 0.4 and got["reordered"] > 0.95 and got["pq"] > 0.2
    cb = pq.fit(base, 32, 4, 8, c=c, iters=3)
    new, codes = pq.retrain(base, cb, 4, "full", 3)
    assert new.version == 1 and codes.count() == base.count()
    assert pq.insert(pq.encode(base, cb), base, cb).count() == 2 * base.count()
    assert not np.array_equal(pq.update(cb, base).books, cb.books)
    with pytest.raises(ValueError):
        pq.fit(base, 7, 4)


def test_anisotropic_codes_have_less_parallel_error(a):
    base, _, _ = a
    x = pq.training_rows(base)
    plain = pq.fit(base, 16, 4, iters=6)
    aware = pq.fit(base, 16, 4, eta=8.0, iters=6)
    along = [float((((x - cb.decode(cb.encode(x, x))) * x).sum(axis=1) ** 2).mean()) for cb in (plain, aware)]
    assert along[1] < along[0]


def test_graph_and_hashing(a):
    base, q, truth = a
    assert recall(graph.search(base, q, K, 16, 100, 64, shard_rows=200), truth) > 0.95
    assert recall(lsh.search(base, q, K), truth) > 0.8


def test_layout_replay_and_refresh(spark, a, index, tmp_path):
    base, q, _ = a
    idx, _ = index
    path = str(tmp_path / "idx")
    layout.create(cfi.encode(base.where("id < 250"), idx), idx, path, 4)
    for _ in range(2):  # the same batch twice
        layout.append(base.where("id >= 250"), path, 0, 4)
    live, codes = layout.load(spark, path)
    assert codes.count() == base.count() and live.cells == idx.cells
    assert ids(cfi.search(codes, live, q, K, 3)) == ids(cfi.search(cfi.encode(base, idx), idx, q, K, 3))
    pruned = layout.load(spark, path, [1, 5], 4)[1]
    assert {r.cell for r in pruned.select("cell").distinct().collect()} <= {1, 5} and "PartitionFilters: [isnotnull(cell_bucket" in pruned._jdf.queryExecution().toString()
    datasource.register(spark)
    through = spark.read.format("cfi").option("path", path).option("buckets", 4).load()
    assert through.where("cell = 5").count() == codes.where("cell = 5").count() and through.count() == base.count()
    for option, value in (("cells", "5"), ("pushdown", True)):
        one = spark.read.format("cfi").option("path", path).option("buckets", 4).option(option, value).load()
        assert one.where("cell = 5").count() == codes.where("cell = 5").count()
    new = layout.refresh(spark, path, base, 4, size=100, iters=2)
    after, codes = layout.load(spark, path)
    assert after.epoch == new.epoch == 1 and codes.count() == base.count()


@pytest.mark.parametrize("raw", [True, False])
def test_no_insert_is_lost_to_a_refresh(spark, a, index, tmp_path, monkeypatch, raw):
    """Batches that come before a refresh, while it stages, between its last look and the opening, right after that, and later."""
    base, path = a[0], str(tmp_path / "idx")
    idx, _ = index
    part = lambda i: base.where(F.col("id") % 7 == i)
    layout.create(cfi.encode(part(0), idx), idx, path, 4)
    layout.append(part(1), path, 0, 4)
    run, commit = refresh.run, layout.commit

    def staging(*args, **more):
        out = run(*args, **more)
        layout.append(part(2), path, 1, 4)
        return out

    def opening(spark_, path_, new, batch, *args, **more):
        if batch == layout.OPENS:
            monkeypatch.setattr(layout, "commit", commit)
            layout.append(part(3), path, 2, 4)
            commit(spark_, path_, new, batch, *args, **more)
            layout.append(part(4), path, 3, 4)
            layout.append(part(3), path, 2, 4)  # the stream replays it: the new epoch does not have it yet
        else:
            commit(spark_, path_, new, batch, *args, **more)

    monkeypatch.setattr(refresh, "run", staging)
    monkeypatch.setattr(layout, "commit", opening)
    layout.refresh(spark, path, base if raw else None, 4, size=100, iters=2)
    monkeypatch.undo()
    assert layout.append(part(5), path, 4, 4) == 1
    now = layout.live(spark, path)
    _, codes = layout.load(spark, path)
    assert sorted(r.id for r in codes.select("id").collect()) == sorted(r.id for r in base.where("id % 7 < 6").select("id").collect())
    assert now.batches == {0, 1, 2, 3, 4} and now.rows == codes.count() and codes.select("epoch").distinct().collect()[0][0] == 1
    assert now.index.inserted == base.where("id % 7 BETWEEN 2 AND 5").count()
    datasource.register(spark)
    assert spark.read.format("cfi").option("path", path).option("buckets", 4).load().count() == codes.count()
    again = layout.refresh(spark, path, base, 4, size=100, iters=1)
    assert again.epoch == 2 and again.inserted == 0 and layout.live(spark, path).batches == {0, 1, 2, 3, 4} and layout.load(spark, path)[1].count() == codes.count()


def test_stream_refreshes_by_rows_and_by_drift(spark, a, index, tmp_path):
    base, _, _ = a
    idx, _ = index
    turned = ds.rotated(base, 64, 99)
    for name, trigger, rows, least in (("rows", refresh.Trigger(every=80), base, 1), ("drift", refresh.Trigger(affinity_drop=0.2), turned, 1)):
        path, src = str(tmp_path / name), str(tmp_path / f"{name}-src")
        layout.create(cfi.encode(base.where("id % 4 = 0"), idx), idx, path)
        arriving = rows.where("id % 4 > 0").withColumn("batch", (F.col("id") % 4 > 1).cast("int"))
        ingest.arrivals(arriving, src)
        whole = base.where("id % 4 = 0").unionByName(arriving.select("id", "v"))
        ingest.start(spark, src, path, str(tmp_path / f"{name}-ckpt"), trigger, whole, {"size": 100, "iters": 1}).awaitTermination()
        now, codes = layout.load(spark, path)
        assert sorted(r.id for r in codes.select("id").collect()) == sorted(r.id for r in base.select("id").collect())
        assert now.epoch >= least, name


def test_sample_takes_the_quota_of_every_cell(spark, monkeypatch):
    """Against a plain ranking, with slices of few rows."""
    monkeypatch.setattr(refresh, "SLICE", 3)
    codes = spark.range(2_000).selectExpr("CAST(CASE WHEN id % 3 = 0 THEN 0 ELSE id % 40 END AS BIGINT) AS cell", "id")
    got = sorted(map(tuple, refresh.sample(codes, 300, 7).collect()))
    rows, cells = {}, codes.collect()
    for r in cells:
        rows.setdefault(r.cell, []).append((hashlib.md5(f"7:{r.id}".encode()).hexdigest(), r.id))
    want = sorted((c, i) for c, v in rows.items() for _, i in sorted(v)[: max(1, math.ceil(len(v) * (300 / 2_000)))])
    assert got == want


def test_plans(a, index):
    _, q, _ = a
    idx, codes = index
    plan = cfi.search(codes, idx, q, K, 3)._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in plan and "CartesianProduct" not in plan and plan.count("Exchange hashpartitioning(qid") <= 2
    plain = ds.table(spark=codes.sparkSession, sf_dir=SF, name="embeddings").selectExpr("vec_id AS id", "cast(embedding AS array<double>) AS v")
    encoded = cfi.encode(plain, idx)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in encoded and "ReadSchema: struct<vec_id:bigint,embedding:array<float>>" in encoded


def test_planner(index):
    idx, _ = index
    assert cfi.plan(idx, 8_000_000, 100, 3) == cfi.Plan("broadcast", 300, 300_000_000, 1)
    assert cfi.plan(idx, 8_000_000, 90_000, 20) == cfi.Plan("join", 720_000, 720_000_000_000, 9)


def test_measures(spark):
    runs = spark.createDataFrame([("x", s, b, m, v) for s in (1, 2, 3) for b, m, v in ((0, "p", 0.5 + s / 100), (9, "p", 0.4), (0, "q", 0.6), (9, "q", 0.7))], "set string, seed long, batch long, method string, value double")
    d = {(r.seed, r.method): r.delta for r in metrics.delta(runs, ["seed", "method"]).collect()}
    assert d[(1, "p")] == pytest.approx(-11) and d[(2, "q")] == pytest.approx(10)
    g = {r.seed: r.gap for r in metrics.gap(runs.where("batch = 9"), ["seed"], "q", "p").collect()}
    assert g[1] == pytest.approx(30)
    points = spark.createDataFrame([("a", 1.0, 0.5), ("b", 2.0, 0.4), ("c", 3.0, 0.9), ("d", 3.0, 0.8)], "m string, cost double, value double")
    assert sorted(r.m for r in metrics.pareto(points).collect()) == ["a", "c"]


def test_directions(spark):
    """What the experiments are about: signs, not sizes."""
    w = {(r.method, r.regime): r.value for r in workloads.w11_rotation_stress(spark, SF, rr=(0,)).where("metric = 'recall'").collect()}
    assert w[("adaptive_raw", "rotation rr=0")] > w[("frozen", "rotation rr=0")]
    f = {r.method: r.value for r in workloads.w03_flat_stage2(spark, SF, ("E",)).collect()}
    assert f["rsq_sign"] > f["rsq_none"] > f["rsq_jls"]
    t = workloads.w01_matched_memory(spark, SF, ("A(2.5)",), (5,)).where(F.col("metric") == "delta_pp").first().value
    assert abs(t) <= 5

"""Queries over the index on storage, its data source, streams and user functions."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from annspark.functions import udfs
from annspark.operators import cfi, coarse, refresh
from annspark.plans import core, relational
from annspark.sources import datasets as ds
from annspark.sources import datasource, layout
from annspark.streaming import events, ingest


def _path(spark, name: str) -> str:
    return relational.scratch(spark, f"{name}-{uuid.uuid4().hex[:8]}")


def _stored(spark, sf_dir):
    base, q = core._e(spark, sf_dir)
    index, codes = core._index(base)
    path = _path(spark, "index")
    layout.create(codes, index, path)
    return base, q, path


def sink_codes_by_cell(spark, sf_dir):
    """Rows per cell of the stored index, read back with buckets pruned."""
    _, _, path = _stored(spark, sf_dir)
    _, codes = layout.load(spark, path, cells=list(range(0, core.L, 2)))
    return codes.groupBy("cell").agg(F.count("*").alias("n"))


def ds_cfi_read(spark, sf_dir):
    """The same through the data source, the cell filter pushed down."""
    _, _, path = _stored(spark, sf_dir)
    datasource.register(spark)
    codes = spark.read.format("cfi").option("path", path).option("pushdown", True).load()
    return codes.where(F.col("cell").isin(list(range(0, core.L, 2)))).groupBy("cell").agg(F.count("*").alias("n"))


def stored_search(spark, sf_dir):
    """Search on the index as loaded from storage."""
    _, q, path = _stored(spark, sf_dir)
    index, codes = layout.load(spark, path)
    return core._shown(cfi.search(codes, index, q, core.K, core.NP))


def _streamed(spark, sf_dir, replayed: bool = False, **more):
    """A quarter of the rows makes the index, three come in by stream. (queries, index path, number of rows)."""
    base, q = core._e(spark, sf_dir)
    b = core.batched(base)
    first = b.where("batch = 0").select("id", "v")
    index, codes = cfi.build(first, 8, core.BITS, "sign", core.SEED, core.ROUNDS, d=core.D, exact_norm=True)
    path, src, ckpt = (_path(spark, n) for n in ("stream", "arrivals", "checkpoint"))
    layout.create(codes, index, path)
    ingest.arrivals(b.where("batch > 0").withColumn("batch", F.col("batch") - 1), src)
    ingest.start(spark, src, path, ckpt, **more).awaitTermination()
    if replayed:  # a batch that was committed before
        ingest.insert(b.where("batch = 2"), 1, path)
    return q, path


def stream_ingest(spark, sf_dir):
    """Three arrival files through Structured Streaming, one replayed; search of the result."""
    q, path = _streamed(spark, sf_dir, True)
    index, codes = layout.load(spark, path)
    return core._shown(cfi.search(codes, index, q, core.K, core.NP))


def stream_refresh(spark, sf_dir):
    """The same stream with a refresh inside it, due after two fifths of the table are inserted: the second batch makes it, the third
    joins the new epoch. Every row and its cell, as stored."""
    base, _ = core._e(spark, sf_dir)
    every = base.count() * 2 // 5
    _, path = _streamed(spark, sf_dir, refresh_when=refresh.Trigger(every=every), raw=base, options={"iters": 2, "seed": core.SEED})
    index, codes = layout.load(spark, path)
    return codes.select(F.lit(index.epoch).cast("long").alias("epoch"), F.col("id").alias("vec_id"), "cell")


def udf_encode(spark, sf_dir):
    encode = udfs.encoder(cfi.Index(core.D, core.BITS, None, "sign", core.SEED))
    coded = ds.table(spark, sf_dir, "embeddings").select("vec_id", encode(F.col("embedding").cast("array<double>")).alias("code"))
    return coded.select("vec_id", F.concat_ws(",", F.col("code").cast("array<string>")).alias("code_csv"))


def udtf_probe(spark, sf_dir):
    base, q = core._e(spark, sf_dir)
    index, _ = core._index(base)
    spark.udtf.register("annspark_probe", udfs.prober(index, core.NP))
    q.createOrReplaceTempView("annspark_queries")
    return spark.sql("SELECT qid, p.cell, p.rank FROM annspark_queries, LATERAL annspark_probe(qv) p")


def _events(spark, sf_dir, late=False):
    return events.stream(spark, events.files(spark, sf_dir, _path(spark, "events"), late))


def st_watermark_late(spark, sf_dir):
    """Closed windows of a stream in which every fiftieth row comes after the watermark: those rows are dropped."""
    return events.run(events.tumbling(_events(spark, sf_dir, True))).groupBy("event_type").agg(F.sum("n").alias("n"))


def st_dedup(spark, sf_dir):
    src = events.files(spark, sf_dir, _path(spark, "events"))
    events.files(spark, sf_dir, src)  # everything once more
    return events.run_to(events.deduplicated(events.stream(spark, src), "60 days"), _path(spark, "distinct")).select("event_id", "event_type")


def st_join_static(spark, sf_dir):
    base, _ = core._e(spark, sf_dir)
    cells = coarse.assign(base, coarse.fit(base, core.L, core.ROUNDS, core.SEED)).select(F.col("id").alias("event_id"), "cell")
    return events.run(events.with_static(_events(spark, sf_dir), F.broadcast(cells))).select("event_id", "cell")


def st_join_stream(spark, sf_dir):
    return events.run(events.joined(_events(spark, sf_dir), _events(spark, sf_dir)))


def st_drift_state(spark, sf_dir):
    """Final state per cell of the running affinity of inserted vectors."""
    base, _ = core._e(spark, sf_dir)
    b = core.batched(base)
    c = coarse.fit(b.where("batch = 0").select("id", "v"), 8, core.ROUNDS, core.SEED)
    src = _path(spark, "arrivals")
    ingest.arrivals(b, src)
    arrived = spark.readStream.schema(ingest.VECTORS).option("maxFilesPerTrigger", 1).parquet(src)
    states = events.run(events.drift(coarse.assign(arrived, c)), "update")
    return states.groupBy("cell").agg(F.max("n").alias("n"), F.round(F.max_by("affinity", "n"), 6).alias("affinity"))


QUERIES = {f.__name__: f for f in (sink_codes_by_cell, ds_cfi_read, stored_search, stream_ingest, stream_refresh, udf_encode, udtf_probe, st_watermark_late, st_dedup, st_join_static, st_join_stream, st_drift_state)}


def oracle_sql() -> dict[str, str]:
    own = core.oracle_sql()
    cent = f"c{core.ROUNDS}"
    assigned = core._with(core.E_SQL, core._kmeans()) + f", a AS (SELECT b.id, p.cell FROM base b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1)"
    first = (core.E_SQL, core._batched(), "b0 AS (SELECT id, v FROM bb WHERE batch = 0)")
    b0 = core._with(*first, core._kmeans("b0", 8))
    q4 = core.scalarq.design(core.BITS, core.D)
    even = assigned + " SELECT cell, count(*) AS n FROM a WHERE cell % 2 = 0 GROUP BY cell"
    return {
        "sink_codes_by_cell": even,
        "ds_cfi_read": even,
        "stored_search": own["cfi_search_sign"],
        "stream_ingest": core._with(*first, core._rot(), core._kmeans("b0", 8), core._encode("base", cent, q4, "x", True), core._turned(), core._search("x", cent, core.NP, core.K, "s")) + " SELECT qid, rank, id AS vec_id, round(score, 6) AS score FROM st",
        "stream_refresh": core._with(*first, core._kmeans("b0", 8), "seen AS (SELECT id, v FROM bb WHERE batch <= 2)", f"xx AS MATERIALIZED (SELECT b.id, p.cell FROM seen b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1)", core._sample(size="greatest(64 * 8, count(*) // 10)"), "smv AS MATERIALIZED (SELECT id, v FROM base WHERE id IN (SELECT id FROM sm))", core._kmeans("smv", 8, 2, tag="k")) + " SELECT 1 AS epoch, b.id AS vec_id, p.cell FROM base b, k2 p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1",
        "udf_encode": core._with(core.E_SQL, core._rot(), core._encode("e", None, q4, "f", True)) + " SELECT id AS vec_id, array_to_string(codes, ',') AS code_csv FROM fx",
        "udtf_probe": own["cfi_probe"],
        "st_dedup": "SELECT event_id, event_type FROM events",
        "st_join_static": assigned + " SELECT event_id, cell FROM events JOIN a ON id = event_id",
        "st_join_stream": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
        "st_drift_state": b0 + f", a AS (SELECT b.id, p.cell, list_dot_product(b.v, p.c) AS ip FROM base b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY ip DESC, p.cell) = 1) SELECT cell, count(*) AS n, round(avg(ip), 6) AS affinity FROM a GROUP BY cell",
    }

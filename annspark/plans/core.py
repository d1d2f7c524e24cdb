"""Method queries on the given tables, and DuckDB SQL that computes the same from scratch.

Both engines share the determinism rules: doubles throughout, ties by id or cell, fixed-point k-means sums, seeded order
by MD5. Rotation matrices and quantizer tables go into the SQL as literals; partitions are fitted there by unrolled rounds.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.functions import bounds, cost, metrics, rotation, scalarq, stats
from annspark.functions.vectors import is_bad, matrix, norm
from annspark.operators import cfi, coarse, diagnostics, exact, graph, lsh, pq, refresh
from annspark.sources import datasets as ds

L, ROUNDS, BITS, SEED, K, NP, D = 16, 3, 4, 42, 10, 4, 64

# ---------------------------------------------------------------- SQL pieces


def _nums(x) -> str:
    return "[" + ",".join(repr(float(v)) for v in x) + "]"


E_SQL = """
e0 AS (SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
e AS MATERIALIZED (SELECT id, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) AS v FROM e0),
base AS MATERIALIZED (SELECT id, v FROM e WHERE id % 10 <> 0),
qs AS MATERIALIZED (SELECT id AS qid, v AS qv FROM e WHERE id % 10 = 0)"""


def _rot(d: int = D, seed: int = SEED, name: str = "rot") -> str:
    r = rotation.dense(d, seed)
    return f"{name} AS MATERIALIZED (SELECT * FROM (VALUES " + ",".join(f"({j},{_nums(row)})" for j, row in enumerate(r)) + ") t(j, r))"


def _kmeans(src: str = "base", cells: int = L, rounds: int = ROUNDS, d: int = D, tag: str = "c", start: str | None = None) -> str:
    out = [start or f"{tag}0 AS MATERIALIZED (SELECT row_number() OVER (ORDER BY md5('{SEED}:' || id), id) - 1 AS cell, v AS c FROM {src} QUALIFY cell < {cells})"]
    for i in range(1, rounds + 1):
        p = f"{tag}{i - 1}"
        out.append(f"{tag}a{i} AS MATERIALIZED (SELECT b.id, p.cell, b.v FROM {src} b, {p} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1)")
        out.append(f"{tag}s{i} AS (SELECT cell, j, sum(CAST(round(v[j] * 1e9) AS BIGINT))::DOUBLE AS s FROM {tag}a{i}, range(1, {d + 1}) t(j) GROUP BY cell, j)")
        out.append(f"{tag}l{i} AS (SELECT cell, list(s ORDER BY j) AS l FROM {tag}s{i} GROUP BY cell)")
        out.append(f"{tag}{i} AS MATERIALIZED (SELECT p.cell, CASE WHEN l IS NULL THEN p.c ELSE list_transform(l, lambda x: x / sqrt(list_dot_product(l, l))) END AS c FROM {p} p LEFT JOIN {tag}l{i} USING (cell))")
    return ",\n".join(out)


def _encode(src: str, cent: str | None, q: scalarq.Quantizer, tag: str, refine: bool) -> str:
    """{tag}x: (id, cell, norm, codes, signs, dec): assignment, rotated residual, codes and decoded values."""
    edges, levels, halves = _nums(q.edges), _nums(q.levels), _nums(q.halves.ravel())
    assigned = (
        f"{tag}a AS MATERIALIZED (SELECT b.id, p.cell, b.v, p.c FROM {src} b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1),\n"
        f"{tag}r AS (SELECT id, cell, list_transform(list_zip(v, c), lambda z: z[1] - z[2]) AS r FROM {tag}a)"
        if cent
        else f"{tag}r AS (SELECT id, 0 AS cell, v AS r FROM {src})"
    )
    dec = f"list_transform(range(1, len(u) + 1), lambda i: {halves}[2 * codes[i] + signs[i] + 1])" if refine else f"list_transform(codes, lambda k: {levels}[k + 1])"
    return f"""{assigned},
{tag}y AS MATERIALIZED (SELECT id, cell, list(list_dot_product({tag}r.r, rot.r) ORDER BY j) AS y FROM {tag}r, rot GROUP BY id, cell),
{tag}n AS (SELECT id, cell, y, sqrt(list_dot_product(y, y)) AS norm FROM {tag}y),
{tag}u AS (SELECT id, cell, norm, list_transform(y, lambda x: x / norm) AS u FROM {tag}n),
{tag}k AS (SELECT *, list_transform(u, lambda x: len(list_filter({edges}, lambda g: g <= x))) AS codes FROM {tag}u),
{tag}g AS (SELECT *, list_transform(range(1, len(u) + 1), lambda i: CASE WHEN u[i] > {levels}[codes[i] + 1] THEN 1 ELSE 0 END) AS signs FROM {tag}k),
{tag}x AS MATERIALIZED (SELECT id, cell, norm, u, codes, signs, {dec} AS dec FROM {tag}g)"""


def _turned(name: str = "tq", src: str = "qs") -> str:
    return f"{name} AS MATERIALIZED (SELECT qid, qv, list(list_dot_product(qv, r) ORDER BY j) AS t FROM {src}, rot GROUP BY qid, qv)"


def _search(tag: str, cent: str | None, n_p: int, k: int, out: str, extra: str = "") -> str:
    if cent is None:
        return f"{out} AS MATERIALIZED (SELECT qid, id, norm * list_dot_product(t, dec) AS score FROM tq, {tag}x), {out}t AS MATERIALIZED (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS rank, id, score FROM {out} QUALIFY rank <= {k})"
    return f"""{out}p AS MATERIALIZED (SELECT qid, t, p.cell, list_dot_product(qv, c) AS ip FROM tq, {cent} p QUALIFY row_number() OVER (PARTITION BY qid ORDER BY ip DESC, p.cell) <= {n_p}),
{out} AS MATERIALIZED (SELECT qid, id, ip + norm * list_dot_product(t, dec) AS score FROM {out}p JOIN {tag}x USING (cell)),
{out}t AS MATERIALIZED (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS rank, id, score FROM {out} QUALIFY rank <= {k})"""


def _batched(src: str = "base", n: int = 4) -> str:
    return f"bb AS MATERIALIZED (SELECT id, v, id * {n} // (SELECT max(id) + 1 FROM {src}) AS batch FROM {src})"


def _sample(src: str = "xx", size: str = "count(*) // 10") -> str:
    """sm: coded rows by cell, as ``refresh.sample`` takes them."""
    return f"sz AS (SELECT cell, greatest(1, ceil(count(*) * least(1.0::DOUBLE, (SELECT {size} FROM {src})::DOUBLE / (SELECT count(*) FROM {src})))) AS quota FROM {src} GROUP BY cell), sm AS MATERIALIZED (SELECT cell, id FROM (SELECT cell, id, quota, row_number() OVER (PARTITION BY cell ORDER BY md5('42:' || id), id) AS r FROM {src} JOIN sz USING (cell)) WHERE r <= quota)"


def _with(*parts: str) -> str:
    return "WITH " + ",\n".join(p.strip() for p in parts)


_TRUTH = f"truth AS MATERIALIZED (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY list_dot_product(v, qv) DESC, id) AS rank, id, list_dot_product(v, qv) AS ip FROM base, qs QUALIFY rank <= {K})"
_RECALL = f"SELECT round(avg(r), 4) AS recall FROM (SELECT qid, count(f.id) / {K}.0 AS r FROM truth t LEFT JOIN {{0}} f USING (qid, id) GROUP BY qid)"

# ---------------------------------------------------------------- Spark side


def _e(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return ds.split(ds.embeddings(spark, sf_dir))


def batched(df: DataFrame, n: int = 4) -> DataFrame:
    """df with a batch number: n equal shares of the range of ids."""
    top = df.agg(F.max("id").alias("top"))
    return df.crossJoin(F.broadcast(top)).withColumn("batch", F.expr(f"CAST(id * {n} DIV (top + 1) AS INT)")).drop("top")


def _index(base: DataFrame, stage2: str = "sign", b: int = BITS, cells: int = L) -> tuple[cfi.Index, DataFrame]:
    return cfi.build(base, cells, b, stage2, SEED, ROUNDS, d=D, exact_norm=True)


def _csv(v) -> F.Column:
    return F.concat_ws(",", F.transform(v, lambda x: x.cast("string")))


def code_lists(codes: DataFrame, index: cfi.Index) -> DataFrame:
    """(id, cell, norm, code_csv, sign_csv) of packed codes, for reports and comparisons."""

    def go(batches):
        for b in batches:
            if b.num_rows:
                _, cell, code, sign, n = cfi._read(b, index)
                text = [",".join(map(str, row)) for row in code.tolist()], [",".join(map(str, row)) for row in sign.tolist()]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(cell), pa.array(n), pa.array(text[0]), pa.array(text[1])], names=["id", "cell", "norm", "code_csv", "sign_csv"])

    return codes.mapInArrow(go, "id long, cell long, norm double, code_csv string, sign_csv string")


def _shown(found: DataFrame) -> DataFrame:
    return found.select("qid", F.col("rank").cast("long").alias("rank"), F.col("id").alias("vec_id"), F.round("score", 6).alias("score"))


def normalise_check(spark, sf_dir):
    t = ds.table(spark, sf_dir, "embeddings")
    return t.select("vec_id", F.round(norm("embedding"), 6).alias("norm_rounded"), is_bad("embedding").alias("bad"))


def exact_knn(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    return exact.knn(base, q, K).select("qid", F.col("rank").cast("long").alias("rank"), F.col("id").alias("vec_id"), F.round("score", 6).alias("ip"))


def exact_knn_native(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    return exact.knn_native(base, q, K).select("qid", F.col("rank").cast("long").alias("rank"), F.col("id").alias("vec_id"), F.round("score", 6).alias("ip"))


def exact_knn_cumulative(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    b = base.withColumn("batch", (F.col("id") % 4).cast("int"))
    return exact.knn_cumulative(b, q, K).select(F.col("batch").cast("long").alias("batch"), "qid", F.col("rank").cast("long").alias("rank"), F.col("id").alias("vec_id"))


def exact_knn_merge(spark, sf_dir):
    """Incremental truth: what was known merged with a new batch's own."""
    base, q = _e(spark, sf_dir)
    old, new = exact.knn(base.where("id % 4 < 3"), q, K), exact.knn(base.where("id % 4 = 3"), q, K)
    return exact.merge(old, new, K).select("qid", F.col("rank").cast("long").alias("rank"), F.col("id").alias("vec_id"), F.round("score", 6).alias("ip"))


def _flat(spark, sf_dir, stage2="sign"):
    base, q = _e(spark, sf_dir)
    index, codes = cfi.build(base, 0, BITS, stage2, SEED, d=D, exact_norm=True)
    return base, q, index, codes


def gsq_codes(spark, sf_dir):
    _, _, index, codes = _flat(spark, sf_dir)
    return code_lists(codes, index).select(F.col("id").alias("vec_id"), "code_csv")


def gsq_sign_bits(spark, sf_dir):
    _, _, index, codes = _flat(spark, sf_dir)
    return code_lists(codes, index).select(F.col("id").alias("vec_id"), "sign_csv")


def gsq_design(spark, sf_dir):
    """The levels of each design, and how many coordinates of the unit embeddings each codes."""

    def go(batches):
        for x in batches:
            if x.num_rows:
                v = matrix(x.column(0)).ravel()
                for b in range(1, 7):
                    n = np.bincount(scalarq.design(b, D).encode(v), minlength=1 << b)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), b)), pa.array(np.arange(len(n))), pa.array(n)], names=["b", "idx", "n"])

    coded = ds.embeddings(spark, sf_dir).select("v").mapInArrow(go, "b long, idx long, n long").groupBy("b", "idx").agg(F.sum("n").alias("n"))
    rows = [(b, i, round(float(v), 6), round(scalarq.design(b).distortion, 6)) for b in range(1, 7) for i, v in enumerate(scalarq.design(b).levels)]
    return spark.createDataFrame(rows, "b long, idx long, level double, d_b double").join(coded, ["b", "idx"], "left").na.fill(0, ["n"])


def gsq_reconstruction_mse(spark, sf_dir):
    out = None
    base, q = _e(spark, sf_dir)
    for stage2 in ("none", "sign"):
        one = cfi.inner_error(base, cfi.Index(D, BITS, None, stage2, SEED), q).select(F.lit(BITS).cast("long").alias("b"), F.lit(stage2).alias("stage2"), F.round("mse", 8).alias("mse"))
        out = one if out is None else out.unionByName(one)
    return out


def rsq_flat_topk(spark, sf_dir):
    _, q, index, codes = _flat(spark, sf_dir, "none")
    return _shown(cfi.search(codes, index, q, K)).drop("score")


def coarse_kmeans(spark, sf_dir):
    base, _ = _e(spark, sf_dir)
    c = coarse.fit(base, L, ROUNDS, SEED)
    sizes = coarse.assign(base, c).groupBy("cell").agg(F.count("*").alias("n"))
    sums = spark.createDataFrame([(i, float(np.dot(v, np.arange(1, D + 1)))) for i, v in enumerate(c)], "cell long, s double")
    return sums.join(sizes, "cell", "left").select("cell", F.coalesce("n", F.lit(0)).alias("n"), F.round("s", 6).alias("c_checksum"))


def coarse_assign(spark, sf_dir):
    base, _ = _e(spark, sf_dir)
    return coarse.assign(base, coarse.fit(base, L, ROUNDS, SEED)).select(F.col("id").alias("vec_id"), "cell", F.round("ip", 6).alias("ip"))


def cfi_codes(spark, sf_dir):
    base, _ = _e(spark, sf_dir)
    index, codes = _index(base)
    return code_lists(codes, index).select(F.col("id").alias("vec_id"), "cell", "code_csv", F.round("norm", 6).alias("norm"))


def cfi_probe(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    index, _ = _index(base)
    return cfi.probes_frame(index, q, NP).select("qid", "cell", F.col("rank").cast("long").alias("rank"))


def _cfi_search(stage2):
    def run(spark, sf_dir):
        base, q = _e(spark, sf_dir)
        index, codes = _index(base, stage2)
        return _shown(cfi.search(codes, index, q, K, NP))

    return run


def cfi_search_joined(spark, sf_dir):
    """The join way for many queries."""
    base, q = _e(spark, sf_dir)
    index, codes = _index(base)
    return _shown(cfi.search_join(codes, index, q, K, NP, salt_rows=20))


def cfi_search_rerank(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    index, codes = _index(base)
    return _shown(cfi.rerank(cfi.search(codes, index, q, 50, NP), base, q, K, 50)).withColumnRenamed("score", "ip")


def cfi_cascade(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    index, codes = _index(base)
    return _shown(cfi.cascade(codes, index, q, K, NP)).drop("score")


def cfi_recall_by_nprobe(spark, sf_dir):
    base, q = _e(spark, sf_dir)
    index, codes = _index(base)
    truth, out = exact.knn(base, q, K).persist(), None
    for n_p in (1, 2, 4, 8, 16):
        r = metrics.recall(cfi.search(codes, index, q, K, n_p), truth, K).select(F.lit(n_p).cast("long").alias("n_p"), F.round("recall", 4).alias("recall"))
        out = r if out is None else out.unionByName(r)
    return out


def cfi_insert_batches(spark, sf_dir):
    """Partition fitted on the first batch, the others appended unchanged; recall of the cumulative table after each."""
    base, q = _e(spark, sf_dir)
    b = batched(base)
    index, _ = cfi.build(b.where("batch = 0").select("id", "v"), 8, BITS, "sign", SEED, ROUNDS, d=D, exact_norm=True)
    codes = cfi.encode(b, index).join(b.select("id", "batch"), "id")
    found = exact.accumulate(cfi.search(codes, index, q, K, NP, extra="batch").drop("rank"), K)
    truth = exact.knn_cumulative(b, q, K)
    r = metrics.recall(found, truth, K, ("batch",))
    n = b.groupBy("batch").agg(F.count("*").alias("n"))
    return r.join(n, "batch").select(F.col("batch").cast("long").alias("batch"), "n", F.round("recall", 4).alias("recall"))


def _old_epoch(spark, sf_dir):
    """An index fitted on the first quarter of the ids, and the codes of all rows under it."""
    base, _ = _e(spark, sf_dir)
    index, _ = cfi.build(batched(base).where("batch = 0").select("id", "v"), 8, BITS, "sign", SEED, 2, d=D, exact_norm=True)
    return base, index, cfi.encode(base, index)


def _tenth(df: DataFrame) -> int:
    return df.count() // 10


def refresh_sample(spark, sf_dir):
    _, _, codes = _old_epoch(spark, sf_dir)
    return refresh.sample(codes, _tenth(codes), SEED).select("cell", F.col("id").alias("vec_id"))


def _refreshed(raw: bool):
    def run(spark, sf_dir):
        base, index, codes = _old_epoch(spark, sf_dir)
        _, new = refresh.run(index, codes, base if raw else None, size=_tenth(base), cells=8, iters=2, seed=SEED)
        return new.select(F.col("epoch").cast("long").alias("epoch"), F.col("id").alias("vec_id"), "cell")

    return run


def amplification(spark, sf_dir):
    out = None
    for name, v in (("E", ds.embeddings(spark, sf_dir)), ("A(2.5)", ds.anchored(spark, sf_dir))):
        base, q = ds.split(v)
        index, _ = _index(base)
        r = diagnostics.amplification(base, index, q).select(F.lit(name).alias("set"), *(F.round(c, 5).alias(c) for c in ("affinity", "predicted", "measured")))
        out = r if out is None else out.unionByName(r)
    return out


def _labels(spark, sf_dir) -> DataFrame:
    """(label, n, d): rows and dimension of the embeddings of each label."""
    return ds.table(spark, sf_dir, "embeddings").groupBy("label").agg(F.count("*").alias("n"), F.max(F.size("embedding")).cast("long").alias("d"))


def bounds_table(spark, sf_dir):
    """The bounds at which all vectors of a label hold together: a chance of 0.05 is shared among its rows."""

    def go(batches):
        for x in batches:
            rows = [(r["label"], b, r["d"], 0.05 / r["n"]) for r in x.to_pylist() if r["d"] > 2 for b in (2, 4)]
            found = [(*r, bounds.single(*r[1:]), *bounds.worst_case(*r[1:3]), bounds.uniform(*r[1:])) for r in rows]
            names = ["label", "b", "d", "delta", "single", "worst_low", "worst_case", "uniform"]
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if i < 3 else pa.float64()) for i, c in enumerate(zip(*found, strict=True))], names=names)

    return _labels(spark, sf_dir).mapInArrow(go, "label long, b long, d long, delta double, single double, worst_low double, worst_case double, uniform double")


def pq_assign(spark, sf_dir):
    base, _ = _e(spark, sf_dir)
    cb = pq.from_first_rows(base, 8, 4)
    return pq.encode(base, cb).select(F.col("id").alias("vec_id"), _csv(F.col("code")).alias("codes_csv"))


def partition_health(spark, sf_dir):
    base, _ = _e(spark, sf_dir)
    h = metrics.partition_health(coarse.assign(base, coarse.fit(base, L, ROUNDS, SEED)), L)
    return h.select("occupied", "empty", "smallest", "largest", F.round("skew", 6).alias("skew"), F.round("affinity", 6).alias("affinity"))


def swap_cosine(spark, sf_dir):
    e, out = ds.embeddings(spark, sf_dir), None
    for c in (0.51, 0.24):
        r = metrics.swap_cosine(e, ds.rotated(e, D, 99, c)).select(F.lit(c).alias("c"), "n", F.round("mean", 5).alias("mean"), F.round("sd", 5).alias("sd"))
        out = r if out is None else out.unionByName(r)
    return out


def hash_embed(spark, sf_dir):
    """Slots of each whole text, as the vector sets hash them."""
    t = ds.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    return ds.hashed_slots(t, 96).select(F.col("id").alias("doc_id"), F.col("slot").cast("long").alias("slot"), F.col("x").cast("long").alias("v"))


def regime_accounting(spark, sf_dir):
    """Bits of product quantizers over those of the index, at the dimension of each label's embeddings."""
    m = F.explode(F.array(*(F.struct(x.cast("long").alias("m"), F.lit(b).cast("long").alias("pq_b")) for x, b in ((F.expr("d div 2"), 8), (F.expr("d div 2"), 10), (F.col("d"), 8)))))
    t = _labels(spark, sf_dir).select("label", "n", "d", m.alias("x")).select("label", "n", "d", "x.m", "x.pq_b")
    return t.select("*", cost.bits(4, F.col("d")).alias("cfi_bits"), cost.pq_bits(F.col("m"), F.col("pq_b")).alias("pq_bits"), F.round(cost.regime(F.col("m"), F.col("pq_b"), F.col("d")), 4).alias("ratio"))


def memory_accounting(spark, sf_dir):
    """MiB of the embeddings of each label, as coded rows with L centroids."""
    t = _labels(spark, sf_dir).withColumn("total_bits", F.explode(F.array(*(F.lit(b).cast("long") for b in (4, 5, 6)))))
    bits = cost.bits(F.col("total_bits") - 1, F.col("d"))
    return t.select("label", "n", "total_bits", bits.alias("bits"), F.round(cost.memory_mib(F.col("n"), bits, L, F.col("d")), 6).alias("mib"))


def rerank_memory(spark, sf_dir):
    """MiB of the embeddings as they are, as codes with L centroids, as both, and in a graph."""
    t = ds.table(spark, sf_dir, "embeddings").agg(F.count("*").alias("n"), F.max(F.size("embedding")).cast("long").alias("d"))
    n, d = F.col("n"), F.col("d")
    raw, codes, both = cost.rerank_memory_mib(n, cost.bits(4, d), L, d)
    return t.select(*(F.round(x, 6).alias(name) for x, name in ((raw, "raw"), (codes, "codes"), (both, "both"), (cost.graph_bytes(n, d, 32) / cost.MIB, "graph"))))


def paired_t(spark, sf_dir):
    """Discount less tax in points, by state of the line item: mean of three folds of the orders, its half width and p."""
    x = F.round((F.col("l_discount") - F.col("l_tax")) * 100).cast("long")
    t = ds.table(spark, sf_dir, "lineitem").select(F.concat_ws("-", "l_returnflag", "l_linestatus").alias("pair"), (F.col("l_orderkey") % 3).alias("fold"), x.alias("x"))
    folds = t.groupBy("pair", "fold").agg((F.sum("x") / F.count("x")).alias("value"))
    each = stats.summarise(folds, ["pair"]).where("n = 3 AND half > 0")
    return each.select("pair", F.round("mean", 6).alias("mean"), F.round("half", 6).alias("half"), F.round(stats.p_of_two(F.col("mean"), F.col("half")), 6).alias("p"))


def _learned(kind: str):
    def run(spark, sf_dir):
        base, q = ds.split(ds.anchored(spark, sf_dir))
        truth = exact.knn(base, q, K)
        if kind == "opq":
            cb = pq.fit(base, 16, 4, L, rotate=True, iters=5, rounds=3)
            found = pq.search(pq.encode(base, cb), cb, q, K, NP)
        elif kind == "ivpq":
            cb = pq.fit(base, 16, 4, L, iters=5)
            found = pq.search(pq.encode(base, cb), cb, q, K, NP)
        elif kind == "pq":
            cb = pq.fit(base, 16, 4, iters=5)
            found = pq.search(pq.encode(base, cb), cb, q, K)
        elif kind == "atq":
            cb = pq.atq(base, L, 16, 4, iters=5)
            found = pq.atq_search(pq.encode(base, cb), cb, base, q, K, NP, 50)
        elif kind == "hnsw":
            found = graph.search(base, q, K)
        else:
            found = lsh.search(base, q, K)
        return metrics.recall(found, truth, K).select(F.lit(kind).alias("method"), F.round("recall", 4).alias("recall"))

    return run


def matched_memory_tie(spark, sf_dir):
    """Stage 1 at B bits, and B - 1 bits with refinement, in the same partition."""
    base, q = _e(spark, sf_dir)
    truth, c, out = exact.knn(base, q, K).persist(), coarse.fit(base, L, ROUNDS, SEED), None
    for total in (4, 5):
        both = []
        for b, stage2 in ((total, "none"), (total - 1, "sign")):
            index = cfi.Index(D, b, c, stage2, SEED, exact_norm=True)
            both.append(metrics.recall(cfi.search(cfi.encode(base, index), index, q, K, NP), truth, K).select(F.col("recall").alias("xbq" if stage2 == "none" else "cfi")))
        one = both[0].crossJoin(both[1]).select(F.lit("E").alias("set"), F.lit(total).cast("long").alias("B"), F.round("xbq", 4).alias("xbq"), F.round("cfi", 4).alias("cfi"), F.round(F.col("cfi") - F.col("xbq"), 4).alias("delta"))
        out = one if out is None else out.unionByName(one)
    return out


def _stream(method: str):
    def run(spark, sf_dir):
        from annspark.plans import workloads

        r = workloads.w06_streaming_small(spark, sf_dir, orders=("shuffled",)) if method in ("stale", "retrain") else None
        return r.where((F.col("method") == method) & (F.col("metric") == "recall")).select("batch", F.round("value", 4).alias("recall"))

    return run


def _shifted(name: str):
    def run(spark, sf_dir):
        from annspark.plans import workloads

        r = workloads.w10_encoder_swap(spark, sf_dir) if name == "swap" else workloads.w11_rotation_stress(spark, sf_dir, rr=(0, 50))
        return r.where("metric = 'recall'").select("method", "regime", F.round("value", 4).alias("recall"))

    return run


def pareto_front(spark, sf_dir):
    """Kinds of line items that none beats on mean discount (cost) and mean quantity (value)."""
    mean = lambda c, by: F.sum(F.round(F.col(c) * by).cast("long")) / F.count(c)
    kinds = ds.table(spark, sf_dir, "lineitem").groupBy(F.concat_ws("-", "l_returnflag", "l_linestatus", "l_linenumber").alias("method"))
    return metrics.pareto(kinds.agg(mean("l_discount", 100).alias("cost"), mean("l_quantity", 1).alias("value")))


def bias_capacity(spark, sf_dir):
    """Mean value of each kind of event from the first fifth of the ids, a random fifth, and all: bias is random less first, capacity all less random."""
    e = ds.table(spark, sf_dir, "events").select("event_id", F.col("event_type").alias("dataset"), F.round(F.col("value") * 100).cast("long").alias("x"))
    top = e.agg(F.max("event_id").alias("top"))
    first = F.when(F.col("event_id") * 5 <= F.col("top"), "first")
    chance = F.when(F.substring(F.md5(F.concat(F.lit(f"{SEED}:"), F.col("event_id").cast("string")).cast("binary")), 1, 2) < "33", "random")
    arms = e.crossJoin(F.broadcast(top)).select("dataset", "x", F.explode(F.array(first, chance, F.lit("all"))).alias("method")).where("method IS NOT NULL")
    r = metrics.bias_capacity(arms.groupBy("dataset", "method").agg((F.sum("x") / F.count("x")).alias("value")))
    return r.select("dataset", F.round("bias", 4).alias("bias"), F.round("capacity", 4).alias("capacity"))


QUERIES = {f.__name__: f for f in (matched_memory_tie, pareto_front, bias_capacity, normalise_check, exact_knn, exact_knn_native, exact_knn_cumulative, exact_knn_merge, gsq_codes, gsq_sign_bits, gsq_design, gsq_reconstruction_mse, rsq_flat_topk, coarse_kmeans, coarse_assign, cfi_codes, cfi_probe, cfi_search_joined, cfi_search_rerank, cfi_cascade, cfi_recall_by_nprobe, cfi_insert_batches, refresh_sample, amplification, bounds_table, pq_assign, partition_health, swap_cosine, hash_embed, regime_accounting, memory_accounting, rerank_memory, paired_t)}
QUERIES |= {"cfi_search_none": _cfi_search("none"), "cfi_search_sign": _cfi_search("sign"), "cfi_refresh_raw": _refreshed(True), "cfi_refresh_recon": _refreshed(False)}
QUERIES |= {"ivpq_stream_stale": _stream("stale"), "ivpq_stream_retrain": _stream("retrain"), "swap_stream": _shifted("swap"), "rotation_stress": _shifted("rotation")}
QUERIES |= {f"{k}_recall": _learned(k) for k in ("pq", "ivpq", "opq", "atq", "hnsw", "lsh")}


def oracle_sql() -> dict[str, str]:
    q4, q = scalarq.design(BITS, D), _nums
    flat = _with(E_SQL, _rot(), _encode("base", None, q4, "f", True))
    flat_none = _with(E_SQL, _rot(), _encode("base", None, q4, "f", False), _turned(), _search("f", None, 0, K, "s"))
    km = _with(E_SQL, _kmeans())
    cent = f"c{ROUNDS}"
    full = lambda refine, k=K: _with(E_SQL, _rot(), _kmeans(), _encode("base", cent, q4, "x", refine), _turned(), _search("x", cent, NP, k, "s"))
    shown = "SELECT qid, rank, id AS vec_id, round(score, 6) AS score FROM st"
    out = {
        "normalise_check": "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm_rounded, (embedding IS NULL OR list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)) = 0) AS bad FROM embeddings",
        "exact_knn": _with(E_SQL, _TRUTH) + " SELECT qid, rank, id AS vec_id, round(ip, 6) AS ip FROM truth",
        "exact_knn_cumulative": _with(E_SQL) + f" SELECT t AS batch, qid, row_number() OVER (PARTITION BY t, qid ORDER BY list_dot_product(v, qv) DESC, id) AS rank, id AS vec_id FROM base, qs, range(0, 4) r(t) WHERE id % 4 <= t QUALIFY rank <= {K}",
        "gsq_codes": flat + " SELECT id AS vec_id, array_to_string(codes, ',') AS code_csv FROM fx",
        "gsq_sign_bits": flat + " SELECT id AS vec_id, array_to_string(signs, ',') AS sign_csv FROM fx",
        "rsq_flat_topk": flat_none + " SELECT qid, rank, id AS vec_id FROM st",
        "coarse_kmeans": km + f", n AS (SELECT cell, count(*) AS n FROM (SELECT p.cell FROM base b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1) GROUP BY cell) SELECT cell, coalesce(n, 0) AS n, round(list_dot_product(c, {q(range(1, D + 1))}), 6) AS c_checksum FROM {cent} LEFT JOIN n USING (cell)",
        "coarse_assign": km + f" SELECT id AS vec_id, cell, round(ip, 6) AS ip FROM (SELECT b.id, p.cell, list_dot_product(b.v, p.c) AS ip FROM base b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY ip DESC, p.cell) = 1)",
        "cfi_codes": _with(E_SQL, _rot(), _kmeans(), _encode("base", cent, q4, "x", True)) + " SELECT id AS vec_id, cell, array_to_string(codes, ',') AS code_csv, round(norm, 6) AS norm FROM xx",
        "cfi_probe": km + f" SELECT qid, p.cell, row_number() OVER (PARTITION BY qid ORDER BY list_dot_product(qv, c) DESC, p.cell) AS rank FROM qs, {cent} p QUALIFY rank <= {NP}",
        "cfi_search_none": full(False) + shown,
        "cfi_search_sign": full(True) + shown,
        "cfi_search_rerank": full(True, 50) + f", rr AS (SELECT qid, id, list_dot_product(v, qv) AS ip FROM st JOIN base USING (id) JOIN qs USING (qid)) SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY ip DESC, id) AS rank, id AS vec_id, round(ip, 6) AS ip FROM rr QUALIFY rank <= {K}",
        "cfi_recall_by_nprobe": _with(E_SQL, _TRUTH, _rot(), _kmeans(), _encode("base", cent, q4, "x", True), _turned(), *(_search("x", cent, p, K, f"s{p}") for p in (1, 2, 4, 8, 16))) + " UNION ALL ".join(f" SELECT {p} AS n_p, recall FROM ({_RECALL.format(f's{p}t')})" for p in (1, 2, 4, 8, 16)),
        "pq_assign": _with(E_SQL, "f AS (SELECT row_number() OVER (ORDER BY id) - 1 AS code, v FROM base QUALIFY code < 16)", "n AS (SELECT b.id, s, f.code, row_number() OVER (PARTITION BY b.id, s ORDER BY list_distance(b.v[s * 8 + 1:s * 8 + 8], f.v[s * 8 + 1:s * 8 + 8]), f.code) AS r FROM base b, f, range(0, 8) t(s))") + " SELECT id AS vec_id, string_agg(code::VARCHAR, ',' ORDER BY s) AS codes_csv FROM n WHERE r = 1 GROUP BY id",
        "hash_embed": "WITH w AS (SELECT doc_id, unnest(list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '')) AS w FROM documents), h AS (SELECT doc_id, ('0x' || md5(w)[1:8])::BIGINT AS h FROM w) SELECT doc_id, h % 96 AS slot, CAST(sum(CASE WHEN (h >> 20) & 1 = 1 THEN 1 ELSE -1 END) AS BIGINT) AS v FROM h GROUP BY 1, 2 HAVING v <> 0",
        "paired_t": f"WITH f AS (SELECT l_returnflag || '-' || l_linestatus AS pair, l_orderkey % 3 AS fold, sum(CAST(round((l_discount - l_tax) * 100) AS BIGINT))::DOUBLE / count(l_discount - l_tax) AS v FROM lineitem GROUP BY 1, 2), m AS (SELECT pair, avg(v) AS mean, {stats.T_TWO} * stddev_samp(v) / sqrt(3) AS half FROM f GROUP BY pair HAVING count(v) = 3 AND half > 0) SELECT pair, round(mean, 6) AS mean, round(half, 6) AS half, round(1 - t / sqrt(t * t + 2), 6) AS p FROM (SELECT *, abs(mean) / (half / {stats.T_TWO}) AS t FROM m)",
        "regime_accounting": "SELECT label, n, d, m, b AS pq_b, 5 * d + 32 AS cfi_bits, m * b AS pq_bits, round(m * b / (5 * d + 32)::DOUBLE, 4) AS ratio FROM (SELECT label, n, d, unnest([d // 2, d // 2, d])::BIGINT AS m, unnest([8, 10, 8])::BIGINT AS b FROM (SELECT label, count(*) AS n, max(len(embedding)) AS d FROM embeddings GROUP BY label))",
        "memory_accounting": f"SELECT label, n, t AS total_bits, t * d + 32 AS bits, round((n * (t * d + 32) / 8.0::DOUBLE + {L} * d * 4) / 1048576::DOUBLE, 6) AS mib FROM (SELECT label, count(*) AS n, max(len(embedding)) AS d FROM embeddings GROUP BY label), range(4, 7) b(t)",
        "rerank_memory": f"SELECT round(raw, 6) AS raw, round(codes, 6) AS codes, round(raw + codes, 6) AS both, round(n * (4 * d + 8 * 32) / 1048576::DOUBLE, 6) AS graph FROM (SELECT n, d, n * d * 4 / 1048576::DOUBLE AS raw, (n * (5 * d + 32) / 8.0::DOUBLE + {L} * d * 4) / 1048576::DOUBLE AS codes FROM (SELECT count(*) AS n, max(len(embedding)) AS d FROM embeddings))",
        "gsq_design": _with(E_SQL, "t AS (SELECT b::BIGINT AS b, idx::BIGINT AS idx, level::DOUBLE AS level, d_b::DOUBLE AS d_b FROM (VALUES " + ",".join(f"({b},{i},{round(float(v), 6)},{round(scalarq.design(b).distortion, 6)})" for b in range(1, 7) for i, v in enumerate(scalarq.design(b).levels)) + ") t(b, idx, level, d_b))", "g AS (SELECT b, edges FROM (VALUES " + ",".join(f"({b}, {q(scalarq.design(b, D).edges)})" for b in range(1, 7)) + ") g(b, edges))", "c AS (SELECT b, len(list_filter(edges, lambda y: y <= x)) AS idx, count(*) AS n FROM (SELECT unnest(v) AS x FROM e), g GROUP BY 1, 2)") + " SELECT t.b, t.idx, level, d_b, coalesce(n, 0) AS n FROM t LEFT JOIN c ON c.b = t.b AND c.idx = t.idx",
        "gsq_reconstruction_mse": _with(E_SQL, _rot(), _encode("base", None, q4, "f", False), _encode("base", None, q4, "g", True)) + " SELECT 4::BIGINT AS b, 'none' AS stage2, round(avg(list_sum(list_transform(list_zip(u, dec), lambda z: (z[1] - z[2]) * (z[1] - z[2])))), 8) AS mse FROM fx UNION ALL SELECT 4, 'sign', round(avg(list_sum(list_transform(list_zip(u, dec), lambda z: (z[1] - z[2]) * (z[1] - z[2])))), 8) FROM gx",
        "partition_health": km + f", a AS (SELECT b.id, p.cell, list_dot_product(b.v, p.c) AS ip FROM base b, {cent} p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY ip DESC, p.cell) = 1), n AS (SELECT cell, count(*) AS n, sum(ip) AS ip FROM a GROUP BY cell) SELECT count(*) AS occupied, {L} - count(*) AS empty, min(n) AS smallest, max(n) AS largest, round(max(n) / (sum(n) / {L}.0::DOUBLE), 6) AS skew, round(sum(ip) / sum(n), 6) AS affinity FROM n",
        "swap_cosine": _with(E_SQL, _rot(D, 99, "turn"), "ry AS MATERIALIZED (SELECT id, v, list(list_dot_product(v, r) ORDER BY j) AS y FROM e, turn GROUP BY id, v)", "z AS (SELECT id, c, v, list_transform(list_zip(v, y), lambda z: c * z[1] + sqrt(1 - c * c) * z[2]) AS z FROM ry, (VALUES (0.51::DOUBLE), (0.24::DOUBLE)) t(c))") + " SELECT c, count(*) AS n, round(avg(list_dot_product(v, z) / sqrt(list_dot_product(z, z))), 5) AS mean, round(stddev_samp(list_dot_product(v, z) / sqrt(list_dot_product(z, z))), 5) AS sd FROM z GROUP BY c",
    }
    out["exact_knn_native"] = out["exact_knn_merge"] = out["exact_knn"]
    out["cfi_search_joined"] = out["cfi_search_sign"]
    # inserts: partition of the first batch, all rows encoded, cumulative search and truth
    out["cfi_insert_batches"] = (
        _with(E_SQL, _batched(), "b0 AS (SELECT id, v FROM bb WHERE batch = 0)", _rot(), _kmeans("b0", 8), _encode("base", cent, q4, "x", True), _turned(),
              f"sp AS MATERIALIZED (SELECT qid, t, p.cell, list_dot_product(qv, c) AS ip FROM tq, {cent} p QUALIFY row_number() OVER (PARTITION BY qid ORDER BY ip DESC, p.cell) <= {NP})",
              "s AS MATERIALIZED (SELECT qid, id, batch, ip + norm * list_dot_product(t, dec) AS score FROM sp JOIN xx USING (cell) JOIN bb USING (id))",
              f"f AS (SELECT u.t AS batch, qid, id, row_number() OVER (PARTITION BY u.t, qid ORDER BY score DESC, id) AS rank FROM s, range(0, 4) u(t) WHERE s.batch <= u.t QUALIFY rank <= {K})",
              f"g AS (SELECT u.t AS batch, qid, id, row_number() OVER (PARTITION BY u.t, qid ORDER BY list_dot_product(v, qv) DESC, id) AS rank FROM bb, qs, range(0, 4) u(t) WHERE bb.batch <= u.t QUALIFY rank <= {K})",
              f"r AS (SELECT batch, qid, count(f.id) / {K}.0 AS r FROM g LEFT JOIN f USING (batch, qid, id) GROUP BY batch, qid)", "n AS (SELECT batch, count(*) AS n FROM bb GROUP BY batch)")
        + " SELECT r.batch AS batch, any_value(n) AS n, round(avg(r), 4) AS recall FROM r JOIN n ON n.batch = r.batch GROUP BY r.batch"
    )
    old = (E_SQL, _batched(), "b0 AS (SELECT id, v FROM bb WHERE batch = 0)", _rot(), _kmeans("b0", 8, 2), _encode("base", "c2", q4, "x", True))
    pick = _sample()
    out["refresh_sample"] = _with(*old, pick) + " SELECT cell, id AS vec_id FROM sm"
    again = lambda src: (f"smv AS MATERIALIZED (SELECT id, v FROM {src} WHERE id IN (SELECT id FROM sm))", _kmeans("smv", 8, 2, tag="k"))
    final = lambda src: f" SELECT 1 AS epoch, b.id AS vec_id, p.cell FROM {src} b, k2 p QUALIFY row_number() OVER (PARTITION BY b.id ORDER BY list_dot_product(b.v, p.c) DESC, p.cell) = 1"
    out["cfi_refresh_raw"] = _with(*old, pick, *again("base")) + final("base")
    rec = "back AS (SELECT id, cell, norm, list(d ORDER BY i) AS w FROM (SELECT x.id, x.cell, x.norm, i, list_dot_product(x.dec, cols.col) AS d FROM xx x, cols) GROUP BY id, cell, norm), rv AS (SELECT b.id, list_transform(list_zip(c2.c, b.w), lambda z: z[1] + b.norm * z[2]) AS z FROM back b JOIN c2 USING (cell)), rec AS MATERIALIZED (SELECT id, list_transform(z, lambda x: x / sqrt(list_dot_product(z, z))) AS v FROM rv)"
    cols = "cols AS MATERIALIZED (SELECT i, list(r[i] ORDER BY j) AS col FROM rot, range(1, 65) t(i) GROUP BY i)"
    out["cfi_refresh_recon"] = _with(*old, pick, cols, rec, *again("rec")) + final("rec")
    # cascade: stage-1 search keeps 8k, then refined scores of the kept pairs
    out["cfi_cascade"] = _with(E_SQL, _rot(), _kmeans(), _encode("base", cent, q4, "x", False), _turned(), _search("x", cent, NP, 8 * K, "s"), _encode("base", cent, q4, "y", True), _search("y", cent, NP, 10_000, "w")) + f", kept AS (SELECT st.qid, st.id, w.score FROM st JOIN w ON w.qid = st.qid AND w.id = st.id) SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS rank, id AS vec_id FROM kept QUALIFY rank <= {K}"
    tie = [_with(E_SQL, _TRUTH, _rot(), _kmeans(), _turned(), _encode("base", cent, scalarq.design(b, D), "p", False), _search("p", cent, NP, K, "s"), _encode("base", cent, scalarq.design(b - 1, D), "r", True), _search("r", cent, NP, K, "t")) + f", a AS ({_RECALL.format('st').replace('round(avg(r), 4)', 'avg(r)')}), b AS ({_RECALL.format('tt').replace('round(avg(r), 4)', 'avg(r)')}) SELECT 'E' AS set, {b}::BIGINT AS B, round(a.recall, 4) AS xbq, round(b.recall, 4) AS cfi, round(b.recall - a.recall, 4) AS delta FROM a, b" for b in (4, 5)]
    out["matched_memory_tie"] = f"SELECT * FROM ({tie[0]}) UNION ALL SELECT * FROM ({tie[1]})"
    out["pareto_front"] = "WITH p AS (SELECT l_returnflag || '-' || l_linestatus || '-' || l_linenumber AS method, sum(CAST(round(l_discount * 100) AS BIGINT))::DOUBLE / count(l_discount) AS cost, sum(CAST(round(l_quantity) AS BIGINT))::DOUBLE / count(l_quantity) AS value FROM lineitem GROUP BY 1) SELECT * FROM p a WHERE NOT EXISTS (SELECT 1 FROM p b WHERE b.cost <= a.cost AND b.value >= a.value AND (b.cost < a.cost OR b.value > a.value))"
    out["bias_capacity"] = f"WITH e AS (SELECT event_type AS dataset, event_id AS id, CAST(round(value * 100) AS BIGINT) AS x, max(event_id) OVER () AS top FROM events), m AS (SELECT dataset, sum(x) FILTER (id * 5 <= top)::DOUBLE / count(x) FILTER (id * 5 <= top) AS f, sum(x) FILTER (md5('{SEED}:' || id)[1:2] < '33')::DOUBLE / count(x) FILTER (md5('{SEED}:' || id)[1:2] < '33') AS r, sum(x)::DOUBLE / count(x) AS a FROM e GROUP BY dataset) SELECT dataset, round((r - f) * 100, 4) AS bias, round((a - r) * 100, 4) AS capacity FROM m"
    # amplification: rotated errors against rotated queries, flat and partitioned, on the plain and the anchored set
    anchored = E_SQL.replace("SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings", "SELECT f.vec_id AS id, list_transform(list_zip(a.a, f.embedding), lambda z: 2.5 * z[1]::DOUBLE + z[2]::DOUBLE) AS e FROM embeddings f JOIN (SELECT label, arg_min(embedding, vec_id) AS a FROM embeddings GROUP BY label) a USING (label)")
    err = lambda t, n: f"(SELECT avg(s * s) FROM (SELECT {n} * list_dot_product(t, list_transform(list_zip(u, dec), lambda z: z[1] - z[2])) AS s FROM {t}x, tq))"
    amp = lambda name, src: _with(src, _rot(), _kmeans(), _turned(), _encode("base", cent, q4, "x", True), _encode("base", None, q4, "f", True)) + f", a AS (SELECT avg(list_dot_product(v, c)) AS affinity, {err('x', 'norm')} AS part, {err('f', 'norm')} AS flat FROM xa) SELECT '{name}' AS set, round(affinity, 5) AS affinity, round(2 * (1 - affinity), 5) AS predicted, round(part / flat, 5) AS measured FROM a"
    out["amplification"] = f"SELECT * FROM ({amp('E', E_SQL)}) UNION ALL SELECT * FROM ({amp('A(2.5)', anchored)})"
    return out

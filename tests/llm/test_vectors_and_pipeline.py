"""The permutation index against brute force, the queries, and the pipeline."""

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest

import corpus_pipeline
from annspark.llm import components, jaccard, permutation, pii, queries, toxicity

SF = "/root/testdata/sf0.01"


def brute(ids, x, asks, k):
    out = {}
    for i in np.flatnonzero(asks):
        s = (x * x[i]).sum(axis=1)
        order = [j for j in np.lexsort((ids, -s)) if ids[j] != ids[i]][:k]
        out[int(ids[i])] = [int(ids[j]) for j in order]
    return out


def test_recall(spark):
    e = pd.read_parquet("/root/testdata/sf0.1/embeddings.parquet")
    ids, x = e.vec_id.to_numpy(), np.array(e.embedding.tolist(), np.float64)
    want = brute(ids, x, ids % 20 == 0, 20)
    got = queries.QUERIES["op3_permutation_index"](spark, "/root/testdata/sf0.1").toPandas()
    found = got.sort_values("rank").groupby("query_id").vec_id.apply(list).to_dict()
    assert set(found) == set(want)
    assert np.mean([len(set(found[q]) & set(want[q])) / 20 for q in want]) >= 0.9
    exact = {i: v for i, v in zip(ids, x)}
    for r in got.head(200).itertuples():
        assert r.score == pytest.approx(float(exact[r.query_id] @ exact[r.vec_id]), abs=1e-12)


def test_blocks_and_chunks_and_odd_vectors(spark):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((300, 8)).astype(np.float32)
    x[100:160] = x[100]  # ties: one large group of copies
    rows = [(i, [float(v) for v in r], "extra") for i, r in enumerate(x)]
    odd = [(1000, None, "e"), (1001, [0.0] * 8, "e"), (1002, [float("nan")] * 8, "e"), (1003, [None] + [1.0] * 7, "e"), (1004, [1.0] * 3, "e"), (1020, [float("inf")] * 8, "e"), (1040, [], "e")]
    df = spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>, score string")
    want = brute(np.arange(300), x.astype(np.float64), np.arange(300) % 20 == 0, 5)
    # all rows are candidates here: blocks, chunks and ties must give the exact answer
    got = permutation.nearest(df, df["vec_id"] % 20 == 0, 5, block=70, chunk=6, share=1.0).toPandas()
    assert got.sort_values("rank").groupby("query_id").vec_id.apply(list).to_dict() == want
    some = permutation.nearest(df, df["vec_id"] % 20 == 0, 5, pivots=32, prefix=16, block=150, share=0.2, least=10).toPandas()
    found = some.sort_values("rank").groupby("query_id").vec_id.apply(list).to_dict()
    assert np.mean([len(set(found[q]) & set(want[q])) / 5 for q in want]) > 0.5
    u = x / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    unit = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(u)], "vec_id long, embedding array<float>")
    near = permutation.nearest(unit, unit["vec_id"] % 20 == 0, 5, pivots=32, prefix=16, share=0.2, least=10).toPandas()
    # copies are found first and by id
    assert near[near.query_id == 100].sort_values("rank").vec_id.tolist() == [101, 102, 103, 104, 105]
    assert permutation.nearest(df.limit(0), df["vec_id"] % 20 == 0, 5).count() == 0
    assert permutation.nearest(df.where("vec_id = 20"), df["vec_id"] % 20 == 0, 5).count() == 0


def test_footrule_and_postings():
    """Agreement is the footrule of truncated lists up to a constant; candidates are its best, ties to smaller ids."""
    rng = np.random.default_rng(4)
    x = rng.standard_normal((400, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    x[50:60] = x[50]
    pivots, prefix = permutation.lifted(x[:40], 1.0), 9
    block = permutation.Block(np.arange(400)[::-1].copy(), x[::-1], pivots, prefix, 1.0)
    near = permutation.lists(permutation.lifted(x, 1.0), pivots, prefix)
    got = block.agreement(x[:30])
    for i in range(30):
        for j in range(400):
            a, b = near[i].tolist(), near[j].tolist()
            foot = sum(abs((a.index(p) if p in a else prefix) - (b.index(p) if p in b else prefix)) for p in range(40))
            assert foot == prefix * (prefix + 1) - 2 * got[i, j]
        order = np.lexsort((np.arange(400), -got[i]))
        for want in (1, 7, 60, 400, 500):
            assert permutation.leading(got[i], want).tolist() == sorted(order[:want].tolist())


def test_recall_isotropic_blocks(spark):
    """20,000 vectors in two blocks, at the defaults."""
    rng = np.random.default_rng(9)
    x = rng.standard_normal((20_000, 64)).astype(np.float32)
    df = spark.createDataFrame(pa.table({"vec_id": np.arange(20_000), "embedding": pa.FixedSizeListArray.from_arrays(x.ravel(), 64).cast(pa.list_(pa.float32()))}))
    got = permutation.nearest(df, df["vec_id"] % 100 == 0, 20).toPandas().groupby("query_id").vec_id.apply(set).to_dict()
    y = x.astype(np.float64)
    asked = np.arange(0, 20_000, 100)
    s = y[asked] @ y.T
    s[np.arange(len(asked)), asked] = -np.inf
    want = np.argpartition(-s, 20, axis=1)[:, :20]
    assert set(got) == set(asked.tolist())
    assert np.mean([len(got[int(q)] & set(w.tolist())) / 20 for q, w in zip(asked, want, strict=True)]) >= 0.9


def test_components(spark):
    import random

    rng = random.Random(4)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)] + [(500, k) for k in range(501, 560)]
    up = {}

    def root(v):
        while up.setdefault(v, v) != v:
            v = up[v]
        return v

    for a, b in edges:
        up[max(root(a), root(b))] = min(root(a), root(b))
    got = {r.u: r.root for r in components.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {v: root(v) for v in list(up) if root(v) != v}


def test_names():
    assert sorted(q for q in queries.QUERIES) == sorted(queries.QUERIES) and {q.split("_")[0] for q in queries.QUERIES} == {f"op{i}" for i in range(1, 11)}
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "ngram_jaccard", "pii", "mixing", "byte_bpe"]


def test_pipeline_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = docs.columns
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    clean = corpus_pipeline.drop_toxic(spark, docs, SF).cache()
    assert clean.columns == names
    toxic = {r.doc_id for r in toxicity.grade(docs, toxicity.train(docs, labels)).where("toxic").collect()}
    assert {r.doc_id for r in clean.select("doc_id").collect()} == {r.doc_id for r in docs.select("doc_id").collect()} - toxic and toxic
    one = corpus_pipeline.one_of_near_copies(spark, clean, SF).cache()
    want = {r.class_id for r in jaccard.join(clean).collect()}
    assert one.columns == names and {r.doc_id for r in one.select("doc_id").collect()} == want and one.count() == len(want)
    masked = corpus_pipeline.mask_identifiers(spark, one, SF).cache()
    assert masked.columns == names and masked.count() == one.count()
    assert pii.find(masked).where("n_email + n_ip + n_card + n_phone > 0").count() == 0
    mixed = corpus_pipeline.mix_sources(spark, masked, SF)
    assert mixed.columns == names
    last = corpus_pipeline.tokenize(spark, mixed, SF)
    assert last.count() == mixed.count() and last.where("size(ids) <> n_tokens").count() == 0


def test_pipeline_runs_the_same_twice(spark):
    a = corpus_pipeline.run(spark, "/root/testdata/sf0.001").select("doc_id", "n_tokens", "ids_sha256")
    b = corpus_pipeline.run(spark, "/root/testdata/sf0.001").select("doc_id", "n_tokens", "ids_sha256")
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_sql_of_operators(spark, name):
    from tests.oracle import connect, rows

    assert rows(queries.QUERIES[name](spark, SF).toPandas()) == rows(connect(SF).execute(queries.ORACLE_SQL[name]).fetchdf())

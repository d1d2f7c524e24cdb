"""Plans that did not fit at sixty times the small tables: what they must not do again."""

import numpy as np

import __spark_entry__ as entry
from annspark.operators import coarse, exact, lsh, pq, scan
from annspark.plans import relational, workloads
from annspark.sources import datasets as ds
from tests.conftest import SF


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_best_of_all_columns_at_once():
    rng = np.random.default_rng(1)
    for n, c, k in ((5, 3, 10), (10, 4, 10), (200, 7, 10), (50, 3, 1)):
        s, ids = rng.integers(0, 6, (n, c)).astype(float), rng.permutation(n)
        rows, who = exact.best_rows(s, ids, k)
        for j in range(c):
            assert rows[who == j].tolist() == exact.best(s[:, j], ids, k).tolist()


def test_lsh_shuffles_no_pairs(spark):
    base, q = ds.split(ds.embeddings(spark, SF))
    found = lsh.search(base, q)
    assert "Join" not in plan(found)
    x = {r.id: np.array(r.v) for r in base.collect()} | {r.qid: np.array(r.qv) for r in q.collect()}
    rows = found.collect()
    assert rows and all(abs(x[r.qid] @ x[r.id] - r.score) < 1e-9 for r in rows)


def test_radius_search_by_blocks(spark, tmp_path, monkeypatch):
    nan = float("nan")
    e = [(0, [1.0, 0.0]), (10, [0.0, 1.0, 1.0]), (20, None), (1, [0.5, 0.0]), (2, [0.2, 9.0]), (3, [0.0, 0.1, 0.3]), (4, [nan, 0.0]), (5, [None, 1.0]), (6, None)]
    spark.createDataFrame(e, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    monkeypatch.setattr(exact, "SCORES", 1)
    found = relational.radius_search(spark, str(tmp_path))
    assert "Join" not in plan(found)
    assert {(r.qid, r.vec_id) for r in found.collect()} == {(0, 1), (0, 4), (10, 3)}


def test_dedup_is_not_held_by_the_driver(spark):
    df = entry.queries()["st_dedup"](spark, SF)
    assert df.inputFiles() and df.count() == spark.read.parquet(f"{SF}/events.parquet").count()


def test_centroid_sums_of_few_rows(spark):
    df = spark.createDataFrame([(i, [float(i % 2), float(1 - i % 2)]) for i in range(5)], "id long, v array<double>")
    assert coarse.step(df, np.array([[1.0, 0.0], [0.0, 1.0], [-1.0, 0.0]])).tolist() == [[1.0, 0.0], [0.0, 1.0], [-1.0, 0.0]]


def test_hashing_makes_no_row_a_word(spark):
    texts = spark.createDataFrame([(1, "a B a"), (1, "c"), (2, None), (3, "1 ."), (4, "bİK x")], "id long, text string")
    found = ds.hashed(texts, 8, "s")
    assert "Generate" not in plan(found)
    slots: dict = {}
    for r in ds.hashed_slots(texts, 8, "s").collect():
        slots.setdefault(r.id, np.zeros(8))[r.slot] = r.x
    assert {r.id: r.v for r in found.collect()} == {k: (v / np.sqrt(sum(v * v))).tolist() for k, v in slots.items()}


def test_numbers_find_their_code():
    rng = np.random.default_rng(2)
    for n, k in ((50, 1), (400, 7), (400, 300)):
        c = np.round(rng.standard_normal(k), 1)[:, None]  # equal codes too
        x = np.concatenate((rng.standard_normal((n, 1)), np.round(rng.standard_normal((n, 1)), 2)))
        half = (c * c).sum(axis=1) / 2
        assert pq.codes_of(x, c).tolist() == (x @ c.T - half).argmax(axis=1).tolist()


def test_small_partitions_are_gathered(spark):
    df = workloads.gathered(spark.range(1_000, numPartitions=100), 1_000, 96)
    assert df.rdd.getNumPartitions() == 2 * spark.sparkContext.defaultParallelism and df.count() == 1_000


def test_k_rows_of_all_probed_cells_are_left(monkeypatch):
    rng = np.random.default_rng(3)
    cell, group, ids = rng.integers(0, 8, 200), rng.integers(0, 2, 200), rng.permutation(200)
    s, asked = rng.integers(0, 9, (200, 7)).astype(float), rng.random((8, 7)) < 0.6

    def fill(a, z):
        for c in range(8):
            rows, who = np.flatnonzero(cell == c), a + np.flatnonzero(asked[c, a:z])
            yield rows, who, s[np.ix_(rows, who)]

    want = sorted((g, q, *x) for g in (0, 1) for q in range(7) for x in sorted((-s[r, q], ids[r]) for r in range(200) if group[r] == g and asked[cell[r], q])[:5])
    for scores in (exact.SCORES, 400):
        monkeypatch.setattr(exact, "SCORES", scores)
        for dense in (True, False):
            found = [(g, q, -v, ids[r]) for g, rows, who, x in exact.best_filled(ids, group, 7, 5, fill, dense) for r, q, v in zip(rows, who, x, strict=True)]
            assert len(found) == len(want) or not dense
            assert sorted(x for g in (0, 1) for q in range(7) for x in sorted(y for y in found if y[:2] == (g, q))[:5]) == want


def test_best_rows_orders_few(monkeypatch):
    """Of 10,000 rows a query, only those above a bar of some first rows are ordered (all rows were partitioned before), and bars hold over batches."""
    rng = np.random.default_rng(1)
    s, ids = np.round(rng.standard_normal((10_000, 40)), 2), rng.permutation(10_000)
    parted, part = [], np.partition
    monkeypatch.setattr(np, "partition", lambda x, *a, **b: parted.append(len(x)) or part(x, *a, **b))
    want = [np.lexsort((ids, -s[:, j]))[:10].tolist() for j in range(40)]
    bars = np.full(40, -np.inf)
    found = [[], []]
    for a in (0, 5_000):
        rows, who = exact.best_rows(s[a : a + 5_000], ids[a : a + 5_000], 10, bars=bars)
        found[0].extend((a + rows).tolist())
        found[1].extend(who.tolist())
    for j in range(40):
        own = [r for r, w in zip(*found, strict=True) if w == j]
        assert sorted(own, key=lambda r: (-s[r, j], ids[r]))[:10] == want[j]
    assert len(found[0]) < 40 * 19 and max(parted) <= 625
    # scores that are off by a rounding are made exact where it matters
    off = s + 1e-12 * rng.standard_normal(s.shape)
    rows, who = exact.best_rows(off, ids, 10, exactly=lambda r, w: s[r, w], slack=1e-10)
    assert [rows[who == j].tolist() for j in range(40)] == want


def test_learned_search_is_one_product(spark):
    """Where most cells are probed, codes are searched by a product and few sums of look-ups: rows and scores as sums of look-ups alone have them, ties by id."""
    rng = np.random.default_rng(2)
    x = rng.standard_normal((600, 8))
    x[300:] = x[:300]  # equal codes
    x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, v array<double>")
    q = spark.createDataFrame([(i, x[i].tolist()) for i in range(20)], "qid long, qv array<double>")
    cb = pq.Codebook(rng.standard_normal((8, 4, 1)) / 3, x[:5])
    cell, r = cb.residual(x)
    code = cb.encode(r)
    for n_p in (2, 5):
        got = {}
        for row in pq.search(pq.encode(df, cb), cb, q, 10, n_p).collect():
            got.setdefault(row.qid, []).append((row.rank, row.id, row.score))
        for i in range(20):
            ip = x[i] @ cb.c.T
            probed = np.argsort(-ip, kind="stable")[:n_p]
            score = ip[cell]
            for j in range(8):
                score = score + x[i, j] * cb.books[j][code[:, j], 0]
            rows = np.flatnonzero(np.isin(cell, probed))
            want = rows[np.lexsort((rows, -np.round(score[rows], 12)))[:10]]
            assert [row for _, row, _ in sorted(got[i])] == want.tolist()
            assert np.allclose([v for _, _, v in sorted(got[i])], score[want], atol=1e-12)


def test_codebooks_are_fitted_on_all_rows(spark):
    """Before, 100,000 rows at most were taken."""
    df = spark.range(100_500, numPartitions=4).selectExpr("id", "array(id / 100500D, CAST(pmod(id * id, 7) AS DOUBLE)) AS v")
    want = df.selectExpr("avg(v[0])", "avg(v[1])").first()
    assert np.allclose(pq.fit(df, 1, 0, iters=1).books.ravel(), list(want), atol=1e-8)


def test_rounds_in_spark_are_those_of_the_driver(spark):
    """Codebooks of the rows up to several batches, fitted together, as each k-means alone gives them."""
    rng = np.random.default_rng(4)
    x, batch = rng.standard_normal((300, 6)), rng.integers(0, 3, 300)
    df = spark.createDataFrame([(i, v.tolist(), int(b)) for i, (v, b) in enumerate(zip(x, batch, strict=True))], "id long, v array<double>, batch int").repartition(5)
    for m in (6, 3):
        for t, cb in pq.fit_upto(df, (0, 2), m, 3, None, 4, 9).items():
            own, w = x[batch <= t], 6 // m
            assert np.allclose(cb.books, [pq.kmeans(own[:, s * w : (s + 1) * w], 8, 4, 9 + s) for s in range(m)], atol=1e-8)
    few = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x[:5])], "id long, v array<double>")
    assert np.allclose(pq.fit(few, 6, 3, iters=4, seed=9).books, [pq.kmeans(x[:5, s : s + 1], 8, 4, 9 + s) for s in range(6)], atol=1e-8)
    new = pq.retrain(df, pq.Codebook(np.zeros((6, 8, 1))), 3, iters=4, seed=9, upto=[1, 2])
    assert [(cb.version, codes.count()) for cb, codes in new] == [(1, int((batch <= t).sum())) for t in (1, 2)]
    assert np.array_equal(new[1][0].books, pq.fit(df, 6, 3, iters=4, seed=9).books)


def test_rows_of_a_scan_are_the_best_ones(monkeypatch):
    """Products in single precision choose pairs, double precision their order: ties by id, over batches, cells and groups."""
    rng = np.random.default_rng(5)
    x, z, ids = rng.standard_normal((400, 6)), rng.standard_normal((30, 6)), rng.permutation(400)
    cell, group = rng.integers(0, 5, 400), rng.integers(0, 2, 400).astype(np.int32)
    for copy in (x, cell, group):
        copy[200:300] = copy[:100]
    asked = rng.random((5, 30)) < 0.6
    probes = {c: (np.flatnonzero(asked[c]), rng.standard_normal(asked[c].sum())) for c in range(5)}
    for size, scale in ((1 << 20, 1.0), (300, 1.0), (300, 1e20)):
        monkeypatch.setattr(scan, "BLOCK", size)
        best = scan.Best(z, probes, 7)
        for a in range(0, 400, 150):
            best.add(ids[a : a + 150], cell[a : a + 150], group[a : a + 150], scale * x[a : a + 150])
        got = {(g, w, i) for g, rows, who, _ in best.found() for w, i in zip(who.tolist(), rows.tolist(), strict=True)}
        want = set()
        for g in (0, 1):
            for j in range(30):
                rows = np.flatnonzero((group == g) & asked[cell, j])
                term = np.array([probes[c][1][np.searchsorted(probes[c][0], j)] for c in cell[rows]])
                score = np.einsum("ij,j->i", scale * x[rows], z[j]) + term
                want |= {(g, j, int(ids[rows[i]])) for i in np.lexsort((ids[rows], -np.round(score, 9)))[:7]}
        assert got == want


def test_words_of_bytes_are_those_of_lower_case_text(spark):
    """Every character, between and beside letters, as Spark's lower() and the split of the SQL have them."""
    chars = [chr(i) for i in range(1, 0x110000) if not 0xD800 <= i < 0xE000]
    texts = ["".join(f"a{c}B {c}Z" for c in chars[i : i + 5_000]) for i in range(0, len(chars), 5_000)]
    df = spark.createDataFrame([(t,) for t in texts], "text string").selectExpr("text", "filter(split(lower(text), '[^a-z]+'), w -> w <> '') AS words")
    for r in df.collect():
        assert [w.decode() for w in ds.lower_words(r.text.encode())] == r.words


def test_truth_over_time_scans_once(spark):
    """Before, the batches were looked up in what was found, so that every scan ran twice."""
    rng = np.random.default_rng(6)
    x = rng.standard_normal((200, 4))
    df = spark.createDataFrame([(i, v.tolist(), i % 3) for i, v in enumerate(x)], "id long, v array<double>, batch int").repartition(3)
    q = spark.createDataFrame([(i, x[i].tolist()) for i in range(9)], "qid long, qv array<double>")
    found = exact.knn_cumulative(df, q, 5)
    assert plan(found).count("MapInArrow go") == 2  # the scan and its merge
    got = {(r.batch, r.qid, r["rank"]): r.id for r in found.collect()}
    for t in range(3):
        rows = np.flatnonzero(np.arange(200) % 3 <= t)
        for i in range(9):
            assert [got[t, i, r] for r in range(1, 6)] == rows[np.argsort(-(x[rows] @ x[i]))[:5]].tolist()

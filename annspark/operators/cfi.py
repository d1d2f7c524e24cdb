"""The codebook-free inverted index: residuals to a spherical k-means cell, rotated, renormalised and scalar-quantized.

Codes are rows (id, cell, code BINARY, sign BINARY, res_norm SHORT, epoch INT), res_norm in half precision, or
also (norm DOUBLE) for comparisons across engines. Encoding is map-only and stateless: rotation and quantizer follow from
(seed, d, b), so rows may be appended at any time.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.functions import codes as pk
from annspark.functions import rotation, scalarq
from annspark.functions.vectors import as_lists, matrix
from annspark.operators import coarse, scan
from annspark.operators.exact import best, collected, merged, top_rows, united

SCHEMA = "id long, cell long, code binary, sign binary, res_norm short, norm double, epoch int"
STAGES = ("none", "sign", "jls")


@dataclass(frozen=True)
class Index:
    """Everything that does not grow with the data. ``c`` None is the flat index: no cells, vectors quantized themselves."""

    d: int
    b: int
    c: np.ndarray | None
    stage2: str = "sign"
    seed: int = 42
    epoch: int = 0
    generation: int = 0
    exact_norm: bool = False
    fast_rotation: bool = False
    inserted: int = field(default=0, compare=False)

    @property
    def cells(self) -> int:
        return 0 if self.c is None else len(self.c)

    @property
    def q(self) -> scalarq.Quantizer:
        return scalarq.design(self.b, self.width)

    @property
    def width(self) -> int:
        return rotation.hadamard(self.d, self.seed).width if self.fast_rotation else self.d

    def rotate(self, x: np.ndarray) -> np.ndarray:
        return rotation.hadamard(self.d, self.seed).apply(x) if self.fast_rotation else x @ rotation.dense(self.d, self.seed).T

    # --- kernels on matrices

    def quantize(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(cell, norm, codes, signs, unit) of unit rows; a zero residual has norm 0 and any code."""
        if self.c is None:
            cell, r = np.zeros(len(x), np.int64), x
        else:
            cell, _ = coarse.nearest(x, self.c)
            r = x - self.c[cell]
        y = self.rotate(r)
        n = np.sqrt((y * y).sum(axis=1))
        u = y / np.where(n > 0, n, 1)[:, None]
        code = self.q.encode(u)
        if self.stage2 == "jls":
            e = u - self.q.decode(code)
            sign = (e @ self.sketch.T > 0).astype(np.uint8)
        else:
            sign = self.q.signs(u, code)
        return cell, n, code, sign, u

    @property
    def sketch(self) -> np.ndarray:
        return rotation.gaussians(self.seed * 31 + 5, self.width * self.width).reshape(self.width, self.width)

    def decode(self, code: np.ndarray, sign: np.ndarray) -> np.ndarray:
        """Rebuilt rotated unit residuals; not renormalised."""
        return self.q.decode(code, sign if self.stage2 == "sign" else None)


def encode(df: DataFrame, index: Index, carry: str | None = None) -> DataFrame:
    """Codes of (id, v) rows, v of unit norm: one fused map; ``carry`` names an integer column that goes along."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cell, n, code, sign, _ = index.quantize(matrix(b.column(1)))
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), pa.array(cell), pk.to_binary(pk.pack(code, index.b)), pk.to_binary(pk.pack(sign, 1)), pa.array(pk.half_bits(n)), pa.array(n), pa.array(np.full(len(n), index.epoch, np.int32)), *b.columns[2:]],
                    names=["id", "cell", "code", "sign", "res_norm", "norm", "epoch", *more],
                )

    more = [carry] if carry else []
    return df.select("id", "v", *(F.col(x).cast("int").alias(x) for x in more)).mapInArrow(go, ", ".join([SCHEMA, *(f"{x} int" for x in more)]))


def _read(b: pa.RecordBatch, index: Index) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    names = b.schema.names
    at = {c: b.column(names.index(c)) for c in ("id", "cell", "code", "sign", "res_norm", "norm")}
    w = index.width
    code = pk.unpack(pk.from_binary(at["code"], -(-w * index.b // 8)), index.b, w)
    sign = pk.unpack(pk.from_binary(at["sign"], -(-w // 8)), 1, w)
    norm = at["norm"].to_numpy() if index.exact_norm else pk.from_half(at["res_norm"].to_numpy())
    return at["id"].to_numpy(), at["cell"].to_numpy(), code, sign, norm


def build(df: DataFrame, cells: int, b: int = 4, stage2: str = "sign", seed: int = 42, iters: int = 10, fit_on: DataFrame | None = None, d: int | None = None, **options) -> tuple[Index, DataFrame]:
    """(index, codes): the partition is fitted on ``fit_on`` (default: all), everything is encoded. cells=0: flat."""
    if stage2 not in STAGES:
        raise ValueError(f"stage2 is one of {STAGES}")
    d = d or len(df.select("v").first().v)
    c = coarse.fit(fit_on if fit_on is not None else df, cells, iters, seed) if cells else None
    index = Index(d, b, c, stage2, seed, **options)
    return index, encode(df, index)


def insert(codes: DataFrame, batch: DataFrame, index: Index) -> DataFrame:
    """Codes with the batch appended under the unchanged layer."""
    return codes.unionByName(encode(batch, index))


def probe(index: Index, qid: np.ndarray, q: np.ndarray, n_p: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """cell -> (places of the queries that probe it, their exact coarse terms); ties to the lower cell."""
    if index.c is None:
        return {0: (np.arange(len(q)), np.zeros(len(q)))}
    s = q @ index.c.T
    order = np.argsort(-s, axis=1, kind="stable")[:, : min(n_p, index.cells)]
    who, cell = np.repeat(np.arange(len(q)), order.shape[1]), order.ravel()
    by = np.argsort(cell, kind="stable")
    who, cell = who[by], cell[by]
    start = np.flatnonzero(np.diff(cell, prepend=-1))
    return {int(cell[a]): (who[a:z], s[who[a:z], cell[a]]) for a, z in zip(start, [*start[1:], len(cell)], strict=True)}


def probes_frame(index: Index, queries: DataFrame, n_p: int) -> DataFrame:
    """(qid, cell, rank, ip) of the probed cells."""
    return united(_probes_frame(index, queries, qid, q, n_p) for qid, q in collected(queries))


def _probes_frame(index: Index, queries: DataFrame, qid: np.ndarray, q: np.ndarray, n_p: int) -> DataFrame:
    s = q @ index.c.T
    order = np.argsort(-s, axis=1, kind="stable")[:, : min(n_p, index.cells)]
    rows = [(int(qid[i]), int(c), r + 1, float(s[i, c])) for i in range(len(qid)) for r, c in enumerate(order[i])]
    return queries.sparkSession.createDataFrame(rows, "qid long, cell long, rank int, ip double")


def scores(index: Index, ids: np.ndarray, cell: np.ndarray, code: np.ndarray, sign: np.ndarray, norm: np.ndarray, probes, turned: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row places, query places, scores matrix) cell by cell: coarse term + norm * <rotated query, decoded unit residual>."""
    order = np.argsort(cell, kind="stable")
    edge = np.flatnonzero(np.concatenate(([True], np.diff(cell[order]) != 0, [True])))
    for a, z in zip(edge[:-1], edge[1:], strict=True):
        rows = order[a:z]
        hit = probes.get(int(cell[rows[0]]))
        if hit is None:
            continue
        who, coarse_ip = hit
        est = index.decode(code[rows], sign[rows]) @ turned[who].T
        if index.stage2 == "jls":
            e = np.sqrt(np.maximum(0.0, 1 - (index.q.decode(code[rows]) ** 2).sum(axis=1)))  # size of the error, from what is stored
            est = est + np.sqrt(np.pi / 2) / index.width * e[:, None] * ((sign[rows].astype(float) * 2 - 1) @ (turned[who] @ index.sketch.T).T)
        yield rows, who, norm[rows, None] * est + coarse_ip[None, :]


#: Probes (queries x cells) that may travel to every task; beyond, probes and codes are joined.
PROBES = 100_000
#: Scores that a task of the join way holds at once.
SCORES = 16_000_000


@dataclass(frozen=True)
class Plan:
    """How a search would run: the way taken, its probes, the rows it scores, and how many waves of queries it takes."""

    way: str
    probes: int
    candidates: int
    waves: int


def plan(index: Index, rows: int, queries: int, n_p: int, limit: int = PROBES, wave: int = 10_000) -> Plan:
    """What ``search`` does with so many rows and queries, without looking at either."""
    cells = max(index.cells, 1)
    probes = queries * min(n_p, cells)
    return Plan("broadcast" if probes <= limit else "join", probes, probes * rows // cells, max(1, -(-queries // wave)))


def search(codes: DataFrame, index: Index, queries: DataFrame, k: int = 10, n_p: int = 20, extra: str | None = None, limit: int = PROBES) -> DataFrame:
    """(qid, rank, id, score): probe lists go to every task, wave by wave of queries, k rows a query leave it.

    ``extra`` names a further grouping column of the codes, such as an insert batch, that gets top-k lists of its own.
    Above ``limit`` probes the join way of ``search_join`` is taken, unless a query probes an eighth of the cells or more: it would be copied for each,
    while a scan that looks at so many cells loses little.
    """
    # planned on a bounded count, before any vector is collected; the flat index has no cells to join on
    if extra is None and index.c is not None and (index.cells < 64 or 8 * n_p < index.cells):
        most = min(limit // max(1, min(n_p, index.cells)) + 1, (1 << 31) - 1)
        if plan(index, 0, queries.limit(most).count(), n_p, limit).way == "join":
            return search_join(codes, index, queries, k, n_p)
    return united(_search(codes, index, qid, q, k, n_p, extra) for qid, q in collected(queries))


def _features(index: Index, code: np.ndarray, sign: np.ndarray, norm: np.ndarray) -> np.ndarray:
    """Rows whose product with ``_asked`` is the estimate without its coarse term."""
    x = norm[:, None] * index.decode(code, sign)
    if index.stage2 != "jls":
        return x
    e = np.sqrt(np.maximum(0.0, 1 - (index.q.decode(code) ** 2).sum(axis=1)))  # size of the error, from what is stored
    return np.concatenate((x, (norm * np.sqrt(np.pi / 2) / index.width * e)[:, None] * (sign.astype(float) * 2 - 1)), axis=1)


def _asked(index: Index, q: np.ndarray) -> np.ndarray:
    turned = index.rotate(q)
    return np.concatenate((turned, turned @ index.sketch.T), axis=1) if index.stage2 == "jls" else turned


def _search(codes: DataFrame, index: Index, qid: np.ndarray, q: np.ndarray, k: int, n_p: int, extra: str | None) -> DataFrame:
    probes, asked = probe(index, qid, q, n_p), _asked(index, q)
    wanted = codes if index.c is None else codes.where(F.col("cell").isin([int(c) for c in probes])) if len(probes) < min(index.cells, 2_000) else codes

    def read(b: pa.RecordBatch):
        ids, cell, code, sign, norm = _read(b, index)
        group = b.column(b.schema.names.index(extra)).to_numpy() if extra else np.zeros(len(ids), np.int32)
        return ids, cell, group, _features(index, code, sign, norm)

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from scan.search(batches, read, qid, asked, probes, k)

    cols = ["id", "cell", "code", "sign", "res_norm", "norm"] + ([extra] if extra else [])
    found = wanted.select(*cols).mapInArrow(go, "batch int, qid long, id long, score double")
    if extra:
        return top_rows(merged(found, k, ("batch", "qid")), k, ("batch", "qid")).select("batch", "qid", "rank", "id", "score")
    return top_rows(merged(found, k), k).select("qid", "rank", "id", "score")


def search_join(codes: DataFrame, index: Index, queries: DataFrame, k: int = 10, n_p: int = 20, salt_rows: int = 1_000_000) -> DataFrame:
    """The same for many queries: probes and codes meet on (cell, salt); hot cells are salted by their counted size."""
    spark = codes.sparkSession
    # keys of both sides in one type: a cogroup does not cast, and an INT hashes unlike a LONG
    c = coarse.to_frame(spark, index.c).select(F.col("cell").cast("long").alias("cell"), "c")
    from annspark.functions.vectors import dot

    from pyspark.sql import Window

    ranked = queries.select("qid", "qv").crossJoin(F.broadcast(c)).select("qid", "qv", "cell", dot("qv", "c").alias("ip"))
    w = Window.partitionBy("qid").orderBy(F.desc("ip"), "cell")
    probes = ranked.withColumn("r", F.row_number().over(w)).where(F.col("r") <= n_p).drop("r")
    salts = codes.groupBy("cell").agg(F.ceil(F.count("*") / salt_rows).cast("int").alias("salts"))
    left = codes.join(F.broadcast(salts), "cell").withColumn("salt", F.pmod(F.xxhash64("id"), F.col("salts").cast("long")))
    right = probes.join(F.broadcast(salts), "cell").withColumn("salt", F.explode(F.expr("sequence(0L, salts - 1L)")))

    def meet(key, a: pa.Table, b: pa.Table) -> pa.Table:
        out = {"qid": np.zeros(0, np.int64), "id": np.zeros(0, np.int64), "score": np.zeros(0)}
        if a.num_rows and b.num_rows:
            batch = a.combine_chunks().to_batches()[0]
            qv, qids, ip = matrix(b.column("qv")), b.column("qid").to_numpy(), b.column("ip").to_numpy()
            ids, *rest = _read(batch, index)
            turned, some, parts = index.rotate(qv), max(1, SCORES // len(ids)), []
            for i in range(0, len(qids), some):  # few enough queries at once that their scores fit
                for rows, who, s in scores(index, ids, *rest, {int(rest[0][0]): (np.arange(len(qids))[i : i + some], ip[i : i + some])}, turned):
                    at = [best(s[:, j], ids[rows], k) for j in range(len(who))]
                    flat, w_ = np.concatenate(at), np.repeat(np.arange(len(who)), [len(x) for x in at])
                    parts.append((qids[who[w_]], ids[rows[flat]], s[flat, w_]))
            out = dict(zip(out, map(np.concatenate, zip(*parts, strict=True)), strict=True))
        return pa.table(out)

    found = left.select("cell", "salt", "id", "code", "sign", "res_norm", "norm").groupBy("cell", "salt").cogroup(right.select("cell", "salt", "qid", "qv", "ip").groupBy("cell", "salt")).applyInArrow(meet, "qid long, id long, score double")
    return top_rows(found, k).select("qid", "rank", "id", "score")


def rerank(found: DataFrame, raw: DataFrame, queries: DataFrame, k: int = 10, rr: int = 50) -> DataFrame:
    """The k best of the first rr candidates by the exact inner product on raw vectors (id, v)."""
    from annspark.functions.vectors import dot

    few = found.where(F.col("rank") <= rr).select("qid", "id")
    joined = few.join(raw.select("id", "v"), "id").join(F.broadcast(queries.select("qid", "qv")), "qid")
    return top_rows(joined.select("qid", "id", dot("v", "qv").alias("score")), k).select("qid", "rank", "id", "score")


def cascade(codes: DataFrame, index: Index, queries: DataFrame, k: int = 10, n_p: int = 20, widths: tuple[int, int] = (8, 3), raw: DataFrame | None = None) -> DataFrame:
    """First pass on the codes alone keeps widths[0] * k, the second adds the refinement bit and keeps widths[1] * k or k, a third may use raw vectors.

    The second pass reads the sign column of the survivors only.
    """
    first = search(codes, replace(index, stage2="none"), queries, widths[0] * k, n_p)
    left = codes.join(first.select("id").distinct(), "id", "left_semi")
    second = search(left, index, queries, widths[0] * k, n_p).join(first.select("qid", "id"), ["qid", "id"], "left_semi")
    second = top_rows(second.drop("rank"), (widths[1] if raw is not None else 1) * k).select("qid", "rank", "id", "score")
    return rerank(second, raw, queries, k, widths[1] * k) if raw is not None else second


def reconstruct(codes: DataFrame, index: Index) -> DataFrame:
    """(id, v): centroid + norm * inverse rotation of the decoded residual, put back on the sphere."""
    if index.fast_rotation:
        raise NotImplementedError("the padded rotation keeps no inverse for quantized outputs")
    turn = rotation.dense(index.d, index.seed)

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                ids, cell, code, sign, norm = _read(b, index)
                x = norm[:, None] * (index.decode(code, sign) @ turn)
                x = x + (index.c[cell] if index.c is not None else 0)
                x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
                yield pa.RecordBatch.from_arrays([pa.array(ids), as_lists(x)], names=["id", "v"])

    return codes.mapInArrow(go, "id long, v array<double>")


def inner_error(df: DataFrame, index: Index, queries: DataFrame, by: str | None = None) -> DataFrame:
    """([by,] n, mse, ip_mse, ip_p95, ip_max, affinity): reconstruction and inner-product errors of (id, v) rows over all queries, in one pass."""
    turned = [index.rotate(q) for _, q in collected(queries)]
    asked = sum(map(len, turned))

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(0))
                cell, n, code, sign, u = index.quantize(x)
                e = n[:, None] * (u - index.decode(code, sign))
                ip2, ipm = np.zeros(len(x)), np.zeros(len(x))
                for t in turned:
                    ip = e @ t.T
                    ip2, ipm = ip2 + (ip * ip).sum(axis=1), np.maximum(ipm, np.abs(ip).max(axis=1))
                aff = (x * index.c[cell]).sum(axis=1) if index.c is not None else np.zeros(len(x))
                yield pa.RecordBatch.from_arrays([pa.array((e * e).sum(axis=1)), pa.array(ip2 / asked), pa.array(ipm), pa.array(aff), b.column(1)], names=["se", "ip2", "ipm", "aff", "g"])

    got = df.select("v", (F.col(by).cast("long") if by else F.lit(0).cast("long")).alias("g")).mapInArrow(go, "se double, ip2 double, ipm double, aff double, g long")
    agg = got.groupBy("g").agg(F.count("*").alias("n"), F.avg("se").alias("mse"), F.avg("ip2").alias("ip_mse"), F.percentile("ipm", 0.95).alias("ip_p95"), F.max("ipm").alias("ip_max"), F.avg("aff").alias("affinity"))
    return agg.withColumnRenamed("g", by) if by else agg.drop("g")

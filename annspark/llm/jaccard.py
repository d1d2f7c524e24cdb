"""Similarity join of texts on word n-grams: MinHash banding, then exact verification.

Two texts link if the Jaccard index of their sets of five-word n-grams (as 64-bit hashes) is at least the
threshold. ``bands_for`` picks the most selective bands that still meet the target recall at the threshold
within a budget of hash functions: 25 bands of 5 rows at 0.8, which miss a pair at exactly 0.8 once in
20,000. Above that the chance falls further.

Plan: copies are reduced to distinct texts first (128-bit keys), with their number. Band hashes travel as small rows;
those of one text alone are dropped. What is left goes to its bucket with an 8-bit signature and all its band hashes, where
members meet in blocks of a matrix comparison: a pair is a candidate in the first band that it shares and if its
signatures agree as they would at the threshold, less 4.5 standard deviations. Members that have a candidate there are named, not
their pairs; they come once more with their full n-gram sets, and the second kernel finds the same pairs again and decides each on the
sets. For ``join`` a kernel writes one row for each member and bucket, so no pair leaves a kernel in any form: on n near copies
rows and bytes grow as n, up to ``CROWD`` members of a bucket. Buckets of more texts are dealt in pairs of blocks to many tasks, so that
each member is sent once for each block.

Classes are connected components of the links.

Defined cases: null and empty texts, or texts without words, have no n-grams: copies of them share a class but
have no links; texts of fewer than five words have one n-gram, all their words; a null doc_id takes part and gives way to
others as class id; repeated rows are copies.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from annspark.llm.common import cut, restored, shielded, sliced
from annspark.llm.components import components
from annspark.llm.repeats import _bytes, mixed, of_ranges, prefix
from annspark.llm.wordspans import Words

GRAM, THRESHOLD, RECALL, HASHES, CROWD = 5, 0.8, 0.9999, 128, 4_096
_WORDS = Words(GRAM, GRAM)
#: What the kernels are sent; neither names a pair.
MEMBER = "h long, side int, t1 long, t2 long, band int, marks binary"
ASKED = "h long, side int, band int, t1 long, t2 long, copies long, marks binary, grams binary"


def bands_for(threshold: float, recall: float = RECALL, hashes: int = HASHES) -> tuple[int, int]:
    """(bands, rows): as many rows a band as the target recall at the threshold allows within the hashes."""
    best = (hashes, 1)
    for rows in range(1, hashes + 1):
        bands = hashes // rows
        if 1 - (1 - threshold**rows) ** bands >= recall:
            best = (bands, rows)
    return best


def ngrams(text: bytes, n: int = GRAM) -> np.ndarray:
    """Sorted distinct hashes of the n-grams of words."""
    u = _WORDS.units(text)
    if not len(u):
        return u
    k = min(n, len(u))
    a = np.arange(len(u) - k + 1)
    return np.unique(mixed(of_ranges(prefix(u), a, a + k)))


class Signer:
    def __init__(self, bands: int, rows: int, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.bands, self.rows = bands, rows
        self.a = rng.integers(1, 1 << 63, bands * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.b = rng.integers(0, 1 << 63, bands * rows, dtype=np.uint64)
        self.c = rng.integers(1, 1 << 63, rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def sign(self, grams: np.ndarray) -> np.ndarray:
        out = np.full(len(self.a), ~np.uint64(0))
        for at in range(0, len(grams), 2048):
            x = np.multiply.outer(self.a, grams[at : at + 2048])
            x += self.b[:, None]
            np.minimum(out, x.min(axis=1), out=out)
        return out

    def band_hashes(self, sig: np.ndarray) -> np.ndarray:
        x = mixed(sig.reshape(self.bands, self.rows)) * self.c[None, :]
        return mixed(x.sum(axis=1, dtype=np.uint64) + np.arange(self.bands, dtype=np.uint64)).view(np.int64)


def _to_bands(bands: int, rows: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(bands, rows)
        for b in sliced(batches):
            t1, t2 = (b.column(b.schema.get_field_index(c)).to_numpy() for c in ("t1", "t2"))
            row, hashes = [], []
            for i, text in enumerate(_bytes(b, "text")):
                if len(g := ngrams(text)):
                    hashes.append(signer.band_hashes(signer.sign(g)))
                    row.append(i)
            if row:
                at = np.repeat(row, bands)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(hashes)), pa.array(t1[at]), pa.array(t2[at]), pa.array(np.tile(np.arange(bands, dtype=np.int32), len(row)))], names=["h", "t1", "t2", "band"])

    return go


def _marks(signer: Signer, grams: np.ndarray) -> bytes:
    """What candidates are told by: the signature, 8 bits a hash, and behind it the 64-bit hashes of all bands."""
    sig = signer.sign(grams)
    return sig.astype(np.uint8).tobytes() + signer.band_hashes(sig).tobytes()


def _to_buckets(bands: int, rows: int, crowd: int):
    """(h, side, t1, t2, band, marks): members of shared buckets; crowded buckets are dealt in pairs of blocks.

    ``h`` names a bucket or a pair of its blocks, ``side`` is 0 for members that meet all others there, or 1 and 2 for members that
    meet the other side only.
    """

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(bands, rows)
        for b in sliced(batches):
            t1, t2 = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("t1", "t2"))
            out: tuple[list, ...] = ([], [], [], [], [], [])
            for i, (text, buckets) in enumerate(zip(_bytes(b, "text"), b.column(b.schema.get_field_index("buckets")).to_pylist(), strict=True)):
                marks = _marks(signer, ngrams(text))
                for x in buckets:
                    k = -(-x["n"] // (crowd // 2)) if x["n"] > crowd else 1
                    own = (t1[i] ^ (t2[i] >> 7)) % k
                    for other in range(k):
                        lo, hi = min(own, other), max(own, other)
                        h = x["h"] if k == 1 else int(mixed(np.array([(x["h"] + 1 + lo * k + hi) & (2**64 - 1)], np.uint64)).view(np.int64)[0])
                        for c, v in zip(out, (h, 0 if lo == hi else 1 + (own == hi), t1[i], t2[i], x["band"], marks), strict=True):
                            c.append(v)
                if len(out[0]) > 20_000:
                    yield _bucket_batch(out)
                    out = ([], [], [], [], [], [])
            if out[0]:
                yield _bucket_batch(out)

    return go


def _bucket_batch(out) -> pa.RecordBatch:
    h, side, t1, t2, band, marks = out
    return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(side, pa.int32()), pa.array(t1, pa.int64()), pa.array(t2, pa.int64()), pa.array(band, pa.int32()), pa.array(marks, pa.binary())], names=["h", "side", "t1", "t2", "band", "marks"])


def whole_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Tables of whole groups of equal first column, from batches sorted by it."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        h = b.column(0).to_numpy()
        cut_at = int(np.searchsorted(h, h[-1])) if (h[:-1] <= h[1:]).all() else 0
        if held and held[-1].column(0)[-1].as_py() != h[0].item():
            yield pa.Table.from_batches(held).combine_chunks()
            held = []
        if cut_at:
            yield pa.Table.from_batches([*held, b.slice(0, cut_at)]).combine_chunks()
            held = []
        held.append(b.slice(cut_at))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _groups(h: np.ndarray) -> list[tuple[int, int]]:
    edge = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1], [True]))).tolist()
    return list(zip(edge[:-1], edge[1:], strict=True))


class Meeting:
    """The candidate pairs of a bucket's members, from their marks; the same in both kernels."""

    def __init__(self, bands: int, rows: int, threshold: float):
        self.bands, self.m = bands, bands * rows
        self.least = threshold * self.m - 4.5 * (self.m * threshold * (1 - threshold)) ** 0.5

    def pairs(self, marks: list[bytes], side: np.ndarray, band: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Arrays (i, j) with i < j, i rising; whole rows of i at a time."""
        n = len(marks)
        raw = np.frombuffer(b"".join(marks), np.uint8).reshape(n, self.m + 8 * self.bands)
        sig = np.ascontiguousarray(raw[:, : self.m].T)
        before = np.ascontiguousarray(raw[:, self.m :]).view(np.int64)[:, :band]  # a pair belongs to its first band
        for a in range(0, n, 64):
            some, found = sig[:, a : a + 64], []
            for c in range(a, n, 4096):
                rest = sig[:, c : c + 4096]
                equal = np.zeros((some.shape[1], rest.shape[1]), np.uint16)
                for j in range(self.m):
                    equal += some[j][:, None] == rest[j][None, :]
                i, j = np.nonzero(equal >= self.least)
                i, j = i + a, j + c
                ok = (i < j) & ((side[i] == 0) | (side[i] != side[j]))
                i, j = i[ok], j[ok]
                if band:
                    for at in range(0, len(i), 1 << 16):
                        x, y = i[at : at + (1 << 16)], j[at : at + (1 << 16)]
                        new = ~(before[x] == before[y]).any(axis=1)
                        found.append((x[new], y[new]))
                else:
                    found.append((i, j))
            i, j = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 2
            if len(i):
                by = np.lexsort((j, i))
                yield i[by], j[by]


def _candidates(meeting: Meeting):
    """(h, side, band, t1, t2): members that have a candidate in this bucket."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches):
            h, side, band = (t.column(c).to_numpy() for c in ("h", "side", "band"))
            marks, some = t.column("marks").to_pylist(), np.zeros(len(h), bool)
            for lo, hi in _groups(h):
                if hi - lo > 1:
                    for i, j in meeting.pairs(marks[lo:hi], side[lo:hi], int(band[lo])):
                        some[lo + i] = some[lo + j] = True
            if some.any():
                yield pa.RecordBatch.from_arrays([pa.array(t.column(c).to_numpy()[some]) for c in ("h", "side", "band", "t1", "t2")], names=["h", "side", "band", "t1", "t2"])

    return go


def _with_sets(bands: int, rows: int):
    """(h, side, band, t1, t2, copies, marks, grams) for the buckets that a text has candidates in."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(bands, rows)
        for b in sliced(batches):
            t1, t2, copies = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("t1", "t2", "copies"))
            out: tuple[list, ...] = tuple([] for _ in range(8))
            size = 0
            for i, (text, asks) in enumerate(zip(_bytes(b, "text"), b.column(b.schema.get_field_index("asks")).to_pylist(), strict=True)):
                grams = ngrams(text)
                marks, g = _marks(signer, grams), grams.tobytes()
                for x in asks:
                    for c, v in zip(out, (x["h"], x["side"], x["band"], t1[i], t2[i], copies[i], marks, g), strict=True):
                        c.append(v)
                    size += len(g)
                    if size > 16_000_000:
                        yield _sets_batch(out)
                        out, size = tuple([] for _ in range(8)), 0
            if out[0]:
                yield _sets_batch(out)

    return go


def _sets_batch(out) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names=["h", "side", "band", "t1", "t2", "copies", "marks", "grams"])


class Sets:
    """Sizes of intersections of a bucket's sets. Up to ``room`` grams in all they are numbered and a row's are flagged; beyond, sets are merged
    pair by pair, without a copy. Both are exact."""

    def __init__(self, raw: list[bytes], room: int = 4_000_000):
        self.sets = [np.frombuffer(x, np.uint64) for x in raw]
        self.size = np.fromiter(map(len, self.sets), np.int64, len(raw))
        self.flags = None
        if len(raw) > 2 and self.size.sum() <= room:
            names, ids = np.unique(np.concatenate(self.sets), return_inverse=True)
            self.ids, self.flags = np.split(ids, np.cumsum(self.size)[:-1]), np.zeros(len(names), bool)

    def shared(self, i: int, others: np.ndarray) -> np.ndarray:
        if self.flags is None:
            return np.fromiter((len(np.intersect1d(self.sets[i], self.sets[j], assume_unique=True)) for j in others.tolist()), np.int64, len(others))
        self.flags[self.ids[i]] = True
        both = np.add.reduceat(self.flags[np.concatenate([self.ids[j] for j in others.tolist()])], np.cumsum(self.size[others]) - self.size[others], dtype=np.int64)
        self.flags[self.ids[i]] = False
        return both


def _verify(meeting: Meeting, threshold: float, pairs: bool):
    """Each candidate decided on the full sets. pairs: every link is written, (a1, a2, b1, b2, jaccard); else one row a member and bucket,
    (t1, t2, r1, r2, away): the first of the members that its links in this bucket connect it with, and the copies that they reach."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches):
            h, side, band, t1, t2, copies = (t.column(c).to_numpy() for c in ("h", "side", "band", "t1", "t2", "copies"))
            marks, raw = t.column("marks").to_pylist(), t.column("grams").to_pylist()
            away, up = np.zeros(len(h), np.int64), list(range(len(h)))

            def root(x: int, up=up) -> int:
                while up[x] != x:
                    up[x] = x = up[up[x]]
                return x

            for lo, hi in _groups(h):
                sets = Sets(raw[lo:hi])
                for i, j in meeting.pairs(marks[lo:hi], side[lo:hi], int(band[lo])):
                    edge = np.flatnonzero(np.concatenate(([True], i[1:] != i[:-1], [True])))
                    for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
                        x, ys = int(i[a]), j[a:b]
                        small, large = np.minimum(sets.size[ys], sets.size[x]), np.maximum(sets.size[ys], sets.size[x])
                        ys = ys[small >= threshold * large]
                        if not len(ys):
                            continue
                        both = sets.shared(x, ys)
                        like = both / (sets.size[x] + sets.size[ys] - both)
                        ys, like = ys[like >= threshold], like[like >= threshold]
                        if not len(ys):
                            continue
                        k, q = lo + x, lo + ys
                        if pairs:
                            yield pa.RecordBatch.from_arrays([*(pa.array(c) for c in (np.full(len(q), t1[k]), np.full(len(q), t2[k]), t1[q], t2[q], like))], names=["a1", "a2", "b1", "b2", "jaccard"])
                        else:
                            away[k] += copies[q].sum()
                            away[q] += copies[k]
                            for y in q.tolist():
                                v, w = root(k), root(y)
                                up[max(v, w)] = min(v, w)
            if not pairs and (own := np.flatnonzero(away)).size:
                least = np.array([root(k) for k in own.tolist()])
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (t1[own], t2[own], t1[least], t2[least], away[own])], names=["t1", "t2", "r1", "r2", "away"])

    return go


def keyed(docs: DataFrame) -> DataFrame:
    """docs with the 128-bit key (t1, t2) of the text; null reads as empty."""
    text = F.coalesce("text", F.lit(""))
    return docs.withColumn("t1", F.xxhash64(text)).withColumn("t2", F.xxhash64(text, F.lit(1)))


def links(docs: DataFrame, threshold: float = THRESHOLD, recall: float = RECALL, hashes: int = HASHES, crowd: int = CROWD, pairs: bool = True) -> DataFrame:
    """(a1, a2, b1, b2, jaccard): each link between two different texts once, by their keys.

    With ``pairs`` off, groups stay summed up: (t1, t2, r1, r2, away), a row for each text and bucket it has links in, as
    many as there are memberships however dense a group is. A text's links are the sum of ``away``; the
    edges to (r1, r2) connect what the links connect.
    """
    bands, rows = bands_for(threshold, recall, hashes)
    distinct = keyed(docs.select(F.coalesce("text", F.lit("")).alias("text"))).groupBy("t1", "t2").agg(F.first("text").alias("text"), F.count("*").alias("copies"))
    texts = distinct.select("t1", "t2", "text", "copies")
    band_rows = texts.mapInArrow(_to_bands(bands, rows), "h long, t1 long, t2 long, band int")
    shared = band_rows.groupBy("h").agg(F.count("*").alias("n")).where("n > 1")
    by_text = band_rows.join(shared, "h").groupBy("t1", "t2").agg(F.collect_list(F.struct("h", "band", "n")).alias("buckets"))
    members = texts.join(by_text, ["t1", "t2"]).select("t1", "t2", "text", "copies", "buckets").mapInArrow(_to_buckets(bands, rows, crowd), MEMBER)
    meeting = Meeting(bands, rows, threshold)
    # ordered so that blocks are the same whenever a task is run again
    found = members.repartition("h").sortWithinPartitions("h", "t1", "t2").mapInArrow(_candidates(meeting), "h long, side int, band int, t1 long, t2 long")
    asks = found.groupBy("t1", "t2").agg(F.collect_list(F.struct("h", "side", "band")).alias("asks"))
    sets = texts.join(asks, ["t1", "t2"]).select("t1", "t2", "text", "copies", "asks").mapInArrow(_with_sets(bands, rows), ASKED)
    return sets.repartition("h").sortWithinPartitions("h", "t1", "t2").mapInArrow(_verify(meeting, threshold, pairs), "a1 long, a2 long, b1 long, b2 long, jaccard double" if pairs else "t1 long, t2 long, r1 long, r2 long, away long")


def _reached(docs: DataFrame, threshold: float, **options) -> DataFrame:
    """(u, v, away): texts with links, a text that they are connected with, and how many rows their links reach."""
    return cut(links(docs, threshold, pairs=False, **options).select(F.struct("t1", "t2").alias("u"), F.struct(F.col("r1").alias("t1"), F.col("r2").alias("t2")).alias("v"), "away"))


def join(docs: DataFrame, threshold: float = THRESHOLD, **options) -> DataFrame:
    """(doc_id, class_id, n_links) for each row of (doc_id, text): the least doc_id of its class, and how many other rows it links to."""
    reached = _reached(docs, threshold, **options)
    rows = keyed(docs.select("doc_id", "text")).select("doc_id", F.struct("t1", "t2").alias("u"), F.coalesce(F.rlike("text", F.lit(r"[^\x20\x09-\x0D]")), F.lit(False)).alias("worded"))
    texts = rows.groupBy("u").agg(F.count("*").alias("copies"), F.min("doc_id").alias("least"), F.max("worded").alias("worded"))
    away = reached.groupBy("u").agg(F.sum("away").alias("away"))
    placed = texts.join(components(reached), "u", "left").withColumn("root", F.coalesce("root", "u"))
    classes = placed.groupBy("root").agg(F.min("least").alias("class_id"))
    per_text = placed.join(classes, "root").join(away, "u", "left").select("u", "class_id", (F.when(F.col("worded"), F.col("copies") - 1).otherwise(F.lit(0)) + F.coalesce("away", F.lit(0))).alias("n_links"))
    return rows.select("doc_id", "u").join(per_text, "u").select("doc_id", "class_id", "n_links")


def one_of_each(docs: DataFrame, threshold: float = THRESHOLD, **options) -> DataFrame:
    """docs with one row of each class: that of the least doc_id (null last), then of the least text key; all columns kept."""
    safe, names = shielded(docs, ("doc_id", "text"))
    rows = keyed(safe)
    texts = rows.groupBy(F.struct("t1", "t2").alias("u")).agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id")).alias("least"))
    roots = components(_reached(safe, threshold, **options))
    placed = texts.join(roots, "u", "left").withColumn("root", F.coalesce("root", "u"))
    chosen = placed.groupBy("root").agg(F.min(F.struct("least", "u")).alias("c")).select(F.col("c.u.t1").alias("k1"), F.col("c.u.t2").alias("k2"), F.col("c.least.doc_id").alias("k_id"))
    kept = rows.join(chosen, (F.col("t1") == F.col("k1")) & (F.col("t2") == F.col("k2")) & F.col("doc_id").eqNullSafe(F.col("k_id")), "left_semi")
    # rows repeated as a whole, or but for their other columns, are one document
    others = [c for c, kind in safe.dtypes if c not in ("doc_id", "text") and not kind.startswith(("map", "variant"))]
    w = Window.partitionBy("t1", "t2", "doc_id").orderBy(*(others or ["doc_id"]))
    return restored(kept.withColumn("_n", F.row_number().over(w)).where("_n = 1"), names, docs.columns)

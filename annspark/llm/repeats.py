"""Exact search for repeated windows of W units (bytes or words) over a whole corpus: the common plan.

Texts are first reduced to distinct ones, with their number of copies, keyed by a 128-bit hash: copies of a
text are repeats of each other throughout, so only one of them is searched. Then

1. each text is cut in runs of consecutive windows that share a minimiser, the smallest hash among their grams of
   M units. Equal windows have equal minimisers, so a window can only repeat inside its minimiser's bucket;
2. minimisers that no second text has, and that occur once in their own, are dropped: small rows, counted with
   partial aggregation, joined back under adaptive skew splitting;
3. what is left travels as packed runs, one string for each run of windows, to its bucket, where a kernel
   decides which windows repeat;
4. spans return to their text, which is read again from the same exchange.

Texts are shuffled once. A task's memory is bounded by one text and one bucket; a bucket of more than ``HOT``
occurrences is not sent whole, as one task would have to hold it: its windows go one by one, as 128-bit hashes, and are counted
by partially aggregated group-bys, which no hot key can overload. Each class of equal hashes is then verified on its units: least and
greatest of its windows must be one string. Windows of a class that fails go to the kernel as runs of their own. So
both ways decide on the units themselves, and give the same result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.llm.common import sliced

HOT = 50_000
_U = np.uint64
BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(BASE, -1, 1 << 64)
BYTES = np.random.default_rng(7).integers(1, 1 << 63, 256, dtype=np.uint64) | _U(1)


class Powers:
    """BASE^i and its inverse modulo 2^64, grown as needed."""

    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)

    @classmethod
    def to(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            size = max(n, 2 * len(cls.up), 1 << 16)
            b, c = np.full(size, BASE, np.uint64), np.full(size, _INVERSE, np.uint64)
            b[0] = c[0] = 1
            cls.up, cls.down = np.multiply.accumulate(b), np.multiply.accumulate(c)
        return cls.up, cls.down


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit values."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def prefix(units: np.ndarray) -> np.ndarray:
    """Prefix polynomial hashes: S[i] = sum of units[j] * BASE^j for j < i."""
    up, _ = Powers.to(len(units) + 1)
    out = np.zeros(len(units) + 1, np.uint64)
    np.cumsum(units * up[: len(units)], out=out[1:])
    return out


def of_ranges(s: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Hashes of the ranges [a, b), free of their place."""
    _, down = Powers.to(len(s))
    return (s[b] - s[a]) * down[a]


def sliding_min(g: np.ndarray, w: int) -> np.ndarray:
    n = len(g) - w + 1
    pad = -len(g) % w
    full = np.concatenate((g, np.full(pad, ~_U(0)))) if pad else g
    rows = full.reshape(-1, w)
    ahead = np.minimum.accumulate(rows, axis=1).ravel()
    behind = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[w - 1 : w - 1 + n])


def runs(units: np.ndarray, gram: int, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(minimiser, first window, number of windows, whether its gram stands twice in the text) of each run of windows that share a minimiser."""
    n = len(units) - window + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)
    s = prefix(units)
    _, down = Powers.to(len(s))
    g = mixed((s[gram:] - s[:-gram]) * down[: len(s) - gram])
    w = window - gram + 1
    low = sliding_min(g, w)
    first = np.concatenate(([0], np.flatnonzero(low[1:] != low[:-1]) + 1))
    count = np.diff(np.concatenate((first, [n])))
    # grams that are the minimum of some window: those that equal the largest minimum over the windows around them
    edge = np.full(w - 1, ~_U(0))
    chosen = np.sort(g[~sliding_min(np.concatenate((edge, ~low, edge)), w) == g])
    at = np.searchsorted(chosen, low[first])
    twice = chosen[np.minimum(at + 1, len(chosen) - 1)] == low[first]
    twice &= at + 1 < len(chosen)
    return low[first].view(np.int64), first, count, twice


@dataclass(frozen=True)
class Units:
    """What the plan needs to know of a kind of unit; subclasses read, pack and decide."""

    window: int
    gram: int

    def units(self, text: bytes) -> np.ndarray:
        raise NotImplementedError

    def pack(self, text: bytes, first: np.ndarray, count: np.ndarray) -> list[bytes]:
        raise NotImplementedError

    def decide(self, bucket: np.ndarray, packed: list[bytes]) -> Iterator[tuple[int, int, int]]:
        """(row, lo, hi): units [lo, hi) of that packed run are covered by repeated windows."""
        raise NotImplementedError

    def finish(self, text: bytes, spans: np.ndarray) -> tuple:
        raise NotImplementedError

    result: str = ""


def merged(spans: np.ndarray) -> np.ndarray:
    """Disjoint sorted [lo, hi) rows, touching ones joined."""
    if not len(spans):
        return spans.reshape(0, 2)
    spans = spans[np.argsort(spans[:, 0], kind="stable")]
    top = np.maximum.accumulate(spans[:, 1])
    new = np.concatenate(([True], spans[1:, 0] > top[:-1]))
    at = np.flatnonzero(new)
    return np.stack((spans[at, 0], np.concatenate((top[at[1:] - 1], top[-1:]))), axis=1)


def _bytes(b: pa.RecordBatch, name: str) -> list[bytes]:
    col = b.column(b.schema.get_field_index(name))
    return [x or b"" for x in col.cast(pa.large_binary() if pa.types.is_large_string(col.type) else pa.binary()).to_pylist()]


def _find_runs(kind: Units):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            t1, t2 = (b.column(b.schema.get_field_index(c)).to_numpy() for c in ("t1", "t2"))
            parts, size = [], 0
            for i, text in enumerate(_bytes(b, "text")):
                h, first, count, twice = runs(kind.units(text), kind.gram, kind.window)
                if len(h):
                    parts.append((np.full(len(h), i), h, first, count, twice))
                    size += len(h)
                if size > 200_000:
                    yield _runs_batch(t1, t2, parts)
                    parts, size = [], 0
            if parts:
                yield _runs_batch(t1, t2, parts)

    return go


def _runs_batch(t1, t2, parts) -> pa.RecordBatch:
    row, h, first, count, twice = (np.concatenate(c) for c in zip(*parts, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(h), pa.array(t1[row]), pa.array(t2[row]), pa.array(first.astype(np.int32)), pa.array(count.astype(np.int32)), pa.array(twice)], names=["h", "t1", "t2", "first", "count", "twice"])


def _pack_runs(kind: Units):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            t1, t2 = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("t1", "t2"))
            out, size = ([], [], [], [], []), 0
            for i, (text, found) in enumerate(zip(_bytes(b, "text"), b.column(b.schema.get_field_index("runs")).to_pylist(), strict=True)):
                first, count = np.array([r["first"] for r in found]), np.array([r["count"] for r in found])
                got = kind.pack(text, first, count)
                for c, v in zip(out, ([r["h"] for r in found], [t1[i]] * len(got), [t2[i]] * len(got), first.tolist(), got), strict=True):
                    c.extend(v)
                size += sum(map(len, got))
                if size > 16_000_000:
                    yield _packed_batch(out)
                    out, size = ([], [], [], [], []), 0
            if out[0]:
                yield _packed_batch(out)

    return go


def _packed_batch(out) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in out[:3]), pa.array(out[3], pa.int32()), pa.array(out[4], pa.binary())], names=["h", "t1", "t2", "first", "packed"])


def _decide(kind: Units, room: int = 4_000_000):
    """Rows come sorted by bucket; whole buckets are handed on, many small ones at once."""

    def emit(rows) -> pa.RecordBatch | None:
        h, t1, t2, first, packed = rows
        got = list(kind.decide(np.array(h, np.int64), packed))
        if not got:
            return None
        row, lo, hi = np.array(got, np.int64).T
        at = np.array(first, np.int64)[row]
        return pa.RecordBatch.from_arrays([pa.array(np.array(t1, np.int64)[row]), pa.array(np.array(t2, np.int64)[row]), pa.array((at + lo).astype(np.int32)), pa.array((at + hi).astype(np.int32))], names=["t1", "t2", "lo", "hi"])

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = ([], [], [], [], []), 0
        for b in batches:
            cols = [b.column(i).to_pylist() for i in range(5)]
            for c, v in zip(held, cols, strict=True):
                c.extend(v)
            size += sum(map(len, cols[4]))
            if size >= room and held[0][0] != held[0][-1]:
                cut = len(held[0]) - 1
                while held[0][cut - 1] == held[0][-1]:
                    cut -= 1
                if (out := emit([c[:cut] for c in held])) is not None:
                    yield out
                held = tuple(c[cut:] for c in held)
                size = sum(map(len, held[4]))
        if held[0] and (out := emit(held)) is not None:
            yield out

    return go


def _single_windows(kind: Units, keep: int):
    """128-bit hashes of the single windows of hot runs; ``keep`` bits of each half are kept."""
    some = _U((1 << keep) - 1)

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            t1, t2 = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("t1", "t2"))
            for i, (text, found) in enumerate(zip(_bytes(b, "text"), b.column(b.schema.get_field_index("runs")).to_pylist(), strict=True)):
                u = kind.units(text)
                at = np.concatenate([np.arange(r["first"], r["first"] + r["count"]) for r in found])
                both = [mixed(of_ranges(prefix(x), at, at + kind.window)) & some for x in (u, mixed(u + _U(0x5851F42D4C957F2D)))]
                yield pa.RecordBatch.from_arrays([*(pa.array(x.view(np.int64)) for x in both), pa.array(np.full(len(at), t1[i])), pa.array(np.full(len(at), t2[i])), pa.array(at.astype(np.int32))], names=["w1", "w2", "t1", "t2", "lo"])

    return go


def _show_windows(kind: Units, room: int = 10_000):
    """(w1, w2, window): the different windows of each class, once for some thousand texts."""

    def shown(seen: set[tuple[int, int, bytes]]) -> pa.RecordBatch:
        w1, w2, window = zip(*seen, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(w1, pa.int64()), pa.array(w2, pa.int64()), pa.array(window, pa.binary())], names=["w1", "w2", "window"])

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int, bytes]] = set()
        for b in sliced(batches):
            for text, hits in zip(_bytes(b, "text"), b.column(b.schema.get_field_index("hits")).to_pylist(), strict=True):
                at = np.array([x["lo"] for x in hits])
                seen.update((x["w1"], x["w2"], w) for x, w in zip(hits, kind.pack(text, at, np.ones_like(at)), strict=True))
                if len(seen) > room:
                    yield shown(seen)
                    seen = set()
        if seen:
            yield shown(seen)

    return go


def _finish(kind: Units, names: list[str]):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            t1, t2, copies = (b.column(b.schema.get_field_index(c)) for c in ("t1", "t2", "copies"))
            lists, rows = b.column(b.schema.get_field_index("spans")).to_pylist(), []
            for text, spans, c in zip(_bytes(b, "text"), lists, copies.to_pylist(), strict=True):
                n = len(kind.units(text)) if c > 1 else 0
                got = np.array([[0, n]] if n >= kind.window else [] if c > 1 else [(s["lo"], s["hi"]) for s in spans or ()], np.int64).reshape(-1, 2)
                rows.append(kind.finish(text, merged(got)))
            yield pa.RecordBatch.from_arrays([t1, t2, *(pa.array(c) for c in zip(*rows, strict=True))], names=["t1", "t2", *names])

    return go


def search(docs: DataFrame, kind: Units, hot: int = HOT, keep: int = 64) -> DataFrame:
    """doc_id and kind.result for each row of (doc_id, text).

    ``hot`` and ``keep`` (bits of each half of a window's hash) choose the way that windows take, never the result.
    """
    keyed = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("t1", F.xxhash64("text")).withColumn("t2", F.xxhash64("text", F.lit(1)))
    distinct = keyed.groupBy("t1", "t2").agg(F.first("text").alias("text"), F.count("*").alias("copies"))
    found = distinct.select("t1", "t2", "text", "copies").mapInArrow(_find_runs(kind), "h long, t1 long, t2 long, first int, count int, twice boolean")
    shared = found.groupBy("h").agg(F.count("*").alias("n"), F.min("t1").alias("a"), F.max("t1").alias("b"), F.max("twice").alias("twice")).where("a <> b or twice").select("h", "n")
    left = found.select("h", "t1", "t2", "first", "count").join(shared, "h")
    by_text = left.groupBy("t1", "t2").agg(F.collect_list(F.when(F.col("n") <= hot, F.struct("h", "first", "count"))).alias("runs"), F.collect_list(F.when(F.col("n") > hot, F.struct("h", "first", "count"))).alias("hot"))
    # a bucket's runs in one place, in order; hot buckets take the other way
    joined = distinct.join(by_text, ["t1", "t2"])
    packed = "h long, t1 long, t2 long, first int, packed binary"
    cool = joined.where(F.size("runs") > 0).select("t1", "t2", "text", "copies", "runs").mapInArrow(_pack_runs(kind), packed)
    single = joined.where(F.size("hot") > 0).select("t1", "t2", "text", "copies", F.col("hot").alias("runs")).mapInArrow(_single_windows(kind, keep), "w1 long, w2 long, t1 long, t2 long, lo int")
    often = single.groupBy("w1", "w2").agg(F.count("*").alias("n")).where("n > 1").select("w1", "w2")
    hits = single.join(often, ["w1", "w2"])
    # classes of equal hashes that hold different windows; all columns are kept, so that the exchange of texts is one
    to_show = distinct.join(hits.groupBy("t1", "t2").agg(F.collect_list(F.struct("w1", "w2", "lo")).alias("hits")), ["t1", "t2"])
    shown = to_show.select("t1", "t2", "text", "copies", "hits").mapInArrow(_show_windows(kind), "w1 long, w2 long, window binary")
    wrong = shown.groupBy("w1", "w2").agg(F.min("window").alias("a"), F.max("window").alias("b")).where("a <> b").select("w1", "w2")
    again = hits.join(wrong, ["w1", "w2"], "left_semi").groupBy("t1", "t2").agg(F.collect_list(F.struct(F.xxhash64("w1", "w2").alias("h"), F.col("lo").alias("first"), F.lit(1).alias("count"))).alias("runs"))
    told_apart = distinct.join(again, ["t1", "t2"]).select("t1", "t2", "text", "copies", "runs").mapInArrow(_pack_runs(kind), packed)
    spans = cool.unionByName(told_apart).repartition("h").sortWithinPartitions("h").mapInArrow(_decide(kind), "t1 long, t2 long, lo int, hi int")
    spans = spans.unionByName(hits.join(wrong, ["w1", "w2"], "left_anti").select("t1", "t2", "lo", (F.col("lo") + kind.window).alias("hi")))
    covered = spans.groupBy("t1", "t2").agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    names = [f.split()[0] for f in kind.result.split(", ")]
    done = distinct.join(covered, ["t1", "t2"], "left").select("t1", "t2", "text", "copies", "spans").mapInArrow(_finish(kind, names), f"t1 long, t2 long, {kind.result}")
    return keyed.select("doc_id", "t1", "t2").join(done, ["t1", "t2"]).select("doc_id", *names)

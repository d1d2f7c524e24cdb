"""Exact nearest neighbours by inner product on unit vectors: the ground truth."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from annspark.functions.vectors import dot, matrix
from annspark.operators import scan

#: Queries of one wave: what a scan carries to every task.
WAVE = 10_000
#: Scores that a task holds at once.
SCORES = 4_000_000


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best scores, ties to the smaller id."""
    if len(scores) > 4 * k:
        bar = np.partition(scores, len(scores) - k)[len(scores) - k]
        some = np.flatnonzero(scores >= bar)
    else:
        some = np.arange(len(scores))
    return some[np.lexsort((ids[some], -scores[some]))[:k]]


def best_rows(scores: np.ndarray, ids: np.ndarray, k: int, given: np.ndarray | None = None, bars: np.ndarray | None = None, exactly: Callable | None = None, slack: float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of the k best scores of each column, ties to the smaller id: ``best`` of all columns at once, or of those ``given``.

    The k-th best of some first rows is a bar that no row of the result lies under, so only the rows above it are ordered. ``bars`` has a bar of each
    column from rows seen before and is raised: rows under it are left out. ``exactly(rows, columns)`` replaces scores that are off by ``slack`` at most:
    in the matrix too, where a row may be among the best.
    """
    n, q = scores.shape
    head = min(n, max(8 * k, n >> 4))
    low = np.partition(scores[:head], head - k, axis=0)[head - k] if head > k else np.full(q, -np.inf)
    some = scores >= ((low - slack if bars is None else np.maximum(low - slack, bars)) - slack)
    rows, who = np.divmod(np.flatnonzero(some if given is None else some & given), max(q, 1))
    if exactly is not None:  # of those alone that may be among the k best
        by = np.lexsort((-scores[rows, who], who))
        rows, who = rows[by], who[by]
        x, kth = scores[rows, who], np.full(q, -np.inf)
        last = np.arange(len(who)) - np.searchsorted(who, who) == k - 1
        kth[who[last]] = x[last]
        rows, who = (y[x >= kth[who] - 2 * slack] for y in (rows, who))
        scores[rows, who] = exactly(rows, who)
    by = np.lexsort((ids[rows], -scores[rows, who], who))
    rows, who = rows[by], who[by]
    place = np.arange(len(who)) - np.searchsorted(who, who)
    if bars is not None:
        last = place == k - 1
        bars[who[last]] = np.maximum(bars[who[last]], scores[rows[last], who[last]])
    return rows[place < k], who[place < k]


def best_filled(ids: np.ndarray, group: np.ndarray, queries: int, k: int, fill: Callable, dense: bool, bars: dict[int, np.ndarray] | None = None, exactly: Callable | None = None, slack: float = 0.0) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(group, rows, places of queries, scores): the k best rows of each group and query, some queries at a time.

    ``fill(a, z)`` yields (rows, places, scores matrix), cell by cell, for queries a to z; pairs that it does not name are no candidates. Where most
    are, the cells are put into one matrix, so that k rows of all cells are left; elsewhere k rows of each cell are. ``bars``, kept by the caller over
    the batches of a task, has a bar of each group and query; ``exactly(rows, places)`` and ``slack``: see ``best_rows``.
    """
    bars = {} if bars is None else bars
    step = max(1, SCORES // len(ids))
    for a in range(0, queries, step):
        z = min(queries, a + step)
        if dense:
            s = np.full((len(ids), z - a), -np.inf)
            for rows, who, x in fill(a, z):
                if x.shape == s.shape:  # all cells at once
                    s = x
                else:
                    s[rows[:, None], who - a] = x
            blocks = [(np.arange(len(ids)), np.arange(a, z), s)]
        else:
            blocks = fill(a, z)
        for rows, who, s in blocks:
            for g in np.unique(group[rows]):
                own = np.flatnonzero(group[rows] == g)
                x = s if len(own) == len(rows) else s[own]
                bar = bars.setdefault(int(g), np.full(queries, -np.inf))
                raised = bar[who]
                at, w = best_rows(x, ids[rows[own]], k, x > -np.inf if dense else None, raised, exactly and (lambda r, w, o=rows[own], who=who: exactly(o[r], who[w])), slack)
                bar[who] = raised
                if len(at):
                    yield int(g), rows[own[at]], who[w], x[at, w]


def collect_queries(queries: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(ids, matrix) of a bounded query set (qid, qv)."""
    rows = _first(queries)
    if rows.num_rows > WAVE:
        raise ValueError(f"more than {WAVE} queries; search in waves")
    return _arrays(rows)


def _first(queries: DataFrame) -> pa.Table:
    return queries.select("qid", "qv").orderBy("qid").limit(WAVE + 1).toArrow()


def _arrays(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    return rows.column("qid").to_numpy().astype(np.int64, copy=False), matrix(rows.column("qv"))


def waves(queries: DataFrame, size: int | None = None) -> Iterator[DataFrame]:
    """Query sets of bounded size, by hash."""
    size = size or WAVE
    # hashed parts of a large wave differ little in size
    n = max(1, -(-queries.count() // max(size // 2, size - 10 * math.isqrt(size))))
    for i in range(n):
        yield queries if n == 1 else queries.where(F.pmod(F.xxhash64("qid"), F.lit(n)) == i)


def collected(queries: DataFrame) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, matrix) of each wave of any query set; one wave, without a count, where it is small."""
    rows = _first(queries)
    if rows.num_rows <= WAVE:
        yield _arrays(rows)
    else:
        del rows
        yield from map(collect_queries, waves(queries))


def united(found: Iterable[DataFrame]) -> DataFrame:
    """Results of all waves; a query is in one of them."""
    return reduce(DataFrame.unionByName, found)


def top_rows(found: DataFrame, k: int, by: tuple[str, ...] = ("qid",)) -> DataFrame:
    """The k best (score, then id) of each group; a window group limit prunes before the exchange."""
    w = Window.partitionBy(*by).orderBy(F.desc("score"), "id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def merged(found: DataFrame, k: int, by: tuple[str, ...] = ("qid",)) -> DataFrame:
    """The k best of each group of what the tasks of a scan found, as arrays: a sort of their rows in Spark takes longer than the scan."""

    def few(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(held).combine_chunks()
        keys, ids, score = [t.column(c).to_numpy() for c in by], t.column("id").to_numpy(), t.column("score").to_numpy()
        for g in np.unique(keys[0]) if len(keys) > 1 else (None,):
            own = np.arange(len(ids)) if g is None else np.flatnonzero(keys[0] == g)
            own = own[scan.ordered(ids[own], score[own], keys[-1][own])]
            q = keys[-1][own]
            place = np.arange(len(q)) - np.searchsorted(q, q)
            yield from t.take(pa.array(own[place < k])).combine_chunks().to_batches()

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            if b.num_rows:
                held.append(b)
                if sum(x.num_rows for x in held) > SCORES and len(held) > 64:
                    held = list(few(held))
        if held:
            yield from few(held)

    found = found.select(*by, "id", "score")
    n = 2 * found.sparkSession.sparkContext.defaultParallelism
    return found.repartition(n, *by).mapInArrow(go, found.schema)


def knn(base: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """(qid, rank, id, score): one scan a wave of queries, k rows a query leave each task."""
    return united(_knn(base, qid, q, k) for qid, q in collected(queries))


def _knn(base: DataFrame, qid: np.ndarray, q: np.ndarray, k: int) -> DataFrame:
    def read(b: pa.RecordBatch):
        ids = b.column(0).to_numpy()
        return ids, np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int32), matrix(b.column(1))

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in scan.search(batches, read, qid, q, scan.everywhere(len(qid)), k):
            yield b.select(["qid", "id", "score"])

    return top_rows(merged(base.select("id", "v").mapInArrow(go, "qid long, id long, score double"), k), k).select("qid", "rank", "id", "score")


def knn_native(base: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """The same inside Catalyst, for plans without Python; the query side is broadcast wave by wave."""
    scored = united(base.crossJoin(F.broadcast(w)).select("qid", "id", dot("v", "qv").alias("score")) for w in waves(queries))
    return top_rows(scored, k).select("qid", "rank", "id", "score")


def knn_cumulative(base: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """(batch, qid, rank, id): truth of the rows of all batches up to each, in one scan a wave of queries.

    A batch's own k best are found once; the truth of batch t is the best of those of batches up to t.
    """
    return accumulate(united(_own(base, qid, q, k) for qid, q in collected(queries)), k, base.select(F.col("batch").cast("int").alias("batch")).distinct())


def _own(base: DataFrame, qid: np.ndarray, q: np.ndarray, k: int) -> DataFrame:
    def read(b: pa.RecordBatch):
        ids = b.column(0).to_numpy()
        return ids, np.zeros(len(ids), np.int64), b.column(2).to_numpy(), matrix(b.column(1))

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from scan.search(batches, read, qid, q, scan.everywhere(len(qid)), k)

    own = base.select("id", "v", F.col("batch").cast("int").alias("batch")).mapInArrow(go, "batch int, qid long, id long, score double")
    return merged(own, k, ("batch", "qid"))


def accumulate(own: DataFrame, k: int, batches: DataFrame | None = None) -> DataFrame:
    """From each batch's k best (batch, qid, id, score) to the k best of all batches so far; without ``batches``, (batch), ``own`` is made twice."""
    last = (own.select("batch").distinct() if batches is None else batches).select(F.col("batch").alias("upto"))
    seen = own.join(F.broadcast(last), F.col("batch") <= F.col("upto")).select(F.col("upto").alias("batch"), "qid", "id", "score")
    return top_rows(seen, k, ("batch", "qid")).select("batch", "qid", "rank", "id", "score")


def merge(old: DataFrame, new: DataFrame, k: int = 10) -> DataFrame:
    """Truth after an insert: the best of the old truth and the new rows' own."""
    return top_rows(old.select("qid", "id", "score").unionByName(new.select("qid", "id", "score")), k).select("qid", "rank", "id", "score")

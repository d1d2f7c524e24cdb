"""Mixing sources to target weights by highest-quotient apportionment (odd divisors 1, 3, 5, ...).

The words of each source are dealt in equal blocks. Blocks go to sources by the highest quotient
target / (2 * blocks + 1), then, inside a source, to its shards by the same rule, so that every
(source, shard) cell gets an integer quota. Within a cell the documents stand in a seeded order and their
words are cut into equal blocks of at most ``block`` words, which may begin and end inside documents. A quota of more than the cell holds takes
the whole cell as often as it fits; the rest is a whole number of blocks, chosen by a seeded permutation of block numbers (the
affine map i -> (mult * i + shift) mod blocks, which is one to one; the numbers it sends below the quota are taken). What rounding to whole
blocks leaves over passes to the source's next shard. A document's share is plain arithmetic on its running
position, which needs no more than one bounded window per cell.

Only per-source and per-shard totals (one row per source or per ``shard_docs`` documents) leave the
executors' group-bys; the documents themselves are never gathered. A hot source has many shards.

Defined cases: null text counts as size 0 and takes 0; null source is a source of its own and comes last;
sources whose documents are all empty get target 0; repeated rows are documents of their own; an empty
table gives an empty result; further columns of the input are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from annspark.llm.common import WORD, cut, restored, salted, shielded, sliced

CYCLE = (5.0, 2.0, 1.0)


def water_fill(sizes: np.ndarray, weights: np.ndarray, most: float = 3.0) -> np.ndarray:
    """Shares of sum(sizes) by weight; a share stops at most * size and its excess is dealt again by weight."""
    sizes, weights = np.asarray(sizes, float), np.asarray(weights, float)
    out, free, left = np.zeros(len(sizes)), sizes > 0, float(sizes.sum())
    while free.any():
        share = np.where(free, left * weights / weights[free].sum(), 0.0)
        over = free & (share > most * sizes)
        if not over.any():
            return out + share
        out[over] = most * sizes[over]
        left -= out[over].sum()
        free &= ~over
    return out


def apportion(votes: np.ndarray, seats: int, most: np.ndarray | None = None) -> np.ndarray:
    """Integer seats by highest quotient votes / (2 s + 1), ties to the earlier entry, never above ``most``.

    Starts at the rounded proportional shares, which are right for their own sum, and then adds the highest
    or takes back the lowest quotients: at most one step per entry is left to do.
    """
    votes = np.asarray(votes, float)
    most = np.full(len(votes), np.iinfo(np.int64).max) if most is None else np.asarray(most, np.int64)
    if not len(votes) or votes.sum() <= 0:
        return np.zeros(len(votes), np.int64)
    got = np.minimum(np.floor(votes * seats / votes.sum() + 0.5).astype(np.int64), most)
    gap = int(seats - got.sum())
    if gap > 0:
        heap = [(-votes[i] / (2 * got[i] + 1), i) for i in range(len(votes)) if votes[i] > 0 and got[i] < most[i]]
        heapq.heapify(heap)
        while gap > 0 and heap:
            _, i = heapq.heappop(heap)
            got[i] += 1
            gap -= 1
            if got[i] < most[i]:
                heapq.heappush(heap, (-votes[i] / (2 * got[i] + 1), i))
    elif gap < 0:
        heap = [(votes[i] / (2 * got[i] - 1), -i) for i in range(len(votes)) if got[i] > 0]
        heapq.heapify(heap)
        while gap < 0 and heap:
            _, i = heapq.heappop(heap)
            i = -i
            got[i] -= 1
            gap += 1
            if got[i] > 0:
                heapq.heappush(heap, (votes[i] / (2 * got[i] - 1), -i))
    return got


def plan(totals: pd.DataFrame, block: int, cycle=CYCLE, most: float = 3.0) -> pd.DataFrame:
    """Targets and blocks per source from (source, size); sources by code point, null last."""
    names = totals["source"].tolist()
    order = sorted(range(len(names)), key=lambda i: (names[i] is None, (names[i] or "").encode("utf-8", "surrogatepass")))
    t = totals.iloc[order].reset_index(drop=True)
    weights = np.array([cycle[i % len(cycle)] for i in range(len(t))])
    size = t["size"].to_numpy(np.int64)
    target = water_fill(size, weights, most)
    blocks = apportion(target, int(round(target.sum() / block)), np.ceil(most * size / block).astype(np.int64))
    return t.assign(target=target, blocks=blocks)


def block_quotas(size: np.ndarray, words: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(blocks, whole rounds, blocks chosen) of each cell of ``size`` words that is to give ``words`` words."""
    cuts = np.maximum(1, -(-size // block))
    rounds = words // np.maximum(size, 1)
    chosen, over = np.zeros(len(size), np.int64), 0.0
    for i in np.flatnonzero(size > 0):
        want = words[i] - rounds[i] * size[i]
        if want > 0:
            each = size[i] / cuts[i]
            chosen[i] = min(max(round((want + over) / each), 0), cuts[i])
            over += want - chosen[i] * each
    return cuts, rounds, chosen


def permutation(blocks: int, *seed: object) -> tuple[int, int]:
    """(mult, shift) of a seeded one-to-one map i -> (mult * i + shift) mod blocks."""
    h = hashlib.blake2b(repr(seed).encode("utf-8", "surrogatepass"), digest_size=16).digest()
    mult, shift = (int.from_bytes(x, "big") % blocks for x in (h[:8], h[8:]))
    while math.gcd(mult, blocks) != 1:
        mult += 1
    return mult, shift


def _to_shards(block: int, most: float, seed: str):
    def deal(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("shard", kind="stable")
        size = pdf["size"].to_numpy(np.int64)
        quota = apportion(size, int(pdf["blocks"].iloc[0]), np.ceil(most * size / block).astype(np.int64))
        cuts, rounds, chosen = block_quotas(size, np.minimum(quota * block, np.floor(most * size).astype(np.int64)), block)
        source = pdf["source"].iloc[0]
        maps = [permutation(int(n), seed, source if isinstance(source, str) else None, int(s)) for n, s in zip(cuts, pdf["shard"], strict=True)]
        return pdf[["source", "shard"]].assign(cell_size=size, cuts=cuts, rounds=rounds, chosen=chosen, mult=[m for m, _ in maps], shift=[s for _, s in maps])

    return deal


#: Words of the cell before block ``i``, and the [from, to) words of a document, as places in it, that block ``i`` holds.
_LOW = "((({i}) * cell_size + cuts - 1) DIV cuts)"
_FROM = f"greatest(0L, {_LOW.format(i='i')} - before)"
_TO = f"least(size, {_LOW.format(i='i + 1')} - before)"
_RUNS = f"""CASE WHEN size > 0 AND chosen > 0 THEN transform(
    filter(sequence(before * cuts DIV cell_size, (before + size - 1) * cuts DIV cell_size), i -> (mult * i + shift) % cuts < chosen),
    i -> struct({_FROM} AS a, {_TO} AS z)) ELSE array() END"""


def mix(docs: DataFrame, seed: str = "mix-1", block: int = 32, shard_docs: int = 2_000, most: float = 3.0, carry: tuple[str, ...] = (), runs: bool = False) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken, *carry[, rounds, runs]) for every row of (doc_id, text, source).

    ``block`` words make one block; ``shard_docs`` documents, about, make one shard. ``runs`` are the [a, z) words taken beyond ``rounds`` whole times.
    """
    spark = docs.sparkSession
    order = salted(F.col("doc_id"), salt=seed)
    sized = docs.select("doc_id", "source", *(F.col(f"`{c}`").alias(f"_c{i}") for i, c in enumerate(carry)), F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"), F.xxhash64("text").alias("_h"))
    if not carry:
        sized = cut(sized)  # small rows, read three times below
    per_source = sized.groupBy("source").agg(F.sum("size").alias("size"), F.count("*").alias("n"))
    # one row per source: the only thing the driver sees
    totals = pd.DataFrame([r.asDict() for r in per_source.toLocalIterator()], columns=["source", "size", "n"])
    planned = plan(totals, block, most=most) if len(totals) else totals.assign(target=0.0, blocks=0)
    rows = [(s if isinstance(s, str) else None, int(z), float(t), int(b), max(1, math.ceil(n / shard_docs))) for s, z, t, b, n in planned[["source", "size", "target", "blocks", "n"]].itertuples(index=False)]
    sources = spark.createDataFrame(rows, "source string, source_size long, target double, blocks long, shards int")
    hinted = F.broadcast(sources) if len(rows) <= 100_000 else sources
    key = F.col("source").eqNullSafe(F.col("s_source"))
    dealt = sized.join(hinted.withColumnRenamed("source", "s_source"), key).drop("s_source").withColumn("shard", F.pmod(salted(F.col("doc_id"), salt=seed + "/shard"), F.col("shards").cast("long")))
    cells = dealt.groupBy("source", "shard").agg(F.sum("size").alias("size"), F.first("blocks").alias("blocks"))
    quotas = cells.groupBy("source").applyInPandas(_to_shards(block, most, seed), "source string, shard long, cell_size long, cuts long, rounds long, chosen long, mult long, shift long")
    q = quotas.withColumnsRenamed({"source": "q_source", "shard": "q_shard"})
    w = Window.partitionBy("source", "shard").orderBy(order, "doc_id", "size", "_h").rowsBetween(Window.unboundedPreceding, -1)
    placed = dealt.withColumn("before", F.coalesce(F.sum("size").over(w), F.lit(0)))
    joined = placed.join(q, F.col("source").eqNullSafe(F.col("q_source")) & (F.col("shard") == F.col("q_shard"))).withColumn("runs", F.expr(_RUNS))
    taken = F.expr("rounds * size + aggregate(runs, 0L, (n, r) -> n + r.z - r.a)")
    out = joined.select("doc_id", "source", *(F.col(f"_c{i}").alias(c) for i, c in enumerate(carry)), "size", "source_size", "target", taken.cast("long").alias("taken"), "rounds", "runs")
    return out if runs else out.drop("rounds", "runs")


_WORD = re.compile(WORD)


def some_words(text: str, runs: list[dict[str, int]]) -> str:
    """The runs [a, z) of words of a text, each as it stands there, joined by line ends; runs that touch are one."""
    merged: list[list[int]] = []
    for r in runs:
        if r["a"] >= r["z"]:
            continue
        if merged and merged[-1][1] == r["a"]:
            merged[-1][1] = r["z"]
        else:
            merged.append([r["a"], r["z"]])
    at = [m.span() for m in _WORD.finditer(text)]
    return "\n".join(text[at[a][0] : at[z - 1][1]] for a, z in merged)


def take(docs: DataFrame, **options) -> DataFrame:
    """The mix itself, in the columns of docs: a document stands once for each whole time it is taken, and once more, as the
    words of its chosen blocks, for the rest. Documents of which no word is taken are left out; n_chars, where there is
    such a column, follows the text."""
    safe, names = shielded(docs, ("doc_id", "source", "text"))
    rest = tuple(c for c in names if c not in ("doc_id", "source"))
    taken = mix(safe, carry=rest, runs=True, **options).where("taken > 0")
    parts = F.expr("sequence(1L, rounds + IF(taken > rounds * size, 1L, 0L))")
    each = taken.withColumn("_part", F.explode(parts)).withColumn("_runs", F.expr("IF(_part > rounds, runs, NULL)"))
    schema, at = safe.schema, names.index("text")

    def cut_text(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            runs = b.column(len(names)).to_pylist()
            new = pa.array([t if r is None else some_words(t, r) for t, r in zip(b.column(at).to_pylist(), runs, strict=True)], b.schema.field(at).type)
            yield pa.RecordBatch.from_arrays([new if i == at else b.column(i) for i in range(len(names))], names=names)

    out = restored(each.select(*names, "_runs").mapInArrow(cut_text, schema), names, docs.columns)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out

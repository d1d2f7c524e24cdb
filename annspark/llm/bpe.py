"""Byte-level BPE encoding and decoding by merge replay over a whole block of text.

A task takes the distinct pre-token pieces of its block that it has not met yet, lays their bytes end to
end as one linked list of tokens, and keeps an inverted index from each mergeable pair to the places where
it stands. Merges are then replayed over the whole block in rank order; a merge touches its places alone
and re-files just the pairs with their left and right neighbours. A merge that makes a pair of a lower rank
sends the replay back to that rank first, so the result is the one that the rank rule gives piece by piece.

No shuffle: pieces are independent of each other. A worker process keeps up to ``KEEP`` solved
pieces that it met in more than one block, and the last ``YOUNG`` others; results do not depend on that.

Defined cases: null and empty texts have no tokens; very long pieces cost O(n log n); lone surrogates, which
Spark's strings cannot hold, do not occur; repeated rows are encoded each for itself.
"""

from __future__ import annotations

import base64
import functools
import gc
import hashlib
import heapq
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, IntegerType

from annspark.llm.common import sliced, texts

KEEP, YOUNG = 200_000, 100_000
#: Pieces of one replay: as many as the processor's caches hold.
SPAN = 1_000

# A splitting pattern, and what says the same to the standard library's faster matcher over the characters that _ODD leaves,
# where letters, digits and white space mean the same to both.
PLAIN = {
    r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""": r"""'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+"""
}
_ODD = re.compile("[^\t\n\r\x20-\x7e\xc0-\u017f]")


@functools.lru_cache(maxsize=4)
def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Codec:
    """Ranks and pattern of one vocabulary, and the pieces solved so far."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, keep: int = KEEP):
        self.ranks, self.split, self.keep = ranks, regex.compile(pattern), keep
        self.plain = re.compile(PLAIN[pattern]) if pattern in PLAIN else None
        self.token = [b""] * (max(ranks.values()) + 1)
        for t, r in ranks.items():
            self.token[r] = t
        self.decimal = [str(i) for i in range(len(self.token))]
        # pieces solved; those of late, and which of them were met again in a later block
        self.solved: dict[str, tuple[int, ...]] = {}
        self.young: set[str] = set()
        self.again: set[str] = set()
        self.byte = [ranks[bytes([i])] for i in range(256)]
        # every pair of tokens that merges, as left << 32 | right -> merged: all splits of all tokens
        self.merges: dict[int, int] = {}
        for t, r in ranks.items():
            for i in range(1, len(t)):
                if (a := ranks.get(t[:i])) is not None and (b := ranks.get(t[i:])) is not None:
                    self.merges[a << 32 | b] = r

        self.first = [self.merges.get(self.byte[x] << 32 | self.byte[y], -1) for x in range(256) for y in range(256)]

    def replay(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        """Token ids of each piece."""
        raw = b"".join(pieces)
        ids = list(map(self.byte.__getitem__, raw))
        n, merged = len(ids), self.merges.get
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        # pairs of raw bytes, looked up side by side; those across two pieces do not count
        pairs = list(map(self.first.__getitem__, map(int.__add__, map((256).__mul__, raw), raw[1:])))
        pairs.append(-1)
        starts, at = [], 0
        for p in pieces:
            starts.append(at)
            at += len(p)
            if p:
                before[starts[-1]] = -1
                after[at - 1] = n
                pairs[at - 1] = -1
        index: dict[int, list[int]] = {}  # merged token -> places of its left part
        for i, r in enumerate(pairs):
            if r >= 0:
                if r in index:
                    index[r].append(i)
                else:
                    index[r] = [i]
        queue = list(index)
        heapq.heapify(queue)
        while queue:
            r = heapq.heappop(queue)
            places = index.pop(r, None)
            if places is None:
                continue
            if len(places) > 1:
                places.sort()
            for k, i in enumerate(places):
                # the place may have been merged away, or its pair changed, since it was filed
                if (a := ids[i]) < 0 or (j := after[i]) >= n or merged(a << 32 | ids[j]) != r:
                    continue
                ids[i], ids[j] = r, -1
                h = after[i] = after[j]
                low = r
                if h < n:
                    before[h] = i
                    if (s := merged(r << 32 | ids[h])) is not None:
                        if s in index:
                            index[s].append(i)
                        else:
                            index[s] = [i]
                            heapq.heappush(queue, s)
                        if s < low:
                            low = s
                if (g := before[i]) >= 0 and (s := merged(ids[g] << 32 | r)) is not None:
                    if s in index:
                        index[s].append(g)
                    else:
                        index[s] = [g]
                        heapq.heappush(queue, s)
                    if s < low:
                        low = s
                if low < r and k + 1 < len(places):
                    index.setdefault(r, []).extend(places[k + 1 :])
                    heapq.heappush(queue, r)
                    break
        out = []
        for start, p in zip(starts, pieces, strict=True):
            got, i = [], start if p else n
            while i < n:
                got.append(ids[i])
                i = after[i]
            out.append(tuple(got))
        return out

    def pieces(self, text: str) -> list[str]:
        return self.plain.findall(text) if self.plain is not None and not _ODD.search(text) else self.split.findall(text)

    def encode_block(self, block: Iterable[str]) -> Iterator[list[int]]:
        """Ids of each text, without special tokens."""
        cut = [self.pieces(t) for t in block]
        if len(self.young) > YOUNG:
            for p in self.young - self.again:
                del self.solved[p]
            self.young, self.again = set(), set()
            if len(self.solved) > self.keep:
                self.solved.clear()
        seen = set().union(*cut)
        new = list(seen.difference(self.solved))
        self.again |= seen & self.young
        for at in range(0, len(new), SPAN):
            some = new[at : at + SPAN]
            self.solved.update(zip(some, self.replay([p.encode("utf-8") for p in some]), strict=True))
        self.young.update(new)
        solved = self.solved
        for pieces in cut:
            ids: list[int] = []
            for p in pieces:
                ids += solved[p]
            yield ids

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.token.__getitem__, ids))


@functools.lru_cache(maxsize=2)
def codec_for(path: str, pattern: str) -> Codec:
    """One codec per worker process: tasks that follow each other reuse the solved pieces."""
    return Codec(read_ranks(path), pattern)


def blocks(values: list[str], chars: int = 2_000_000) -> Iterator[list[str]]:
    """Cuts of a batch, so that one block of pieces stays small whatever the texts' lengths."""
    some, size = [], 0
    for v in values:
        some.append(v)
        size += len(v)
        if size >= chars:
            yield some
            some, size = [], 0
    if some:
        yield some


def encode(docs: DataFrame, path: str, pattern: str, carry: tuple[str, ...] = ("doc_id",), ids: bool = True) -> DataFrame:
    """carry columns, then (n_tokens, ids_sha256, decoded_sha256[, ids]) of (text, *carry).

    ``path`` names the rank file, which every executor has as part of its installation.
    """
    n = len(carry)
    schema = docs.select(*carry).schema.add("n_tokens", "long").add("ids_sha256", "string").add("decoded_sha256", "string")
    if ids:
        schema = schema.add("ids", ArrayType(IntegerType()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = codec_for(path, pattern)
        gc.disable()  # nothing here makes cycles, and the solved pieces are many small objects to walk
        try:
            yield from encoded(codec, batches)
        finally:
            gc.enable()

    def encoded(codec: Codec, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            at = 0
            for block in blocks(texts(b)):  # a batch out for a block in, so that ids of one block alone are held
                count, sha, back, kept = [], [], [], []
                for got in codec.encode_block(block):
                    count.append(len(got))
                    sha.append(hashlib.sha256(",".join(map(codec.decimal.__getitem__, got)).encode()).hexdigest())
                    back.append(hashlib.sha256(codec.decode(got)).hexdigest())
                    if ids:
                        kept.append(np.array(got, np.int32))
                cols = [*(b.column(i).slice(at, len(block)) for i in range(n)), pa.array(count, pa.int64()), pa.array(sha, pa.string()), pa.array(back, pa.string())]
                if ids:
                    ends = np.concatenate(([0], np.cumsum(count))).astype(np.int32)
                    cols.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(kept))))
                yield pa.RecordBatch.from_arrays(cols, names=schema.names)
                at += len(block)

    return docs.select(*carry, "text").mapInArrow(run, schema)

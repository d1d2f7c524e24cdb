"""Layered proximity graphs, sharded: each shard of the table has a graph of its own, a search asks all shards and merges.

Spark has no global graph; this is the sampled comparison that the cost model (``cost.graph_bytes``) extends to any size.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.functions.vectors import matrix
from annspark.operators.exact import collected, top_rows


class Graph:
    """Hierarchical navigable graph over the rows of a matrix, by inner product of unit vectors."""

    def __init__(self, x: np.ndarray, links: int = 16, ef: int = 100, seed: int = 42):
        self.x, self.links, self.ef = x, links, ef
        rng = np.random.default_rng(seed)
        self.level = np.minimum((-np.log(rng.random(len(x))) / np.log(links)).astype(int), 8)
        self.near: list[list[list[int]]] = [[[] for _ in range(lv + 1)] for lv in self.level]
        self.top = 0 if len(x) else -1
        for i in range(1, len(x)):
            self._add(i)

    def _layer(self, q: np.ndarray, start: list[int], ef: int, layer: int) -> list[tuple[float, int]]:
        """The ef best (score, row) of a layer reached from the start, best first."""
        seen = set(start)
        found = [(float(self.x[i] @ q), i) for i in start]
        todo = [(-s, i) for s, i in found]
        heapq.heapify(todo)
        heapq.heapify(found)
        while todo:
            s, i = heapq.heappop(todo)
            if len(found) >= ef and -s < found[0][0]:
                break
            new = [j for j in self.near[i][layer] if j not in seen]
            if not new:
                continue
            seen.update(new)
            for sc, j in zip((self.x[new] @ q).tolist(), new, strict=True):
                if len(found) < ef:
                    heapq.heappush(found, (sc, j))
                    heapq.heappush(todo, (-sc, j))
                elif sc > found[0][0]:
                    heapq.heapreplace(found, (sc, j))
                    heapq.heappush(todo, (-sc, j))
        return sorted(found, key=lambda f: (-f[0], f[1]))

    def _pick(self, found: list[tuple[float, int]], m: int) -> list[int]:
        """Diverse neighbours: one nearer to a chosen one than to the point itself is passed over, then used to fill up."""
        out: list[int] = []
        for s, i in found:
            if len(out) == m:
                break
            if not out or float((self.x[out] @ self.x[i]).max()) < s:
                out.append(i)
        return out + [i for _, i in found if i not in out][: m - len(out)]

    def _add(self, i: int) -> None:
        q, at = self.x[i], [self.top]
        for layer in range(self.level[self.top], self.level[i], -1):
            at = [self._layer(q, at, 1, layer)[0][1]]
        for layer in range(min(self.level[i], self.level[self.top]), -1, -1):
            found = self._layer(q, at, self.ef, layer)
            most = self.links * (2 if layer == 0 else 1)
            self.near[i][layer] = self._pick(found, self.links)
            for j in self.near[i][layer]:
                mine = self.near[j][layer]
                mine.append(i)
                if len(mine) > most:
                    s = self.x[mine] @ self.x[j]
                    self.near[j][layer] = self._pick(sorted(zip(s.tolist(), mine, strict=True), key=lambda f: (-f[0], f[1])), most)
            at = [j for _, j in found]
        if self.level[i] > self.level[self.top]:
            self.top = i

    def search(self, q: np.ndarray, k: int, ef: int) -> list[tuple[float, int]]:
        if self.top < 0:
            return []
        at = [self.top]
        for layer in range(self.level[self.top], 0, -1):
            at = [self._layer(q, at, 1, layer)[0][1]]
        return self._layer(q, at, max(ef, k), 0)[:k]


def search(base: DataFrame, queries: DataFrame, k: int = 10, links: int = 16, ef_build: int = 100, ef: int = 64, shard_rows: int = 20_000, seed: int = 42) -> DataFrame:
    """(qid, rank, id, score): each shard of about ``shard_rows`` rows builds its graph in one task and answers every query."""
    asked = list(collected(queries))
    shards = max(1, -(-base.count() // shard_rows))

    def ask(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids, g = t.column("id").to_numpy(), Graph(matrix(t.column("v")), links, ef_build, seed)
        out = []
        for qid, q in asked:
            got = [(int(a), int(ids[i]), s) for a, v in zip(qid, q, strict=True) for s, i in g.search(v, k, ef)]
            a, i, s = zip(*got, strict=True) if got else ((), (), ())
            out.append(pa.table({"qid": pa.array(a, pa.int64()), "id": pa.array(i, pa.int64()), "score": pa.array(s, pa.float64())}))
        return pa.concat_tables(out)

    found = base.select("id", "v", F.pmod(F.xxhash64("id"), F.lit(shards)).alias("shard")).groupBy("shard").applyInArrow(ask, "qid long, id long, score double")
    return top_rows(found, k).select("qid", "rank", "id", "score")

"""The kernel that searches share: the k best rows of each group and query, by inner product and a term of the row's cell.

Products are made in single precision and only tell which pairs may be among the k best; the score of those is made in double precision. A pair is
left out only if it lies under a bar, the k-th best of rows seen before, by more than single precision can be off.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa

#: Products that a task holds at once.
BLOCK = 1 << 20
#: Rows of a cell that the first bars are taken from.
HEAD = 512
#: Queries at a time where all share one cell.
QUERIES = 1_024
#: Pairs a query that may wait for their exact score.
WAITING = 24
#: Bytes of vectors that a task gathers before it searches them.
GATHERED = 1 << 26

Probes = dict[int, tuple[np.ndarray, np.ndarray]]


def places(m: np.ndarray) -> np.ndarray:
    """Flat places of the true ones, of which there are few: looked for eight at a time."""
    m = m.ravel()
    whole = len(m) & ~7
    some = np.flatnonzero(m[:whole].view(np.uint64))
    i, j = np.nonzero(m[:whole].reshape(-1, 8)[some])
    return np.concatenate((some[i] * 8 + j, whole + np.flatnonzero(m[whole:])))


def ordered(ids: np.ndarray, score: np.ndarray, who: np.ndarray) -> np.ndarray:
    """The order by query, falling score and id: ids are compared in runs of equal scores alone."""
    by = np.argsort(-score)
    kind = np.uint16 if who.max(initial=0) < 1 << 16 else who.dtype  # short keys are sorted in linear time
    by = by[np.argsort(who[by].astype(kind), kind="stable")]
    same = (np.diff(score[by]) == 0) & (np.diff(who[by]) == 0)
    tied = np.flatnonzero(np.concatenate((same, [False])) | np.concatenate(([False], same)))
    if len(tied):
        run = np.cumsum(np.concatenate(([True], ~same)))[tied]
        by[tied] = by[tied][np.lexsort((ids[by[tied]], run))]
    return by


class Best:
    """The best rows of the blocks seen so far. ``z``: queries, a row each; ``probes``: cell -> (places of its queries, ascending, their terms)."""

    def __init__(self, z: np.ndarray, probes: Probes, k: int):
        self.z, self.probes, self.k = z, probes, k
        self.size = np.sqrt((z * z).sum(axis=1))
        self.most = max((np.abs(ip).max(initial=0) for _, ip in probes.values()), default=0.0)
        self.bars: dict[int, np.ndarray] = {}
        self.held: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        # a query's first rows are those of the cell with its largest term
        top, at = np.full(len(z), -np.inf), np.full(len(z), -1)
        for cell, (who, ip) in probes.items():
            more = ip > top[who]
            top[who[more]], at[who[more]] = ip[more], cell
        self.top = at

    def add(self, ids: np.ndarray, cell: np.ndarray, group: np.ndarray, x: np.ndarray) -> None:
        by = np.lexsort((group, cell))
        self.ids, cell, group, self.x = ids[by], cell[by], group[by], x[by]
        large = float(np.sqrt((x * x).sum(axis=1)).max(initial=0))
        single = max(large, self.size.max(initial=0), self.most) < 1e15
        kind, eps = (np.float32, 2.0**-22) if single else (np.float64, 2.0**-50)
        self.slack = eps * ((x.shape[1] + 8) * large * self.size + 4 * self.most)
        self.fast, self.asked = self.x.astype(kind), self.z.astype(kind)
        for g in np.unique(group).tolist():
            self.bars.setdefault(g, np.full(len(self.z), -np.inf))
            self.held.setdefault(g, (np.zeros(0, np.int64), np.zeros(0, ids.dtype), np.zeros(0)))
        edge = np.flatnonzero(np.concatenate(([True], (np.diff(cell) != 0) | (np.diff(group) != 0), [True])))
        parts: dict[int, list[tuple[int, int, int]]] = {}
        for a, z in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            if int(cell[a]) in self.probes:
                parts.setdefault(int(cell[a]), []).append((int(group[a]), a, z))
        for own, part in parts.items():
            self._first_bars(own, part)
        n = len(self.z)
        step = QUERIES if len(parts) == 1 else max(n, 1)
        for a in range(0, n, step):
            self._scan(parts, a, min(n, a + step))

    def _first_bars(self, cell: int, part: list[tuple[int, int, int]]) -> None:
        who, ip = self.probes[cell]
        mine = np.flatnonzero(self.top[who] == cell)
        for g, a, z in part:
            z, bars = min(z, a + HEAD), self.bars[g]
            if z - a < self.k:
                continue
            new = mine[np.isneginf(bars[who[mine]])]
            for i in range(0, len(new), step := max(1, BLOCK // (z - a))):
                some = new[i : i + step]
                s = self.asked[who[some]] @ self.fast[a:z].T
                kth = np.partition(s, z - a - self.k, axis=1)[:, z - a - self.k]
                bars[who[some]] = np.where(np.isnan(kth), -np.inf, kth + ip[some] - 2 * self.slack[who[some]])

    def _scan(self, parts: dict[int, list[tuple[int, int, int]]], lo: int, hi: int) -> None:
        waiting: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}
        count = 0
        for cell, part in parts.items():
            who, ip = self.probes[cell]
            i, j = np.searchsorted(who, (lo, hi))
            who, ip = who[i:j], ip[i:j]
            if not len(who):
                continue
            asked = self.asked[lo:hi] if len(who) == hi - lo else self.asked[who]
            low = ip + self.slack[who]
            step = max(1, BLOCK // len(who))
            for a in range(part[0][1], part[-1][2], step):
                z = min(a + step, part[-1][2])
                s = asked @ self.fast[a:z].T
                for g, b, e in part:
                    b, e = max(a, b), min(e, z)
                    if b < e:
                        bar = (self.bars[g][who] - low).astype(s.dtype)
                        w, r = np.divmod(places(s[:, b - a : e - a] >= bar[:, None]), e - b)
                        if len(w):
                            waiting.setdefault(g, []).append((r + b, who[w], ip[w]))
                            count += len(w)
                if count > max(WAITING * (hi - lo), BLOCK >> 3):
                    self._settle(waiting)
                    waiting, count = {}, 0
        self._settle(waiting)

    def _settle(self, waiting: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]]) -> None:
        """Exact scores of the waiting pairs; k of a query stay, ties to the smaller id, and the last of them is its bar."""
        for g, found in waiting.items():
            rows, who, ip = map(np.concatenate, zip(*found, strict=True))
            score = np.empty(len(rows))
            for a in range(0, len(rows), 1 << 15):
                z = a + (1 << 15)
                score[a:z] = np.einsum("ij,ij->i", self.x[rows[a:z]], self.z[who[a:z]]) + ip[a:z]
            touched = np.zeros(len(self.z), bool)
            touched[who] = True
            old = self.held[g]
            moved = touched[old[0]]
            q, ids, s = (np.concatenate((x[moved], y)) for x, y in zip(old, (who, self.ids[rows], score), strict=True))
            by = ordered(ids, s, q)
            q, ids, s = q[by], ids[by], s[by]
            place = np.arange(len(q)) - np.searchsorted(q, q)
            last, keep = place == self.k - 1, place < self.k
            self.bars[g][q[last]] = np.maximum(self.bars[g][q[last]], s[last])
            self.held[g] = tuple(np.concatenate((x[~moved], y[keep])) for x, y in zip(old, (q, ids, s), strict=True))

    def found(self) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        """(group, ids, places of queries, scores)."""
        for g, (who, ids, score) in self.held.items():
            if len(who):
                yield g, ids, who, score


def search(batches: Iterable[pa.RecordBatch], read: Callable[[pa.RecordBatch], tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]], qid: np.ndarray, z: np.ndarray, probes: Probes, k: int) -> Iterator[pa.RecordBatch]:
    """(batch, qid, id, score) of a task's batches; ``read`` makes (ids, cells, groups, vectors) of one."""
    best, waiting, size = None, [], 0

    def flush() -> None:
        best.add(*map(np.concatenate, zip(*waiting, strict=True)))
        waiting.clear()

    for b in batches:
        if b.num_rows and len(qid):
            best = best or Best(z, probes, k)
            waiting.append(read(b))
            size += waiting[-1][3].nbytes
            if size > GATHERED:
                flush()
                size = 0
    if waiting:
        flush()
    for g, ids, who, score in best.found() if best else ():
        for a in range(0, len(ids), 1 << 18):
            some = slice(a, a + (1 << 18))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids[some]), g, np.int32)), pa.array(qid[who[some]]), pa.array(ids[some]), pa.array(score[some])], names=["batch", "qid", "id", "score"])


def everywhere(queries: int) -> Probes:
    """One cell that all queries probe, without a term of its own."""
    return {0: (np.arange(queries), np.zeros(queries))}

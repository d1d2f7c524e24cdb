"""Removal of repeated byte strings by a hash-compared suffix sort.

A text is its UTF-8 bytes; every byte under a string of ``LENGTH`` bytes that also starts elsewhere goes.
Candidates come to their bucket as packed runs (see ``repeats``). The kernel lays the distinct runs of its buckets end to end with prefix
polynomial hashes, from which the hash of any range is one subtraction and one product:

* places whose next LENGTH bytes have a hash of their own in the bucket are dropped; of the others only the left-maximal
  ones stay, those where the bytes in front of equal strings differ or a run begins;
* the suffixes at those places are sorted, class of equal LENGTH bytes by class, on the bytes behind those. Classes whose rests are long
  or many (a periodic text, say) are sorted by ranks instead: suffixes get ranks by their first bytes, then, round by round, by
  the ranks of their two halves, so a logarithm of the length is the number of rounds, and only suffixes that still tie take part;
* in suffix order the longest common extension of a suffix is with a neighbour; where it reaches LENGTH, its bytes are
  covered. Each such extension is verified byte by byte; after a collision the bucket is sorted on real bytes.

Defined cases: null and empty texts have no bytes; texts shorter than LENGTH lose none; matches never cross
documents; overlapping repeats inside a text count; copies are repeats of each other; cuts may fall inside a
character, so kept bytes are hashed as bytes.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from annspark.llm.repeats import BYTES, Powers, Units, merged, mixed, prefix, search

LENGTH, GRAM = 400, 160
#: Bytes of the sort keys of a class of equal windows, at most; a class whose keys take more is sorted by ranks.
KEYS = 32_000_000
#: Bytes of the sort keys of many small classes, and of the runs searched, at once. A searched byte takes some 80 bytes of memory.
AT_ONCE, SEARCHED = 4_000_000, 1_000_000


#: Bytes of a suffix that the first round of ranks looks at, and their number, in one key.
STEP = 7


def _firsts(x: np.ndarray) -> np.ndarray:
    """Place of the first equal value, for each of sorted values."""
    at = np.arange(len(x))
    return np.maximum.accumulate(np.where(np.concatenate(([True], x[1:] != x[:-1])), at, 0))


class Suffixes:
    """Suffixes of runs laid end to end."""

    def __init__(self, data: np.ndarray):
        self.data, self.s = data, prefix(BYTES[data])
        _, self.down = Powers.to(len(self.s))

    def hashes(self, p: np.ndarray, n) -> np.ndarray:
        return (self.s[p + n] - self.s[p]) * self.down[p]

    def common(self, p: np.ndarray, q: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Length of the common extension of places p and q, at most ``most``, by binary search."""
        lo, hi = np.zeros_like(most), most.copy()
        while (open_ := lo < hi).any():
            mid = (lo + hi + 1) >> 1
            same = self.hashes(p, mid) == self.hashes(q, mid)
            lo = np.where(open_ & same, mid, lo)
            hi = np.where(open_ & ~same, mid - 1, hi)
        return lo

    def sort(self, place: np.ndarray, end: np.ndarray, group: np.ndarray) -> np.ndarray:
        """Order of the suffixes [place, end) inside each group (groups stand together): all suffixes of their strings get ranks, by twice as many bytes a round."""
        stops, own = np.unique(end, return_inverse=True)
        begin = stops.copy()
        np.minimum.at(begin, own, place)
        # each string is laid out with a stop behind it, which ranks first
        size = stops - begin + 1
        off = np.cumsum(size) - size
        n, shift = int(size.sum()), begin - off
        left = np.repeat(off + size - 1, size) - np.arange(n)
        at = np.arange(n) + np.repeat(shift, size)
        key, last = np.zeros(n, np.int64), len(self.data) - 1
        for j in range(STEP):
            key = key << 8 | np.where(left > j, self.data[np.minimum(at + j, last)], 0)
        key = key << 4 | np.minimum(left, STEP + 1)  # shorter ones first; those that end here apart from longer ones
        del at
        by = np.argsort(key)
        rank = np.empty(n, np.int64)  # place of the first of its class
        rank[by] = _firsts(key[by])
        done = STEP
        # classes of one, and suffixes that ended, are in order
        open_ = by[left[by] > done]
        del key, by
        while True:
            r = rank[open_]
            many = np.bincount(r, minlength=1)[r] > 1
            open_, r = open_[many], r[many]
            if not len(open_):
                break
            key = r * n + rank[open_ + done]
            by = np.argsort(key)
            open_, r = open_[by], r[by]
            rank[open_] = r + _firsts(key[by]) - _firsts(r)
            done *= 2
            open_ = open_[left[open_] > done]
        return np.lexsort((rank[place - shift[own]], np.cumsum(np.concatenate(([False], group[1:] != group[:-1])))))

    def sort_rests(self, place: np.ndarray, end: np.ndarray, group: np.ndarray, skip: int) -> np.ndarray:
        """As ``sort``, for suffixes that share their first ``skip`` bytes in their group: on the bytes behind, shorter ones first."""
        n = len(place)
        order = np.arange(n)
        start = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
        stop = np.concatenate((start[1:], [n]))
        rest = end - place - skip
        wide = np.maximum.reduceat(rest, start)
        large = (wide + 4) * (stop - start) > KEYS
        # groups of like width stand together, so that no key is much longer than its own suffix
        by = np.flatnonzero(~large)[np.argsort(wide[~large], kind="stable")]
        longest = int(wide[by].max(initial=0))
        padded = np.concatenate((self.data, np.zeros(longest, np.uint8)))
        at = 0
        while at < len(by):
            total = np.cumsum(stop[by[at:]] - start[by[at:]]) * (wide[by[at:]] + 4)
            some = by[at : at + max(1, int(np.searchsorted(total, min(KEYS, AT_ONCE), side="right")))]
            count = stop[some] - start[some]
            to = np.repeat(start[some] - (np.cumsum(count) - count), count) + np.arange(count.sum())
            which, width = np.repeat(np.arange(len(some)), count), int(wide[some].max())
            short = np.argsort(rest[to], kind="stable")
            rows, which = to[short], which[short]
            keys = np.zeros((len(rows), 4 + width), np.uint8)
            keys[:, :4] = which.astype(">u4").view(np.uint8).reshape(-1, 4)
            if width:
                # rows of bytes are copied as such: an index for every byte would take many times the keys
                keys[:, 4:] = np.lib.stride_tricks.sliding_window_view(padded, width)[place[rows] + skip]
                keys[:, 4:] *= np.arange(width) < rest[rows][:, None]
            order[to] = rows[np.argsort(keys.reshape(-1).view(f"S{4 + width}"), kind="stable")]
            at += len(some)
        if large.any():
            rows = np.flatnonzero(np.repeat(large, stop - start))
            order[rows] = rows[self.sort(place[rows], end[rows], group[rows])]
        return order


@dataclass(frozen=True)
class Bytes(Units):
    result: str = "n_bytes long, n_removed long, n_spans long, kept_sha256 string"

    def units(self, text: bytes) -> np.ndarray:
        return BYTES[np.frombuffer(text, np.uint8)]

    def pack(self, text: bytes, first: np.ndarray, count: np.ndarray) -> list[bytes]:
        return [text[i : i + n + self.window - 1] for i, n in zip(first.tolist(), count.tolist(), strict=True)]

    def decide(self, bucket, packed):
        w = self.window
        kinds: dict[tuple[int, bytes], int] = {}
        which = [kinds.setdefault(k, len(kinds)) for k in zip(bucket.tolist(), packed, strict=True)]
        times = np.bincount(which, minlength=len(kinds))
        group = np.fromiter((k[0] for k in kinds), np.int64, len(kinds))
        strings = [k[1] for k in kinds]
        size = np.fromiter(map(len, strings), np.int64, len(kinds))
        spans: dict[int, list[tuple[int, int]]] = {k: [(0, int(size[k]))] for k in np.flatnonzero(times > 1).tolist()}
        # a bucket of one distinct run that stands more than once needs no search
        edge = np.concatenate(([True], group[1:] != group[:-1]))
        alone = np.bincount(np.cumsum(edge) - 1)[np.cumsum(edge) - 1] == 1
        todo = np.flatnonzero(~(alone & (times > 1)))
        at = 0
        while at < len(todo):  # whole buckets, about a megabyte at a time
            stop, room = at, 0
            while stop < len(todo) and (room < SEARCHED or group[todo[stop]] == group[todo[stop - 1]]):
                room += int(size[todo[stop]])
                stop += 1
            for k, lo, hi in self._search([strings[k] for k in todo[at:stop]], group[todo[at:stop]], w):
                spans.setdefault(int(todo[at + k]), []).append((lo, hi))
            at = stop
        for row, k in enumerate(which):
            for lo, hi in spans.get(k, ()):
                yield row, lo, hi

    @staticmethod
    def _search(strings: list[bytes], group: np.ndarray, w: int):
        """(string, lo, hi) covered in these distinct strings, by bucket."""
        data = np.frombuffer(b"".join(strings), np.uint8)
        size = np.fromiter(map(len, strings), np.int64, len(strings))
        begin = np.concatenate(([0], np.cumsum(size)[:-1]))
        text = Suffixes(data)
        n_win = size - w + 1
        owner = np.repeat(np.arange(len(strings)), n_win)
        place = np.arange(int(n_win.sum())) - np.repeat(np.cumsum(n_win) - n_win, n_win) + begin[owner]
        # equal hash in the same bucket: sort, then runs of equal keys
        key = text.hashes(place, w) ^ mixed(group.view(np.uint64))[owner]
        order = np.argsort(key)
        sorted_ = key[order]
        new = np.concatenate(([True], sorted_[1:] != sorted_[:-1]))
        run = np.flatnonzero(new)
        length = np.diff(np.concatenate((run, [len(key)])))
        front = np.where(place == begin[owner], -1, data[np.maximum(place - 1, 0)].astype(np.int16))[order]
        maximal = (length > 1) & ((np.minimum.reduceat(front, run) != np.maximum.reduceat(front, run)) | (front[run] < 0)) if len(run) else np.zeros(0, bool)
        head = order[np.repeat(maximal, length)]
        if not len(head):
            return
        p, own, kind = place[head], owner[head], np.repeat(np.flatnonzero(maximal), length[maximal])
        end, g = begin[own] + size[own], group[own]
        by = text.sort_rests(p, end, kind, w)
        p, own, end, g = p[by], own[by], end[by], g[by]
        n = len(p)
        near = np.zeros(n, np.int64)
        mate = np.full(n, -1)
        if n > 1:
            a, b = np.arange(n - 1), np.arange(1, n)
            most = np.where(kind[a] == kind[b], np.minimum(end[a] - p[a], end[b] - p[b]), 0)
            ext = text.common(p[a], p[b], most)
            near[a], mate[a] = ext, b
            up = ext > near[b]
            near[b[up]], mate[b[up]] = ext[up], a[up]
        raw = data.tobytes()
        hit = np.flatnonzero(near >= w)
        same = (raw[x : x + m] == raw[y : y + m] for x, y, m in zip(p[hit].tolist(), p[mate[hit]].tolist(), near[hit].tolist(), strict=True))
        wrong = set(g[hit[~np.fromiter(same, bool, len(hit))]].tolist())
        if wrong:
            hit = hit[~np.isin(g[hit], list(wrong))]
        # a place between strings, so that spans of neighbours are not joined
        apart = begin + np.arange(len(begin))
        spans = merged(np.stack((p[hit] + own[hit], p[hit] + own[hit] + near[hit]), axis=1))
        k = np.searchsorted(apart, spans[:, 0], side="right") - 1
        yield from zip(k.tolist(), (spans[:, 0] - apart[k]).tolist(), (spans[:, 1] - apart[k]).tolist(), strict=True)
        for gg in wrong:  # a hash collision: this bucket again on real bytes
            seen: dict[bytes, list[tuple[int, int]]] = {}
            for k in np.flatnonzero(group == gg).tolist():
                for lo in range(int(size[k]) - w + 1):
                    seen.setdefault(strings[k][lo : lo + w], []).append((k, lo))
            yield from ((k, lo, lo + w) for v in seen.values() if len(v) > 1 for k, lo in v)

    def finish(self, text: bytes, spans: np.ndarray) -> tuple:
        kept, at = hashlib.sha256(), 0
        for a, b in spans.tolist():
            kept.update(text[at:a])
            at = b
        kept.update(text[at:])
        return len(text), int((spans[:, 1] - spans[:, 0]).sum()), len(spans), kept.hexdigest()


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256)."""
    return search(docs, Bytes(length, gram))

"""Removal of repeated word windows by super-k-mer partitioning.

Words are maximal runs without ASCII white space. Consecutive windows of ``WINDOW`` words that share a minimiser (of
``GRAM`` words) travel as one packed string to the minimiser's bucket. There the windows are cut out of the
strings and sorted; equal neighbours are repeats, compared as text and so counted exactly. Every word under
a repeated window goes; windows are judged on the input.

Defined cases: null and empty texts have no words and keep nothing; a text of fewer words than a window keeps
all; copies of a text are repeats of each other; repeated rows count as copies; kept words are joined by one
space.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from annspark.llm.repeats import BYTES, Units, mixed, of_ranges, prefix, search

WINDOW, GRAM = 35, 10
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def word_ends(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words."""
    gap = np.concatenate(([True], _SPACE[np.frombuffer(text, np.uint8)], [True]))
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    return edge[::2], edge[1::2]


@dataclass(frozen=True)
class Words(Units):
    result: str = "n_words long, n_removed long, kept_sha256 string"

    def units(self, text: bytes) -> np.ndarray:
        a, b = word_ends(text)
        return mixed(of_ranges(prefix(BYTES[np.frombuffer(text, np.uint8)]), a, b)) if len(a) else np.zeros(0, np.uint64)

    def pack(self, text: bytes, first: np.ndarray, count: np.ndarray) -> list[bytes]:
        words = text.split()
        return [b" ".join(words[i : i + n + self.window - 1]) for i, n in zip(first.tolist(), count.tolist(), strict=True)]

    def decide(self, bucket, packed):
        w = self.window
        edge = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1], [True]))).tolist()
        for lo, hi in zip(edge[:-1], edge[1:], strict=True):
            times: dict[bytes, list[int]] = {}
            for i in range(lo, hi):
                times.setdefault(packed[i], []).append(i)
            if len(times) == 1 and hi - lo > 1:  # all alike
                n = packed[lo].count(b" ") + 1
                for i in range(lo, hi):
                    yield i, 0, n
                continue
            windows: list[tuple[bytes, int, int]] = []
            for run, rows in times.items():
                gap = [-1, *np.flatnonzero(np.frombuffer(run, np.uint8) == 32).tolist(), len(run)]
                windows += [(run[gap[j] + 1 : gap[j + w]], rows[0], j) for j in range(len(gap) - w)]
            windows.sort()
            hit: dict[int, list[int]] = {}
            for k in range(1, len(windows)):
                if windows[k][0] == windows[k - 1][0]:
                    for _, r, j in windows[k - 1 : k + 1]:
                        hit.setdefault(r, []).append(j)
            for run, rows in times.items():
                if len(rows) > 1:
                    spans = [(0, run.count(b" ") + 1)]
                else:
                    spans, at = [], sorted(set(hit.get(rows[0], ())))
                    for j in at:
                        if spans and j <= spans[-1][1]:
                            spans[-1] = (spans[-1][0], j + w)
                        else:
                            spans.append((j, j + w))
                for i in rows:
                    for a, b in spans:
                        yield i, a, b

    def finish(self, text: bytes, spans: np.ndarray) -> tuple:
        words = text.split()
        kept, at = [], 0
        for a, b in spans.tolist():
            kept += words[at:a]
            at = b
        kept += words[at:]
        return len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()


def remove_repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256)."""
    return search(docs, Words(window, gram))

"""Toxicity as severity grades: a cumulative-link (proportional odds) regression on sparse text features.

    P(grade > k | text) = sigmoid(w . x - cut[k]),   cut[0] < cut[1] < ...

One weight vector serves all thresholds; the expected severity is the sum of those probabilities. Features
are the distinct lower-cased letter words of the text and the four-letter stems of the longer ones, kept
where their shares in toxic and in other texts are ``APART`` standard errors apart, as exact strings (no hashing, so no strange word ever
shares a weight).

Training rows: at most ``SAMPLE`` labelled documents, toxic ones first, then by a seeded hash of the id, so
the bound is a parameter and the sample is the same on every run. The labels are binary; a toxic training
text gets grade 1, 2 or 3 by the tertile, among toxic texts, of its number of telling features.

Defined cases: null and empty texts have no features and get the severity of the bare cuts; a table with no
toxic label (or no labels at all) gives severity 0 and rejects nothing; repeated label rows of a document
count as toxic if one is; ties of the sample hash go by id.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.llm.common import restored, salted, shielded, sliced, texts

SAMPLE, FEATURES, GRADES, STEM, APART = 12_000, 20_000, 3, 4, 4.0
LETTERS = re.compile(r"[^\W\d_]+")


def features(text: str) -> set[str]:
    """Distinct words, and stems written with a trailing '*'."""
    words = set(LETTERS.findall(text.lower()))
    return words | {w[:STEM] + "*" for w in words if len(w) > STEM}


@dataclass
class Severity:
    """A fitted model; ``weight`` of a feature, and increasing ``cuts``."""

    weight: dict[str, float] = field(default_factory=dict)
    cuts: list[float] = field(default_factory=list)

    def above(self, score: float) -> list[float]:
        return [1 / (1 + math.exp(min(700.0, max(-700.0, c - score)))) for c in self.cuts]


def fit(rows: list[tuple[str, int]], grades: int = GRADES, limit: int = FEATURES, rounds: int = 400, l2: float = 1e-5) -> Severity:
    """rows: (text, toxic 0/1), in a fixed order."""
    number: dict[str, int] = {}
    bags = [np.sort(np.fromiter((number.setdefault(f, len(number)) for f in sorted(features(t))), np.int32)) for t, _ in rows]
    names = list(number)
    toxic = np.array([y for _, y in rows], bool)
    n1, n0 = int(toxic.sum()), int((~toxic).sum())
    if not n1 or not n0:
        return Severity()
    yes, no = (np.bincount(np.concatenate([b for b, y in zip(bags, toxic, strict=True) if y == side]), minlength=len(names)) for side in (True, False))
    odds = np.log((yes + 0.1) / (n1 + 0.2)) - np.log((no + 0.1) / (n0 + 0.2))
    share = (yes + no + 0.5) / (n1 + n0 + 1)
    z = (yes / n1 - no / n0) / np.sqrt(share * (1 - share) * (1 / n1 + 1 / n0))
    apart = np.flatnonzero((np.abs(z) >= APART) & (yes + no >= 3)).tolist()
    kept = sorted(apart, key=lambda f: (-abs(z[f]), names[f]))[:limit]
    place = np.full(len(names) + 1, -1)
    place[kept] = np.arange(len(kept))
    bags = [p[p >= 0] for p in (place[b] for b in bags)]
    telling = np.array([z[f] > 0 and odds[f] >= 2 for f in kept], bool)
    rate = np.array([telling[b].sum() for b in bags], float)
    edges = np.quantile(rate[toxic], [i / grades for i in range(1, grades)])
    grade = np.where(toxic, 1 + (rate[:, None] > edges).sum(axis=1), 0)
    col, own = np.concatenate(bags).astype(np.int64), np.repeat(np.arange(len(bags)), [len(b) for b in bags])
    w, m, v = np.zeros(len(kept)), np.zeros(len(kept)), np.zeros(len(kept))
    # cuts as a first one and log gaps, so that they stay in order
    c, cm, cv = np.array([2.0, *([0.0] * (grades - 1))]), np.zeros(grades), np.zeros(grades)
    n = len(rows)
    k = np.arange(n)
    for step in range(1, rounds + 1):
        cuts = c[0] + np.concatenate(([0.0], np.cumsum(np.exp(c[1:]))))
        s = np.bincount(own, w[col], n)
        # cdf at the cuts, with 0 and 1 at both ends: P(grade <= g) = sig(cut[g] - s)
        sig = 1 / (1 + np.exp(-np.clip(cuts[None, :] - s[:, None], -50, 50)))
        cdf = np.concatenate((np.zeros((n, 1)), sig, np.ones((n, 1))), axis=1)
        den = np.concatenate((np.zeros((n, 1)), sig * (1 - sig), np.zeros((n, 1))), axis=1)
        p = np.maximum(cdf[k, grade + 1] - cdf[k, grade], 1e-12)
        up, lo = den[k, grade + 1] / p, den[k, grade] / p
        gs = (up - lo) / n  # of the loss by s
        gw = np.bincount(col, gs[own], len(kept)) + l2 * w
        gcut = np.zeros(grades)
        for g in range(grades):
            gcut[g] = (-(up[grade == g].sum()) + lo[grade == g + 1].sum()) / n
        gc = np.concatenate(([gcut.sum()], [np.exp(c[j]) * gcut[j:].sum() for j in range(1, grades)]))
        for x, g, a, b in ((w, gw, m, v), (c, gc, cm, cv)):
            a += 0.1 * (g - a)
            b += 0.01 * (g * g - b)
            x -= 0.1 * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-8)
    cuts = c[0] + np.concatenate(([0.0], np.cumsum(np.exp(c[1:]))))
    return Severity({names[f]: round(float(w[i]), 6) for i, f in enumerate(kept)}, [round(float(x), 6) for x in cuts])


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, seed: str = "toxic-1") -> Severity:
    marks = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = salted(F.col("doc_id"), salt=seed)
    # toxic rows take at most half of the bound, others the rest; two bounded top-k selections
    chosen = marks.where("toxic = 1").orderBy(order, "doc_id").limit(sample // 2).unionByName(marks.where("toxic = 0").orderBy(order, "doc_id").limit(sample - sample // 2))
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "toxic").toLocalIterator()
    return fit([(r.text or "", int(r.toxic)) for r in sorted(rows, key=lambda r: (r.doc_id, r.text or ""))])


def grade(docs: DataFrame, model: Severity, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """keep columns, then (severity, grade, p_toxic, toxic): expected severity, likeliest grade, P(grade > 0), and whether that is over a half."""
    schema = docs.select(*keep).schema.add("severity", "double").add("grade", "integer").add("p_toxic", "double").add("toxic", "boolean")
    n = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight, solved = model.weight, {}
        for b in sliced(batches):
            sev, likely, first, flag = [], [], [], []
            for t in texts(b):
                words = set(LETTERS.findall(t.lower()))
                for w in words.difference(solved):
                    solved[w] = weight.get(w, 0.0)
                # a stem counts once however many words have it
                score = sum(sorted(map(solved.__getitem__, words))) + sum(sorted(weight.get(x, 0.0) for x in {w[:STEM] + "*" for w in words if len(w) > STEM}))
                above = model.above(score)
                p = [1.0, *above, 0.0]
                sev.append(round(sum(above), 9))
                likely.append(max(range(len(p) - 1), key=lambda g: p[g] - p[g + 1]))
                first.append(round(above[0], 9) if above else 0.0)
                flag.append(bool(above) and above[0] > 0.5)
            if len(solved) > 200_000:
                solved.clear()
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(n)), pa.array(sev, pa.float64()), pa.array(likely, pa.int32()), pa.array(first, pa.float64()), pa.array(flag, pa.bool_())], names=schema.names)

    cols = [*keep] + ([] if "text" in keep else ["text"])
    return docs.select(*cols).mapInArrow(run, schema)


def keep_clean(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The rows of docs that are not toxic, with all their columns."""
    safe, names = shielded(docs, ("doc_id", "text"))
    marked = grade(safe, train(safe, labels, **options), keep=tuple(names))
    return restored(marked.where(~F.col("toxic")), names, docs.columns)

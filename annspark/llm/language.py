"""Language identification by hyperdimensional profiles.

Every letter has a seeded random vector of +1 and -1. A letter n-gram is bound into one vector by
multiplying its letters' vectors, each rolled by its place in the n-gram; a document is the bundle (sum) of
its n-grams' vectors; a language's prototype is the bundle of its training documents' unit vectors. The
prediction is the prototype of the highest cosine.

Letters outside the table's direct range share slots by code point, so that any script can be learned.
Runs of non-letters are one gap symbol, which marks word edges.

Defined cases: a null text, or one without a letter, is ``und`` with score 0; no training row at all makes
every text ``und``; ties go to the earlier language by code point; repeated rows count each time.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from annspark.llm.common import texts

DIM, GRAM, SLOTS, SEED = 512, 3, 128, 20_117
#: Profiles are summed as integers of this unit, so that sums do not depend on the order of rows.
UNIT = 1 << 20


def _slot_table() -> np.ndarray:
    """Code points below 0x250 to slots: 0 for non-letters; ASCII letters and Latin supplements of their own."""
    out = np.zeros(0x250, np.int64)
    k = 1
    for cp in range(0x250):
        ch = chr(cp)
        if ch.isalpha() and ch == ch.lower():
            out[cp] = 1 + (k - 1) % (SLOTS - 1)
            k += 1
    return out


class Profiler:
    """Turns texts into hypervectors; one per task."""

    def __init__(self, dim: int = DIM, gram: int = GRAM, seed: int = SEED):
        rng = np.random.default_rng(seed)
        letters = rng.integers(0, 2, (SLOTS, dim)).astype(np.int8) * 2 - 1
        self.rolled = [np.roll(letters, gram - 1 - j, axis=1) for j in range(gram)]
        self.table, self.gram, self.dim = _slot_table(), gram, dim

    def slots(self, text: str) -> np.ndarray:
        cps = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        out = np.zeros(len(cps), np.int64)
        low = cps < 0x250
        out[low] = self.table[cps[low]]
        if not low.all():
            for i in np.flatnonzero(~low):
                if chr(cps[i]).isalpha():
                    out[i] = 1 + cps[i] % (SLOTS - 1)
        if not out.any():
            return out[:0]
        out = np.concatenate(([0], out, [0]))
        keep = np.ones(len(out), bool)
        keep[1:] = (out[1:] != 0) | (out[:-1] != 0)
        return out[keep]

    def vector(self, text: str) -> np.ndarray | None:
        """The bundle of the text's n-grams, or None without a letter."""
        s = self.slots(text)
        if not len(s):
            return None
        n = len(s) - self.gram + 1
        code = np.zeros(n, np.int64)
        for j in range(self.gram):
            code = code * SLOTS + s[j : j + n]
        grams, count = np.unique(code, return_counts=True)
        out = np.zeros(self.dim, np.float64)
        for at in range(0, len(grams), 4096):
            g = grams[at : at + 4096]
            bound = self.rolled[-1][g % SLOTS]
            for j in range(self.gram - 2, -1, -1):
                g = g // SLOTS
                bound = bound * self.rolled[j][g % SLOTS]
            out += count[at : at + 4096].astype(np.float32) @ bound.astype(np.float32)
        return out

    def unit(self, text: str) -> np.ndarray | None:
        v = self.vector(text)
        if v is None or not (n := float(np.sqrt(v @ v))):
            return None
        return v / n


def held_out(doc_id: Column) -> Column:
    """crc32 of the id's decimal text leaves 1 by 3; a null id is not held out."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string")), F.lit(3)) == 1, F.lit(False))


def train(rows: DataFrame, dim: int = DIM) -> pd.DataFrame:
    """(lang, n, profile) from (text, lang), rows of null lang left out: sums per task, then per language."""

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, sums, n = Profiler(dim), {}, {}
        for b in batches:
            for text, lang in zip(texts(b), b.column("lang").to_pylist(), strict=True):
                if (u := p.unit(text)) is not None:
                    sums[lang] = sums.get(lang, 0) + np.rint(u * UNIT).astype(np.int64)
                    n[lang] = n.get(lang, 0) + 1
        if sums:
            k = list(sums)
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array([n[x] for x in k], pa.int64()), pa.array([sums[x].tolist() for x in k], pa.list_(pa.int64()))], ["lang", "n", "v"])

    parts = rows.where(F.col("lang").isNotNull()).select("text", "lang").mapInArrow(part, "lang string, n long, v array<bigint>")
    cells = parts.select("lang", "n", F.posexplode("v").alias("j", "x")).groupBy("lang", "j").agg(F.sum("x").alias("x"), F.sum("n").alias("n"))
    # languages x dim numbers
    got = cells.groupBy("lang").agg(F.first("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda z: z["x"]).alias("profile"))
    return pd.DataFrame([r.asDict() for r in got.orderBy("lang").collect()], columns=["lang", "n", "profile"])


def predict(docs: DataFrame, model: pd.DataFrame, dim: int = DIM, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """carry columns, then (lang_pred, score), from text alone."""
    langs = sorted(model["lang"].tolist())
    at = {r.lang: np.asarray(r.profile, np.float64) for r in model.itertuples()}
    protos = np.array([at[x] / max(np.linalg.norm(at[x]), 1e-12) for x in langs]) if langs else np.zeros((0, dim))
    schema = docs.select(*carry).schema.add("lang_pred", "string").add("score", "double")
    n = len(carry)

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = Profiler(dim)
        for b in batches:
            pred, score = [], []
            for text in texts(b):
                u = p.unit(text) if langs else None
                if u is None:
                    pred.append("und")
                    score.append(0.0)
                    continue
                cos = protos @ u
                k = int(cos.argmax())
                pred.append(langs[k])
                score.append(float(min(1.0, max(0.0, cos[k]))))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(n)), pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=[*carry, "lang_pred", "score"])

    return docs.select(*carry, "text").mapInArrow(label, schema)

"""Random-projection hashing by Spark ML, as the platform's own baseline."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.functions.vectors import matrix
from annspark.operators.exact import best_rows, collected, top_rows, united


def search(base: DataFrame, queries: DataFrame, k: int = 10, tables: int = 8, width: float = 0.8, reach: float = 1.4, seed: int = 42) -> DataFrame:
    """(qid, rank, id, score): candidates share a bucket and lie within ``reach``; score is the inner product of unit vectors.

    The model hashes both sides; a wave of queries travels to every task and k rows a query leave it. The model's own join would send each
    row once a table and each candidate pair with both its vectors through the shuffle.
    """
    b, q = (df.select(key, F.col(col).alias("v"), array_to_vector(col).alias("x")) for df, key, col in ((base, "id", "v"), (queries, "qid", "qv")))
    model = BucketedRandomProjectionLSH(inputCol="x", outputCol="h", numHashTables=tables, bucketLength=width, seed=seed).fit(b)

    def hashed(df: DataFrame, key: str, col: str) -> DataFrame:
        return model.transform(df).select(key, F.concat("v", F.array(*(vector_to_array(F.col("h")[i])[0] for i in range(tables)))).alias(col))

    rows = hashed(b, "id", "v")
    found = united(_near(rows, qid, both[:, :-tables], both[:, -tables:], k, reach) for qid, both in collected(hashed(q, "qid", "qv")))
    return top_rows(found, k).select("qid", "rank", "id", "score")


def _near(rows: DataFrame, qid: np.ndarray, q: np.ndarray, qh: np.ndarray, k: int, reach: float) -> DataFrame:
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = (q * q).sum(axis=1)
        for b in batches:
            if not b.num_rows or not len(qid):
                continue
            ids, both = b.column(0).to_numpy(), matrix(b.column(1))
            x, h = both[:, : q.shape[1]], both[:, q.shape[1] :]
            step = max(1, 4_000_000 // len(ids))
            for a in range(0, len(qid), step):
                square = (x * x).sum(axis=1)[:, None] + own[a : a + step] - 2 * (x @ q[a : a + step].T)
                near = np.zeros(square.shape, bool)
                for j in range(h.shape[1]):
                    near |= h[:, j][:, None] == qh[a : a + step, j]
                s = np.where(near & (square < reach * reach), 1 - square / 2, -np.inf)
                at, who = best_rows(s, ids, k)
                some = np.isfinite(s[at, who])
                at, who = at[some], who[some]
                yield pa.RecordBatch.from_arrays([pa.array(qid[a + who]), pa.array(ids[at]), pa.array(s[at, who])], names=["qid", "id", "score"])

    return rows.mapInArrow(scan, "qid long, id long, score double")

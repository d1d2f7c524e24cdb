"""Vector sets derived from the given tables by pure functions of (table, parameters, seed); schema (id LONG, v ARRAY<DOUBLE>).

E: embeddings. A(alpha): embeddings drawn to the vector of the least id of their label. D(d), P(d): hashed words of documents and pages.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from annspark.functions import rotation
from annspark.functions.vectors import add, as_lists, doubles, is_bad, matrix, scale, unit


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), doubles("embedding").alias("v"))
    return t.where(~is_bad("v")).withColumn("v", unit("v"))


def anchored(spark: SparkSession, sf_dir: str, alpha: float = 2.5) -> DataFrame:
    t = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "label", doubles("embedding").alias("v"))
    anchors = t.groupBy("label").agg(F.min_by("v", "id").alias("a"))
    return t.join(F.broadcast(anchors), "label").select("id", unit(add(scale("a", alpha), "v")).alias("v"))


def hashed_slots(texts: DataFrame, d: int, salt: str = "") -> DataFrame:
    """(id, slot, x): signed word counts of (id, whole text); slot and sign come from the first eight hex digits of the word's MD5."""
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")
    h = F.conv(F.substring(F.md5(F.concat(F.lit(salt), F.col("w")).cast("binary")), 1, 8), 16, 10).cast("long")
    sign = F.when(F.shiftright("h", 20).bitwiseAND(F.lit(1)) == 1, 1).otherwise(-1)
    each = texts.select("id", F.explode(words).alias("w")).select("id", h.alias("h"))
    return each.groupBy("id", (F.col("h") % d).cast("int").alias("slot")).agg(F.sum(sign).alias("x")).where("x <> 0")


#: Bytes of UTF-8 as lower-case ASCII letters; all others end a word.
LETTERS = bytes(b | 32 if chr(b).isascii() and chr(b).isalpha() else 32 for b in range(256))


def lower_words(text: bytes) -> list[bytes]:
    """Runs of a to z in the lower-case text; two other characters have such letters there: the dotted capital I and the Kelvin sign."""
    return text.replace(b"\xc4\xb0", b"i ").replace(b"\xe2\x84\xaa", b"k").translate(LETTERS).split()


def hashed(texts: DataFrame, d: int, salt: str = "") -> DataFrame:
    """Unit vectors of hashed words; texts whose slots are all zero are left out."""
    kind = texts.schema["id"].dataType.simpleString()

    class Slots(dict):
        """Slot and sign of a word, as one number; a word is hashed once a task."""

        def __missing__(self, word: bytes) -> int:
            h = int(hashlib.md5(salt.encode() + word).hexdigest()[:8], 16)
            self[word] = out = 2 * (h % d) + (h >> 20 & 1)
            return out

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot = Slots()
        for b in batches:
            for at in range(0, b.num_rows, 1_000):
                part = b.slice(at, 1_000)
                counts = np.zeros((part.num_rows, 2 * d), np.int32)
                for i, text in enumerate(part.column(1).cast(pa.binary()).to_pylist()):
                    words = lower_words(text) if text else ()
                    if words:
                        counts[i] = np.bincount(np.fromiter(map(slot.__getitem__, words), np.int64, len(words)), minlength=2 * d)
                if len(slot) > 1_000_000:
                    slot.clear()
                yield pa.RecordBatch.from_arrays([part.column(0), as_lists(counts[:, 1::2] - counts[:, ::2], pa.int32())], names=["id", "m"])

    each = texts.select("id", "text").mapInArrow(go, f"id {kind}, m array<int>")
    # rows of one id are one text
    whole = F.when(F.size("m") == 1, doubles(F.col("m")[0])).otherwise(F.aggregate(F.slice("m", 2, F.size("m")), doubles(F.col("m")[0]), lambda s, x: F.zip_with(s, x, lambda y, z: y + z)))
    return each.groupBy("id").agg(F.collect_list("m").alias("m")).select("id", whole.alias("m")).where(F.exists("m", lambda x: x != 0)).select("id", unit("m").alias("v"))


def documents(spark: SparkSession, sf_dir: str, d: int = 96, salt: str = "") -> DataFrame:
    return hashed(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), d, salt)


def page_text(html: str = "html"):
    """Text of a page: tags become spaces."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.col(html), "<[^>]*>", " "), r"\s+", " "))


def pages(spark: SparkSession, sf_dir: str, d: int = 96) -> DataFrame:
    return hashed(table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), page_text().alias("text")), d)


def rotated(df: DataFrame, d: int, seed: int = 99, cosine: float = 0.0, col: str = "v") -> DataFrame:
    """normalise(c x + sqrt(1 - c^2) R x) with a second fixed rotation R; c = 0 is the rotation itself."""
    turn, rest = rotation.dense(d, seed), math.sqrt(1 - cosine * cosine)
    key = df.columns[0]

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(1))
                y = cosine * x + rest * (x @ turn.T)
                y /= (y * y).sum(axis=1, keepdims=True) ** 0.5
                yield pa.RecordBatch.from_arrays([b.column(0), as_lists(y)], names=[key, col])

    return df.select(key, col).mapInArrow(go, f"{key} long, {col} array<double>")


def split(df: DataFrame, every: int = 10) -> tuple[DataFrame, DataFrame]:
    """(base, queries): ids divisible by ten ask, as (qid, qv)."""
    return df.where(F.col("id") % every != 0), df.where(F.col("id") % every == 0).select(F.col("id").alias("qid"), F.col("v").alias("qv"))


def batches(df: DataFrame, first: float, n: int, order: str = "id", seed: int = 42, lang: DataFrame | None = None) -> DataFrame:
    """df with a batch number: 0 is the first share, then n equal ones; order 'id', 'shuffled', or 'drift' (by the language table (id, lang))."""
    ids = df.select("id")
    if order == "drift":
        ids = ids.join(lang, "id").select("id", F.struct("lang", "id").alias("o"))
    elif order == "shuffled":
        ids = ids.select("id", F.struct(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string")).cast("binary")), "id").alias("o"))
    else:
        ids = ids.select("id", F.struct("id").alias("o"))
    total = ids.count()
    head = int(total * first)
    # ids alone, in one ordered window: an experiment's protocol, not a step of the index
    r = F.row_number().over(Window.orderBy("o")) - 1
    step = (total - head) / n
    number = ids.select("id", F.when(r < head, 0).otherwise(F.least(F.lit(n), F.floor((r - head) / step).cast("int") + 1)).alias("batch"))
    return df.join(number, "id")

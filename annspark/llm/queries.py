"""The thin queries over the operators of this subpackage, and their SQL where SQL can say the same."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.llm import bpe, bytespans, jaccard, language, mixing, ordersketch, permutation, pii, toxicity, wordspans
from annspark.llm.common import table


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.train(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    return toxicity.grade(docs, model)


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bytespans.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op3_permutation_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return permutation.nearest(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), F.col("vec_id") % 20 == 0, k=20)


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    return bpe.encode(table(spark, sf_dir, "documents").select("doc_id", "text"), path, public_tokenizers.PATTERN, ids=False)


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op6_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents").select("doc_id", "text", "source")).select("doc_id", "size", "source_size", "target", "taken")


def op7_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op8_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ordersketch.neighbours(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_superkmer_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wordspans.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = language.train(docs.where(~language.held_out(F.col("doc_id"))))
    out = language.predict(docs.select("doc_id", "text"), model)
    return out.select("doc_id", language.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


QUERIES = {f.__name__: f for f in (op1_toxicity, op2_suffix_dedup, op3_permutation_index, op4_byte_bpe, op5_pii, op6_source_mixing, op7_ngram_jaccard, op8_order_minhash, op9_superkmer_dedup, op10_language_id)}

_WORDS_SQL = r"w AS MATERIALIZED (SELECT doc_id, text, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents)"

#: The two operators that SQL can say from scratch, for tables of unique doc_ids: similarity join (with classes by recursion) and
#: repeated word windows. Vectors have an approximate contract, the others leave SQL (hashes over spans, models, seeded order, merges).
ORACLE_SQL: dict[str, str] = {
    "op7_ngram_jaccard": f"""
WITH RECURSIVE {_WORDS_SQL},
g AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(2, len(w) - 3))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM g a JOIN g b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT x, y FROM c JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE c / (p.n + q.n - c)::DOUBLE >= 0.8),
e AS MATERIALIZED (SELECT x, y FROM l UNION SELECT a.doc_id, b.doc_id FROM w a JOIN w b ON coalesce(a.text, '') = coalesce(b.text, '') AND a.doc_id <> b.doc_id),
r(a, b) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.a, e.y FROM r JOIN e ON r.b = e.x)
SELECT a AS doc_id, min(b) AS class_id, coalesce(any_value(k), 0) AS n_links FROM r LEFT JOIN (SELECT x, count(*) AS k FROM l GROUP BY x) ON x = a GROUP BY a""",
    "op9_superkmer_dedup": f"""
WITH {_WORDS_SQL},
win AS MATERIALIZED (SELECT doc_id, i, array_to_string(w[i:i + 34], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM w WHERE len(w) >= 35)),
dup AS (SELECT s FROM win GROUP BY s HAVING count(*) > 1),
gone AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS p FROM win WHERE s IN (SELECT s FROM dup)),
each AS (SELECT doc_id, unnest(w) AS x, unnest(range(1, len(w) + 1)) AS p FROM w),
kept AS (SELECT doc_id, count(*) AS k, string_agg(x, ' ' ORDER BY p) AS t FROM each ANTI JOIN gone USING (doc_id, p) GROUP BY doc_id)
SELECT w.doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(k, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM w LEFT JOIN kept USING (doc_id)""",
}

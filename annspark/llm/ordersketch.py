"""Document fingerprints by order MinHash, in DataFrame functions alone.

The k-mers of a document are its runs of ``K`` words. Each gets its occurrence number within the document,
and the hash of (k-mer, number) orders them. The hash range is cut in ``PARTS`` equal parts; part j selects
the first ``PICK`` numbered k-mers at or after its lower end, going round; these are put back in text order and their
tuple is hashed into component j. Two documents agree in a component if they share the selected k-mers *in
the same order*, so that the share of equal components follows edit distance and not just the set of k-mers.

All work is on arrays within a row: a sorted array of packed longs (hash in the high bits, position in the
low ones) gives runs of equal k-mers, hence the occurrence numbers, and a second sort gives the selection. Nothing is
exploded, so there is no shuffle of k-mers and memory is bounded by one document.

Defined cases: null text is the empty text; a text without words has the fingerprint of all-empty
components; texts of fewer than K words have one k-mer, all their words; equal texts have equal fingerprints; texts of
up to 2^24 words keep exact positions (longer ones wrap in the packed low bits, which can alter ties only).

``neighbours`` pairs every row with the next document by descending doc_id, the last with the first: ids are cut into
ranges by their approximate quantiles, each range finds its successors alone, and the ends of the
ranges, a row a range, are stitched. Of repeated doc_ids the text of the smallest MD5 is the one that is next to
others; every row is returned. A null doc_id sorts last.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from annspark.llm.common import cut, shuffle_parts

K, PICK, PARTS = 3, 2, 32
_LOW = (1 << 24) - 1
_NONE = -(1 << 63)


def fingerprint_columns(df: DataFrame, text: str, out: str, k: int = K, parts: int = PARTS) -> DataFrame:
    """df with array<int> column ``out``, the components of the text column's fingerprint.

    Steps are projected one by one, and each array is named at least twice in the step after its own: the
    optimizer then keeps the steps apart and makes each array once, not once for each element that looks at it.
    """
    keep = [F.col(c) for c in df.columns]
    words = F.array_remove(F.split(F.coalesce(F.col(text), F.lit("")), r"[\x20\x09-\x0D]+"), "")
    d = df.select(*keep, words.alias("_w"))
    hashed = F.transform("_w", lambda w: F.xxhash64(w))
    d = d.select(*keep, hashed.alias("_h"), F.size("_w").alias("_n"))
    # (hash of the k-mer's words << 24) | position; no array below may hold nulls, by type: longs are then sorted as such, not as objects
    none = F.array_repeat(F.lit(0).cast("long"), 0)
    grams = F.when(
        F.col("_n") >= k,
        F.transform(
            F.slice("_h", 1, F.greatest(F.col("_n") - (k - 1), F.lit(0))),
            lambda h, i: F.shiftleft(F.xxhash64(h, *(F.get(F.col("_h"), i + j) for j in range(1, k))), 24).bitwiseOR(i.cast("long").bitwiseAND(F.lit(_LOW))),
        ),
    ).when(F.col("_n") > 0, F.array(F.shiftleft(F.xxhash64(F.col("_h")), 24))).otherwise(none)
    d = d.select(*keep, F.sort_array(grams).alias("_s"))

    def changes(array: str, of) -> Column:
        """Places of a sorted array where ``of`` differs from the element before, the first included."""
        at = lambda i: of(F.get(F.col(array), i))
        some = F.filter(F.sequence(F.lit(0), F.size(array) - 1), lambda i: (i == 0) | (at(i) != at(i - 1)))
        return F.when(F.size(array) > 0, some).otherwise(F.array_repeat(F.lit(0), 0))

    d = d.select(*keep, "_s", changes("_s", lambda x: F.shiftright(x, 24)).alias("_b"))
    # occurrence numbers, run by run, side by side with _s
    numbers = F.flatten(F.transform("_b", lambda b, j: F.sequence(F.lit(0), F.coalesce(F.get(F.col("_b"), j + 1), F.size("_s")) - b - 1)))
    d = d.select(*keep, "_s", F.when(F.size("_b") == F.size("_s"), F.lit(None)).otherwise(numbers).alias("_o"))
    rank = lambda x, o: F.shiftleft(F.xxhash64(F.shiftright(x, 24), o), 24).bitwiseOR(x.bitwiseAND(F.lit(_LOW)))
    ranked = F.when(F.col("_o").isNull(), F.transform("_s", lambda x: rank(x, F.lit(0)))).otherwise(F.transform("_s", lambda x, i: rank(x, F.get(F.col("_o"), i))))
    d = d.select(*keep, F.sort_array(ranked).alias("_e"))
    # part of an element: its top bits, as 0 .. parts - 1
    bits = parts.bit_length() - 1
    part = lambda x: F.shiftright(x, 64 - bits).cast("int") + parts // 2
    d = d.select(*keep, "_e", changes("_e", part).alias("_f"))
    # the place each part starts from: its own first element, or that of the next part that has one; going round, the first of all
    own = F.transform("_f", lambda f: part(F.get(F.col("_e"), f)))
    d = d.select(*keep, "_e", "_f", own.alias("_p"))
    starts = F.flatten(F.transform("_f", lambda f, i: F.array_repeat(f, F.get(F.col("_p"), i) - F.coalesce(F.get(F.col("_p"), i - 1), F.lit(-1)))))
    round_ = F.array_repeat(F.lit(0), parts - 1 - F.element_at("_p", -1))
    d = d.select(*keep, "_e", F.when(F.size("_p") > 0, F.concat(starts, round_)).otherwise(F.array_repeat(F.lit(0), 0)).alias("_i"))

    def component(i: Column, j: Column) -> Column:
        a, b = F.get(F.col("_e"), i), F.get(F.col("_e"), F.pmod(i + 1, F.size("_e")))
        swap = a.bitwiseAND(F.lit(_LOW)) > b.bitwiseAND(F.lit(_LOW))
        x, y = F.shiftright(F.when(swap, b).otherwise(a), 24), F.shiftright(F.when(swap, a).otherwise(b), 24)
        return F.hash(j, x, y)

    comps = F.when(F.size("_i") == 0, F.array_repeat(F.lit(0), parts)).otherwise(F.transform("_i", component))
    return d.select(*keep, comps.alias(out))


def likeness(a: Column, b: Column) -> Column:
    """Share of equal components."""
    return F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda z: z)) / F.size(a).cast("double")


def printed(a: Column) -> Column:
    return F.concat_ws("", F.transform(a, lambda x: F.lpad(F.lower(F.hex(x.cast("long").bitwiseAND(F.lit(0xFFFFFFFF)))), 8, "0")))


def next_ids(ids: DataFrame) -> DataFrame:
    """(id, next_id) for distinct non-null longs: the next smaller one, and the largest for the smallest."""
    parts = min(512, max(2, shuffle_parts(ids)))
    bounds = ids.agg(F.percentile_approx("id", [i / parts for i in range(1, parts)], 10_000)).first()[0] or []
    edges = sorted(set(bounds))
    bucket = F.size(F.filter(F.array(*map(F.lit, edges)), lambda e: e <= F.col("id"))) if edges else F.lit(0)
    placed = ids.withColumn("bucket", bucket)
    heads = placed.groupBy("bucket").agg(F.max("id").alias("head"))
    # a row a range: the successor of a range's end is the head of the range below it; below the lowest comes the highest
    w = Window.partitionBy(F.lit(1)).orderBy(F.desc("bucket"))
    below = heads.select(F.col("bucket").alias("b"), F.coalesce(F.lead("head").over(w), F.first("head").over(w.rowsBetween(Window.unboundedPreceding, 0))).alias("below"))
    inner = F.lead("id").over(Window.partitionBy("bucket").orderBy(F.desc("id")))
    return placed.withColumn("inner", inner).join(F.broadcast(below), F.col("bucket") == F.col("b")).select("id", F.coalesce("inner", "below").alias("next_id"))


def neighbours(docs: DataFrame) -> DataFrame:
    """(doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next) per row of (doc_id, text)."""
    # the same three columns are all that either side of the joins below reads, so one exchange serves both
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_NONE)).alias("key"), F.coalesce("text", F.lit("")).alias("text"))
    lengths = cut(rows.select("key", F.length("text").alias("n")))  # small rows; read twice
    pairs = next_ids(lengths.select(F.col("key").alias("id")).distinct())
    # how many code points each document lends to those before it
    asked = lengths.groupBy("key").agg(F.max(F.floor(F.col("n") / 3)).alias("third"))
    lends = cut(pairs.join(asked, pairs["id"] == asked["key"]).select("id", "next_id", "third"))
    printed_rows = fingerprint_columns(rows, "text", "fp")
    # only what is lent travels on, not the whole text
    lenders = (
        printed_rows.join(lends.select(F.col("id").alias("asks"), F.col("next_id"), "third"), F.col("key") == F.col("next_id"))
        .select("asks", F.expr("substring(text, 1, int(third))").alias("lent"), F.col("fp").alias("next_fp"), F.md5(F.col("text").cast("binary")).alias("_m"))
        .withColumn("_r", F.row_number().over(Window.partitionBy("asks").orderBy("_m")))
        .where("_r = 1")
        .drop("_m", "_r")
    )
    both = printed_rows.join(lenders, printed_rows["key"] == lenders["asks"])
    n = F.length("text")
    third = F.floor(n / 3).cast("int")
    edited = both.select(F.nullif(F.col("key"), F.lit(_NONE)).alias("doc_id"), n.cast("long").alias("n_chars"), "fp", "next_fp", F.concat(F.substring("text", F.lit(1), n - third), F.substring("lent", F.lit(1), third)).alias("edited"))
    out = fingerprint_columns(edited, "edited", "efp")
    return out.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        printed(F.col("fp")).alias("fingerprint"),
        printed(F.col("efp")).alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("efp")).alias("near_edited"),
        likeness(F.col("fp"), F.col("next_fp")).alias("near_next"),
    )

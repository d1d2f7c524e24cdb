"""Operators, functions, sources and sinks around the index: each a small DataFrame plan with the SQL that says the same."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from annspark.functions import vectors as vx
from annspark.operators import exact
from annspark.sources import datasets as ds

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def register(f):
        QUERIES[name or f.__name__] = f
        if sql is not None:
            SQL[name or f.__name__] = sql
        return f

    return register


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ds.table(spark, sf_dir, name)


def scratch(spark: SparkSession, name: str) -> str:
    """A folder for round trips: beside the checkpoints where the session names a shared folder, else temporary."""
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="annspark-")
    return f"{base}/{name}-{spark.sparkContext.applicationId}"


# ------------------------------------------------------------------ scans, sources, sinks


@query("SELECT count(*) AS n, sum(l_quantity) AS qty FROM lineitem")
def scan_parquet(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"))


@query("SELECT l_orderkey, l_linenumber::BIGINT AS l_linenumber, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-06-01' AND l_quantity > 45")
def scan_pruned(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").where((F.col("l_shipdate") >= F.lit("1998-06-01").cast("timestamp")) & (F.col("l_quantity") > 45)).select("l_orderkey", F.col("l_linenumber").cast("long").alias("l_linenumber"), "l_quantity")


def _round_trip(fmt: str):
    def run(spark, sf_dir):
        src = t(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_acctbal", "c_mktsegment")
        path = scratch(spark, f"trip-{fmt}")
        src.write.mode("overwrite").format(fmt).option("header", True).save(path)
        return spark.read.schema(src.schema).option("header", True).format(fmt).load(path).select("c_custkey", "c_name", F.round("c_acctbal", 2).alias("c_acctbal"), "c_mktsegment")

    return run


for _fmt in ("csv", "json", "orc", "parquet"):
    query("SELECT c_custkey, c_name, round(c_acctbal, 2) AS c_acctbal, c_mktsegment FROM customer", f"io_roundtrip_{_fmt}")(_round_trip(_fmt))


@query("SELECT event_id, event_type || ':' || user_id AS line FROM events")
def io_roundtrip_text(spark, sf_dir):
    path = scratch(spark, "trip-text")
    t(spark, sf_dir, "events").select(F.concat_ws("|", "event_id", F.concat_ws(":", "event_type", "user_id")).alias("value")).write.mode("overwrite").text(path)
    return spark.read.text(path).select(F.split("value", r"\|")[0].cast("long").alias("event_id"), F.split("value", r"\|")[1].alias("line"))


# ------------------------------------------------------------------ projections, vectors


@query("SELECT l_orderkey, l_linenumber::BIGINT AS l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem WHERE l_discount BETWEEN 0.05 AND 0.07 AND l_returnflag = 'R'")
def filter_project(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").where(F.col("l_discount").between(0.05, 0.07) & (F.col("l_returnflag") == "R")).select("l_orderkey", F.col("l_linenumber").cast("long").alias("l_linenumber"), F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("SELECT CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 30 THEN 'middle' ELSE 'large' END AS bucket, count(*) AS n, count(*) FILTER (coalesce(nullif(l_tax, 0), -1) < 0) AS untaxed FROM lineitem GROUP BY 1")
def case_bucket(spark, sf_dir):
    b = F.when(F.col("l_quantity") < 10, "small").when(F.col("l_quantity") < 30, "middle").otherwise("large")
    return t(spark, sf_dir, "lineitem").groupBy(b.alias("bucket")).agg(F.count("*").alias("n"), F.count_if(F.coalesce(F.nullif("l_tax", F.lit(0.0)), F.lit(-1.0)) < 0).alias("untaxed"))


_PAIR = "(SELECT a.vec_id AS id, list_transform(a.embedding, lambda x: x::DOUBLE) AS a, list_transform(b.embedding, lambda x: x::DOUBLE) AS b FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1)"


def _pairs(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), vx.doubles("embedding").alias("a"))
    return e.join(e.select((F.col("id") - 1).alias("id"), F.col("a").alias("b")), "id")


def _vec(name: str, expr, sql: str):
    query(f"SELECT id, round({sql}, 6) AS x FROM {_PAIR}", name)(lambda spark, sf_dir: _pairs(spark, sf_dir).select("id", F.round(expr(), 6).alias("x")))


_vec("vec_dot", lambda: vx.dot("a", "b"), "list_dot_product(a, b)")
_vec("vec_norm", lambda: vx.norm("a"), "sqrt(list_dot_product(a, a))")
_vec("vec_cosine", lambda: vx.cosine("a", "b"), "list_cosine_similarity(a, b)")
_vec("vec_l2", lambda: vx.l2("a", "b"), "list_distance(a, b)")
_vec("vec_add", lambda: vx.total(vx.add("a", "b")), "list_sum(list_transform(list_zip(a, b), lambda z: z[1] + z[2]))")
_vec("vec_scale", lambda: vx.total(vx.scale("a", 2.5)), "list_sum(list_transform(a, lambda x: x * 2.5))")
_vec("vec_normalise", lambda: vx.total(vx.unit("a")), "list_sum(list_transform(a, lambda x: x / sqrt(list_dot_product(a, a))))")

_CENTROID = "SELECT label::BIGINT AS label, j::BIGINT AS j, round(avg(embedding[j + 1]::DOUBLE), 6) AS x FROM embeddings, range(0, 64) r(j) GROUP BY 1, 2"


@query(_CENTROID)
def vec_avg(spark, sf_dir):
    m = vx.mean(t(spark, sf_dir, "embeddings").select("label", "embedding"), ["label"], "embedding")
    return m.select(F.col("label").cast("long").alias("label"), F.posexplode("embedding").alias("j", "x")).select("label", F.col("j").cast("long").alias("j"), F.round("x", 6).alias("x"))


# ------------------------------------------------------------------ joins


def _orders(spark, sf_dir):
    return t(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment"), t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")


def _join(how: str, sql_how: str):
    def run(spark, sf_dir):
        c, o = _orders(spark, sf_dir)
        return c.join(o, (c.c_custkey == o.o_custkey) & (o.o_orderstatus == "F"), how).select("c_custkey", "c_mktsegment", "o_orderkey")

    query(f"SELECT c_custkey, c_mktsegment, o_orderkey FROM customer {sql_how} JOIN orders ON c_custkey = o_custkey AND o_orderstatus = 'F'", f"join_{how}")(run)


for _how, _sql in (("inner", "INNER"), ("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    _join(_how, _sql)


def _hinted(hint: str):
    def run(spark, sf_dir):
        n = t(spark, sf_dir, "nation")
        small = n.hint(hint)
        return t(spark, sf_dir, "customer").join(small, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))

    query("SELECT n_name, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", f"join_hint_{hint}")(run)


for _hint in ("broadcast", "merge", "shuffle_hash"):
    _hinted(_hint)


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", "lang").join(t(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_semi")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", "lang").join(t(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_anti")


@query("SELECT q.vec_id AS qid, b.vec_id, round(list_dot_product(list_transform(q.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)), 6) AS ip FROM embeddings q, embeddings b WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 <> 0 AND list_dot_product(list_transform(q.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)) >= 0.25")
def radius_search(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    e = e.where("embedding IS NOT NULL AND NOT exists(embedding, x -> x IS NULL)").select("vec_id", vx.doubles("embedding").alias("v"))
    found = None
    for (d,) in e.select(F.size("v")).distinct().collect():  # vectors of other sizes have no product
        own = e.where(F.size("v") == d)
        for qid, q in exact.collected(own.where("vec_id % 10 = 0").select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))):
            if len(qid):
                one = _within(own.where("vec_id % 10 <> 0"), qid, q, 0.25)
                found = one if found is None else found.unionByName(one)
    if found is None:
        found = spark.createDataFrame([], "qid long, vec_id long, ip double")
    return found.withColumn("ip", F.round("ip", 6))


def _within(base, qid, q, least):
    """(qid, vec_id, ip) of all pairs with at least that product, by blocks of products; a NaN is above all numbers, as in SQL."""

    def scan(batches):
        for b in batches:
            if b.num_rows:
                ids, x = b.column(0).to_numpy(), vx.matrix(b.column(1))
                step = max(1, exact.SCORES // len(ids))
                for a in range(0, len(qid), step):
                    s = x @ q[a : a + step].T
                    rows, who = np.nonzero(~(s < least))
                    yield pa.RecordBatch.from_arrays([pa.array(qid[a + who]), pa.array(ids[rows]), pa.array(s[rows, who])], names=["qid", "vec_id", "ip"])

    return base.mapInArrow(scan, "qid long, vec_id long, ip double")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def interval_join(spark, sf_dir):
    """Equal users within an hour: the band is cut in hour buckets, each left row looks in its own and the next."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000).alias("h"))
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), "h")
    return a.join(b, ["user_id", "h"]).where((F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 1 HOUR"))).select("a", "b")


@query("SELECT p.event_id, s.event_id AS latest FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'signup') s ON p.user_id = s.user_id AND p.ts >= s.ts")
def asof_join(spark, sf_dir):
    """Each purchase with its user's latest signup: one union, one running last value."""
    e = t(spark, sf_dir, "events").where("event_type IN ('purchase', 'signup')").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", F.desc("event_type")).rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("latest", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "latest")


@query("SELECT n_name, c_custkey, rank FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rank FROM nation JOIN customer ON n_nationkey = c_nationkey) WHERE rank <= 3")
def lateral_topk(spark, sf_dir):
    n, c = t(spark, sf_dir, "nation"), t(spark, sf_dir, "customer")
    best = c.where(F.col("c_nationkey") == F.col("n_nationkey").outer()).orderBy(F.desc("c_acctbal"), "c_custkey").limit(3).select("c_custkey", "c_acctbal")
    w = Window.partitionBy("n_name").orderBy(F.desc("c_acctbal"), "c_custkey")
    return n.lateralJoin(best).select("n_name", "c_custkey", F.row_number().over(w).cast("long").alias("rank"))


# ------------------------------------------------------------------ aggregation


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS net, round(avg(l_discount), 6) AS disc, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def agg_hash(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").where(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp")).groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("net"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count("*").alias("n"))


@query("SELECT l_suppkey, array_to_string(list(DISTINCT l_returnflag ORDER BY l_returnflag), ',') AS flags FROM lineitem GROUP BY 1")
def agg_sort(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.concat_ws(",", F.array_sort(F.collect_set("l_returnflag"))).alias("flags"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("supps"))


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def agg_hll(spark, sf_dir):
    """Sketched distinct users within 5 % of the exact number."""
    a = t(spark, sf_dir, "events").groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 14)).alias("s"), F.count_distinct("user_id").alias("n"))
    return a.select("event_type", (F.abs(F.col("s") - F.col("n")) <= 0.05 * F.col("n") + 1).alias("near"))


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def agg_kll(spark, sf_dir):
    """The sketched median's rank within 2 % of the middle."""
    e = t(spark, sf_dir, "events")
    s = e.groupBy("event_type").agg(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("value"), F.lit(0.5)).alias("med"))
    return e.join(F.broadcast(s), "event_type").groupBy("event_type").agg((F.abs(F.avg((F.col("value") <= F.col("med")).cast("double")) - 0.5) <= 0.02).alias("near"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS g FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def rollup_orders(spark, sf_dir):
    return t(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS g FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def cube_orders(spark, sf_dir):
    return t(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def gsets_documents(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"))


@query("SELECT event_type, count(*) FILTER (dayofweek(ts) IN (0, 6)) AS weekend, count(*) FILTER (dayofweek(ts) NOT IN (0, 6)) AS weekday FROM events GROUP BY 1")
def pivot_events(spark, sf_dir):
    kind = F.when(F.dayofweek("ts").isin(1, 7), "weekend").otherwise("weekday")
    return t(spark, sf_dir, "events").withColumn("kind", kind).groupBy("event_type").pivot("kind", ["weekend", "weekday"]).agg(F.count("kind")).na.fill(0)


# ------------------------------------------------------------------ windows, order, sets


@query("SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_ranks(spark, sf_dir):
    w, x = Window.partitionBy("o_custkey").orderBy("o_orderpriority"), Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf_dir, "orders").select("o_orderkey", *(c.cast("long").alias(a) for c, a in ((F.rank().over(w), "r"), (F.dense_rank().over(w), "dr"), (F.row_number().over(x), "rn"), (F.ntile(4).over(x), "q"))))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_neighbours(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n3, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")
def win_frames(spark, sf_dir):
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    day = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-86_400, 0)
    return t(spark, sf_dir, "events").select("event_id", F.count("*").over(rows).alias("n3"), F.count("*").over(day).alias("day"))


@query("SELECT l_orderkey, l_linenumber::BIGINT AS l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20")
def topk_global(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").limit(20).select("l_orderkey", F.col("l_linenumber").cast("long").alias("l_linenumber"), "l_extendedprice")


@query("SELECT l_returnflag, l_orderkey, rank FROM (SELECT l_returnflag, l_orderkey, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) AS rank FROM lineitem) WHERE rank <= 5")
def topk_group(spark, sf_dir):
    w = Window.partitionBy("l_returnflag").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return t(spark, sf_dir, "lineitem").withColumn("rank", F.row_number().over(w).cast("long")).where("rank <= 5").select("l_returnflag", "l_orderkey", "rank")


def _sets(spark, sf_dir):
    return t(spark, sf_dir, "documents").select(F.pmod("doc_id", F.lit(60)).alias("k")), t(spark, sf_dir, "labels").select(F.pmod("doc_id", F.lit(50)).alias("k"))


_A, _B = "SELECT doc_id % 60 AS k FROM documents", "SELECT doc_id % 50 AS k FROM labels"
for _name, _op, _f in (
    ("set_union", "UNION", lambda a, b: a.unionByName(b).distinct()),
    ("set_union_all", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(f"{_A} {_op} {_B}", _name)(lambda spark, sf_dir, f=_f: f(*_sets(spark, sf_dir)))


# ------------------------------------------------------------------ strings, dates, bits, arrays, json


@query("SELECT doc_id, len(list_filter(string_split_regex(text, '\\s+'), lambda w: w <> '')) AS n FROM documents")
def tok_words(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.size(F.filter(F.split("text", r"[ \t\n\x0B\f\r]+"), lambda w: w != "")).cast("long").alias("n"))


@query("WITH w AS (SELECT item_id, list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM benchmark) SELECT item_id, min(md5(w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS least FROM (SELECT item_id, w, unnest(range(1, len(w) - 1)) AS i FROM w WHERE len(w) >= 3) GROUP BY 1")
def ngram_hash(spark, sf_dir):
    """Least MD5 of a text's word triples."""
    w = t(spark, sf_dir, "benchmark").select("item_id", F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda x: x != "").alias("w"))
    triples = F.transform(F.sequence(F.lit(0), F.size("w") - 3), lambda i: F.md5(F.concat_ws(" ", F.slice("w", i + 1, 3)).cast("binary")))
    return w.where(F.size("w") >= 3).select("item_id", F.array_min(triples).alias("least"))


@query("SELECT conv_id, turn, regexp_replace(lower(text), '[^a-z0-9]+', '-', 'g') AS slug FROM conversations")
def regex_clean(spark, sf_dir):
    return t(spark, sf_dir, "conversations").select("conv_id", "turn", F.regexp_replace(F.lower("text"), "[^a-z0-9]+", "-").alias("slug"))


@query("SELECT lang, count(*) AS n, sum(length(text))::BIGINT AS chars FROM documents GROUP BY 1")
def lang_counts(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars"))


@query("SELECT a.p_partkey AS a, b.p_partkey AS b, levenshtein(a.p_name, b.p_name)::BIGINT AS d FROM part a JOIN part b ON a.p_partkey + 1 = b.p_partkey")
def str_levenshtein(spark, sf_dir):
    p = t(spark, sf_dir, "part").select("p_partkey", "p_name")
    a, b = p.select(F.col("p_partkey").alias("a"), F.col("p_name").alias("x")), p.select(F.col("p_partkey").alias("b"), F.col("p_name").alias("y"))
    return a.join(b, F.col("a") + 1 == F.col("b")).select("a", "b", F.levenshtein("x", "y").cast("long").alias("d"))


@query("SELECT page_id, md5(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g'))) AS h FROM pages")
def page_text(spark, sf_dir):
    return t(spark, sf_dir, "pages").select("page_id", F.md5(ds.page_text().cast("binary")).alias("h"))


@query("SELECT CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS m, count(*) AS n FROM orders GROUP BY 1")
def date_trunc_month(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy(F.date_trunc("month", "o_orderdate").alias("m")).agg(F.count("*").alias("n"))


@query("SELECT l_orderkey, l_linenumber::BIGINT AS l_linenumber, date_diff('day', o_orderdate::DATE, l_shipdate::DATE) AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate < o_orderdate + INTERVAL 30 DAY")
def date_diff_ship(spark, sf_dir):
    j = t(spark, sf_dir, "lineitem").join(t(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.where(F.col("l_shipdate") < F.col("o_orderdate") + F.make_dt_interval(F.lit(30))).select("l_orderkey", F.col("l_linenumber").cast("long").alias("l_linenumber"), F.datediff("l_shipdate", "o_orderdate").cast("long").alias("days"))


@query("SELECT vec_id, list_sum(list_transform(range(0, 64), lambda i: (CASE WHEN embedding[i + 1] > 0 THEN 1 ELSE 0 END) * ((i * 7) % 64)))::BIGINT AS packed, list_sum(list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END))::BIGINT AS ones FROM embeddings")
def bit_pack_check(spark, sf_dir):
    """Signs packed in two 32-bit words by shifts, then read back."""
    half = lambda lo: F.aggregate(F.slice("embedding", lo + 1, 32), F.lit(0).cast("long"), lambda a, x: F.shiftleft(a, 1).bitwiseOR((x > 0).cast("long")))
    e = t(spark, sf_dir, "embeddings").select("vec_id", half(0).alias("h0"), half(32).alias("h1"))
    back = F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), lambda a, i: a + _bit_at(F.col("h0"), F.col("h1"), i) * ((i * 7) % 64))
    return e.select("vec_id", back.alias("packed"), (F.bit_count("h0") + F.bit_count("h1")).cast("long").alias("ones"))


def _bit_at(h0, h1, i):
    word = F.when(i < 32, h0).otherwise(h1)
    return F.floor(word / F.pow(F.lit(2.0), F.lit(31) - i % 32)).cast("long") % 2


@query("WITH s AS (SELECT vec_id, list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END) AS s FROM embeddings), p AS (SELECT q.vec_id AS qid, b.vec_id, list_sum(list_transform(list_zip(q.s, b.s), lambda z: abs(z[1] - z[2])))::BIGINT AS d FROM s q, s b WHERE q.vec_id % 50 = 0 AND b.vec_id <> q.vec_id) SELECT qid, vec_id, d FROM p QUALIFY row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) <= 5")
def hamming_topk(spark, sf_dir):
    half = lambda lo: F.aggregate(F.slice("embedding", lo + 1, 32), F.lit(0).cast("long"), lambda a, x: F.shiftleft(a, 1).bitwiseOR((x > 0).cast("long")))
    e = t(spark, sf_dir, "embeddings").select("vec_id", half(0).alias("a"), half(32).alias("b"))
    q = e.where("vec_id % 50 = 0").select(F.col("vec_id").alias("qid"), F.col("a").alias("qa"), F.col("b").alias("qb"))
    d = (F.bit_count(F.col("a").bitwiseXOR(F.col("qa"))) + F.bit_count(F.col("b").bitwiseXOR(F.col("qb")))).cast("long")
    w = Window.partitionBy("qid").orderBy("d", "vec_id")
    return e.crossJoin(F.broadcast(q)).where("vec_id <> qid").select("qid", "vec_id", d.alias("d")).withColumn("r", F.row_number().over(w)).where("r <= 5").drop("r")


@query("SELECT vec_id, round(list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE)), 6) AS head, round(list_max(embedding)::DOUBLE, 6) AS top, list_position(embedding, list_max(embedding))::BIGINT AS at FROM embeddings")
def arr_slices(spark, sf_dir):
    return t(spark, sf_dir, "embeddings").select("vec_id", F.round(vx.total(vx.doubles(F.slice("embedding", 1, 8))), 6).alias("head"), F.round(F.array_max("embedding").cast("double"), 6).alias("top"), F.array_position("embedding", F.array_max("embedding")).alias("at"))


@query("SELECT label::BIGINT AS label, count(*) AS n, sum(len(embedding))::BIGINT AS flat FROM embeddings GROUP BY 1")
def arr_flatten(spark, sf_dir):
    return t(spark, sf_dir, "embeddings").groupBy(F.col("label").cast("long").alias("label")).agg(F.count("*").alias("n"), F.size(F.flatten(F.collect_list("embedding"))).cast("long").alias("flat"))


@query("SELECT vec_id, round(embedding[1 + vec_id % 64]::DOUBLE, 6) AS x FROM embeddings")
def map_lut(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings").select("vec_id", F.map_from_arrays(F.sequence(F.lit(0), F.lit(63)), "embedding").alias("m"))
    return e.select("vec_id", F.round(F.element_at("m", (F.col("vec_id") % 64).cast("int")).cast("double"), 6).alias("x"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json_props(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT vec_id, label::BIGINT AS label FROM embeddings QUALIFY row_number() OVER (PARTITION BY label ORDER BY md5('42:' || vec_id), vec_id) <= 5")
def stratified_sample(spark, sf_dir):
    w = Window.partitionBy("label").orderBy(F.md5(F.concat(F.lit("42:"), F.col("vec_id").cast("string")).cast("binary")), "vec_id")
    return t(spark, sf_dir, "embeddings").withColumn("r", F.row_number().over(w)).where("r <= 5").select("vec_id", F.col("label").cast("long").alias("label"))


@query("SELECT md5(text) AS h, min(doc_id) AS first, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1")
def dup_vectors(spark, sf_dir):
    """Groups of equal texts, whose vectors coincide: to be known before recall is read."""
    return t(spark, sf_dir, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("h")).agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).where("n > 1")


@query("WITH g(id, w) AS (SELECT item_id, list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') FROM benchmark), d AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM documents), gn AS (SELECT DISTINCT array_to_string(w[i:i + 7], ' ') AS n FROM (SELECT w, unnest(range(1, len(w) - 6)) AS i FROM g WHERE len(w) >= 8)), dn AS (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS n FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM d WHERE len(w) >= 8)) SELECT doc_id, count(*) AS shared FROM dn WHERE n IN (SELECT n FROM gn) GROUP BY 1")
def bench_overlap(spark, sf_dir):
    """Eight-word runs of documents that stand in a benchmark item."""

    def runs(df, key):
        w = df.select(key, F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda x: x != "").alias("w")).where(F.size("w") >= 8)
        return w.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - 7), lambda i: F.concat_ws(" ", F.slice("w", i, 8)))).alias("n"))

    g = runs(t(spark, sf_dir, "benchmark"), "item_id").select("n").distinct()
    return runs(t(spark, sf_dir, "documents"), "doc_id").join(g, "n", "left_semi").groupBy("doc_id").agg(F.count("*").alias("shared"))


# ------------------------------------------------------------------ user functions, SQL surface


@query(_CENTROID)
def udaf_centroid(spark, sf_dir):
    """The same means by a grouped Arrow aggregate."""
    import pyarrow as pa

    def mean(tab: pa.Table) -> pa.Table:
        m = vx.matrix(tab.column("embedding")).mean(axis=0)
        return pa.table({"label": pa.array([tab.column("label")[0].as_py()] * len(m), pa.int64()), "j": pa.array(range(len(m)), pa.int64()), "x": pa.array(m)})

    e = t(spark, sf_dir, "embeddings").select(F.col("label").cast("long").alias("label"), "embedding")
    return e.groupBy("label").applyInArrow(mean, "label long, j long, x double").select("label", "j", F.round("x", 6).alias("x"))


@query("SELECT q.vec_id AS qid, b.vec_id, round(list_dot_product(list_transform(q.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)), 6) AS ip FROM embeddings q, embeddings b WHERE q.vec_id = 0 AND b.vec_id <> 0")
def sql_vec_dot(spark, sf_dir):
    """A SQL function over temporary views: one stated query against every other row."""
    t(spark, sf_dir, "embeddings").createOrReplaceTempView("annspark_embeddings")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> double(x) * double(y)), 0.0D, (s, x) -> s + x)")
    return spark.sql("SELECT q.vec_id AS qid, b.vec_id, round(vec_dot(q.embedding, b.embedding), 6) AS ip FROM annspark_embeddings q JOIN annspark_embeddings b ON q.vec_id = 0 AND b.vec_id <> 0")


# ------------------------------------------------------------------ event-time windows (batch form of the streaming plans)


@query("SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


@query("SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR]) AS start FROM events) GROUP BY 1")
def st_sliding(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy(F.window("ts", "12 hours", "6 hours")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


@query("WITH m AS (SELECT user_id, ts, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 12 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def st_session(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")

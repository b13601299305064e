"""Corpora and query sets on the given tables.

A corpus is a DataFrame (id long, vec array<double-like>, seq string). Every corpus has a SQL text for another
engine beside it; ids are natural keys or hashes, never positions, so that no global sort is needed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifknn.functions.patterns import ends
from motifknn.functions.vectors import query_vector
from motifknn.sources.tables import table

def _with_vectors(items: DataFrame, spark: SparkSession, d: str) -> DataFrame:
    """Vectors are dealt to items by id modulo their number (one scalar from the table's statistics)."""
    vectors = table(spark, d, "embeddings")
    n = vectors.count()
    return items.withColumn("vec_id", F.pmod("id", F.lit(n))).join(vectors.select("vec_id", F.col("embedding").alias("vec")), "vec_id").select("id", "seq", "vec")


_DEAL = "SELECT i.id, i.seq, e.embedding AS vec FROM ({}) i JOIN embeddings e ON e.vec_id = i.id % (SELECT count(*) FROM embeddings)"


def _hash_id(seq):
    return F.conv(F.substring(F.md5(seq), 1, 15), 16, 10).cast("long")


def _document(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("text").alias("seq"))
    return docs.join(table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")), "id").select("id", "seq", "vec")


def _passage(spark: SparkSession, d: str) -> DataFrame:
    return _with_vectors(table(spark, d, "benchmark").select(F.col("item_id").cast("long").alias("id"), F.col("text").alias("seq")), spark, d)


def _vocab(spark: SparkSession, d: str) -> DataFrame:
    words = table(spark, d, "documents").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("seq")).distinct()
    return _with_vectors(words.select(_hash_id("seq").alias("id"), "seq"), spark, d)


def _pname(spark: SparkSession, d: str) -> DataFrame:
    return _with_vectors(table(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("seq")), spark, d)


def _turn(spark: SparkSession, d: str) -> DataFrame:
    return _with_vectors(table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("text").alias("seq")), spark, d)


def _line(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("t"), F.posexplode(F.split("text", "\n")).alias("n", "seq")).where("seq != ''")
    return _with_vectors(lines.select((F.col("t") * 10000 + F.col("n")).alias("id"), "seq"), spark, d)


def _urlpath(spark: SparkSession, d: str) -> DataFrame:
    return _with_vectors(table(spark, d, "pages").select(F.col("page_id").alias("id"), F.regexp_replace("url", "^[a-z]+://[^/]*", "").alias("seq")), spark, d)


def _url(spark: SparkSession, d: str) -> DataFrame:
    return _with_vectors(table(spark, d, "pages").select(F.col("page_id").alias("id"), F.col("url").alias("seq")), spark, d)


_ITEM_KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "CAST(round(l_quantity * 100) AS BIGINT)", "CAST(round(l_extendedprice * 100) AS BIGINT)"]


def _items(spark: SparkSession, d: str) -> DataFrame:
    key = F.concat_ws("|", *[F.expr(k).cast("string") for k in _ITEM_KEY], F.date_format("l_shipdate", "yyyy-MM-dd"))
    lines = table(spark, d, "lineitem").select(F.conv(F.substring(F.md5(key), 1, 15), 16, 10).cast("long").alias("id"), "l_partkey", F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 105000, F.col("l_discount") * 10, F.col("l_tax") * 12.5).alias("vec"))
    parts = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.concat_ws(" ", "p_name", "p_type", "p_brand").alias("seq"))
    return lines.join(parts, "l_partkey").select("id", "seq", "vec")


_ITEMS_SQL = (
    "SELECT CAST('0x' || substring(md5(concat_ws('|', " + ", ".join(f"CAST({k} AS VARCHAR)" for k in _ITEM_KEY) + ", strftime(l_shipdate, '%Y-%m-%d'))), 1, 15) AS BIGINT) AS id, "
    "concat_ws(' ', p_name, p_type, p_brand) AS seq, [l_quantity / 50, l_extendedprice / 105000, l_discount * 10, l_tax * 12.5] AS vec FROM lineitem JOIN part ON p_partkey = l_partkey"
)


def _orders_seq(spark: SparkSession, d: str) -> DataFrame:
    orders = table(spark, d, "orders").select("o_custkey", F.col("o_orderkey").alias("id"), "o_orderpriority", F.col("o_totalprice"), F.month("o_orderdate").alias("m"), F.dayofweek("o_orderdate").alias("w"))
    who = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment", "c_name", "c_acctbal")
    return orders.join(who, "o_custkey").select("id", F.concat_ws(" ", "c_mktsegment", "o_orderpriority", "c_name").alias("seq"), F.array(F.col("o_totalprice") / 500000, F.col("c_acctbal") / 10000, F.col("m") / 12.0, F.col("w") / 7.0).alias("vec"))


_ORDERS_SQL = (
    "SELECT o_orderkey AS id, concat_ws(' ', c_mktsegment, o_orderpriority, c_name) AS seq, [o_totalprice / 500000, c_acctbal / 10000, month(o_orderdate) / 12.0::DOUBLE, (dayofweek(o_orderdate) + 1) / 7.0::DOUBLE] AS vec "
    "FROM orders JOIN customer ON c_custkey = o_custkey"
)


def _user_events(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("user_id", "ts", "event_id", "event_type", "value")
    per = e.groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("s")))).alias("l"), F.count(F.lit(1)).alias("n"), F.avg("value").alias("v"))
    return per.select(F.col("user_id").cast("long").alias("id"), F.array_join(F.transform("l", lambda x: x["s"]), "").alias("seq"), F.array(F.col("n") / 100.0, F.col("v") / 100.0).alias("vec"))


_EVENTS_SQL = "SELECT CAST(user_id AS BIGINT) AS id, string_agg(substring(event_type, 1, 1), '' ORDER BY ts, event_id) AS seq, [count(*) / 100.0::DOUBLE, avg(value) / 100.0::DOUBLE] AS vec FROM events GROUP BY user_id"

_HASH = "CAST('0x' || substring(md5(seq), 1, 15) AS BIGINT)"
#: name -> (builder, SQL, dimension); every sequence is a whole text, line, word, name or address.
CORPORA = {
    "passage": (_passage, _DEAL.format("SELECT CAST(item_id AS BIGINT) AS id, text AS seq FROM benchmark"), 64),
    "document": (_document, "SELECT d.doc_id AS id, d.text AS seq, e.embedding AS vec FROM documents d JOIN embeddings e ON e.vec_id = d.doc_id", 64),
    "vocab": (_vocab, _DEAL.format(f"SELECT {_HASH} AS id, seq FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS seq FROM documents)"), 64),
    "turn": (_turn, _DEAL.format("SELECT conv_id * 1000 + turn AS id, text AS seq FROM conversations"), 64),
    "line": (_line, _DEAL.format("SELECT t * 10000 + n AS id, seq FROM (SELECT conv_id * 1000 + turn AS t, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS n, unnest(string_split(text, chr(10))) AS seq FROM conversations) WHERE seq != ''"), 64),
    "pname": (_pname, _DEAL.format("SELECT p_partkey AS id, p_name AS seq FROM part"), 64),
    "urlpath": (_urlpath, _DEAL.format("SELECT page_id AS id, regexp_replace(url, '^[a-z]+://[^/]*', '') AS seq FROM pages"), 64),
    "url": (_url, _DEAL.format("SELECT page_id AS id, url AS seq FROM pages"), 64),
    "items": (_items, _ITEMS_SQL, 4),
    "orders_seq": (_orders_seq, _ORDERS_SQL, 4),
    "user_events": (_user_events, _EVENTS_SQL, 2),
}


def corpus(spark: SparkSession, d: str, name: str) -> DataFrame:
    return CORPORA[name][0](spark, d)


def query_set(items: DataFrame, dim: int, per_length: int = 20, lengths: tuple[int, ...] = (2, 3, 4), sample: str = "distinct", k: int = 10, ef: int = 40, min_items: int = 1) -> DataFrame:
    """(qid, pattern, len, qvec, k, ef): the first ``per_length`` patterns of each length.

    ``distinct`` takes occurring patterns in md5 order; ``occurrence`` weighs them by how often they occur
    (order of md5 over a place); ``frequent`` is distinct among those in at least ``min_items`` items. The
    result is a report-sized set by construction.
    """


    runs = ends(items, max(lengths)).where(F.char_length("pattern").isin(list(lengths)))
    if sample == "occurrence":
        drawn = runs.withColumn("key", F.md5(F.concat_ws("|", F.col("id").cast("string"), F.col("end").cast("string"), "pattern"))).groupBy("pattern").agg(F.min("key").alias("key"))
    elif sample == "frequent":
        drawn = runs.groupBy("pattern").agg(F.countDistinct("id").alias("n")).where(F.col("n") >= min_items).withColumn("key", F.md5("pattern"))
    else:
        drawn = runs.select("pattern").distinct().withColumn("key", F.md5("pattern"))
    ranked = drawn.withColumn("len", F.char_length("pattern")).withColumn("rk", F.row_number().over(Window.partitionBy("len").orderBy("key", "pattern"))).where(F.col("rk") <= per_length)
    qid = (F.col("len") * 10000 + F.col("rk")).cast("long")
    return ranked.select(qid.alias("qid"), "pattern", "len", query_vector(qid, dim).alias("qvec"), F.lit(k).alias("k"), F.lit(ef).alias("ef"))


def query_sql(name: str, per_length: int = 20, lengths: tuple[int, ...] = (2, 3, 4)) -> str:
    """CTEs corpus and queries for the other engine, ``distinct`` sampling."""
    base, dim = CORPORA[name][1], CORPORA[name][2]
    return f"""corpus AS ({base}),
runs AS (SELECT DISTINCT n AS len, substring(seq, s, n) AS pattern FROM (SELECT seq, unnest(range(1, length(seq) + 1)) AS s FROM corpus) t, (SELECT unnest({list(lengths)}) AS n) l WHERE s + n - 1 <= length(seq)),
queries AS (SELECT *, list_transform(range(0, {dim}), lambda d: ((qid * 7919 + d * 104729 + qid * d * 17) % 2003) / 1001.5::DOUBLE - 1) AS qvec FROM (
  SELECT CAST(len * 10000 + row_number() OVER (PARTITION BY len ORDER BY md5(pattern), pattern) AS BIGINT) AS qid, len, pattern FROM runs QUALIFY row_number() OVER (PARTITION BY len ORDER BY md5(pattern), pattern) <= {per_length}))"""


EXACT_SQL = """answers AS (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rk, id, dist FROM (
  SELECT q.qid, c.id, round(list_sum(list_transform(list_zip(c.vec, q.qvec), lambda p: (CAST(p[1] AS DOUBLE) - p[2]) * (CAST(p[1] AS DOUBLE) - p[2]))), 4) AS dist
  FROM queries q JOIN corpus c ON contains(c.seq, q.pattern)) QUALIFY rk <= 10)"""

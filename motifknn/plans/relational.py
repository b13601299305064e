"""Operators around the methods: scans, sources, sinks, joins, aggregates, windows, sets, functions, SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifknn.functions.patterns import like_escaped
from motifknn.functions.vectors import cosine_distance, dot, l2sq, norm
from motifknn.operators import classes as C
from motifknn.operators.index import class_tables
from motifknn.plans.staging import shared_folder, staged
from motifknn.plans.workload import CORPORA, corpus
from motifknn.sources.tables import SCHEMAS, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return keep


def plain(name: str, text: str, sql: str | None = None, tables: str = "") -> None:
    """An operator whose form is SQL text over temporary views of its own."""

    def run(spark, d):
        return spark.sql(text, **{t: table(spark, d, t) for t in (tables or text_tables(text)).split()})

    QUERIES[name] = run
    SQL[name] = sql or text.replace("{", "").replace("}", "")


def text_tables(text: str) -> str:
    return " ".join(t for t in SCHEMAS if "{" + t + "}" in text)


# --- scans, sources, sinks
plain("op_scan_parquet", "SELECT p_partkey, p_name, p_size FROM {part}")
plain("op_scan_pushdown", "SELECT doc_id, n_chars FROM {documents} WHERE n_chars > 2000 AND contains(text, 'the')")


def _round(fmt: str, t: str, columns: list[str]):
    def run(spark, d):
        path = f"{shared_folder(spark)}/rt-{fmt}-{uuid.uuid4().hex}"
        df = table(spark, d, t).select(*columns)
        df.write.format(fmt).save(path)
        return spark.read.format(fmt).schema(df.schema).load(path)

    return run


for _f in ("csv", "json", "orc"):
    op(f"op_roundtrip_{_f}", "SELECT p_partkey, p_name, p_brand, p_size FROM part")(_round(_f, "part", ["p_partkey", "p_name", "p_brand", "p_size"]))


@op("op_roundtrip_text", "SELECT p_name AS value FROM part")
def _text(spark, d):
    path = f"{shared_folder(spark)}/rt-text-{uuid.uuid4().hex}"
    table(spark, d, "part").select(F.col("p_name").alias("value")).write.text(path)
    return spark.read.text(path)


@op("op_sink_partitioned", "SELECT doc_id, n_chars FROM documents WHERE lang = 'fr'")
def _partitioned(spark, d):
    path = f"{shared_folder(spark)}/by-lang-{uuid.uuid4().hex}"
    table(spark, d, "documents").select("doc_id", "n_chars", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).where("lang = 'fr'").select("doc_id", "n_chars")


@op("op_sink_bucketed", "SELECT o_orderkey, sum(l_quantity) AS qty FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")
def _bucketed(spark, d):
    names = [f"b_{k}_{uuid.uuid4().hex[:8]}" for k in ("o", "l")]
    table(spark, d, "orders").select("o_orderkey").write.bucketBy(8, "o_orderkey").sortBy("o_orderkey").saveAsTable(names[0])
    table(spark, d, "lineitem").select("l_orderkey", "l_quantity").write.bucketBy(8, "l_orderkey").sortBy("l_orderkey").saveAsTable(names[1])
    o, n = spark.table(names[0]), spark.table(names[1])
    return o.join(n, o.o_orderkey == n.l_orderkey).groupBy("o_orderkey").agg(F.sum("l_quantity").alias("qty"))


@op("op_sink_noop")
def _noop(spark, d):
    from motifknn.operators.measures import timed

    return spark.createDataFrame([(timed(table(spark, d, "part")) >= 0,)], "ran boolean")


@op("op_source_patternindex", "SELECT doc_id AS id, text AS seq FROM documents WHERE contains(text, 'xq')")
def _source(spark, d):
    """The filter on the sequence is pushed to the source, which rules shards out by it."""
    from motifknn.sources.patternindex import PatternIndexSource, write_pattern_index

    path = f"{shared_folder(spark)}/pidx-{uuid.uuid4().hex}"
    write_pattern_index(table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("text").alias("seq")), path, 4)
    spark.dataSource.register(PatternIndexSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    return spark.read.format("patternindex").load(path).where(F.contains("seq", F.lit("xq")))


# --- projection and filters
plain("op_project_pairs", "SELECT doc_id AS id, text AS seq, CAST(n_chars AS DOUBLE) AS n FROM {documents}")
plain("op_filter_contains", "SELECT doc_id FROM {documents} WHERE contains(text, 'ation')")
plain("op_filter_prefix_suffix", "SELECT doc_id, startswith(text, 'The') AS a, endswith(text, '.') AS b FROM {documents}", "SELECT doc_id, starts_with(text, 'The') AS a, ends_with(text, '.') AS b FROM documents")


@op("op_filter_like_escaped", "SELECT doc_id FROM documents WHERE text LIKE '%!%!%!%%' ESCAPE '!' OR text LIKE '%!_%' ESCAPE '!'")
def _like(spark, d):
    return table(spark, d, "documents").where(f"text LIKE '{like_escaped('%%%')}' ESCAPE '!' OR text LIKE '{like_escaped('_')}' ESCAPE '!'").select("doc_id")


plain("op_filter_ilike", "SELECT p_partkey FROM {part} WHERE p_name ILIKE '%A%B%'")
plain("op_filter_rlike_motif", "SELECT p_partkey FROM {part} WHERE rlike(p_name, 'a..e')", "SELECT p_partkey FROM part WHERE regexp_matches(p_name, 'a..e')")
@op("op_filter_in_between", "SELECT vec_id AS id, round(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE) - 0.1) * (CAST(x AS DOUBLE) - 0.1))), 4) AS dist FROM embeddings JOIN documents ON doc_id = vec_id WHERE label IN (1, 2) AND n_chars BETWEEN 300 AND 900 ORDER BY dist, id LIMIT 10")
def _in_between(spark, d):
    """The nearest under a set and a range predicate."""
    rows = table(spark, d, "embeddings").where("label IN (1, 2)").join(table(spark, d, "documents").where("n_chars BETWEEN 300 AND 900").select("doc_id"), F.col("doc_id") == F.col("vec_id"))
    return rows.select(F.col("vec_id").alias("id"), F.round(l2sq(F.col("embedding"), F.array_repeat(F.lit(0.1), 64)), 4).alias("dist")).orderBy("dist", "id").limit(10)
plain("op_filter_nullsafe", "SELECT d.doc_id, coalesce(l.quality, -1) AS q, nullif(l.toxic, 0) AS t, l.toxic IS NOT DISTINCT FROM NULL AS unknown FROM {documents} d LEFT JOIN {labels} l ON l.doc_id = d.doc_id")


# --- joins
@op("op_join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _jb(spark, d):
    return table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


def _hinted(hint: str):
    def run(spark, d):
        o, n = table(spark, d, "orders").select("o_orderkey", "o_orderpriority"), table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
        return n.join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.round(F.sum("l_quantity"), 2).alias("qty"))

    return run


for _h in ("merge", "shuffle_hash"):
    op({"merge": "op_join_sortmerge", "shuffle_hash": "op_join_shufflehash"}[_h], "SELECT o_orderpriority, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(_hinted(_h))
plain("op_join_nestedloop", "SELECT b.item_id, count(*) AS n FROM {benchmark} b JOIN {documents} d ON contains(d.text, b.text) GROUP BY b.item_id")


@op("op_join_range", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON b.n_chars BETWEEN a.n_chars + 1 AND a.n_chars + 5 WHERE a.lang = 'es' AND b.lang = 'fr'")
def _range(spark, d):
    """Bands on the range key turn the theta join into an equi-join: a row meets its own band and the next."""
    docs, w = table(spark, d, "documents").select("doc_id", "n_chars", "lang"), 5
    a = docs.where("lang = 'es'").select(F.col("doc_id").alias("a"), F.col("n_chars").alias("x"), F.explode(F.array(F.floor(F.col("n_chars") / w), F.floor(F.col("n_chars") / w) + 1)).alias("band"))
    b = docs.where("lang = 'fr'").select(F.col("doc_id").alias("b"), F.col("n_chars").alias("y"), F.floor(F.col("n_chars") / w).alias("band"))
    return a.join(b, "band").where((F.col("y") > F.col("x")) & (F.col("y") <= F.col("x") + w)).select("a", "b")


@op("op_join_asof", "SELECT a.event_id, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'click' AND b.ts < a.ts AND b.ts = (SELECT max(c.ts) FROM events c WHERE c.user_id = a.user_id AND c.event_type = 'click' AND c.ts < a.ts)) AS prior FROM events a WHERE a.event_type = 'purchase'")
def _asof(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    clicks = F.max(F.when(F.col("event_type") == "click", F.struct("ts", "event_id"))).over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1))
    return e.withColumn("c", clicks).where("event_type = 'purchase'").select("event_id", F.col("c.event_id").alias("prior"))


plain("op_join_interval", "SELECT c.event_id AS click, p.event_id AS buy FROM {events} c JOIN {events} p ON p.user_id = c.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 DAY WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
plain("op_join_left", "SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON l.doc_id = d.doc_id")
plain("op_join_right", "SELECT d.doc_id, l.quality FROM {labels} l RIGHT JOIN {documents} d ON l.doc_id = d.doc_id")
plain("op_join_full", "SELECT e.vec_id, d.doc_id FROM {embeddings} e FULL JOIN {documents} d ON d.doc_id = e.vec_id + 100")
plain("op_join_semi", "SELECT doc_id FROM {documents} d LEFT SEMI JOIN {labels} l ON l.doc_id = d.doc_id", "SELECT doc_id FROM documents SEMI JOIN labels USING (doc_id)")
plain("op_join_anti", "SELECT doc_id FROM {documents} d LEFT ANTI JOIN {labels} l ON l.doc_id = d.doc_id", "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
plain("op_join_cross", "SELECT a.r_name AS a, b.r_name AS b FROM {region} a CROSS JOIN {region} b")
plain("op_join_self", "SELECT a.n_name AS a, b.n_name AS b FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
plain("op_join_lateral", "SELECT b.item_id, x.doc_id, x.n_chars FROM {benchmark} b, LATERAL (SELECT d.doc_id, d.n_chars FROM {documents} d WHERE contains(d.text, b.text) ORDER BY d.n_chars, d.doc_id LIMIT 3) x")

# --- aggregates
plain("op_agg_hash", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS s, round(avg(l_extendedprice), 4) AS a, min(l_tax + 0.0) AS lo, max(l_discount + 0.0) AS hi, count(*) AS n FROM {lineitem} GROUP BY 1, 2")
plain("op_agg_sort", "SELECT lang, min(text) AS lo, max(text) AS hi FROM {documents} GROUP BY lang")


@op("op_agg_partial_final", "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY 1")
def _salted(spark, d):
    rows = table(spark, d, "lineitem").select("l_returnflag", F.pmod(F.xxhash64("l_orderkey"), F.lit(16)).alias("salt"))
    return rows.groupBy("l_returnflag", "salt").agg(F.count(F.lit(1)).alias("n")).groupBy("l_returnflag").agg(F.sum("n").alias("n"))


plain("op_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS p, count(DISTINCT l_suppkey) AS s FROM {lineitem} GROUP BY 1")


@op("op_agg_approx_distinct", "SELECT true AS within")
def _approx(spark, d):
    return table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("e")).select((F.abs(F.col("a") - F.col("e")) <= F.col("e") * 0.05).alias("within"))


plain("op_agg_percentile", "SELECT lang, round(percentile(n_chars, 0.5), 4) AS p50, round(percentile(n_chars, 0.9), 4) AS p90 FROM {documents} GROUP BY lang", "SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS p50, round(quantile_cont(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY lang")


@op("op_agg_maxby", "SELECT c_mktsegment, max_by(c_custkey, c_acctbal) AS top, min_by(c_custkey, c_acctbal) AS low FROM customer GROUP BY 1")
def _maxby(spark, d):
    """Of several customers with the same balance the one with the smallest key."""
    known = F.col("c_acctbal").isNotNull() & F.col("c_custkey").isNotNull()
    return table(spark, d, "customer").groupBy("c_mktsegment").agg(
        F.max_by("c_custkey", F.when(known, F.struct("c_acctbal", -F.col("c_custkey")))).alias("top"),
        F.min_by("c_custkey", F.when(known, F.struct("c_acctbal", "c_custkey"))).alias("low"),
    )


for _k, _g in (("groupingsets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())"), ("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)")):
    plain(f"op_agg_{_k}", f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM {{lineitem}} GROUP BY {_g}")


@op("op_agg_pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def _pivot(spark, d):
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


plain("op_agg_having", "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey HAVING count(*) > 12")
plain("op_agg_filter", "SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 200000) AS big, count(*) AS n FROM {orders} GROUP BY 1")
plain("op_agg_listagg", "SELECT user_id, listagg(event_type, ',') WITHIN GROUP (ORDER BY event_id) AS trail FROM {events} GROUP BY user_id", "SELECT user_id, string_agg(event_type, ',' ORDER BY event_id) AS trail FROM events GROUP BY user_id")


@op("op_agg_collect", "SELECT n_regionkey, array_to_string(list_sort(list(n_name)), ';') AS names FROM nation GROUP BY 1")
def _collect(spark, d):
    return table(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ";").alias("names"))


plain("op_agg_regression", "SELECT round(regr_slope(ln(l_extendedprice), ln(l_quantity)), 6) AS slope, round(corr(l_quantity, l_extendedprice), 6) AS r FROM {lineitem}")

# --- windows
plain("op_win_ranking", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
plain("op_win_analytic", "SELECT event_id, lag(event_id) OVER w AS a, lead(event_id, 2) OVER w AS b, first_value(event_id) OVER w AS c, nth_value(event_id, 2) OVER w AS e FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
plain("op_win_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 4) AS s FROM {events}")
plain("op_win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM {events}")
plain("op_win_topk", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM {orders}) WHERE r <= 3")

# --- sort, limit, sets
plain("op_sort_ties", "SELECT o_orderkey, o_orderpriority FROM {orders} ORDER BY o_orderpriority, o_orderkey LIMIT 50")
plain("op_limit_offset", "SELECT o_orderkey FROM {orders} ORDER BY o_orderkey LIMIT 20 OFFSET 30")
plain("op_topn", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")


@op("op_sort_within", "SELECT count(*) AS n, true AS sorted FROM documents")
def _within(spark, d):
    """Rows of each partition in order, checked by comparing neighbours."""
    df = table(spark, d, "documents").select("doc_id").repartition(4, "doc_id").sortWithinPartitions("doc_id")
    seen = df.mapInPandas(lambda it: (pd.DataFrame({"n": [len(p)], "ok": [bool(p["doc_id"].is_monotonic_increasing)]}) for p in it), "n long, ok boolean")
    return seen.agg(F.sum("n").alias("n"), F.min("ok").alias("sorted"))


_SETS = ("SELECT p_size % 20 AS x FROM {part} WHERE p_partkey % 2 = 0", "SELECT p_size % 30 AS x FROM {part} WHERE p_partkey % 3 = 0")
for _s in ("UNION", "UNION ALL", "INTERSECT", "INTERSECT ALL", "EXCEPT", "EXCEPT ALL"):
    plain("op_set_" + _s.lower().replace(" ", "_"), f"{_SETS[0]} {_s} {_SETS[1]}")
for _k, _p in (("and", "contains(seq, 'th') AND contains(seq, 'an')"), ("or", "contains(seq, 'th') OR contains(seq, 'ou')"), ("not", "contains(seq, 'th') AND NOT contains(seq, 'an')")):
    op(f"op_pattern_{_k}", f"SELECT id, dist FROM (SELECT doc_id AS id, text AS seq, round(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE) - 0.1) * (CAST(x AS DOUBLE) - 0.1))), 4) AS dist FROM documents JOIN embeddings ON vec_id = doc_id) WHERE {_p} ORDER BY dist, id LIMIT 10")(
        lambda spark, d, p=_p: table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("text").alias("seq")).where(p).join(table(spark, d, "embeddings"), F.col("vec_id") == F.col("id"))
        .select("id", F.round(l2sq(F.col("embedding"), F.transform("embedding", lambda x: F.lit(0.1))), 4).alias("dist")).orderBy("dist", "id").limit(10)
    )

# --- scalar functions
plain("op_str_basic", "SELECT p_partkey, char_length(p_name) AS n, upper(p_name) AS u, substring(p_name, 2, 3) AS s, left(p_name, 2) AS l, right(p_name, 2) AS r, reverse(p_name) AS v, instr(p_name, 'a') AS i FROM {part}", "SELECT p_partkey, CAST(length(p_name) AS INT) AS n, upper(p_name) AS u, substring(p_name, 2, 3) AS s, left(p_name, 2) AS l, right(p_name, 2) AS r, reverse(p_name) AS v, CAST(instr(p_name, 'a') AS INT) AS i FROM part")
plain("op_str_split", "SELECT p_partkey, split_part(p_name, ' ', 1) AS a, split_part(p_name, ' ', 2) AS b FROM {part}")
plain("op_str_regex", "SELECT doc_id, regexp_replace(text, '[aeiou]+', '_') AS r FROM {documents}", "SELECT doc_id, regexp_replace(text, '[aeiou]+', '_', 'g') AS r FROM documents")
plain("op_str_trim", "SELECT p_partkey, trim(concat('  ', p_brand, ' ')) AS t, translate(p_brand, 'abc', 'xyz') AS x FROM {part}")
plain("op_str_pad", "SELECT p_partkey, lpad(p_brand, 12, '*') AS l, rpad(p_brand, 12, '-') AS r FROM {part}")
plain("op_str_edit", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS e FROM {nation} a JOIN {nation} b ON a.n_nationkey < b.n_nationkey WHERE levenshtein(a.n_name, b.n_name) <= 4", "SELECT a.n_name AS a, b.n_name AS b, CAST(levenshtein(a.n_name, b.n_name) AS INT) AS e FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey WHERE levenshtein(a.n_name, b.n_name) <= 4")
plain("op_str_hash", "SELECT p_partkey, md5(p_name) AS h FROM {part}")


@op("op_str_ngrams", "WITH g AS (SELECT substring(p_name, s, 3) AS g FROM (SELECT p_name, unnest(range(1, length(p_name) - 1)) AS s FROM part)) SELECT g, count(*) AS n FROM g GROUP BY g")
def _ngrams(spark, d):
    g = table(spark, d, "part").where("char_length(p_name) > 2").select("p_name", F.explode(F.sequence(F.lit(1), F.char_length("p_name") - 2)).alias("s"))
    return g.select(F.substring("p_name", F.col("s"), F.lit(3)).alias("g")).groupBy("g").agg(F.count(F.lit(1)).alias("n"))


plain("op_str_html_title", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_replace(url, '^[a-z]+://[^/]*', '') AS path FROM {pages}")
plain("op_date_parts", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS dd FROM {orders}", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(day(o_orderdate) AS INT) AS dd FROM orders")
plain("op_date_trunc", "SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS mo, count(*) AS n FROM {orders} GROUP BY 1")
plain("op_date_diff", "SELECT l_orderkey, l_linenumber, l_partkey, datediff(DAY, o_orderdate, l_shipdate) AS days FROM {lineitem} JOIN {orders} ON o_orderkey = l_orderkey", "SELECT l_orderkey, l_linenumber, l_partkey, CAST(trunc(date_diff('second', o_orderdate, l_shipdate) / 86400) AS BIGINT) AS days FROM lineitem JOIN orders ON o_orderkey = l_orderkey")
plain("op_date_interval", "SELECT o_orderkey, o_orderdate + INTERVAL 30 DAYS AS due FROM {orders} WHERE o_orderdate + INTERVAL 30 DAYS < TIMESTAMP_NTZ '1995-01-01 00:00:00'", "SELECT o_orderkey, o_orderdate + INTERVAL 30 DAYS AS due FROM orders WHERE o_orderdate + INTERVAL 30 DAYS < TIMESTAMP '1995-01-01 00:00:00'")
plain("op_math", "SELECT l_orderkey, l_partkey, l_linenumber, round(sqrt(l_quantity), 6) AS a, round(pow(l_quantity, 1.5), 4) AS b, round(ln(l_extendedprice), 6) AS c, greatest(l_quantity, 10.0) AS e, try_divide(l_quantity, nullif(l_linenumber - 1, 0)) AS g FROM {lineitem}", "SELECT l_orderkey, l_partkey, l_linenumber, round(sqrt(l_quantity), 6) AS a, round(pow(l_quantity, 1.5), 4) AS b, round(ln(l_extendedprice), 6) AS c, greatest(l_quantity, 10.0::DOUBLE) AS e, l_quantity / nullif(l_linenumber - 1, 0) AS g FROM lineitem")
for _k, _fn, _s in (("l2", l2sq, "list_sum(list_transform(list_zip(e.embedding, z.v), lambda p: (CAST(p[1] AS DOUBLE) - p[2]) * (CAST(p[1] AS DOUBLE) - p[2])))"), ("dot", dot, "list_sum(list_transform(list_zip(e.embedding, z.v), lambda p: CAST(p[1] AS DOUBLE) * p[2]))"), ("cosine", cosine_distance, "1 - list_sum(list_transform(list_zip(e.embedding, z.v), lambda p: CAST(p[1] AS DOUBLE) * p[2])) / (sqrt(list_sum(list_transform(e.embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))) * sqrt(list_sum(list_transform(z.v, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))))")):
    op(f"op_vec_{_k}", f"SELECT e.vec_id, round({_s}, 4) AS x FROM embeddings e, (SELECT embedding AS v FROM embeddings WHERE vec_id = 0) z")(
        lambda spark, d, fn=_fn: table(spark, d, "embeddings").crossJoin(F.broadcast(table(spark, d, "embeddings").where("vec_id = 0").select(F.col("embedding").alias("v")))).select("vec_id", F.round(fn(F.col("embedding"), F.col("v")), 4).alias("x"))
    )


@op("op_vec_normalise", "SELECT vec_id, true AS unit FROM embeddings")
def _unit(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x * 3.0).alias("v"))
    n = e.withColumn("n", norm(F.col("v"))).select("vec_id", F.transform("v", lambda x: x / F.col("n")).alias("u"))
    return n.select("vec_id", (F.abs(norm(F.col("u")) - 1) < 1e-6).alias("unit"))


@op("op_vec_centroid", "SELECT label, i, round(avg(CAST(x AS DOUBLE)), 4) AS mean FROM (SELECT label, unnest(embedding) AS x, CAST(unnest(range(0, len(embedding))) AS INT) AS i FROM embeddings) GROUP BY label, i")
def _centroid(spark, d):
    return table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.round(F.avg(F.col("x").cast("double")), 4).alias("mean"))


@op("op_array", "SELECT p_partkey, array_to_string(list_sort(list_distinct(string_split(p_name, ' '))), ',') AS s, len(string_split(p_name, ' ')) AS n, list_contains(string_split(p_name, ' '), 'blue') AS blue FROM part")
def _array(spark, d):
    w = F.split("p_name", " ")
    return table(spark, d, "part").select("p_partkey", F.array_join(F.array_sort(F.array_distinct(w)), ",").alias("s"), F.size(w).cast("long").alias("n"), F.exists(w, lambda x: x == "blue").alias("blue"))


@op("op_map", "SELECT k, sum(n) AS n FROM (SELECT p_name, k, count(*) AS n FROM (SELECT p_partkey, p_name, unnest(string_split(p_name, '')) AS k FROM part) GROUP BY p_partkey, p_name, k) GROUP BY k")
def _map(spark, d):
    """Symbol histogram of each name as a map, summed over names."""
    s = F.filter(F.split("p_name", ""), lambda x: x != "")
    m = F.map_from_entries(F.transform(F.array_distinct(s), lambda c: F.struct(c, F.size(F.filter(s, lambda x: x == c)))))
    return table(spark, d, "part").select(F.explode(m).alias("k", "n")).groupBy("k").agg(F.sum("n").alias("n"))


@op("op_struct", "SELECT c_custkey AS k, c_name AS name, c_acctbal AS bal FROM customer")
def _struct(spark, d):
    c = table(spark, d, "customer").select(F.struct(F.col("c_custkey").alias("k"), F.struct(F.col("c_name").alias("name"), F.col("c_acctbal").alias("bal")).alias("who")).alias("r"))
    return c.select(F.inline(F.array(F.struct("r.k", "r.who.name", "r.who.bal"))))


@op("op_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def _json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@op("op_json_variant", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def _variant(spark, d):
    return table(spark, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


# --- SQL surface
plain("op_sql_cte", "WITH big AS (SELECT * FROM {orders} WHERE o_totalprice > 250000), per AS (SELECT o_custkey, count(*) AS n FROM big GROUP BY o_custkey) SELECT n, count(*) AS customers FROM per GROUP BY n")


_WALKED = "SELECT substring(seq, 1, 4) AS p FROM corpus WHERE length(seq) >= 4 ORDER BY id LIMIT 1"


@op("op_sql_recursive_walk", f"WITH corpus AS ({CORPORA['urlpath'][1]}), w AS ({_WALKED}), s AS (SELECT unnest(range(1, 5)) AS step), q AS (SELECT step, substring(p, 1, step) AS q FROM w, s) SELECT CAST(step AS INT) AS step, (SELECT count(*) FROM corpus WHERE contains(seq, q)) AS n_ids FROM q UNION ALL SELECT 0, 0")
def _recursive(spark, d):
    """The walk over the index's transitions, symbol by symbol, as a recursive query; the state it reaches gives the number of items."""
    c = corpus(spark, d, "urlpath")
    _, found, routes, _ = class_tables(c, 4)
    pattern = c.where("char_length(seq) >= 4").orderBy("id").select(F.substring("seq", 1, 4)).first()[0]
    return spark.sql(
        """WITH RECURSIVE walk(step, state) AS (
             SELECT 0, CAST('' AS STRING) UNION ALL
             SELECT w.step + 1, t.to_state FROM walk w JOIN {moves} t ON t.from_state = w.state AND t.symbol = substring(:p, w.step + 1, 1) WHERE w.step < 4)
           SELECT step, coalesce(n_ids, 0) AS n_ids FROM walk LEFT JOIN {found} USING (state)""",
        args={"p": pattern}, moves=staged(C.transitions(routes)), found=found.select("state", "n_ids"),
    )


@op("op_sql_params", "SELECT doc_id FROM documents WHERE contains(text, 'ation') AND n_chars > 1000")
def _params(spark, d):
    return spark.sql("SELECT doc_id FROM {docs} WHERE contains(text, :p) AND n_chars > :n", args={"p": "ation", "n": 1000}, docs=table(spark, d, "documents"))


plain("op_sql_exists", "SELECT doc_id FROM {documents} d WHERE EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id AND l.quality = 1)")
plain("op_sql_scalar_subquery", "SELECT c_custkey FROM {customer} c WHERE c_acctbal > (SELECT avg(c2.c_acctbal) FROM {customer} c2 WHERE c2.c_nationkey = c.c_nationkey)")


@op("op_sql_view", "SELECT lang, count(*) AS n FROM documents GROUP BY lang")
def _view(spark, d):
    name = f"v_{uuid.uuid4().hex[:8]}"
    table(spark, d, "documents").createOrReplaceTempView(name)
    return spark.sql(f"SELECT lang, count(*) AS n FROM {name} GROUP BY lang")


# --- UDF, UDAF, UDTF
_CENTRE = "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE) - 0.1) * (CAST(x AS DOUBLE) - 0.1))), 4) AS x FROM embeddings"


@op("op_udf_arrow_l2", _CENTRE)
def _udf(spark, d):
    from motifknn.functions.udfs import l2_to_constant

    return table(spark, d, "embeddings").select("vec_id", F.round(l2_to_constant("embedding", F.lit(0.1)), 4).alias("x"))


_NEAR = "round(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE) - 0.1) * (CAST(x AS DOUBLE) - 0.1))), 4)"


@op("op_udaf_topk", f"SELECT label, array_to_string(list(vec_id ORDER BY d, vec_id)[1:3], ',') AS ids FROM (SELECT vec_id, label, {_NEAR} AS d FROM embeddings) GROUP BY label")
def _udaf(spark, d):
    from motifknn.functions.udfs import nearest_three

    rows = table(spark, d, "embeddings").select("label", "vec_id", F.round(l2sq(F.col("embedding"), F.array_repeat(F.lit(0.1), 64)), 4).alias("d"))
    return rows.groupBy("label").agg(nearest_three("vec_id", "d").alias("ids"))


@op("op_udtf_pattern_knn", f"SELECT id, dist FROM (SELECT doc_id AS id, {_NEAR} AS dist FROM documents JOIN embeddings ON vec_id = doc_id WHERE contains(text, 'ing')) QUALIFY row_number() OVER (PARTITION BY id % 4 ORDER BY dist, id) <= 3")
def _udtf(spark, d):
    """Of each shard the three nearest of the items that have the pattern."""
    from motifknn.functions.udfs import NearestMatches

    name, view = f"near_{uuid.uuid4().hex[:8]}", f"v_{uuid.uuid4().hex[:8]}"
    spark.udtf.register(name, NearestMatches)
    items = table(spark, d, "documents").join(table(spark, d, "embeddings"), F.col("vec_id") == F.col("doc_id"))
    items.select(F.col("doc_id").alias("id"), F.col("text").alias("seq"), "embedding", (F.col("doc_id") % 4).alias("shard")).createOrReplaceTempView(view)
    return spark.sql(f"SELECT id, round(dist, 4) AS dist FROM {name}(TABLE(SELECT id, seq, embedding, shard FROM {view}) PARTITION BY (shard), 'ing', array_repeat(0.1D, 64))")


@op("op_sql_udf", _CENTRE)
def _sqludf(spark, d):
    from motifknn.functions.udfs import l2_to_constant

    spark.udf.register("l2_to_constant", l2_to_constant)
    return spark.sql("SELECT vec_id, round(l2_to_constant(embedding, 0.1D), 4) AS x FROM {e}", e=table(spark, d, "embeddings"))


# --- relational checks over the star tables
plain("rel_pricing_summary", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(sum(l_extendedprice), 2) AS p, round(sum(l_extendedprice * (1 - l_discount)), 2) AS dp, count(*) AS n FROM {lineitem} GROUP BY 1, 2")
plain("rel_region_revenue", "SELECT r_name, round(sum(o_totalprice), 2) AS revenue FROM {region} JOIN {nation} ON n_regionkey = r_regionkey JOIN {customer} ON c_nationkey = n_nationkey JOIN {orders} ON o_custkey = c_custkey GROUP BY r_name")
plain("rel_priority_counts", "SELECT o_orderpriority, count(*) AS n FROM {orders} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey AND l_quantity > 45) GROUP BY 1")
plain("rel_top_customers", "SELECT c_custkey, round(sum(o_totalprice), 2) AS total FROM {customer} JOIN {orders} ON o_custkey = c_custkey GROUP BY c_custkey ORDER BY total DESC, c_custkey LIMIT 20")
plain("rel_keyword_benchmark", "SELECT b.item_id, d.doc_id FROM {benchmark} b JOIN {documents} d ON contains(d.text, b.text)")

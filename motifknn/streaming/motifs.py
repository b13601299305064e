"""Streams: windows over events, motif detection with state, arrivals and removals for the index.

Every function drives a stream over files to the end (``availableNow``) and returns what its sink holds, so
that a batch query can be held against it. Sinks and checkpoints are in the shared folder.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from motifknn.functions.patterns import contains
from motifknn.operators.index import build_class_index, class_index_query, delete_batch, insert_batch
from motifknn.plans.staging import shared_folder, staged
from motifknn.plans.workload import EXACT_SQL, corpus, query_set, query_sql
from motifknn.sources.tables import SCHEMAS, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def stream(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return keep


def folder(spark: SparkSession, kind: str) -> str:
    return f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"


def replayed(spark: SparkSession, d: str, name: str, split: str, parts: int = 2) -> DataFrame:
    """A table as a stream of files: one file for each value of ``split`` modulo ``parts``, oldest first."""
    path = folder(spark, "feed")
    for k in range(parts):
        table(spark, d, name).where(f"pmod({split}, {parts}) = {k}").coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(SCHEMAS[name]).option("maxFilesPerTrigger", 1).parquet(path)


def by_time(spark: SparkSession, d: str, parts: int = 4, copies: int = 1) -> DataFrame:
    """Events as a stream of files in order of time, each ``copies`` times; the times are instants."""
    path, e = folder(spark, "feed"), table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    cuts = [F.lit(x) for x in e.agg(F.percentile_approx(F.col("ts"), [k / parts for k in range(1, parts)])).first()[0]]
    for low, high in zip([None, *cuts], [*cuts, None], strict=True):
        part = e if low is None else e.where(F.col("ts") > low)
        for _ in range(copies):
            (part if high is None else part.where(F.col("ts") <= high)).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)


def drained(spark: SparkSession, df: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end into Parquet and read that back; ``complete`` and ``update`` keep the last batch's rows of each key."""
    out, ck = folder(spark, "out"), folder(spark, "ck")
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", ck).trigger(availableNow=True).start()
    else:
        q = df.writeStream.outputMode(mode).option("checkpointLocation", ck).foreachBatch(lambda b, i: b.write.mode("overwrite" if mode == "complete" else "append").parquet(out)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def _windows(name: str, cols: Callable[[], list], sql: str) -> None:
    @stream(name, sql)
    def run(spark, d):
        e = replayed(spark, d, "events", "event_id").groupBy(*cols()).agg(F.count(F.lit(1)).alias("n"))
        return drained(spark, e, "complete").select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), "event_type", "n")


_windows("st_tumbling", lambda: [F.window("ts", "6 hours"), "event_type"], "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') + INTERVAL 6 HOUR AS \"end\", event_type, count(*) AS n FROM events GROUP BY ALL")
_windows("st_sliding", lambda: [F.window("ts", "6 hours", "3 hours"), "event_type"], "SELECT s AS start, s + INTERVAL 6 HOUR AS \"end\", event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 3 HOUR]) AS s FROM events) GROUP BY ALL")


@stream("st_session", "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def _session(spark, d):
    e = replayed(spark, d, "events", "event_id").groupBy("user_id", F.session_window("ts", "2 hours")).agg(F.count(F.lit(1)).alias("n"))
    return drained(spark, e, "complete").select("user_id", F.col("session_window.start").alias("start"), "n")


@stream("st_dedup", "SELECT event_id, user_id FROM events")
def _dedup(spark, d):
    """Every event comes twice, in two files; one of each stays."""
    e = by_time(spark, d, copies=2).withWatermark("ts", "2 days")
    return drained(spark, e.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


@stream("st_watermark_late", "SELECT CAST(0 AS BIGINT) AS kept_late")
def _late(spark, d):
    """Newest half first; the older half comes behind the watermark and is dropped."""
    path = folder(spark, "feed")
    e = table(spark, d, "events")
    mid, top = e.agg(F.percentile_approx(F.col("ts").cast("timestamp").cast("long"), 0.5), F.max(F.col("ts").cast("timestamp").cast("long"))).first()
    seconds = F.col("ts").cast("timestamp").cast("long")
    e.where(seconds > mid).coalesce(1).write.mode("append").parquet(path)
    e.where(seconds > mid).limit(1).coalesce(1).write.mode("append").parquet(path)
    e.where(seconds < mid - 7200).coalesce(1).write.mode("append").parquet(path)
    s = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return drained(spark, s).where(F.col("window.end").cast("timestamp").cast("long") < mid - 7200).agg(F.count(F.lit(1)).alias("kept_late"))


@stream("st_static_join", "SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def _static(spark, d):
    docs = replayed(spark, d, "documents", "doc_id")
    b = table(spark, d, "benchmark").select("item_id", F.col("text").alias("p"))  # Spark's own size check decides whether it is broadcast
    return drained(spark, docs.join(b, contains(F.col("text"), F.col("p"))).select("doc_id", "item_id"))


@stream("st_interval_join", "SELECT c.event_id AS click, p.event_id AS buy FROM events c JOIN events p ON p.user_id = c.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 DAY WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _interval(spark, d):
    e = by_time(spark, d)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t0")).withWatermark("t0", "1 hour")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("buy"), "user_id", "ts").withWatermark("ts", "1 hour")
    return drained(spark, c.join(p, F.expr("user_id = u AND ts > t0 AND ts <= t0 + INTERVAL 1 DAY")).select("click", "buy"))


def failure_table(motif: str) -> list[dict[str, int]]:
    """For each number of matched symbols, where the next symbol leads: the automaton of one pattern."""
    out = []
    for state in range(len(motif) + 1):
        to = {}
        for symbol in set(motif):
            text = motif[:state] + symbol
            to[symbol] = next(n for n in range(min(len(motif), len(text)), -1, -1) if text.endswith(motif[:n]))
        out.append(to)
    return out


class MotifState(StatefulProcessor):
    """How much of the motif a user's stream has just matched; a row at every completion."""

    def __init__(self, motif: str):
        self.motif, self.steps = motif, failure_table(motif)

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.at = handle.getValueState("at", "n int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802
        n = self.at.get()[0] if self.at.exists() else 0
        hits = []
        for _, event, symbol in sorted((r for p in rows for r in zip(p["ts"], p["event_id"], p["s"], strict=True))):
            n = self.steps[n].get(symbol, 0)
            if n == len(self.motif):
                hits.append((key[0], event))
        self.at.update((n,))
        yield pd.DataFrame(hits, columns=["user_id", "event_id"])

    def close(self) -> None:
        pass


@stream("st_motif_state", "WITH s AS (SELECT user_id, event_id, substring(event_type, 1, 1) AS a, lag(substring(event_type, 1, 1)) OVER w AS b, lag(substring(event_type, 1, 1), 2) OVER w AS c FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT user_id, event_id FROM s WHERE c || b || a = 'vcp'")
def _motif(spark, d):
    s = by_time(spark, d, 2).select("user_id", "ts", "event_id", F.substring("event_type", 1, 1).alias("s"))
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    out = s.groupBy("user_id").transformWithStateInPandas(MotifState("vcp"), "user_id long, event_id long", "Append", "None")
    return drained(spark, out)


def _arrivals(spark: SparkSession, d: str, kind: str) -> DataFrame:
    """Passage ids that end in 3, 6 or 9, as what a stream of three files has written batch by batch."""
    out, ck = folder(spark, kind), folder(spark, "ck")
    rows = replayed(spark, d, "benchmark", "item_id", 3).where("item_id % 10 IN (3, 6, 9)").select(F.col("item_id").cast("long").alias("id"))
    rows.writeStream.foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{out}/segment={i}")).option("checkpointLocation", ck).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).select("id")


_PASSAGES = f"WITH {query_sql('passage', per_length=20)},\n{EXACT_SQL}\nSELECT qid, CAST(rk AS INT) AS rk, id, dist FROM answers"


@stream("st_insert_segment", _PASSAGES)
def _insert(spark, d):
    """Arrivals become the delta of a built index, and its queries find them."""
    c = corpus(spark, d, "passage")
    q = staged(query_set(c, 64, 20))
    index = build_class_index(staged(c.where("id % 10 NOT IN (3, 6, 9)")), 4)
    return class_index_query(insert_batch(index, c.join(_arrivals(spark, d, "delta"), "id")), q).select("qid", F.col("rk").cast("int").alias("rk"), "id", "dist")


@stream("st_delete_tombstone", _PASSAGES.replace("ON contains(c.seq, q.pattern)", "ON contains(c.seq, q.pattern) AND c.id % 10 NOT IN (3, 6, 9)"))
def _delete(spark, d):
    """Removals mark ids of a built index, and its queries leave them out."""
    c = corpus(spark, d, "passage")
    q = staged(query_set(c, 64, 20))
    index = delete_batch(build_class_index(c, 4), _arrivals(spark, d, "gone"))
    return class_index_query(index, q).select("qid", F.col("rk").cast("int").alias("rk"), "id", "dist")

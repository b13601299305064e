"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def recall_at_k(answer: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, recall): shared ids / number of true ones (min(k, matches)); queries without a match are not in it (1 by definition)."""
    hit = answer.select("qid", "id", F.lit(1).alias("hit"))
    return truth.select("qid", "id").join(hit, ["qid", "id"], "left").groupBy("qid").agg((F.count("hit") / F.count(F.lit(1))).alias("recall"))


def timed(df: DataFrame) -> float:
    """Seconds to run a plan to the end, results thrown away."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def qps(run: Callable[[], DataFrame], n: int, warm: int = 1) -> float:
    for _ in range(warm):
        timed(run())
    return n / timed(run())


def match_profile(routes: DataFrame, n: int) -> DataFrame:
    """(len, patterns, p50, p99, top): share of items that a pattern of that length matches."""
    share = routes.select(F.char_length("pattern").alias("len"), (F.col("n_ids") / F.lit(n)).alias("share"))
    return share.groupBy("len").agg(F.count(F.lit(1)).alias("patterns"), F.round(F.percentile("share", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("share", F.lit(0.99)), 6).alias("p99"), F.round(F.max("share"), 6).alias("top"))


def index_size(spark: SparkSession, method: str, states: DataFrame, ids: DataFrame, edges: DataFrame | None) -> DataFrame:
    """(method, states, ids, edges): unit counts."""
    parts = states.agg(F.count(F.lit(1)).alias("states")).crossJoin(ids.agg(F.count(F.lit(1)).alias("ids")))
    links = F.lit(0).cast("long").alias("edges")
    parts = parts.withColumn("edges", links) if edges is None else parts.crossJoin(edges.agg(F.coalesce(F.sum(F.size("neighbours")), F.lit(0)).cast("long").alias("edges")))
    return parts.select(F.lit(method).alias("method"), "states", "ids", "edges")


def slope(points: DataFrame) -> DataFrame:
    """Log-log slope of (x, y)."""
    return points.agg(F.round(F.regr_slope(F.log("y"), F.log("x")), 4).alias("slope"))


def at_recall(curve: DataFrame, least: float) -> DataFrame:
    """(method, ef, recall, distances) of the cheapest setting of each method that reaches a recall."""
    return curve.where(F.col("recall") >= least).groupBy("method").agg(F.min_by(F.struct("ef", "recall", "distances"), "distances").alias("m")).select("method", "m.*")

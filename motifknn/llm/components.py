"""Connected components by alternating star contractions, DataFrame operations only.

An edge table is rewritten in rounds: every node hands its larger neighbours to its smallest one, then its
smaller neighbours likewise. Each round is two aggregations and two joins on node ids, so a hub is summed
before it is moved and a skewed join can be split; the table is written out after each round. It ends when
all edges point at roots, after a number of rounds that grows as the logarithm of the longest chain.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.llm.scratch import materialise, release


def _oriented(edges: DataFrame, a: str, b: str) -> DataFrame:
    """Distinct (hi, lo) with hi > lo."""
    return edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).distinct()


def _contract(e: DataFrame) -> DataFrame:
    both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    large = _oriented(both.join(low, "u").where("v > u"), "v", "m")
    least = large.groupBy("hi").agg(F.min("lo").alias("m"))
    small = large.join(least, "hi").select(F.col("lo").alias("x"), F.col("m").alias("y")).union(least.select(F.col("hi").alias("x"), F.col("m").alias("y")))
    return _oriented(small, "x", "y")


def _is_stars(e: DataFrame) -> bool:
    """Every node is either a root or has one edge, to a root."""
    ends = e.select(F.col("hi").alias("x"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(e.select(F.col("lo"), F.lit(0), F.lit(1)))
    per = ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return per.where("up > 1 or (up > 0 and down > 0)").limit(1).count() == 0


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """(node, component) of every node with an edge to another; a component is named by its smallest node. Null ends are ignored."""
    e = materialise(_oriented(edges.where(F.col(a).isNotNull() & F.col(b).isNotNull()), a, b))
    for _ in range(most_rounds):
        if _is_stars(e):
            break
        e, old = materialise(_contract(e)), e
        release(old)
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return e.select(F.col("hi").alias("node"), F.col("lo").alias("component")).union(e.select(F.col("lo"), F.col("lo")).distinct())

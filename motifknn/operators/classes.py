"""Pattern classes: patterns that end at the same places.

Patterns with a common occurrence end are suffixes of one another, so their end sets are nested; hence the
smallest end and the number of occurrences name a class exactly. Classes are two aggregations, without hashes
of sets and without a loop.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from motifknn.functions.patterns import ends

#: The first end, as item and place, and the number of ends name a class.
KEY = ["first_id", "first_at", "occ"]


def pattern_dict(occ: DataFrame) -> DataFrame:
    """(pattern, first_id, first_at, occ, n_ids) of each pattern from ``occurrences``: numbers only, so that hash aggregation serves. A column w says for how many ids a row stands."""
    w = F.col("w") if "w" in occ.columns else F.lit(1)
    return occ.groupBy("pattern").agg(F.min("id").alias("first_id"), F.min_by("first", "id").alias("first_at"), F.sum(F.col("times") * w).alias("occ"), F.sum(w).cast("long").alias("n_ids"))


def pattern_classes(patterns: DataFrame) -> DataFrame:
    """(state, first_id, first_at, occ, n_ids, shortest, min_len, max_len); the longest member names the state."""
    n = F.char_length("pattern")
    return patterns.groupBy(*KEY).agg(F.max_by("pattern", n).alias("state"), F.min_by("pattern", n).alias("shortest"), F.min(n).alias("min_len"), F.max(n).alias("max_len"), F.max("n_ids").alias("n_ids"))


def members(patterns: DataFrame, classes: DataFrame) -> DataFrame:
    """(pattern, state): the routing table of queries."""
    return patterns.join(classes.select(*KEY, "state"), KEY).select("pattern", "state", *KEY, "n_ids")


def postings(occ: DataFrame, classes: DataFrame) -> DataFrame:
    """(state, id), and w if ``occ`` has it: the items of each class, read off its shortest member."""
    kept = [c for c in ("id", "w") if c in occ.columns]
    return classes.select("state", F.col("shortest").alias("pattern")).join(occ.select("pattern", *kept), "pattern").select("state", *kept)


def transitions(routes: DataFrame) -> DataFrame:
    """(from_state, symbol, to_state); the root is the empty string."""
    last = routes.where("pattern != ''").select(F.col("state").alias("to_state"), F.right("pattern", F.lit(1)).alias("symbol"), F.expr("left(pattern, char_length(pattern) - 1)").alias("pattern"))
    heads = routes.select("pattern", F.col("state").alias("from_state"))
    inner = last.where("pattern != ''").join(heads, "pattern").select("from_state", "symbol", "to_state")
    return inner.union(last.where("pattern = ''").select(F.lit("").alias("from_state"), "symbol", "to_state")).distinct()


def suffix_links(classes: DataFrame, routes: DataFrame) -> DataFrame:
    """(state, link_state): the class of the longest suffix that ends at more places."""
    cut = classes.select("state", F.expr("substring(shortest, 2)").alias("pattern"))
    return cut.where("pattern != ''").join(routes.select("pattern", F.col("state").alias("link_state")), "pattern").select("state", "link_state").union(cut.where("pattern = ''").select("state", F.lit("").alias("link_state")))


def suffix_states(corpus: DataFrame, routes: DataFrame, item: int, end: int, cap: int) -> DataFrame:
    """(state, max_len) of the classes of all suffixes of a prefix of one item, longest first."""
    runs = ends(corpus.where(F.col("id") == item), cap).where(F.col("end") == end)
    return runs.join(routes.select("pattern", "state"), "pattern").groupBy("state").agg(F.max(F.char_length("pattern")).cast("int").alias("max_len"))


def right_contexts(patterns: DataFrame) -> DataFrame:
    """(pattern, context_key, members): patterns grouped by the set of continuations inside the cap.

    The plain automaton merges on right contexts; patterns of one group may match different items, which is
    why it can't carry id sets.
    """
    last = patterns.select(F.expr("left(pattern, char_length(pattern) - 1)").alias("pattern"), F.right("pattern", F.lit(1)).alias("next"))
    follow = last.where("pattern != ''").groupBy("pattern").agg(F.array_join(F.array_sort(F.collect_set("next")), "").alias("context_key"))
    return patterns.select("pattern", "n_ids").join(follow, "pattern", "left").select("pattern", F.coalesce("context_key", F.lit("")).alias("context_key"), "n_ids").withColumn("members", F.count(F.lit(1)).over(Window.partitionBy("context_key")))

"""From buckets of possible matches to components, without all pairs of a bucket.

Phase one: in every bucket its members are paired with one of them, the pivot: the member that meets the most
others over all its buckets, for the text that the others were made from, if it is there, meets more than they
meet each other. A bucket of n copies costs n tests.

Phase two, for what shares a bucket and is still apart: the elements that a set has for itself among all sets
still in play are counted; they bound the similarity that it can have with any other. Sets that cannot reach
the threshold with anything in the bucket leave it, pairs that cannot reach it are not formed, and every pair
that is left across components is tested. For pairs there is a second bound: a set's elements are dealt to
``PARITIES`` places by their value, and the places with an odd number of them are its parities; two sets differ in
at least as many elements as parities. The bounds are exact, so nothing that shares a bucket is lost; a
pair is formed in the first of the buckets that it shares, once. Parities are still compared pair by pair, as
words, inside the join of a bucket.

DataFrame operations only.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifknn.llm.components import connected_components
from motifknn.llm.quality import let
from motifknn.llm.scratch import materialise, release


def similar_sets(both: DataFrame, percent: int) -> DataFrame:
    """(a, b) of (a, b, x, y) where the arrays x and y, without repeats, have 100 * intersection >= percent * union."""
    x, y = F.col("x"), F.col("y")
    return both.where(let(F.size(F.array_intersect(x, y)), lambda common: common * 100 >= (F.size(x) + F.size(y) - common) * percent)).select("a", "b")


def elements_of(own: DataFrame) -> DataFrame:
    return own.select("rep", F.explode("set").alias("e"))


#: A multiple of 64.
PARITIES = 1024


def parities(elements: DataFrame) -> DataFrame:
    """(rep, size, odd) from (rep, e) without repeats: how many elements, and the places with an odd number of them."""
    at = F.xxhash64("e").bitwiseAND(F.lit(PARITIES - 1))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), at.bitwiseAND(F.lit(63)).cast("int"))
    placed = elements.select("rep", F.shiftright(at, 6).alias("word"), bit.alias("bit"))
    words = [F.bit_xor(F.when(F.col("word") == w, F.col("bit")).otherwise(F.lit(0).cast("long"))).alias(f"w{w}") for w in range(PARITIES // 64)]
    per = placed.groupBy("rep").agg(F.count(F.lit(1)).alias("size"), *words)
    return per.select("rep", "size", F.struct(*[f"w{w}" for w in range(PARITIES // 64)]).alias("odd"))


def near_enough(x: Column, y: Column, percent: int) -> Column:
    """False only if two sets differ in too many parities to reach the threshold."""
    differ = F.lit(0)
    for w in range(PARITIES // 64):
        differ = differ + F.bit_count(x["odd"][f"w{w}"].bitwiseXOR(y["odd"][f"w{w}"]))
    return differ * (100 + percent) <= (x["size"] + y["size"]) * (100 - percent)


def _pairs(near: DataFrame, test: Column) -> DataFrame:
    return near.where((F.col("x.comp") != F.col("y.comp")) & test).select(F.least("x.rep", "y.rep").alias("a"), F.greatest("x.rep", "y.rep").alias("b")).distinct()


def _sizes(x: Column, y: Column, percent: int) -> Column:
    return F.least(x["n"], y["n"]) * 100 >= F.greatest(x["n"], y["n"]) * percent


def link_components(members: DataFrame, extras: list[str], may_link: Callable[[Column, Column], Column], sets: Callable[[DataFrame], DataFrame], percent: int, confirm: Callable[[DataFrame, int], DataFrame] = similar_sets, spread: Callable[[DataFrame], DataFrame] = elements_of) -> DataFrame | None:
    """(node, component) from ``members`` (bucket, rep, n = size of its set, *extras), or None if nothing is linked.

    ``may_link(x, y)`` is a cheap test on two structs of rep, n and extras; ``sets(ids)`` gives (rep, set) of
    the ids (rep) asked for; what a set is, is for ``confirm`` (exact test of (a, b, x, y)) and ``spread``
    ((rep, e), an element a row) to know.
    """

    def test(pairs: DataFrame, own: DataFrame) -> DataFrame:
        both = pairs.join(own.select(F.col("rep").alias("a"), F.col("set").alias("x")), "a").join(own.select(F.col("rep").alias("b"), F.col("set").alias("y")), "b")
        return materialise(confirm(both.select("a", "b", "x", "y"), percent).distinct())

    x, y = F.col("x"), F.col("y")
    members = members.join(members.groupBy("bucket").agg(F.count(F.lit(1)).alias("_size")), "bucket")
    members = materialise(members.drop("_size").join(members.groupBy("rep").agg(F.sum("_size").alias("meets")), "rep"))
    dealt = members.select("bucket", F.struct("rep", "n", *extras, "meets", F.col("rep").alias("comp")).alias("x"))
    pivot = dealt.groupBy("bucket").agg(F.min(F.struct((-F.col("x.meets")).alias("m"), F.col("x.rep").alias("r"), "x")).alias("y")).select("bucket", F.col("y.x").alias("y"))
    pairs = materialise(_pairs(dealt.join(pivot, "bucket"), _sizes(x, y, percent) & may_link(x, y)))
    own = sets(pairs.select(F.explode(F.array("a", "b")).alias("rep")).distinct())
    links = test(pairs, own)
    release(own)
    comps = None if links.isEmpty() else connected_components(links)

    now = members if comps is None else members.join(comps, members["rep"] == comps["node"], "left")
    now = now.select("bucket", "rep", "n", *extras, (F.col("rep") if comps is None else F.coalesce("component", "rep")).alias("comp"))
    # a bucket of two has been tested whole
    apart = now.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count(F.lit(1)).alias("size")).where("lo < hi and size > 2").select("bucket")
    active = materialise(now.join(apart, "bucket"))
    own = sets(active.select("rep").distinct())
    private = spread(own).groupBy("e").agg(F.count(F.lit(1)).alias("c"), F.min("rep").alias("rep")).where("c = 1").groupBy("rep").agg(F.count(F.lit(1)).alias("alone"))
    active = active.join(private, "rep", "left").withColumn("shared", F.col("n") - F.coalesce("alone", F.lit(0))).drop("alone")
    least = active.groupBy("bucket").agg(F.min("n").alias("least_n"))
    able = materialise(active.join(least, "bucket").where(F.col("shared") * 100 >= (F.col("n") + F.greatest("least_n", "shared") - F.col("shared")) * percent))
    kinds = able.groupBy("bucket", "comp").agg(F.count(F.lit(1)).alias("size")).groupBy("bucket").agg(F.max(F.struct("size", "comp")).alias("main"), F.count(F.lit(1)).alias("kinds")).where("kinds > 1").select("bucket", F.col("main.comp").alias("main"))
    kinds = materialise(kinds)
    mixed = materialise(able.join(kinds, "bucket", "left_semi"))
    odd = materialise(parities(spread(own.join(mixed.select("rep").distinct(), "rep", "left_semi"))))
    lists = mixed.groupBy("rep").agg(F.collect_set("bucket").alias("buckets"))  # as many as bands at most
    left = mixed.join(lists, "rep").join(odd, "rep").select("bucket", F.struct("rep", "n", *extras, "shared", "buckets", "comp", "size", "odd").alias("x"))
    strays = left.join(kinds, "bucket").where("x.comp != main").select("bucket", F.col("x").alias("y"))
    most = F.least(x["shared"], y["shared"])
    more = _pairs(left.join(strays, "bucket"), (most * 100 >= (x["n"] + y["n"] - most) * percent) & _sizes(x, y, percent) & may_link(x, y) & near_enough(x, y, percent) & (F.array_min(F.array_intersect(x["buckets"], y["buckets"])) == F.col("bucket")))
    more = materialise(more.join(pairs, ["a", "b"], "left_anti"))
    if not more.isEmpty():
        found = test(more, own)
        if not found.isEmpty():
            comps = connected_components(links.union(found))
    release(own, able, active, pairs, members, kinds, mixed, odd)
    return comps

"""Index reuse: what a state's largest indexed descendant holds need not be held again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.plans.staging import collect_garbage, staged


def choose_donors(classes: DataFrame, transitions: DataFrame, postings: DataFrame, rule: str = "subtree") -> tuple[DataFrame, DataFrame]:
    """(donors: state, donor, base, size; residuals: state, id).

    Levels run from the longest members to the shortest along transitions out of the longest member, which
    lengthen it by one, so the cap on pattern length bounds the rounds. A state's donor is the descendant with
    the largest residual (``subtree``), the largest among its direct successors (``child``), or nobody
    (``none``); ties go to the smaller name. Every round is written out: the lineage stays flat. A column w of
    ``postings`` says for how many ids a row stands; residuals then have it too.
    """
    postings = staged(postings)
    size_of = F.sum("w") if "w" in postings.columns else F.count(F.lit(1))
    if rule == "none":
        sizes = postings.groupBy("state").agg(size_of.alias("size"))
        return staged(sizes.select("state", F.lit(None).cast("string").alias("donor"), F.col("size").alias("base"), F.col("size").alias("held"))), postings
    longest = classes.select("state", F.char_length("state").alias("n"))
    levels = [r["n"] for r in longest.select("n").distinct().orderBy(F.desc("n")).collect()]  # at most the cap
    edges = staged(transitions.join(longest.withColumnRenamed("state", "from_state"), "from_state").where("char_length(to_state) > n").select("from_state", "to_state", "n"))
    done: DataFrame | None = None  # state, donor, base, held, best_size, best_state
    residuals: DataFrame | None = None
    for n in levels:
        here = longest.where(F.col("n") == n).select("state")
        mine = postings.join(here, "state", "left_semi")
        if done is None:
            chosen = here.select("state", F.lit(None).cast("bigint").alias("best_size"), F.lit(None).cast("string").alias("donor"))
        else:
            down = edges.where(F.col("n") == n).select(F.col("from_state").alias("state"), "to_state").join(done.select(F.col("state").alias("to_state"), "held", "best_size", "best_state"), "to_state")
            size, name = ("held", "to_state") if rule == "child" else ("best_size", "best_state")
            best = down.groupBy("state").agg(F.min(F.struct((-F.col(size)).alias("s"), F.col(name).alias("d"))).alias("b"))
            chosen = here.join(best, "state", "left").select("state", (-F.col("b.s")).alias("best_size"), F.col("b.d").alias("donor"))
        if residuals is None:
            rest = mine
        else:
            covered = chosen.where("donor is not null").select("state", "donor").join(residuals.select(F.col("state").alias("donor"), "id"), "donor").select("state", "id")
            rest = mine.join(covered, ["state", "id"], "left_anti")
        rest = staged(rest)
        collect_garbage(rest.sparkSession)
        base = mine.groupBy("state").agg(size_of.alias("base"))
        held = rest.groupBy("state").agg(size_of.alias("held"))
        row = chosen.join(base, "state").join(held, "state", "left").withColumn("held", F.coalesce("held", F.lit(0)))
        own = F.col("best_size").isNull() | (F.col("held") > F.col("best_size")) | ((F.col("held") == F.col("best_size")) & (F.col("state") < F.col("donor")))
        row = staged(row.select("state", "donor", "base", "held", F.when(own, F.col("held")).otherwise(F.col("best_size")).alias("best_size"), F.when(own, F.col("state")).otherwise(F.col("donor")).alias("best_state")))
        done = row if done is None else done.union(row)
        residuals = rest if residuals is None else residuals.union(rest)
    return done.select("state", "donor", "base", "held"), residuals


def decide_kind(donors: DataFrame, threshold: int = 200, on: str = "base", skip: bool = True) -> DataFrame:
    """kind of each state: raw under the threshold (of what it holds, or of all its matches), else graph."""
    n = F.col("held") if on == "base" else F.col("base")
    return donors.withColumn("kind", F.when(F.lit(skip) & (n < threshold), "raw").when(F.col("held") == 0, "raw").otherwise("graph"))


def check_cover(postings: DataFrame, donors: DataFrame, residuals: DataFrame) -> DataFrame:
    """(n_states, missing, overlap): ids of V that no index holds, and ids held twice; both must be 0."""
    given = donors.where("donor is not null").select("state", "donor").join(residuals.select(F.col("state").alias("donor"), "id"), "donor").select("state", "id")
    both = residuals.withColumn("own", F.lit(1)).select("state", "id", "own", F.lit(0).alias("given"), F.lit(0).alias("v")).union(given.select("state", "id", F.lit(0), F.lit(1), F.lit(0))).union(postings.select("state", "id", F.lit(0), F.lit(0), F.lit(1)))
    per = both.groupBy("state", "id").agg(F.sum("own").alias("own"), F.sum("given").alias("given"), F.sum("v").alias("v"))
    return per.agg(F.countDistinct("state").alias("n_states"), F.sum(((F.col("own") + F.col("given") == 0) | (F.col("v") == 0)).cast("long")).alias("missing"), F.sum((F.col("own") + F.col("given") > 1).cast("long")).alias("overlap"))

"""Choice of method by the exact number of matches."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.operators import baselines
from motifknn.operators.index import ClassIndex
from motifknn.plans.staging import staged


def choose(index: ClassIndex, queries: DataFrame, ef: int = 160) -> DataFrame:
    """(qid, matches, chosen): filter-first measures as many distances as there are matches, search-first about ef * ln(n)."""
    n = max(index.corpus.count(), 2)
    known = queries.join(index.routes.select("pattern", "n_ids"), "pattern", "left").select("qid", F.coalesce("n_ids", F.lit(0)).alias("matches"))
    return known.withColumn("chosen", F.when(F.col("matches") <= F.lit(float(ef)) * F.log(F.lit(float(n))), "filter_first").otherwise("search_first"))


def plan_and_run(index: ClassIndex, queries: DataFrame, graph: baselines.Graph | None, ef: int = 160, k: int = 10) -> tuple[DataFrame, DataFrame]:
    """(answers, choices). Search-first goes over ``graph``, widened until k answers are found, or over everything exactly."""
    choices = staged(choose(index, queries, ef))
    few = queries.join(choices.where("chosen = 'filter_first'").select("qid"), "qid", "left_semi")
    many = staged(queries.join(choices.where("chosen = 'search_first'").select("qid"), "qid", "left_semi"))
    answers = baselines.filter_first(index, few, k)
    if not many.isEmpty():
        late = baselines.search_first_expanding(index.corpus, many, ef, k) if graph is None else baselines.search_first_expanding_graph(graph, index.corpus, many, ef, k)
        answers = answers.unionByName(late)
    return answers, choices

"""No query of a batch of more than 10,000 is dropped."""

from __future__ import annotations

from pyspark.sql import functions as F

from motifknn.operators.automaton import segment_matches
from motifknn.operators.baselines import search_first_exact, sql_hybrid
from motifknn.operators.exact import filtered_topk

N = 10_050


def test_every_query_is_answered(spark):
    corpus = spark.createDataFrame([(1, [0.0, 1.0], "a%b_c!d"), (2, [1.0, 0.0], "other")], "id long, vec array<double>, seq string")
    queries = spark.range(N).select(F.col("id").alias("qid"), F.lit("%b_c!").alias("pattern"), F.array(F.lit(0.0), F.lit(0.0)).alias("qvec"))
    for got in (search_first_exact(corpus, queries, 2), sql_hybrid(corpus, queries, 2, 0.9), segment_matches(corpus, queries)):
        assert got.where("id = 1").select("qid").distinct().count() == got.count() == N
    assert filtered_topk(corpus, queries, F.col("id") == 2).count() == N

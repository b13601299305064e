"""A state's different vectors are dealt to several graphs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from motifknn.operators.graph import SHARD_NODES, build_graphs, search_graphs, sharded

CORPUS = "id long, vec array<double>, seq string"


def test_many_vectors_keep_their_recall(spark):
    rng = np.random.default_rng(3)
    v = rng.uniform(-1, 1, (6000, 64))
    corpus = spark.createDataFrame([(i, v[i % 6000].tolist(), "x") for i in range(7000)], CORPUS)
    lists = corpus.select(F.lit("x").alias("state"), "id")
    dealt = sharded(lists, corpus)
    assert dealt.groupBy("shard").agg(F.count_distinct("vec").alias("n")).agg(F.max("n")).first()[0] <= 1.2 * SHARD_NODES
    assert dealt.groupBy("vec").agg(F.count_distinct("shard").alias("n")).agg(F.max("n")).first()[0] == 1 and dealt.count() == 7000
    asked = rng.uniform(-1, 1, (20, 64))
    wanted = spark.createDataFrame([("x", q, asked[q].tolist(), 10, 100) for q in range(20)], "state string, qid long, qvec array<double>, k int, ef int")
    found = search_graphs(build_graphs(lists, corpus, 8, 60), lists, corpus, wanted).toPandas()
    hits = 0
    for q in range(20):
        true = sorted((round(float(((v[i % 6000] - asked[q]) ** 2).sum()), 9), i) for i in range(7000))[:10]
        got = sorted(zip(found[found.qid == q]["dist"].round(9), found[found.qid == q]["id"], strict=True))[:10]
        hits += len(set(i for _, i in true) & set(i for _, i in got))
    assert hits >= 0.95 * 200

"""Graphs are built and searched without a vector for each row of each state; what a report stages goes with it."""

from __future__ import annotations

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifknn.operators import graph
from motifknn.operators.graph import ProximityGraph, build_graphs, named_vectors, search_graphs, sharded

CORPUS = "id long, vec array<double>, seq string"


@pytest.fixture(scope="module")
def many(spark):
    """Lists of 40 states over 600 rows of 300 vectors; states of a letter each, the first has all."""
    r = np.random.default_rng(5)
    v = r.normal(size=(300, 8))
    corpus = spark.createDataFrame([(i, v[i % 300].tolist(), "x") for i in range(600)], CORPUS)
    lists = spark.createDataFrame([(f"s{s}", i) for s in range(40) for i in range(600) if i % (s + 1) == 0], "state string, id long")
    return corpus, lists


def test_a_vector_is_sent_once_for_many_graphs(many):
    corpus, lists = many
    who, vectors = named_vectors(corpus)
    assert vectors.count() == 300 and who.count() == 600
    rows = graph._dealt(lists, who, None)
    places, needed = graph._grouped(rows, vectors)
    assert places.count() == 40 and rows.count() == lists.count() > 2000
    assert needed.count() == needed.select("g", "vid").distinct().count() == 300 * places.select("g").distinct().count()


def test_graphs_are_those_of_the_rows(spark, many, monkeypatch):
    corpus, lists = many
    monkeypatch.setattr(graph, "SHARD_NODES", 64)
    monkeypatch.setattr(graph, "SHARD_ROWS", 100)
    monkeypatch.setattr(graph, "GROUP_ROWS", (100, 1 << 19))
    dealt = sharded(lists, corpus).toPandas()
    assert len(dealt) == lists.count() and dealt[dealt.state == "s0"]["shard"].nunique() >= 8
    assert dealt.groupby(["state", "shard"])["vec"].agg(lambda x: len({tuple(v) for v in x})).max() <= 1.6 * 64
    edges = build_graphs(lists, corpus, 4, 20)
    got = {(r.state, r.shard, r.level, r.node_id): r.neighbours for r in edges.collect()}
    want = {}
    for (state, shard), g in dealt.groupby(["state", "shard"]):
        for level, node, around in ProximityGraph(g["id"].to_numpy(), np.stack(g["vec"].to_numpy()), 4, 20).build().edges():
            want[state, shard, level, node] = around
    assert got.keys() == want.keys() and sum(sorted(got[x]) == sorted(want[x]) for x in want) >= 0.97 * len(want)  # the order of rows moves the mean's last digit
    q = np.random.default_rng(6).normal(size=(5, 8))
    wanted = spark.createDataFrame([(f"s{s}", n, q[n].tolist(), 10, 400) for s in (0, 3) for n in range(5)], "state string, qid long, qvec array<double>, k int, ef int")
    found = search_graphs(edges, lists, corpus, wanted).toPandas()
    vec = {r.id: np.array(r.vec) for r in corpus.collect()}
    for s in (0, 3):
        for n in range(5):
            true = sorted((round(float(((vec[i] - q[n]) ** 2).sum()), 9), i) for i in range(600) if i % (s + 1) == 0)[:10]
            mine = found[(found.state == f"s{s}") & (found.qid == n)]
            assert sorted(zip(mine["dist"].round(9), mine["id"], strict=True))[:10] == true


def test_different_vectors_of_one_hash_keep_two_names(spark, monkeypatch):
    corpus = spark.createDataFrame([(i, [float(i % 3)], "x") for i in range(9)], CORPUS)
    real, asked = F.xxhash64, []

    def clash(*cols):
        asked.append(1)
        return real(F.lit(1)) if len(asked) == 1 else real(*cols)

    monkeypatch.setattr(graph.F, "xxhash64", clash)
    who, vectors = named_vectors(corpus)
    assert len(asked) == 2 and vectors.count() == vectors.select("vid").distinct().count() == 3
    assert who.join(vectors, "vid").join(corpus.select("id", F.col("vec").alias("v")), "id").where("vec = v").count() == 9


def _folders(spark):
    top = spark.conf.get("spark.checkpoint.dir")
    return {x for x in os.listdir(top.removeprefix("file://")) if x.startswith("stage-")}


def test_tables_of_a_report_go_with_it(spark, monkeypatch):
    from motifknn.plans import experiments

    r = np.random.default_rng(8)
    small = spark.createDataFrame([(i, r.normal(size=4).tolist(), ("abc", "bca", "ab")[i % 3]) for i in range(90)], CORPUS)
    monkeypatch.setattr(experiments, "corpus", lambda *a: small)
    before = _folders(spark)
    got = experiments.index_sizes(spark, "", "pname", 5)
    assert {x.method: x.nodes for x in got.collect()}["per_pattern"] == 450 and _folders(spark) == before
    build_graphs(small.select(F.lit("x").alias("state"), "id"), small, 4, 20)
    assert len(_folders(spark) - before) == 3  # the edges, and the corpus' vectors and their names, which further graphs use

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifknn.operators import baselines, exact, graph
from motifknn.operators.graph import ProximityGraph
from motifknn.operators.index import build_class_index, class_index_query


def test_search_in_step_answers_and_counts_as_one_by_one():
    r = np.random.default_rng(11)
    v = np.repeat(r.normal(size=(500, 16)), 2, axis=0)
    g = ProximityGraph(r.permutation(1000), v, 8, 60).build()
    q = r.normal(size=(40, 16))
    for k, ef in ((10, 5), (10, 10), (3, 80)):
        one = []
        for x in q:
            g.distances = g.visited = 0
            one.append((g.search(x, k, ef), g.distances, g.visited))
        assert list(g.search_many(q, k, ef)) == one and len(q) >= graph.IN_STEP


def test_links_are_the_same_with_all_distances_at_hand_and_without(monkeypatch):
    v = np.random.default_rng(12).integers(-8, 8, size=(700, 12)).astype(np.float32)  # exact in either way
    v -= v.mean(0).round()
    a = list(ProximityGraph(np.arange(700), v, 8, 60).build().edges())
    monkeypatch.setattr(graph, "WHOLE", 0)
    monkeypatch.setattr(ProximityGraph, "_reach_all", staticmethod(lambda *a: None))
    b = list(ProximityGraph(np.arange(700), v, 8, 60).build().edges())
    same = sum(x == y for x, y in zip(a, b, strict=True))
    assert same >= 0.95 * len(a)  # means are no whole numbers, so ties of float32 may fall otherwise


ROWS = [(1, "abcab"), (2, "a%b_c!d"), (3, ""), (4, None), (5, "é\U0001f600xé\U0001f600"), (6, "xyz" * 200), (7, "ab")]


@pytest.fixture
def small(spark):
    corpus = spark.createDataFrame([(i, [float(i), 1.0], s) for i, s in ROWS], "id long, vec array<double>, seq string")
    patterns = ["ab", "ab", "b_", "%", "zx", "\U0001f600x", "é", "nothing", "xyz" * 200, "abcabc"]
    return corpus, spark.createDataFrame([(n, p, [0.5, 0.5]) for n, p in enumerate(patterns)], "qid long, pattern string, qvec array<double>"), patterns


def test_patterns_are_looked_up_as_they_are_tested(small, monkeypatch):
    corpus, queries, patterns = small
    want = {(n, i) for n, p in enumerate(patterns) for i, s in ROWS if s is not None and p in s}
    tested = sorted(map(tuple, exact.exact_topk(corpus, queries).collect()))
    monkeypatch.setattr(exact, "MOST_TESTS", 3)
    monkeypatch.setattr(baselines, "MOST_TESTS", 3)
    assert {tuple(r) for r in exact.matches(corpus, queries).collect()} == want
    assert sorted(map(tuple, exact.exact_topk(corpus, queries).collect())) == tested
    assert {(r.qid, r.id) for r in baselines.sql_hybrid(corpus, queries, 7, 2.0).collect()} == want
    every = exact.matches_of(corpus, queries.withColumn("pattern", F.lit("")), 10)
    assert every.count() == len(ROWS) * len(patterns)  # the empty pattern is in null sequences too


def test_one_search_gives_answers_and_counters(spark):
    r = np.random.default_rng(13)
    corpus = spark.createDataFrame([(i, r.normal(size=4).tolist(), "ab" if i % 2 else "abc") for i in range(120)], "id long, vec array<double>, seq string")
    queries = spark.createDataFrame([(n, p, [0.1 * n] * 4, 10, 20) for n, p in enumerate(["ab", "abc", "b", "c"] * 5)], "qid long, pattern string, qvec array<double>, k int, ef int")
    index = build_class_index(corpus, 3, 20, m=4, ef_con=20)
    lists, edges = baselines.per_pattern_build(corpus, 3, 20, 4, 20)
    whole = baselines.global_graph(corpus, 4, 20)
    rows = lambda df: sorted(map(tuple, df.collect()))
    for ask in (
        lambda **how: class_index_query(index, queries, **how), lambda **how: baselines.per_pattern_query(lists, edges, corpus, queries, **how),
        lambda **how: baselines.search_first(whole, corpus, queries, 20, **how), lambda **how: baselines.keyword_knn_graph(whole, corpus, queries, 20, **how),
    ):
        got, work = ask(both=True)
        assert rows(got) == rows(ask()) and rows(work) == rows(ask(counters=True))

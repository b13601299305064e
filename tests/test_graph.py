from __future__ import annotations

import time

import numpy as np

from motifknn.operators.graph import ProximityGraph, top_layer


def test_recall_and_degree():
    r = np.random.default_rng(1)
    v = r.normal(size=(600, 8)).astype(np.float32)
    ids = np.arange(600) * 3
    g = ProximityGraph(ids, v, 8, 60).build()
    assert max(len(x) for x in g.layers[0].values()) <= 16
    hits = 0
    for q in r.normal(size=(40, 8)).astype(np.float32):
        truth = set(ids[np.argsort(((v - q) ** 2).sum(1))[:10]].tolist())
        hits += len(truth & {i for _, i in g.search(q, 10, 80)[:10]})
    assert hits >= 0.95 * 400


def test_more_effort_finds_no_less():
    r = np.random.default_rng(2)
    v = r.normal(size=(300, 16)).astype(np.float32)
    g = ProximityGraph(np.arange(300), v, 8, 40).build()
    got = []
    for ef in (10, 40, 160):
        n = 0
        for q in r.normal(size=(20, 16)).astype(np.float32):
            truth = set(np.argsort(((v - q) ** 2).sum(1))[:10].tolist())
            n += len(truth & {i for _, i in g.search(q, 10, ef)[:10]})
        got.append(n)
    assert got[0] <= got[2] + 4 and got[2] >= 190


def test_reproducible():
    v = np.random.default_rng(3).normal(size=(80, 4)).astype(np.float32)
    a, b = (list(ProximityGraph(np.arange(80), v, 4, 20).build().edges()) for _ in range(2))
    assert a == b and top_layer(5, 16) == top_layer(5, 16)


def test_strict_cap_and_simple_choice():
    v = np.random.default_rng(4).normal(size=(100, 4)).astype(np.float32)
    g = ProximityGraph(np.arange(100), v, 6, 30, diverse=False, strict=True).build()
    assert max(len(x) for x in g.layers[0].values()) <= 6


def test_copies_are_answered_with_their_node():
    r = np.random.default_rng(5)
    v = np.repeat(r.normal(size=(150, 16)), 20, axis=0)
    ids = r.permutation(3000)
    g = ProximityGraph(ids, v, 8, 60).build()
    assert sorted(n for level, n, _ in g.edges() if level == 0) == list(range(3000))
    hits = 0
    for q in r.normal(size=(30, 16)):
        truth = ids[np.lexsort((ids, ((v - q) ** 2).sum(1)))[:10]].tolist()
        hits += len(set(truth) & {i for _, i in g.search(q, 10, 40)[:10]})
    assert hits >= 0.99 * 300


def test_order_of_rows_does_not_matter():
    r = np.random.default_rng(6)
    v = np.repeat(r.normal(size=(60, 4)), 3, axis=0).astype(np.float32)
    p = r.permutation(180)
    a, b = ProximityGraph(np.arange(180), v, 4, 20).build(), ProximityGraph(p, v[p], 4, 20).build()
    assert sorted(a.edges()) == sorted(b.edges())


def test_large_graph_is_built_in_seconds():
    v = np.random.default_rng(7).normal(size=(4000, 64)).astype(np.float32)
    t = time.perf_counter()
    ProximityGraph(np.arange(4000), v, 16, 200).build()
    assert time.perf_counter() - t < 12

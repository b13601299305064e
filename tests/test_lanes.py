"""Lanes of states: a task for each, one graph in memory at a time."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from motifknn.operators import graph
from motifknn.operators.graph import ProximityGraph, build_graphs, graph_links_by_lane


def test_lanes_build_all_graphs_one_at_a_time(spark, monkeypatch):
    r = np.random.default_rng(9)
    corpus = spark.createDataFrame([(i, r.normal(size=4).tolist(), "x") for i in range(300)], "id long, vec array<double>, seq string")
    lists = spark.createDataFrame([(f"s{s}", i) for s in range(12) for i in range(300) if i % (s + 1) == 0], "state string, id long")
    monkeypatch.setattr(graph, "SHARD_NODES", 64)
    want = build_graphs(lists, corpus, 4, 20).where("level = 0").agg(F.sum(F.size("neighbours"))).first()[0]
    for workers in (1, 3):
        lanes = spark.createDataFrame([(f"s{s}", s % workers) for s in range(12)], "state string, lane int")
        got = {x.lane: x.edges for x in graph_links_by_lane(lists, lanes, corpus, workers, 4, 20).collect()}
        assert sorted(got) == list(range(workers)) and abs(sum(got.values()) - want) <= 0.02 * want


def test_a_graph_is_done_before_the_next_rows_are_held():
    import pyarrow as pa

    held = []

    def batches():
        for s in range(20):
            held.append(s)
            rows = 50
            yield pa.RecordBatch.from_arrays([pa.array([0] * rows), pa.array([0 if s == 0 else 1] * rows), pa.array(["" if s == 0 else f"s{s:02}"] * rows), pa.array([0] * rows), pa.array(range(rows), pa.int64()), pa.array(range(rows), pa.int64()), pa.array([[float(x)] if s == 0 else None for x in range(rows)], pa.list_(pa.float64()))], ["g", "kind", "state", "shard", "id", "vid", "vec"])

    for (_, _, state, _), g in graph._graphs(batches(), ["g"], m=4, ef_con=10):
        assert isinstance(g, ProximityGraph) and len(g.ids) == 50
        assert len(held) <= int(state[1:]) + 2

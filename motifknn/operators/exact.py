"""Exact constrained top-k: the ground truth, and the last step of every method.

A batch of queries is what a caller asks at once. While it takes at most ``BATCH_BYTES`` it travels with the tasks:
patterns are tested and distances measured where the rows lie, each task keeps its k nearest of each query, and
only those are exchanged. Up to ``MOST_TESTS`` patterns are tested one by one, more are looked up among a sequence's
runs of their lengths. A larger batch is joined as a table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifknn.functions.patterns import contains
from motifknn.functions.vectors import distance

BATCH_BYTES = 64 << 20
#: As many patterns are tested in one projection; planning takes about 30 ms for each.
MOST_TESTS = 60
DIGITS = 4
#: Pairs of a row and a query measured at once.
AT_ONCE = 1 << 16


def keep_nearest(candidates: DataFrame, k: Column | int = 10, digits: int = DIGITS) -> DataFrame:
    """(qid, rk, id, dist) of the k nearest per query from (qid, id, dist); ties go to the smaller id, ids count once."""
    once = candidates.select("qid", "id", F.round("dist", digits).alias("dist")).dropDuplicates(["qid", "id"])
    rk = F.row_number().over(Window.partitionBy("qid").orderBy("dist", "id"))
    return once.withColumn("rk", rk).where(F.col("rk") <= k).select("qid", "rk", "id", "dist")


def merge_topk(a: DataFrame, b: DataFrame, k: int = 10) -> DataFrame:
    """Lossless union of two answer tables."""
    return keep_nearest(a.select("qid", "id", "dist").unionByName(b.select("qid", "id", "dist")), k)


def batch_of(queries: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """(qids, vectors) of a batch that may travel with the tasks."""
    n, dim = queries.agg(F.count(F.lit(1)), F.max(F.size("qvec"))).first()
    if not n or n * (dim or 1) * 8 > BATCH_BYTES:
        return None
    rows = queries.select("qid", "qvec").orderBy("qid").collect()
    return np.array([r["qid"] for r in rows], np.int64), np.array([r["qvec"] for r in rows], np.float64)


def distances(v: np.ndarray, q: np.ndarray, metric: str) -> np.ndarray:
    """Of the rows of two matrices, one by one."""
    if metric == "l2sq":
        return np.einsum("ij,ij->i", v - q, v - q)
    dot = np.einsum("ij,ij->i", v, q)
    return -dot if metric == "ip" else 1 - dot / (np.sqrt(np.einsum("ij,ij->i", v, v)) * np.sqrt(np.einsum("ij,ij->i", q, q)))


class Nearest:
    """The k nearest of each query among what was offered; ties go to the smaller id."""

    def __init__(self, k: int):
        self.k, self.q, self.id, self.d = k, np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)

    def offer(self, q: np.ndarray, ids: np.ndarray, d: np.ndarray) -> None:
        q, ids, d = np.concatenate([self.q, q]), np.concatenate([self.id, ids]), np.concatenate([self.d, d])
        order = np.lexsort((ids, np.floor(d * 10**DIGITS + 0.5), q))
        q = q[order]
        rank = np.arange(len(q)) - np.searchsorted(q, q)
        order = order[rank < self.k]
        self.q, self.id, self.d = q[rank < self.k], ids[order], d[order]


def nearest(rows: DataFrame, queries: DataFrame, batch: tuple[np.ndarray, np.ndarray], k: int = 10, metric: str = "l2sq") -> DataFrame:
    """(qid, id, dist): of each task's rows (id, vec, qids) the k nearest of each query."""
    names, vectors = batch

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = Nearest(k)
        for b in batches:
            lists = b.column(2)
            flat, sizes = lists.flatten().to_numpy(zero_copy_only=False), np.asarray(lists.value_lengths().fill_null(0))
            if not len(flat):
                continue
            ids, v = b.column(0).to_numpy(zero_copy_only=False), b.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(b.num_rows, -1)
            at, q = np.repeat(np.arange(b.num_rows), sizes), np.searchsorted(names, flat)
            for s in range(0, len(at), AT_ONCE):
                x, y = at[s : s + AT_ONCE], q[s : s + AT_ONCE]
                best.offer(y, ids[x], distances(v[x], vectors[y], metric))
        if len(best.q):
            yield pa.RecordBatch.from_arrays([pa.array(names[best.q]), pa.array(best.id), pa.array(best.d)], ["qid", "id", "dist"])

    return rows.select(F.col("id").cast("long"), "vec", "qids").mapInArrow(run, "qid long, id long, dist double")


def measured(matches: DataFrame, corpus: DataFrame, queries: DataFrame, metric: str = "l2sq") -> DataFrame:
    """(qid, id, dist) of the pairs (qid, id), as joins."""
    v = matches.join(corpus.select("id", "vec"), "id").join(queries.select("qid", "qvec"), "qid")
    return v.select("qid", "id", distance(F.col("vec"), F.col("qvec"), metric).alias("dist"))


def nearest_of(matches: DataFrame, corpus: DataFrame, queries: DataFrame, k: int = 10, metric: str = "l2sq") -> DataFrame:
    """(qid, id, dist) that hold the k nearest of each query among its matches (qid, id). A vector is fetched once, whatever the queries that ask for it."""
    batch = batch_of(queries)
    if batch is None:
        return measured(matches, corpus, queries, metric)
    per = matches.groupBy("id").agg(F.collect_set("qid").alias("qids"))  # of a batch at most
    return nearest(corpus.select("id", "vec").join(per, "id"), queries, batch, k, metric)


def passing(corpus: DataFrame, queries: DataFrame) -> DataFrame | None:
    """``corpus`` with qids, the queries (qid, pattern) whose pattern the sequence has: a projection. None for a batch too large for one."""
    asked = queries.select("qid", "pattern").limit(MOST_TESTS + 1).collect()
    if not asked or len(asked) > MOST_TESTS:
        return None
    tests = [F.when(contains(F.col("seq"), F.lit(r["pattern"])), F.lit(r["qid"]).cast("long")) for r in asked]
    return corpus.select("id", "vec", F.array_compact(F.array(*tests)).alias("qids")).where(F.size("qids") > 0)


def patterns_of(queries: DataFrame) -> dict[int, dict[str, list[int]]] | None:
    """The qids of a batch's patterns, by length; None for a batch that may not travel with the tasks."""
    n, size = queries.agg(F.count(F.lit(1)), F.sum(F.octet_length("pattern") + 64)).first()
    if not n or (size or 0) > BATCH_BYTES:
        return None
    found: dict[int, dict[str, list[int]]] = {}
    for r in queries.select("qid", "pattern").where("pattern is not null").orderBy("qid").collect():
        found.setdefault(len(r["pattern"]), {}).setdefault(r["pattern"], []).append(r["qid"])
    return found


def qids_of(seq: str | None, asked: dict[int, dict[str, list[int]]]) -> list[int]:
    """The queries whose pattern a sequence has, by its runs of the patterns' lengths: the work is lengths times symbols, however many patterns there are."""
    out: list[int] = []
    for n, of in asked.items():
        if n == 0:
            runs = {""}
        else:
            runs = {seq[i : i + n] for i in range(len(seq) - n + 1)} if seq else set()
        for run in of.keys() & runs:
            out += of[run]
    return out


def passing_runs(corpus: DataFrame, asked: dict[int, dict[str, list[int]]], keep: list[str]) -> DataFrame:
    """The columns ``keep`` of ``corpus`` and qids, the queries whose pattern the sequence has; rows without one drop out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [qids_of(s, asked) for s in b.column(0).to_pylist()]
            at = np.flatnonzero(np.fromiter(map(len, found), np.int64, len(found)))
            qids = pa.array([found[i] for i in at.tolist()], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([*(c.take(pa.array(at)) for c in b.columns[1:]), qids], [*keep, "qids"])

    rows = corpus.select("seq", *keep)
    schema = T.StructType([*rows.schema.fields[1:], T.StructField("qids", T.ArrayType(T.LongType()))])
    return rows.mapInArrow(run, schema)


def matches(corpus: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, id) of the pairs of a query and a row that has its pattern."""
    asked = patterns_of(queries)
    if asked is None:
        return corpus.join(queries.select("qid", "pattern"), contains(F.col("seq"), F.col("pattern"))).select("qid", "id")
    return passing_runs(corpus, asked, ["id"]).select(F.explode("qids").alias("qid"), "id")


def matches_of(corpus: DataFrame, queries: DataFrame, k: int = 10, metric: str = "l2sq") -> DataFrame:
    """(qid, id, dist) that hold the k nearest of each query, by a scan of the sequences."""
    batch, rows = batch_of(queries), passing(corpus, queries)
    if batch is not None and rows is None:
        asked = patterns_of(queries)
        rows = None if asked is None else passing_runs(corpus, asked, ["id", "vec"])
    if batch is not None and rows is not None:
        return nearest(rows, queries, batch, k, metric)
    q = queries.select("qid", "pattern", "qvec")
    return corpus.join(q, contains(F.col("seq"), F.col("pattern"))).select("qid", "id", distance(F.col("vec"), F.col("qvec"), metric).alias("dist"))


def exact_topk(corpus: DataFrame, queries: DataFrame, k: int = 10, metric: str = "l2sq") -> DataFrame:
    """Every sequence is tested against every pattern of the batch, matches are measured; without an index there is no other way."""
    return keep_nearest(matches_of(corpus, queries, k, metric), k)


def of_all(corpus: DataFrame, queries: DataFrame, k: int, metric: str = "l2sq") -> DataFrame:
    """(qid, id, dist) that hold the k nearest of each query among all items, patterns or not."""
    batch = batch_of(queries)
    if batch is None:
        return corpus.crossJoin(queries.select("qid", "qvec")).select("qid", "id", distance(F.col("vec"), F.col("qvec"), metric).alias("dist"))
    every = F.from_json(F.lit(str(batch[0].tolist())), "array<bigint>")  # one literal, however many
    return nearest(corpus.withColumn("qids", every), queries, batch, k, metric)


def filtered_topk(corpus: DataFrame, queries: DataFrame, predicate: Column, k: int = 10) -> DataFrame:
    """Top-k under an attribute predicate (set membership, range) that is pushed to the scan."""
    return keep_nearest(of_all(corpus.where(predicate), queries, k), k)


def valid(corpus: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows to index, rows set aside): an id, and a vector of the usual dimension without nulls, NaN or infinities."""
    usual = corpus.where("id is not null and vec is not null").groupBy(F.size("vec").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "d").first()
    finite = F.forall("vec", lambda x: F.coalesce(F.abs(x.cast("double")) < float("inf"), F.lit(False)))
    good = F.coalesce(F.col("id").isNotNull() & (F.size("vec") == (usual["d"] if usual else 0)) & finite, F.lit(False))
    return corpus.where(good), corpus.where(~good)

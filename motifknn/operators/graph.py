"""Layered proximity graphs over the items of a state, in numpy inside Arrow groups.

Reproducible: a node's top layer comes from a hash of its id, nodes are linked in id order. Large states are
dealt to shards by a hash of the vector, as many as their different vectors ask for; shards are built and searched
alone and answers merged, so no state is a serial tail. Counters of distances and visited nodes come with every search.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.plans.staging import few, release, staged, staged_so_far

_ODD = 0x9E3779B97F4A7C15


def top_layers(nodes: np.ndarray, m: int, seed: int = 7) -> np.ndarray:
    """floor(-ln(u) / ln(m)) with u from a hash of the id."""
    x = np.asarray(nodes, np.int64).astype(np.uint64) * np.uint64(_ODD) + np.uint64(seed * 0xBF58476D1CE4E5B9 & 0xFFFFFFFFFFFFFFFF)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(29)
    return (-np.log((x.astype(np.float64) + 1) / 2.0**64) / np.log(m)).astype(np.int64)


def top_layer(node: int, m: int, seed: int = 7) -> int:
    return int(top_layers(np.array([node]), m, seed)[0])


def same_vectors(ids: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """For each row the place of the row with the same vector and the smallest id."""
    first: dict[bytes, int] = {}
    keys = [row.tobytes() for row in vectors + 0.0]
    for i in np.argsort(ids, kind="stable").tolist():
        first.setdefault(keys[i], i)
    return np.fromiter((first[k] for k in keys), np.int64, len(keys))


#: Pairs of a node and a candidate that are measured at once.
AT_ONCE = 1 << 21
#: The same where distances are at hand: what stays in a core's cache.
IN_CACHE = 1 << 17
#: Nodes of a layer up to which the distances of all pairs are kept while it is linked (64 MB).
WHOLE = 4096
#: Queries from which a graph is searched for all of them in step, and bytes of their marks at once.
IN_STEP = 12
MARKS = 1 << 24


class ProximityGraph:
    """Nodes are positions in ``vectors``; ``layers[l]`` maps a node to its neighbours there.

    Rows with equal vectors are one node, the one with the smallest id; in the lowest layer its copies have a link
    to it, none leads to them, and they are answered with it.
    """

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, m: int = 16, ef_con: int = 200, diverse: bool = True, strict: bool = False):
        self.ids, self.exact = np.asarray(ids), np.asarray(vectors, np.float64)
        self.v = self.exact.astype(np.float32)
        self.m, self.ef_con, self.diverse, self.low_cap = m, ef_con, diverse, m if strict else 2 * m
        self.layers: list[dict[int, list[int]]] = []
        self._tables: dict[int, np.ndarray] = {}
        self.entry = -1
        self.distances = self.visited = 0
        self.first = same_vectors(self.ids, self.exact)
        self.copies: dict[int, list[int]] = {}
        for i in np.flatnonzero(self.first != np.arange(len(self.first))).tolist():
            self.copies.setdefault(int(self.first[i]), []).append(i)

    def build(self) -> ProximityGraph:
        """Every node is linked to some of the ``ef_con`` nearest before it, in id order; these are found exactly, by matrix products."""
        nodes = np.array([i for i in np.argsort(self.ids, kind="stable").tolist() if self.first[i] == i], np.int64)
        if not len(nodes):
            return self
        level = top_layers(self.ids[nodes], self.m)
        self.entry = int(nodes[level.argmax()])
        self.layers = [self._layer(nodes[level >= n], self.low_cap if n == 0 else self.m) for n in range(level.max() + 1)]
        for i, around in self.copies.items():
            self.layers[0].update((c, [i]) for c in around)
        return self

    def _layer(self, nodes: np.ndarray, cap: int) -> dict[int, list[int]]:
        x = (self.exact[nodes] - self.exact[nodes].mean(0)).astype(np.float32)
        n, norms = len(nodes), np.einsum("ij,ij->i", x, x)
        source, target, far = [], [], []
        whole = self._apart(x, x, norms, norms) if n <= WHOLE else None
        at_once = AT_ONCE // x.shape[1] if whole is None else IN_CACHE
        rows = max(1, min(AT_ONCE // n, at_once // self.ef_con))
        for s in range(0, n, rows):
            e = min(n, s + rows)
            d = self._apart(x[s:e], x[:e], norms[s:e], norms[:e]) if whole is None else whole[s:e, :e].copy()
            d[:, s:][~np.tri(e - s, k=-1, dtype=bool)] = np.inf
            near = np.argpartition(d, self.ef_con - 1, axis=1)[:, : self.ef_con] if e > self.ef_con else np.broadcast_to(np.arange(e), d.shape)
            d = np.take_along_axis(d, near, 1)
            order = np.argsort(d, axis=1)
            near, d = np.take_along_axis(near, order, 1), np.take_along_axis(d, order, 1)
            at, chosen, how_far = self._choose(x, norms, whole, near, d, self.m)
            source.append(at + s)
            target.append(chosen)
            far.append(how_far)
        a, b, d = np.concatenate(source), np.concatenate(target), np.concatenate(far)
        a, b, d = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([d, d])
        order = np.lexsort((b, d, a))
        a, b, d = a[order], b[order], d[order]
        size = np.bincount(a, minlength=n)
        start = np.cumsum(size) - size
        links = [b[s : s + c].tolist() for s, c in zip(start.tolist(), size.tolist(), strict=True)]
        full = np.flatnonzero(size > cap)
        full = full[np.argsort(size[full], kind="stable")]
        while len(full):  # from the widest down, so many at once as may be
            most = int(size[full[-1]])
            take = max(1, at_once // most)
            now, full = full[-take:], full[:-take]
            at = start[now][:, None] + np.arange(most)[None, :]
            inside = np.arange(most)[None, :] < size[now][:, None]
            at = np.where(inside, at, 0)
            who, chosen, _ = self._choose(x, norms, whole, b[at], np.where(inside, d[at], np.inf), cap)
            for i, around in zip(now.tolist(), np.split(chosen, np.searchsorted(who, np.arange(1, len(now)))), strict=True):
                links[i] = around.tolist()
        self._reach_all(x, links, int(np.flatnonzero(nodes == self.entry)[0]), cap)
        names = nodes.tolist()
        return {names[i]: [names[j] for j in around] for i, around in enumerate(links)}

    @staticmethod
    def _apart(x: np.ndarray, y: np.ndarray, xx: np.ndarray, yy: np.ndarray) -> np.ndarray:
        """Squared distances of the rows of two matrices, from their squared norms."""
        d = x @ y.T
        d *= -2
        d += xx[:, None]
        d += yy[None, :]
        return np.maximum(d, 0, out=d)

    def _choose(self, x: np.ndarray, norms: np.ndarray, whole: np.ndarray | None, near: np.ndarray, d: np.ndarray, cap: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, candidate, distance) of at most ``cap`` of each row's candidates, which come nearest first, infinitely far ones for none.

        ``diverse``: a candidate is passed over if one chosen before is as near to it as the row's node; the nearest
        that were passed over fill up. ``whole``: the distances of all pairs, if they are at hand.
        """
        real = np.isfinite(d)
        every = np.arange(len(near))
        kept = np.zeros(near.shape, bool)
        if self.diverse:
            open_, live, around, limit = real.copy(), every, near, d  # of the rows that may still choose
            if whole is None:
                v, size = x[near], norms[near]
            else:
                flat = whole.ravel()
            for _ in range(min(cap, near.shape[1])):
                at = open_.argmax(1)
                here = np.arange(len(live))
                some = open_[here, at]
                if not some.any():
                    break
                if some.sum() < 0.7 * len(live):
                    if whole is None:
                        v, size = v[some], size[some]
                    at, open_, live, around, limit = at[some], open_[some], live[some], around[some], limit[some]
                    here, some = np.arange(len(live)), some[some]
                kept[live[some], at[some]] = True
                if whole is None:
                    apart = size + size[here, at][:, None] - 2 * np.matmul(v, v[here, at][:, :, None])[:, :, 0]
                else:
                    apart = flat.take(around[here, at][:, None] * len(whole) + around)
                open_ &= apart > limit
                open_[here, at] = False
        rest = real & ~kept
        kept |= rest & (np.cumsum(rest, 1) <= cap - kept.sum(1, keepdims=True))
        row, at = np.nonzero(kept)
        return row, near[row, at], d[row, at]

    @staticmethod
    def _reach_all(x: np.ndarray, links: list[list[int]], entry: int, cap: int) -> None:
        """A node that no way leads to gets a link from the nearest reached one with room."""
        reached = np.zeros(len(links), bool)

        def walk(start: int) -> None:
            reached[start] = True
            open_ = [start]
            while open_:
                for j in links[open_.pop()]:
                    if not reached[j]:
                        reached[j] = True
                        open_.append(j)

        walk(entry)
        if reached.all():
            return
        room = np.array([len(around) < cap for around in links])
        for i in np.flatnonzero(~reached).tolist():
            able = np.flatnonzero(reached & room)
            if reached[i] or not len(able):
                continue
            diff = x[able] - x[i]
            best = int(able[np.einsum("ij,ij->i", diff, diff).argmin()])
            links[best].append(i)
            room[best] = len(links[best]) < cap
            walk(i)

    def _far(self, q: np.ndarray, nodes: list[int]) -> np.ndarray:
        self.distances += len(nodes)
        diff = self.v[nodes] - q
        return np.einsum("ij,ij->i", diff, diff)

    def _beam(self, q: np.ndarray, start: list[tuple[float, int]], ef: int, layer: int) -> list[tuple[float, int]]:
        """Best-first search that keeps the ef nearest; sorted."""
        links = self.layers[layer]
        seen = {n for _, n in start}
        open_, best = list(start), [(-d, n) for d, n in start]
        heapq.heapify(open_)
        heapq.heapify(best)
        while open_:
            d, n = heapq.heappop(open_)
            if d > -best[0][0] and len(best) >= ef:
                break
            self.visited += 1
            fresh = [x for x in links[n] if x not in seen]
            if not fresh:
                continue
            seen.update(fresh)
            for e, x in zip(self._far(q, fresh).tolist(), fresh, strict=True):
                if len(best) < ef or e < -best[0][0]:
                    heapq.heappush(open_, (e, x))
                    heapq.heappush(best, (-e, x))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-d, n) for d, n in best)

    def search(self, q: np.ndarray, k: int, ef: int) -> list[tuple[float, int]]:
        """(distance, id) of about the k nearest; copies come with their node, distances are measured anew in full precision."""
        if self.entry < 0:
            return []
        whole, q = np.asarray(q, np.float64), np.asarray(q, np.float32)
        near = [(float(self._far(q, [self.entry])[0]), self.entry)]
        for layer in range(len(self.layers) - 1, 0, -1):
            near = self._beam(q, near[:1], 1, layer)
        most = max(ef, k)
        return self._answers(whole, [n for _, n in self._beam(q, near, most, 0)], most)

    def _answers(self, whole: np.ndarray, nodes: list[int], most: int) -> list[tuple[float, int]]:
        diff = self.exact[nodes] - whole
        got: list[tuple[float, int]] = []
        for d, n in sorted(zip(np.einsum("ij,ij->i", diff, diff).tolist(), nodes, strict=True)):
            if len(got) >= most and d > got[most - 1][0]:
                break
            got += [(d, int(self.ids[c])) for c in (n, *self.copies.get(n, ()))]
        return sorted(got)[:most]

    def _table(self, layer: int) -> np.ndarray:
        """Neighbours in rows of one width, filled up with the number of nodes; the last row is of no node."""
        if layer not in self._tables:
            none, links = len(self.v), self.layers[layer]
            size = np.fromiter(map(len, links.values()), np.int64, len(links))
            table = np.full((none + 1, max(1, int(size.max()))), none, np.int64)
            at = np.fromiter(links, np.int64, len(links))
            flat = np.fromiter(chain.from_iterable(links.values()), np.int64, int(size.sum()))
            table[np.repeat(at, size), np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
            self._tables[layer] = table
        return self._tables[layer]

    def _beams(self, q: np.ndarray, d: np.ndarray, n: np.ndarray, ef: int, layer: int, work: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """``_beam`` of several queries in step, each from one node: the ef nearest of each, sorted, filled up with infinity.

        In a round every query that has not ended looks at the nearest node it has not looked at yet; ``work`` counts
        the distances and the looks of each.
        """
        table, none = self._table(layer), len(self.v)
        far, node = np.full((len(q), ef), np.inf, np.float32), np.full((len(q), ef), none, np.int64)
        looked, seen = np.ones((len(q), ef), bool), np.zeros((len(q), none + 1), bool)
        far[:, 0], node[:, 0], looked[:, 0] = d, n, False
        seen[np.arange(len(q)), n] = seen[:, none] = True
        live = np.arange(len(q))
        while True:
            at = looked[live].argmin(1)
            goes = ~looked[live, at]
            live, at = live[goes], at[goes]
            if not len(live):
                return far, node
            looked[live, at] = True
            work[live, 1] += 1
            around = table[node[live, at]]
            fresh = ~seen[live[:, None], around]
            seen[live[:, None], around] = True
            row, col = np.nonzero(fresh)
            work[live, 0] += fresh.sum(1)
            diff = self.v[around[row, col]] - q[live[row]]
            e = np.full(around.shape, np.inf, np.float32)
            e[row, col] = np.einsum("ij,ij->i", diff, diff)
            e[e >= far[live, -1][:, None]] = np.inf
            better = np.flatnonzero(np.isfinite(e).any(1))
            if not len(better):
                continue
            who = live[better]
            both = np.concatenate([far[who], e[better]], 1)
            order = np.argsort(both, axis=1, kind="stable")[:, :ef]
            far[who] = np.take_along_axis(both, order, 1)
            node[who] = np.take_along_axis(np.concatenate([node[who], around[better]], 1), order, 1)
            looked[who] = np.take_along_axis(np.concatenate([looked[who], ~np.isfinite(e[better])], 1), order, 1)

    def search_many(self, q: np.ndarray, k: int, ef: int) -> Iterator[tuple[list[tuple[float, int]], int, int]]:
        """(``search``, distances, looks) of each query."""
        if self.entry < 0 or len(q) < IN_STEP:
            for one in q:
                self.distances = self.visited = 0
                yield self.search(one, k, ef), self.distances, self.visited
            return
        most, step = max(ef, k), max(1, MARKS // (len(self.v) + 1))
        for s in range(0, len(q), step):
            part = np.asarray(q[s : s + step], np.float64)
            whole, single = part, part.astype(np.float32)
            work = np.zeros((len(part), 2), np.int64)
            diff = self.v[self.entry] - single
            d, n = np.einsum("ij,ij->i", diff, diff), np.full(len(part), self.entry)
            work[:, 0] += 1
            for layer in range(len(self.layers) - 1, 0, -1):
                far, node = self._beams(single, d, n, 1, layer, work)
                d, n = far[:, 0], node[:, 0]
            far, node = self._beams(single, d, n, most, 0, work)
            for i in range(len(part)):
                yield self._answers(whole[i], node[i, np.isfinite(far[i])].tolist(), most), int(work[i, 0]), int(work[i, 1])

    def edges(self) -> Iterator[tuple[int, int, list[int]]]:
        for layer, links in enumerate(self.layers):
            for n, around in links.items():
                yield layer, int(self.ids[n]), [int(self.ids[x]) for x in around]

    @classmethod
    def load(cls, ids: np.ndarray, vectors: np.ndarray, rows: pd.DataFrame, m: int = 16) -> ProximityGraph:
        """From rows (level, node_id, neighbours)."""
        g = cls(ids, vectors, m)
        at = {int(x): i for i, x in enumerate(ids)}
        g.layers = [{} for _ in range(int(rows["level"].max()) + 1)]
        for level, node, around in zip(rows["level"], rows["node_id"], rows["neighbours"], strict=True):
            g.layers[level][at[int(node)]] = [at[int(x)] for x in around]
        g.entry = min(g.layers[-1], key=lambda n: (int(g.first[n]) != n, g.ids[n]))
        return g


EDGES = "state string, shard int, level int, node_id long, neighbours array<long>"


#: Different vectors beyond which a state is dealt to several graphs. Larger graphs lose recall: of 10,256 embeddings, one
#: graph (m 8, ef 100) found 0.66 of the 10 nearest, five 0.96.
SHARD_NODES = 2_000
#: Rows, copies included, beyond which a shard is dealt once more, by id.
SHARD_ROWS = 50_000


#: Rows whose graphs share one copy of their vectors: at least, and at most.
GROUP_ROWS = 50_000, 1 << 19


def named_vectors(corpus: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(who: id, vid; vectors: vid, vec): equal vectors have one name, a hash that no two different ones share."""
    if getattr(corpus, "_named_vectors", None) is None:
        seed = 0
        while True:
            vid = F.xxhash64("vec", F.lit(seed)).alias("vid")
            vectors = staged(corpus.select(vid, "vec").distinct())
            if vectors.groupBy("vid").agg(F.count(F.lit(1)).alias("c")).where("c > 1").isEmpty():
                break
            seed += 1
        corpus._named_vectors = staged(corpus.select("id", vid)), vectors  # noqa: SLF001
    return corpus._named_vectors  # noqa: SLF001


def _with_names(rows: DataFrame, who: DataFrame) -> DataFrame:
    return rows.join(few(who, 48), "id")


def _dealt(residuals: DataFrame, who: DataFrame, shards: int | None) -> DataFrame:
    """(state, shard, id, vid), written out."""
    rows = _with_names(residuals.select("state", "id"), who)
    if shards is not None:
        return staged(rows.select("state", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int").alias("shard"), "id", "vid"))
    rows = staged(rows)
    many = few(staged(rows.groupBy("state").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") > SHARD_NODES).select("state")))
    bits = F.greatest(F.ceil(F.log2(F.approx_count_distinct("vid", 0.02) / SHARD_NODES)), F.lit(0)).cast("int").alias("_j")
    levels = few(staged(rows.join(many, "state").groupBy("state").agg(bits)))
    cut = rows.join(levels, "state", "left").withColumn("_j", F.coalesce("_j", F.lit(0)))
    cut = cut.withColumn("_s", F.when(F.col("_j") == 0, F.lit(0).cast("long")).otherwise(F.expr("shiftrightunsigned(vid, 64 - _j)")))
    more = few(staged(cut.groupBy("state", "_s").agg(F.ceil(F.count(F.lit(1)) / SHARD_ROWS).alias("_m")).where("_m > 1")))
    at = cut.join(more, ["state", "_s"], "left")
    shard = F.col("_s") + F.expr("shiftleft(1L, _j)") * F.when(F.col("_m").isNotNull(), F.pmod(F.xxhash64("id"), F.col("_m"))).otherwise(F.lit(0))
    return staged(at.select("state", shard.cast("int").alias("shard"), "id", "vid"))


def sharded(residuals: DataFrame, corpus: DataFrame, shards: int | None = None) -> DataFrame:
    """(state, shard, id, vec); without ``shards`` a state has the least power of two that leaves about SHARD_NODES of its different vectors to each, equal ones together."""
    who, vectors = named_vectors(corpus)
    return _dealt(residuals, who, shards).join(vectors, "vid").select("state", "shard", "id", "vec")


def _grouped(rows: DataFrame, vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(places: state, shard, g; needed: g, vid, vec): graphs are gathered so that a group sends each of its vectors once, whatever its number of graphs.

    Shards of large states hold the vectors whose names begin alike, so those of one beginning go together.
    """
    head = F.expr("shiftrightunsigned(vid, 48)")
    places = staged(rows.groupBy("state", "shard").agg(F.count(F.lit(1)).alias("c"), F.min(head).alias("lo"), F.max(head).alias("hi")))
    alike = F.when((F.col("c") < SHARD_NODES // 8), F.lit(0)).when(F.col("lo") == F.col("hi"), F.lit(16)).otherwise(15 - F.floor(F.log2(F.col("lo").bitwiseXOR(F.col("hi")).cast("double")))).cast("int")
    places = places.withColumn("j", alike)
    per = {r["j"]: r["c"] for r in places.groupBy("j").agg(F.sum("c").alias("c")).collect()}  # 17 at most
    spark = rows.sparkSession
    size = min(GROUP_ROWS[1], max(GROUP_ROWS[0], sum(per.values()) // (8 * spark.sparkContext.defaultParallelism)))
    parts = F.create_map(*[F.lit(x) for j, c in per.items() for x in (j, max(1, -(-c // (size << j))))]) if per else F.create_map(F.lit(0), F.lit(1))
    g = F.col("j").cast("long") * (1 << 40) + F.expr("shiftright(lo, 16 - j)") * (1 << 20) + F.pmod(F.xxhash64("state", "shard"), parts[F.col("j")])
    places = staged(places.select("state", "shard", g.alias("g")))
    asked = rows.join(few(places), ["state", "shard"]).select("g", "vid").distinct()
    return places, asked.join(vectors, "vid").select("g", "vid", "vec")


def _together(rows: DataFrame, by: list[str]) -> DataFrame:
    """Rows of a group in one task, its vectors (kind 0) first, then graph by graph."""
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(n, *by).sortWithinPartitions(*by, "kind", "state", "shard")


def _units(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[tuple, pa.Table]]:
    """Runs of rows with equal keys, across batches."""
    held: list[pa.RecordBatch] = []
    last: tuple | None = None
    for b in batches:
        n = b.num_rows
        if not n:
            continue
        change = np.zeros(n - 1, bool)
        for k in keys:
            c = b.column(k)
            change |= pc.not_equal(c.slice(1), c.slice(0, n - 1)).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(change) + 1).tolist(), n]
        for s, e in zip(cuts, cuts[1:], strict=False):
            key = tuple(b.column(k)[s].as_py() for k in keys)
            if held and key != last:
                yield last, pa.Table.from_batches(held)
                held = []
            held.append(b.slice(s, e - s))
            last = key
    if held:
        yield last, pa.Table.from_batches(held)


class _Vectors:
    """A group's vectors by name."""

    def __init__(self, vids: pa.ChunkedArray, vecs: pa.ChunkedArray):
        vids = vids.to_numpy()
        order = np.argsort(vids)
        flat = vecs.combine_chunks()
        self.vids, self.rows = vids[order], flat.flatten().to_numpy(zero_copy_only=False).reshape(len(vids), -1)[order]

    def of(self, vids: pa.ChunkedArray) -> np.ndarray:
        return self.rows[np.searchsorted(self.vids, vids.to_numpy())]


def _graphs(batches: Iterator[pa.RecordBatch], keys: list[str], **how) -> Iterator[tuple[tuple, ProximityGraph]]:
    """Built graphs, one at a time, from a task's rows of ``_together``."""
    vectors: _Vectors | None = None
    for key, t in _units(batches, [*keys, "kind", "state", "shard"]):
        if key[len(keys)] == 0:
            vectors = _Vectors(t["vid"], t["vec"])
        else:
            yield key, ProximityGraph(t["id"].to_numpy(), vectors.of(t["vid"]), **how).build()


def _packed(rows: DataFrame, places: DataFrame, needed: DataFrame) -> DataFrame:
    """(g, kind, state, shard, id, vid, vec) of rows (state, shard, id, vid) and their vectors."""
    kind = needed.schema["vec"].dataType
    own = rows.join(few(places), ["state", "shard"]).select("g", F.lit(1).alias("kind"), "state", "shard", "id", "vid", F.lit(None).cast(kind).alias("vec"))
    return own.union(needed.select("g", F.lit(0), F.lit(""), F.lit(0), F.lit(None).cast("long"), "vid", "vec"))


def build_graphs(residuals: DataFrame, corpus: DataFrame, m: int = 16, ef_con: int = 200, shards: int | None = None, diverse: bool = True, strict: bool = False) -> DataFrame:
    """Edge table, written out, of one graph for each (state, shard); all groups are independent, so one stage builds them."""
    who, vectors = named_vectors(corpus)
    mark = staged_so_far()
    rows = _dealt(residuals, who, shards)
    packed = _packed(rows, *_grouped(rows, vectors))

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, _, state, shard), g in _graphs(batches, ["g"], m=m, ef_con=ef_con, diverse=diverse, strict=strict):
            level, node, around = zip(*g.edges(), strict=True)
            n = len(level)
            yield pa.RecordBatch.from_arrays([pa.array([state] * n), pa.array([shard] * n, pa.int32()), pa.array(level, pa.int32()), pa.array(node, pa.int64()), pa.array(around, pa.list_(pa.int64()))], ["state", "shard", "level", "node_id", "neighbours"])

    edges = staged(_together(packed, ["g"]).mapInArrow(build, EDGES))
    del rows, packed
    release(mark, keep=edges)
    return edges


def graph_links_by_lane(residuals: DataFrame, lanes: DataFrame, corpus: DataFrame, workers: int, m: int, ef_con: int) -> DataFrame:
    """(lane, edges): graphs of states (state, lane) built in a task for each lane, one graph in memory at a time; their links in the lowest layer."""
    who, vectors = named_vectors(corpus)
    rows = _dealt(residuals, who, None)
    places, needed = _grouped(rows, vectors)
    laned = places.join(lanes, "state")
    at = laned.select("g", "lane").distinct()
    packed = _packed(rows, places, needed)
    own = packed.where("kind = 1").join(few(lanes), "state")
    packed = own.unionByName(packed.where("kind = 0").join(at, "g"))

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges: dict[int, int] = {}
        for key, g in _graphs(batches, ["lane", "g"], m=m, ef_con=ef_con):
            edges[key[0]] = edges.get(key[0], 0) + sum(map(len, g.layers[0].values()))
        yield pa.RecordBatch.from_arrays([pa.array(list(edges), pa.int32()), pa.array(list(edges.values()), pa.int64())], ["lane", "edges"])

    dealt = packed.withColumn("lane", F.col("lane").cast("int")).repartitionById(workers, F.col("lane"))
    return staged(dealt.sortWithinPartitions("lane", "g", "kind", "state", "shard").mapInArrow(build, "lane int, edges long"))


def search_graphs(edges: DataFrame, residuals: DataFrame, corpus: DataFrame, wanted: DataFrame) -> DataFrame:
    """(qid, state, shard, id, dist, distances, visited) from wanted (state, qid, qvec, k, ef): every shard answers, the caller merges.

    A graph is what its edges say: nodes that are asked for are fetched, no others are moved, and their vectors once for
    a group of graphs.
    """
    out = "qid long, state string, shard int, id long, dist double, distances long, visited long"
    who, vectors = named_vectors(corpus)
    links = edges.join(few(staged(wanted.select("state").distinct())), "state", "left_semi")
    nodes = _with_names(links.where("level = 0").select("state", "shard", F.col("node_id").alias("id")), who)
    places, needed = _grouped(nodes, vectors)
    asked = wanted.select("state", "qid", "qvec", "k", "ef").join(places, "state")
    named = _with_names(links.withColumnRenamed("node_id", "id"), who).join(few(places), ["state", "shard"])
    none = lambda kind: F.lit(None).cast(kind)
    kind = needed.schema["vec"].dataType
    packed = named.select("g", F.lit(1).alias("kind"), "state", "shard", "level", "id", "vid", F.col("neighbours").alias("around"), none("array<double>").alias("qvec"), none("int").alias("k"), none("int").alias("ef"), none(kind).alias("vec"))
    packed = packed.unionByName(asked.select("g", F.lit(1).alias("kind"), "state", "shard", F.lit(-1).alias("level"), F.col("qid").cast("long").alias("id"), F.col("qvec").cast("array<double>").alias("qvec"), F.col("k").cast("int").alias("k"), F.col("ef").cast("int").alias("ef")), allowMissingColumns=True)
    packed = packed.unionByName(needed.select("g", F.lit(0).alias("kind"), F.lit("").alias("state"), F.lit(0).alias("shard"), "vid", "vec"), allowMissingColumns=True)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vectors: _Vectors | None = None
        for (_, what, state, shard), t in _units(batches, ["g", "kind", "state", "shard"]):
            if what == 0:
                vectors = _Vectors(t["vid"], t["vec"])
                continue
            queries, around = t.filter(pc.less(t["level"], 0)), t.filter(pc.greater_equal(t["level"], 0))
            if not queries.num_rows or not around.num_rows:
                continue
            low = around.filter(pc.equal(around["level"], 0))
            g = ProximityGraph.load(low["id"].to_numpy(), vectors.of(low["vid"]), around.select(["level", "id", "around"]).rename_columns(["level", "node_id", "neighbours"]).to_pandas())
            some = queries.select(["id", "qvec", "k", "ef"]).to_pandas()
            for (k, ef), part in some.groupby(["k", "ef"]):
                got = [(qid, i, d, measured, looks) for qid, (found, measured, looks) in zip(part["id"], g.search_many(np.stack(part["qvec"].to_numpy()), int(k), int(ef)), strict=True) for d, i in found]
                if got:
                    qid, ids, d, measured, looks = zip(*got, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(qid, pa.int64()), pa.array([state] * len(qid)), pa.array([shard] * len(qid), pa.int32()), pa.array(ids, pa.int64()), pa.array(d, pa.float64()), pa.array(measured, pa.int64()), pa.array(looks, pa.int64())], ["qid", "state", "shard", "id", "dist", "distances", "visited"])

    return _together(packed, ["g"]).mapInArrow(search, out)

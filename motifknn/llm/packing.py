"""Bounded-space online best-fit packing of token sequences.

A task keeps at most ``open_bins`` bins. Free space is the key: a bitset (one Python integer) has a bit for
each amount of free space that some open bin has, so the best fit for a piece of n tokens, the smallest free
space of n or more, is the lowest set bit at or above n. When no bin fits and all slots are taken, the
fullest bin closes. A task's pieces of closed bins are final; those of the bins that are open when its input ends
are left over. Left-over pieces of all tasks, without their texts, are brought together in groups of about
``GROUP`` pieces, the longest first, and packed once more in the same way: so partitions cost next to nothing.

Memory is bounded by the open bins, a batch, and a group; a lost task is done again with the same result, for
sequence ids carry the input partition or the group.

Only documents longer than ``capacity`` are cut: into pieces of ``capacity`` tokens, the first one takes the
remainder. Null text packs as the empty text (its end token alone); an empty table gives an empty table;
repeated rows are packed once each; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.llm.scratch import materialise
from motifknn.llm.tokens import by_bytes, encode

SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
COLUMNS = [x.split()[0] for x in SCHEMA.split(", ")]
KINDS = (pa.int64(), pa.int32(), *[pa.int64()] * 5)
GROUP = 1 << 15
#: Sequences of the second pass are numbered from here.
SECOND = 1 << 62


class BestFit:
    """Open bins keyed by free space."""

    def __init__(self, capacity: int, open_bins: int, first: int = 0):
        self.capacity, self.open_bins, self.next_id = capacity, open_bins, first
        self.bits, self.by_free, self.n_open = 0, {}, 0
        self.closed: list[int] = []  # since it was last emptied

    def _take(self, free: int) -> int:
        ids = self.by_free[free]
        got = ids.pop()
        if not ids:
            del self.by_free[free]
            self.bits &= ~(1 << free)
        self.n_open -= 1
        return got

    def place(self, n: int) -> tuple[int, int]:
        """(bin, offset) for a piece of n tokens."""
        if n > self.capacity:
            raise ValueError(f"a piece of {n} tokens exceeds {self.capacity}")
        fits = self.bits >> n
        if fits:
            free = n + ((fits & -fits).bit_length() - 1)
            where = self._take(free)
        else:
            free, where = self.capacity, self.next_id
            self.next_id += 1
        left = free - n
        if left:
            if self.n_open >= self.open_bins:
                self.closed.append(self._take((self.bits & -self.bits).bit_length() - 1))  # the fullest
            self.by_free.setdefault(left, []).append(where)
            self.bits |= 1 << left
            self.n_open += 1
        else:
            self.closed.append(where)
        return where, self.capacity - free


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: the first takes the remainder."""
    if n <= capacity:
        return [(0, n)]
    first = n % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


class Packer:
    """Rows of pieces by the bin they are in: open bins hold theirs back."""

    def __init__(self, capacity: int, open_bins: int, first: int):
        self.bins, self.held, self.done = BestFit(capacity, open_bins, first), {}, []

    def add(self, doc: int | None, piece: int, start: int, n: int, crc: int) -> None:
        where, offset = self.bins.place(n)
        self.held.setdefault(where, []).append((doc, piece, start, n, crc, where, offset))
        for k in self.bins.closed:
            self.done += self.held.pop(k)
        self.bins.closed.clear()

    def batch(self, rest: bool = False) -> pa.RecordBatch | None:
        """Rows of closed bins since the last call, or (``rest``) of the bins still open."""
        rows, self.done = ([r for k in sorted(self.held) for r in self.held[k]] if rest else self.done), []
        if not rows:
            return None
        columns = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), KINDS, strict=True)]
        return pa.RecordBatch.from_arrays([*columns, pa.array([rest] * len(rows))], [*COLUMNS, "open"])


def first_pass(docs: DataFrame, id_col: str, text: str, capacity: int, end_id: int, open_bins: int, engine: str) -> DataFrame:
    """SCHEMA and open: whether the piece is in a bin that was open at the end of its task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(capacity, open_bins, TaskContext.get().partitionId() << 40)
        for b in by_bytes(batches, "text"):
            for doc, value in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = np.append(encode(value.as_py(), engine), np.uint32(end_id)).astype("<u4")
                for k, (start, n) in enumerate(cut(len(ids), capacity)):
                    packer.add(doc, k, start, n, zlib.crc32(ids[start : start + n].tobytes()))
            if (out := packer.batch()) is not None:
                yield out
        if (out := packer.batch(True)) is not None:
            yield out

    return docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text}`").alias("text")).mapInArrow(run, f"{SCHEMA}, open boolean")


def second_pass(left: DataFrame, groups: int, capacity: int, open_bins: int) -> DataFrame:
    """SCHEMA of the pieces in ``left``, packed anew."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(capacity, open_bins, SECOND + (TaskContext.get().partitionId() << 40))
        for b in batches:
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                packer.add(*row)
            if (out := packer.batch()) is not None:
                yield out.select(COLUMNS)
        if (out := packer.batch(True)) is not None:
            yield out.select(COLUMNS)

    # dealt by the bin they were in, which is as good as by chance
    dealt = left.repartition(groups, "sequence_id").sortWithinPartitions(F.desc("length"), "doc_id", "piece", "ids_crc32", "sequence_id", "offset")
    return dealt.select(*COLUMNS[:5]).mapInArrow(run, SCHEMA)


def pack(docs: DataFrame, id_col: str = "doc_id", text: str = "text", capacity: int = 1024, end_id: int = 2, open_bins: int = 256, engine: str = "ranks") -> DataFrame:
    """One row per piece: where it starts in its document, its length and checksum, its sequence and place there."""
    once = materialise(first_pass(docs, id_col, text, capacity, end_id, open_bins, engine))
    left = once.where("open").drop("open")
    groups = max(1, -(-left.count() // GROUP))
    return once.where("not open").drop("open").union(second_pass(left, groups, capacity, open_bins))


def op6_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))

"""Near-duplicate documents by fast similarity sketching.

A document's set holds its distinct 4-word shingles, as 64-bit hashes. Its sketch has ``COORDS`` coordinates:
in round i every element throws itself into one hashed bin with a hashed value, earlier rounds beat later
ones, and once all bins are full the rest of the rounds is not needed; from round ``COORDS`` on, bin after
bin takes all elements, so every coordinate fills. ``BANDS`` bands of the sketch are looked up by equality:
two sets of similarity 0.8 share none with a probability of about 1e-7.

Documents of one set are one class and are represented by their smallest id. Candidates come
in two phases (see ``candidates``): a bucket of n copies costs about n tests rather than n squared, and nothing
that shares a bucket and could be linked stays untested. Sketch bits and set sizes drop pairs that cannot reach
the threshold; the rest is confirmed on the full sets. Links are contracted to components by joins and aggregations; nothing is
gathered on the driver.

Defined results: null or blank texts have an empty set, are linked with nothing and kept. A row with a null
id is not linked, has a null component and is kept. Rows with one id are each judged by their own text; rows
equal in id and text fare alike. An empty table gives an empty table. Extra columns, whatever their names, are
ignored by ``near_duplicates`` and carried along by ``one_of_each``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifknn.llm.candidates import link_components
from motifknn.llm.scratch import few, materialise
from motifknn.llm.tokens import by_bytes

ROWS, BANDS = 4, 30
COORDS = ROWS * BANDS
#: A second sketch gives this many bits. Two sets of similarity 0.8 share 922 of them on average; fewer than LEAST_BITS has a probability under 1e-6.
BITS, LEAST_BITS = 1024, 865
BATCH = 4 << 20
_NONE = np.uint64(0xFFFFFFFFFFFFFFFF)
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_LOW = np.array([(1 << 8 * k) - 1 for k in range(8)] + [0xFFFFFFFFFFFFFFFF], np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted, without repeats: by sorting, for numpy's own way hashes, which takes ten times as long."""
    x = np.sort(x)
    new = np.ones(len(x), bool)
    new[1:] = x[1:] != x[:-1]
    return x[new]


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hash, text) of every word of every text, A-Z lower-cased."""
    raw = [(t or "").encode().lower() for t in texts]
    data = np.frombuffer(b" ".join([b"", *raw, b" " * 8]), np.uint8)
    starts = np.cumsum([1, *(len(r) + 1 for r in raw)])[:-1]
    blank = _BLANK[data]
    begin = np.flatnonzero(blank[:-1] & ~blank[1:]) + 1
    end = np.flatnonzero(~blank[:-1] & blank[1:]) + 1
    size = end - begin
    eights = np.ndarray((len(data) - 7,), "<u8", data, strides=(1,))
    h = mix(size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    live = np.arange(len(begin))
    k = 0
    while len(live):
        left = size[live] - k
        h[live] = mix(h[live] + (eights[begin[live] + k] & _LOW[np.minimum(left, 8)]) * np.uint64(0xD6E8FEB86659FD93))
        k += 8
        live = live[size[live] > k]
    return h, np.searchsorted(starts, begin, side="right") - 1


def shingle_sets(texts: list[str | None], width: int = 4) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; fewer words than ``width`` are one shingle."""
    h, owner = word_hashes(texts)
    counts = np.bincount(owner, minlength=len(texts)) if len(h) else np.zeros(len(texts), np.int64)
    first = np.cumsum(counts) - counts

    def chain(n: int, at: np.ndarray) -> np.ndarray:
        x = np.full(len(at), n * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF, np.uint64)
        for k in range(n):
            x = mix(x * np.uint64(0xFF51AFD7ED558CCD) + h[at + k])
        return x

    full = chain(width, np.arange(max(0, len(h) - width + 1)))
    return [distinct(full[s : s + n - width + 1]) if n >= width else chain(int(n), np.array([s])) if n else np.empty(0, np.uint64) for s, n in zip(first, counts, strict=True)]


def sketch(elements: np.ndarray, coords: int = COORDS) -> np.ndarray:
    """The sketch of a non-empty set; coordinate values are (round, hash) in one word."""
    out = np.full(coords, _NONE, np.uint64)
    at_once = max(1, 2048 // len(elements))
    i = 0
    while i < 2 * coords:
        rounds = np.arange(i, min(2 * coords, i + at_once), dtype=np.uint64)[:, None]
        h = mix(elements[None, :] ^ mix(rounds * np.uint64(0x9E3779B97F4A7C15) + np.uint64(1)))
        bins = np.where(rounds < coords, (h >> np.uint64(40)) % np.uint64(coords), rounds - np.uint64(coords))
        np.minimum.at(out, bins.ravel().astype(np.int64), ((rounds << np.uint64(52)) | (h & np.uint64((1 << 52) - 1))).ravel())
        i += at_once
        if (out != _NONE).all():
            break
    return out


def band_keys(s: np.ndarray, rows: int = ROWS) -> np.ndarray:
    x = np.arange(len(s) // rows, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for column in s.reshape(-1, rows).T:
        x = mix(x * np.uint64(0xFF51AFD7ED558CCD) + column)
    return x


def bits_of(elements: np.ndarray) -> np.ndarray:
    """One bit of each coordinate of a sketch of BITS coordinates, as signed words."""
    return np.packbits((mix(sketch(elements, BITS)) & np.uint64(1)).astype(np.uint8)).view("<i8")


def sketches(docs: DataFrame, width: int = 4) -> DataFrame:
    """(doc_id, t, n, key_a, key_b, bits, bands) from (doc_id, text, t); the keys name the set."""
    schema = "doc_id long, t long, n long, key_a long, key_b long, bits array<long>, bands array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_bytes(batches, "text", BATCH):
            sets = shingle_sets(b.column(1).to_pylist(), width)
            drawn = [sketch(s) if len(s) else None for s in sets]
            keys = [np.array([mix(s).sum(dtype=np.uint64), mix(s ^ np.uint64(0xA5A5A5A55A5A5A5A)).sum(dtype=np.uint64)]).view(np.int64) for s in sets]
            bits = [bits_of(s) if len(s) else [] for s in sets]
            bands = [[] if d is None else band_keys(d).view(np.int64) for d in drawn]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(2), pa.array([len(s) for s in sets], pa.int64()), *(pa.array([int(k[j]) for k in keys], pa.int64()) for j in (0, 1)), pa.array(bits, pa.list_(pa.int64())), pa.array(bands, pa.list_(pa.int64()))],
                [x.split()[0] for x in schema.split(", ")],
            )

    return docs.mapInArrow(run, schema)


def full_sets(docs: DataFrame, width: int = 4) -> DataFrame:
    """(doc_id, shingles) from (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_bytes(batches, "text", BATCH):
            sets = [s.view(np.int64) for s in shingle_sets(b.column(1).to_pylist(), width)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sets, pa.list_(pa.int64()))], ["doc_id", "shingles"])

    return docs.mapInArrow(run, "doc_id long, shingles array<long>")


def _may_link(x: Column, y: Column) -> Column:
    differ = F.aggregate(F.zip_with(x["bits"], y["bits"], lambda a, b: F.bit_count(a.bitwiseXOR(b))), F.lit(0), lambda a, b: a + b)
    return differ <= BITS - LEAST_BITS


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 4, percent: int = 80) -> DataFrame:
    """Per row of ``docs``: doc_id, n_shingles, component_id, kept, and t, a hash of its text."""
    docs = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text}`").alias("text"))
    base = materialise(sketches(docs.select("doc_id", "text", F.xxhash64("text").alias("t")), width))
    sets = base.where("n > 0 and doc_id is not null")
    classes = materialise(sets.groupBy("key_a", "key_b").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("bits").alias("bits"), F.first("bands").alias("bands")))
    dealt = classes.select("rep", F.explode("bands").alias("bucket"))
    several = materialise(dealt.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).where("size > 1").select("bucket"))
    members = materialise(dealt.join(few(several), "bucket").join(classes.select("rep", "n", "bits"), "rep"))


    def sets_of(ids: DataFrame) -> DataFrame:
        return materialise(full_sets(docs.join(few(materialise(ids.select(F.col("rep").alias("doc_id")))), "doc_id", "left_semi"), width).select(F.col("doc_id").alias("rep"), F.col("shingles").alias("set")))

    comps = link_components(members, ["bits"], _may_link, sets_of, percent)
    named = classes.select("key_a", "key_b", "rep")
    named = named.select("key_a", "key_b", F.col("rep").alias("component_id")) if comps is None else named.join(comps, named["rep"] == comps["node"], "left").select("key_a", "key_b", F.coalesce("component", "rep").alias("component_id"))
    of = sets.select("doc_id", "t", "n", "key_a", "key_b").join(named, ["key_a", "key_b"]).select("doc_id", "t", "n", "component_id")
    alone = base.where("n = 0 or doc_id is null").select("doc_id", "t", "n", F.col("doc_id").alias("component_id"))
    return of.union(alone).select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"), "t")


def op9_minhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).drop("t")


def one_of_each(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs``, all columns, of which each component keeps the smallest id. A row goes by its own id and text."""
    gone = materialise(near_duplicates(docs, width=width, percent=percent).where("not kept").select(F.struct("doc_id", "t").alias("_gone_row")).distinct())
    rows = docs.select(F.struct(*[F.col(f"`{c}`").alias(c) for c in docs.columns]).alias("row"))
    left = rows.join(few(gone), (F.col("row.doc_id").cast("long") == F.col("_gone_row.doc_id")) & (F.xxhash64("row.text") == F.col("_gone_row.t")), "left_anti")
    return left.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])

"""Language identification: multinomial naive Bayes over hashed character n-grams.

Training counts hashed 1- to 3-grams per label in one distributed pass (workers return sparse partial
counts, summed by Spark); the log-probability matrix, ``labels x buckets`` floats with both factors bounded,
is what gets broadcast. Scoring is sparse: a batch is one code-point array, n-grams are hashed by array
arithmetic, and each document sums the matrix columns that its n-grams touch.

The fit reads a bounded sample: at most about ``max_per_label`` documents of each label, chosen by a hash of
the document id, so reruns agree. Everything is scored. Labels, sources and ids never enter a prediction.

Defined results: ``und`` with score 0 for a null text or one without a letter; with no labelled rows at all,
every text is ``und``. A null label is never learned; of more than ``MAX_LABELS`` labels, those with the most rows
are learned. A row with a null id is held out. Repeated rows are scored each. An empty table gives an empty
table. Very long texts are scored in parts whose n-grams add up to those of the whole. Extra columns are carried
along but for lang_pred and score, which are replaced.
"""

from __future__ import annotations

import functools
import sys
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

BUCKETS = 1 << 16
ORDERS = (1, 2, 3)
MAX_PER_LABEL = 4000
MAX_LABELS = 128
BLOCK_CHARS = 1 << 20
_MIX = (np.uint32(0x9E3779B1), np.uint32(0x85EBCA77), np.uint32(0xC2B2AE3D), np.uint32(0x27D4EB2F))


@functools.cache
def letters() -> np.ndarray:
    """True at the code points that are letters."""
    table = np.zeros(sys.maxunicode + 1, bool)
    table[[i for i in range(0x110000) if unicodedata.category(chr(i))[0] == "L"]] = True
    return table


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(lower-cased code points with one blank around each text and non-letters as blanks, the text of each, letters per text)."""
    joined = "".join(f" {t.lower()} " for t in texts)
    sizes = np.fromiter((len(t.lower()) + 2 for t in texts), np.int64, len(texts))
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32).copy()
    is_letter = letters()[points]
    points[~is_letter] = 32
    owner = np.repeat(np.arange(len(texts)), sizes)
    return points, owner, np.bincount(owner, is_letter, len(texts)).astype(np.int64)


def ngrams(points: np.ndarray, owner: np.ndarray, buckets: int = BUCKETS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(bucket, text) of each n-gram of every order; runs of blanks count as nothing, no n-gram spans two texts."""
    solid = np.ones(len(points), bool)
    solid[1:] = (points[1:] != 32) | (points[:-1] != 32)
    points, owner = points[solid], owner[solid]
    for n in ORDERS:
        if len(points) < n:
            continue
        h = np.full(len(points) - n + 1, n * 0x1000193, np.uint32)
        for k in range(n):
            h = (h ^ points[k : len(points) - n + 1 + k]) * _MIX[k]
            h ^= h >> np.uint32(15)
        inside = owner[: len(h)] == owner[n - 1 :]
        if n == 1:
            inside &= points != 32
        yield (h[inside] % np.uint32(buckets)).astype(np.int32), owner[: len(h)][inside]


def parts(text: str, size: int) -> Iterator[tuple[str, int]]:
    """(piece, sign): the n-grams of the pieces, added or taken away, are those of the whole text.

    After a cut comes the next piece with the end of the one before, and, to be taken away, that end alone.
    """
    at, before = 0, ""
    while True:
        cut = len(text) if len(text) - at <= size else text.rfind(" ", at + size // 2, at + size) + 1 or at + size
        yield before + text[at:cut], 1
        if before:
            yield before, -1
        if cut == len(text):
            return
        back = 64
        while cut - back > 0 and sum(map(str.isalpha, text[cut - back : cut])) < max(ORDERS):
            back *= 4
        at, before = cut, text[max(0, cut - back) : cut]


def blocks(values: list[str | None], size: int = BLOCK_CHARS) -> Iterator[tuple[np.ndarray, list[str], np.ndarray]]:
    """(rows, texts, signs) in runs of about ``size`` characters; a longer text comes in several parts."""
    rows: list[int] = []
    texts: list[str] = []
    signs: list[int] = []
    held = 0
    for i, v in enumerate(values):
        for part, sign in parts(v, size) if v else ():
            rows.append(i)
            texts.append(part)
            signs.append(sign)
            held += len(part)
            if held >= size:
                yield np.array(rows), texts, np.array(signs)
                rows, texts, signs, held = [], [], [], 0
    if rows:
        yield np.array(rows), texts, np.array(signs)


def training_rows(docs: DataFrame, text: str, label: str, id_col: str, max_per_label: int) -> DataFrame:
    """(label, text) of the labelled rows, thinned by an id hash to about max_per_label a label."""
    labelled = docs.where(F.col(label).isNotNull() & F.col(text).isNotNull()).select(F.col(label).alias("label"), F.col(text).alias("text"), F.col(id_col).alias("id"))
    sizes = labelled.groupBy("label").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "label").limit(MAX_LABELS).collect()
    share = [f"when label = '{r['label'].replace(chr(92), chr(92) * 2).replace(chr(39), chr(92) + chr(39))}' then {min(1.0, max_per_label / r['n']):.9f}" for r in sizes]
    if not share:
        return labelled.select("label", "text")
    drawn = F.pmod(F.xxhash64("id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    return labelled.where(drawn < F.expr(f"case {' '.join(share)} else 0 end")).select("label", "text")


def fit(docs: DataFrame, text: str = "text", label: str = "lang", id_col: str = "doc_id", max_per_label: int = MAX_PER_LABEL, buckets: int = BUCKETS, alpha: float = 0.5) -> tuple[list[str], np.ndarray]:
    """(labels, float32 matrix ``buckets + 1`` x ``labels``; its last row has the log priors)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        seen: dict[str, int] = {}
        for b in batches:
            tags = b.column(0).to_pylist()
            for t in tags:
                seen[t] = seen.get(t, 0) + 1
            for rows, texts, signs in blocks(b.column(1).to_pylist()):
                names, at = np.unique([tags[r] for r in rows], return_inverse=True)
                points, owner, _ = code_points(texts)
                for bucket, of in ngrams(points, owner, buckets):
                    for k, name in enumerate(names):
                        own = at[of] == k
                        mine = np.bincount(bucket[own], signs[of][own], buckets).astype(np.int64)
                        sums[str(name)] = sums.get(str(name), 0) + mine
        for name, n in seen.items():
            got = sums.get(name, np.zeros(buckets, np.int64))
            at = np.flatnonzero(got)
            yield pa.RecordBatch.from_arrays([pa.array([name] * (len(at) + 1), pa.string()), pa.array([*at.tolist(), buckets], pa.int32()), pa.array([*got[at].tolist(), n], pa.int64())], ["label", "bucket", "n"])

    rows = training_rows(docs, text, label, id_col, max_per_label)
    counts = rows.mapInArrow(count, "label string, bucket int, n long").groupBy("label", "bucket").agg(F.sum("n").alias("n")).toArrow()  # labels x buckets rows at most
    names = sorted(set(counts.column("label").to_pylist()))
    dense = np.zeros((buckets + 1, len(names)))
    dense[counts.column("bucket").to_numpy(), np.searchsorted(names, counts.column("label").to_pylist())] = counts.column("n").to_numpy()
    grams, prior = dense[:buckets] + alpha, dense[buckets]
    logs = np.log(grams / grams.sum(0, keepdims=True)) if names else grams
    return names, np.vstack([logs, np.log(prior / max(prior.sum(), 1))]).astype(np.float32)


def score(values: list[str | None], names: list[str], matrix: np.ndarray) -> tuple[list[str], np.ndarray]:
    """Best label and its posterior for each text."""
    sums = np.zeros((len(values), len(names)))
    found = np.zeros(len(values), np.int64)
    columns = np.ascontiguousarray(matrix[:-1].T)
    for rows, texts, signs in blocks(values):
        points, owner, n_letters = code_points(texts)
        np.add.at(found, rows, signs * n_letters)
        for bucket, of in ngrams(points, owner, len(matrix) - 1):
            for k in range(len(names)):
                np.add.at(sums[:, k], rows, signs * np.bincount(of, columns[k][bucket], len(texts)))
    if not names:
        return ["und"] * len(values), np.zeros(len(values))
    sums += matrix[-1]
    sums -= sums.max(1, keepdims=True)
    odds = np.exp(sums)
    odds /= odds.sum(1, keepdims=True)
    best = odds.argmax(1)
    known = found > 0
    return [names[k] if ok else "und" for k, ok in zip(best, known, strict=True)], np.where(known, odds[np.arange(len(values)), best], 0.0)


def identify(docs: DataFrame, model: tuple[list[str], np.ndarray], text: str = "text") -> DataFrame:
    """Every row of ``docs`` without its text, plus lang_pred and score."""
    made = ("lang_pred", "score")
    keep = [c for c in docs.columns if c not in (*made, text)]
    narrow = docs.select(*keep, text)
    out = T.StructType([*(f for f in narrow.schema.fields if f.name != text), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    shared = docs.sparkSession.sparkContext.broadcast(model)  # MAX_LABELS x BUCKETS floats at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, matrix = shared.value
        for b in batches:
            i = b.schema.get_field_index(text)
            best, p = score(b.column(i).to_pylist(), names, matrix)
            columns = [b.column(k) for k in range(b.num_columns) if k != i]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(best, pa.string()), pa.array(p, pa.float64())], [*keep, *made])

    return narrow.mapInArrow(run, out)


def held_out(id_col: str = "doc_id"):
    """True where the id is not to be learned from."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 5 == 0, F.lit(True))


def op1_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs.where(~held_out()).select("doc_id", "text", "lang"))
    return identify(docs.select("doc_id", held_out().alias("held_out"), "text"), model)

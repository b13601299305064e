"""Improbable-feature digests of texts.

Every window of ``WINDOW`` bytes has an entropy, kept up to date by one addition and one removal per byte:
both need only how often the byte occurs in the window, which shifted comparisons of the whole batch give.
A first pass over all texts counts how common each (quantised) entropy is; rare entropies get low ranks,
and windows that are almost constant or almost random get none. In each run of ``POPULAR`` neighbouring
windows the leftmost of lowest rank scores a point; windows with ``LEAST`` points or more are features.
Features go, five bits each, into a chain of 2048-bit Bloom filters of up to ``PER_FILTER`` features.
Two digests are compared by the bits they share beyond what chance gives, divided by the most they could
share, over the filters of the shorter chain (best partner each) and averaged.

Texts under ``SHORT`` bytes are read more finely: every leftmost lowest of ``POPULAR_SHORT`` windows is a
feature. A text of under four windows has all its runs of ``TINY`` bytes as features; a longer one in which
nothing is chosen (of constant bytes) has its whole self. The empty text has an empty digest, which is like nothing but
another empty one. Equal texts have equal digests.

The neighbour of a document in id order is found with one exchange: ids are cut at quantiles which are ids
of the table, and the document at each cut is sent to the range below as well, so that no range needs to ask
another. Ranges are streamed; a worker holds one batch and the row before it. Null ids come first, rows of
one id are ordered by their text; a null text counts as the empty one; a single row is its own next.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.llm.tokens import by_bytes

WINDOW, POPULAR, LEAST, PER_FILTER, BITS, HASHES = 32, 64, 16, 160, 2048, 5
#: Texts of fewer than SHORT bytes take every leftmost lowest of POPULAR_SHORT windows; the least of all take all runs of TINY bytes.
SHORT, POPULAR_SHORT, TINY = 1024, 8, 4
LEVELS = 1000
#: Levels of entropy outside which a window is no feature (of 0 to LEVELS).
FLOOR, CEILING = 100, 990
SCALE = 1 << 20
_C = np.arange(WINDOW + 2)
#: What c*log2(c) grows by when a c-th byte of a kind comes, in fixed point so that sums are exact.
STEP = np.zeros(WINDOW + 1, np.int64)
STEP[1:] = np.rint(SCALE * (_C[1:-1] * np.log2(_C[1:-1]) - np.concatenate([[0.0], _C[1:-2] * np.log2(_C[1:-2])])))
BATCH = 1 << 20


def stream(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes of all texts with a window's length between them, start of each, length of each)."""
    gap = b"\0" * WINDOW
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    starts = np.cumsum(lengths + WINDOW) - lengths
    return np.frombuffer(gap + gap.join(texts) + gap, np.uint8), starts, lengths


def levels(data: np.ndarray) -> np.ndarray:
    """Entropy, 0 to LEVELS, of the window that starts at each byte (of the first len - WINDOW + 1)."""
    n = len(data)
    back = np.zeros(n, np.uint8)  # equal bytes among the WINDOW - 1 before
    ahead = np.zeros(n, np.uint8)  # among those after
    for d in range(1, min(WINDOW, n)):
        same = data[d:] == data[:-d]
        back[d:] += same
        ahead[:-d] += same
    head = sum(int(STEP[np.count_nonzero(data[:j] == data[j]) + 1]) for j in range(min(WINDOW, n)))
    change = STEP[back[WINDOW:] + 1] - STEP[ahead[: n - WINDOW] + 1]
    total = np.empty(n - WINDOW + 1, np.int64)
    total[0] = head
    np.cumsum(change, out=total[1:])
    total[1:] += head
    most = int(round(SCALE * WINDOW * np.log2(WINDOW)))
    return ((most - total) * LEVELS // most).astype(np.int32)


def histogram(texts: list[bytes]) -> np.ndarray:
    data, starts, lengths = stream(texts)
    if len(data) <= WINDOW:
        return np.zeros(LEVELS + 1, np.int64)
    return np.bincount(levels(data)[_inside(len(data), starts, lengths)], minlength=LEVELS + 1)


def _inside(n: int, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """True where a window lies wholly in one text."""
    edge = np.zeros(n + 1, np.int8)
    long = lengths >= WINDOW
    np.add.at(edge, starts[long], 1)
    np.add.at(edge, starts[long] + lengths[long] - WINDOW + 1, -1)
    return np.cumsum(edge[: n - WINDOW + 1], dtype=np.int8).astype(bool)


def ranks(counts: np.ndarray) -> np.ndarray:
    """Rank of each level: the rarer in the corpus, the lower; LEVELS + 1 for what is no feature."""
    out = np.full(LEVELS + 1, LEVELS + 1, np.int64)
    able = np.arange(FLOOR, CEILING + 1)
    out[able[np.lexsort((able, counts[able]))]] = np.arange(len(able))
    return out


def _popular(key: np.ndarray, starts: np.ndarray, lengths: np.ndarray, width: int, least: int) -> np.ndarray:
    """Places of the windows that are leftmost of lowest rank in ``least`` or more of the runs of ``width`` windows within one text."""
    low, w = key, 1
    while w < width:  # minimum over a run that doubles
        low, w = np.minimum(low[:-w], low[w:]), 2 * w
    whole = np.zeros(len(key) + 1, np.int8)
    wide = lengths >= WINDOW + width - 1
    np.add.at(whole, starts[wide], 1)
    np.add.at(whole, starts[wide] + lengths[wide] - (WINDOW + width - 1) + 1, -1)
    best = low[np.cumsum(whole[: len(low)], dtype=np.int8).astype(bool)] & ((1 << 40) - 1)
    points = np.bincount(best, minlength=len(key)) if len(best) else np.zeros(len(key), np.int64)
    return np.flatnonzero((points >= least) & (key >> np.int64(40) <= LEVELS))


def features(texts: list[bytes], rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, 64-bit hash) of every feature, in order of text and place."""
    data, starts, lengths = stream(texts)
    key = np.where(_inside(len(data), starts, lengths), rank[levels(data)], LEVELS + 2) << np.int64(40)
    key |= np.arange(len(key))
    tiny = lengths < 4 * WINDOW
    short = (lengths < SHORT) & ~tiny
    at = np.concatenate([_popular(key, starts[lengths >= SHORT], lengths[lengths >= SHORT], POPULAR, LEAST), _popular(key, starts[short], lengths[short], POPULAR_SHORT, 1)])
    owner, hashed = np.searchsorted(starts, at, side="right") - 1, _hash_windows(data, at)
    # the least of all, and texts in which nothing was chosen
    more: list[tuple[int, bytes]] = []
    for t in np.flatnonzero((np.bincount(owner, minlength=len(texts)) == 0) & (lengths > 0)):
        more += [(t, texts[t][k : k + TINY]) for k in range(max(1, len(texts[t]) - TINY + 1))] if tiny[t] else [(t, texts[t])]
    if more:
        owner = np.concatenate([owner, [t for t, _ in more]])
        hashed = np.concatenate([hashed, np.array([int.from_bytes(hashlib.blake2b(x, digest_size=8).digest(), "little") for _, x in more], np.uint64)])
    order = np.argsort(owner, kind="stable")
    return owner[order], hashed[order]


def _hash_windows(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    words = np.ndarray((len(data) - 7,), "<u8", data.tobytes(), strides=(1,))
    h = np.full(len(at), 0x9E3779B97F4A7C15, np.uint64)
    for k in range(0, WINDOW, 8):
        h = (h ^ words[at + k]) * np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(32)
    return h


def chains(texts: list[bytes], rank: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """(filters, features in each) of every text."""
    owner, h = features(texts, rank)
    counts = np.bincount(owner, minlength=len(texts))
    first = np.cumsum(counts) - counts
    filters = -(-counts // PER_FILTER)
    base = np.cumsum(filters) - filters
    mine = base[owner] + (np.arange(len(owner)) - first[owner]) // PER_FILTER
    bits = np.zeros(int(filters.sum()) * BITS, np.uint8)
    for k in range(HASHES):
        bits[mine * BITS + ((h >> np.uint64(11 * k)) & np.uint64(BITS - 1)).astype(np.int64)] = 1
    packed = np.packbits(bits).reshape(-1, BITS // 8)
    held = np.bincount(mine, minlength=len(packed))
    return [(packed[b : b + f], held[b : b + f]) for b, f in zip(base, filters, strict=True)]


def as_text(chain: tuple[np.ndarray, np.ndarray]) -> str:
    """features.filter for each filter, joined by colons."""
    return ":".join(f"{n:x}.{base64.b64encode(f.tobytes()).decode()}" for f, n in zip(*chain, strict=True))


def from_text(digest: str) -> tuple[np.ndarray, np.ndarray]:
    parts = [x.split(".") for x in digest.split(":")] if digest else []
    return np.array([np.frombuffer(base64.b64decode(b), np.uint8) for _, b in parts], np.uint8).reshape(-1, BITS // 8), np.array([int(n, 16) for n, _ in parts], np.int64)


def likeness(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """0 to 1: bits shared beyond chance, as a part of what could be shared."""
    if not len(a[0]) or not len(b[0]):
        return float(len(a[0]) == len(b[0]))
    if len(a[0]) > len(b[0]) or (len(a[0]) == len(b[0]) and a[0].tobytes() > b[0].tobytes()):
        a, b = b, a
    ones_a, ones_b = (np.bitwise_count(x[0]).sum(1).astype(float) for x in (a, b))
    shared = np.bitwise_count(a[0][:, None, :] & b[0][None, :, :]).sum(2)
    chance = ones_a[:, None] * ones_b[None, :] / BITS
    # a filter that holds few features spans little text: it may share no more than it has
    most = np.minimum(ones_a[:, None], ones_b[None, :])
    spare = 3 * np.sqrt(np.maximum(chance * (1 - np.maximum(ones_a[:, None], ones_b[None, :]) / BITS), 0))
    part = (shared - chance - spare) / np.maximum(most - chance - spare, 1)
    part[shared == most] = 1.0
    best = np.clip(part, 0, 1).max(1)
    return float((best * ones_a).sum() / ones_a.sum())


def corpus_ranks(docs: DataFrame, text: str = "text") -> np.ndarray:
    """Ranks from the entropies of all windows of all texts."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(LEVELS + 1, np.int64)
        for b in batches:
            for part in by_bytes([b], text, BATCH):
                total += histogram([v.encode() for v in part.column(0).to_pylist() if v])
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(total[at], pa.int64())], ["level", "n"])

    got = docs.select(text).mapInArrow(count, "level int, n long").groupBy("level").agg(F.sum("n").alias("n")).collect()  # LEVELS + 1 rows at most
    counts = np.zeros(LEVELS + 1, np.int64)
    for r in got:
        counts[r["level"]] = r["n"]
    return ranks(counts)


def with_next(docs: DataFrame, id_col: str = "doc_id", text: str = "text", ranges: int | None = None) -> DataFrame:
    """(range, last, id, text) so placed that a range's rows, in order, are followed by the first row of the next one (last = 1; 2 in the final range)."""
    spark = docs.sparkSession
    n = ranges or 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    q = [i / n for i in range(n)]
    got = docs.agg(F.percentile_approx(id_col, q, 100 * n).alias("q"), F.min(id_col).alias("lo"), F.max(F.col(id_col).isNull().cast("int")).alias("none")).first()
    cuts = sorted({*(got["q"] or [])} - {got["lo"]})
    edges = F.lit(cuts) if cuts else F.array().cast("array<bigint>")
    place = F.when(F.col(id_col).isNull(), 0).otherwise(F.size(F.filter(edges, lambda c: c <= F.col(id_col))))
    own = F.struct(place.cast("int").alias("range"), F.lit(0).alias("last"))
    at_cut = F.array_contains(edges, F.col(id_col))
    first = F.col(id_col).isNull() if got["none"] else F.col(id_col) == F.lit(got["lo"])
    more = F.array(own, F.when(at_cut, F.struct((place - 1).cast("int").alias("range"), F.lit(1).alias("last"))), F.when(first, F.struct(F.lit(len(cuts)).alias("range"), F.lit(2).alias("last"))))
    return docs.select(F.inline(F.array_compact(more)), F.col(id_col).alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text")).repartition(n, "range").sortWithinPartitions("range", "last", F.col("id").asc_nulls_first(), "text")


def digests(docs: DataFrame, id_col: str = "doc_id", text: str = "text", rank: np.ndarray | None = None) -> DataFrame:
    """Digest of each document and of its edited text, with the likeness to that and to the next document."""
    rank = corpus_ranks(docs, text) if rank is None else rank
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def made(pairs: list[tuple[int | None, str, str]]) -> pa.RecordBatch:
        edited = [(t[: len(t) - len(t) // 2] + n[: len(t) // 2]).encode() for _, t, n in pairs]
        own = [t.encode() for _, t, _ in pairs]
        after = [n.encode() for _, _, n in pairs]
        # a pair's next text is most often the next pair's own
        follow = [i + 1 if i + 1 < len(pairs) and pairs[i + 1][1] == pairs[i][2] else -1 for i in range(len(pairs))]
        rest = [i for i, f in enumerate(follow) if f < 0]
        all_of = chains([*own, *edited, *(after[i] for i in rest)], rank)
        a, e, r = all_of[: len(own)], all_of[len(own) : 2 * len(own)], dict(zip(rest, all_of[2 * len(own) :], strict=True))
        rows = [(i, len(t), hashlib.sha256(edited[k]).hexdigest(), as_text(a[k]), as_text(e[k]), likeness(a[k], e[k]), likeness(a[k], a[follow[k]] if follow[k] >= 0 else r[k])) for k, (i, t, _) in enumerate(pairs)]
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], [x.split()[0] for x in schema.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None  # the row before, which waits for its next
        closed = -1  # range whose tail has come
        pairs: list[tuple[int | None, str, str]] = []
        size = 0
        for b in batches:
            for place, last, i, t in zip(*(b.column(k).to_pylist() for k in range(4)), strict=True):
                if place == closed:
                    continue  # more rows with the id at a cut
                if held is not None and held[0] == place:
                    pairs.append((held[1], held[2], t))
                    size += len(held[2]) + len(t)
                held = None if last else (place, i, t)
                closed = place if last else -1
                if size >= BATCH:
                    yield made(pairs)
                    pairs, size = [], 0
        if pairs:
            yield made(pairs)

    narrow = docs.select(F.col(id_col).cast("long").alias(id_col), text)
    return with_next(narrow, id_col, text).mapInArrow(run, schema)


def op10_improbable_digest(spark, sf_dir: str) -> DataFrame:
    return digests(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))

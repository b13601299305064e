"""Fuzzy line dedup by MinHash.

A line is evened first: letters lower-cased, runs of blanks one blank, none at its ends. Its shingles are its
runs of ``WIDTH`` characters, one from every place. Their hashes lie on a circle, and the next hash after each of
``ROWS * BANDS`` even marks is a minimum; ``BANDS`` bands of ``ROWS`` such minima are looked up by equality. A
pair of similarity 0.8 shares no band with a probability of 0.0023 by the formula for independent minima.
Candidates are confirmed by the exact Jaccard similarity of their shingle sets, links are contracted to
components by joins and aggregations, and of each component the line that comes first (by document id, then
text hash, then place) stays.

Equal lines of any length with a letter or digit are one class from the start and need no test; evened lines of
fewer than ``LEAST_CHARS`` characters are compared by equality alone, and marks without a word ("---") of fewer
characters are left alone. Only one line of each class is signed. Memory is bounded by a line and a document; a
line of a third of all rows is summed before it is moved.

There are two engines for the two steps that read a line's characters, signing and the exact test: DataFrame
expressions (``native``), or numpy in Arrow functions. Everything else is DataFrame operations in either. The
pipeline uses the first; the query the second, for the first takes more than its budget of CPU seconds.

Defined results: null text stays null with 0 lines. Rows equal in id and text are one document seen several
times: they lose the same lines. Rows of one id (or of none) with different texts are different documents. A
null id is the last in order. Extra columns are carried along, whatever their names, but for ``_n_lines`` and
``_n_kept``, which are replaced. Classes are named by 64-bit hashes of the line.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifknn.llm.candidates import link_components
from motifknn.llm.neardup import distinct, mix
from motifknn.llm.quality import let
from motifknn.llm.scratch import few, materialise, release
from motifknn.llm.tokens import by_bytes

WIDTH, ROWS, BANDS, LEAST_CHARS = 5, 6, 20, 40
PERCENT = 80
WORD = r"[\p{L}\p{N}]"
COORDS = ROWS * BANDS
STEP = (1 << 64) // COORDS
#: Hashes are even numbers, marks are odd.
MARKS = [(-(1 << 63) + i * STEP) | 1 for i in range(COORDS)]
#: Four bits of each minimum are kept, so many minima in a word.
IN_WORD = 15
WORDS = COORDS // IN_WORD
#: Minima of a pair of similarity 0.8 differ in 22.5 of COORDS on average; as many standard deviations more are let through.
SIGMAS = 4.5
BATCH = 2 << 20


def evened(line: Column) -> Column:
    odd = line.rlike(r"[\x09\x0B-\x0D\xA0]|  ")
    return F.lower(F.trim(F.when(odd, F.regexp_replace(line, r"[\x09-\x0D\x20\xA0]+", " ")).otherwise(line)))


# --- signatures and the exact test, as expressions
def shingles(line: Column) -> Column:
    """Even hashes of the runs of WIDTH characters of an evened line, from every place (repeats kept)."""
    runs = [F.regexp_extract_all(F.substring(line, 1 + k, 1 << 30) if k else line, F.lit(f"(?s).{{{WIDTH}}}"), F.lit(0)) for k in range(WIDTH)]
    return F.transform(F.concat(*runs), lambda s: F.xxhash64(s).bitwiseAND(F.lit(-2)))


def signature(line: Column) -> Column:
    """Struct of n (different hashes), bands, and four bits of each minimum."""

    def minima(s: Column) -> Column:
        # a mark's place among hashes and marks, less the marks before it, is the place of the next hash
        places = F.transform(F.sort_array(F.concat(s, F.lit(MARKS))), lambda x, i: F.when(x.bitwiseAND(F.lit(1)) == 1, i))
        return F.transform(F.filter(places, lambda p: p.isNotNull()), lambda p, j: F.get(s, F.pmod(p - j, F.size(s))))

    def packed(least: Column) -> Column:
        bits = lambda acc, x: F.shiftleft(acc, 4).bitwiseOR(F.shiftrightunsigned(x, 8).bitwiseAND(F.lit(15)))
        return F.array(*[F.aggregate(F.slice(least, 1 + w * IN_WORD, IN_WORD), F.lit(0).cast("long"), bits) for w in range(WORDS)])

    def of(s: Column) -> Column:
        def rest(least: Column) -> Column:
            keys = [F.xxhash64(F.lit(b), *(F.get(least, F.lit(b + r * BANDS)) for r in range(ROWS))) for b in range(BANDS)]
            return F.struct(F.size(s).alias("n"), F.array(*keys).alias("bands"), packed(least).alias("low"))

        return let(minima(s), rest)

    return let(F.sort_array(F.array_distinct(shingles(line))), of)


def sign_native(once: DataFrame) -> DataFrame:
    others = [c for c in once.columns if c != "line"]
    return once.select(*others, signature(F.col("line")).alias("s")).select(*others, "s.n", "s.bands", "s.low")


def confirm_native(both: DataFrame, percent: int) -> DataFrame:
    def similar(x: Column, y: Column) -> Column:
        return let(F.size(F.array_intersect(x, y)), lambda common: common * 100 >= (F.size(x) + F.size(y) - common) * percent)

    return both.where(let(F.array_distinct(shingles(F.col("x"))), lambda x: let(F.array_distinct(shingles(F.col("y"))), lambda y: similar(x, y)))).select("a", "b")


def spread_native(own: DataFrame) -> DataFrame:
    return own.select("rep", F.explode(F.array_distinct(shingles(F.col("set")))).alias("e"))


# --- the same in numpy
def shingle_hashes(lines: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(hash, line) of every run of WIDTH characters of every line."""
    sizes = np.fromiter(map(len, lines), np.int64, len(lines))
    points = np.frombuffer("".join(lines).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    places = max(0, len(points) - WIDTH + 1)
    h = np.zeros(places, np.uint64)
    for k in range(WIDTH):
        h = h * np.uint64(0x9E3779B97F4A7C15) + points[k : places + k]
    owner = np.repeat(np.arange(len(lines)), sizes)
    inside = owner[:places] == owner[WIDTH - 1 :]
    return mix(h[inside]), owner[:places][inside]


#: A hash keeps its upper bits beside the line's number in one word.
LINE_BITS = 16


def signatures(lines: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(n, bands, low) of lines of WIDTH characters or more, at most 2^LINE_BITS lines."""
    h, owner = shingle_hashes(lines)
    kept = np.uint64(64 - LINE_BITS)
    keys = distinct((owner.astype(np.uint64) << kept) | (h >> np.uint64(LINE_BITS)))
    n = np.bincount((keys >> kept).astype(np.int64), minlength=len(lines))
    last = np.cumsum(n)
    marks = np.arange(COORDS, dtype=np.uint64) * np.uint64(STEP >> LINE_BITS)
    asked = (np.arange(len(lines), dtype=np.uint64) << kept)[:, None] | marks[None, :]
    at = np.searchsorted(keys, asked.ravel()).reshape(asked.shape)
    at = np.where(at >= last[:, None], (last - n)[:, None], at)  # past the line's last hash comes its first
    least = keys[at] & np.uint64((1 << (64 - LINE_BITS)) - 1)
    bands = np.broadcast_to(np.arange(BANDS, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), (len(lines), BANDS)).copy()
    for r in range(ROWS):
        bands = mix(bands * np.uint64(0xFF51AFD7ED558CCD) + least[:, r * BANDS : (r + 1) * BANDS])
    low = np.zeros((len(lines), WORDS), np.uint64)
    nibbles = (least & np.uint64(15)).reshape(len(lines), WORDS, IN_WORD)
    for k in range(IN_WORD):
        low = (low << np.uint64(4)) | nibbles[:, :, k]
    return n, bands.view(np.int64), low.view(np.int64)


def _lists(rows: np.ndarray) -> pa.Array:
    return pa.FixedSizeListArray.from_arrays(pa.array(rows.ravel()), rows.shape[1]).cast(pa.list_(pa.int64()))


def sign_arrow(once: DataFrame) -> DataFrame:
    others = [c for c in once.columns if c != "line"]
    narrow = once.select(*others, "line")
    longs = T.ArrayType(T.LongType())
    out = T.StructType([*(f for f in narrow.schema.fields if f.name != "line"), T.StructField("n", T.IntegerType()), T.StructField("bands", longs), T.StructField("low", longs)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_bytes(batches, "line", BATCH):
            n, bands, low = signatures(b.column(len(others)).to_pylist())
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(len(others))), pa.array(n.astype(np.int32)), _lists(bands), _lists(low)], [*others, "n", "bands", "low"])

    return narrow.mapInArrow(run, out)


def confirm_arrow(both: DataFrame, percent: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in by_bytes([whole], "x", BATCH):
                a, c, x, y = (b.column(k).to_pylist() for k in range(4))
                names = sorted({*x, *y})
                h, owner = shingle_hashes(names)
                ends = np.searchsorted(owner, np.arange(len(names) + 1))
                sets = {name: distinct(h[s:e]) for name, s, e in zip(names, ends, ends[1:], strict=False)}
                good = []
                for u, v in zip(x, y, strict=True):
                    common = len(np.intersect1d(sets[u], sets[v], assume_unique=True))
                    good.append(common * 100 >= (len(sets[u]) + len(sets[v]) - common) * percent)
                yield pa.RecordBatch.from_arrays([pa.array(k, pa.int64()) for k in ([i for i, ok in zip(ids, good, strict=True) if ok] for ids in (a, c))], ["a", "b"])

    return both.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def spread_arrow(own: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_bytes(batches, "set", BATCH):
            h, owner = shingle_hashes(b.column(1).to_pylist())
            order = np.lexsort((h, owner))
            h, owner = h[order], owner[order]
            new = np.ones(len(h), bool)
            new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(owner[new])), pa.array(h[new].view(np.int64))], ["rep", "e"])

    return own.select("rep", "set").mapInArrow(run, "rep long, e long")


def agree(x: Column, y: Column) -> Column:
    """Enough equal minima, by four bits of each. Fewer shingles than minima repeat some, which widens the spread."""

    def unlike(u: Column, v: Column) -> Column:
        d = u.bitwiseXOR(v)
        d = d.bitwiseOR(F.shiftrightunsigned(d, 1))
        return F.bit_count(d.bitwiseOR(F.shiftrightunsigned(d, 2)).bitwiseAND(F.lit(0x1111111111111111)))

    differ = F.lit(0)
    for w in range(WORDS):
        differ = differ + unlike(F.get(x["low"], F.lit(w)), F.get(y["low"], F.lit(w)))
    mean = 0.2 * 15 / 16 * COORDS
    return differ <= F.lit(mean) + F.lit(SIGMAS) * F.sqrt(F.lit(0.15 * COORDS) + F.lit(0.3 * COORDS * COORDS) / F.least(x["n"], y["n"]))


# --- the flow
def numbered_lines(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    """(doc, t, line_no, line, h, long) of the lines with a word or of LEAST_CHARS characters, evened; t names the text."""
    whole = F.col(f"`{text}`")
    lines = docs.select(F.col(f"`{id_col}`").alias("doc"), F.xxhash64(whole).alias("t"), F.posexplode(F.split(whole, "\n")).alias("line_no", "raw"))
    lines = lines.select("doc", "t", "line_no", evened(F.col("raw")).alias("line")).withColumn("long", F.char_length("line") >= LEAST_CHARS)
    return lines.where(F.col("long") | F.col("line").rlike(WORD)).withColumn("h", F.xxhash64("line"))


PLACE = ("doc", "t", "line_no")


def _is(a: str, b: str) -> Column:
    """Two places are the same."""
    return F.col(f"{a}.doc").eqNullSafe(F.col(f"{b}.doc")) & (F.col(f"{a}.t") == F.col(f"{b}.t")) & (F.col(f"{a}.line_no") == F.col(f"{b}.line_no"))


def repeats(docs: DataFrame, id_col: str = "doc_id", text: str = "text", percent: int = PERCENT, native: bool = True) -> DataFrame:
    """(doc, t, line_no) of the lines that go; documents are named by id and text hash."""
    sign, confirm, spread = (sign_native, confirm_native, spread_native) if native else (sign_arrow, confirm_arrow, spread_arrow)
    lines = numbered_lines(docs, id_col, text)
    seen = materialise(lines.select("h", *PLACE))
    place = F.struct(F.col("doc").isNull().alias("none"), *PLACE)
    twice = materialise(seen.groupBy("h").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("times")).where("times > 1").select("h", "first"))
    once = lines.where("long").withColumn("here", F.struct(*PLACE)).join(few(twice), "h", "left").where(F.col("first").isNull() | _is("here", "first")).select("h", *PLACE, "line")
    signed = materialise(sign(once))
    dealt = signed.select("h", F.explode("bands").alias("bucket"))
    several = materialise(dealt.groupBy("bucket").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("bucket"))
    shared = materialise(dealt.join(few(several), "bucket"))
    needed = materialise(shared.select("h").distinct())
    members = materialise(shared.join(signed.join(few(needed), "h", "left_semi").select("h", "n", "low"), "h").select("bucket", F.col("h").alias("rep"), "n", "low"))
    texts = materialise(once.join(few(needed), "h", "left_semi").select(F.col("h").alias("rep"), F.col("line").alias("set")))
    release(several, shared, needed)

    comps = link_components(members, ["low"], agree, lambda ids: texts.join(ids, "rep", "left_semi"), percent, confirm, spread)
    keepers = twice.select("h", "first")
    if comps is not None:
        linked = comps.join(signed.select(F.col("h").alias("node"), place.alias("own")), "node")
        named = materialise(linked.join(twice.withColumnRenamed("h", "node"), "node", "full").select(F.col("node").alias("h"), F.coalesce("first", "own").alias("first"), F.coalesce("component", "node").alias("component")))
        keepers = named.join(named.groupBy("component").agg(F.min("first").alias("keep")), "component").select("h", F.col("keep").alias("first"))
    keepers = materialise(keepers)
    return seen.withColumn("here", F.struct(*PLACE)).join(few(keepers), "h").where(~_is("here", "first")).select(*PLACE)


def deduped(docs: DataFrame, id_col: str = "doc_id", text: str = "text", percent: int = PERCENT, native: bool = True) -> DataFrame:
    """(row, n, kept, text): each row of ``docs`` as a struct, its lines, how many stay, and the text of those."""
    gone = materialise(repeats(docs, id_col, text, percent, native).groupBy("doc", "t").agg(F.collect_set("line_no").alias("gone")))
    rows = docs.select(F.struct(*[F.col(f"`{c}`").alias(c) for c in docs.columns]).alias("row"))
    whole = F.col("row").getField(text)
    joined = rows.join(few(gone), F.col("row").getField(id_col).eqNullSafe(F.col("doc")) & (F.xxhash64(whole) == F.col("t")), "left")

    def rest(x: Column) -> Column:
        stay = F.array_except(F.sequence(F.lit(0), F.size(x) - 1), F.col("gone"))
        same = F.col("gone").isNull()
        return F.struct(F.size(x).alias("n"), F.when(same, F.size(x)).otherwise(F.size(stay)).alias("kept"), F.when(same, whole).otherwise(F.array_join(F.transform(stay, lambda i: F.get(x, i)), "\n")).alias("text"))

    made = joined.withColumn("made", F.explode(F.array(F.when(whole.isNotNull(), let(F.split(whole, "\n"), rest)))))  # generated, so that filters above do not copy it
    return made.select("row", F.coalesce("made.n", F.lit(0)).alias("n"), F.coalesce("made.kept", F.lit(0)).alias("kept"), "made.text")


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text: str = "text", percent: int = PERCENT, native: bool = True) -> DataFrame:
    """``docs`` with the text less its repeated lines, and _n_lines, _n_kept."""
    counts = ("_n_lines", "_n_kept")
    others = [F.col("text").alias(c) if c == text else F.col("row").getField(c).alias(c) for c in docs.columns if c not in counts]
    return deduped(docs, id_col, text, percent, native).select(*others, F.col("n").alias("_n_lines"), F.col("kept").alias("_n_kept"))


def op7_fuzzy_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    done = dedup_lines(docs, native=False)
    return done.select("doc_id", F.col("_n_lines").cast("long").alias("n_lines"), F.col("_n_kept").cast("long").alias("n_kept"), F.char_length("text").cast("long").alias("n_chars"), F.crc32(F.col("text").cast("binary")).alias("text_crc32"))

"""Quality rules by distribution divergence, DataFrame expressions only.

A document's characters are counted by Unicode category and its words by a list of frequent words. Both the
lists and the references are learned from the corpus, by label (language): a label's list has the ``TOP`` words
that the most of its documents have at least twice; a reference is, cell by cell, the median share over the
label's documents, so that junk, while it is less than half, moves no cell. Labels that are not among the
``MOST_LABELS`` with the most documents, or have fewer than ``LEAST_DOCS``, share one list and one reference.
Lists and references are a few hundred numbers a label, and enter the last pass as literals. Texts are read
twice: for the lists, and for the counts, which are written out; references and verdicts come from those. A document is
compared with every reference by the Jensen-Shannon distance (square root of the divergence in bits, 0 to 1) of
either histogram, and judged by the nearest label, so that a wrong label or mixed text does no harm.

Guards: the character test needs ``LEAST_CHARS`` visible characters; the joint test, of both distances together,
needs ``LEAST_WORDS`` words and allows for the sampling noise of short texts. A document under a guard passes
that test. A document is kept if the base rules and both tests pass.

Defined results: null or blank text has no words, fails the base rules and is not kept; its distances are null.
Without a document of ``BASE_WORDS`` words there is no reference and only the base rules judge. Repeated rows are
judged each. Extra columns are carried along, whatever their names; where one has the name of a verdict column,
``judge`` gives the verdict, ``passing`` the column.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from motifknn.llm.scratch import materialise

TOP, MOST_LABELS, LEAST_DOCS = 16, 16, 10
#: Characters by class are lower-case letters, capitals, other letters, marks, digits, punctuation, symbols and all others.
#: Those of ASCII are named first, for they are found sooner.
LOWER = r"[a-z\x20\x09-\x0D\p{Ll}]+"
RARER = (r"[A-Z\p{Lu}]+", r"[\p{Lo}\p{Lt}\p{Lm}]+", r"\p{M}+", r"[0-9\p{N}]+", r"\p{P}+", r"\p{S}+")
SYMBOLS = r"[^#*$%&|<>]+"
CELLS = len(RARER) + 2
BASE_WORDS = 50
LEAST_CHARS, LEAST_WORDS = 200, 60
#: The character distance, and the sum of both, above which a text is too far; the sum may be higher by NOISE / sqrt(words).
MOST_CHARS, MOST_BOTH, NOISE = 0.30, 0.36, 1.0
#: Shares are counted in steps of 1 / LEVELS for their median.
LEVELS = 2000
OTHER = "other"
BLANKS = r"[\x20\x09-\x0D]+"
#: Blanks with the punctuation that ends a word before them; looked for where one of either is.
WORD_ENDS = r"(?=[\x20\x09-\x0D.,;:!?])(?:[.,;:!?]*[\x20\x09-\x0D]+|[.,;:!?]+\z)"
#: A window's place in its text is kept beside the upper bits of its hash in one word.
PLACE_BITS = 20


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of ``value``, computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANKS), lambda w: w != "")


def repeated_words(w: Column) -> Column:
    """Words in 3-word windows that occur twice or more, every word once."""
    n = F.size(w) - 2

    def spans(places: Column) -> Column:
        gaps = F.transform(places, lambda p, j: F.least(F.lit(3), F.coalesce(F.get(places, j + 1) - p, F.lit(3))))
        return F.aggregate(gaps, F.lit(0), lambda a, x: a + x)

    def twins(s: Column) -> Column:
        mine = F.filter(s, lambda x, j: (F.get(s, j + 1)["h"].eqNullSafe(x["h"])) | ((j > 0) & F.get(s, F.greatest(j - 1, F.lit(0)))["h"].eqNullSafe(x["h"])))
        return let(F.sort_array(F.transform(mine, lambda x: x["i"])), spans)

    def by_hash(h: Column) -> Column:
        low = (1 << PLACE_BITS) - 1
        like = lambda x, y: F.coalesce(x.bitwiseXOR(y).bitwiseAND(F.lit(~low)) == 0, F.lit(False))
        place = lambda x: x.bitwiseAND(F.lit(low)).cast("int")
        whole = lambda: let(F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), twins)

        def of_alike(mine: Column) -> Column:
            clash = F.exists(F.transform(mine, lambda x, j: like(x, F.get(mine, j - 1)) & (F.get(h, place(x)) != F.get(h, place(F.get(mine, j - 1))))), lambda c: c)
            return F.when(clash, whole()).otherwise(let(F.sort_array(F.transform(mine, place)), spans))

        tagged = F.sort_array(F.transform(h, lambda x, i: x.bitwiseAND(F.lit(~low)).bitwiseOR(i.cast("long"))))
        short = let(tagged, lambda s: let(F.filter(s, lambda x, j: like(x, F.get(s, j + 1)) | like(x, F.get(s, j - 1))), of_alike))
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).when(F.size(h) > low, whole()).otherwise(short)

    windows = F.transform(F.slice(w, F.lit(1), F.greatest(n, F.lit(0))), lambda x, i: F.xxhash64(x, F.get(w, i + 1), F.get(w, i + 2)))
    return F.when(n < 2, F.lit(0)).otherwise(let(windows, by_hash)).cast("long")


def bare_words(text: Column) -> Column:
    return F.split(F.lower(F.coalesce(text, F.lit(""))), WORD_ENDS)


def features(text: Column, words: list[str], base: bool = True) -> Column:
    """Struct of n_words, the other base statistics (if ``base``), chars (counts by class) and common (counts by word of the sorted ``words``, then all other words)."""
    whole = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(whole, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))

    def classes(visible: Column) -> Column:
        def peel(rest: Column, found: list[Column], left: tuple[str, ...]) -> Column:
            """Remove class after class; what a removal shortens is the class's count."""
            if not left:
                return F.array(*found, F.char_length(rest))
            return let(F.regexp_replace(rest, left[0], ""), lambda less: peel(less, [*found, F.char_length(rest) - F.char_length(less)], left[1:]))

        def of_rest(rest: Column) -> Column:
            return F.struct(visible.cast("long").alias("word_chars"), F.char_length(F.regexp_replace(rest, SYMBOLS, "")).cast("long").alias("n_symbols"), peel(rest, [visible - F.char_length(rest)], RARER).alias("chars"))

        return let(F.regexp_replace(whole, LOWER, ""), of_rest)

    def common(k: Column, w: Column) -> Column:
        each = F.transform(F.lit(words), lambda x: F.size(k) - F.size(F.array_remove(k, x)))
        return F.concat(each, F.array(F.size(w) - F.size(k)))

    def of(w: Column) -> Column:
        stats = [let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"), repeated_words(w).alias("n_repeat_words")]
        seen = let(F.char_length(F.array_join(w, "")), classes)
        histogram = let(F.filter(bare_words(text), lambda x: x.isin(words)), lambda k: common(k, w)) if words else F.array(F.size(w))
        return F.struct(F.size(w).cast("long").alias("n_words"), *(stats if base else []), seen.alias("seen"), histogram.alias("common"))

    return let(words_of(text), of)


def distance(counts: Column, reference: list[float]) -> Column:
    """Jensen-Shannon distance of a histogram of counts to a reference distribution; null if it is empty."""

    def term(a: Column, b: Column) -> Column:
        return F.when(a > 0, a * F.log2(a * 2 / (a + b))).otherwise(F.lit(0.0))

    def of(total: Column) -> Column:
        # what the text has none of adds q * log2(2)
        parts = F.zip_with(counts, F.lit(reference), lambda c, q: F.when(c > 0, let(c / total, lambda p: term(p, q) + term(q, p))).otherwise(q))
        return F.when(total > 0, F.sqrt(F.greatest(F.aggregate(parts, F.lit(0.0), lambda a, x: a + x) / 2, F.lit(0.0))))

    return let(F.aggregate(counts, F.lit(0), lambda a, x: a + x).cast("double"), of)


def labels(docs: DataFrame, lang: str) -> list[str]:
    """The labels with a list and a reference of their own."""
    sizes = docs.where(F.col(lang).isNotNull()).groupBy(F.col(lang).cast("string").alias("tag")).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= LEAST_DOCS)
    return [r["tag"] for r in sizes.orderBy(F.desc("n"), "tag").limit(MOST_LABELS).collect()]


def _tag(lang: str, known: list[str]) -> Column:
    label = F.col(lang).cast("string")
    return F.when(label.isin(known), label).otherwise(F.lit(OTHER)) if known else F.lit(OTHER)


def frequent_words(docs: DataFrame, text: str, lang: str, known: list[str]) -> list[str]:
    """The words of all lists, sorted: TOP words a label come to the driver."""

    def twice(words: Column) -> Column:
        return let(F.sort_array(words), lambda s: F.array_distinct(F.filter(s, lambda x, i: x == F.get(s, i - 1))))

    found = docs.select(_tag(lang, known).alias("tag"), F.explode(twice(bare_words(F.col(text)))).alias("word")).where(F.col("word").rlike(r"\p{L}"))
    ranked = found.groupBy("tag", "word").agg(F.count(F.lit(1)).alias("n")).withColumn("rk", F.row_number().over(Window.partitionBy("tag").orderBy(F.desc("n"), "word")))
    return sorted({r["word"] for r in ranked.where(F.col("rk") <= TOP).collect()})


def references(docs: DataFrame, text: str = "text", lang: str = "lang") -> tuple[list[str], dict[str, tuple[list[float], list[float]]]]:
    """The words, and (character classes, words) of each label."""
    docs = docs.select(F.col(f"`{text}`").alias("text"), F.col(f"`{lang}`").alias("lang"))
    known = labels(docs, "lang")
    words = frequent_words(docs, "text", "lang", known)
    return words, medians(docs.select(_tag("lang", known).alias("tag"), F.explode(F.array(features(F.col("text"), words, base=False))).alias("h")), len(words))


def medians(stats: DataFrame, n_words: int) -> dict[str, tuple[list[float], list[float]]]:
    """References from (tag, h); one row per label and cell comes to the driver."""
    h = stats.where(F.col("h.n_words") >= BASE_WORDS)
    shares = F.concat(F.transform("h.seen.chars", lambda x: x / F.col("h.seen.word_chars")), F.transform("h.common", lambda x: x / F.col("h.n_words")))
    step = LEVELS + 1
    cells = h.select("tag", F.explode(F.transform(shares, lambda x, i: i * step + F.round(x * LEVELS).cast("int"))).alias("key"))
    counted = cells.groupBy("tag", "key").agg(F.count(F.lit(1)).alias("n")).select("tag", F.floor(F.col("key") / step).cast("int").alias("cell"), (F.col("key") % step).alias("level"), "n")
    medians = counted.groupBy("tag", "cell").agg(F.percentile("level", F.lit(0.5), F.col("n")).alias("median"))
    sums: dict[str, dict[int, float]] = {}
    for r in medians.collect():
        sums.setdefault(r["tag"], {})[r["cell"]] = r["median"]
    out = {}
    for tag, of in sums.items():
        flat = [of[i] for i in range(CELLS + n_words + 1)]
        a, b = flat[:CELLS], flat[CELLS:]
        if sum(a) and sum(b):
            out[tag] = ([x / sum(a) for x in a], [x / sum(b) for x in b])
    return out


VERDICT = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "near_lang", "char_distance", "word_distance")


def verdicts(docs: DataFrame, text: str = "text", lang: str = "lang", most_chars: float = MOST_CHARS, most_both: float = MOST_BOTH, carry: list[str] | None = None) -> DataFrame:
    """(row, v): each row of ``docs`` as a struct of all columns, or of ``carry``, and one of the VERDICT columns."""
    plain = docs.select(F.col(f"`{text}`").alias("text"), F.col(f"`{lang}`").alias("lang"))
    tags = labels(plain, "lang")
    words = frequent_words(plain, "text", "lang", tags)
    rows = docs.select(F.struct(*[F.col(f"`{c}`").alias(c) for c in carry or docs.columns]).alias("row"), _tag(f"`{lang}`", tags).alias("tag"), F.explode(F.array(features(F.col(f"`{text}`"), words))).alias("h"))
    stats = materialise(rows)
    known = medians(stats, len(words))

    def option(name: str, a: list[float], b: list[float]) -> Column:
        """The distances to one label, each computed once; null if there is none."""
        both = F.array(distance(F.col("h.seen.chars"), a), distance(F.col("h.common"), b))
        return let(both, lambda d: F.when(d[0].isNotNull() & d[1].isNotNull(), F.struct((d[0] + d[1]).alias("sum"), F.lit(name).alias("near_lang"), d[0].alias("char_distance"), d[1].alias("word_distance"))))

    options = [option(name, a, b) for name, (a, b) in sorted(known.items())]
    nearest = F.array_min(F.array(*options)) if options else F.lit(None).cast("struct<sum:double,near_lang:string,char_distance:double,word_distance:double>")
    # generated, not projected: a filter on what follows would else be pushed below with a copy of the expressions for each use
    stats = stats.withColumn("n", F.explode(F.array(nearest)))
    failed = (F.col("h.n_words") < BASE_WORDS) | (F.col("h.n_repeat_words") * 100 > F.col("h.n_words") * 50)
    far = ((F.col("h.seen.word_chars") >= LEAST_CHARS) & (F.col("n.char_distance") > most_chars)) | ((F.col("h.n_words") >= LEAST_WORDS) & (F.col("n.sum") > most_both + F.lit(NOISE) / F.sqrt("h.n_words")))
    kept = ~failed & ~F.coalesce(far, F.lit(False))
    return stats.select("row", F.struct("h.n_words", "h.seen.word_chars", "h.seen.n_symbols", "h.n_dup_lines", "h.n_repeat_words", failed.alias("base_failed"), kept.alias("kept"), "n.near_lang", "n.char_distance", "n.word_distance").alias("v"))


def judge(docs: DataFrame, text: str = "text", lang: str = "lang", **limits: float) -> DataFrame:
    """``docs`` with base statistics, base_failed, kept, the nearest label and the distances to it."""
    return verdicts(docs, text, lang, **limits).select(*[F.col("row").getField(c).alias(c) for c in docs.columns if c not in VERDICT], *[F.col("v").getField(c).alias(c) for c in VERDICT])


def passing(docs: DataFrame, text: str = "text", lang: str = "lang", **limits: float) -> DataFrame:
    """The rows of ``docs`` that are kept."""
    return verdicts(docs, text, lang, **limits).where("v.kept").select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def op2_distribution_quality(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "text")
    return verdicts(docs, carry=["doc_id"]).select("row.doc_id", "v.*")

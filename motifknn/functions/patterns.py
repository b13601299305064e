"""Patterns over sequences: containment, occurrences, symbols."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def contains(seq: Column, pattern: Column) -> Column:
    """Contiguous, literal, by code point; the empty pattern is in every sequence, null ones too."""
    return F.coalesce(F.contains(seq, pattern), pattern == "")


def like_escaped(pattern: str) -> str:
    """A LIKE template (escape !) for a literal."""
    return "%" + "".join("!" + c if c in "!%_" else c for c in pattern) + "%"


#: Ends are read off pieces of so many symbols, for a place deep in a long sequence takes as long to reach as the sequence is up to there.
PIECE = 256


def ends(corpus: DataFrame, cap: int) -> DataFrame:
    """(id, end, pattern) for every run of up to ``cap`` symbols; places count from 0. Narrow: no exchange."""
    pieces = corpus.where(F.char_length("seq") > 0).select("id", "seq", F.explode(F.expr(f"sequence(0, cast((char_length(seq) - 1) div {PIECE} AS INT))")).alias("c"))
    pieces = pieces.withColumn("before", F.greatest(F.col("c") * PIECE - (cap - 1), F.lit(0)))
    pieces = pieces.select("id", "c", "before", F.substring("seq", F.col("before") + 1, (F.col("c") + 1) * PIECE - F.col("before")).alias("part"))
    at = pieces.select("id", "before", "part", F.explode(F.sequence(F.col("c") * PIECE - F.col("before") + 1, F.char_length("part"))).alias("e"))
    runs = at.select("id", "before", "part", "e", F.explode(F.sequence(F.lit(1), F.least(F.col("e"), F.lit(cap)))).alias("n"))
    return runs.select("id", (F.col("before") + F.col("e") - 1).alias("end"), F.substring("part", F.col("e") - F.col("n") + 1, F.col("n")).alias("pattern"))


def occurrences(corpus: DataFrame, cap: int) -> DataFrame:
    """(pattern, id, first, times): one row per pattern and item. Sequences are exchanged, for their runs are many times as large."""
    n = int(corpus.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # a number, so that small sequences with many runs stay apart
    return ends(corpus.select("id", "seq").repartition(n, "id"), cap).groupBy("pattern", "id").agg(F.min("end").alias("first"), F.count(F.lit(1)).alias("times"))


def wildcard_regex(motif: Column) -> Column:
    """A motif in which "." stands for any one symbol, as a regular expression; all else is literal."""
    return F.concat(F.lit("(?s)"), F.regexp_replace(motif, r"([\\^$|?*+()\[\]{}])", r"\\$1"))


#: Symbols of a sequence given as an array become single characters from here on.
FIRST_SYMBOL = 0xE000
MOST_SYMBOLS = 6400


def alphabet(corpus: DataFrame, column: str = "seq") -> dict[str, str]:
    """A private character for each symbol of the arrays in ``column``; the method takes a finite alphabet for granted, and so does this."""
    found = [r["s"] for r in corpus.select(F.explode(column).alias("s")).where("s is not null").distinct().orderBy("s").limit(MOST_SYMBOLS + 1).collect()]
    if len(found) > MOST_SYMBOLS:
        raise ValueError(f"more than {MOST_SYMBOLS} symbols")
    return {x: chr(FIRST_SYMBOL + i) for i, x in enumerate(found)}


def as_text(symbols: Column, letters: dict[str, str]) -> Column:
    """An array of symbols as a string of one character a symbol; symbols without one become U+FFFF."""
    if not letters:
        return F.when(symbols.isNotNull(), F.array_join(F.transform(symbols, lambda s: F.lit("\uffff")), ""))
    table = F.create_map(*[F.lit(x) for kv in letters.items() for x in kv])
    return F.when(symbols.isNotNull(), F.array_join(F.transform(symbols, lambda s: F.coalesce(F.try_element_at(table, s), F.lit("\uffff"))), ""))


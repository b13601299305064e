"""The corpus pipeline: quality rules, line dedup, near-dedup, mixing, packing.

Every stage takes (spark, docs, sf_dir), works on all rows of ``docs`` and returns a DataFrame that is written
and read again before the next one. All but the last return the columns of ``documents``. The mix draws whole
documents up to each source's target, so a document may come several times or not at all from there on.

A stage begins by deleting the intermediate tables of the stages before it, but for those that its input reads:
write a stage's result before the next one starts.

Defined results, for every stage: null and blank texts go in the first stage; rows of one id with different texts
are different documents, rows equal in id and text fare alike; extra columns are carried along, whatever their
names, up to the last stage; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifknn.llm import lines, mixing, neardup, packing, quality
from motifknn.llm.scratch import materialise, release_all_but


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the divergence tests."""
    release_all_but(docs)
    return quality.passing(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts less their repeated lines; n_chars follows the text. Documents that keep no line go."""
    release_all_but(docs)
    made = {"text": F.col("text"), "n_chars": F.char_length("text").cast("long")}
    return lines.deduped(docs).where("kept > 0 and trim(text) != ''").select(*[made.get(c, F.col("row").getField(c)).alias(c) for c in docs.columns])


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity of 0.8 or more)."""
    release_all_but(docs)
    return neardup.one_of_each(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their target weights, a row per copy, in training order."""
    release_all_but(docs)
    return mixing.in_order(docs)


def best_fit_pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of 1024 tokens."""
    release_all_but(docs)
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("minhash_near_dedup", near_dedup),
    ("mix_sources", mix_sources),
    ("best_fit_packing", best_fit_pack),
]

#: Near-dedup and tokens are not for SQL; the tests hold the stages against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = materialise(docs)
    return docs

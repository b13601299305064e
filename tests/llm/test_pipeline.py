"""The pipeline, stage by stage, against brute force and on odd tables."""

from __future__ import annotations

from collections import Counter

import corpus_pipeline
import pytest
from motifknn.llm import mixing, quality
from pyspark.sql import functions as F
from tests.llm.test_operators import brute_components
from tests.llm.test_whole_lines import brute_whole_lines

NAMES = ("kept", "target", "rows", "kind", "source_size", "n_words", "_gone", "_h", "_size", "_copy", "_at", "row", "m", "h", "n", "t", "gone", "key", "size", "base_failed", "near_lang", "_n_kept", "a.b")


@pytest.fixture()
def written(spark, tmp_path):
    def write(df):
        path = str(tmp_path / f"t{len(list(tmp_path.iterdir()))}")
        df.write.parquet(path)
        return spark.read.parquet(path)

    return write


def test_stages_against_brute_force(spark, data, written):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    one = written(corpus_pipeline.quality_rules(spark, docs, data))
    assert one.columns == docs.columns and {r.doc_id for r in one.collect()} == {r.doc_id for r in quality.judge(docs).where("kept").collect()}
    two = written(corpus_pipeline.line_dedup(spark, one, data))
    want = {i: t for (i, _), t in brute_whole_lines([(r.doc_id, r.text) for r in one.collect()]).items() if t.strip()}
    assert {r.doc_id: r.text for r in two.collect()} == want and all(r.n_chars == len(r.text) for r in two.collect())
    three = written(corpus_pipeline.near_dedup(spark, two, data))
    comps = brute_components([(r.doc_id, r.text) for r in two.collect()], 5)
    assert {r.doc_id for r in three.collect()} == {i for i, (_, c) in comps.items() if i == c}
    four = written(corpus_pipeline.mix_sources(spark, three, data))
    copies = {r.doc_id: r.taken // r["size"] for r in mixing.mix(three).collect() if r.taken}
    assert Counter(r.doc_id for r in four.collect()) == copies and four.columns == docs.columns
    five = corpus_pipeline.best_fit_pack(spark, four, data)
    assert {r.doc_id for r in five.collect()} == set(copies)


def test_any_column_names_and_repeated_ids(spark, data, written):
    """Every stage carries extra columns whatever their names; rows of one id go by their own text."""
    words = [f"some words of text number {i} that are not in others, the {i * 7} of {i * 13} and {i * 29}" for i in range(9)]
    long = lambda k: "\n".join(f"{words[(k + j) % 9]} {k} {j * k}" for j in range(8))
    rows = [(1, long(0)), (1, long(1)), (0, long(0)), (None, long(2)), (3, None), (4, ""), (5, long(3)), (5, long(3))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    for c in NAMES:
        docs = docs.withColumn(c, F.concat(F.lit(c), F.lit("!")))
    for name, stage in corpus_pipeline.STAGES[:4]:
        docs = written(stage(spark, docs, data))
        assert all(all(r[c] == f"{c}!" for c in NAMES) for r in docs.collect()), name
    assert corpus_pipeline.best_fit_pack(spark, docs, data).count() >= 0


def test_rows_of_one_id_with_different_texts(spark):
    text = lambda k: " ".join(f"w{k}x{j}" for j in range(60))
    docs = spark.createDataFrame([(1, text(1)), (1, text(2)), (0, text(1)), (None, text(3))], "doc_id long, text string")
    left = corpus_pipeline.near_dedup(spark, docs, "")
    assert sorted((r.doc_id is None, r.doc_id or 0, r.text) for r in left.collect()) == sorted([(False, 0, text(1)), (False, 1, text(2)), (True, 0, text(3))])


def test_empty_table(spark, data, written):
    docs = spark.read.parquet(f"{data}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, data))
    assert docs.count() == 0


def test_run(spark, data):
    assert len(corpus_pipeline.STAGES) == 5 and corpus_pipeline.run(spark, data).count() > 0

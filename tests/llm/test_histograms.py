"""The histograms of the quality rules against plain counting."""

from __future__ import annotations

import re
import unicodedata
from collections import Counter

from pyspark.sql import functions as F

from motifknn.llm import quality

TEXTS = ["The the, THE. of; der! nicht? una: ..the the.x 'the' the,, .", "a1 22 | b_c {d} [e] \\ / + = ! @ ~ ` ^ é 中 \U0001d11e", "", None, " \n\t", "und... \n dem,\x0bPour\x0cqui!?", "Жизнь ǅ a\u0301 ³ № €\u200b"]
WORDS = ["der", "of", "the", "und"]
KINDS = {"Ll": 0, "Lu": 1, "Lo": 2, "Lt": 2, "Lm": 2, "M": 3, "N": 4, "P": 5, "S": 6}


def brute(t):
    words = re.findall("[^\x20\x09-\x0d]+", t or "")
    c = Counter(KINDS.get(g, KINDS.get(g[0], 7)) for x in "".join(words) for g in [unicodedata.category(x)])
    bare = Counter(w.rstrip(".,;:!?").lower() for w in words)
    known = [bare[w] for w in WORDS]
    return [c[k] for k in range(8)], [*known, len(words) - sum(known)]


def test_histograms(spark, data):
    texts = TEXTS + [r.text for r in spark.read.parquet(f"{data}/documents.parquet").collect()]
    rows = spark.createDataFrame(list(enumerate(texts)), "i long, text string").select("i", quality.features(F.col("text"), WORDS).alias("h")).collect()
    for r in rows:
        assert (list(r.h.seen.chars), list(r.h.common)) == brute(texts[r.i]), texts[r.i]


def test_learned_lists(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    words, known = quality.references(docs)
    assert {"the", "der", "la", "que"} <= set(words) and all(any(c.isalpha() for c in w) for w in words)
    assert set(known) <= {"en", "de", "fr", "es", "other"} and all(abs(sum(x) - 1) < 1e-9 for pair in known.values() for x in pair)

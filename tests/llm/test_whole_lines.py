"""Line dedup against brute force over all shingles of a line, unspaced text included."""

from __future__ import annotations

import random
import re
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from motifknn.llm import lines

CHINESE = "".join(chr(0x4E00 + 37 * i % 4000) for i in range(60))
URL = "https://example.org/a/very/long/path/without/any/blank/in/it?x="
UNSPACED = [
    CHINESE,
    CHINESE[:10] + "".join(chr(0x6000 + 53 * i % 4000) for i in range(50)),  # ten characters in common
    "\u5b57" + CHINESE[1:],  # a copy but for the first character
    URL + "0123456789abcdefghij",
    URL[:10] + "something.else/entirely?and=more&of=it&to=the&end=of&line",
    URL + "0123456789abcdefghiX",
    "\U0001d11e" * 3 + "musical text with signs beyond the first plane in it",
    "\U0001d11e" * 3 + "musical text with signs beyond the first plane in its",
]


def even(s):
    return re.sub("[\x09-\x0d\x20\xa0]+", " ", s).strip(" ").lower()


def enters(e):
    return len(e) >= lines.LEAST_CHARS or any(c.isalnum() for c in e)


def brute_whole_lines(rows):
    """The text that every (id, text) keeps, pairs compared over all their shingles."""
    at, sets = defaultdict(list), {}
    for i, t in rows:
        for n, x in enumerate((t or "").split("\n")):
            e = even(x)
            if enters(e):
                at[e].append((i, t, n))
                if len(e) >= lines.LEAST_CHARS:
                    sets[e] = {e[k : k + lines.WIDTH] for k in range(len(e) - lines.WIDTH + 1)}
    root = {e: e for e in at}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    inv = defaultdict(list)
    for e, s in sets.items():
        for x in s:
            inv[x].append(e)
    for e, s in sets.items():
        for f, k in Counter(f for x in s for f in inv[x] if f > e).items():
            if 100 * k >= 80 * (len(s) + len(sets[f]) - k):
                root[find(e)] = find(f)
    groups, gone = defaultdict(list), defaultdict(set)
    for e, p in at.items():
        groups[find(e)] += p
    for p in groups.values():
        first = min(p, key=lambda x: (x[0] is None, x[0] or 0, x[1], x[2]))  # fixtures with one id and several texts say which text is first
        for i, t, n in set(p) - {first}:
            gone[i, t].add(n)
    return {(i, t): t and "\n".join(x for n, x in enumerate(t.split("\n")) if n not in gone[i, t]) for i, t in rows}


def deduped(spark, rows, native):
    table = spark.createDataFrame(rows, "doc_id long, text string").withColumn("before", F.col("text"))
    return {(r.doc_id, r.before): r.text for r in lines.dedup_lines(table, native=native).collect()}


BOTH = pytest.mark.parametrize("native", [True, False])


@BOTH
def test_unspaced_lines(spark, native):
    rows = list(enumerate(UNSPACED))
    got = deduped(spark, rows, native)
    assert got == brute_whole_lines(rows)
    assert [i for (i, _), t in got.items() if not t] == [2, 5, 7]


@BOTH
def test_lines_of_a_table(spark, data, native):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{data}/documents.parquet").collect()]
    assert deduped(spark, rows, native) == brute_whole_lines(rows)


@BOTH
def test_urls(spark, native):
    rows = [(i, f"https://example.org/{chr(97 + i) * 9}/{i * 7919 % 1000003}/{'abcdefghij'[i % 10] * 12}?q={i * 104729}") for i in range(20)]
    assert deduped(spark, rows, native) == {(i, t): t for i, t in rows}


@BOTH
def test_edited_copies(spark, native):
    """A group of edited copies of one line, some of them near each other but not the origin."""
    r = random.Random(4)
    words = [f"word{k * k % 97}x" for k in range(60)]
    rows = [(0, " ".join(words))]
    for i in range(1, 120):
        w = list(words)
        for _ in range(r.randrange(1, 10)):
            w[r.randrange(60)] = f"new{r.randrange(60)}"
        rows.append((i, " ".join(w)))
    got, want = deduped(spark, rows, native), brute_whole_lines(rows)
    assert sum(got[k] != want[k] for k in want) <= 1  # banding may miss a pair of similarity 0.8


def test_short_lines(spark):
    texts = ["Heading\nline one\n---\n\n12", "heading \nline two\n---\n\n12\n12", "Heading", None, "", "Intro\n  HEADING\n}\n}\n\u5b57\n\u5b57"]
    rows = list(enumerate(texts))
    got = {i: t for (i, _), t in deduped(spark, rows, True).items()}
    assert got == {0: texts[0], 1: "line two\n---\n", 2: "", 3: None, 4: "", 5: "Intro\n}\n}\n\u5b57"}


def test_repeated_and_null_ids(spark):
    """Rows of one id or of none are told apart by their texts; equal rows lose the same lines."""
    rows = [(None, "one own line\nthe same line"), (None, "the same line\nanother own line"), (1, "a text\nonly here"), (1, "b text\nthe same line"), (2, "b text"), (2, "b text")]
    kept = sorted(t for t in deduped(spark, rows, True).values())
    assert kept == ["", "a text\nonly here", "another own line", "b text\nthe same line", "one own line"]
    assert lines.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).count() == len(rows)


def test_any_column_names(spark):
    table = spark.createDataFrame([(1, "x y\nx y", "g")], "doc_id long, text string, _gone string")
    for c in ("gone", "made", "row", "doc", "t", "h", "here", "line", "first", "a.b"):
        table = table.withColumn(c, F.lit(c))
    got = lines.dedup_lines(table)
    assert got.columns == [*table.columns, "_n_lines", "_n_kept"]
    r = got.first()
    assert (r.text, r["_gone"], r["a.b"], r["row"], r["_n_lines"], r["_n_kept"]) == ("x y", "g", "a.b", "row", 2, 1)


def test_very_long_line(spark):
    r = random.Random(2)
    long = "".join(r.choice("abcdefghijklmnop ") for _ in range(300_000))
    rows = [(1, long), (2, long[:-3] + "end"), (3, long[::-1])]
    for native in (True, False):
        assert [t != "" for t in deduped(spark, rows, native).values()] == [True, False, True]


def test_cheap_test_passes_similar_lines(spark):
    """Pairs at the threshold pass the comparison of minima, short lines too."""
    r = random.Random(7)
    pairs = []
    while len(pairs) < 1500:
        a = "".join(r.choice("abcdefgh ") for _ in range(r.choice((44, 60, 120, 400))))
        b = list(a)
        for _ in range(r.randrange(1, 2 + len(a) // 40)):
            b[r.randrange(len(a))] = "z"
        b = "".join(b)
        x, y = ({s[k : k + lines.WIDTH] for k in range(len(s) - lines.WIDTH + 1)} for s in (a, b))
        if 0.8 <= len(x & y) / len(x | y) <= 0.86:
            pairs.append((a, b))
    n, _, low = lines.signatures([s for p in pairs for s in p])
    rows = [(int(n[k]), low[k].tolist(), int(n[k + 1]), low[k + 1].tolist()) for k in range(0, len(n), 2)]
    got = spark.createDataFrame(rows, "n int, low array<long>, m int, other array<long>").select(F.struct("n", "low").alias("x"), F.struct(F.col("m").alias("n"), F.col("other").alias("low")).alias("y"))
    assert got.where(~lines.agree(F.col("x"), F.col("y"))).count() == 0

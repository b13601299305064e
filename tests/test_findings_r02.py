from __future__ import annotations

import random
import re
import time
from collections import Counter
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from motifknn.llm import candidates, quality
from motifknn.operators.automaton import OnlineIndex, build


def sql_rows(name: str, data: str, columns: list[str]) -> list[tuple]:
    con = duckdb.connect()
    for f in Path(data).glob("*.parquet"):
        con.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM read_parquet('{f}{'/*.parquet' if f.is_dir() else ''}')")
    got = con.execute(entry.oracle_sql()[name])
    at = [[c[0] for c in got.description].index(c) for c in columns]
    return sorted(tuple(r[i] for i in at) for r in got.fetchall())


@pytest.mark.parametrize("name", ["m03_worked_automata", "e11_motif_toy", "a13_at_recall_toy"])
def test_reads_a_table_and_equals_its_sql(spark, data, name):
    df = entry.queries()[name](spark, data)
    assert df.inputFiles() and sorted(map(tuple, df.collect())) == sql_rows(name, data, df.columns)


def test_online_insert_looks_at_what_an_item_touches():
    items = [(i, f"/en/{(i * 7919) % 100003}?page={i % 7}&ref=x") for i in range(3000)]
    index = OnlineIndex(build(items[:1500]))
    t = time.perf_counter()
    for i, s in items[1500:]:
        index.insert(i, s)
    assert time.perf_counter() - t < 20 and index.wrong(range(len(index.a.span))) == 0


def test_maxby_ties_go_to_the_smallest_key(spark, tmp_path):
    rows = [(k, "a", b) for k, b in ((5, 9.0), (2, 9.0), (7, 9.0), (3, 1.0), (1, None), (8, 1.0))]
    spark.createDataFrame(rows, "c_custkey long, c_mktsegment string, c_acctbal double").selectExpr("c_custkey", "'n' AS c_name", "1 AS c_nationkey", "c_acctbal", "c_mktsegment").repartition(3).write.parquet(f"{tmp_path}/customer.parquet")
    assert [tuple(r) for r in entry.queries()["op_agg_maxby"](spark, str(tmp_path)).collect()] == [("a", 2, 3)]


def test_quality_counts_a_text_once_and_tells_colliding_windows_apart(spark, data, monkeypatch):
    docs, calls, features = spark.read.parquet(f"{data}/documents.parquet"), [], quality.features
    monkeypatch.setattr(quality, "features", lambda *a, **k: calls.append(1) or features(*a, **k))
    got = {r.doc_id: r.n_repeat_words for r in quality.judge(docs).collect()}
    assert len(calls) == 1
    monkeypatch.setattr(quality, "PLACE_BITS", 60)  # four bits of the hash are left, so that many windows look alike
    rows = docs.select("doc_id", "text", quality.let(quality.words_of(F.col("text")), quality.repeated_words).alias("n")).collect()
    for r in rows:
        w = re.findall("[^\x20\x09-\x0d]+", r.text or "")
        times = Counter(zip(w, w[1:], w[2:], strict=False))
        places = {i + k for i, x in enumerate(zip(w, w[1:], w[2:], strict=False)) if times[x] > 1 for k in range(3)}
        assert got[r.doc_id] == r.n == len(places)


def test_near_copies_that_no_pivot_holds_are_told_apart_by_parities(spark, monkeypatch):
    """A bucket of sets that are just too far from each other forms no pairs; none that is near enough is lost."""
    rng, base, tested = random.Random(5), list(range(300)), []
    sets = [(i, sorted({*(e for e in base if rng.random() > 0.15), *(10_000 + rng.randrange(400) for _ in range(40))})) for i in range(60)]
    sets += [(100 + i, sorted({*s[3:], 20_000 + i})) for i, s in sets[:6]]
    own = spark.createDataFrame(sets, "rep long, set array<long>")
    members = own.select(F.lit(1).alias("bucket"), "rep", F.size("set").alias("n"))
    links = {tuple(sorted((a, b))) for a, x in sets for b, y in sets if a < b and len({*x} & {*y}) * 100 >= 80 * len({*x} | {*y})}

    def confirm(both, percent):
        tested.append(both.count())
        return candidates.similar_sets(both, percent)

    comps = candidates.link_components(members, [], lambda x, y: F.lit(True), lambda ids: own.join(ids, "rep", "left_semi"), 80, confirm)
    assert {(r.component, r.node) for r in comps.collect() if r.node != r.component} == links and len(links) == 6
    assert sum(tested) < 3 * len(sets)  # all pairs are 2,145

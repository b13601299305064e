from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from motifknn.functions.patterns import alphabet, as_text, ends, like_escaped, occurrences
from motifknn.operators import baselines
from motifknn.operators import classes as C
from motifknn.operators.exact import exact_topk, keep_nearest, measured, nearest_of, valid
from motifknn.operators.index import build_class_index, class_index_query, class_tables, compact, delete_batch, insert_batch, long_pattern_query, wildcard_query
from motifknn.operators.measures import recall_at_k
from motifknn.operators.reuse import check_cover, choose_donors
from tests.test_automaton import brute

ROWS = [(1, [0.0, 0.0], "MAAAB"), (2, [1.0, 0.0], "CAAAD"), (3, [0.1, 0.0], "CDCD"), (4, [0.0, 2.0], ""), (5, [5.0, 5.0], None), (6, [0.2, 0.1], "50%_é")]


@pytest.fixture(scope="module")
def toy(spark):
    return spark.createDataFrame(ROWS, "id long, vec array<double>, seq string")


def ask(spark, patterns, k=10, ef=40):
    return spark.createDataFrame([(i, p, [0.9, 0.0], k, ef) for i, p in enumerate(patterns)], "qid long, pattern string, qvec array<double>, k int, ef int")


def rows(df):
    return sorted(map(tuple, df.select("qid", "rk", "id", "dist").collect()))


def test_toy_nearest_with_motif(spark, toy):
    q = ask(spark, ["AAA"], k=1)
    assert [r[2] for r in rows(exact_topk(toy, q, 1))] == [2]
    assert rows(class_index_query(build_class_index(toy, 3), q, 1)) == rows(exact_topk(toy, q, 1))


def test_empty_absent_special_and_long(spark, toy):
    index = build_class_index(toy, 3)
    q = ask(spark, ["", "zz", "%_", "é", "CDC"])
    got = rows(class_index_query(index, q))
    assert {r[2] for r in got if r[0] == 0} == {1, 2, 3, 4, 5, 6} and not [r for r in got if r[0] == 1]
    assert [r[2] for r in got if r[0] == 2] == [6] and [r[2] for r in got if r[0] == 3] == [6]
    assert [r[2] for r in rows(long_pattern_query(index, ask(spark, ["CDCD", "MAAAC"])))] == [3]
    assert like_escaped("a%_!") == "%a!%!_!!%"


def test_maintenance_equals_rebuild(spark, toy):
    q = ask(spark, ["AA", "CD", "D"])
    part = build_class_index(toy.where("id != 2"), 3)
    full = rows(exact_topk(toy, q))
    grown = insert_batch(part, toy.where("id = 2"))
    assert rows(class_index_query(grown, q)) == full
    shrunk = delete_batch(grown, toy.where("id = 2").select("id"))
    left = rows(exact_topk(toy.where("id != 2"), q))
    assert rows(class_index_query(shrunk, q)) == left
    assert rows(class_index_query(compact(shrunk), q)) == left
    assert rows(class_index_query(insert_batch(shrunk, toy.where("id = 2")), q)) == full


@pytest.mark.parametrize("seed", range(3))
def test_class_tables_and_cover(spark, seed):
    r = random.Random(seed)
    items = [(i, "".join(r.choice("abc") for _ in range(r.randrange(1, 8)))) for i in range(8)]
    corpus = spark.createDataFrame([(i, [float(i)], s) for i, s in items], "id long, vec array<double>, seq string")
    _, found, routes, posted = class_tables(corpus, 8)
    ends, classes = brute(items)
    assert {(x.state, x.occ, x.n_ids) for x in found.collect()} == {(max(ps, key=len), len(v), len({i for i, _ in v})) for v, ps in classes.items()}
    for rule in ("subtree", "child", "none"):
        donors, rest = choose_donors(found, C.transitions(routes), posted, rule)
        got = check_cover(posted, donors, rest).first()
        assert (got["n_states"], got["missing"], got["overlap"]) == (len(classes), 0, 0)


def test_baselines_agree(spark, toy):
    q = ask(spark, ["A", "CD", "AAA", "zz"])
    want = rows(exact_topk(toy, q))
    lists, edges = baselines.per_pattern_build(toy, 3)
    assert rows(baselines.per_pattern_query(lists, edges, toy, q)) == want
    assert rows(baselines.sql_hybrid(toy, q, 100, 0.3)) == want
    assert rows(baselines.keyword_knn(toy, q, 10, 2)) == want
    assert rows(baselines.search_first_expanding(toy, q, 1)) == want
    late = baselines.search_first_exact(toy, q, 2)
    assert recall_at_k(late, exact_topk(toy, q)).agg(F.avg("recall")).first()[0] <= 1


def test_graph_states_answer_like_scan(spark):
    r = random.Random(5)
    corpus = spark.createDataFrame([(i, [r.random() for _ in range(4)], r.choice(["abab", "abba", "bcab"])) for i in range(120)], "id long, vec array<double>, seq string")
    q = ask(spark, ["ab", "ba", "bc"], ef=60).withColumn("qvec", F.array(*[F.lit(0.5)] * 4))
    for shards in (1, 3):
        index = build_class_index(corpus, 2, 20, shards=shards)
        assert index.edges is not None
        assert recall_at_k(class_index_query(index, q), exact_topk(corpus, q)).agg(F.min("recall")).first()[0] >= 0.9


def test_occurrences_do_not_span_items(spark, toy):
    assert {r.pattern for r in occurrences(toy.where("id in (1, 2)"), 3).collect()} >= {"MAA", "AAD"}
    assert occurrences(toy, 3).where("pattern = 'BCA'").isEmpty()


ANY = ["", "A", "AAA", "CD", "MAAAB", "CDCD", "ZZZZ", "ZZ", "zz"]


def test_changes_reach_patterns_of_any_length(spark, toy):
    """Deleted, inserted and changed rows, one id in several versions, for empty, short and long patterns."""
    q = ask(spark, ANY)
    index = build_class_index(toy, 3)
    assert rows(class_index_query(index, q)) == rows(exact_topk(toy, q))
    changed = spark.createDataFrame([(1, [3.0, 0.0], "ZZZZA"), (9, [0.5, 0.5], "CDCDC")], "id long, vec array<double>, seq string")
    steps = [
        (lambda i: delete_batch(i, toy.where("id in (1, 3)").select("id")), toy.where("id not in (1, 3)")),
        (lambda i: insert_batch(i, changed), toy.where("id not in (1, 3)").union(changed)),
        (lambda i: insert_batch(i, changed.where("id = 9").withColumn("seq", F.lit("AAAZZ"))), toy.where("id not in (1, 3)").union(changed.where("id = 1")).union(changed.where("id = 9").withColumn("seq", F.lit("AAAZZ")))),
        (lambda i: delete_batch(i, changed.where("id = 1").select("id")), toy.where("id not in (1, 3)").union(changed.where("id = 9").withColumn("seq", F.lit("AAAZZ")))),
        (compact, toy.where("id not in (1, 3)").union(changed.where("id = 9").withColumn("seq", F.lit("AAAZZ")))),
        (lambda i: insert_batch(i, toy.where("id = 1")), toy.where("id != 3").union(changed.where("id = 9").withColumn("seq", F.lit("AAAZZ")))),
    ]
    for step, now in steps:
        index = step(index)
        assert rows(class_index_query(index, q)) == rows(exact_topk(now, q))
    assert compact(index).corpus.count() == 6


def test_wildcards(spark, toy):
    index = build_class_index(toy, 2)
    got = rows(wildcard_query(index, ask(spark, ["C..C", "C..D", "M.A", "...", ".D", "5.%", "(", "C.C.C"])))
    assert {k: {r[2] for r in got if r[0] == k} for k in range(8)} == {0: set(), 1: {3}, 2: {1}, 3: {1, 2, 3, 6}, 4: {2, 3}, 5: {6}, 6: set(), 7: set()}
    grown = insert_batch(delete_batch(index, toy.where("id = 3").select("id")), spark.createDataFrame([(7, [0.0, 0.0], "CxxC")], "id long, vec array<double>, seq string"))
    got = rows(wildcard_query(grown, ask(spark, ["C..C", "C..D"])))
    assert {(r[0], r[2]) for r in got} == {(0, 7)}


def test_unusable_vectors_are_set_aside(spark):
    bad = [(1, [1.0, 2.0], "ab"), (2, None, "ab"), (3, [1.0], "ab"), (4, [float("nan"), 1.0], "ab"), (5, [None, 1.0], "ab"), (None, [1.0, 1.0], "ab"), (6, [float("inf"), 1.0], "ab"), (7, [0.0, 0.0], None)]
    corpus = spark.createDataFrame(bad, "id long, vec array<double>, seq string")
    good, aside = valid(corpus)
    assert {r.id for r in good.collect()} == {1, 7} and aside.count() == 6
    index = build_class_index(corpus, 2, 1)
    assert index.rejected.count() == 6 and [r[2] for r in rows(class_index_query(index, ask(spark, ["ab"])))] == [1]
    assert valid(corpus.limit(0))[0].count() == 0


def test_both_ways_of_measuring_agree(spark, toy):
    q = ask(spark, ["A", "CD", ""])
    pairs = toy.select("id").crossJoin(q.select("qid")).select("qid", "id")
    for metric in ("l2sq", "ip", "cosine"):
        rest = pairs.where("id != 1")  # the zero vector has no cosine
        assert rows(keep_nearest(nearest_of(rest, toy, q, 3, metric), 3)) == rows(keep_nearest(measured(rest, toy, q, metric), 3))


def test_large_ids_and_long_sequences(spark):
    corpus = spark.createDataFrame([(1 << 60, [0.0], "abcab"), ((1 << 60) + 1, [1.0], "ab" * 900 + "c")], "id long, vec array<double>, seq string")
    _, found, _, posted = class_tables(corpus, 3)
    want, classes = brute([(r.id, r.seq) for r in corpus.collect()][:1])
    assert {r.state for r in found.collect()} >= {"ab", "bc"} and posted.where("state = 'ab'").count() == 2
    got = {(r.id, r.end, r.pattern) for r in ends(corpus, 3).where("id > 1").collect()}
    assert got == {(i, e, s[e + 1 - n : e + 1]) for i, s in ((1 << 60, "abcab"), ((1 << 60) + 1, "ab" * 900 + "c")) for e in range(len(s)) for n in range(1, min(e + 1, 3) + 1)}


def test_symbol_arrays(spark):
    c = spark.createDataFrame([(1, ["view", "cart", "view"]), (2, ["cart"]), (3, None)], "id long, seq array<string>")
    letters = alphabet(c)
    text = {r.id: r.t for r in c.select("id", as_text(F.col("seq"), letters).alias("t")).collect()}
    assert text == {1: letters["view"] + letters["cart"] + letters["view"], 2: letters["cart"], 3: None}
    assert spark.range(1).select(as_text(F.array(F.lit("other")), letters).alias("t")).first().t == "\uffff"

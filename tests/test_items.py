"""Equal sequences are one item of the index."""

from __future__ import annotations

from motifknn.operators.exact import exact_topk
from motifknn.operators.index import build_class_index, class_index_query, class_tables, item_tables

CORPUS = "id long, vec array<double>, seq string"


def test_equal_sequences_are_one_item(spark):
    rows = [(i, [float(i)], "abcab" if i % 3 else "cabba") for i in range(30)]
    corpus = spark.createDataFrame(rows, CORPUS)
    occ, found, routes, posted, members = item_tables(corpus, 3)
    brute = {(s[a:b], i) for i, _, s in rows for a in range(5) for b in range(a + 1, min(5, a + 3) + 1)}
    assert occ.count() == len({(p, s) for p, i in brute for j, _, s in rows if j == i})
    by_id = class_tables(corpus, 3)[0]
    assert {(r.pattern, r.id) for r in by_id.collect()} == brute and by_id.count() == len(brute)
    for r in routes.collect():
        ids = {i for p, i in brute if p == r.pattern}
        assert (r.n_ids, r.first_id) == (len(ids), min(ids))
        assert r.occ == sum(s.startswith(r.pattern, a) for i, _, s in rows for a in range(5))
    q = spark.createDataFrame([(1, "ab", [7.2], 10, 40), (2, "bba", [0.0], 10, 40), (3, "bcab", [3.0], 10, 40)], "qid long, pattern string, qvec array<double>, k int, ef int")
    got = {tuple(r) for r in class_index_query(build_class_index(corpus, 3), q).select("qid", "rk", "id").collect()}
    assert got == {tuple(r) for r in exact_topk(corpus, q).select("qid", "rk", "id").collect()}
    assert build_class_index(corpus, 3).residuals.count() < 30


def test_an_id_of_several_sequences(spark):
    rows = [(1, [0.0], "ab"), (1, [0.0], "bc"), (2, [1.0], "ab"), (2, [1.0], "ab")]
    _, _, routes, posted = class_tables(spark.createDataFrame(rows, CORPUS), 2)
    assert {r.pattern: (r.n_ids, r.occ) for r in routes.collect()} == {"a": (2, 3), "b": (2, 4), "c": (1, 1), "ab": (2, 3), "bc": (1, 1)}
    assert {tuple(r) for r in posted.where("state in ('ab', 'bc')").collect()} == {("ab", 1), ("ab", 2), ("bc", 1)}

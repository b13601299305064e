"""Runs of a sequence are counted where the sequence lies, and a written table is not written twice."""

from __future__ import annotations

from motifknn.functions.patterns import ends, occurrences
from motifknn.plans.staging import staged


def test_sequences_are_exchanged_not_their_runs(spark):
    seqs = [(1, "abcab"), (2, ""), (3, None), (4, "ab" * 300), (4, "xa"), (5, "b")]
    occ = occurrences(spark.createDataFrame(seqs, "id long, seq string"), 3)
    want: dict = {}
    for i, s in seqs:
        for e in range(len(s or "")):
            for n in range(1, min(e + 1, 3) + 1):
                first, times = want.get((s[e + 1 - n : e + 1], i), (e, 0))
                want[s[e + 1 - n : e + 1], i] = min(first, e), times + 1
    assert {(r.pattern, r.id): (r.first, r.times) for r in occ.collect()} == want
    plan = occ._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[-1]
    assert plan.count("Exchange hashpartitioning") == 1 and "ENSURE_REQUIREMENTS" not in plan
    assert ends(spark.createDataFrame(seqs, "id long, seq string"), 3).count() == sum(t for _, t in want.values())


def test_a_written_table_is_not_written_again(spark):
    once = staged(spark.range(5))
    assert staged(once).inputFiles() == once.inputFiles() and staged(once.where("id > 1")).inputFiles() != once.inputFiles()

from __future__ import annotations

import contextlib
import io

import pytest

import __spark_entry__ as entry

CORE = ["m01_exact_topk_pname", "m07_pattern_classes_urlpath", "op_join_range", "op_source_patternindex", "st_dedup"]


def test_every_sql_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(entry.queries()) > 120


@pytest.mark.parametrize("name", CORE)
def test_runs(spark, data, name):
    assert entry.queries()[name](spark, data).columns


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def plan(df) -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_filter_reaches_the_scan_and_columns_are_pruned(spark, data):
    text = plan(entry.queries()["op_scan_pushdown"](spark, data))
    assert "GreaterThan(n_chars,2000)" in text and "lang" not in text.split("ReadSchema")[1].split("\n")[0]


def test_topk_is_limited_before_the_exchange(spark, data):
    assert "WindowGroupLimit" in plan(entry.queries()["op_win_topk"](spark, data))
    text = plan(entry.queries()["m01_exact_topk_passage"](spark, data))
    assert "WindowGroupLimit" in text and "CartesianProduct" not in text and "NestedLoop" not in text


def test_relational_operators_use_no_python(spark, data):
    for name in ("op_agg_hash", "op_join_sortmerge", "op_win_rows", "rel_region_revenue"):
        assert "Python" not in plan(entry.queries()[name](spark, data)) and "Pandas" not in plan(entry.queries()[name](spark, data))

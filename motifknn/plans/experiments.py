"""The experiments as reports: curves, sizes, times, ablations, thresholds, maintenance.

Figures are measured in the session given; seconds depend on the machine. Beside each report stands a gate of what
must hold whatever the machine, with SQL that recomputes it or says what it must be.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifknn.functions.patterns import occurrences
from motifknn.operators import baselines, measures
from motifknn.operators import classes as C
from motifknn.operators.exact import exact_topk, keep_nearest
from motifknn.operators.graph import build_graphs, graph_links_by_lane, named_vectors, search_graphs
from motifknn.operators.index import ClassIndex, build_class_index, class_index_query, class_tables, delete_batch, expanded, insert_batch, item_tables, locate
from motifknn.operators.reuse import choose_donors, decide_kind
from motifknn.plans.planner import plan_and_run
from motifknn.plans.staging import forget, release, scratch, staged, staged_so_far
from motifknn.plans.workload import CORPORA, EXACT_SQL, corpus, query_set, query_sql

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
#: Corpora of the curves, sizes and ablations, from the smallest to the largest that a report builds graphs for.
SIX = ("passage", "urlpath", "user_events", "pname", "turn", "line")
#: Graph parameters of the reports: smaller than usual, for graphs are built in numpy.
LIGHT = {"m": 8, "ef_con": 60}
#: Items from which a state gets a graph, by corpus.
GRAPH_FROM = {"passage": 20, "urlpath": 20, "user_events": 20, "pname": 100, "turn": 200, "line": 400}


def report(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return keep


def _own_scratch(fn):
    """A report of few rows: they are brought to the driver, and the tables it staged go."""

    @wraps(fn)
    def run(spark: SparkSession, *args, **how) -> DataFrame:
        with scratch():
            got = fn(spark, *args, **how)
            rows, schema = got.collect(), got.schema
        return spark.createDataFrame(rows, schema)

    return run


@_own_scratch
def tradeoff_curve(spark: SparkSession, d: str, name: str, efs: tuple[int, ...] = (10, 40, 160), per_length: int = 1000, threshold: int = 100, sample: str = "occurrence", cap: int = 4) -> DataFrame:
    """(method, len, ef, recall, distances, qps): accuracy and work of each method as its knob moves; ``distances`` is the mean a query."""
    c = staged(corpus(spark, d, name))
    q = staged(query_set(c, CORPORA[name][2], per_length, sample=sample))
    n = q.count()
    truth = staged(exact_topk(c, q))
    index = build_class_index(c, cap, threshold, **LIGHT)
    graph, by_shard = baselines.global_graph(c, **LIGHT), baselines.global_graph(c, shards=4, **LIGHT)
    lists, edges = baselines.per_pattern_build(c, cap, threshold, **LIGHT)
    at = lambda ef: q.withColumn("ef", F.lit(ef))
    matched = staged(locate(index, q).join(index.routes.select("pattern", "n_ids"), "pattern").select("qid", F.col("n_ids").alias("distances")))
    scan = q.select("qid", F.lit(c.count()).alias("distances"))
    methods = {  # answers, and the distances measured for them, of one search
        "class_index": lambda ef: class_index_query(index, at(ef), both=True),
        "per_pattern": lambda ef: baselines.per_pattern_query(lists, edges, c, at(ef), both=True),
        "search_first": lambda ef: baselines.search_first(graph, c, q, ef, both=True),
        "keyword_knn": lambda ef: baselines.keyword_knn_graph(by_shard, c, q, ef, both=True),
        "sql_hybrid": lambda ef: (baselines.sql_hybrid(c, q, ef, 0.3, graph=graph), matched),
        "filter_first": lambda ef: (baselines.filter_first(index, q), matched),
        "scan": lambda ef: (exact_topk(c, q), scan),
    }
    rows = []
    for method, run in methods.items():
        for ef in efs if method not in ("filter_first", "scan") else efs[:1]:
            mark, t = staged_so_far(), time.perf_counter()
            got, work = run(ef)
            got = staged(got)
            rate = n / (time.perf_counter() - t)
            each = measures.recall_at_k(got, truth).join(q.select("qid", "len"), "qid").join(work, "qid", "left")
            row = each.groupBy("len").agg(F.round(F.avg("recall"), 4).alias("recall"), F.round(F.avg("distances"), 1).alias("distances"))
            rows += [(method, r["len"], ef, r["recall"], r["distances"], round(rate, 2)) for r in row.collect()]
            del got, work, each, row
            release(mark)
    return spark.createDataFrame(rows, "method string, len int, ef int, recall double, distances double, qps double")


def _e01(name: str):
    return lambda spark, d: tradeoff_curve(spark, d, name, threshold=GRAPH_FROM[name], per_length=1000 if name in ("urlpath", "pname", "user_events", "passage") else 200)


for _n in SIX[:4]:
    QUERIES[f"e01_tradeoff_{_n}"] = _e01(_n)


@report("e01_invariants_pname", "SELECT true AS exact_methods_exact, true AS class_index_high, true AS more_effort_no_worse, true AS cheaper_than_filter_first")
def _e01_gate(spark, d):
    """What the curve must show: exact methods exact, the class index near them at a wide ef, recall growing with ef, and fewer distances than measuring all matches."""
    t = staged(tradeoff_curve(spark, d, "pname", (10, 160), 40, 100))
    per = t.groupBy("method", "ef").agg(F.avg("recall").alias("r"), F.avg("distances").alias("d"))
    rows = {(r["method"], r["ef"]): (r["r"], r["d"]) for r in per.collect()}  # a row for each method and knob
    graphs = ("class_index", "per_pattern", "search_first", "keyword_knn")
    got = (
        all(rows[m, 10][0] == 1.0 for m in ("filter_first", "scan")),
        rows["class_index", 160][0] >= 0.95,
        all(rows[m, 160][0] >= rows[m, 10][0] for m in graphs),
        rows["class_index", 10][1] <= rows["filter_first", 10][1],
    )
    return spark.createDataFrame([got], "exact_methods_exact boolean, class_index_high boolean, more_effort_no_worse boolean, cheaper_than_filter_first boolean")


@report("e02_search_first_falls_with_length", "SELECT true AS falls, true AS below_class_index")
@_own_scratch
def _e02(spark, d):
    """Search-first loses recall as patterns get longer and rarer; the class index, on the same queries, does not."""
    c = staged(corpus(spark, d, "line"))
    q = staged(query_set(c, 64, 30))
    truth = staged(exact_topk(c, q))
    by_len = lambda got: measures.recall_at_k(got, truth).join(q.select("qid", "len"), "qid").groupBy("len").agg(F.avg("recall").alias("r"))
    late = by_len(baselines.search_first(baselines.global_graph(c, **LIGHT), c, q, 80))
    index = by_len(class_index_query(build_class_index(c, 4, 800, **LIGHT), q)).select("len", F.col("r").alias("index_r"))
    r = late.join(index, "len").agg(F.max(F.when(F.col("len") == 2, F.col("r"))).alias("two"), F.max(F.when(F.col("len") == 4, F.col("r"))).alias("four"), F.min(F.col("index_r") - F.col("r")).alias("gap"), F.min("index_r").alias("low"))
    return r.select((F.col("four") < F.col("two")).alias("falls"), ((F.col("gap") > 0) & (F.col("low") >= 0.95)).alias("below_class_index"))


#: Bytes a unit takes: an id, an edge (an id), a state (its key, link, donor and counts), a transition.
UNIT = {"ids": 8, "edges": 8, "states": 40, "transitions": 20}


@_own_scratch
def index_sizes(spark: SparkSession, d: str, name: str, threshold: int, arms: bool = True, cap: int = 4) -> DataFrame:
    """(corpus, method, states, ids, nodes, edges, bytes, seconds): the class index by arm, and lists or graphs for each pattern."""
    c = staged(corpus(spark, d, name))
    t0 = time.perf_counter()
    occ, found, routes, posted, members = item_tables(c, cap)
    forget(occ)
    moves = staged(C.transitions(routes))
    n_moves, shared = moves.count(), time.perf_counter() - t0
    t0 = time.perf_counter()
    named_vectors(c)
    named = time.perf_counter() - t0  # part of every method's graphs
    rows = []
    for reuse, skip in ((True, True), (True, False), (False, True), (False, False)) if arms else ((True, True),):
        mark, t = staged_so_far(), time.perf_counter()
        donors, rest = choose_donors(found, moves, posted, "subtree" if reuse else "none")
        kinds = staged(decide_kind(donors, threshold, skip=skip))
        t1 = time.perf_counter()
        edges = build_graphs(expanded(rest.join(kinds.where("kind = 'graph'").select("state"), "state"), members), c, **LIGHT)
        t2 = time.perf_counter()
        rows.append((f"class_index reuse={reuse} skip={skip}", found.count(), _ids(rest), *_edges(edges), n_moves, shared, t1 - t, t2 - t1 + named))
        del donors, rest, kinds, edges
        release(mark)
    t = time.perf_counter()
    lists, edges = baselines.per_pattern_build(c, cap, threshold, **LIGHT)
    rows.append(("per_pattern", routes.count(), lists.count(), *_edges(edges), 0, 0.0, 0.0, time.perf_counter() - t + named))
    out = spark.createDataFrame(rows, "method string, states long, ids long, nodes long, edges long, transitions long, tables_s double, residuals_s double, graphs_s double")
    size = sum(F.col(k) * v for k, v in UNIT.items())
    return out.select(F.lit(name).alias("corpus"), "method", "states", "ids", "nodes", "edges", "transitions", size.alias("bytes"), *[F.round(x, 2).alias(x) for x in ("tables_s", "residuals_s", "graphs_s")])


def _edges(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.coalesce(F.sum((F.col("level") == 0).cast("long")), F.lit(0)).alias("n"), F.coalesce(F.sum(F.size("neighbours")), F.lit(0)).cast("long").alias("e")).first()
    return r["n"], r["e"]


def _ids(rows: DataFrame) -> int:
    """For how many ids the rows of items stand."""
    return rows.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]


def _sizes(spark, d, name: str, cap: int = 4) -> tuple[int, int, int]:
    """(ids of the per-pattern lists, ids of the classes, ids with reuse)."""
    c = corpus(spark, d, name)
    occ, found, routes, posted, _ = item_tables(c, cap)
    donors, rest = choose_donors(found, C.transitions(routes), posted)
    return _ids(occ), _ids(posted), _ids(rest)


@report("e03_index_size_ratio", "SELECT 'pname' AS corpus, true AS smaller UNION ALL SELECT 'passage', true UNION ALL SELECT 'urlpath', true")
def _e03(spark, d):
    rows = [(n, *_sizes(spark, d, n)) for n in ("passage", "pname", "urlpath")]
    return spark.createDataFrame([(n, a > b > r) for n, a, b, r in rows], "corpus string, smaller boolean")


def _each(names: tuple[str, ...], one: Callable[[str], DataFrame]) -> DataFrame:
    out = one(names[0])
    for n in names[1:]:
        out = out.unionByName(one(n))
    return out


@report("e03_index_size_figures")
def _e03f(spark, d):
    """Sizes in units and bytes, and build seconds by part, of class index and per-pattern lists or graphs."""
    return _each(SIX[:4], lambda n: index_sizes(spark, d, n, GRAPH_FROM[n], arms=False))


@report("e04_construction_time")
def _e04(spark, d):
    """Ratio of build times, per-pattern to class index, with the class index's parts."""
    t = staged(_each(SIX[:4], lambda n: index_sizes(spark, d, n, GRAPH_FROM[n], arms=False))).withColumn("total", F.col("tables_s") + F.col("residuals_s") + F.col("graphs_s"))
    mine, other = t.where("method != 'per_pattern'"), t.where("method = 'per_pattern'").select("corpus", F.col("total").alias("other"))
    return mine.join(other, "corpus").select("corpus", "tables_s", "residuals_s", "graphs_s", "total", "other", F.round(F.col("other") / F.col("total"), 2).alias("ratio"))


@report("e05_growth")
def _e05(spark, d):
    """Ids and seconds at 10 to 100 % of a corpus, of classes and of per-pattern lists."""
    rows = []
    for f in range(1, 11):
        c = staged(corpus(spark, d, "passage").where(F.col("id") % 10 < f))
        m = c.agg(F.sum(F.char_length("seq"))).first()[0] or 0
        t = time.perf_counter()
        occ, found, routes, posted = class_tables(c, 4)
        rows.append(("classes", f, m, posted.count(), time.perf_counter() - t))
        t = time.perf_counter()
        rows.append(("per_pattern", f, m, staged(occurrences(c, 4)).count(), time.perf_counter() - t))
    return spark.createDataFrame(rows, "method string, tenths int, m long, ids long, seconds double")


def _growth_point(f: int) -> str:
    return f"""SELECT {f} AS tenths, (SELECT CAST(sum(length(seq)) AS BIGINT) FROM corpus WHERE id % 10 < {f}) AS m, (SELECT count(*) FROM (
  WITH e AS (SELECT id, seq, unnest(range(1, length(seq) + 1)) AS e FROM corpus WHERE id % 10 < {f}), r AS (SELECT id, e - 1 AS fin, substring(seq, e - n + 1, n) AS pattern FROM (SELECT *, unnest(range(1, least(e, 4) + 1)) AS n FROM e)),
  p AS (SELECT pattern, min(id * 1048576 + fin) AS fe, count(*) AS oc FROM r GROUP BY pattern), c AS (SELECT fe, oc, arg_min(pattern, length(pattern)) AS sh FROM p GROUP BY fe, oc) SELECT DISTINCT sh, id FROM c JOIN r ON r.pattern = c.sh)) AS classes,
  (SELECT count(*) FROM (SELECT DISTINCT id, substring(seq, s, n) FROM (SELECT id, seq, unnest(range(1, length(seq) + 1)) AS s FROM corpus WHERE id % 10 < {f}), (SELECT unnest([1, 2, 3, 4]) AS n) WHERE s + n - 1 <= length(seq))) AS per_pattern"""


@report("e05_growth_ids_passage", f"WITH corpus AS ({CORPORA['passage'][1]}) " + " UNION ALL ".join(_growth_point(f) for f in range(1, 11)))
def _e05_ids(spark, d):
    """The same curve in ids, ten points each."""
    c = staged(corpus(spark, d, "passage"))

    def point(f: int) -> DataFrame:
        part = c.where(F.col("id") % 10 < f)
        occ, found, routes, posted = class_tables(part, 4)
        m = part.agg(F.sum(F.char_length("seq")).alias("m"))
        return m.crossJoin(posted.agg(F.count(F.lit(1)).alias("classes"))).crossJoin(occ.agg(F.count(F.lit(1)).alias("per_pattern"))).select(F.lit(f).alias("tenths"), "m", "classes", "per_pattern")

    out = point(1)
    for f in range(2, 11):
        out = out.unionByName(point(f))
    return out


@report("e06_parallel_build")
@_own_scratch
def _e06(spark, d):
    """Seconds to build all graphs, those of the class index, as 1, 2, 4 and 8 groups of states at a time, the largest states first."""
    rows = []
    for name in ("pname", "urlpath", "user_events"):
        c = staged(corpus(spark, d, name))
        _, found, routes, posted, members = item_tables(c, 4)
        donors, rest = choose_donors(found, C.transitions(routes), posted)
        large = staged(decide_kind(donors, 20).where("kind = 'graph'").select("state", "held"))
        named_vectors(c)
        order = Window.orderBy(F.desc("held"), "state")  # of the states with graphs alone
        for workers in (1, 2, 4, 8):
            mark = staged_so_far()
            lanes = staged(large.withColumn("lane", (F.row_number().over(order) - 1) % workers).select("state", "lane"))
            t = time.perf_counter()
            graph_links_by_lane(expanded(rest.join(lanes.select("state"), "state"), members), lanes, c, workers, **LIGHT)
            rows.append((name, workers, time.perf_counter() - t))
            release(mark)
    return spark.createDataFrame(rows, "corpus string, workers int, seconds double")


@report("e07_ablation_figures")
def _e07f(spark, d):
    """Size and time that reuse, skip-build and both save, in per cent, by corpus."""
    t = staged(_each(("pname", "urlpath", "user_events"), lambda n: index_sizes(spark, d, n, GRAPH_FROM[n]))).where("method != 'per_pattern'").withColumn("total", F.col("residuals_s") + F.col("graphs_s"))
    full = t.where("method = 'class_index reuse=False skip=False'").select("corpus", F.col("bytes").alias("b0"), F.col("total").alias("s0"))
    return t.join(full, "corpus").select("corpus", "method", "ids", "nodes", "edges", "bytes", F.round(100 * (1 - F.col("bytes") / F.col("b0")), 1).alias("size_saved"), F.round(100 * (1 - F.col("total") / F.col("s0")), 1).alias("time_saved"))


@report("e07_ablation_pname", "SELECT true AS reuse_saves, true AS skip_saves, true AS both_save_most")
def _e07(spark, d):
    """Bytes of the arms, graphs built: reuse saves, skip-build saves, both save the most."""
    arms = {r["method"]: r["bytes"] for r in index_sizes(spark, d, "pname", 100).collect()}
    at = lambda r, s: arms[f"class_index reuse={r} skip={s}"]
    return spark.createDataFrame([(at(True, False) < at(False, False), at(False, True) < at(False, False), at(True, True) == min(at(r, s) for r in (True, False) for s in (True, False)))], "reuse_saves boolean, skip_saves boolean, both_save_most boolean")


@report("e08_threshold_study")
def _e08(spark, d):
    """Bytes, build seconds, queries a second and recall as the threshold moves, lengths mixed."""
    rows = []
    c = staged(corpus(spark, d, "pname"))
    q = staged(query_set(c, 64, 40, sample="occurrence"))
    truth, n = staged(exact_topk(c, q)), q.count()
    for t in (50, 100, 200, 400, 800):
        t0 = time.perf_counter()
        index = build_class_index(c, 4, t, **LIGHT)
        t1 = time.perf_counter()
        got = staged(class_index_query(index, q))
        t2 = time.perf_counter()
        r = measures.recall_at_k(got, truth).agg(F.avg("recall")).first()[0]
        nodes, edges = _edges(index.edges) if index.edges is not None else (0, 0)
        ids = _ids(index.residuals)
        rows.append((t, ids, nodes, edges, UNIT["ids"] * ids + UNIT["edges"] * edges, t1 - t0, n / (t2 - t1), r))
    return spark.createDataFrame(rows, "threshold int, ids long, nodes long, edges long, bytes long, build_s double, qps double, recall double")


@report("e08_threshold_counts_pname", "SELECT unnest([50, 100, 200, 400, 800]) AS threshold, true AS fewer_nodes")
def _e08_gate(spark, d):
    """Graph nodes fall as the threshold grows, and residuals stay what they are."""
    c = corpus(spark, d, "pname")
    _, found, routes, posted, _ = item_tables(c, 4)
    donors = staged(choose_donors(found, C.transitions(routes), posted)[0])
    counts = [decide_kind(donors, t).agg(F.coalesce(F.sum(F.when(F.col("kind") == "graph", F.col("held"))), F.lit(0)), F.sum("held")).first() for t in (50, 100, 200, 400, 800)]
    return spark.createDataFrame([(t, a[0] <= b[0] and a[1] == b[1]) for t, a, b in zip((50, 100, 200, 400, 800), counts, [counts[0], *counts], strict=False)], "threshold int, fewer_nodes boolean")


@report("e09_summary_at_recall")
def _e09(spark, d):
    """The cheapest setting of each method that reaches a recall of 0.9, by corpus, with its distances and rate against the class index's."""

    def one(n: str) -> DataFrame:
        curve = staged(tradeoff_curve(spark, d, n, threshold=GRAPH_FROM[n], per_length=100))
        per = staged(curve.groupBy("method", "ef").agg(F.avg("recall").alias("recall"), F.avg("distances").alias("distances"), F.avg("qps").alias("qps")))
        return measures.at_recall(per, 0.9).select(F.lit(n).alias("corpus"), "*")

    return _each(("pname", "urlpath"), one)


@report("e10_maintenance_recall", "SELECT true AS inserts_equal, true AS deletes_equal")
def _e10(spark, d):
    c = staged(corpus(spark, d, "passage"))
    q = staged(query_set(c, 64, 10))
    index = build_class_index(c.where("id % 10 != 7"), 4)
    grown = staged(class_index_query(insert_batch(index, c.where("id % 10 = 7")), q))
    shrunk = staged(class_index_query(delete_batch(build_class_index(c, 4), c.where("id % 10 = 7").select("id")), q))
    same = lambda a, b: a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
    return spark.createDataFrame([(same(grown, staged(exact_topk(c, q))), same(shrunk, staged(exact_topk(c.where("id % 10 != 7"), q))))], "inserts_equal boolean, deletes_equal boolean")


#: Squared distance of a corpus row's vector to the one that is 0.1 throughout.
_TO_TENTH = "round(list_sum(list_transform(vec, lambda x: (CAST(x AS DOUBLE) - 0.1) * (CAST(x AS DOUBLE) - 0.1))), 4)"


@report("e11_motif_toy", f"WITH corpus AS ({CORPORA['pname'][1]}) SELECT id FROM corpus WHERE contains(seq, 'old p') ORDER BY {_TO_TENTH}, id LIMIT 1")
def _e11(spark, d):
    """One motif, one vector, one answer: the nearest name that has the motif."""
    q = spark.createDataFrame([(0, "old p", [0.1] * 64)], "qid long, pattern string, qvec array<double>")
    return exact_topk(corpus(spark, d, "pname"), q, 1).select("id")


@report("a02_throughput")
def _a02(spark, d):
    """Queries a second once everything is built, and, apart, the seconds that building took."""
    c = staged(corpus(spark, d, "line"))
    q = staged(query_set(c, 64, 40))
    t = time.perf_counter()
    index = build_class_index(c, 4)
    built, n = time.perf_counter() - t, q.count()
    rows = [("class_index", built, measures.qps(lambda: class_index_query(index, q), n)), ("filter_first", built, measures.qps(lambda: baselines.filter_first(index, q), n)), ("scan", 0.0, measures.qps(lambda: exact_topk(c, q), n))]
    return spark.createDataFrame(rows, "method string, build_s double, qps double")


@report("a06_build_parts_pname", "SELECT unnest(['tables_s', 'residuals_s', 'graphs_s']) AS part, true AS took_time")
def _a06(spark, d):
    """Every part of a build takes measurable time."""
    r = index_sizes(spark, d, "pname", 100, arms=False).where("method != 'per_pattern'").first()
    return spark.createDataFrame([(p, r[p] > 0) for p in ("tables_s", "residuals_s", "graphs_s")], "part string, took_time boolean")


@report("a11_work_counters", "SELECT true AS graph_measures_fewer, true AS index_measures_no_more_than_matches")
def _a11(spark, d):
    """A global graph measures fewer distances than a scan at a small ef; the class index with raw lists measures each match once."""
    c = staged(corpus(spark, d, "pname"))
    q = staged(query_set(c, 64, 4, ef=20))
    lists, edges = baselines.global_graph(c, **LIGHT)
    got = search_graphs(edges, lists, c, q.withColumn("state", F.lit(""))).groupBy("qid").agg(F.max("distances").alias("n")).agg(F.avg("n").alias("n"))
    index = build_class_index(c, 4)
    work = class_index_query(index, q, counters=True).join(q.join(index.routes, "pattern").select("qid", "n_ids"), "qid").agg(F.max((F.col("distances") - F.col("n_ids")).cast("long")).alias("extra"))
    return got.crossJoin(c.agg(F.count(F.lit(1)).alias("all"))).crossJoin(work).select((F.col("n") < F.col("all")).alias("graph_measures_fewer"), (F.col("extra") == 0).alias("index_measures_no_more_than_matches"))


_EFS = (10, 40, 160, 640)


@report("a13_at_recall_toy", f"""WITH {query_sql('passage', per_length=20)},
far AS (SELECT q.qid, c.id, contains(c.seq, q.pattern) AS hit, round(list_sum(list_transform(list_zip(c.vec, q.qvec), lambda p: (CAST(p[1] AS DOUBLE) - p[2]) * (CAST(p[1] AS DOUBLE) - p[2]))), 4) AS dist FROM queries q, corpus c),
ranked AS (SELECT qid, hit, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS place, row_number() OVER (PARTITION BY qid, hit ORDER BY dist, id) AS rk FROM far),
each AS (SELECT qid, ef, count(*) FILTER (WHERE place <= ef) / count(*)::DOUBLE AS recall FROM ranked, (SELECT unnest({list(_EFS)}) AS ef) WHERE hit AND rk <= 10 GROUP BY qid, ef),
curve AS (SELECT 'search_first' AS method, ef, round(avg(recall), 4) AS recall, CAST(ef AS DOUBLE) AS distances FROM each GROUP BY ef UNION ALL SELECT 'filter_first', 10, 1.0, round(avg(n), 4) FROM (SELECT count(*) AS n FROM far WHERE hit GROUP BY qid))
SELECT method, CAST(ef AS INT) AS ef, CAST(recall AS DOUBLE) AS recall, distances FROM curve WHERE recall >= 0.9 QUALIFY row_number() OVER (PARTITION BY method ORDER BY distances) = 1""")
def _a13(spark, d):
    """The cheapest setting that reaches a recall, on a curve of exact searches: rows that the filter tests, and matches that are measured."""
    c = staged(corpus(spark, d, "passage"))
    q = staged(query_set(c, 64))
    truth = staged(exact_topk(c, q))
    late = lambda ef: measures.recall_at_k(baselines.search_first_exact(c, q, ef), truth).agg(F.round(F.avg("recall"), 4).alias("recall"))
    curve = c.join(q.select("qid", "pattern"), F.contains("seq", F.col("pattern"))).groupBy("qid").agg(F.count(F.lit(1)).alias("n"))
    curve = curve.agg(F.round(F.avg("n"), 4).alias("distances")).select(F.lit("filter_first").alias("method"), F.lit(_EFS[0]).alias("ef"), F.lit(1.0).alias("recall"), "distances")
    for ef in _EFS:
        curve = curve.unionByName(late(ef).select(F.lit("search_first").alias("method"), F.lit(ef).alias("ef"), "recall", F.lit(float(ef)).alias("distances")))
    return measures.at_recall(curve, 0.9)


@report("planner_answers_line", f"WITH {query_sql('line', per_length=20)},\n{EXACT_SQL}\nSELECT qid, CAST(rk AS INT) AS rk, id, dist FROM answers")
def _planner(spark, d):
    """Every query by the method that its number of matches makes cheapest; with exact branches the answers are the scan's."""
    c = staged(corpus(spark, d, "line"))
    q = staged(query_set(c, 64, 20))
    _, found, routes, posted = class_tables(c, 4)
    index = ClassIndex(c, 4, None, routes, found, posted, found, posted, None)
    got, _ = plan_and_run(index, q, None)
    return keep_nearest(got, 10).select("qid", F.col("rk").cast("int").alias("rk"), "id", "dist")


@report("planner_choices_line", f"WITH {query_sql('line', per_length=20)}, v AS (SELECT qid, (SELECT count(*) FROM corpus WHERE contains(seq, pattern)) AS n FROM queries) SELECT qid, n AS matches, CASE WHEN n <= 160 * ln((SELECT count(*) FROM corpus)) THEN 'filter_first' ELSE 'search_first' END AS chosen FROM v")
def _choices(spark, d):
    c = staged(corpus(spark, d, "line"))
    q = staged(query_set(c, 64, 20))
    _, found, routes, posted = class_tables(c, 4)
    return plan_and_run(ClassIndex(c, 4, None, routes, found, posted, found, posted, None), q, None)[1]

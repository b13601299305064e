"""Registered queries of the methods, variants, baselines, measures and workloads, with SQL for another engine."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifknn.functions.patterns import alphabet, as_text, ends, occurrences
from motifknn.functions.vectors import distance
from motifknn.operators import automaton, baselines, measures
from motifknn.operators import classes as C
from motifknn.operators.exact import exact_topk, filtered_topk, keep_nearest, merge_topk, nearest_of, valid
from motifknn.operators.index import ClassIndex, build_class_index, class_index_query, class_tables, compact, delete_batch, insert_batch, long_pattern_query, wildcard_query
from motifknn.operators.reuse import check_cover, choose_donors, decide_kind
from motifknn.plans.staging import staged
from motifknn.plans.workload import CORPORA, EXACT_SQL, corpus, query_set, query_sql
from motifknn.sources.tables import table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
CAP, PER = 4, 20


def _add(name: str, fn: Query, sql: str | None = None) -> None:
    QUERIES[name] = fn
    if sql:
        SQL[name] = sql


def _setup(spark: SparkSession, d: str, name: str, **how) -> tuple[DataFrame, DataFrame]:
    c = corpus(spark, d, name)
    return c, staged(query_set(c, CORPORA[name][2], **{"per_length": PER, **how}))


def _with(name: str, body: str, **how) -> str:
    return f"WITH {query_sql(name, **{'per_length': PER, **how})},\n{EXACT_SQL}\n{body}"


ANSWERS = "SELECT qid, CAST(rk AS INT) AS rk, id, dist FROM answers"


def _out(df: DataFrame) -> DataFrame:
    return df.select("qid", F.col("rk").cast("int").alias("rk"), "id", "dist")


def _classes_sql(name: str, cap: int = CAP) -> str:
    return f"""WITH corpus AS ({CORPORA[name][1]}),
e AS (SELECT id, seq, unnest(range(1, length(seq) + 1)) AS e FROM corpus),
r AS (SELECT id, e - 1 AS fin, substring(seq, e - n + 1, n) AS pattern FROM (SELECT *, unnest(range(1, least(e, {cap}) + 1)) AS n FROM e)),
p AS (SELECT pattern, min(id) AS first_id, CAST(arg_min(fin, id::HUGEINT * 4294967296 + fin) AS INT) AS first_at, count(*) AS occ, count(DISTINCT id) AS n_ids FROM r GROUP BY pattern),
c AS (SELECT first_id, first_at, occ, arg_max(pattern, length(pattern)) AS state, arg_min(pattern, length(pattern)) AS shortest, min(length(pattern)) AS min_len, max(length(pattern)) AS max_len, max(n_ids) AS n_ids FROM p GROUP BY first_id, first_at, occ),
m AS (SELECT pattern, state FROM p JOIN c USING (first_id, first_at, occ)),
v AS (SELECT DISTINCT state, id FROM c JOIN r ON r.pattern = c.shortest),
t AS (SELECT DISTINCT coalesce(h.state, '') AS from_state, right(m.pattern, 1) AS symbol, m.state AS to_state FROM m LEFT JOIN m h ON h.pattern = left(m.pattern, length(m.pattern) - 1))
"""


# --- exact answers, one per corpus; every exact method must give the same table
def _exact(name: str) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, name)
        return _out(exact_topk(c, q))

    return run


def _index_query(name: str) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, name)
        return _out(class_index_query(build_class_index(c, CAP), q))

    return run


def _filter_first(name: str) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, name)
        occ, found, routes, posted = class_tables(c, CAP)
        return _out(baselines.filter_first(ClassIndex(c, CAP, None, routes, found, posted, found, posted, None), q))

    return run


for _n in CORPORA:
    _add(f"m01_exact_topk_{_n}", _exact(_n), _with(_n, ANSWERS))
for _n in ("passage", "turn", "line", "vocab", "pname", "urlpath", "items", "user_events"):
    _add(f"m24_class_index_{_n}", _index_query(_n), _with(_n, ANSWERS))
for _n in ("passage", "pname", "orders_seq", "urlpath"):
    _add(f"b02_filter_first_{_n}", _filter_first(_n), _with(_n, ANSWERS))


def _m02(spark, d):
    c, q = _setup(spark, d, "passage")
    return c.join(q.select("qid", "pattern"), F.contains("seq", F.col("pattern"))).groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("first_id"))


_add("m02_containment_passage", _m02, _with("passage", "SELECT qid, count(*) AS n, min(id) AS first_id FROM queries JOIN corpus ON contains(seq, pattern) GROUP BY qid"))


def _m06(spark, d):
    return ends(corpus(spark, d, "urlpath"), CAP).groupBy("pattern").agg(F.count(F.lit(1)).alias("occ"), F.min("end").alias("low"), F.max("end").alias("high"))


_add("m06_end_positions_urlpath", _m06, _classes_sql("urlpath") + "SELECT pattern, count(*) AS occ, CAST(min(fin) AS INT) AS low, CAST(max(fin) AS INT) AS high FROM r GROUP BY pattern")


def _tables(name: str, pick: Callable[..., DataFrame]) -> Query:
    def run(spark, d):
        c = corpus(spark, d, name)
        occ, found, routes, posted = class_tables(c, CAP)
        return pick(c, occ, found, routes, posted)

    return run


for _n in ("passage", "pname", "urlpath"):
    _add(f"m07_pattern_classes_{_n}", _tables(_n, lambda c, o, f, r, p: f.select("first_id", "first_at", "occ", "state", "shortest", "min_len", "max_len", "n_ids")), _classes_sql(_n) + "SELECT first_id, first_at, occ, state, shortest, CAST(min_len AS INT) AS min_len, CAST(max_len AS INT) AS max_len, n_ids FROM c")
    _add(f"m10_postings_{_n}", _tables(_n, lambda c, o, f, r, p: p.select("state", "id")), _classes_sql(_n) + "SELECT state, id FROM v")
    _add(f"m12_transitions_{_n}", _tables(_n, lambda c, o, f, r, p: C.transitions(r)), _classes_sql(_n) + "SELECT from_state, symbol, to_state FROM t")
_add("m04_pattern_lookup_passage", lambda s, d: (lambda cq: cq[1].join(class_tables(cq[0], CAP)[2].select("pattern", "state", "n_ids"), "pattern").select("qid", "pattern", "state", "n_ids"))(_setup(s, d, "passage")), _classes_sql("passage").replace("corpus AS (" + CORPORA["passage"][1] + ")", query_sql("passage", per_length=PER).replace("runs AS", "lens AS").replace("FROM runs", "FROM lens")) + "SELECT qid, pattern, state, p.n_ids FROM queries JOIN m USING (pattern) JOIN p USING (pattern)")
_add("m08_longest_members_pname", _tables("pname", lambda c, o, f, r, p: f.select("state", "max_len", "n_ids")), _classes_sql("pname") + "SELECT state, CAST(max_len AS INT) AS max_len, n_ids FROM c")
_add("m13_suffix_links_passage", _tables("passage", lambda c, o, f, r, p: C.suffix_links(f, r)), _classes_sql("passage") + "SELECT c.state, coalesce(m.state, '') AS link_state FROM c LEFT JOIN m ON m.pattern = substring(c.shortest, 2)")
_add("m14_suffix_states_passage", _tables("passage", lambda c, o, f, r, p: C.suffix_states(c, r, 3, 20, CAP)), _classes_sql("passage") + "SELECT state, CAST(max(length(r.pattern)) AS INT) AS max_len FROM r JOIN m ON m.pattern = r.pattern WHERE id = 3 AND fin = 20 GROUP BY state")
_add("m05_right_contexts_urlpath", _tables("urlpath", lambda c, o, f, r, p: C.right_contexts(C.pattern_dict(o)).groupBy("context_key").agg(F.count(F.lit(1)).alias("patterns"), F.countDistinct("n_ids").alias("sizes"))), _classes_sql("urlpath") + ", f AS (SELECT left(pattern, length(pattern) - 1) AS pattern, string_agg(DISTINCT right(pattern, 1), '' ORDER BY right(pattern, 1)) AS k FROM p WHERE length(pattern) > 1 GROUP BY 1) SELECT coalesce(k, '') AS context_key, count(*) AS patterns, count(DISTINCT n_ids) AS sizes FROM p LEFT JOIN f USING (pattern) GROUP BY 1")
def _m17(spark, d):
    """Runs across two neighbouring items: the class index finds them only where some item has them itself."""
    c = corpus(spark, d, "pname")
    routes = class_tables(c, CAP)[2]
    joints = c.select("id", F.right("seq", F.lit(2)).alias("tail")).join(c.select((F.col("id") - 1).alias("id"), F.left("seq", F.lit(2)).alias("head")), "id")
    return joints.select(F.concat("tail", "head").alias("pattern")).distinct().join(routes, "pattern", "left").select("pattern", F.coalesce("n_ids", F.lit(0)).alias("n_ids"))


_add("m17_no_pattern_across_items_pname", _m17, f"WITH corpus AS ({CORPORA['pname'][1]}), j AS (SELECT DISTINCT concat(right(a.seq, 2), left(b.seq, 2)) AS pattern FROM corpus a JOIN corpus b ON b.id = a.id + 1) SELECT pattern, (SELECT count(*) FROM corpus WHERE contains(seq, pattern)) AS n_ids FROM j")


def _m09(spark, d):
    c = corpus(spark, d, "passage")
    occ, found, routes, posted = class_tables(c, CAP)
    m = c.agg(F.sum(F.char_length("seq")).alias("m"))
    return m.crossJoin(found.agg(F.count(F.lit(1)).alias("states"))).crossJoin(C.transitions(routes).agg(F.count(F.lit(1)).alias("edges"))).select("m", "states", "edges", (F.col("states") < 2 * F.col("m")).alias("states_ok"), (F.col("edges") <= 3 * F.col("m")).alias("edges_ok"))


_add("m09_state_bound_passage", _m09, _classes_sql("passage") + "SELECT m, states, edges, states < 2 * m AS states_ok, edges <= 3 * m AS edges_ok FROM (SELECT (SELECT CAST(sum(length(seq)) AS BIGINT) FROM corpus) AS m, (SELECT count(*) FROM c) AS states, (SELECT count(*) FROM t) AS edges)")


def _reuse(name: str, rule: str, pick: Callable[..., DataFrame]) -> Query:
    def run(spark, d):
        c = corpus(spark, d, name)
        _, found, routes, posted = class_tables(c, CAP)
        posted = staged(posted)
        donors, residuals = choose_donors(found, C.transitions(routes), posted, rule)
        return pick(posted, donors, residuals)

    return run


for _n in ("passage", "pname", "urlpath"):
    for _r in ("subtree", "child", "none"):
        _add(f"m20_cover_{_r}_{_n}", _reuse(_n, _r, check_cover), _classes_sql(_n) + "SELECT count(*) AS n_states, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS overlap FROM c")


def _donors_sql(name: str, rule: str, cap: int = CAP) -> str:
    """Donors and residuals recomputed level by level, longest members first; ends with the table done(state, donor, base, held)."""
    out = _classes_sql(name, cap) + ", l AS (SELECT state, length(state) AS n FROM c), g AS (SELECT from_state, to_state FROM t WHERE length(to_state) > length(from_state) AND from_state != '')\n"
    size, pick = ("held", "to_state") if rule == "child" else ("best_size", "best_state")
    done, rest = "SELECT CAST(NULL AS VARCHAR) AS state, CAST(NULL AS VARCHAR) AS donor, 0 AS base, 0 AS held, 0 AS best_size, CAST(NULL AS VARCHAR) AS best_state WHERE false", "SELECT CAST(NULL AS VARCHAR) AS state, CAST(NULL AS BIGINT) AS id WHERE false"
    out += f", done0 AS ({done}), rest0 AS ({rest})\n"
    for k, n in enumerate(range(cap, 0, -1), 1):
        out += f""", ch{k} AS (SELECT l.state, b.donor, b.size FROM l LEFT JOIN (SELECT from_state AS state, arg_min({pick}, struct_pack(s := -{size}, d := {pick})) AS donor, arg_min({size}, struct_pack(s := -{size}, d := {pick})) AS size FROM g JOIN done{k - 1} d ON d.state = g.to_state GROUP BY 1) b USING (state) WHERE l.n = {n}),
new{k} AS MATERIALIZED (SELECT v.state, v.id FROM v JOIN ch{k} USING (state) LEFT JOIN rest{k - 1} r ON r.state = ch{k}.donor AND r.id = v.id WHERE r.id IS NULL),
row{k} AS (SELECT state, donor, base, coalesce(held, 0) AS held, size FROM ch{k} JOIN (SELECT state, count(*) AS base FROM v GROUP BY state) USING (state) LEFT JOIN (SELECT state, count(*) AS held FROM new{k} GROUP BY state) USING (state)),
done{k} AS MATERIALIZED (SELECT * FROM done{k - 1} UNION ALL SELECT state, donor, base, held, CASE WHEN own THEN held ELSE size END, CASE WHEN own THEN state ELSE donor END FROM (SELECT *, size IS NULL OR held > size OR (held = size AND state < donor) AS own FROM row{k})),
rest{k} AS MATERIALIZED (SELECT * FROM rest{k - 1} UNION ALL SELECT state, id FROM new{k})
"""
    return out + f", done AS (SELECT * FROM done{cap}), rest AS (SELECT * FROM rest{cap})\n"


for _n in ("passage", "pname", "urlpath"):
    for _r in ("subtree", "child"):
        _add(f"m18_donors_{_r}_{_n}", _reuse(_n, _r, lambda p, d, r: d.select("state", "donor", "base", "held")), _donors_sql(_n, _r) + "SELECT state, donor, base, held FROM done")
_add("m18_residuals_pname", _reuse("pname", "subtree", lambda p, d, r: r.select("state", "id")), _donors_sql("pname", "subtree") + "SELECT state, id FROM rest")
for _o in ("base", "matches"):
    _add(f"m19_kinds_{_o}_pname", _reuse("pname", "subtree", lambda p, d, r, o=_o: decide_kind(d, 100, o).groupBy("kind").agg(F.count(F.lit(1)).alias("states"), F.sum("held").alias("ids"))), _donors_sql("pname", "subtree") + f"SELECT CASE WHEN {'held' if _o == 'base' else 'base'} < 100 OR held = 0 THEN 'raw' ELSE 'graph' END AS kind, count(*) AS states, CAST(sum(held) AS BIGINT) AS ids FROM done GROUP BY 1")


def _metric(metric: str) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, "passage")
        return _out(exact_topk(c, q, metric=metric))

    return run


_L2 = "list_sum(list_transform(list_zip(c.vec, q.qvec), lambda p: (CAST(p[1] AS DOUBLE) - p[2]) * (CAST(p[1] AS DOUBLE) - p[2])))"
_IP = "list_sum(list_transform(list_zip(c.vec, q.qvec), lambda p: CAST(p[1] AS DOUBLE) * p[2]))"
_NV, _NQ = "sqrt(list_sum(list_transform(c.vec, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))))", "sqrt(list_sum(list_transform(q.qvec, lambda x: x * x)))"
_add("m01_exact_topk_ip", _metric("ip"), _with("passage", ANSWERS).replace(_L2, "-" + _IP))
_add("m01_exact_topk_cosine", _metric("cosine"), _with("passage", ANSWERS).replace(_L2, f"1 - {_IP} / ({_NV} * {_NQ})"))


def _m23(spark, d):
    c, q = _setup(spark, d, "passage")
    ids = q.select("qid").crossJoin(c.where("id % 10 = 3").select("id"))
    return _out(keep_nearest(nearest_of(ids, c, q)))


_add("m23_raw_list_passage", _m23, _with("passage", ANSWERS).replace("ON contains(c.seq, q.pattern)", "ON c.id % 10 = 3"))


def _m27(spark, d):
    c, q = _setup(spark, d, "passage", per_length=PER, lengths=(6, 9))
    return _out(long_pattern_query(build_class_index(c, CAP, rule="none", reuse=False), q))


_add("m27_long_patterns_passage", _m27, _with("passage", ANSWERS, lengths=(6, 9)))


#: One batch of patterns of any length: empty, short, longer than the cap.
ANY = {"lengths": (2, 4, 6, 9), "per_length": 6}


def _any_batch(spark, d) -> tuple[DataFrame, DataFrame]:
    c, q = _setup(spark, d, "passage", **ANY)
    return c, staged(q.withColumn("pattern", F.when((F.col("len") == 2) & (F.col("qid") % 3 == 0), F.lit("")).otherwise(F.col("pattern"))))


def _any_sql(rows: str) -> str:
    """Exact answers of that batch over ``rows`` (id, seq, vec) made from corpus."""
    text = _with("passage", ANSWERS, **ANY).replace("FROM queries q JOIN corpus c ON contains(c.seq, q.pattern)", "FROM (SELECT * REPLACE (CASE WHEN len = 2 AND qid % 3 = 0 THEN '' ELSE pattern END AS pattern) FROM queries) q JOIN rows c ON contains(c.seq, q.pattern)")
    return text.replace("answers AS (", f"rows AS ({rows}),\nanswers AS (", 1)


def _changed(c: DataFrame) -> DataFrame:
    """Ids that end in 3, with another sequence and another vector."""
    return c.where("id % 10 = 3").select("id", F.transform("vec", lambda x: -x).alias("vec"), F.concat(F.lit("the changed of "), F.substring("seq", 3, 1 << 30)).alias("seq"))


_CHANGED = "SELECT id, CASE WHEN id % 10 = 3 THEN 'the changed of ' || substring(seq, 3) ELSE seq END AS seq, CASE WHEN id % 10 = 3 THEN list_transform(vec, lambda x: -x) ELSE vec END AS vec FROM corpus"


def _m28(spark, d):
    c, q = _any_batch(spark, d)
    return _out(class_index_query(insert_batch(build_class_index(staged(c.where("id % 10 != 3")), CAP), c.where("id % 10 = 3")), q))


def _m28_changed(spark, d):
    c, q = _any_batch(spark, d)
    index = insert_batch(delete_batch(build_class_index(c, CAP), c.where("id % 10 = 3").select("id")), _changed(c))
    return _out(class_index_query(index, q))


def _m29(spark, d):
    c, q = _any_batch(spark, d)
    return _out(class_index_query(delete_batch(insert_batch(build_class_index(c, CAP), _changed(c)), c.where("id % 10 in (3, 4)").select("id")), q))


def _m30(spark, d):
    c, q = _any_batch(spark, d)
    index = delete_batch(insert_batch(build_class_index(c, CAP), _changed(c)), c.where("id % 10 = 4").select("id"))
    return _out(class_index_query(compact(index), q))


_add("m24_any_length_passage", lambda s, d: (lambda cq: _out(class_index_query(build_class_index(cq[0], CAP), cq[1])))(_any_batch(s, d)), _any_sql("SELECT * FROM corpus"))
_add("m28_insert_passage", _m28, _any_sql("SELECT * FROM corpus"))
_add("m28_changed_reinsert_passage", _m28_changed, _any_sql(_CHANGED))
_add("m29_lazy_delete_passage", _m29, _any_sql("SELECT * FROM corpus WHERE id % 10 NOT IN (3, 4)"))
_add("m30_compaction_passage", _m30, _any_sql(f"SELECT * FROM ({_CHANGED}) WHERE id % 10 != 4"))


def _m27_wild(spark, d):
    """Motifs of five symbols whose middle one is any."""
    c, q = _setup(spark, d, "passage", per_length=PER, lengths=(5,))
    motifs = q.withColumn("pattern", F.concat(F.substring("pattern", 1, 2), F.lit("."), F.substring("pattern", 4, 2)))
    return _out(wildcard_query(build_class_index(c, CAP, reuse=False), motifs.where(~F.col("pattern").contains("..") & ~F.col("pattern").startswith(".") & ~F.col("pattern").endswith("."))))


_add("m27_wildcard_motifs_passage", _m27_wild, _with("passage", ANSWERS, lengths=(5,)).replace("FROM queries q JOIN corpus c ON contains(c.seq, q.pattern)", "FROM (SELECT * REPLACE (substring(pattern, 1, 2) || '.' || substring(pattern, 4, 2) AS pattern) FROM queries) q JOIN corpus c ON NOT contains(q.pattern, '..') AND left(q.pattern, 1) != '.' AND right(q.pattern, 1) != '.' AND len(list_filter(range(1, length(c.seq) - 3), lambda i: substring(c.seq, i, 2) = left(q.pattern, 2) AND substring(c.seq, i + 3, 2) = right(q.pattern, 2))) > 0"))


def _online(spark, d):
    """Items one by one into an automaton that keeps donors and residuals: covers are exact and disjoint.

    All classes are looked at before the first item and after the last, those that changed after each tenth.
    """
    rows = [(r["id"], r["seq"]) for r in corpus(spark, d, "urlpath").select("id", "seq").orderBy("id").collect()]  # a segment's worth
    half = len(rows) // 2
    online = automaton.OnlineIndex(automaton.build(rows[:half]))
    wrong, changed = online.wrong(range(len(online.a.span))), set()
    for k, (i, seq) in enumerate(rows[half:]):
        before = len(online.a.span)
        changed |= {*online.changed_by(online.insert(i, seq)), *range(before, len(online.a.span))}
        if k % 10 == 0:
            wrong += online.wrong(changed)
            changed = set()
    wrong += online.wrong(range(len(online.a.span)))
    return spark.createDataFrame([(online.a.name(s), len(set.union(*online.cover(s))), wrong) for s in range(1, len(online.a.span))], "state string, n_ids long, wrong long")


_add("m28_online_insert_urlpath", _online, _classes_sql("urlpath", 64) + "SELECT state, n_ids, CAST(0 AS BIGINT) AS wrong FROM c")


def _m31(spark, d):
    c, q = _setup(spark, d, "passage", per_length=2)
    odd = q.where("len = 2").withColumn("pattern", F.when(F.col("qid") % 2 == 0, F.lit("")).otherwise(F.lit("@@##")))
    return _out(class_index_query(build_class_index(c, CAP, reuse=False), odd))


_add("m31_empty_and_absent_passage", _m31, _with("passage", ANSWERS, per_length=2).replace("ON contains(c.seq, q.pattern)", "ON q.len = 2 AND q.qid % 2 = 0"))


def _m32(spark, d):
    c, q = _setup(spark, d, "passage")
    return _out(merge_topk(exact_topk(c.where("id % 2 = 0"), q), exact_topk(c.where("id % 2 = 1"), q)))


_add("m32_merge_topk_passage", _m32, _with("passage", ANSWERS))


# --- automata over segments
def _m03(spark, d):
    """Automata of single names and of ten names at a time: states, transitions, ids held."""

    def of(kind: str, pdf: pd.DataFrame) -> tuple:
        a = automaton.build(zip(pdf["id"], pdf["seq"], strict=True))
        return kind, int(pdf["grp"].iloc[0]), len(a.span), sum(map(len, a.next)), sum(map(len, a.ids)), all(a.locate(s[len(s) // 2 :]) is not None for s in pdf["seq"])

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        rows = [of("ten", pdf)] + [of("one", pdf.iloc[[i]].assign(grp=pdf["id"].iloc[i])) for i in range(len(pdf))]
        return pd.DataFrame(rows, columns=["kind", "grp", "states", "edges", "ids", "found"])

    names = table(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("seq"))
    return names.withColumn("grp", F.expr("id div 10")).groupBy("grp").applyInPandas(run, "kind string, grp long, states long, edges long, ids long, found boolean")


_add("m03_worked_automata", _m03, """WITH names AS (SELECT p_partkey AS id, p_name AS seq FROM part),
g AS (SELECT 'one' AS kind, id AS grp, id, seq FROM names UNION ALL SELECT 'ten', id // 10, id, seq FROM names),
e AS (SELECT *, unnest(range(1, length(seq) + 1)) AS e FROM g),
r AS (SELECT kind, grp, id, e AS fin, substring(seq, e - n + 1, n) AS pattern FROM (SELECT *, unnest(range(1, e + 1)) AS n FROM e)),
p AS (SELECT kind, grp, pattern, min(id::HUGEINT * 4294967296 + fin) AS first_end, count(*) AS occ, count(DISTINCT id) AS n_ids FROM r GROUP BY kind, grp, pattern),
c AS (SELECT kind, grp, first_end, occ, max(n_ids) AS n_ids FROM p GROUP BY kind, grp, first_end, occ),
t AS (SELECT DISTINCT p.kind, p.grp, h.first_end AS f1, h.occ AS o1, right(p.pattern, 1) AS symbol, p.first_end AS f2, p.occ AS o2 FROM p LEFT JOIN p h ON h.kind = p.kind AND h.grp = p.grp AND h.pattern = left(p.pattern, length(p.pattern) - 1))
SELECT kind, grp, states + 1 AS states, edges, CAST(ids AS BIGINT) + items AS ids, true AS found FROM (SELECT kind, grp, count(*) AS states, sum(n_ids) AS ids FROM c GROUP BY kind, grp) JOIN (SELECT kind, grp, count(*) AS edges FROM t GROUP BY kind, grp) USING (kind, grp) JOIN (SELECT kind, grp, count(*) AS items FROM g GROUP BY kind, grp) USING (kind, grp)""")


def _m11(spark, d):
    c = corpus(spark, d, "pname")
    return automaton.segment_tables(c, 1).where("state != ''").select("state", F.col("n_ids"))


_add("m11_online_id_sets_pname", _m11, _classes_sql("pname", 64) + "SELECT state, n_ids FROM c")


def _m15(spark, d):
    c = corpus(spark, d, "urlpath")
    t = automaton.segment_tables(c, 1)
    return t.agg(F.count(F.lit(1)).alias("states"), F.sum("n_next").alias("edges"), F.sum("n_ids").alias("ids"), (F.sum("n_held") < F.sum("n_ids")).alias("reuse_saves"))


_add("m15_segment_automaton_urlpath", _m15, _classes_sql("urlpath", 64) + "SELECT (SELECT count(*) FROM c) + 1 AS states, (SELECT count(*) FROM t) AS edges, (SELECT count(*) FROM v) + (SELECT count(*) FROM corpus) AS ids, true AS reuse_saves")


def _m16(spark, d):
    c, q = _setup(spark, d, "passage", lengths=(3, 9))
    return _out(keep_nearest(nearest_of(automaton.segment_matches(c, q, 4), c, q)))


_add("m16_segment_query_passage", _m16, _with("passage", ANSWERS, lengths=(3, 9)))


# --- baselines
def _b01(spark, d):
    c, q = _setup(spark, d, "passage")
    lists, edges = baselines.per_pattern_build(c, CAP)
    return _out(baselines.per_pattern_query(lists, edges, c, q))


_add("b01_per_pattern_passage", _b01, _with("passage", ANSWERS))


def _late_sql(ef: int) -> str:
    return _with("passage", f"""SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS INT) AS rk, id, dist FROM (SELECT * FROM (
SELECT q.qid, q.pattern, c.id, c.seq, round({_L2}, 4) AS dist FROM queries q, corpus c) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY dist, id) <= {ef}) WHERE contains(seq, pattern) QUALIFY rk <= 10""")


def _b03(ef: int) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, "passage")
        return _out(baselines.search_first_exact(c, q, ef))

    return run


for _ef in (40, 160):
    _add(f"b03_search_first_exact_ef{_ef}_passage", _b03(_ef), _late_sql(_ef))


def _b03x(spark, d):
    c, q = _setup(spark, d, "passage", per_length=8)
    return _out(baselines.search_first_expanding(c, q, 64))


_add("b03_search_first_expanding_passage", _b03x, _with("passage", ANSWERS, per_length=8))


def _b04(threshold: float) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, "passage")
        return _out(baselines.sql_hybrid(c, q, 500_000, threshold))

    return run


_add("b04_sql_hybrid_filter_passage", _b04(1.1), _with("passage", ANSWERS))
_add("b04_sql_hybrid_mixed_passage", _b04(0.05), _with("passage", ANSWERS))


def _b05(mode: str) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, "passage", sample="distinct")
        return _out(baselines.keyword_knn(c, q, 20, 4, mode))

    return run


_SHARD = """SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS INT) AS rk, id, dist FROM (SELECT q.qid, c.id, round({l2}, 4) AS dist, c.id % 4 AS shard FROM queries q JOIN corpus c ON {hit}
QUALIFY row_number() OVER (PARTITION BY q.qid, c.id % 4 ORDER BY dist, c.id) <= 20) QUALIFY rk <= 10"""
_add("b05_keyword_knn_wildcard_passage", _b05("wildcard"), _with("passage", _SHARD.format(l2=_L2, hit="contains(c.seq, q.pattern)")))
_add("b05_keyword_knn_match_passage", _b05("match"), _with("passage", _SHARD.format(l2=_L2, hit="list_contains(string_split(c.seq, ' '), q.pattern)")))


def _b06(reuse: bool, skip: bool) -> Query:
    """States, ids in raw lists and ids in graphs of one arm."""

    def run(spark, d):
        c = corpus(spark, d, "pname")
        _, found, routes, posted = class_tables(c, CAP)
        kinds = decide_kind(choose_donors(found, C.transitions(routes), posted, "subtree" if reuse else "none")[0], 100, skip=skip)
        return kinds.groupBy("kind").agg(F.count(F.lit(1)).alias("states"), F.sum("held").alias("ids"))

    return run


for _a in (True, False):
    for _s in (True, False):
        _held = "done" if _a else "(SELECT state, base AS held FROM done)"
        _kind = "CASE WHEN held < 100 THEN 'raw' ELSE 'graph' END" if _s else "CASE WHEN held = 0 THEN 'raw' ELSE 'graph' END"
        _add(f"b06_ablation_reuse_{str(_a).lower()}_skip_{str(_s).lower()}_pname", _b06(_a, _s), _donors_sql("pname", "subtree") + f"SELECT {_kind} AS kind, count(*) AS states, CAST(sum(held) AS BIGINT) AS ids FROM {_held} GROUP BY 1")


def _b07(pred: str) -> Query:
    def run(spark, d):
        docs = table(spark, d, "documents").select(F.col("doc_id").alias("id"), "n_chars")
        e = table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label", F.col("embedding").alias("vec"))
        _, q = _setup(spark, d, "passage", per_length=5)
        return _out(filtered_topk(e.join(docs, "id"), q, F.expr(pred)))

    return run


for _k, _p in (("label_in", "label IN (1, 3, 5)"), ("range", "n_chars BETWEEN 500 AND 2500")):
    _add(f"b07_attribute_{_k}", _b07(_p), _with("passage", ANSWERS, per_length=5).replace("JOIN corpus c ON contains(c.seq, q.pattern)", f"CROSS JOIN (SELECT vec_id AS id, embedding AS vec, label, n_chars FROM embeddings JOIN documents ON doc_id = vec_id WHERE {_p}) c"))


# --- graphs: gates on recall
def _graph_gate(name: str, threshold: int, least: float = 0.95, ef: int = 100, per: int = 25) -> Query:
    """Mean recall by pattern length, occurrence-weighted patterns, states of ``threshold`` items or more as graphs; there must be some."""

    def run(spark, d):
        c, q = _setup(spark, d, name, sample="occurrence", per_length=per, ef=ef)
        index = build_class_index(c, CAP, threshold, m=8, ef_con=60)
        r = measures.recall_at_k(class_index_query(index, q), exact_topk(c, q)).join(q.select("qid", "len"), "qid")
        graphs = index.states.where("kind = 'graph'").count()
        return r.groupBy("len").agg(((F.avg("recall") >= least) & F.lit(graphs > 0)).alias("pass"))

    return run


_THREE = "SELECT unnest([2, 3, 4]) AS len, true AS pass"
for _n, _t in (("pname", 20), ("pname", 200), ("urlpath", 20), ("user_events", 20), ("passage", 20), ("turn", 200), ("line", 400)):
    _add(f"m24_class_index_graphs_t{_t}_{_n}", _graph_gate(_n, _t), _THREE)


def _frequent(spark, d):
    """Only patterns that many items have: every query goes through graphs."""
    c, q = _setup(spark, d, "pname", sample="frequent", min_items=40, per_length=10, ef=80, lengths=(2, 3))
    index = build_class_index(c, 3, 20)
    return measures.recall_at_k(class_index_query(index, q), exact_topk(c, q)).agg((F.avg("recall") >= 0.9).alias("pass"))


_add("m21_graph_recall_pname", _frequent, "SELECT true AS pass")


def _m25(spark, d):
    """Sizes of a built index with graphs: states, ids held, graph nodes."""
    i = build_class_index(corpus(spark, d, "pname"), CAP, 100, m=8, ef_con=40)
    nodes = i.edges.where("level = 0").agg(F.count(F.lit(1)).alias("nodes"))
    return i.states.agg(F.count(F.lit(1)).alias("states"), F.sum("held").alias("ids")).crossJoin(nodes)


_add("m25_build_pname", _m25, _donors_sql("pname", "subtree") + "SELECT count(*) AS states, CAST(sum(held) AS BIGINT) AS ids, CAST(coalesce(sum(held) FILTER (WHERE held >= 100), 0) AS BIGINT) AS nodes FROM done")


def _m22(spark, d):
    c, q = _setup(spark, d, "passage", per_length=10)
    lists, edges = baselines.global_graph(c)
    truth = exact_topk(c, q.withColumn("pattern", F.lit("")))
    r = measures.recall_at_k(baselines.search_first((lists, edges), c, q.withColumn("pattern", F.lit("")), 160), truth)
    return r.agg((F.avg("recall") >= 0.95).alias("pass"))


_add("m22_global_graph_recall_passage", _m22, "SELECT true AS pass")


def _m26(spark, d):
    """Graphs of all large states, dealt otherwise and in another number of tasks: the same edges."""
    c = corpus(spark, d, "pname")
    one, two = (build_class_index(x, CAP, 20, m=4, ef_con=20).edges for x in (c, c.repartition(7)))
    count = lambda e, n: e.agg(F.count(F.lit(1)).alias(f"{n}_nodes"), F.sum(F.hash("state", "node_id", "level", "neighbours").cast("long")).alias(n))
    return count(one, "a").crossJoin(count(two, "b")).select((F.col("a") == F.col("b")).alias("same"), (F.col("a_nodes") > 1000).alias("many"))


_add("m26_parallel_build_same_pname", _m26, "SELECT true AS same, true AS many")


# --- baselines with graphs: their answers are a subset of the matches, in order, and near the truth at a wide ef
def _b_graph(which: str) -> Query:
    def run(spark, d):
        c, q = _setup(spark, d, "passage", per_length=10, ef=120)
        truth = exact_topk(c, q)
        if which == "per_pattern":
            lists, edges = baselines.per_pattern_build(c, CAP, 20, 8, 60)
            got = baselines.per_pattern_query(lists, edges, c, q)
        elif which == "search_first":
            got = baselines.search_first(baselines.global_graph(c), c, q, 500)
        elif which == "expanding":
            got = baselines.search_first_expanding_graph(baselines.global_graph(c), c, q, 20)
        elif which == "sql_hybrid":
            got = baselines.sql_hybrid(c, q, 500, 0.3, graph=baselines.global_graph(c))
        else:
            got = baselines.keyword_knn_graph(baselines.global_graph(c, shards=4), c, q, 120)
        got = staged(got)
        strange = got.join(c.select("id", "seq"), "id").join(q.select("qid", "pattern"), "qid").where(~F.contains("seq", F.col("pattern"))).count()
        return measures.recall_at_k(got, truth).agg((F.avg("recall") >= 0.95).alias("near")).select("near", F.lit(strange).alias("strange"))

    return run


for _b, _k in (("b01_per_pattern", "per_pattern"), ("b03_search_first", "search_first"), ("b03_search_first_expanding", "expanding"), ("b04_sql_hybrid", "sql_hybrid"), ("b05_keyword_knn", "keyword")):
    _add(f"{_b}_graph_passage", _b_graph(_k), "SELECT true AS near, 0 AS strange")


# --- measures
def _a01(spark, d):
    c, q = _setup(spark, d, "passage")
    r = measures.recall_at_k(baselines.search_first_exact(c, q, 160), exact_topk(c, q)).join(q.select("qid", "len"), "qid")
    return r.groupBy("len").agg(F.round(F.avg("recall"), 4).alias("recall"), F.count(F.lit(1)).alias("queries"))


_add("a01_recall_search_first_passage", _a01, _with("passage", f""", late AS (SELECT qid, id FROM (SELECT * FROM (SELECT q.qid, q.pattern, c.id, c.seq, round({_L2}, 4) AS dist FROM queries q, corpus c) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY dist, id) <= 160) WHERE contains(seq, pattern) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY dist, id) <= 10),
h AS (SELECT a.qid, count(l.id) / count(*)::DOUBLE AS recall FROM answers a LEFT JOIN late l USING (qid, id) GROUP BY a.qid)
SELECT len, round(avg(recall), 4) AS recall, count(*) AS queries FROM h JOIN queries USING (qid) GROUP BY len""".replace(", late AS", "SELECT * FROM (WITH late AS", 1) + ")"))


def _a04(spark, d):
    c = corpus(spark, d, "passage")
    return measures.match_profile(class_tables(c, CAP)[2], c.count())


_add("a04_match_profile_passage", _a04, _classes_sql("passage") + ", s AS (SELECT length(pattern) AS len, n_ids / (SELECT count(*) FROM corpus)::DOUBLE AS share FROM p) SELECT CAST(len AS INT) AS len, count(*) AS patterns, round(quantile_cont(share, 0.5), 6) AS p50, round(quantile_cont(share, 0.99), 6) AS p99, round(max(share), 6) AS top FROM s GROUP BY len")


def _a05(spark, d):
    c = corpus(spark, d, "pname")
    occ, found, routes, posted = class_tables(c, CAP)
    full = measures.index_size(spark, "all_ids", found, posted, None)
    every = measures.index_size(spark, "per_pattern", routes, occ, None)
    return full.unionByName(every)


_add("a05_index_size_pname", _a05, _classes_sql("pname") + "SELECT 'all_ids' AS method, (SELECT count(*) FROM c) AS states, (SELECT count(*) FROM v) AS ids, CAST(0 AS BIGINT) AS edges UNION ALL SELECT 'per_pattern', (SELECT count(*) FROM p), (SELECT count(*) FROM (SELECT DISTINCT pattern, id FROM r)), 0")


def _a07(spark, d):
    c = corpus(spark, d, "passage")
    occ, found, routes, posted = class_tables(c, CAP)
    return occ.agg(F.count(F.lit(1)).alias("b")).crossJoin(posted.agg(F.count(F.lit(1)).alias("a"))).select("a", "b", F.round(1 - F.col("a") / F.col("b"), 4).alias("reduction"))


_add("a07_reduction_passage", _a07, _classes_sql("passage") + ", x AS (SELECT (SELECT count(*) FROM v) AS a, (SELECT count(*) FROM (SELECT DISTINCT pattern, id FROM r)) AS b) SELECT a, b, round(1 - a / b::DOUBLE, 4) AS reduction FROM x")


def _a12(spark, d):
    c = corpus(spark, d, "passage")
    occ, found, routes, posted = class_tables(c, CAP)
    n = F.char_length("seq").cast("long")
    return c.agg(F.sum(n).alias("m"), F.sum(n * (n + 1) / 2).cast("long").alias("most")).crossJoin(posted.agg(F.count(F.lit(1)).alias("v"))).crossJoin(occ.agg(F.count(F.lit(1)).alias("pp"))).select("m", "v", (F.col("v") <= F.pow("m", F.lit(1.5))).alias("class_ok"), (F.col("pp") <= F.col("most")).alias("pattern_ok"))


_add("a12_bounds_passage", _a12, _classes_sql("passage") + "SELECT m, v, v <= m ** 1.5 AS class_ok, pp <= most AS pattern_ok FROM (SELECT CAST(sum(length(seq)) AS BIGINT) AS m, sum(length(seq) * (length(seq) + 1) / 2) AS most, (SELECT count(*) FROM v) AS v, (SELECT count(*) FROM (SELECT DISTINCT pattern, id FROM r)) AS pp FROM corpus)")


def _a08(spark, d):
    parts = []
    for f in (2, 4, 6, 8, 10):
        c = corpus(spark, d, "passage").where(F.col("id") % 10 < f)
        occ, found, routes, posted = class_tables(c, CAP)
        parts.append(c.agg(F.sum(F.char_length("seq")).alias("x")).crossJoin(posted.agg(F.count(F.lit(1)).alias("y"))))
    points = parts[0]
    for p in parts[1:]:
        points = points.unionByName(p)
    return measures.slope(points)


def _a08_sql() -> str:
    base = CORPORA["passage"][1]
    point = "(SELECT CAST(sum(length(seq)) AS DOUBLE) AS x, (SELECT count(*) FROM (WITH e AS (SELECT id, seq, unnest(range(1, length(seq) + 1)) AS e FROM corpus WHERE id % 10 < {f}), r AS (SELECT id, e - 1 AS fin, substring(seq, e - n + 1, n) AS pattern FROM (SELECT *, unnest(range(1, least(e, 4) + 1)) AS n FROM e)), p AS (SELECT pattern, min(id::HUGEINT * 4294967296 + fin) AS fe, count(*) AS oc FROM r GROUP BY pattern), c AS (SELECT fe, oc, arg_min(pattern, length(pattern)) AS sh FROM p GROUP BY fe, oc) SELECT DISTINCT sh, id FROM c JOIN r ON r.pattern = c.sh)) AS y FROM corpus WHERE id % 10 < {f})"
    return f"WITH corpus AS ({base}), pts AS (" + " UNION ALL ".join("SELECT * FROM " + point.format(f=f) for f in (2, 4, 6, 8, 10)) + ") SELECT round(regr_slope(ln(y), ln(x)), 4) AS slope FROM pts"


_add("a08_growth_slope_passage", _a08, _a08_sql())


# --- corpora as workloads
for _n in CORPORA:
    _add(f"w_corpus_{_n}", lambda s, d, n=_n: corpus(s, d, n).select("id", "seq", F.round(F.aggregate(F.transform("vec", lambda x: x.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("total")), f"WITH corpus AS ({CORPORA[_n][1]}) SELECT id, seq, round(list_sum(list_transform(vec, lambda x: CAST(x AS DOUBLE))), 6) AS total FROM corpus")
_add("w_queries_passage", lambda s, d: _setup(s, d, "passage")[1].select("qid", "pattern", F.round(F.element_at("qvec", 7), 6).alias("v7")), f"WITH {query_sql('passage', per_length=PER)} SELECT qid, pattern, round(qvec[7], 6) AS v7 FROM queries")


def _symbols(spark, d):
    """Sequences as arrays of event types: the same classes as over their initials."""
    e = table(spark, d, "events").select("user_id", "ts", "event_id", "event_type")
    c = e.groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("l")).select(F.col("user_id").cast("long").alias("id"), F.col("l.event_type").alias("symbols"))
    letters = alphabet(c, "symbols")
    return staged(occurrences(c.select("id", as_text(F.col("symbols"), letters).alias("seq")), 3)).groupBy("pattern").agg(F.sum("times").alias("occ"), F.count(F.lit(1)).alias("n_ids")).select(F.char_length("pattern").alias("len"), "occ", "n_ids")


_add("m06_symbol_arrays_user_events", _symbols, f"WITH corpus AS ({CORPORA['user_events'][1]}), r AS (SELECT id, n, substring(seq, s, n) AS p FROM (SELECT id, seq, unnest(range(1, length(seq) + 1)) AS s FROM corpus), (SELECT unnest([1, 2, 3]) AS n) WHERE s + n - 1 <= length(seq)) SELECT CAST(length(p) AS INT) AS len, count(*) AS occ, count(DISTINCT id) AS n_ids FROM r GROUP BY p")


def _quarantine(spark, d):
    """Rows whose vector is null, short, or not finite are set aside, the rest is indexed."""
    c = corpus(spark, d, "passage")
    bad = c.withColumn("vec", F.when(F.col("id") % 5 == 0, F.lit(None)).when(F.col("id") % 5 == 1, F.slice("vec", 1, 3)).when(F.col("id") % 5 == 2, F.concat(F.slice("vec", 1, 63), F.array(F.lit(float("nan")).cast("float")))).otherwise(F.col("vec")))
    good, aside = valid(bad)
    return good.select("id", F.lit("good").alias("kind")).union(aside.select("id", F.lit("aside")))


_add("m25_quarantine_passage", _quarantine, "SELECT CAST(item_id AS BIGINT) AS id, CASE WHEN item_id % 5 > 2 THEN 'good' ELSE 'aside' END AS kind FROM benchmark")

"""The methods that the class index is compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from motifknn.functions.patterns import contains
from motifknn.functions.vectors import distance
from motifknn.operators.exact import MOST_TESTS, exact_topk, keep_nearest, matches, nearest_of, of_all
from motifknn.operators.graph import build_graphs, search_graphs
from motifknn.operators.index import ClassIndex, expanded, grouped, ids_of, item_occurrences, locate
from motifknn.plans.staging import staged

Graph = tuple[DataFrame, DataFrame]  # lists (state, id), edges


def per_pattern_build(corpus: DataFrame, cap: int, threshold: int | None = None, m: int = 16, ef_con: int = 200) -> tuple[DataFrame, DataFrame | None]:
    """(lists: state, id; edges): a list for every pattern, a graph where it has ``threshold`` items or more."""
    items, members = grouped(corpus)
    lists = staged(expanded(item_occurrences(items, cap).select(F.col("pattern").alias("state"), "id"), members))
    if threshold is None:
        return lists, None
    large = lists.groupBy("state").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= threshold).select("state")
    return lists, build_graphs(lists.join(large, "state"), corpus, m, ef_con)


def work_of(found: DataFrame) -> DataFrame:
    """(qid, distances) of what ``search_graphs`` found, all its graphs together."""
    return found.groupBy("qid", "state", "shard").agg(F.max("distances").alias("distances")).groupBy("qid").agg(F.sum("distances").alias("distances"))


def per_pattern_query(lists: DataFrame, edges: DataFrame | None, corpus: DataFrame, queries: DataFrame, k: int = 10, counters: bool = False, both: bool = False) -> DataFrame | tuple[DataFrame, DataFrame]:
    """``counters``: (qid, distances) measured instead; ``both``: answers and these, of one search."""
    asked = queries.withColumn("state", F.col("pattern"))
    alone, found = asked, None
    if edges is not None:
        with_graph = edges.select("state").distinct()
        alone = asked.join(with_graph, "state", "left_anti")
        found = search_graphs(edges, lists, corpus, asked.join(with_graph, "state", "left_semi"))
        found = staged(found) if both else found
    pairs = alone.select("state", "qid").join(lists, "state").select("qid", "id")
    work = pairs.groupBy("qid").agg(F.count(F.lit(1)).alias("distances"))
    work = work if found is None else work.unionByName(work_of(found))
    if counters:
        return work
    near = nearest_of(pairs, corpus, queries, k)
    near = keep_nearest(near if found is None else near.unionByName(found.select("qid", "id", "dist")), k)
    return (near, work) if both else near


def filter_first(index: ClassIndex, queries: DataFrame, k: int = 10) -> DataFrame:
    """Look the pattern's items up, measure them all."""
    ids = ids_of(index, locate(index, queries).select("state", "qid"), index.postings).select("qid", "id")
    return keep_nearest(nearest_of(ids, index.corpus, queries, k), k)


def filter_first_scan(corpus: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """The same without an index."""
    return exact_topk(corpus, queries, k)


def global_graph(corpus: DataFrame, m: int = 16, ef_con: int = 200, shards: int | None = None) -> Graph:
    """(lists, edges) of one graph over everything."""
    lists = corpus.select(F.lit("").alias("state"), "id")
    return lists, build_graphs(lists, corpus, m, ef_con, shards)


def _nearest_of_graph(graph: Graph, corpus: DataFrame, queries: DataFrame, ef: int) -> DataFrame:
    lists, edges = graph
    return search_graphs(edges, lists, corpus, queries.withColumn("state", F.lit("")).withColumn("ef", F.lit(ef)))


def _filtered(top: DataFrame, corpus: DataFrame, queries: DataFrame, k: int, hit: Column | None = None) -> DataFrame:
    """The late filter, then the cut."""
    hit = contains(F.col("seq"), F.col("pattern")) if hit is None else hit
    kept = top.select("qid", "id", "dist").join(corpus.select("id", "seq"), "id").join(queries.select("qid", "pattern"), "qid").where(hit)
    return keep_nearest(kept.select("qid", "id", "dist"), k)


def search_first(graph: Graph, corpus: DataFrame, queries: DataFrame, ef: int = 160, k: int = 10, counters: bool = False, both: bool = False) -> DataFrame | tuple[DataFrame, DataFrame]:
    """The ef nearest of everything, then the filter, then the cut; ``counters`` and ``both`` as in ``per_pattern_query``."""
    near = _nearest_of_graph(graph, corpus, queries, ef)
    if counters:
        return work_of(near)
    near = staged(near) if both else near
    top = near.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("dist", "id"))).where(F.col("r") <= ef)
    got = _filtered(top, corpus, queries, k)
    return (got, work_of(near)) if both else got


def search_first_exact(corpus: DataFrame, queries: DataFrame, ef: int, k: int = 10) -> DataFrame:
    """Search-first over an exact global search: what it loses is lost by the late filter alone."""
    return _filtered(keep_nearest(of_all(corpus, queries, ef), ef), corpus, queries, k)


def search_first_expanding(corpus: DataFrame, queries: DataFrame, ef: int, k: int = 10, most: int | None = None) -> DataFrame:
    """Queries with fewer than k answers are asked again with twice the ef, until all have k or everything was seen."""
    n = corpus.count() if most is None else most
    open_, done = staged(queries), None
    while True:
        got = staged(search_first_exact(corpus, open_, ef, k))
        enough = got.groupBy("qid").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") >= k).select("qid")
        last = ef >= n
        final = got if last else got.join(enough, "qid", "left_semi")
        done = final if done is None else done.unionByName(final)
        if last:
            return done
        open_ = staged(open_.join(enough, "qid", "left_anti"))
        if open_.isEmpty():
            return done
        ef = min(n, 2 * ef)


def search_first_expanding_graph(graph: Graph, corpus: DataFrame, queries: DataFrame, ef: int, k: int = 10) -> DataFrame:
    """The same over a graph: it ends when all queries have k answers or ef covers everything."""
    n, open_, done = corpus.count(), staged(queries), None
    while True:
        got = staged(search_first(graph, corpus, open_, ef, k))
        enough = got.groupBy("qid").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") >= k).select("qid")
        last = ef >= n
        final = got if last else got.join(enough, "qid", "left_semi")
        done = final if done is None else done.unionByName(final)
        open_ = staged(open_.join(enough, "qid", "left_anti"))
        if last or open_.isEmpty():
            return done
        ef = min(n, 4 * ef)


def sql_hybrid(corpus: DataFrame, queries: DataFrame, ef: int = 160, threshold: float = 0.5, k: int = 10, graph: Graph | None = None) -> DataFrame:
    """Relational text query with LIKE; the share of matching items decides between filter-first and search-first.

    Templates are a column of the query table, one join with LIKE, whose pairs are written out for both uses. Of more than
    ``MOST_TESTS`` queries the patterns are looked up instead: a template that is a literal between two % asks for
    no more than that it is contained. The late branch searches ``graph``, as a relational engine with a vector graph
    does, or everything exactly without one.
    """
    n = corpus.count()
    if len(queries.select("qid").limit(MOST_TESTS + 1).collect()) > MOST_TESTS:
        met = matches(corpus.where("seq is not null"), queries)
    else:
        asked = queries.select("qid", F.concat(F.lit("%"), F.regexp_replace("pattern", "([!%_])", "!$1"), F.lit("%")).alias("template"))
        met = corpus.select("id", "seq").join(asked, F.expr("seq LIKE template ESCAPE '!'")).select("qid", "id")
    met = staged(met)
    share = staged(met.groupBy("qid").agg((F.count(F.lit(1)) / F.lit(max(n, 1))).alias("share")))
    first = keep_nearest(nearest_of(met.join(share.where(F.col("share") < threshold).select("qid"), "qid", "left_semi"), corpus, queries, k), k)
    wide = staged(queries.join(share.where(F.col("share") >= threshold).select("qid"), "qid", "left_semi"))
    if wide.isEmpty():
        return first
    return first.unionByName(search_first_exact(corpus, wide, ef, k) if graph is None else search_first(graph, corpus, wide, ef, k))


def _hit(mode: str) -> Column:
    return contains(F.col("seq"), F.col("pattern")) if mode == "wildcard" else F.array_contains(F.split("seq", " "), F.col("pattern"))


def keyword_knn(corpus: DataFrame, queries: DataFrame, num_candidates: int = 100, shards: int = 4, mode: str = "wildcard", k: int = 10) -> DataFrame:
    """Per shard the nearest ``num_candidates`` that pass the filter (substring, or a whole token), then the nearest of all."""
    near = corpus.join(queries.select("qid", "pattern", "qvec"), _hit(mode)).select("qid", "id", F.round(distance(F.col("vec"), F.col("qvec")), 4).alias("dist"), F.pmod("id", F.lit(shards)).alias("shard"))
    top = near.withColumn("r", F.row_number().over(Window.partitionBy("qid", "shard").orderBy("dist", "id"))).where(F.col("r") <= num_candidates)
    return keep_nearest(top.select("qid", "id", "dist"), k)


def keyword_knn_graph(graph: Graph, corpus: DataFrame, queries: DataFrame, num_candidates: int = 100, mode: str = "wildcard", k: int = 10, counters: bool = False, both: bool = False) -> DataFrame | tuple[DataFrame, DataFrame]:
    """The same over a graph for each shard (``global_graph`` with shards): every shard gives its ``num_candidates`` nearest, the filter comes after."""
    near = _nearest_of_graph(graph, corpus, queries, num_candidates)
    if counters:
        return work_of(near)
    near = staged(near) if both else near
    got = _filtered(near, corpus, queries, k, _hit(mode))
    return (got, work_of(near)) if both else got

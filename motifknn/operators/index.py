"""The class-state index: build, query, insert, delete, compact."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifknn.functions.patterns import contains, occurrences, wildcard_regex
from motifknn.operators import classes as C
from motifknn.operators.exact import keep_nearest, matches_of, nearest_of, of_all, valid
from motifknn.operators.graph import build_graphs, search_graphs
from motifknn.operators.reuse import choose_donors, decide_kind
from motifknn.plans.staging import few, forget, staged


@dataclass
class ClassIndex:
    """``delta`` holds the present version of each row inserted since the build, ``dead`` the ids whose built version no longer counts."""

    corpus: DataFrame
    cap: int
    shards: int | None
    routes: DataFrame  # pattern, state, first_id, first_at, occ, n_ids
    classes: DataFrame
    postings: DataFrame
    states: DataFrame  # state, donor, base, held, kind
    residuals: DataFrame  # state, id
    edges: DataFrame | None
    delta: DataFrame | None = None
    dead: DataFrame | None = None
    rejected: DataFrame | None = None  # rows without a usable vector
    members: DataFrame | None = None  # of, id: if given, postings and residuals have a row for each sequence, see ``grouped``


def grouped(corpus: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(items: id, w, seq; members: of, id): rows of one sequence are one item, named by the smallest of their w ids.

    Such rows have all patterns in common, so they are in the same postings and residuals. If an id comes several
    times, every row is left alone.
    """
    rows = corpus.where(F.char_length("seq") > 0).select("id", "seq")
    if not rows.groupBy("id").agg(F.count(F.lit(1)).alias("c")).where("c > 1").isEmpty():
        return rows.select("id", F.lit(1).cast("long").alias("w"), "seq"), staged(rows.select(F.col("id").alias("of"), "id").distinct())
    items = staged(rows.groupBy("seq").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("w")).select("id", "w", "seq"))
    return items, staged(rows.join(items.select("seq", F.col("id").alias("of")), "seq").select("of", "id"))


def item_occurrences(items: DataFrame, cap: int) -> DataFrame:
    """(pattern, id, w, first, times): ``occurrences`` of the items of ``grouped``."""
    occ = occurrences(items.select(F.struct("id", "w").alias("id"), "seq"), cap)
    return occ.select("pattern", "id.id", "id.w", "first", "times")


def expanded(rows: DataFrame, members: DataFrame) -> DataFrame:
    """Rows of items as rows of their ids."""
    others = [c for c in rows.columns if c not in ("id", "w")]
    return rows.withColumnRenamed("id", "of").join(members, "of").select(*others, "id")


def item_tables(corpus: DataFrame, cap: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, DataFrame]:
    """(occurrences, classes, routes, postings, members), written out; occurrences and postings by item."""
    items, members = grouped(corpus)
    occ = staged(item_occurrences(items, cap))
    patterns = C.pattern_dict(occ)
    found = staged(C.pattern_classes(patterns))
    routes = staged(C.members(patterns, found))
    return occ, found, routes, staged(C.postings(occ, few(found, 256))), members


def class_tables(corpus: DataFrame, cap: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(occurrences, classes, routes, postings); occurrences and postings by id."""
    occ, found, routes, posted, members = item_tables(corpus, cap)
    return expanded(occ, members).select("pattern", "id", "first", "times"), found, routes, expanded(posted, members)


def build_class_index(corpus: DataFrame, cap: int = 4, threshold: int | None = None, reuse: bool = True, skip: bool = True, on: str = "base", rule: str = "subtree", m: int = 16, ef_con: int = 200, shards: int | None = None) -> ClassIndex:
    """Patterns up to ``cap`` symbols; ``threshold`` None keeps every state a raw list. Large graphs are cut into shards by size unless ``shards`` says how."""
    corpus, rejected = valid(corpus)
    corpus = staged(corpus)
    occ, found, routes, posted, members = item_tables(corpus, cap)
    forget(occ)
    donors, residuals = choose_donors(found, C.transitions(routes), posted, rule if reuse else "none")
    kinds = staged(decide_kind(donors, threshold if threshold is not None else 1 << 62, on, skip))
    graphs = kinds.where("kind = 'graph'").select("state")
    edges = None
    if threshold is not None and not graphs.isEmpty():
        edges = build_graphs(expanded(residuals.join(graphs, "state"), members), corpus, m, ef_con, shards)
    return ClassIndex(corpus, cap, shards, routes, found, posted, kinds, residuals, edges, rejected=rejected, members=members)


def ids_of(index: ClassIndex, asked: DataFrame, rows: DataFrame) -> DataFrame:
    """Asked (state, ...) with the ids that ``rows``, the index's postings or residuals, have for its states; rows that are not asked for are not expanded."""
    met = asked.join(rows, "state")
    return met if index.members is None else expanded(met, index.members)


def locate(index: ClassIndex, queries: DataFrame) -> DataFrame:
    """Queries with their state: one equi-join instead of a walk; unknown patterns drop out."""
    return queries.join(index.routes.select("pattern", "state"), "pattern")


def sources(index: ClassIndex, queries: DataFrame) -> DataFrame:
    """(state, qid, qvec, k, ef, kind): a query's own state and its donor."""
    kinds = index.states.select("state", "donor", "kind")
    routed = locate(index, queries).join(kinds, "state")
    own = routed.select("state", "qid", "qvec", "k", "ef", "kind")
    donor = routed.where("donor is not null").select(F.col("donor").alias("state"), "qid", "qvec", "k", "ef").join(kinds.select("state", "kind"), "state")
    return own.unionByName(donor)


def rarest_windows(index: ClassIndex, asked: DataFrame) -> DataFrame:
    """(qid, whole, id) of candidates from asked (qid, whole, windows): items of the rarest window, whole still to be verified."""
    windows = asked.select("qid", "whole", F.explode("windows").alias("pattern"))
    known = windows.join(index.routes.select("pattern", "state", "n_ids"), "pattern", "left")
    rare = known.groupBy("qid", "whole").agg(F.min_by("state", F.coalesce("n_ids", F.lit(0))).alias("state"), F.max(F.col("state").isNull().cast("int")).alias("absent")).where("absent = 0")
    return ids_of(index, rare, index.postings).select("qid", "whole", "id")


def long_matches(index: ClassIndex, queries: DataFrame) -> DataFrame:
    """(qid, id) of the built items that have a pattern longer than the cap."""
    cap = index.cap
    windows = F.transform(F.sequence(F.lit(1), F.char_length("pattern") - cap + 1), lambda i: F.substring("pattern", i, F.lit(cap)))
    found = rarest_windows(index, queries.where(F.char_length("pattern") > cap).select("qid", F.col("pattern").alias("whole"), windows.alias("windows")))
    return found.join(index.corpus.select("id", "seq"), "id").where(contains(F.col("seq"), F.col("whole"))).select("qid", "id")


def _living(index: ClassIndex, rows: DataFrame) -> DataFrame:
    return rows if index.dead is None else rows.join(index.dead, "id", "left_anti")


def class_index_query(index: ClassIndex, queries: DataFrame, k: int = 10, counters: bool = False, both: bool = False) -> DataFrame | tuple[DataFrame, DataFrame]:
    """Top-k of each query (qid, pattern, qvec, k, ef), whatever its pattern's length.

    Up to the cap: own residual and donor's, raw lists measured, graphs searched, merged without loss. Longer: items
    of the rarest window, verified. The empty pattern asks for all items. Deleted and replaced rows are taken out
    before any cut, rows inserted since the build are scanned. ``counters``: (qid, distances) measured instead;
    ``both``: answers and these, of one search.
    """
    short = queries.where((F.char_length("pattern") <= index.cap) & (F.col("pattern") != ""))
    wanted = staged(sources(index, short))
    raw = ids_of(index, wanted.where("kind = 'raw'").select("state", "qid"), index.residuals).select("qid", "id")
    pairs = _living(index, raw.union(long_matches(index, queries)))
    found = None
    if index.edges is not None:
        graphs = wanted.where("kind = 'graph'")
        if index.dead is not None:
            graphs = graphs.withColumn("ef", F.col("ef") + F.lit(index.dead.count()))
        found = search_graphs(index.edges, index.residuals, index.corpus, graphs)
        found = staged(found) if both else found
    if counters or both:
        work = pairs.groupBy("qid").agg(F.count(F.lit(1)).alias("distances"))
        if found is not None:
            work = work.unionByName(found.groupBy("qid", "state", "shard").agg(F.max("distances").alias("distances")).groupBy("qid").agg(F.sum("distances").alias("distances")))
        work = work.groupBy("qid").agg(F.sum("distances").alias("distances"))
    if counters:
        return work
    near = nearest_of(pairs, index.corpus, queries, k)
    if found is not None:
        near = near.unionByName(_living(index, found.select("qid", "id", "dist")))
    everything = queries.where("pattern = ''")
    if not everything.isEmpty():
        near = near.unionByName(of_all(_living(index, index.corpus), everything, k))
    if index.delta is not None:
        near = near.unionByName(matches_of(index.delta, queries, k))
    return (keep_nearest(near, k), work) if both else keep_nearest(near, k)


def wildcard_query(index: ClassIndex, queries: DataFrame, k: int = 10) -> DataFrame:
    """Top-k among items that match a motif in which "." is any one symbol, as in "C..C".

    Candidates are the items of the rarest window of the motif's literal runs; a motif without one asks all items.
    """
    cap = index.cap
    runs = F.filter(F.split("pattern", r"\."), lambda r: r != "")
    cut = lambda r: F.transform(F.sequence(F.lit(1), F.greatest(F.char_length(r) - cap + 1, F.lit(1))), lambda i: F.substring(r, i, F.lit(cap)))
    asked = queries.select("qid", F.col("pattern").alias("whole"), F.flatten(F.transform(runs, cut)).alias("windows"))
    built = index.corpus.select("id", "seq")
    fits = F.expr("seq rlike motif")
    some = rarest_windows(index, asked.where(F.size("windows") > 0)).join(built, "id").withColumn("motif", wildcard_regex(F.col("whole"))).where(fits).select("qid", "id")
    bare = asked.where(F.size("windows") == 0).select("qid", wildcard_regex(F.col("whole")).alias("motif"))
    pairs = _living(index, some if bare.isEmpty() else some.union(built.join(bare, fits).select("qid", "id")))
    near = nearest_of(pairs, index.corpus, queries, k)
    if index.delta is not None:
        fresh = index.delta.join(queries.select("qid", wildcard_regex(F.col("pattern")).alias("motif")), fits).select("qid", "id")
        near = near.unionByName(nearest_of(fresh, index.delta, queries, k))
    return keep_nearest(near, k)


def long_pattern_query(index: ClassIndex, queries: DataFrame, k: int = 10) -> DataFrame:
    """The part of ``class_index_query`` for patterns longer than the cap."""
    return class_index_query(index, queries.where(F.char_length("pattern") > index.cap), k)


def insert_batch(index: ClassIndex, rows: DataFrame) -> ClassIndex:
    """Rows (id, vec, seq) become the present version of their ids: a delta that queries read beside the built index."""
    good, _ = valid(rows)
    fresh = staged(good.dropDuplicates(["id"]))
    ids = fresh.select("id")
    return replace(index, delta=fresh if index.delta is None else staged(index.delta.join(ids, "id", "left_anti").unionByName(fresh)), dead=_more_dead(index, ids))


def delete_batch(index: ClassIndex, ids: DataFrame) -> ClassIndex:
    """Ids are marked: their built version is dead, and they leave the delta."""
    ids = staged(ids.select("id").distinct())
    return replace(index, delta=None if index.delta is None else staged(index.delta.join(ids, "id", "left_anti")), dead=_more_dead(index, ids))


def _more_dead(index: ClassIndex, ids: DataFrame) -> DataFrame:
    """Of the built ids only, so that the table is no larger than need be."""
    built = index.corpus.select("id").join(ids, "id", "left_semi")
    return staged(built if index.dead is None else index.dead.union(built).distinct())


def compact(index: ClassIndex, **how) -> ClassIndex:
    """Rebuild over what is left."""
    rows = _living(index, index.corpus)
    rows = rows if index.delta is None else rows.unionByName(index.delta)
    return build_class_index(staged(rows), index.cap, **{"shards": index.shards, **how})



"""Mixing sources to target weights along a time-varying curriculum.

Each source has a weight schedule over training time 0 to 1, straight between knots. Its integral is the
source's weight: the budget (``share`` of all words) is dealt by weight, no source gets more than ``most``
times its own words, and the excess is dealt again until none is above, which is one water level over the
sources sorted by the level at which they are full. A source takes its documents in order of a hash of their
id, as many rounds as the target holds, whole documents only; the last round stops at the document whose
middle passes the target. A document whose copy lies at a part f of its source's demand trains at the time
by which the schedule has spent the part f of its integral; that inversion is a closed formula per segment.

A source may hold any part of the rows: its documents are cut into ranges of the hash, ranges are summed,
and running sums within a range start at the sum of those before; nothing else crosses a source. Sums of
sources meet in one task, as many rows as there are sources.

Documents of a source follow each other by a hash of id and text, so that a null or repeated id is no hot key.
Texts pass two exchanges, that of the ranges and that of the training order.

Defined results: null text has size 0; null is a source of its own, the last; documents without words are
never taken (taken 0, null position, last in order); a source without words has target 0; repeated rows are
mixed each; an empty table gives an empty table. Extra columns, whatever their names, are carried along by
``in_order`` and ignored by ``mix``.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from motifknn.llm.scratch import few, materialise

#: Schedules dealt to the sources in turn: (time, weight) knots. Their integrals are 3, 1 and 2.
SCHEDULES: tuple[tuple[tuple[float, float], ...], ...] = (((0.0, 4.0), (1.0, 2.0)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 1.0), (0.5, 2.0), (1.0, 3.0)))
RANGE_ROWS = 1024


def integral(knots: Sequence[tuple[float, float]]) -> float:
    return sum((t1 - t0) * (w0 + w1) / 2 for (t0, w0), (t1, w1) in zip(knots, knots[1:], strict=False))


def time_at(part: Column, knots: Sequence[tuple[float, float]]) -> Column:
    """The time by which ``part`` of the schedule's integral is spent."""
    need = part * F.lit(integral(knots))
    out, before = F.lit(1.0), integral(knots)
    for (t0, w0), (t1, w1) in reversed(list(zip(knots, knots[1:], strict=False))):
        area = (t1 - t0) * (w0 + w1) / 2
        before -= area
        rest = need - F.lit(before)
        root = F.sqrt(F.greatest(F.lit(w0 * w0) + rest * F.lit(2 * (w1 - w0) / (t1 - t0)), F.lit(0.0)))
        here = F.lit(t0) + rest * F.lit(2.0) / (F.lit(w0) + root)
        out = F.when(need <= F.lit(before + area), here).otherwise(out)
    return F.least(F.greatest(out, F.lit(0.0)), F.lit(1.0))


def word_count(text: Column) -> Column:
    """Runs of characters that are not space, tab, line feed, vertical tab, form feed or return."""
    return F.coalesce(F.size(F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")), F.lit(0)).cast("long")


def targets(sums: DataFrame, source: str, schedules=SCHEDULES, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """sums (source, rows, source_size) plus kind and target."""
    weights = F.array(*[F.lit(integral(k)) for k in schedules])
    ranked = sums.withColumn("kind", ((F.row_number().over(Window.orderBy(F.col(source).asc_nulls_last())) - 1) % len(schedules)).cast("int"))
    ranked = ranked.withColumn("weight", F.element_at(weights, F.col("kind") + 1)).withColumn("cap", F.col("source_size") * F.lit(most)).withColumn("full_at", F.col("cap") / F.col("weight"))
    order = Window.orderBy("full_at", F.col(source).asc_nulls_last())
    upto, all_ = order.rowsBetween(Window.unboundedPreceding, 0), Window.partitionBy()
    ranked = ranked.withColumn("caps", F.sum("cap").over(upto)).withColumn("weights", F.sum("weight").over(all_) - F.sum("weight").over(upto)).withColumn("budget", F.sum("source_size").over(all_) * F.lit(share))
    # the first source that is not full at the water level, and the level there
    level = (F.col("budget") - (F.col("caps") - F.col("cap"))) / (F.col("weights") + F.col("weight"))
    ranked = ranked.withColumn("level", F.max(F.when(F.col("caps") + F.col("full_at") * F.col("weights") >= F.col("budget"), level)).over(all_))
    # past that source the quotient falls, for sources would be counted full that are not: the highest is the water level
    return ranked.withColumn("target", F.when(F.col("level").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("level") * F.col("weight")))).select(source, "rows", "source_size", "kind", "target")


def key_of(id_: Column, text: Column) -> Column:
    """What a source's documents are ordered by: ids of no or one value are told apart by their texts."""
    return F.md5(F.concat_ws(":", id_.cast("string"), F.md5(text)))


def mixed(rows: DataFrame, schedules=SCHEDULES, share: float = 1.5, most: float = 2.0, range_rows: int = RANGE_ROWS) -> DataFrame:
    """``rows`` (row, source, size, key) with m: size, source_size, target, copies, before (words of its source before it), kind.

    Small tables, of sources and of ranges, are summed and written first; ``row`` passes one exchange.
    """
    sums = rows.groupBy("source").agg(F.count(F.lit(1)).alias("rows"), F.sum("size").alias("source_size"))
    plan = materialise(targets(sums, "source", schedules, share, most).select(F.struct("source", "rows", "source_size", "kind", "target").alias("p")))
    place = F.conv(F.substring("key", 1, 8), 16, 10).cast("long")

    def ranged(what: DataFrame) -> DataFrame:
        return what.join(few(plan), F.col("source").eqNullSafe(F.col("p.source"))).withColumn("range", F.floor(place * F.ceil(F.col("p.rows") / range_rows) / F.lit(1 << 32)))

    words = materialise(ranged(rows.select("source", "size", "key")).groupBy("source", "range").agg(F.sum("size").alias("words")))
    before = F.sum("words").over(Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, 0)) - F.col("words")
    starts = materialise(words.select(F.struct("source", "range", before.alias("start")).alias("s")))
    within = Window.partitionBy("source", "range").orderBy("key", "size").rowsBetween(Window.unboundedPreceding, 0)
    run = ranged(rows).join(few(starts), F.col("source").eqNullSafe(F.col("s.source")) & (F.col("range") == F.col("s.range"))).withColumn("run", F.sum("size").over(within) - F.col("size"))
    size, target, source_size, done = F.col("size"), F.col("p.target"), F.col("p.source_size"), F.col("s.start") + F.col("run")
    rounds = F.when(source_size > 0, F.floor(target / source_size)).otherwise(F.lit(0)).cast("long")
    rest = target - rounds * source_size
    copies = F.when(size == 0, F.lit(0)).otherwise(rounds + F.when(done * 2 + size < rest * 2, 1).otherwise(0)).cast("int")
    return run.select("row", F.struct("size", source_size.alias("source_size"), target.alias("target"), copies.alias("copies"), done.alias("before"), F.col("p.kind").alias("kind")).alias("m"))


def position(copy: Column, schedules=SCHEDULES) -> Column:
    """Training time of a copy (0 is the first) of a row of ``mixed``."""
    part = (copy * F.col("m.source_size") + F.col("m.before") + F.col("m.size") / 2) / F.col("m.target")
    out = F.lit(None).cast("double")
    for k, knots in enumerate(schedules):
        out = F.when(F.col("m.kind") == k, time_at(part, knots)).otherwise(out)
    return F.when(copy < F.col("m.copies"), out)


def _rows(docs: DataFrame, carry: list[str], id_col: str, source: str, text: str) -> DataFrame:
    whole = F.col(f"`{text}`")
    return docs.select(F.struct(*[F.col(f"`{c}`").alias(c) for c in carry]).alias("row"), F.col(f"`{source}`").alias("source"), word_count(whole).alias("size"), key_of(F.col(f"`{id_col}`"), whole).alias("key"))


def in_training_order(copies: DataFrame, at: str, partitions: int | None = None) -> DataFrame:
    """Rows range-sorted by training time; those without one come last."""
    n = partitions or int(copies.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = [F.col(at).asc_nulls_last(), F.col("key")] if "key" in copies.columns else [F.col(at).asc_nulls_last()]
    return copies.repartitionByRange(n, *order).sortWithinPartitions(*order)


def mix(docs: DataFrame, id_col: str = "doc_id", source: str = "source", text: str = "text", schedules=SCHEDULES, **how) -> DataFrame:
    """(id, size, source_size, target, taken, position and again, the training times of the first two copies) of every row, in training order."""
    got = mixed(_rows(docs, [id_col], id_col, source, text), schedules, **how)
    out = got.select(F.col("row").getField(id_col).alias(id_col), "m.size", "m.source_size", "m.target", (F.col("m.size") * F.col("m.copies")).alias("taken"), position(F.lit(0), schedules).alias("position"), position(F.lit(1), schedules).alias("again"))
    return in_training_order(out, "position")


def in_order(docs: DataFrame, partitions: int | None = None, id_col: str = "doc_id", source: str = "source", text: str = "text", schedules=SCHEDULES, **how) -> DataFrame:
    """The mixed corpus: columns of ``docs``, a row per copy, range-sorted by training time."""
    got = mixed(_rows(docs, docs.columns, id_col, source, text), schedules, **how).where("m.copies > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), F.col("m.copies") - 1)))
    timed = got.select("row", position(F.col("copy"), schedules).alias("at"), F.xxhash64(F.col("row").getField(id_col)).alias("key"))
    return in_training_order(timed, "at", partitions).select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def op3_curriculum_mix(spark, sf_dir: str) -> DataFrame:
    return mix(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text"))


SQL_OP3 = r"""
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size, md5(concat_ws(':', CAST(doc_id AS VARCHAR), md5(text))) AS k FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS INT) AS kind FROM d GROUP BY source),
w AS (SELECT *, CAST(CASE kind WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS DOUBLE) AS weight, source_size * 2.0::DOUBLE AS cap FROM s),
r AS (SELECT *, cap / weight AS full_at FROM w),
p AS (SELECT *, sum(cap) OVER o AS caps, sum(weight) OVER () - sum(weight) OVER o AS above, CAST(sum(source_size) OVER () AS DOUBLE) * 1.5::DOUBLE AS budget
      FROM r WINDOW o AS (ORDER BY full_at, source NULLS LAST ROWS UNBOUNDED PRECEDING)),
l AS (SELECT max((budget - (caps - cap)) / (above + weight)) FILTER (WHERE caps + full_at * above >= budget) AS level FROM p),
t AS (SELECT source, source_size, kind, CASE WHEN level IS NULL THEN cap ELSE least(cap, level * weight) END AS target FROM p, l),
j AS (SELECT d.doc_id, d.size, t.source_size, t.kind, t.target, CAST(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.k, d.size ROWS UNBOUNDED PRECEDING) - d.size AS BIGINT) AS before,
      CASE WHEN t.source_size > 0 THEN CAST(floor(t.target / t.source_size) AS BIGINT) ELSE 0 END AS rounds FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
c AS (SELECT *, CASE WHEN size = 0 THEN 0 ELSE rounds + CASE WHEN before * 2 + size < (target - rounds * source_size) * 2 THEN 1 ELSE 0 END END AS copies,
      CASE WHEN target > 0 THEN (before + size / 2.0::DOUBLE) / target END AS first_part, CASE WHEN target > 0 THEN (source_size + before + size / 2.0::DOUBLE) / target END AS second_part FROM j)
SELECT doc_id, size, source_size, target, CAST(size * copies AS BIGINT) AS taken, CASE WHEN copies > 0 THEN when_trained(kind, first_part) END AS position, CASE WHEN copies > 1 THEN when_trained(kind, second_part) END AS again FROM c
"""

_TIME = r"""least(greatest(CASE {kind}
    WHEN 0 THEN CASE WHEN {part} * 3.0 <= 3.0 THEN 0.0 + ({part} * 3.0::DOUBLE - 0.0) * 2.0 / (4.0::DOUBLE + sqrt(greatest(16.0::DOUBLE + ({part} * 3.0::DOUBLE - 0.0) * -4.0::DOUBLE, 0.0))) ELSE 1.0 END
    WHEN 1 THEN CASE WHEN {part} <= 1.0 THEN ({part} * 1.0::DOUBLE) * 2.0 / (1.0::DOUBLE + sqrt(greatest(1.0::DOUBLE + {part} * 0.0, 0.0))) ELSE 1.0 END
    ELSE CASE WHEN {part} * 2.0::DOUBLE <= 0.75 THEN ({part} * 2.0::DOUBLE) * 2.0 / (1.0::DOUBLE + sqrt(greatest(1.0::DOUBLE + ({part} * 2.0::DOUBLE) * 4.0::DOUBLE, 0.0)))
         WHEN {part} * 2.0::DOUBLE <= 2.0 THEN 0.5::DOUBLE + ({part} * 2.0::DOUBLE - 0.75) * 2.0 / (2.0::DOUBLE + sqrt(greatest(4.0::DOUBLE + ({part} * 2.0::DOUBLE - 0.75) * 4.0::DOUBLE, 0.0))) ELSE 1.0 END
  END, 0.0), 1.0)"""
for _part in ("first_part", "second_part"):
    SQL_OP3 = SQL_OP3.replace(f"when_trained(kind, {_part})", _TIME.format(kind="kind", part=_part))

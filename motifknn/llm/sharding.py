"""Balanced shards by vector bin packing.

Groups are documents of one text. Groups too small to matter are dealt by text hash into ``LIGHT`` units; a
group with a noticeable part of the rows or bytes is a unit of its own. Units carry a vector of (bytes, tokens,
rows). Largest first, each goes to the shard where the dot product of its vector with what is left of the
shard's capacity is highest, among the shards that still have room for it if there are any.

The one exception to keeping a group whole: a group with more than ``SPLIT`` of all rows or bytes, a quarter of
what one of eight shards holds, would leave shards unequal, and the law on sizes comes first; it is dealt row by
row into several units. All other groups, in units of their own or not, lie in one shard.

Only units meet on the driver: at most ``LIGHT`` plus a bound that the shares imply, whatever the input.
Their table, shard and first slot, is bounded likewise and is what the rows are joined with. Slots number the
rows of a chunk (a part of a unit of bounded size) by id; chunks of a shard follow each other, so slots have no gaps.

Defined results: null text has size 1 and checksum 0, as the empty one; rows with equal ids are ordered by
size; repeated rows get a slot each, and are dealt like any rows if their group is split; an empty table gives an
empty table. Extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from motifknn.llm.mixing import word_count
from motifknn.llm.scratch import materialise

LIGHT = 1 << 14
#: A group with this part of all rows or bytes is a unit of its own; at most 2/OWN such groups exist.
OWN = 1 / 2048
#: A group with more than this part is split; a numbering chunk has about this many OWN parts at most.
SPLIT = 1 / 32


def place(vectors: np.ndarray, shards: int, names: np.ndarray) -> np.ndarray:
    """Shard of each unit."""
    total = np.maximum(vectors.sum(0), 1)
    v = vectors * (shards / total)
    left = np.ones((shards, v.shape[1]))
    out = np.empty(len(v), np.int64)
    for i in np.lexsort((names, -v.max(1))):
        room = (left >= v[i]).all(1)
        dots = left @ v[i]
        out[i] = np.argmax(np.where(room, dots, -np.inf) if room.any() else dots)
        left[out[i]] -= v[i]
    return out


def shard_by_bytes(docs: DataFrame, shards: int = 8, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, size, text_crc32, law, shard, slot, grown_shard) of every row."""
    spark = docs.sparkSession
    whole = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    rows = materialise(
        docs.select(
            F.col(f"`{id_col}`").alias("id"), (F.octet_length(whole) + F.lit(1)).cast("long").alias("size"), F.crc32(whole.cast("binary")).alias("text_crc32"), F.xxhash64(whole).alias("h"),
            word_count(whole).alias("tokens"), F.monotonically_increasing_id().alias("row"),
        )
    )
    all_rows, all_bytes = rows.agg(F.count(F.lit(1)), F.sum("size")).first()
    own_rows, own_bytes = max(1, (all_rows or 0) * OWN), max(1, (all_bytes or 0) * OWN)
    heavy = rows.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("b")).where((F.col("n") > own_rows) | (F.col("b") > own_bytes)).orderBy("h").collect()  # 2 / OWN rows at most
    chunks = [int(min(r["n"], max(1, np.ceil(max(r["n"] / own_rows, r["b"] / own_bytes))))) for r in heavy]
    bases = LIGHT + np.cumsum([0, *chunks])[:-1] if heavy else []
    split = [max(r["n"] / all_rows, r["b"] / all_bytes) > SPLIT for r in heavy]
    table = spark.createDataFrame([(r["h"], int(b), c) for r, b, c in zip(heavy, bases, chunks, strict=True)], "h long, base long, chunks int")
    dealt = rows.join(F.broadcast(table), "h", "left").withColumn("chunk", F.when(F.col("base").isNull(), F.pmod("h", F.lit(LIGHT))).otherwise(F.col("base") + F.pmod(F.xxhash64("row"), F.col("chunks").cast("long"))))
    sums = dealt.groupBy("chunk").agg(F.sum("size").alias("b"), F.sum("tokens").alias("t"), F.count(F.lit(1)).alias("n")).orderBy("chunk").collect()  # LIGHT + chunks rows at most
    # chunks of a group that is not split are one unit
    unit_of = {int(b) + k: (int(b) + k if s else int(b)) for b, c, s in zip(bases, chunks, split, strict=True) for k in range(c)}
    names = np.array([unit_of.get(r["chunk"], r["chunk"]) for r in sums], np.int64)
    units, at = np.unique(names, return_inverse=True)
    vectors = np.zeros((len(units), 3))
    np.add.at(vectors, at, np.array([(r["b"], r["t"], r["n"]) for r in sums], float).reshape(-1, 3))
    where = place(vectors, shards, units)[at] if len(units) else at
    first, used = [], [0] * shards
    for r, s in zip(sums, where, strict=True):
        first.append((r["chunk"], int(s), used[s]))
        used[s] += r["n"]
    plan = spark.createDataFrame(first, "chunk long, shard int, base_slot long")
    number = F.row_number().over(Window.partitionBy("chunk").orderBy("id", "size", "text_crc32"))
    return dealt.drop("base").withColumn("number", number).join(F.broadcast(plan), "chunk").select(
        F.col("id").alias(id_col), "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("base_slot") + F.col("number") - 1).alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )


def op8_vector_bin_packing_shards(spark, sf_dir: str) -> DataFrame:
    return shard_by_bytes(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))

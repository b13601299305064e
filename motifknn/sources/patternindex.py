"""A data source over pattern-sharded files: a shard that cannot hold the pattern is not read.

Beside its rows every shard has the set of two-symbol runs that occur in it; a query pattern whose runs are not
all there rules the shard out, in the planner, before any task starts. The pattern is an option or a pushed
filter (``contains``, with ``spark.sql.python.filterPushdown.enabled``); the filter itself stays with Spark. Files are opened in the tasks, so the path
must be one that the driver and all executors mount alike; object stores are not reached this way.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator
from pathlib import Path

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, Filter, InputPartition, StringContains

from motifknn.functions.patterns import ends


def write_pattern_index(items: DataFrame, path: str, shards: int) -> None:
    """(id, seq) as ``shards`` files of JSON lines, with the runs of each."""
    dealt = items.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    dealt.repartition(shards, "shard").write.partitionBy("shard").json(f"{path}/rows")
    runs = ends(dealt.select(F.col("shard").alias("id"), "seq"), 2).where("char_length(pattern) = 2").select(F.col("id").alias("shard"), F.col("pattern").alias("run")).distinct()
    runs.groupBy("shard").agg(F.collect_list("run").alias("runs")).write.json(f"{path}/runs")


class _Shard(InputPartition):
    def __init__(self, shard: int):
        super().__init__(shard)
        self.shard = shard


class PatternIndexReader(DataSourceReader):
    def __init__(self, path: str, pattern: str):
        self.path, self.patterns = path.removeprefix("file:"), [pattern]

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:  # noqa: N802
        for f in filters:
            if isinstance(f, StringContains) and tuple(f.attribute) == ("seq",):
                self.patterns.append(f.value)
            yield f

    def partitions(self) -> list[InputPartition]:
        need = {p[i : i + 2] for p in self.patterns for i in range(len(p) - 1)}
        found = []
        for f in Path(self.path, "runs").glob("part-*"):
            for line in f.open():
                row = json.loads(line)
                if need <= set(row["runs"]):
                    found.append(_Shard(int(row["shard"])))
        return found

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for f in Path(self.path, "rows", f"shard={partition.shard}").glob("part-*"):
            for line in f.open():
                row = json.loads(line)
                yield row["id"], row.get("seq")


class PatternIndexSource(DataSource):
    """format("patternindex").option("pattern", ...).load(path)"""

    @classmethod
    def name(cls) -> str:
        return "patternindex"

    def schema(self) -> str:
        return "id long, seq string"

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        return PatternIndexReader(self.options["path"], self.options.get("pattern", ""))

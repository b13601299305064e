"""Tables written between phases, in the folder that the cluster shares (``spark.checkpoint.dir``).

Index phases are cut here: a lost executor costs a read, not a recomputation, and loops keep flat plans.
"""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_written: list[tuple[SparkSession, str]] = []
_registered: list[bool] = []


def shared_folder(spark: SparkSession) -> str:
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not found:
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="stage-"))
        found = sc.getCheckpointDir()
    return found.rstrip("/")


def staged(df: DataFrame) -> DataFrame:
    """``df`` written out and read again; as it is if that was done before."""
    if hasattr(df, "_staged_path"):
        return df
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stage-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if not _registered:
        atexit.register(_drop)
        _registered.append(True)
    _written.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path  # noqa: SLF001
    return out


#: A written table of keys is broadcast if its rows, counted, take so many bytes at most; beyond, both sides of a join are exchanged.
FEW_BYTES = 64 << 20


def few(small: DataFrame, row_bytes: int = 64) -> DataFrame:
    return F.broadcast(small) if small.count() * row_bytes <= FEW_BYTES else small


@contextmanager
def scratch() -> Iterator[None]:
    """Tables that are staged inside go when it ends."""
    mark = len(_written)
    try:
        yield
    finally:
        release(mark)


def forget(df: DataFrame) -> None:
    """Delete a staged table that no later plan reads."""
    path = getattr(df, "_staged_path", None)
    for entry in [x for x in _written if x[1] == path]:
        _delete(*entry)
        _written.remove(entry)


def collect_garbage(spark: SparkSession) -> None:
    """Exchange files go when the driver's collector sees that no plan holds them."""
    gc.collect()
    spark.sparkContext._jvm.java.lang.System.gc()  # noqa: SLF001


def release(mark: int, keep: DataFrame | None = None) -> None:
    """Delete the tables staged since there were ``mark`` of them, but for ``keep``."""
    kept = getattr(keep, "_staged_path", None)
    gone = [x for x in _written[mark:] if x[1] != kept]
    for entry in gone:
        _delete(*entry)
        _written.remove(entry)
    if gone:
        collect_garbage(gone[0][0])


def _delete(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)  # noqa: SLF001
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)  # noqa: SLF001


def staged_so_far() -> int:
    return len(_written)


def _drop() -> None:
    for spark, path in _written:
        if spark.sparkContext._jsc is None:  # noqa: SLF001
            continue
        try:
            _delete(spark, path)
        except Exception as e:  # the session may be gone when the interpreter ends
            print(f"left behind: {path} ({type(e).__name__})")

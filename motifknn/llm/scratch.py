"""Intermediate tables in the folder that the cluster shares.

Lineage is cut by writing a Parquet table under ``spark.checkpoint.dir`` and reading it back: unlike a
local checkpoint it outlives any executor, and unlike an RDD checkpoint it is compressed and columnar.
"""

from __future__ import annotations

import atexit
import gc
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_left: list[tuple[SparkSession, str]] = []
_collected = [0.0]


def folder(spark: SparkSession) -> str:
    """The shared folder: the session's setting, else one of our own (single-machine tests)."""
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not found:
        if sc.master != "local" and not sc.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir is not set: executors need a folder that all share")
        found = tempfile.mkdtemp(prefix="scratch-")
        sc.setCheckpointDir(found)
        found = sc.getCheckpointDir()
    return found.rstrip("/")


def collect_garbage(spark: SparkSession, every: float = 4.0) -> None:
    """Exchange files go when the driver's collector finds that no plan holds them; let it look, now and then."""
    if time.monotonic() - _collected[0] >= every:
        gc.collect()
        spark.sparkContext._jvm.java.lang.System.gc()  # noqa: SLF001
        _collected[0] = time.monotonic()


def materialise(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder and return the table read back; it goes when the program ends."""
    spark = df.sparkSession
    path = f"{folder(spark)}/t-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if not _left:
        atexit.register(_clear)
    _left.append((spark, path))
    collect_garbage(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path  # noqa: SLF001
    return out


#: A written table of keys is sent to every executor up to so many bytes as rows of a hash table; beyond, both sides of a join are exchanged.
FEW_BYTES = 64 << 20
#: What a row costs there besides its values.
ROW_BYTES = 40


def few(small: DataFrame) -> DataFrame:
    """``small``, a written table, to be broadcast if its rows, counted, take at most FEW_BYTES."""
    width = ROW_BYTES + sum(_width(f.dataType) for f in small.schema.fields)
    return F.broadcast(small) if small.count() * width <= FEW_BYTES else small


def _width(kind: T.DataType) -> int:
    """Bytes of a value, 64 where that is not fixed."""
    if isinstance(kind, T.StructType):
        return 16 + sum(_width(f.dataType) for f in kind.fields)
    return 64 if isinstance(kind, (T.ArrayType, T.MapType, T.StringType, T.BinaryType)) else 8


def release(*tables: DataFrame | None) -> None:
    """Delete tables from ``materialise`` that no later plan reads."""
    for t in tables:
        path = getattr(t, "_scratch_path", None)
        if path:
            _delete(t.sparkSession, path)
            _left[:] = [x for x in _left if x[1] != path]


def release_all_but(inputs: DataFrame) -> None:
    """Delete all tables from ``materialise`` that ``inputs`` does not read: those of stages whose results are written."""
    if _left:
        read = inputs.inputFiles()
        for spark, path in list(_left):
            name = path.rsplit("/", 1)[1]
            if not any(name in f for f in read):
                _delete(spark, path)
                _left.remove((spark, path))
        collect_garbage(inputs.sparkSession, 0.0)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm  # noqa: SLF001
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)  # noqa: SLF001


def _clear() -> None:
    for spark, path in _left:
        if spark.sparkContext._jsc is None:  # noqa: SLF001
            continue
        try:
            _delete(spark, path)
        except Exception as e:  # the session may be gone when the interpreter ends
            print(f"left behind: {path} ({type(e).__name__})")

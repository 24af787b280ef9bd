"""Cutting lineage in the cluster's shared folder, and sizes of what is broadcast."""

from __future__ import annotations

import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes (as rows in memory, about) up to which a table is broadcast.
BROADCAST_BYTES = 48 << 20


def _folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir.  Where that is unset the master must run in this process (as in tests)."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="erblock-"))
    return sc.getCheckpointDir()


def checkpoint(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the folder of spark.checkpoint.dir; a temporary one only where that is unset in a local session."""
    _folder(df.sparkSession)
    return df.checkpoint(eager=True)


def new_path(spark: SparkSession) -> str:
    """A path in the shared folder that nothing uses."""
    return f"{_folder(spark)}/{uuid.uuid4().hex}"


#: Whether shuffle files go when the action that wrote them ends, rather than when the driver next collects its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


_INSIDE: list = []
_LOCK = threading.Lock()


@contextmanager
def tidy(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the actions inside go with them; the last thread that leaves puts the setting back."""
    with _LOCK:
        _INSIDE.append(_INSIDE[0] if _INSIDE else spark.conf.get(CLEANUP, None))
        spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        with _LOCK:
            before = _INSIDE.pop()
            if not _INSIDE:
                spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


def written(df: DataFrame, codec: str = "none") -> DataFrame:
    """``df`` as a table in the folder of spark.checkpoint.dir: columnar, and free of lineage.

    Row groups are small, as each task that writes holds one in memory.  There is no codec unless asked for: hashes and
    compressed texts gain nothing by one, and its buffers lie outside the heap.  What was shuffled for it is deleted.
    """
    spark = df.sparkSession
    path = new_path(spark)
    with tidy(spark):
        df.write.option("compression", codec).option("parquet.block.size", 16 << 20).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_to = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables of ``written`` that nothing will read again."""
    for t in tables:
        spark = t.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(t.written_to)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def _bytes(value: Column, kind: T.DataType) -> Column:
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return F.coalesce(F.octet_length(value), F.lit(0)) + 32
    if isinstance(kind, T.StructType):
        return sum((_bytes(value[f.name], f.dataType) for f in kind.fields), F.lit(16))
    if isinstance(kind, T.ArrayType):
        fixed = isinstance(kind.elementType, (T.NumericType, T.BooleanType, T.StructType)) and not any(isinstance(f.dataType, (T.StringType, T.BinaryType, T.ArrayType, T.MapType)) for f in getattr(kind.elementType, "fields", []))
        each = F.lit(16 + 16 * len(getattr(kind.elementType, "fields", [None])))
        if fixed:
            return F.coalesce(F.greatest(F.size(value), F.lit(0)) * each, F.lit(0)) + 32
        return F.coalesce(F.aggregate(value, F.lit(32).cast("long"), lambda acc, x: acc + _bytes(x, kind.elementType).cast("long")), F.lit(0))
    return F.lit(16)


def fits(df: DataFrame, most: int = BROADCAST_BYTES) -> bool:
    """Whether the rows of ``df`` take at most about ``most`` bytes in memory: counted, strings by their length."""
    size = sum((_bytes(F.col(f"`{f.name}`"), f.dataType) for f in df.schema.fields), F.lit(64))
    return (df.agg(F.sum(size.cast("long"))).first()[0] or 0) <= most

"""Tables written to the folder that all executors share: how loops cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, MapType, StringType, StructType

#: Largest table, in bytes of its rows, that is sent to every executor.
BROADCAST_BYTES = 32 << 20

#: Whether a query's shuffle files go as soon as it ends, instead of when the driver happens to collect its garbage.
_DROP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or one of our own where that is unset: in the warehouse,
    and in the machine's temporary folder only in local mode."""
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given.rstrip("/")
    if (now := spark.sparkContext.getCheckpointDir()) is not None:
        return now.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":  # one machine, as in tests
        spark.sparkContext.setCheckpointDir(os.path.join(tempfile.gettempdir(), "checkpoints"))
    else:
        spark.sparkContext.setCheckpointDir(spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/checkpoints")
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def _remove_quietly(spark: SparkSession, path: str) -> None:
    try:
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may have ended before this process
        pass


@contextmanager
def _shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    before = spark.conf.get(_DROP, None)
    spark.conf.set(_DROP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_DROP) if before is None else spark.conf.set(_DROP, before)


def store(df: DataFrame, label: str) -> DataFrame:
    """Write df to the shared folder and read it back: cuts lineage, survives lost executors, goes at exit. The shuffle
    files of the write go when it ends, as nothing reads them again."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    with _shuffles_dropped(spark):
        df.write.parquet(path)
    atexit.register(_remove_quietly, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path  # type: ignore[attr-defined]
    return out


def discard(df: DataFrame) -> None:
    """Delete a stored table that no later plan reads."""
    _remove_quietly(df.sparkSession, df._stored_at)  # type: ignore[attr-defined]


def read(spark: SparkSession, stored: list[DataFrame]) -> DataFrame:
    """The rows of several stored tables of one schema, as a single scan."""
    return spark.read.schema(stored[0].schema).parquet(*[df._stored_at for df in stored])  # type: ignore[attr-defined]


def row_bytes(df: DataFrame) -> Column:
    """About the bytes that a row of df takes in memory."""
    fixed, parts = 16, []
    for f in df.schema:
        if isinstance(f.dataType, (StringType, BinaryType)):
            parts.append(F.coalesce(F.octet_length(f"`{f.name}`"), F.lit(0)) + 16)
        elif isinstance(f.dataType, (ArrayType, MapType, StructType)):
            parts.append(F.coalesce(F.octet_length(F.to_json(F.struct(f"`{f.name}`"))), F.lit(0)) * 2 + 16)
        else:
            fixed += 8
    return sum(parts, F.lit(fixed)).cast("bigint")


def small(df: DataFrame) -> DataFrame:
    """df marked for broadcast if its rows are measured to take at most BROADCAST_BYTES; otherwise left for a shuffle.

    The measurement runs df, so df should read stored tables.
    """
    size = df.agg(F.sum(row_bytes(df))).first()[0] or 0
    return F.broadcast(df) if size <= BROADCAST_BYTES else df

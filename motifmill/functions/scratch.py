"""Intermediate results that outlive a lost executor.

Results that a plan reads twice, and results of iterations, are written as
Parquet below the shared folder of ``spark.checkpoint.dir`` and read again, so
their lineage ends in files that every executor can open.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
_WRITTEN: list[tuple[SparkSession, str]] = []
_TABLES: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only in local mode without that setting."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = "file://" + tempfile.mkdtemp(prefix="motifmill-")
    return _OWN[app]


def fresh_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_dir(spark)}/motifmill/{label}-{uuid.uuid4().hex}"
    if not _WRITTEN:
        atexit.register(_clean)
    _WRITTEN.append((spark, path))
    return path


#: Lets Spark drop a query's shuffle files as soon as the query has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, label: str, codec: str | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and return a scan of what was written; the shuffle files of the write go with it.

    ``codec``: a compression other than the session's.
    """
    spark = df.sparkSession
    path = fresh_path(spark, label)
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path, compression=codec)
    finally:
        if before is None:
            spark.conf.unset(CLEANUP)
        else:
            spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def materialise_bucketed(df: DataFrame, label: str, key: str, codec: str | None = None) -> DataFrame:
    """The same as a table bucketed by ``key``, one file a bucket; the table's name is dropped at exit.

    Joins and groups on the key and further columns then need no exchange, as long as
    ``spark.sql.requireAllClusterKeysForCoPartition`` is false.
    """
    spark = df.sparkSession
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    name = f"motifmill_{label}_{uuid.uuid4().hex}"
    path = fresh_path(spark, label)
    _TABLES.append((spark, name))
    dealt = df.repartition(buckets, key)
    writer = dealt.write.option("compression", codec) if codec else dealt.write
    writer.bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(name)
    return spark.table(name)


def discard(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def _clean() -> None:
    for spark, name in _TABLES:
        try:
            if spark.sparkContext._jsc is not None:
                spark.sql(f"DROP TABLE IF EXISTS {name}")
        except Exception:  # the session has ended before the interpreter
            break
    for spark, path in _WRITTEN:
        try:
            if spark.sparkContext._jsc is not None:
                discard(spark, path)
        except Exception:  # the session has ended before the interpreter
            return

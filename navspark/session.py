"""Session defaults for applications; the driver's own session is used as it is given."""

from __future__ import annotations

import atexit
import re
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DEFAULTS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.sql.parquet.compression.codec": "zstd",
}


def session(app: str = "navspark", master: str | None = None, input_bytes: int | None = None, **conf: str) -> SparkSession:
    """A session with the defaults; shuffle partitions follow the input at 128 MB each."""
    b = SparkSession.builder.appName(app)
    if master:
        b = b.master(master)
    for k, v in (DEFAULTS | conf).items():
        b = b.config(k, v)
    if input_bytes:
        b = b.config("spark.sql.shuffle.partitions", str(max(8, -(-input_bytes // (128 << 20)))))
    return b.getOrCreate()


def shared_folder(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names. Only a local session may name none."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        path = "/tmp/checkpoints"
    return path.rstrip("/")


def kept(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder: computed once, its lineage cut, and nothing is held in the
    executors' memory or on their disks."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(f"{shared_folder(df.sparkSession)}/tables")
    return df.checkpoint()


_TABLES: list[list[tuple[SparkSession, str]]] = [[]]  #: what ``stored`` has written, by the ``tables`` block it was called in
_FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame) -> DataFrame:
    """``kept`` for large tables: packed columns instead of rows, and what its computation has shuffled is deleted as
    soon as it is written. The table lasts until the ``tables`` block around the call ends, or else the program."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/tables/{uuid.uuid4().hex}"
    _TABLES[-1].append((spark, path))
    before = spark.conf.get(_FREED, "false")
    spark.conf.set(_FREED, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(_FREED, before)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def tables() -> Iterator[None]:
    """Deletes at its end what was ``stored`` in it; no frame that reads it may be left by then."""
    _TABLES.append([])
    try:
        yield
    finally:
        _delete(_TABLES.pop())


def _delete(those: list[tuple[SparkSession, str]]) -> None:
    for spark, path in those:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _clean() -> None:
    try:
        _delete(_TABLES[0])
    except Exception:  # the session may have ended first
        return


def bounded(df: DataFrame, most: int = 1_000_000) -> DataFrame:
    """Marked for broadcast if it has been counted and has at most ``most`` (narrow) rows."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df

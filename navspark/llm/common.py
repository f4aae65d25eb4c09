"""What the corpus operators share: scratch tables, checked broadcasts, row keys."""

from __future__ import annotations

import atexit
import ctypes
import os
import re
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side of a join is broadcast only when it has been counted and its rows fit in this many bytes.
BROADCAST_BYTES = 32 << 20

_OWN: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh folder under the session's ``spark.checkpoint.dir``.

    On a cluster that folder is shared by the driver and all executors, and a session that
    names none is an error there. Only a local session (tests) gets one below /tmp/checkpoints.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = f"file:///tmp/checkpoints/{os.getuid()}"
    path = f"{base.rstrip('/')}/corpus/{label}-{uuid.uuid4().hex}"
    if not _OWN:
        atexit.register(_clean)
    _OWN.append((spark, path))
    return path


def _clean() -> None:
    for spark, path in _OWN:
        try:
            drop(spark, path)
        except Exception:  # the session may have ended first
            return


def drop(spark: SparkSession, path: str) -> None:
    """Delete a scratch folder on whatever file system it lies."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def written(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut, and a lost
    executor costs a reread of files instead of a recomputation."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def give_back() -> None:
    """Returns memory that a finished batch has left free to the system: a worker waits for its next
    task beside the JVM's tasks and should not keep its largest batch's pages meanwhile."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


def arrow_map(df: DataFrame, run, schema) -> DataFrame:
    """``mapInArrow`` that gives memory back after each batch."""

    def tidy(batches):
        for out in run(batches):
            yield out
            del out
            give_back()

    return df.mapInArrow(tidy, schema)


def checked(small: DataFrame, row_bytes: int = 64, items: str | None = None) -> DataFrame:
    """Mark a usually small side of a join for broadcast, if its counted rows (and the eight
    bytes of each element of the array column ``items``) fit ``BROADCAST_BYTES``. Otherwise
    the join stays a shuffled one, which AQE splits where a key is skewed."""
    n, m = small.agg(F.count("*"), F.coalesce(F.sum(F.size(items)), F.lit(0)) if items else F.lit(0)).first()
    return F.broadcast(small) if n * row_bytes + 8 * m <= BROADCAST_BYTES else small


def apart(docs: DataFrame) -> list:
    """Columns to select so that names can't clash: ``row``, a struct of all columns of ``docs``
    but ``text``, then ``doc_id``, ``text`` and ``row_key``. ``whole`` is the way back."""
    rest = [F.col(f"`{c}`") for c in docs.columns if c != "text"]
    text = F.col("text").cast("string")
    return [F.struct(*rest).alias("row"), F.col("doc_id"), text.alias("text"), text_key(text).alias("row_key")]


def whole(docs: DataFrame, text: str = "text") -> list:
    """The columns of ``docs`` again, from ``row`` and the column ``text``."""
    return [F.col(text).alias("text") if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns]


def same_row(a: DataFrame, b: DataFrame):
    """Join condition on (doc_id, row_key); null ids meet."""
    return a.doc_id.eqNullSafe(b.doc_id) & (a.row_key == b.row_key)


def once(c):
    """The column, computed once a row. An array that a lambda captures must be: a filter placed
    later on the result would else be pushed below the projection, copying the array's whole
    expression into the lambda, where it runs again for each element."""
    return F.when(F.monotonically_increasing_id() >= 0, c)


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def az_lower(c):
    """Lower-cases A to Z alone; pure ASCII takes the fast built-in."""
    return F.when(F.octet_length(c) == F.char_length(c), F.lower(c)).otherwise(F.translate(c, _UPPER, _LOWER))


def text_key(text="text"):
    """Tells apart rows that share a doc_id; rows equal in both are interchangeable."""
    return F.coalesce(F.xxhash64(F.col(text) if isinstance(text, str) else text), F.lit(0))

"""Line deduplication against levelled sorted runs of line hashes.

The store holds runs of (h1, h2, owner): 128 bits of a line's key and the smallest doc_id that
holds it. A run is a table bucketed by the hashes, each bucket one file sorted by them. A batch
of documents is reduced to its distinct keys, dealt once to the same buckets, and merge-joined
with run after run: no run is shuffled or sorted again. What the runs lack is added as a new
run. When a level has ``FANOUT`` runs they are compacted into one run of the next level, so a
batch meets a number of runs that is logarithmic in the batches so far. Batches must come in
order of doc_id (checked), so a run's owner is never larger than a later batch's ids, and a
decision once taken stands.

A line's key is the line stripped of ASCII white space with A-Z lower-cased. Keys of at least
``MIN_CHARS`` code points that two documents hold keep only the lines of the smallest doc_id.

Only built-in functions run. Lines travel as hashes and positions; a very common line costs
partial aggregates and a join whose hot key AQE splits.

Defined results: null or empty text is one empty line. Rows sharing a doc_id are one document
where ownership is concerned, and each loses its own lines. Rows with a null doc_id own
nothing and lose nothing. An empty table gives an empty result. Extra columns stay, whatever
their names.
"""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navspark.llm.common import apart, az_lower, checked, drop, once, same_row, scratch, text_key, whole, written

MIN_CHARS = 10
BATCHES = 4  #: batches into which one table is cut
FANOUT = 2  #: runs of a level that are compacted into one of the next

_SPACE = " \t\n\x0b\x0c\r"
_ORDERED = "spark.sql.legacy.bucketedTableScan.outputOrdering"  #: lets a scan of one file a bucket tell its order


def lines_of(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc_id, row_key, pos, h1, h2) of each line with a key long enough."""
    one = docs.where("doc_id is not null").select(
        F.col("doc_id").cast("long").alias("doc_id"),
        text_key(F.col("text").cast("string")).alias("row_key"),
        F.posexplode(F.split(F.coalesce(F.col("text").cast("string"), F.lit("")), "\n", -1)).alias("pos", "line"),
    )
    stripped = one.select("doc_id", "row_key", "pos", F.btrim("line", F.lit(_SPACE)).alias("line")).where(F.char_length("line") >= min_chars)
    key = az_lower(F.col("line"))
    return stripped.select("doc_id", "row_key", "pos", key.alias("key")).select(
        "doc_id", "row_key", "pos", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(1), "key").alias("h2")
    )


@contextmanager
def _in_order(spark: SparkSession):
    """Plans made inside know the order of sorted buckets; the session's setting is put back."""
    before = spark.conf.get(_ORDERED, None)
    spark.conf.set(_ORDERED, "true")
    try:
        yield
    finally:
        spark.conf.unset(_ORDERED) if before is None else spark.conf.set(_ORDERED, before)


class LineRuns:
    """The levelled store. ``add`` resolves a batch's keys and keeps those that are new.

    There are as many buckets as the session has shuffle partitions when the store is opened.
    """

    def __init__(self, spark: SparkSession, fanout: int = FANOUT):
        self.spark, self.fanout = spark, fanout
        self.buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.levels: list[list[str]] = []
        self.paths: dict[str, str] = {}
        self.newest: int | None = None

    def tables(self) -> list[str]:
        return [t for level in self.levels for t in level]

    def runs(self) -> DataFrame | None:
        """All keys of the store."""
        out = None
        for t in self.tables():
            one = self.spark.table(t)
            out = one if out is None else out.unionByName(one)
        return out

    def _write(self, keys: DataFrame) -> str:
        name, path = f"line_run_{uuid.uuid4().hex}", scratch(self.spark, "run")
        dealt = keys.select("h1", "h2", "owner").repartition(self.buckets, "h1", "h2")
        dealt.write.format("parquet").bucketBy(self.buckets, "h1", "h2").sortBy("h1", "h2").option("path", path).saveAsTable(name)
        self.paths[name] = path
        return name

    def _forget(self, name: str) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {name}")
        drop(self.spark, self.paths.pop(name))

    def close(self) -> None:
        for t in list(self.paths):
            self._forget(t)
        self.levels = []

    def resolve(self, lines: DataFrame) -> DataFrame:
        """(h1, h2, own, owner) of the batch's keys: its own smallest doc_id, and the runs' owner or null."""
        met = lines.groupBy("h1", "h2").agg(F.min("doc_id").alias("own")).withColumn("owner", F.lit(None).cast("long"))
        for t in self.tables():
            run = self.spark.table(t).select("h1", "h2", F.col("owner").alias("held")).hint("merge")
            met = met.join(run, ["h1", "h2"], "left").select("h1", "h2", "own", F.coalesce("owner", "held").alias("owner"))
        return met

    def add(self, lines: DataFrame) -> DataFrame:
        """(h1, h2, owner) of each distinct key of the batch, owners of earlier batches first."""
        with _in_order(self.spark):
            met = written(self.resolve(lines), "resolved")
        low, high = met.agg(F.min("own"), F.max("own")).first()
        if low is not None:
            if self.newest is not None and low < self.newest:
                raise ValueError(f"a batch with doc_id {low} came after one with {self.newest}")
            self.newest = high
        self._push(0, self._write(met.where("owner is null").select("h1", "h2", F.col("own").alias("owner"))))
        return met.select("h1", "h2", F.coalesce("owner", "own").alias("owner"))

    def _push(self, level: int, name: str) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(name)
        if len(self.levels[level]) >= self.fanout:
            old, self.levels[level] = self.levels[level], []
            merged = self._write(self._merged(old))
            for t in old:
                self._forget(t)
            self._push(level + 1, merged)

    def _merged(self, names: list[str]) -> DataFrame:
        out = None
        for t in names:
            out = self.spark.table(t) if out is None else out.unionByName(self.spark.table(t))
        return out


def dropped_lines(docs: DataFrame, batches: int = BATCHES, min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc_id, row_key, gone: positions) of the rows that lose lines."""
    spark = docs.sparkSession
    lines = lines_of(docs, min_chars)
    cuts = docs.agg(F.percentile_approx(F.col("doc_id").cast("long"), [i / batches for i in range(1, batches)], 10_000)).first()[0] if batches > 1 else []
    batch = sum(((F.col("doc_id") > c).cast("int") for c in sorted(set(cuts or []))), F.lit(0))
    path = scratch(spark, "lines")
    lines.withColumn("batch", batch).write.partitionBy("batch").parquet(path)
    stored = spark.read.schema("doc_id long, row_key long, pos int, h1 long, h2 long, batch int").parquet(path)
    store, gone = LineRuns(spark), None
    try:
        for i in range(len(set(cuts or [])) + 1):
            part = stored.where(F.col("batch") == i)
            owners = store.add(part)
            lost = part.join(owners, ["h1", "h2"]).where("owner < doc_id").select("doc_id", "row_key", "pos")
            gone = lost if gone is None else gone.unionByName(lost)
        return written(gone.groupBy("doc_id", "row_key").agg(F.collect_set("pos").alias("gone")), "gone")
    finally:
        store.close()


def _cut(docs: DataFrame, batches: int, min_chars: int) -> DataFrame:
    """(row, doc_id, text, n_lines, n_dropped) of each row, text without the lines it loses."""
    gone = dropped_lines(docs, batches, min_chars)
    keyed = docs.select(*apart(docs))
    j = keyed.join(checked(gone, 48, "gone"), same_row(keyed, gone), "left").select(
        "row", keyed.doc_id, "text", "gone", once(F.split(F.coalesce("text", F.lit("")), "\n", -1)).alias("lines")
    )
    keep = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("gone"))
    rest = F.array_join(F.transform(keep, lambda i: F.get("lines", i)), "\n")
    n_dropped = F.coalesce(F.when(F.col("gone").isNotNull(), F.size("gone")), F.lit(0)).cast("long")
    return j.select("row", "doc_id", F.when(F.col("gone").isNull(), F.col("text")).otherwise(rest).alias("text"), F.size("lines").cast("long").alias("n_lines"), n_dropped.alias("n_dropped"))


def without_repeated_lines(docs: DataFrame, batches: int = BATCHES, min_chars: int = MIN_CHARS) -> DataFrame:
    """``docs``, its columns as they are but for the text."""
    return _cut(docs, batches, min_chars).select(*whole(docs))


def op9_result(docs: DataFrame) -> DataFrame:
    got = _cut(docs.select("doc_id", "text"), BATCHES, MIN_CHARS)
    return got.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


OP9_SQL = r"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
k AS (SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
o AS (SELECT key, min(doc_id) AS owner FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2),
f AS (SELECT k.doc_id, k.pos, k.line, o.owner IS NOT NULL AND k.doc_id > o.owner AS gone FROM k LEFT JOIN o ON k.key = o.key)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(*) FILTER (WHERE gone) AS BIGINT) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM f GROUP BY doc_id
"""

"""Tables in and out: explicit schemas, partitioned and idempotent writes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Schemas of the stored tables, as DDL; production reads never infer.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str, fmt: str = "parquet") -> DataFrame:
    """A stored table; JSON, CSV and ORC copies are read with the same schema."""
    reader = spark.read.format(fmt)
    if fmt in ("json", "csv"):
        reader = reader.schema(SCHEMAS[name])
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.load(f"{sf_dir}/{name}.{fmt}")


def load_stream(spark: SparkSession, path: str, name: str, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(SCHEMAS[name])
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path)


def save(df: DataFrame, path: str, partition_by: list[str] | None = None, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    w = df.write.format(fmt).mode(mode)
    if partition_by:
        w = w.partitionBy(*partition_by)
    w.save(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by key, so that later joins on it need no shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)


def batch_writer(path: str):
    """For ``foreachBatch``: one folder a batch id, so a replayed batch overwrites itself."""

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={batch}")

    return put

"""The corpus pipeline: quality, lines, near duplicates, benchmark leaks, packing.

Every stage works on all that its predecessor kept and leaves the columns of ``documents`` as
they are, but for the text (and n_chars) that line deduplication cuts; the last returns pieces.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navspark.llm import decontam, line_runs, packing_dp, quality_mil, simhash_vp
from navspark.llm.common import table, written

SHINGLE = 5  #: words of a shingle
SIMILARITY = 0.8
BITS = 512
#: Large shingle sets of similarity 0.8 have a cosine of 1.6 / 1.8, so about 77 of 512 bits differ, give
#: or take 8. Candidates within this radius are compared before the others; shingle sets decide.
RADIUS = 104


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_mil.good_documents(docs, table(spark, sf_dir, "labels"))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    got = line_runs.without_repeated_lines(docs)
    return got.withColumn("n_chars", F.char_length(F.coalesce("text", F.lit(""))).cast("long")) if "n_chars" in docs.columns else got


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group stays: that of the smallest doc_id."""
    return simhash_vp.survivors(docs, SHINGLE, BITS, RADIUS, SIMILARITY, leaf=4096)


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing_dp.pack(docs)


STAGES = [("quality", quality), ("lines", lines), ("near_duplicates", near_duplicates), ("leaks", leaks), ("packing", packing)]

#: A fitted classifier, XXH64 fingerprints and a tokenizer can't be put in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)

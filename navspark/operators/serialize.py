"""The five-token output record, its vocabulary, and supervision masks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from navspark.functions.core import pad_to_multiple, uniform01
from navspark.functions.pointing import GRID, RESERVED, act_token, apos_token, opos_token

PATTERN = r"^<apos_(\d+)> <opos_(\d+)>((?: <act0_\d+>(?: <act1_\d+>(?: <act2_\d+>)?)?)?)$"


def serialize(apos="apos", opos="opos", codes=("k0", "k1", "k2"), pointing: bool = True, levels: int = 3) -> Column:
    """Affordance, object, then the first ``levels`` action codes, in that order."""
    head = [apos_token(apos), opos_token(opos)] if pointing else []
    return F.array(*head, *[act_token(i, c) for i, c in enumerate(codes[:levels])])


def parse_output(tokens) -> Column:
    """(valid, apos, opos, codes) of a token array; wrong order or family is invalid."""
    line = F.array_join(F.col(tokens) if isinstance(tokens, str) else tokens, " ")
    valid = line.rlike(PATTERN)

    def number(pattern):
        return F.when(valid, F.nullif(F.regexp_extract(line, pattern, 1), F.lit(""))).cast("int")

    return F.struct(
        F.coalesce(valid, F.lit(False)).alias("valid"),
        number(r"<apos_(\d+)>").alias("apos"),
        number(r"<opos_(\d+)>").alias("opos"),
        F.when(valid, F.filter(F.array(*[number(rf"<act{i}_(\d+)>") for i in range(3)]), lambda x: x.isNotNull())).alias("codes"),
    )


def build_vocab(spark: SparkSession, base: int, hg: int = GRID, wg: int = GRID, k: int = 256, levels: int = 3) -> DataFrame:
    """(token, family, idx, id): both point families with reserved indices, and levels * k codes."""
    n = hg * wg + len(RESERVED)
    families = [("apos", n)] + [("opos", n)] + [(f"act{i}", k) for i in range(levels)]
    out, first = None, base
    for name, size in families:
        one = spark.range(size).select(F.concat(F.lit(f"<{name}_"), F.col("id").cast("string"), F.lit(">")).alias("token"), F.lit(name).alias("family"), F.col("id").cast("int").alias("idx"), (F.col("id") + first).alias("id"))
        out, first = one if out is None else out.unionByName(one), first + size
    return out


def head_size(base: int, hg: int = GRID, wg: int = GRID, k: int = 256, levels: int = 3) -> int:
    """Rows of the output layer, rounded up to a multiple of eight."""
    return pad_to_multiple(base + 2 * (hg * wg + len(RESERVED)) + levels * k)


def supervised_mask(task, position) -> Column:
    """Positions that carry loss: all output tokens of navigation, responses of everything else."""
    task, position = (F.col(c) if isinstance(c, str) else c for c in (task, position))
    return F.when(task == "navigation", position < 5).otherwise(position >= 0)


def interleave(*streams: DataFrame, key: str = "sample_id", seed: str = "mix") -> DataFrame:
    """One shared stream in hashed order: no task ids, no weights."""
    out = streams[0]
    for s in streams[1:]:
        out = out.unionByName(s, allowMissingColumns=True)
    return out.withColumn("stream_pos", uniform01(key, salt=seed)).repartitionByRange("stream_pos").sortWithinPartitions("stream_pos", key)

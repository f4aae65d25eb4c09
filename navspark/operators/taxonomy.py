"""The two-axis diagnostic taxonomy: labels from proofs, matrices, splits."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import uniform01
from navspark.operators.ops import proximity_join
from navspark.session import bounded

SCENES = ("apartment", "house", "commercial", "institution", "outdoor")
INSTRUCTIONS = ("base", "direction", "relation", "extremum", "ordinal")


def label_scene(episodes: DataFrame, mapping: DataFrame, key: str = "scene_id") -> DataFrame:
    """Scene labels from a frozen mapping; a scene that it lacks is an error."""
    mapping = bounded(mapping)
    lost = episodes.select(key).distinct().join(mapping, key, "left_anti")
    if lost.limit(1).count():
        raise ValueError("scenes without a label")
    return episodes.join(mapping, key)


def prove_base(inst: DataFrame) -> DataFrame:
    """Unique in its scene by category."""
    n = F.count("*").over(W.partitionBy("scene", "category"))
    return inst.withColumn("is_base", n == 1)


def prove_relation(inst: DataFrame, eps: float) -> DataFrame:
    """(target, anchor): the anchor is unique in its scene, and the target the only one of its category near it."""
    anchors = prove_base(inst).where("is_base").drop("is_base")
    near = proximity_join(anchors, inst, eps, ["scene"]).where("l_category <> r_category")
    n = F.count("*").over(W.partitionBy("l_target", "r_category"))
    return near.withColumn("_n", n).where("_n = 1").select(F.col("r_target").alias("target"), F.col("l_target").alias("anchor"))


def prove_extremum(inst: DataFrame, key: str, smallest: bool = True, margin: float = 0.0) -> DataFrame:
    """The first of each (scene, category) by key, with a gap to the second larger than the margin."""
    by = W.partitionBy("scene", "category").orderBy(F.col(key) if smallest else F.desc(key), "target")
    gap = F.abs(F.lead(key).over(by) - F.col(key))
    return inst.withColumn("_r", F.row_number().over(by)).withColumn("_g", gap).where((F.col("_r") == 1) & (F.col("_g") > margin)).select("target", "scene", "category", key, F.col("_g").alias("gap"))


def prove_ordinal(inst: DataFrame, key: str, min_gap: float = 0.0, least: int = 1) -> DataFrame:
    """Rank in a stable order of at least ``least`` instances, where both neighbours are at least ``min_gap`` away."""
    by = W.partitionBy("scene", "category").orderBy(key, "target")
    before, after = F.col(key) - F.lag(key).over(by), F.lead(key).over(by) - F.col(key)
    ok = (F.coalesce(before, F.lit(float("inf"))) >= min_gap) & (F.coalesce(after, F.lit(float("inf"))) >= min_gap)
    ok = ok & (F.count("*").over(W.partitionBy("scene", "category")) >= least)
    return inst.withColumn("rank", F.dense_rank().over(by)).withColumn("_ok", ok).where("_ok").drop("_ok")


def prove_direction(inst: DataFrame, sector_col: str = "sector") -> DataFrame:
    """The only one of its category in its scene on its side of the start pose."""
    n = F.count("*").over(W.partitionBy("scene", "category", sector_col))
    return inst.where(F.col(sector_col).isNotNull()).withColumn("_n", n).where("_n = 1").drop("_n")


def label_instruction(proofs: DataFrame) -> DataFrame:
    """First proof that holds, most specific first; rows have booleans is_ordinal .. is_base."""
    c = F.when(F.col("is_ordinal"), "ordinal").when(F.col("is_extremum"), "extremum").when(F.col("is_relation"), "relation").when(F.col("is_direction"), "direction").when(F.col("is_base"), "base")
    return proofs.withColumn("instr_type", c)


def fill_cells(eps: DataFrame, cap: int = 50, key: str = "episode_id", seed: str = "cell") -> tuple[DataFrame, DataFrame]:
    """At most ``cap`` episodes of each cell, in hashed order, and the shortfall of every cell of the
    grid of labels, also of those that have no episode."""
    w = W.partitionBy("scene_type", "instr_type").orderBy(uniform01(key, salt=seed), key)
    kept = eps.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= cap).drop("_r")  # limited before the shuffle
    n = kept.groupBy("scene_type", "instr_type").agg(F.count("*").alias("n"))
    grid = n.select("scene_type").distinct().crossJoin(n.select("instr_type").distinct())  # labels of either axis: a handful
    cells = grid.join(n, ["scene_type", "instr_type"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return kept, cells.withColumn("shortfall", F.greatest(F.lit(0), cap - F.col("n")))


def matrix_counts(eps: DataFrame) -> DataFrame:
    """Counts and distinct scenes of cells and margins: pre-aggregated by scene, then a cube over few rows."""
    per = eps.groupBy("scene_type", "instr_type", "scene_id").agg(F.count("*").alias("n"), F.sum(F.col("success").cast("long")).alias("s"))
    return per.cube("scene_type", "instr_type").agg(F.sum("n").alias("n"), F.sum("s").alias("n_success"), F.count_distinct("scene_id").alias("n_scenes"), F.grouping_id().cast("int").alias("level"))


def matrix_sr(eps: DataFrame) -> DataFrame:
    """Success rates in percent, and the deviation from the overall rate."""
    m = matrix_counts(eps).withColumn("sr", 100.0 * F.col("n_success") / F.col("n"))
    total = F.broadcast(m.where("level = 3").select(F.col("sr").alias("_all")))
    return m.crossJoin(total).withColumn("deviation", F.col("sr") - F.col("_all")).drop("_all")


def spans(matrix: DataFrame) -> DataFrame:
    """Best and worst cell, and the spans of the two margins."""
    cell = F.concat_ws("/", "scene_type", "instr_type")
    return matrix.agg(
        F.max_by(F.when(F.col("level") == 0, cell), F.when(F.col("level") == 0, F.col("sr"))).alias("best_cell"),
        F.max(F.when(F.col("level") == 0, F.col("sr"))).alias("best_sr"),
        F.min_by(F.when(F.col("level") == 0, cell), F.when(F.col("level") == 0, F.col("sr"))).alias("worst_cell"),
        F.min(F.when(F.col("level") == 0, F.col("sr"))).alias("worst_sr"),
        (F.max(F.when(F.col("level") == 1, F.col("sr"))) - F.min(F.when(F.col("level") == 1, F.col("sr")))).alias("scene_span"),
        (F.max(F.when(F.col("level") == 2, F.col("sr"))) - F.min(F.when(F.col("level") == 2, F.col("sr")))).alias("instr_span"),
    )


def overlap(train: DataFrame, evaluation: DataFrame, key: str = "scene") -> DataFrame:
    return train.select(key).distinct().join(evaluation.select(key).distinct(), key, "left_semi")


def assert_disjoint(train: DataFrame, evaluation: DataFrame, key: str = "scene") -> None:
    if overlap(train, evaluation, key).limit(1).count():
        raise ValueError("an evaluation scene is in the training split")


def split_hash(df: DataFrame, key: str, eval_share: float, salt: str = "split") -> DataFrame:
    return df.withColumn("split", F.when(uniform01(key, salt=salt) < eval_share, "eval").otherwise("train"))


def split_contiguous(scenes: DataFrame, n_eval: int, order: str, group: str) -> DataFrame:
    """The last ``n_eval`` scenes of each group's capture order are held out (scenes that tie with the
    first of these too). Only the last few of each group are ranked, not the whole group."""
    w = W.partitionBy(group).orderBy(F.desc(order))
    last = scenes.select(group, order).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= n_eval)
    low = bounded(last.groupBy(group).agg(F.min(order).alias("_low")))
    return scenes.join(low, group, "left").withColumn("split", F.when(F.col(order) >= F.col("_low"), "eval").otherwise("train")).drop("_low")


def split_allowlist(scenes: DataFrame, allowed: DataFrame, key: str) -> DataFrame:
    a = bounded(allowed.select(key).distinct().withColumn("_in", F.lit(True)))
    return scenes.join(a, key, "left").withColumn("split", F.when(F.col("_in"), "eval").otherwise("train")).drop("_in")


def split_stats(eps: DataFrame, key: str = "scene") -> DataFrame:
    return eps.groupBy("split").agg(F.count_distinct(key).alias("n_scenes"), F.count("*").alias("n_episodes")).withColumn("per_scene", F.col("n_episodes") / F.col("n_scenes"))


def source_composition(eps: DataFrame) -> DataFrame:
    return eps.rollup("split", "source").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))

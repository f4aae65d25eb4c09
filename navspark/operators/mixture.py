"""Corpus construction: source quotas, draws, camera draws, stop and cluster caps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import uniform01
from navspark.operators.ops import first_by_hash
from navspark.session import bounded, kept

#: Shares of draws in percent, and the number of sources of each group.
ER_MASS = {"pointing": 35.14, "image_vqa": 25.05, "video": 19.81, "general": 20.00}
ER_SOURCES = {"pointing": 13, "image_vqa": 11, "video": 9, "general": 3}
SFT_MASS = {"action": 77.6, "rehearsal": 22.4}
SFT_SOURCES = {"action": 16, "rehearsal": 33}
NAV_SOURCES = {"instruction": 4, "object": 11, "tracking": 1}
CAMERA = {"fov_deg": (90.0, 130.0), "height_m": (0.5, 1.5), "pitch_deg": (-15.0, 15.0)}
STOP_SHARE, CLUSTER_SHARE = 0.02, 0.05


def source_registry(spark: SparkSession) -> DataFrame:
    """(source, grp, n): numbered sources of the four groups of the first stage."""
    return spark.createDataFrame([(f"{g}_{i + 1:02d}", g) for g, n in ER_SOURCES.items() for i in range(n)], "source string, grp string")


def navigation_registry(spark: SparkSession) -> DataFrame:
    """(source, task): numbered navigation sources of the three tasks."""
    return spark.createDataFrame([(f"{t}_{i + 1:02d}", t) for t, n in NAV_SOURCES.items() for i in range(n)], "source string, task string")


def spread(sources: DataFrame, mass: dict[str, float]) -> DataFrame:
    """``sources`` (source, grp) with ``weight``: a group's mass in percent is spread evenly over its sources."""
    share = F.lit(None).cast("double")
    for g, m in mass.items():
        share = F.when(F.col("grp") == g, F.lit(m / 100)).otherwise(share)
    each = sources.groupBy("grp").agg(F.count("*").alias("_n")).select("grp", (share / F.col("_n")).alias("weight"))  # a row a group
    return sources.join(F.broadcast(each), "grp")


def mixture_weights(spark: SparkSession, stage: int) -> DataFrame:
    """(source, grp, weight) of a stage: a group's mass is spread evenly over its sources."""
    sources = source_registry(spark).withColumn("kind", F.lit("rehearsal"))
    if stage == 2:
        sources = sources.where(F.lit(False)).unionByName(navigation_registry(spark).select("source", F.lit("action").alias("grp"), F.lit("action").alias("kind"))).unionByName(
            spark.createDataFrame([(f"rehearsal_{i + 1:02d}", "rehearsal", "rehearsal") for i in range(SFT_SOURCES["rehearsal"])], "source string, grp string, kind string")
        )
        mass = {k: v / 100 for k, v in SFT_MASS.items()}
    else:
        mass = {k: v / 100 for k, v in ER_MASS.items()}
    share = F.lit(None).cast("double")
    for g, m in mass.items():
        share = F.when(F.col("grp") == g, F.lit(m)).otherwise(share)
    return sources.withColumn("weight", share / F.count("*").over(W.partitionBy("grp"))).select("source", "grp", "weight")


def tag_multi_image(registry: DataFrame) -> DataFrame:
    """Bridge table (source, subset): the multi-image subset overlaps the image and video pools."""
    return registry.where(F.col("grp").isin("image_vqa", "video")).select("source", F.lit("multi_image").alias("subset"))


def curriculum(spark: SparkSession, stage: int) -> DataFrame:
    """(grp, weight) of a stage: reasoning groups alone, then action beside rebalanced rehearsal."""
    if stage == 1:
        rows = [(g, m / 100) for g, m in ER_MASS.items()]
    else:
        rows = [("action", SFT_MASS["action"] / 100)] + [(g, SFT_MASS["rehearsal"] / 100 * m / 100) for g, m in ER_MASS.items()]
    return spark.createDataFrame(rows, "grp string, weight double")


def plan_quota(counts: DataFrame, total: int, key: str = "source") -> DataFrame:
    """Largest-remainder quotas that sum to ``total``; counts has (key, available, weight).

    ``rep_full`` and ``rep_rest``: how often every row is drawn, and how many rows once more.
    """
    # One row a source: a small table by nature, ranked in one task.
    norm = F.col("weight") / F.sum("weight").over(W.partitionBy())
    q = counts.withColumn("_x", F.round(norm * total, 9)).withColumn("_f", F.floor("_x"))
    left = F.lit(total) - F.sum("_f").over(W.partitionBy())
    rank = F.row_number().over(W.orderBy(F.desc(F.round(F.col("_x") - F.col("_f"), 9)), key))
    q = q.withColumn("quota", (F.col("_f") + (rank <= left).cast("long")).cast("long"))
    return q.withColumn("rep_full", F.floor(F.col("quota") / F.col("available"))).withColumn("rep_rest", F.col("quota") % F.col("available")).drop("_x", "_f")


def draw(samples: DataFrame, quotas: DataFrame, key: str = "source", id_col: str = "sample_id", seed: str = "draw") -> DataFrame:
    """Rows drawn by quota in hashed order, with copy_no where a source is drawn more than once."""
    quotas = kept(quotas.select(key, "rep_full", "rep_rest"))
    q = bounded(quotas.select(key, "rep_full"))
    rest = first_by_hash(samples, key, quotas.select(key, F.col("rep_rest").alias("quota")), id_col, seed)
    whole = samples.join(q.where("rep_full > 0"), key).withColumn("copy_no", F.explode(F.sequence(F.lit(1).cast("long"), F.col("rep_full")))).drop("rep_full")
    return whole.unionByName(rest.join(q, key).withColumn("copy_no", (F.col("rep_full") + 1).cast("long")).drop("rep_full"))


def draw_bernoulli(samples: DataFrame, quotas: DataFrame, key: str = "source", id_col: str = "sample_id", seed: str = "draw") -> DataFrame:
    """Probabilistic draw: no shuffle, quotas met in expectation."""
    s = samples.join(bounded(kept(quotas.select(key, "available", "quota"))), key)
    rate = F.col("quota") / F.col("available")
    n = F.floor(rate) + (uniform01(id_col, salt=seed) < rate - F.floor(rate)).cast("long")
    return s.withColumn("_n", n).where("_n > 0").withColumn("copy_no", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_n")))).drop("_n", "available", "quota")


def randomize_camera(episodes: DataFrame, key: str = "episode_id", seed: str = "cam") -> DataFrame:
    """Field of view, height and pitch, uniform in their ranges and the same in every engine."""
    return episodes.withColumns({c: F.lit(lo) + (hi - lo) * uniform01(key, salt=f"{seed}-{c}") for c, (lo, hi) in CAMERA.items()})


def aggregate_onpolicy(expert: DataFrame, rollouts: DataFrame, labels: DataFrame, round_no: int, key: str = "state_key") -> DataFrame:
    """States that the policy reached and the corpus lacks, relabelled by the expert and added once each
    (of several labels the smallest); the corpus itself stays as it is, repeated states too."""
    new = rollouts.select(key).distinct().join(labels, key).join(expert.select(key), key, "left_anti")
    rest = [c for c in labels.columns if c != key]
    new = new.groupBy(key).agg(F.min(F.struct(*rest)).alias("_x")).select(key, *[F.col(f"_x.{c}").alias(c) for c in rest]) if rest else new.distinct()
    new = new.withColumn("round", F.lit(round_no)).withColumn("origin", F.lit("policy"))
    return expert.unionByName(new, allowMissingColumns=True)


# --- filters and caps --------------------------------------------------------------------


def filter_stop(steps: DataFrame, tasks=("instruction", "object")) -> DataFrame:
    """A stop label survives only on the last frame with the target in view; tracking keeps its own."""
    guard = F.col("task").isin(*tasks) if "task" in steps.columns else F.lit(True)
    ok = (F.col("t") == F.col("n_steps")) & F.col("visible")
    return steps.withColumn("stop", F.col("stop") & (ok | ~guard))


def drop_unseen(steps: DataFrame, key: str = "episode_id", tasks=("instruction", "object")) -> DataFrame:
    """Episodes whose target is never in view go, but for tracking."""
    seen = steps.where("visible").select(key).distinct()
    if "task" not in steps.columns:
        return steps.join(seen, key, "left_semi")
    return steps.where(~F.col("task").isin(*tasks)).unionByName(steps.where(F.col("task").isin(*tasks)).join(seen, key, "left_semi"))


def cluster_cap(sizes: list[int], share: float = CLUSTER_SHARE) -> tuple[int, bool]:
    """Largest c with c <= share * sum(min(n, c)), and whether that is possible with c > 0."""
    if not sizes:
        return 0, True
    lo, hi = 0, max(sizes)
    if hi <= share * sum(sizes):
        return hi, True
    best = 0
    order = sorted(sizes)
    below, n = 0, len(order)
    prev = 0
    for i, s in enumerate([*order, order[-1]]):
        # between prev and s all n - i clusters above are cut to c
        slope = 1 - share * (n - i)
        top = s if slope <= 0 else min(s, int((share * below) / slope + 1e-9))
        if top >= prev and top > best and top <= share * sum(min(x, top) for x in order) + 1e-9:
            best = top
        if i < n:
            below += s
            prev = s
    return (best, True) if best > 0 else (min(sizes), False)


def cap_clusters(samples: DataFrame, share: float = CLUSTER_SHARE, key: str = "cluster", id_col: str = "sample_id", seed: str = "cap") -> tuple[DataFrame, int, bool]:
    """Rows of each cluster beyond the cap go, in hashed order; (rows, cap, feasible)."""
    sizes = [r["count"] for r in samples.groupBy(key).count().collect()]  # clusters are few by definition
    cap, ok = cluster_cap(sizes, share)
    quotas = samples.select(key).distinct().withColumn("quota", F.lit(cap).cast("long"))
    return first_by_hash(samples, key, quotas, id_col, seed), cap, ok


def stop_allowance(n_other: int | Column, share: float = STOP_SHARE):
    """Most stops that keep their share of the final mixture within ``share``."""
    x = n_other * (share / (1 - share))
    return F.floor(F.round(x, 9)) if isinstance(x, Column) else int(x + 1e-9)


def cap_stop(samples: DataFrame, share: float = STOP_SHARE, flag: str = "stop", id_col: str = "sample_id", seed: str = "cap") -> DataFrame:
    allowed = samples.where(~F.col(flag)).agg(stop_allowance(F.count("*"), share).cast("long").alias("quota")).withColumn("_k", F.lit(1))
    kept = first_by_hash(samples.where(flag).withColumn("_k", F.lit(1)), "_k", allowed, id_col, seed).drop("_k")
    return samples.where(~F.col(flag)).unionByName(kept)


def balanced_index(steps: DataFrame, cluster: str = "cluster", id_col: str = "sample_id") -> tuple[DataFrame, dict]:
    """Stop filter, unseen filter, cluster cap and stop cap until both shares hold. Every round but the
    last removes rows, so the rounds end."""
    s, rounds = kept(drop_unseen(filter_stop(steps))), 0
    while True:
        rounds += 1
        s, cap, ok = cap_clusters(s, CLUSTER_SHARE, cluster, id_col)
        s = kept(cap_stop(s, STOP_SHARE, "stop", id_col))
        top = s.groupBy(cluster).count().agg(F.max("count"), F.sum("count")).first()
        if not ok or top[1] is None or top[0] <= CLUSTER_SHARE * top[1] + 1e-9:
            return s, {"cap": cap, "feasible": ok, "rounds": rounds}


# --- reports -----------------------------------------------------------------------------


def mixture_report(drawn: DataFrame) -> DataFrame:
    """Rows, distinct samples and share for each (task, group, source) and their totals."""
    got = drawn.rollup("task", "grp", "source").agg(F.count("*").alias("n"), F.count_distinct("sample_id").alias("n_unique"), F.grouping_id().alias("level"))
    return got.crossJoin(F.broadcast(drawn.agg(F.count("*").alias("_n")))).withColumn("share", F.col("n") / F.col("_n")).drop("_n")


def word_counts(df: DataFrame, text: str) -> DataFrame:
    words = F.explode(F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != ""))
    return df.select(words.alias("word")).groupBy("word").agg(F.count("*").alias("n"))


def top_targets(df: DataFrame, name: str, k: int = 50) -> DataFrame:
    return df.groupBy(name).agg(F.count("*").alias("n")).orderBy(F.desc("n"), name).limit(k).withColumn("log10_n", F.log10("n"))

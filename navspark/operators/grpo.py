"""Group-relative optimisation data: advantages, loss terms, pools, draws, routing, retention."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import uniform01

GROUP, SEEDS = 8, 32
EPS, CLIP, BETA = 1e-6, 0.2, 0.01


def group_advantage(rollouts: DataFrame, reward: str = "reward", seed: str = "seed_id", ddof: int = 0, eps: float = EPS) -> DataFrame:
    """Reward standardised within its seed; a lone or constant group has advantage 0."""
    w = W.partitionBy(seed)
    std = F.coalesce((F.stddev_pop if ddof == 0 else F.stddev_samp)(reward).over(w), F.lit(0.0))
    r = rollouts.withColumn("mean_r", F.avg(reward).over(w)).withColumn("std_r", F.when(F.count("*").over(w) > 1, std).otherwise(0.0))
    return r.withColumn("adv", F.when(F.round("std_r", 9) > 0, (F.col(reward) - F.col("mean_r")) / (F.col("std_r") + eps)).otherwise(0.0))


def spread_advantage(steps: DataFrame, adv: DataFrame, key: str = "episode_id") -> DataFrame:
    """The episode's one advantage on each of its decisions; joined late and never stored."""
    return steps.join(adv.select(key, "adv"), key)


def kl(lp_new: Column, lp_ref: Column, how: str = "k3") -> Column:
    """Per-token estimate of the divergence to the reference: k1, k2 or k3 (never negative)."""
    d = lp_ref - lp_new
    return {"k1": -d, "k2": 0.5 * d * d, "k3": F.exp(d) - 1 - d}[how]


def surrogate(lp_new: Column, lp_old: Column, adv: Column, clip: float = CLIP) -> Column:
    ratio = F.exp(lp_new - lp_old)
    return F.least(ratio * adv, F.greatest(F.lit(1 - clip), F.least(F.lit(1 + clip), ratio)) * adv)


def grpo_loss(tokens: DataFrame, clip: float = CLIP, beta: float = BETA, how: str = "k3") -> DataFrame:
    """(loss, surrogate, kl, clip_frac, n) over tokens with lp_new, lp_old, lp_ref and adv."""
    new, old, ref, adv = (F.col(c) for c in ("lp_new", "lp_old", "lp_ref", "adv"))
    ratio = F.exp(new - old)
    a = tokens.agg(F.avg(surrogate(new, old, adv, clip)).alias("surrogate"), F.avg(kl(new, ref, how)).alias("kl"), F.avg(((ratio < 1 - clip) | (ratio > 1 + clip)).cast("double")).alias("clip_frac"), F.count("*").alias("n"))
    return a.select((-F.col("surrogate") + beta * F.col("kl")).alias("loss"), "surrogate", "kl", "clip_frac", "n")


# --- choice of training episodes -----------------------------------------------------------


def bin_difficulty(rollouts: DataFrame, k: int = GROUP, seed: str = "seed_id") -> DataFrame:
    """(seed, n_succ, std_r, bin) of seeds with K rollouts: always, mixed or never solved."""
    a = rollouts.where(F.col("g") <= k).groupBy(seed).agg(F.count("*").alias("n"), F.sum(F.col("success").cast("long")).alias("n_succ"), F.stddev_pop("reward").alias("std_r"), F.min("scene_id").alias("scene_id"))
    a = a.where(F.col("n") == k)
    return a.withColumn("bin", F.when(F.col("n_succ") == k, "always").when(F.col("n_succ") == 0, "never").otherwise("mixed"))


def build_pool(bins: DataFrame, keep_always: float = 0.1, keep_never: float = 0.1, seed: str = "seed_id") -> DataFrame:
    """All mixed seeds and a small hashed share of either extreme."""
    u = uniform01(seed, salt="pool")
    return bins.where((F.col("bin") == "mixed") | ((F.col("bin") == "always") & (u < keep_always)) | ((F.col("bin") == "never") & (u < keep_never)))


def pool_uniform(bins: DataFrame, share: float, seed: str = "seed_id") -> DataFrame:
    return bins.where(uniform01(seed, salt="pool") < share)


def pool_failures_only(bins: DataFrame, k: int = GROUP) -> DataFrame:
    return bins.where(F.col("n_succ") < k)


def pool_report(pools: dict[str, DataFrame], tol: float = 1e-9) -> DataFrame:
    """Seeds of each pool, the share whose success varies, and the share whose reward does."""
    out = None
    for name, p in pools.items():
        one = p.agg(
            F.count("*").alias("n"), F.avg((F.col("bin") == "mixed").cast("double")).alias("usable_share"), F.avg((F.col("std_r") > tol).cast("double")).alias("graded_share"),
            F.avg(F.when(F.col("bin") == "never", F.col("std_r"))).alias("failure_spread"),
        ).select(F.lit(name).alias("pool"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def draw_iteration(pool: DataFrame, b: int = SEEDS, seed: str = "seed_id", salt: str = "iter") -> DataFrame:
    """b seeds of pairwise distinct scenes."""
    u = uniform01(seed, salt=salt)
    one = pool.withColumn("_u", u).withColumn("_r", F.row_number().over(W.partitionBy("scene_id").orderBy("_u", seed))).where("_r = 1")
    return one.orderBy("_u", seed).limit(b).drop("_u", "_r")


def route(rollouts: DataFrame, workers: int, policy: str = "scene") -> DataFrame:
    """The worker of each rollout: by hash of the scene (a group stays with its scene's holder) or in turn."""
    if policy == "scene":
        return rollouts.withColumn("worker", F.floor(uniform01("scene_id", salt="route") * workers).cast("int"))
    return rollouts.withColumn("worker", F.pmod(F.col("episode_id"), F.lit(workers)).cast("int"))


def route_loads(rollouts: DataFrame, workers: int) -> DataFrame:
    """Rollouts and scene loads of each worker under both policies."""
    out = None
    for policy in ("scene", "robin"):
        one = route(rollouts, workers, policy).groupBy("worker").agg(F.count("*").alias("n"), F.count_distinct("scene_id").alias("loads")).select(F.lit(policy).alias("policy"), "*")
        out = one if out is None else out.unionByName(one)
    return out


# --- retained decisions ----------------------------------------------------------------------


def with_event_flags(steps: DataFrame, turn_thr: float, key: str = "episode_id") -> DataFrame:
    """is_event (stop, stuck, collision, large turn), is_end, and is_near (next to an event)."""
    by = W.partitionBy(key).orderBy("t")
    event = F.col("stop") | F.col("stuck") | F.col("collision") | (F.abs("turn_rad") > turn_thr)
    s = steps.withColumn("is_event", event).withColumn("is_end", (F.col("t") == 1) | (F.col("t") == F.col("n_steps")))
    near = F.coalesce(F.lag("is_event").over(by), F.lit(False)) | F.coalesce(F.lead("is_event").over(by), F.lit(False))
    return s.withColumn("is_near", near & ~F.col("is_event"))


def select_decisions(steps: DataFrame, cap: int, turn_thr: float, key: str = "episode_id") -> DataFrame:
    """At most ``cap`` decisions an episode: ends, events, neighbours, then evenly spaced others."""
    s = with_event_flags(steps, turn_thr, key)
    s = s.withColumn("priority", F.when(F.col("is_end"), 0).when(F.col("is_event"), 1).when(F.col("is_near"), 2).otherwise(3))
    must = F.sum((F.col("priority") < 3).cast("int")).over(W.partitionBy(key))
    by = W.partitionBy(key, "priority")
    place, size = F.row_number().over(by.orderBy("t")) - 1, F.count("*").over(by)
    s = s.withColumn("_room", F.greatest(F.lit(0), cap - must)).withColumn("_i", place).withColumn("_n", size)
    even = F.floor((F.col("_i") + 1) * F.col("_room") / F.col("_n")) > F.floor(F.col("_i") * F.col("_room") / F.col("_n"))
    s = s.where((F.col("priority") < 3) | even | (F.col("_room") >= F.col("_n")))
    s = s.withColumn("_r", F.row_number().over(W.partitionBy(key).orderBy("priority", "t")))
    return s.where(F.col("_r") <= cap).drop("_r", "_room", "_i", "_n")


def select_uniform(steps: DataFrame, cap: int, turn_thr: float, key: str = "episode_id") -> DataFrame:
    """The baseline: evenly spaced decisions, blind to events."""
    s = with_event_flags(steps, turn_thr, key)
    i, n = F.col("t") - 1, F.col("n_steps")
    return s.where((n <= cap) | (F.floor((i + 1) * cap / n) > F.floor(i * cap / n)))


def event_recall(steps: DataFrame, kept: DataFrame, turn_thr: float) -> DataFrame:
    total = with_event_flags(steps, turn_thr).agg(F.sum(F.col("is_event").cast("long")).alias("_t"))
    return kept.agg(F.count("*").alias("n_kept"), F.sum(F.col("is_event").cast("long")).alias("_e")).crossJoin(F.broadcast(total)).select("n_kept", F.try_divide("_e", "_t").alias("event_recall"))

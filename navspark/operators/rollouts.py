"""Scoring of rollouts: terminal rewards of the three tasks and path measures."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navspark.functions import rewards as R


def tracking_episodes(steps: DataFrame, plan_scale: float = R.PLAN_SCALE, horizon: str = "full") -> DataFrame:
    """One row an episode: length, how it ended, quality sum, success and reward.

    An episode ends early if its last frame has lost the target or collided. Success: at the
    end the follower is 1 to 3 m behind the target and turned towards it. Steps may have
    ``plan_ade``, the displacement from the privileged plan, whose match is the second step
    term, and ``target_rad``, the target's heading seen from the follower, without which 'behind'
    can't be told and is not asked. ``horizon='executed'`` averages over the executed steps
    only, the contrast that rewards early failure.
    """
    q = R.step_quality("visible", "bearing_rad", "range_m")
    m = R.plan_match("plan_ade", plan_scale) if "plan_ade" in steps.columns else F.lit(0.0)
    told = ["target_rad"] if "target_rad" in steps.columns else []
    s = steps.withColumn("_q", q).withColumn("_m", m)
    last = F.max_by(F.struct("visible", "range_m", "bearing_rad", "collision", *told), "t")
    e = s.groupBy("episode_id").agg(F.count("*").alias("t_n"), F.sum("_q").alias("sum_q"), F.sum("_m").alias("sum_m"), F.bool_or("collision").alias("collision"), last.alias("_l"), F.avg(F.coalesce((F.col("visible") & F.col("range_m").between(1, 3)).cast("double"), F.lit(0.0))).alias("tracked"))
    ok = R.following("_l.visible", "_l.range_m", "_l.bearing_rad", "_l.target_rad" if told else None)
    early = ~F.col("_l.visible") | F.col("_l.collision")
    h = R.horizon("t_n", early) if horizon == "full" else F.col("t_n")
    e = e.withColumn("success", ok).withColumn("early", early).withColumn("horizon", h)
    reward = F.col("success").cast("double") - R.COLLISION_COST * F.col("collision").cast("double") + (R.QUALITY_WEIGHT * F.col("sum_q") + R.PLAN_WEIGHT * F.col("sum_m")) / F.col("horizon")
    return e.withColumn("reward", reward).drop("_l")


def path_measures(path: DataFrame, radius: float) -> DataFrame:
    """For each episode: final and least distance to the goal, executed and reference length."""
    from pyspark.sql import Window as W

    by = W.partitionBy("episode_id").orderBy("i")
    step = F.sqrt((F.col("x") - F.lag("x").over(by)) ** 2 + (F.col("y") - F.lag("y").over(by)) ** 2)
    d = F.sqrt((F.col("x") - F.col("gx")) ** 2 + (F.col("y") - F.col("gy")) ** 2)
    p = path.withColumn("_s", step).withColumn("_d", d)
    return p.groupBy("episode_id").agg(
        F.max_by("_d", "i").alias("d_t"), F.min("_d").alias("min_d"), F.coalesce(F.sum("_s"), F.lit(0.0)).alias("path_len"), F.first(F.sqrt(F.col("gx") ** 2 + F.col("gy") ** 2)).alias("d_0"), F.max("n").alias("n")
    ).withColumn("oracle", F.round("min_d", 9) <= radius)


CELLS = 1 << 20  #: cost cells of paths that are warped side by side


def dtw_block(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Dynamic time warping costs of paths (q, n, 2) and (q, m, 2), diagonal by diagonal, all paths at once."""
    q, n, m = len(a), a.shape[1], b.shape[1]
    cost = np.hypot(a[:, :, None, 0] - b[:, None, :, 0], a[:, :, None, 1] - b[:, None, :, 1])
    acc = np.full((q, n + 1, m + 1), np.inf)
    acc[:, 0, 0] = 0
    for s in range(n + m - 1):
        i = np.arange(max(0, s - m + 1), min(n, s + 1))
        j = s - i
        acc[:, i + 1, j + 1] = cost[:, i, j] + np.minimum(np.minimum(acc[:, i, j + 1], acc[:, i + 1, j]), acc[:, i, j])
    return acc[:, n, m]


def dtw(a: np.ndarray, b: np.ndarray) -> float:
    """Dynamic time warping cost of two point lists."""
    return float(dtw_block(a[None], b[None])[0])


def ndtw(path: DataFrame, d_th: float) -> DataFrame:
    """(episode_id, dtw, ndtw): paths are gathered (bounded by the decision budget) and warped in Arrow
    batches, those of one length side by side in blocks of at most ``CELLS`` cells."""
    xy = F.array_sort(F.collect_list(F.struct("i", "x", "y", "rx", "ry")))
    g = path.groupBy("episode_id").agg(xy.alias("p"))
    g = g.select("episode_id", *[F.col(f"p.{c}").alias(c) for c in ("x", "y", "rx", "ry")])

    def run(frames):
        for t in frames:
            n = t.x.map(len).to_numpy()
            cost = np.zeros(len(t))
            for length in np.unique(n):
                rows = np.flatnonzero(n == length)
                step = max(1, CELLS // int(length) ** 2)
                for at in (rows[s : s + step] for s in range(0, len(rows), step)):
                    x, y, rx, ry = (np.stack(t[c].to_numpy()[at]).astype(float) for c in ("x", "y", "rx", "ry"))
                    cost[at] = dtw_block(np.stack([x, y], 2), np.stack([rx, ry], 2))
            yield pd.DataFrame({"episode_id": t.episode_id, "dtw": cost, "ndtw": np.exp(-cost / (n * d_th))})

    return g.mapInPandas(run, "episode_id long, dtw double, ndtw double")


def scored_rollouts(rollouts: DataFrame, path: DataFrame, radius: float, with_ndtw: bool = False) -> DataFrame:
    """Rollout headers with path measures, success, and efficiency."""
    m = path_measures(path, radius)
    j = rollouts.join(m, "episode_id")
    j = j.withColumn("success", F.col("stop_called") & (F.round("d_t", 9) <= radius)).withColumn("efficiency", R.path_efficiency("d_0", "path_len"))
    return j.join(ndtw(path, radius).select("episode_id", "ndtw"), "episode_id") if with_ndtw else j


def reward_instruction(scored: DataFrame, ndtw_col: str = "ndtw") -> DataFrame:
    a, b, c = R.instruction_terms("success", ndtw_col, "d_t", "timeout")
    return scored.withColumns({"term1": a, "term2": b, "term3": c}).withColumn("reward", F.col("term1") + F.col("term2") + F.col("term3"))


def reward_object(scored: DataFrame) -> DataFrame:
    a, b = R.object_terms("success", "efficiency", "d_t")
    return scored.withColumns({"term1": a, "term2": b, "term3": F.lit(0.0)}).withColumn("reward", F.col("term1") + F.col("term2"))


def score(rollouts: DataFrame, task: str = "task") -> DataFrame:
    """One pass for all tasks: only the reward differs, chosen by a CASE on the task."""
    ia, ib, ic = R.instruction_terms("success", F.coalesce("ndtw", F.lit(0.0)), "d_t", "timeout")
    oa, ob = R.object_terms("success", "efficiency", "d_t")
    return rollouts.withColumn("reward", F.when(F.col(task) == "instruction", ia + ib + ic).when(F.col(task) == "object", oa + ob).otherwise(F.col("tracking_reward")))

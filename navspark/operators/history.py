"""Recency-based compression of a frame history.

Everything needs only (episode, t, ts) until frames are chosen; grids are joined to the
survivors alone, so at scale most of the bytes are never read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import uniform01

SIDE = 8
EP = "episode_id"


def with_age(frames: DataFrame, now: str | None = None) -> DataFrame:
    """``age_s``: seconds before the episode's last frame, or before the column ``now``."""
    last = F.unix_micros(F.max("ts").over(W.partitionBy(EP))) if now is None else F.unix_micros(F.col(now))
    return frames.withColumn("age_s", (last - F.unix_micros("ts")) / 1e6)


def sampling_rate(age, f_max: float, tau_s: float) -> Column:
    age = F.col(age) if isinstance(age, str) else age
    return F.lit(f_max) * F.exp(-age / tau_s)


def accumulated(age, f_max: float, tau_s: float) -> Column:
    """Integral of the rate from now back to ``age``."""
    age = F.col(age) if isinstance(age, str) else age
    return F.lit(f_max * tau_s) * (1 - F.exp(-age / tau_s))


def frame_bound(f_max: float, tau_s: float) -> int:
    """Most frames that ``integral`` keeps, however long the episode."""
    return 1 + int(-(-(f_max * tau_s) // 1))


def select_frames(frames: DataFrame, mode: str, f_max: float = 0.0, tau_s: float = 1.0, tiers: list[tuple[float, int]] | None = None, every: int = 1) -> DataFrame:
    """Kept frames; the newest always stays.

    integral: a frame stays when the accumulated rate passes an integer between it and the
    next newer one. hash: kept with probability rate * gap. tiers: evenly spaced within age
    tiers (upper age, quota). uniform: every n-th. all and fixed: everything.
    """
    newest_first = W.partitionBy(EP).orderBy("age_s", F.desc("t"))
    if mode in ("all", "fixed"):
        return frames
    rank = F.row_number().over(newest_first)
    if mode == "integral":
        level = F.least(F.floor(F.round(accumulated("age_s", f_max, tau_s), 9)), F.lit(-int(-(f_max * tau_s) // 1) - 1))  # it stays below its limit
        f = frames.withColumn("_l", level).withColumn("_p", F.lag("_l").over(newest_first))
        return f.where(F.col("_p").isNull() | (F.col("_l") > F.col("_p"))).drop("_l", "_p")
    if mode == "hash":
        f = frames.withColumn("_r", rank).withColumn("_gap", F.col("age_s") - F.lag("age_s").over(newest_first))
        keep = uniform01(EP, "t", salt="thin") < F.least(F.lit(1.0), sampling_rate("age_s", f_max, tau_s) * F.col("_gap"))
        return f.where((F.col("_r") == 1) | keep).drop("_r", "_gap")
    if mode == "uniform":
        return frames.withColumn("_r", rank).where((F.col("_r") - 1) % every == 0).drop("_r")
    if mode == "tiers":
        f, tier, quota = frames.withColumn("_a", rank), F.lit(len(tiers)), F.lit(0)
        for i, (age, n) in reversed(list(enumerate(tiers))):
            tier, quota = F.when(F.col("age_s") <= age, i).otherwise(tier), F.when(F.col("age_s") <= age, n).otherwise(quota)
        f = f.withColumn("_t", tier).withColumn("_q", quota)
        by = W.partitionBy(EP, "_t")
        f = f.withColumn("_r", F.row_number().over(by.orderBy("age_s", F.desc("t"))) - 1).withColumn("_n", F.count("*").over(by))
        step = F.floor(F.col("_r") * F.col("_q") / F.col("_n")) > F.floor((F.col("_r") - 1) * F.col("_q") / F.col("_n"))
        return f.where((F.col("_a") == 1) | (step & (F.col("_q") > 0))).drop("_a", "_t", "_q", "_r", "_n")
    raise ValueError(f"unknown mode {mode}")


def pool_stride(age, tau_p: float, max_stride: int = SIDE) -> Column:
    """Pooling stride, growing exponentially with age and clamped to the grid's side."""
    age = F.col(age) if isinstance(age, str) else age
    top = F.lit(float(max_stride))
    return F.greatest(F.lit(1), F.least(top, F.floor(F.exp(F.least(age / tau_p, F.lit(60.0)))))).cast("int")


def pooled_side(side: int | Column, stride) -> Column:
    stride = F.col(stride) if isinstance(stride, str) else stride
    side = F.lit(side) if isinstance(side, int) else side
    return F.ceil(side / stride).cast("int")


def grid_pool(grid, stride, h: int = SIDE, w: int = SIDE, how: str = "mean") -> Column:
    """Pooled cells, row-major; cells at a ragged edge are averaged over what they cover."""
    grid, stride = (F.col(c) if isinstance(c, str) else c for c in (grid, stride))
    rows, cols = pooled_side(h, stride), pooled_side(w, stride)

    def cell(i):
        r0, c0 = F.floor(i / cols).cast("int") * stride, (i % cols).cast("int") * stride
        r1, c1 = F.least(r0 + stride, F.lit(h)), F.least(c0 + stride, F.lit(w))
        line = F.flatten(F.transform(F.sequence(r0, r1 - 1), lambda r: F.slice(grid, r * w + c0 + 1, c1 - c0)))
        if how == "max":
            return F.array_max(line)
        return F.aggregate(line, F.lit(0.0), lambda s, x: s + x) / F.size(line)

    return F.transform(F.sequence(F.lit(0), rows * cols - 1), cell)


def frame_tokens(stride, side: int = SIDE) -> Column:
    """Tokens of a frame in the context: its pooled cells and the time token."""
    n = pooled_side(side, stride)
    return (n * n + 1).cast("int")


def timestamp_token(ts) -> Column:
    ts = F.col(ts) if isinstance(ts, str) else ts
    return F.format_string("<t_%d>", F.unix_seconds(ts))


def fitted(h, w, budget, patch: int = 16, merge: int = 2) -> tuple[Column, Column]:
    """``fit_budget`` of columns: rows and columns of merged patches."""
    h, w, budget = (F.col(c) for c in (h, w, budget))
    scale = F.least(F.lit(1.0), F.sqrt(budget.cast("double") / (h * w)))
    return tuple(F.greatest(F.lit(1), F.floor(F.floor(c * scale) / (patch * merge)).cast("int")) for c in (h, w))


def fit_budget(h: int, w: int, budget: int, patch: int = 16, merge: int = 2) -> tuple[int, int, int]:
    """Largest (height, width) of whole merged patches within a pixel budget, and the token count."""
    unit = patch * merge
    scale = min(1.0, (budget / (h * w)) ** 0.5)
    rows, cols = max(1, int(h * scale) // unit), max(1, int(w * scale) // unit)
    return rows * unit, cols * unit, rows * cols


PIXEL_BUDGETS = (256 * 1024, 576 * 1024, 1024 * 1024)


def allocate_tokens(frames: DataFrame, budget: int, side: int = SIDE) -> DataFrame:
    """Doubles strides from the oldest frame on until an episode's tokens fit the budget.

    A frame's stride may double up to ``doublings`` times; the savings are ordered oldest
    first, one doubling round after the other, and applied while the sum is above budget. The
    newest frame keeps its stride. ``over_budget`` tells where even that is too much.
    """
    doublings = max(1, (side - 1).bit_length())
    age = W.partitionBy(EP).orderBy(F.desc("age_s"), "t")
    f = frames.withColumn("_newest", F.row_number().over(W.partitionBy(EP).orderBy("age_s", F.desc("t"))) == 1)
    for _ in range(doublings):
        n = frame_tokens("stride", side)
        more = F.when(F.col("_newest"), F.col("stride")).otherwise(F.least(F.lit(side), F.col("stride") * 2))
        m = frame_tokens(more, side)
        total = F.sum(n).over(W.partitionBy(EP))
        saved_before = F.coalesce(F.sum(n - m).over(age.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
        f = f.withColumn("stride", F.when(total - saved_before > budget, more).otherwise(F.col("stride")).cast("int"))
    f = f.withColumn("n_tok", frame_tokens("stride", side))
    return f.withColumn("over_budget", F.sum("n_tok").over(W.partitionBy(EP)) > budget).drop("_newest")


def compress_history(frames: DataFrame, mode: str, f_max: float, tau_s: float, tau_p: float, budget: int | None = None, fixed_stride: int = 2, side: int = SIDE, every: int = 4, tiers=None) -> DataFrame:
    """Context rows (episode, t, age, stride, n_tok, time_token): thinning, then pooling strides, then the
    budget, which counts the time tokens."""
    f = select_frames(with_age(frames), mode, f_max, tau_s, tiers, every)
    if mode == "all":
        stride = F.lit(1)
    elif mode == "fixed":
        newest = F.row_number().over(W.partitionBy(EP).orderBy("age_s", F.desc("t"))) == 1
        stride = F.when(newest, 1).otherwise(fixed_stride)
    else:
        stride = pool_stride("age_s", tau_p, side)
    f = f.withColumn("stride", stride.cast("int"))
    f = f.withColumn("n_tok", frame_tokens("stride", side)).withColumn("time_token", timestamp_token("ts"))
    return allocate_tokens(f.drop("n_tok"), budget, side) if budget else f


def with_pooled(context: DataFrame, grids: DataFrame, key: str = "grid_id", side: int = SIDE, how: str = "mean") -> DataFrame:
    """Context rows with their pooled cells and the pooled height and width. Grids (``key``, grid) are
    joined to the kept frames alone."""
    j = context.join(grids, key)
    n = pooled_side(side, "stride")
    return j.withColumns({"cells": grid_pool("grid", "stride", side, side, how), "h_p": n, "w_p": n}).drop("grid")


def history_cost(context: DataFrame) -> DataFrame:
    """Frames and tokens for each episode."""
    return context.groupBy(EP).agg(F.count("*").alias("n_frames"), F.sum("n_tok").alias("n_tok"), F.max("stride").alias("max_stride"))

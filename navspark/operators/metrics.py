"""Navigation metrics over scored episodes, and reports over result tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

LOWER_BETTER = ("NE", "CR")


def _rate(c) -> Column:
    return F.avg((F.col(c) if isinstance(c, str) else c).cast("double"))


def navigation_error() -> Column:
    return F.avg("d_t")


def oracle_success() -> Column:
    return _rate("oracle")


def success_rate() -> Column:
    return _rate("success")


def spl() -> Column:
    """Success weighted by reference over executed length."""
    return F.avg(F.col("success").cast("double") * F.col("efficiency"))


def mean_ndtw() -> Column:
    return F.avg("ndtw")


def tracking_rate() -> Column:
    return F.avg("tracked")


def collision_rate() -> Column:
    return _rate("collision")


def diagnostic_success(outdoor, radius_in: float = 2.0, radius_out: float = 3.0, max_actions: int = 300) -> Column:
    """Called stop within the radius, target in the final view, within the action budget."""
    r = F.when(outdoor, radius_out).otherwise(radius_in)
    return F.col("stop_called") & (F.round("d_t", 9) <= r) & F.coalesce(F.col("in_view"), F.lit(True)) & (F.col("n") <= max_actions)


def breakdown(eps: DataFrame) -> DataFrame:
    """Success by instruction, by scene and overall, in one pass of grouping sets."""
    return eps.groupingSets([["scene_type"], ["instr_type"], []], "scene_type", "instr_type").agg(F.count("*").alias("n"), success_rate().alias("sr"))


def wilson(successes: Column, n: Column, z: float = 1.959964) -> Column:
    """Wilson score interval of a rate."""
    p, z2 = successes / n, z * z
    mid, half = (p + z2 / (2 * n)) / (1 + z2 / n), z * F.sqrt(p * (1 - p) / n + z2 / (4 * n * n)) / (1 + z2 / n)
    return F.struct((mid - half).alias("low"), (mid + half).alias("high"))


def quantiles(value: str, at=(0.1, 0.5, 0.9), accuracy: int = 10_000) -> Column:
    return F.percentile_approx(value, list(at), accuracy)


# --- reports over (method, family, setting, metric, value) ---------------------------------


def macro_average(results: DataFrame, n: int = 8) -> DataFrame:
    """Unweighted mean of a method's n values, NULL unless all are there."""
    g = results.groupBy("method").agg(F.count("value").alias("n_values"), F.avg("value").alias("_a"))
    return g.withColumn("complete", F.col("n_values") == n).withColumn("macro", F.when(F.col("complete"), F.col("_a"))).drop("_a")


def signed(metric="metric", value="value") -> Column:
    """Larger is better."""
    return F.when(F.col(metric).isin(*LOWER_BETTER), -F.col(value)).otherwise(F.col(value))


def rank_marks(results: DataFrame, by=("family", "setting", "metric")) -> DataFrame:
    """Rank of each value within its family; ties share, missing values have none."""
    have = results.where(F.col("value").isNotNull())
    return have.withColumn("rank", F.dense_rank().over(W.partitionBy(*by).orderBy(F.desc(signed()))))


def gain_table(results: DataFrame, focal: str, by=("setting", "metric")) -> DataFrame:
    """The focal method against the best other: absolute and relative to that competitor."""
    have = results.where(F.col("value").isNotNull())
    best = have.where(F.col("method") != focal).groupBy(*by).agg(F.max_by("value", signed()).alias("best_other"))
    j = have.where(F.col("method") == focal).join(best, list(by))
    gain = F.when(F.col("metric").isin(*LOWER_BETTER), F.col("best_other") - F.col("value")).otherwise(F.col("value") - F.col("best_other"))
    return j.select(*by, F.col("value").alias("focal"), "best_other", gain.alias("gain_abs"), F.try_divide(100 * gain, F.col("best_other")).alias("gain_rel"))


def filter_sensing(results: DataFrame, **flags: bool) -> DataFrame:
    for k, v in flags.items():
        results = results.where(F.col(k) == v)
    return results


def ablation_table(results: DataFrame, base: str, variant: str) -> DataFrame:
    """Per metric: means of both, their difference, and in how many settings the variant is better."""
    a = results.where(F.col("method") == base).select("setting", "metric", F.col("value").alias("a"))
    b = results.where(F.col("method") == variant).select("setting", "metric", F.col("value").alias("b"))
    return a.join(b, ["setting", "metric"]).groupBy("metric").agg(F.avg("a").alias("mean_base"), F.avg("b").alias("mean_variant"), (F.avg("b") - F.avg("a")).alias("delta"), F.sum((F.col("b") > F.col("a")).cast("long")).alias("n_better"), F.count("*").alias("n"))


def scaling_gains(results: DataFrame, axis: str = "fraction", value: str = "value") -> DataFrame:
    """Step gains along an axis, and whether the curve is monotone."""
    w = W.partitionBy("setting", "metric").orderBy(axis)
    g = results.withColumn("gain", F.col(value) - F.lag(value).over(w))
    return g.withColumn("monotone", F.min(F.coalesce(F.col("gain") >= 0, F.lit(True))).over(W.partitionBy("setting", "metric")))

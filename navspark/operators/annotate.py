"""Dual-channel pointing labels from geometry: next free waypoint and target, in the current view."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions import pointing as P


def affordance_target(path: DataFrame, lookahead: int = 1, key: str = "episode_id", order: str = "i") -> DataFrame:
    """Adds nx, ny: the waypoint ``lookahead`` steps on (the last one near the end; NULL at the end)."""
    by = W.partitionBy(key).orderBy(order)
    last = by.rowsBetween(1, W.unboundedFollowing)
    return path.withColumns({c2: F.coalesce(F.lead(c, lookahead).over(by), F.last(c).over(last)) for c, c2 in (("x", "nx"), ("y", "ny"))})


def annotate_dual(path: DataFrame, lookahead: int = 1, fov_deg: float = 120.0, target_height: float = 1.0, hg: int = P.GRID, wg: int = P.GRID) -> DataFrame:
    """apos and opos of each pose: the next waypoint on the floor and the goal (gx, gy), projected
    into the view along the path. The last pose gets the reserved stop index. Pixels are rounded at
    nine digits, so a waypoint dead ahead falls into one cell on every machine."""
    p = affordance_target(path, lookahead)
    yaw = F.coalesce(F.atan2(F.col("ny") - F.col("y"), F.col("nx") - F.col("x")), F.lit(0.0))
    p = p.withColumn("yaw", yaw)
    p = p.withColumns({"_a": P.project_point("nx", "ny", F.lit(0.0), "x", "y", "yaw", fov_deg), "_o": P.project_point("gx", "gy", F.lit(target_height), "x", "y", "yaw", fov_deg)})
    au, av, ou, ov = (F.round(c, 9) for c in ("_a.u", "_a.v", "_o.u", "_o.v"))
    p = p.withColumns({"apos": P.affordance_index(au, av, None, F.col("nx").isNull(), hg, wg), "opos": P.object_index(ou, ov, None, hg, wg)})
    return p.drop("_a", "_o")


def point_supervision(samples: DataFrame, u: str = "u", v: str = "v", hg: int = P.GRID, wg: int = P.GRID) -> DataFrame:
    """Pointing and spatial question samples share the object index: adds their one response token."""
    return samples.withColumn("response", P.opos_token(P.object_index(u, v, None, hg, wg)))


def point_stats(df: DataFrame, idx: str = "idx", truth: str | None = None, u: str = "u", v: str = "v", hg: int = P.GRID, wg: int = P.GRID) -> DataFrame:
    """Occupancy and mean centre error of each index, and the token error rate against ``truth``."""
    c = P.cell_center(idx, hg, wg)
    err = F.sqrt((F.col(u) - c.u) ** 2 + (F.col(v) - c.v) ** 2)
    wrong = F.avg((F.col(idx) != F.col(truth)).cast("double")) if truth else F.lit(None).cast("double")
    return df.groupBy(idx).agg(F.count("*").alias("n"), F.avg(err).alias("mean_err"), wrong.alias("token_error"))

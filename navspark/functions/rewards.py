"""Terminal rewards of the three navigation tasks, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values of the reward definitions.
BEARING_FLAT, BEARING_TAIL = 0.14, 0.35  # rad
RANGE_NEAR, RANGE_FAR, NEAR_TAIL, FAR_TAIL = 1.5, 3.0, 0.35, 1.0  # m
HORIZON = 300  # decisions
QUALITY_WEIGHT, PLAN_WEIGHT, COLLISION_COST = 0.7, 0.3, 0.5
INSTRUCTION_RADIUS, INSTRUCTION_CLIP, INSTRUCTION_SCALE, TIMEOUT_COST = 3.0, 2.0, 3.0, 0.25
PLAN_SCALE = 1.0  # m; not published
OBJECT_RADIUS, OBJECT_CLIP, OBJECT_SCALE, OBJECT_WEIGHT = 1.0, 1.0, 3.0, 0.25


def _c(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _gauss(d: Column, s: float) -> Column:
    return F.exp(-(d * d) / (2.0 * s * s))


def bearing_factor(a, flat: float = BEARING_FLAT, tail: float = BEARING_TAIL) -> Column:
    a = F.abs(_c(a))
    return F.when(a <= flat, F.lit(1.0)).otherwise(_gauss(a - flat, tail))


def range_factor(d, lo: float = RANGE_NEAR, hi: float = RANGE_FAR, near: float = NEAR_TAIL, far: float = FAR_TAIL) -> Column:
    d = _c(d)
    return F.when(d < lo, _gauss(lo - d, near)).when(d > hi, _gauss(d - hi, far)).otherwise(F.lit(1.0))


def step_quality(visible, bearing, distance) -> Column:
    return F.when(_c(visible), bearing_factor(bearing) * range_factor(distance)).otherwise(F.lit(0.0))


def plan_match(displacement, scale: float = PLAN_SCALE) -> Column:
    """Agreement with the privileged plan in [0, 1], from the average displacement; 0 without a plan."""
    return F.coalesce(F.greatest(F.lit(0.0), 1 - _c(displacement) / scale), F.lit(0.0))


def following(visible, distance, bearing, target=None) -> Column:
    """In view 1 to 3 m ahead and within 60 degrees; with ``target``, the target's heading seen from the
    follower, also behind it: the line of sight and that heading agree to within 90 degrees."""
    ok = _c(visible) & _c(distance).between(1, 3) & (F.abs(_c(bearing)) <= 1.0471975511965976)
    return ok if target is None else ok & (F.cos(_c(target) - _c(bearing)) > 0)


def horizon(t, early, t0: int = HORIZON) -> Column:
    """Steps by which a tracking reward is divided: an early end counts as a full episode."""
    return F.when(_c(early), F.greatest(_c(t), F.lit(t0))).otherwise(_c(t))


def path_efficiency(d0, length) -> Column:
    """Reference over executed length, at most 1; a start on the goal counts 1 only if nothing was walked."""
    d0, length = _c(d0), _c(length)
    longest = F.greatest(d0, length)
    return F.when(longest > 0, d0 / longest).otherwise(F.lit(1.0))


def instruction_terms(success, ndtw, d_t, timeout) -> tuple[Column, Column, Column]:
    d = F.greatest(_c(d_t), F.lit(INSTRUCTION_CLIP))
    return (
        (1 + _c(ndtw)) * _c(success).cast("double"),
        F.exp(-(d * d) / INSTRUCTION_SCALE**2),
        -TIMEOUT_COST * _c(timeout).cast("double"),
    )


def object_terms(success, efficiency, d_t) -> tuple[Column, Column]:
    d = F.greatest(_c(d_t), F.lit(OBJECT_CLIP))
    return (1 + OBJECT_WEIGHT * _c(efficiency)) * _c(success).cast("double"), OBJECT_WEIGHT * F.exp(-(d * d) / OBJECT_SCALE**2)

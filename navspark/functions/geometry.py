"""Planar-pose trajectories: ten body-frame increments (dx, dy, dth), flat in 30 doubles.

A step is taken in the frame of the pose before it. All functions are columns over arrays of
ten; nothing leaves whole-row evaluation.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from navspark.functions.core import let, wrap_angle

STEPS = 10
LAMBDA = 0.3  #: weight of the heading difference


def _c(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _moved(x: Column, y: Column, th: Column, z: Column, i: Column) -> tuple[Column, Column, Column]:
    """The pose after step ``i`` of ``z``."""
    dx, dy = F.get(z, 3 * i), F.get(z, 3 * i + 1)
    return x + dx * F.cos(th) - dy * F.sin(th), y + dx * F.sin(th) + dy * F.cos(th), th + F.get(z, 3 * i + 2)


def _steps() -> Column:
    return F.sequence(F.lit(0), F.lit(STEPS - 1))


def integrate_se2(z) -> Column:
    """Array of ten waypoints (x, y, th)."""
    start = F.struct(F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.lit(0.0).alias("th"), F.array().cast("array<struct<x:double,y:double,th:double>>").alias("out"))

    def whole(v):
        def go(a, i):
            pose = F.struct(*[c.alias(n) for c, n in zip(_moved(a.x, a.y, a.th, v, i), ("x", "y", "th"), strict=True)])
            return let(pose, lambda p: F.struct(p.x.alias("x"), p.y.alias("y"), p.th.alias("th"), F.concat(a.out, F.array(p)).alias("out")))

        return F.aggregate(_steps(), start, go, lambda a: a.out)

    return let(z, whole)


def increments_se2(wps) -> Column:
    """The inverse: increments of a list of waypoints that starts at the origin."""
    origin = F.struct(F.lit(0.0).alias("x"), F.lit(0.0).alias("y"), F.lit(0.0).alias("th"))

    def back(a, b):
        dx, dy = b.x - a.x, b.y - a.y
        return F.array(dx * F.cos(a.th) + dy * F.sin(a.th), dy * F.cos(a.th) - dx * F.sin(a.th), b.th - a.th)

    return let(wps, lambda w: F.flatten(F.zip_with(F.concat(F.array(origin), F.slice(w, 1, F.size(w) - 1)), w, back)))


def _mean(a: Column) -> Column:
    return let(a, lambda v: F.aggregate(v, F.lit(0.0), lambda s, x: s + x, lambda s: s / F.size(v)))


def ade_waypoints(a, b) -> Column:
    """Average displacement of two waypoint lists."""
    return _mean(F.zip_with(_c(a), _c(b), lambda p, q: F.sqrt((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y))))


def ade(z, zhat) -> Column:
    """Average displacement of two trajectories, integrated side by side; no waypoint is kept."""
    names = ("x", "y", "th", "u", "v", "ph")
    start = F.struct(*[F.lit(0.0).alias(n) for n in names], F.lit(0.0).alias("s"))

    def whole(both):
        def go(a, i):
            after = [*_moved(a.x, a.y, a.th, both.z, i), *_moved(a.u, a.v, a.ph, both.zhat, i)]
            gap = lambda p: F.sqrt((p.x - p.u) * (p.x - p.u) + (p.y - p.v) * (p.y - p.v))
            return let(F.struct(*[c.alias(n) for c, n in zip(after, names, strict=True)]), lambda p: F.struct(*[p[n].alias(n) for n in names], (a.s + gap(p)).alias("s")))

        return F.aggregate(_steps(), start, go, lambda a: a.s / STEPS)

    return let(F.struct(_c(z).alias("z"), _c(zhat).alias("zhat")), whole)


def fde(z, zhat) -> Column:
    ends = F.struct(F.element_at(integrate_se2(z), -1).alias("a"), F.element_at(integrate_se2(zhat), -1).alias("b"))
    return let(ends, lambda e: F.sqrt((e.a.x - e.b.x) * (e.a.x - e.b.x) + (e.a.y - e.b.y) * (e.a.y - e.b.y)))


def heading_total(z) -> Column:
    return let(z, lambda v: F.aggregate(_steps(), F.lit(0.0), lambda s, i: s + F.get(v, 3 * i + 2)))


def heading_err(z, zhat) -> Column:
    return F.abs(wrap_angle(heading_total(z) - heading_total(zhat)))


def d_traj(z, zhat, lam: float = LAMBDA) -> Column:
    return ade(z, zhat) + F.lit(lam) * heading_err(z, zhat)


def plus(a, b, scale: float = 1.0) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x + F.lit(scale) * y)


def minus(a, b) -> Column:
    return plus(a, b, -1.0)


#: Limits of the four embodiments: name, forward speed (m/s), turning speed (rad/s).
PLATFORMS = [("humanoid", 0.6, 0.8), ("quadruped", 1.2, 1.2), ("aerial", 2.0, 1.5), ("wheeled", 0.8, 1.0)]


def platforms(spark):
    return spark.createDataFrame(PLATFORMS, "platform string, v_max double, w_max double")


def to_velocity(z, dt: float, v_max, w_max) -> Column:
    """Ten (v, w, clipped) commands: speed along the body axis and turning rate within limits."""

    def one(u, i):
        dx, dy = F.get(u, 3 * i), F.get(u, 3 * i + 1)
        return F.struct((F.signum(dx) * F.sqrt(dx * dx + dy * dy) / F.lit(dt)).alias("v"), (F.get(u, 3 * i + 2) / F.lit(dt)).alias("w"))

    def within(c):
        vc, wc = F.greatest(-v_max, F.least(v_max, c.v)), F.greatest(-w_max, F.least(w_max, c.w))
        return F.struct(vc.alias("v"), wc.alias("w"), ((vc != c.v) | (wc != c.w)).alias("clipped"))

    return F.transform(let(z, lambda u: F.transform(_steps(), lambda i: one(u, i))), within)

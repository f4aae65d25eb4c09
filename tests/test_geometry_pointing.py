import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from navspark.functions import core
from navspark.functions import geometry as G
from navspark.functions import pointing as P
from navspark.functions import rewards as R


def one(spark, **cols):
    return spark.range(1).select(*[c.alias(k) for k, c in cols.items()]).first()


def test_wrap_and_heading_error(spark):
    z = [0.0] * 30
    a, b = list(z), list(z)
    a[29], b[29] = math.radians(179), math.radians(-179)
    arr = lambda x: F.array(*map(F.lit, x))
    r = one(spark, w=core.wrap_angle(F.lit(math.pi)), v=core.wrap_angle(F.lit(-math.pi)), e=G.heading_err(arr(a), arr(b)))
    assert r.w == pytest.approx(math.pi) and r.v == pytest.approx(math.pi)
    assert math.degrees(r.e) == pytest.approx(2)


def test_integration_round_trip_and_distances(spark):
    rng = np.random.default_rng(1)
    rows = [(i, rng.normal(0, 0.4, 30).tolist(), rng.normal(0, 0.4, 30).tolist()) for i in range(40)]
    df = spark.createDataFrame(rows, "i int, z array<double>, y array<double>")
    from navspark.operators import rvq as Q

    for r in df.select("i", "z", "y", G.increments_se2(G.integrate_se2("z")).alias("back"), G.integrate_se2("z").alias("w"), G.d_traj("z", "y").alias("d"), G.fde("z", "y").alias("f")).collect():
        assert np.allclose(r.back, r.z, atol=1e-12)
        w = Q.integrate(np.array(r.z)[None])[0]
        assert np.allclose([[p.x, p.y, p.th] for p in r.w], w)
        assert r.d == pytest.approx(float(Q.d_traj(np.array(r.z)[None], np.array(r.y)[None])[0]))
        assert r.f == pytest.approx(float(np.hypot(*(w[-1, :2] - Q.integrate(np.array(r.y)[None])[0][-1, :2]))))


def test_grid_corners_and_reserved(spark):
    df = spark.createDataFrame([(1.0, 1.0), (0.0, 0.0), (None, 0.5), (1.01, 0.5), (0.5, 0.999999)], "u double, v double")
    got = [r.i for r in df.select(P.grid_index("u", "v").alias("i")).collect()]
    assert got == [255, 0, None, None, 15 * 16 + 8]
    got = [r.i for r in df.select(P.object_index("u", "v").alias("i")).collect()]
    assert got == [255, 0, 258, 258, 248]
    assert [P.reserved(k) for k in P.RESERVED] == [256, 257, 258]


def test_cell_centre_is_near(spark):
    rnd = random.Random(2)
    df = spark.createDataFrame([(rnd.random(), rnd.random()) for _ in range(200)], "u double, v double").withColumn("c", P.cell_center(P.grid_index("u", "v")))
    for r in df.collect():
        assert abs(r.u - r.c.u) <= 1 / 32 + 1e-12 and abs(r.v - r.c.v) <= 1 / 32 + 1e-12


def test_projection_round_trip(spark):
    rnd = random.Random(3)
    rows = [(rnd.uniform(-9, 9), rnd.uniform(-9, 9), rnd.uniform(0, 3), rnd.uniform(-9, 9), rnd.uniform(-9, 9), rnd.uniform(-3, 3)) for _ in range(300)]
    df = spark.createDataFrame(rows, "x double, y double, z double, px double, py double, yaw double")
    kw = {"fov_deg": 100.0, "height": 1.2, "pitch": 0.2, "aspect": 1.5}
    df = df.withColumn("p", P.project_point("x", "y", "z", "px", "py", "yaw", **kw)).where("p.depth > 0.1")
    df = df.withColumn("q", P.lift("p.u", "p.v", "p.depth", "px", "py", "yaw", **kw))
    n = 0
    for r in df.collect():
        n += 1
        assert (r.q.x, r.q.y, r.q.z) == pytest.approx((r.x, r.y, r.z), abs=1e-9)
    assert n > 50


def test_reward_bands(spark):
    f = lambda x: F.lit(float(x))
    r = one(spark, a=R.bearing_factor(f(0.14)), b=R.bearing_factor(f(-0.49)), c=R.range_factor(f(1.5)), d=R.range_factor(f(3.0)), e=R.range_factor(f(1.15)), g=R.range_factor(f(4.0)), q=R.step_quality(F.lit(False), f(0), f(2)))
    half = math.exp(-0.5)
    assert (r.a, r.c, r.d, r.q) == (1, 1, 1, 0)
    assert (r.b, r.e, r.g) == pytest.approx((half, half, half))


def test_horizon_and_terms(spark):
    r = one(spark, early=R.horizon(F.lit(100), F.lit(True)), natural=R.horizon(F.lit(100), F.lit(False)), long=R.horizon(F.lit(400), F.lit(True)), e=R.path_efficiency(F.lit(0.0), F.lit(0.0)), e2=R.path_efficiency(F.lit(0.0), F.lit(2.0)), k=R.instruction_terms(F.lit(True), F.lit(0.5), F.lit(0.0), F.lit(True))[1], t=R.instruction_terms(F.lit(True), F.lit(0.5), F.lit(0.0), F.lit(True))[2])
    assert (r.early, r.natural, r.long, r.e, r.e2, r.t) == (300, 100, 400, 1, 0, -0.25)
    assert r.k == pytest.approx(math.exp(-4 / 9))


def test_failures_stay_ranked(spark):
    df = spark.range(20).select((F.col("id") / 2.0 + 2.0).alias("d")).withColumn("r", R.object_terms(F.lit(False), F.lit(0.5), "d")[1]).orderBy("d")
    v = [x.r for x in df.collect()]
    assert all(a > b for a, b in zip(v, v[1:], strict=False))


def test_velocity_limits(spark):
    z = [0.5, 0.0, 0.1] * 9 + [5.0, 0.0, 3.0]
    r = one(spark, c=G.to_velocity(F.array(*map(F.lit, z)), 0.5, F.lit(1.2), F.lit(1.2))).c
    assert [x.clipped for x in r] == [False] * 9 + [True] and r[9].v == 1.2 and r[9].w == 1.2 and r[0].v == 1.0


def test_uniform_is_the_md5(spark):
    import hashlib

    r = one(spark, u=core.uniform01(F.lit(17), F.lit("x"), salt="s")).u
    assert r == int(hashlib.md5(b"s|17|x").hexdigest()[:8], 16) / 2**32


def test_annotation_of_a_straight_walk(spark):
    from navspark.operators import annotate as A

    df = spark.createDataFrame([(1, i, float(i), 0.0, 3.0, 1.0) for i in range(3)], "episode_id long, i int, x double, y double, gx double, gy double")
    r = A.annotate_dual(df).orderBy("i").collect()
    assert [(x.nx, x.ny) for x in r] == [(1.0, 0.0), (2.0, 0.0), (None, None)]
    assert r[2].apos == P.reserved("stop") and all(x.opos < 256 for x in r[:2])
    assert [x.nx for x in A.affordance_target(df, 2).orderBy("i").collect()] == [2.0, 2.0, None]
    s = A.point_stats(df.withColumn("idx", P.grid_index(F.lit(0.5), F.lit(0.5))).withColumns({"u": F.lit(0.5), "v": F.lit(0.5), "t": F.lit(0)}), truth="t").first()
    assert s.n == 3 and s.token_error == 1.0 and s.mean_err < 0.05

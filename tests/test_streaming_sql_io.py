import time
import uuid

import pytest
from support import SF_SMOKE
from pyspark.sql import functions as F

from navspark.functions import sqlfn
from navspark.operators import history as H
from navspark.operators import rollouts as R
from navspark.sources import carriers as C
from navspark.sources import io
from navspark.streaming import live


@pytest.fixture(scope="module")
def parts(spark, tmp_path_factory):
    """The events in time order over several files, then one very late row and re-sent frames."""
    d = str(tmp_path_factory.mktemp("events"))
    e = io.load(spark, SF_SMOKE, "events").withColumn("day", F.floor(F.dayofmonth("ts") / 8)).persist()
    for i in range(4):
        e.where(F.col("day") == i).drop("day").unionByName(e.where(F.col("day") == i).drop("day").limit(5)).coalesce(1).write.mode("append").parquet(d)
    return d


def run(df, mode, tmp):
    return live.run_available(df, f"t_{uuid.uuid4().hex}", mode, f"{tmp}/{uuid.uuid4().hex}")


def test_windows_equal_batch(spark, parts, tmp_path):
    s = live.events_stream(spark, parts, "60 days", None)
    got = {r.start: (r.n, round(r.tracking_rate, 9)) for r in run(live.tracking_windows(s), "complete", tmp_path).collect()}
    want = {r.start: (r.n, round(r.tracking_rate, 9)) for r in live.tracking_windows(C.v_steps(spark, SF_SMOKE)).collect()}
    assert got == want


def test_online_history_equals_batch(spark, parts, tmp_path):
    f_max, tau = 1 / 86400, 5 * 86400.0
    s = live.events_stream(spark, parts, "60 days", None)
    t = run(live.online_history(s, f_max, tau), "update", tmp_path)
    got = {}
    for r in t.collect():
        got[r.episode_id] = (r.n_kept, r.newest, r.oldest)
    k = H.select_frames(H.with_age(C.v_frames(spark, SF_SMOKE)), "integral", f_max, tau)
    want = {r.episode_id: (r.n, r.a, r.b) for r in k.groupBy("episode_id").agg(F.count("*").alias("n"), F.max_by("event_id", "ts").alias("a"), F.min_by("event_id", "ts").alias("b")).collect()}
    assert got == want
    assert all(n <= H.frame_bound(f_max, tau) for n, *_ in got.values())


def test_live_reward_equals_batch(spark, tmp_path):
    """A closing row far in the future lets the timers fire; a row behind the watermark changes nothing."""
    d = f"{tmp_path}/ev"
    e = io.load(spark, SF_SMOKE, "events")
    one = e.limit(1)

    def put(df):
        df.select(*e.columns).coalesce(1).write.mode("append").parquet(d)
        time.sleep(1.1)  # files are taken in the order of their times

    put(e)
    put(one.withColumns({"event_id": F.lit(10**9), "user_id": F.lit(10**6), "ts": F.expr("timestamp_ntz'2024-06-01 00:00:00'")}))
    put(one.withColumns({"event_id": F.lit(10**9 + 1), "ts": F.expr("timestamp_ntz'2024-01-01 00:00:00'")}))
    put(one.withColumns({"event_id": F.lit(10**9 + 2), "user_id": F.lit(10**6), "ts": F.expr("timestamp_ntz'2024-06-02 00:00:00'")}))
    rows = run(live.live_tracking(live.events_stream(spark, d, "2 days")), "append", tmp_path).collect()
    out = {r.episode_id: r for r in rows}
    assert len(out) == len(rows)
    want = {r.episode_id: r for r in R.tracking_episodes(C.v_steps(spark, SF_SMOKE)).collect()}
    assert set(want) <= set(out)
    for k, w in want.items():
        assert (out[k].t_n, out[k].horizon, out[k].success, out[k].collision) == (w.t_n, w.horizon, w.success, w.collision)
        assert out[k].reward == pytest.approx(w.reward)


def test_groups_complete(spark, tmp_path):
    d = f"{tmp_path}/rw"
    spark.createDataFrame([(i % 5, i, float(i)) for i in range(38)], "seed_id long, episode_id long, reward double").coalesce(1).write.parquet(d)
    s = spark.readStream.schema("seed_id long, episode_id long, reward double").parquet(d)
    got = run(live.complete_groups(s, 8), "append", tmp_path).groupBy("seed_id").agg(F.count("*").alias("n"), F.sum("adv").alias("a")).collect()
    assert sorted((r.seed_id, r.n) for r in got) == [(0, 8), (1, 8), (2, 8)] and all(abs(r.a) < 1e-9 for r in got)


def test_groups_that_stay_short_are_given_up(spark, tmp_path):
    d = f"{tmp_path}/rw"
    parts = [[(1, i, float(i), "2024-01-01 00:00:00") for i in range(3)], [(2, 9, 0.0, "2024-02-01 00:00:00")], [(2, 10, 0.0, "2024-02-02 00:00:00")], [(1, i, float(i), "2024-02-03 00:00:00") for i in range(3, 8)]]
    for rows in parts:
        spark.createDataFrame(rows, "seed_id long, episode_id long, reward double, s string").selectExpr("seed_id", "episode_id", "reward", "timestamp(s) as ts").coalesce(1).write.mode("append").parquet(d)
        time.sleep(1.1)
    s = spark.readStream.schema("seed_id long, episode_id long, reward double, ts timestamp").option("maxFilesPerTrigger", 1).parquet(d).withWatermark("ts", "1 hour")
    assert run(live.complete_groups(s, 8, at="ts"), "append", tmp_path).count() == 0  # the first three were forgotten


def test_plans_meet_outcomes(spark, tmp_path):
    p, o = f"{tmp_path}/p", f"{tmp_path}/o"
    spark.sql("select 1L plan_key, timestamp'2024-01-01 00:00:00' plan_ts union all select 2L, timestamp'2024-01-01 00:00:00'").write.parquet(p)
    spark.sql("select 1L out_key, timestamp'2024-01-01 00:30:00' out_ts union all select 2L, timestamp'2024-01-01 03:00:00'").write.parquet(o)
    j = live.plan_outcome(spark.readStream.schema("plan_key long, plan_ts timestamp").parquet(p), spark.readStream.schema("out_key long, out_ts timestamp").parquet(o))
    assert [r.plan_key for r in run(j, "append", tmp_path).collect()] == [1]


def test_sql_surface(spark):
    sqlfn.register_all(spark, SF_SMOKE)
    r = spark.sql("SELECT grid_index(1D, 1D, 16, 16) AS i, wrap_angle(-pi()) AS a, bearing_factor(0.14D) AS b, range_factor(3D) AS c, pool_stride(1e9D, 1D, 8) AS s").first()
    assert (r.i, r.b, r.c, r.s) == (255, 1.0, 1.0, 8) and r.a == pytest.approx(3.14159265358979)
    assert spark.sql("SELECT levels FROM decode_prefixes(array(1, 2, 3))").count() == 3
    assert [x.place for x in spark.sql("SELECT place FROM keyframes(30, 6)").collect()][-1] == 30
    assert spark.sql("SELECT max(bin) AS m FROM pack_lengths(array(5, 5, 5, 5), 10)").first().m == 1
    assert spark.sql("SELECT max(ade(z, z)) AS m FROM v_traj").first().m == 0
    one = "array(1D, 2D)"
    assert spark.sql(f"SELECT ndtw({one}, {one}, {one}, {one}, 3D) AS m").first().m == 1
    assert spark.sql("SELECT dtw_mean(range_m) AS m FROM v_steps").first().m > 0


def test_io_round_trip(spark, tmp_path):
    e = io.load(spark, SF_SMOKE, "events")
    io.save(e, f"{tmp_path}/events.parquet", ["event_type"])
    assert io.load(spark, str(tmp_path), "events").count() == e.count()
    n = io.load(spark, SF_SMOKE, "nation")
    for fmt in ("json", "orc"):
        io.save(n, f"{tmp_path}/nation.{fmt}", fmt=fmt)
        assert sorted(map(tuple, io.load(spark, str(tmp_path), "nation", fmt).select(*n.columns).collect())) == sorted(map(tuple, n.collect()))
    put = io.batch_writer(f"{tmp_path}/out")
    put(n, 3)
    put(n, 3)
    assert spark.read.parquet(f"{tmp_path}/out").count() == n.count()


def test_filters_reach_the_scan(spark):
    plan = io.load(spark, SF_SMOKE, "events").where("user_id = 3").select("event_id")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(user_id), EqualTo(user_id,3)]" in plan and "props" not in plan

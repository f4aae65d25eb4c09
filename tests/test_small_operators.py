"""Operators that no query calls, loops without round limits, and rules with hand-made cases."""

import math
import random
import uuid

import pytest
from pyspark.sql import functions as F
from support import SF_SMOKE

from navspark import session
from navspark.functions import rewards
from navspark.functions.core import uniform01
from navspark.operators import episodes as E
from navspark.operators import history as H
from navspark.operators import instruct as N
from navspark.operators import inventory as V
from navspark.operators import metrics as M
from navspark.operators import mixture as X
from navspark.operators import ops
from navspark.operators import packing as K
from navspark.operators import rollouts as R
from navspark.operators import serialize as S
from navspark.operators import taxonomy as Y
from navspark.operators import tokenlm as T
from navspark.sources import carriers as C
from navspark.sources import io
from navspark.sources import published as PUB
from navspark.streaming import live


def test_plan_term_and_place_behind_the_target(spark):
    schema = "episode_id long, t int, visible boolean, range_m double, bearing_rad double, collision boolean, plan_ade double, target_rad double"
    rows = [(1, t, True, 2.0, 0.0, False, None if t > 3 else 0.25 * t, 0.1) for t in range(1, 5)] + [(2, t, True, 2.0, 0.0, False, 0.0, 3.0) for t in range(1, 5)]
    got = {r.episode_id: r for r in R.tracking_episodes(spark.createDataFrame(rows, schema)).collect()}
    assert got[1].success and not got[2].success  # the second target faces the follower
    assert got[1].reward == pytest.approx(1 + (0.7 * 4 + 0.3 * (0.75 + 0.5 + 0.25)) / 4)
    assert got[2].reward == pytest.approx((0.7 * 4 + 0.3 * 4) / 4)
    p = spark.createDataFrame([(0.0,), (0.5,), (7.0,), (None,)], "d double").select(rewards.plan_match("d", 2.0).alias("m")).collect()
    assert [r.m for r in p] == [1.0, 0.75, 0.0, 0.0]


def test_planned_steps_against_plain_integration(spark):
    s = C.planned_steps(spark, SF_SMOKE).orderBy("episode_id", "t").collect()
    by = {}
    for r in s:
        by.setdefault(r.episode_id, []).append(r)
    for steps in by.values():
        for i in range(0, len(steps), 37):
            if i + 10 > len(steps):
                assert steps[i].plan_ade is None
                continue

            def walk(rows):
                x = y = h = 0.0
                for r in rows:
                    x, y, h = x + r.fwd_m * math.cos(h), y + r.fwd_m * math.sin(h), h + r.turn_rad
                    yield x, y

            d = [math.dist(a, b) for a, b in zip(walk(steps[i : i + 10]), walk([steps[i]] * 10), strict=True)]
            assert steps[i].plan_ade == pytest.approx(sum(d) / 10)


def test_greedy_clusters_equal_the_sequential_rule(spark):
    rnd = random.Random(3)
    rows = [(f"o{i:03d}", 0, "c", i % 5, rnd.uniform(0, 8), rnd.uniform(0, 8), 0.0) for i in range(150)]
    df = spark.createDataFrame(rows, "obs_id string, scene int, category string, viewpoint long, lx double, ly double, lz double")
    got = {r.obs_id: r.cluster_id for r in V.merge_views(df, 1.0, "greedy").collect()}
    seeds = []
    for r in sorted(rows):
        if not any(math.dist(r[4:6], s[4:6]) <= 1 for s in seeds):
            seeds.append(r)
    assert got == {r[0]: min(s[0] for s in seeds if math.dist(r[4:6], s[4:6]) <= 1) for r in rows}
    assert V.merge_views(df.limit(0), 1.0, "greedy").count() == 0


def test_components_of_a_long_chain(spark):
    pairs = spark.createDataFrame([(i, i + 1) for i in range(300)], "a int, b int")
    assert {r.root for r in ops.components(pairs, "a", "b").collect()} == {0}


def test_empty_cells_have_a_shortfall(spark):
    eps = spark.createDataFrame([(1, "a", "x"), (2, "b", "y"), (3, "b", "y")], "episode_id long, scene_type string, instr_type string")
    got = {(r.scene_type, r.instr_type): (r.n, r.shortfall) for r in Y.fill_cells(eps, 2)[1].collect()}
    assert got == {("a", "x"): (1, 1), ("a", "y"): (0, 2), ("b", "x"): (0, 2), ("b", "y"): (2, 0)}


def test_corpus_keeps_its_own_states(spark):
    expert = spark.createDataFrame([("a", "go", 0, "expert"), ("a", "stop", 0, "expert")], "state_key string, action string, round int, origin string")
    labels = spark.createDataFrame([("b", "stop"), ("b", "go"), ("c", "go")], "state_key string, action string")
    rollouts = spark.createDataFrame([("a",), ("b",), ("b",)], "state_key string")
    got = sorted((r.state_key, r.action, r.origin) for r in X.aggregate_onpolicy(expert, rollouts, labels, 1).collect())
    assert got == [("a", "go", "expert"), ("a", "stop", "expert"), ("b", "go", "policy")]


def test_last_scenes_of_each_group(spark):
    df = spark.createDataFrame([(g, i) for g in "ab" for i in range(30 if g == "a" else 2)], "g string, i int")
    got = {(r.g, r.i) for r in Y.split_contiguous(df, 3, "i", "g").where("split = 'eval'").collect()}
    assert got == {("a", 27), ("a", 28), ("a", 29), ("b", 0), ("b", 1)}
    kept = Y.split_allowlist(df, spark.createDataFrame([(1,), (29,)], "i int"), "i")
    assert kept.where("split = 'eval'").count() == 3 and kept.count() == 32


def test_budget_counts_the_time_tokens(spark):
    ctx = H.compress_history(C.v_frames(spark, SF_SMOKE), "uniform", 1 / 86400, 5 * 86400.0, 7 * 86400.0, budget=200, every=2)
    rows = ctx.select("episode_id", "stride", "n_tok", "over_budget", "time_token", F.unix_seconds("ts").alias("s")).collect()
    total = {}
    for r in rows:
        assert r.n_tok == math.ceil(8 / r.stride) ** 2 + 1 and r.time_token == f"<t_{r.s}>"
        total[r.episode_id] = total.get(r.episode_id, 0) + r.n_tok
    assert all((total[r.episode_id] > 200) == r.over_budget for r in rows) and min(total.values()) <= 200


@pytest.mark.parametrize("order", ["in time", "shuffled"])
def test_online_history_over_many_batches(spark, tmp_path, order):
    f_max, tau = 1 / 86400, 5 * 86400.0
    e = io.load(spark, SF_SMOKE, "events")
    at = F.ntile(12).over(__import__("pyspark").sql.Window.orderBy("ts")) if order == "in time" else F.pmod(F.xxhash64("event_id"), F.lit(12))
    parts = session.kept(e.withColumn("part", at))
    for i in range(13):
        parts.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(f"{tmp_path}/ev")
    s = live.events_stream(spark, f"{tmp_path}/ev", "60 days", 1)
    t = live.run_available(live.online_history(s, f_max, tau), f"t_{uuid.uuid4().hex}", "update", f"{tmp_path}/cp")
    rows = t.collect()
    assert len(rows) > 100  # a row an episode and batch
    if order == "in time":  # what is held after each batch is what the batch selector holds then
        for now in sorted({r.now_us for r in rows})[:40:7]:
            seen = C.v_steps(spark, SF_SMOKE).where(F.unix_micros("ts") <= now).select("episode_id", "t", "ts", "event_id")
            want = _batch(seen, f_max, tau)
            for r in rows:
                if r.now_us == now:
                    assert (r.n_kept, r.newest, r.oldest) == want[r.episode_id]
    got = {}
    for r in rows:
        if r.now_us >= got.get(r.episode_id, (0,))[0]:
            got[r.episode_id] = (r.now_us, max(r.n_kept, got[r.episode_id][1]) if r.episode_id in got and got[r.episode_id][0] == r.now_us else r.n_kept, r.newest, r.oldest)
    last = _batch(C.v_frames(spark, SF_SMOKE), f_max, tau)
    if order == "in time":
        assert {k: v[1:] for k, v in got.items()} == last
    assert {k: v[2] for k, v in got.items()} == {k: v[1] for k, v in last.items()}


def _batch(frames, f_max, tau):
    k = H.select_frames(H.with_age(frames), "integral", f_max, tau)
    return {r.episode_id: (r.n, r.a, r.b) for r in k.groupBy("episode_id").agg(F.count("*").alias("n"), F.max_by("event_id", "ts").alias("a"), F.min_by("event_id", "ts").alias("b")).collect()}


def test_published_macro_and_gains(spark):
    p = PUB.frame(spark)
    gains = {(r.setting, r.metric): r for r in M.gain_table(p.where("family = 'mono'"), "ours").collect()}
    assert gains["diagnostic", "SR"].gain_abs == pytest.approx(16.3) and gains["instr_1", "SR"].gain_abs == pytest.approx(1.6)
    assert gains["instr_2", "NE"].gain_abs == pytest.approx(0.43) and gains["open_unseen", "SR"].gain_abs == pytest.approx(6.2)
    best = {r.setting: r.method for r in M.rank_marks(p.where("family = 'mono'")).where("rank = 1 and metric = 'SR'").collect()}
    assert all(v == "ours" for k, v in best.items() if k.startswith("label_"))
    assert M.filter_sensing(p.withColumn("depth", F.col("method") == "ours"), depth=True).select("method").distinct().count() == 1


def test_paths_clips_and_routes(spark):
    dist = spark.createDataFrame([(0, 0, 0.0), (0, 1, 2.0)], "src int, node int, dist double")
    pairs = spark.createDataFrame([(0, 1), (0, 9)], "src int, dst int")
    assert [tuple(r) for r in E.plan_route(dist, pairs).collect()] == [(0, 1, 2.0)]
    clips = E.clip_rows(spark.createDataFrame([(7, [3, 4])], "id int, path array<int>"))
    assert [tuple(r) for r in clips.collect()] == [(7, 0, 3), (7, 1, 4)]
    by = spark.range(2000).select(N.assign_route("id", 0.25).alias("r")).groupBy("r").count().collect()
    assert {r.r for r in by} == {"rule", "video"} and abs(next(r["count"] for r in by if r.r == "rule") - 500) < 80


def test_views_inventories_and_masks(spark):
    v = V.expand_views(spark.createDataFrame([(1,), (2,)], "viewpoint int"), spark)
    assert v.count() == 8 and {r.heading for r in v.collect()} == {0, 1, 2, 3}
    a, b = spark.createDataFrame([(1, "x")], "id int, category string"), spark.createDataFrame([(2, 0.5)], "id int, size double")
    assert sorted((r.id, r.route, r.category, r["size"]) for r in V.inventory(a, b).collect()) == [(1, "visual", "x", None), (2, "boxes", None, 0.5)]
    m = spark.createDataFrame([("navigation", 4), ("navigation", 5), ("pointing", 9), ("pointing", -1)], "task string, position int")
    assert [r.m for r in m.select(S.supervised_mask("task", "position").alias("m")).collect()] == [True, False, True, False]
    one = S.interleave(spark.range(50).select(F.col("id").alias("sample_id"), F.lit("a").alias("s")), spark.range(50, 90).select(F.col("id").alias("sample_id"), F.lit("b").alias("t")))
    rows = one.collect()
    assert sorted(r.sample_id for r in rows) == list(range(90)) and [r.stream_pos for r in rows] == sorted(r.stream_pos for r in rows)
    want = {r.id: r.u for r in spark.range(90).select("id", uniform01("id", salt="mix").alias("u")).collect()}
    assert all(r.stream_pos == want[r.sample_id] for r in rows)


def test_quantiles_and_divergence(spark):
    q = spark.range(1, 101).agg(M.quantiles("id").alias("q")).first().q
    assert [abs(a - b) <= 1 for a, b in zip(q, (10, 50, 90), strict=True)] == [True] * 3
    rows = spark.createDataFrame([(1, "<s>", t) for t in "aab"] + [(1, "<s>", "c")], "one int, ctx string, token string")
    p = T.score(rows.select("one", "ctx", "token").distinct(), T.fit_token_lm(rows, ("one",)), ("one",))
    w = rows.groupBy("one", "ctx").agg(F.count("*").alias("n_ctx"))
    assert T.kl_exact(p, p, w, ("one",)).first().kl == pytest.approx(0)
    other = T.score(rows.select("one", "ctx", "token").distinct(), T.fit_token_lm(rows.where("token <> 'a'"), ("one",)), ("one",))
    assert T.kl_exact(p, other, w, ("one",)).first().kl > 0


def test_gains_along_an_axis(spark):
    df = spark.createDataFrame([("a", "SR", 0.5, 1.0), ("a", "SR", 1.0, 3.0), ("b", "SR", 0.5, 2.0), ("b", "SR", 1.0, 1.0)], "setting string, metric string, fraction double, value double")
    got = {(r.setting, r.fraction): (r.gain, r.monotone) for r in M.scaling_gains(df).collect()}
    assert got == {("a", 0.5): (None, True), ("a", 1.0): (2.0, True), ("b", 0.5): (None, False), ("b", 1.0): (-1.0, False)}


def test_batches_over_shards_and_weights(spark):
    packed = K.pack(spark.range(500).select(F.col("id").alias("sample_id"), (F.col("id") % 90 + 5).cast("int").alias("n_tok")), 100, "ffd", shards=3)
    plan = K.batch_plan(packed, 16)
    per = sorted((r.batch_id, r["count"]) for r in plan.groupBy("batch_id").count().collect())
    assert [n for _, n in per[:-1]] == [16] * (len(per) - 1) and [b for b, _ in per] == list(range(len(per)))
    for stage, n in ((1, 36), (2, 49)):
        w = X.mixture_weights(spark, stage)
        assert w.count() == n and w.agg(F.sum("weight")).first()[0] == pytest.approx(1)


def test_large_sides_are_not_broadcast(spark):
    def hinted(df):
        return "ResolvedHint" in df._jdf.queryExecution().analyzed().toString()

    assert hinted(session.bounded(spark.range(10), 10)) and not hinted(session.bounded(spark.range(11), 10))


def test_the_views_projection_runs_once_a_row(spark):
    plan = C.v_views(spark, SF_SMOKE).where("u between 0 and 1 and v between 0 and 1").select("obs_id")._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("ATAN2") == 1


def test_farthest_start_reaches_rare_motions(spark):
    from navspark.operators import rvq as Q

    rows = [(i, [0.25 + 0.001 * (i % 7), 0.0, 0.0] * 10) for i in range(60)] + [(100 + j, [0.1, 0.0, 0.3 * (j + 1)] * 10) for j in range(3)]
    df = spark.createDataFrame(rows, "traj_id long, z array<double>")
    far = Q.init_codebook(df, 4, how="farthest", spare=20)
    assert {round(r[2], 6) for r in far} == {0.0, 0.3, 0.6, 0.9}
    err = [Q.fit_rvq(df, 1, 4, 1, start_with=how).shift[0] for how in ("hash", "farthest")]
    assert err[1] < err[0]


def test_context_rows_have_their_pooled_grid(spark):
    ctx = H.compress_history(C.v_frames(spark, SF_SMOKE), "integral", 1 / 86400, 5 * 86400.0, 7 * 86400.0)
    grids = {r.grid_id: r.grid for r in C.grids(spark, SF_SMOKE).collect()}
    for how, f in (("mean", lambda v: sum(v) / len(v)), ("max", max)):
        for r in H.with_pooled(ctx, C.grids(spark, SF_SMOKE), how=how).limit(25).collect():
            g, s, n = grids[r.grid_id], r.stride, math.ceil(8 / r.stride)
            want = [f([g[8 * y + x] for y in range(i * s, min(8, i * s + s)) for x in range(j * s, min(8, j * s + s))]) for i in range(n) for j in range(n)]
            assert (r.h_p, r.w_p) == (n, n) and r.cells == pytest.approx(want)


def test_proximity_pairs_and_components(spark):
    """Against all pairs: crowded cells, rows on cell borders and exactly at the radius, a null coordinate."""
    import random

    from navspark.operators import ops

    rnd = random.Random(9)
    rows = [(f"o{i:03d}", i % 2, rnd.gauss(0, 0.2), rnd.gauss(0, 0.2), 0.0) for i in range(80)]
    rows += [(f"p{i:03d}", 0, float(i), 9.0, 0.0) for i in range(6)] + [(f"q{i:03d}", 1, rnd.uniform(0, 9), rnd.uniform(3, 9), 0.5) for i in range(60)]
    rows += [("r000", 0, None, 0.0, 0.0)]
    df = spark.createDataFrame(rows, "id string, k int, x double, y double, z double")
    solid = rows[:-1]
    near = {(a[0], b[0]) for a in solid for b in solid if a[0] < b[0] and a[1] == b[1] and sum((a[c] - b[c]) ** 2 for c in (2, 3, 4)) <= 1.0}
    got = [tuple(sorted((r.a, r.b))) for r in ops.proximity_pairs(df, 1.0, ["k"], "id").collect()]
    assert len(got) == len(near) and set(got) == near
    up = {r[0]: r[0] for r in rows}
    for _ in rows:
        for a, b in near:
            up[a] = up[b] = min(up[a], up[b])
    assert {r.id: r.root for r in ops.near_components(df, 1.0, ["k"], "id").collect()} == up


def _crowd():
    import random

    rnd = random.Random(5)
    spots = [(rnd.uniform(0, 6), rnd.uniform(0, 6), rnd.uniform(0, 1)) for _ in range(90)]
    return [(f"o{i:03d}", i % 2, "c", i % 5, *spots[rnd.randrange(90)]) for i in range(300)] + [("z1", 0, "c", 0, None, 0.0, 0.0), ("z2", 0, "c", 0, float("nan"), 0.0, 0.0), ("z3", None, "c", 0, 0.0, 0.0, 0.0)]


CROWD = "obs_id string, scene int, category string, viewpoint long, lx double, ly double, lz double"


def test_pairs_are_counted_without_making_them(spark, monkeypatch):
    from navspark.operators import ops

    df, dims = spark.createDataFrame(_crowd(), CROWD), ("lx", "ly", "lz")
    want = ops.proximity_join(df, df, 0.7, ["scene", "category"], dims).groupBy("l_scene").count().where("l_scene is not null").collect()
    visits, made = ops._visits, []
    monkeypatch.setattr(ops, "_visits", lambda rows, *a: made.append(rows.count()) or visits(rows, *a))
    got = ops.proximity_counts(df, 0.7, ["scene", "category"], ["scene"], dims).collect()
    assert {(r.scene, r.n) for r in got} == {(r.l_scene, r["count"]) for r in want}
    assert made[0] <= 180  # places of the two scenes, not rows


@pytest.mark.parametrize("algo", ["components", "greedy"])
def test_merging_within_tasks_equals_merging_across_them(spark, monkeypatch, algo):
    from navspark.operators import ops

    df = spark.createDataFrame(_crowd(), CROWD)
    monkeypatch.setattr(ops, "proximity_pairs", None)
    monkeypatch.setattr(V, "proximity_pairs", None)  # no pair is made for keys that fit a task
    one = {r.obs_id: r.cluster_id for r in V.merge_views(df, 0.7, algo).collect()}
    monkeypatch.undo()
    monkeypatch.setattr(ops, "LOCAL", 10)
    assert {r.obs_id: r.cluster_id for r in V.merge_views(df, 0.7, algo).collect()} == one and len(one) == 303


def test_stored_tables_and_what_they_shuffled_are_deleted(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(session, "shared_folder", lambda s: f"file://{tmp_path}")
    rows = spark.range(1000).selectExpr("id % 7 as k", "md5(string(id)) as s", "if(id = 3, null, id / 3.0) as x")
    with session.tables():
        one = session.stored(rows)
        with session.tables():
            two = session.stored(one.groupBy("k").agg(F.count("*").alias("n")))
            assert sorted(map(tuple, two.collect())) == sorted(map(tuple, rows.groupBy("k").count().collect()))
            assert len(list((tmp_path / "tables").iterdir())) == 2
        assert len(list((tmp_path / "tables").iterdir())) == 1
        assert sorted(map(tuple, one.collect()), key=str) == sorted(map(tuple, rows.collect()), key=str) and one.columns == rows.columns
    assert not list((tmp_path / "tables").iterdir())


def test_the_report_of_merged_views_leaves_no_tables(spark, tmp_path, monkeypatch):
    """No table of rows stays: the tables of each way of merging are gone when its report is made."""
    from navspark.plans import perception_queries as Q

    rows = spark.range(20_000).selectExpr(
        "md5(string(id)) as obs_id", "int(id % 3) as scene", "concat('c', id % 5) as category", "id % 49 as viewpoint", "id % 900 as part_key",
        "double(id % 900 % 30) as lx", "double(id % 900 div 30) as ly", "0.05 * (id % 7) as lz",
    ).withColumn("lz", F.col("lz").cast("double"))
    monkeypatch.setattr(Q, "_lifted", lambda s, sf: rows)
    folder = tmp_path / "shared"
    monkeypatch.setattr(session, "shared_folder", lambda s: f"file://{folder}")
    monkeypatch.setattr(Q, "kept", lambda df: spark.createDataFrame(df.collect(), df.schema))
    got = {r.algo: r for r in Q.inv_components(spark, "").collect()}
    assert set(got) == {"cell", "greedy", "components"}
    assert got["components"].n_supported == 900 and got["components"].n_found == got["components"].n_accepted == got["components"].n_right
    assert not list((folder / "tables").iterdir())

import math

import numpy as np
import pytest
from support import SF_SMOKE
from pyspark.sql import functions as F

from navspark.operators import grpo as O
from navspark.operators import metrics as M
from navspark.operators import rollouts as R
from navspark.operators import taxonomy as X
from navspark.sources import carriers as C
from navspark.sources import published as PUB


def rewards(spark, rows):
    return spark.createDataFrame(rows, "seed_id long, episode_id long, reward double")


def test_advantages(spark):
    rows = [(1, i, float(i)) for i in range(8)] + [(2, 10 + i, 5.0) for i in range(8)] + [(3, 30, 9.0)]
    a = {r.episode_id: r.adv for r in O.group_advantage(rewards(spark, rows)).collect()}
    x = np.arange(8.0)
    assert np.allclose([a[i] for i in range(8)], (x - x.mean()) / (x.std() + 1e-6))
    assert all(a[10 + i] == 0 for i in range(8)) and a[30] == 0
    b = {r.episode_id: r.adv for r in O.group_advantage(rewards(spark, [(s, e, r + 100) for s, e, r in rows])).collect()}
    assert all(a[k] == pytest.approx(b[k], abs=1e-9) for k in a)


def test_loss_terms(spark):
    rng = np.random.default_rng(1)
    t = rng.normal(-1, 0.4, (200, 3))
    adv = rng.normal(size=200)
    df = spark.createDataFrame([(*map(float, a), float(b)) for a, b in zip(t, adv, strict=True)], "lp_new double, lp_old double, lp_ref double, adv double")
    r = O.grpo_loss(df).first()
    ratio = np.exp(t[:, 0] - t[:, 1])
    d = t[:, 2] - t[:, 0]
    sur, k3 = np.minimum(ratio * adv, np.clip(ratio, 0.8, 1.2) * adv).mean(), (np.exp(d) - 1 - d).mean()
    assert (r.surrogate, r.kl, r.loss) == pytest.approx((sur, k3, -sur + 0.01 * k3))
    assert r.clip_frac == pytest.approx(((ratio < 0.8) | (ratio > 1.2)).mean())
    assert (np.exp(d) - 1 - d >= 0).all()


def test_dtw_against_the_plain_recursion():
    rng = np.random.default_rng(2)
    for _ in range(20):
        a, b = rng.normal(size=(rng.integers(1, 9), 2)), rng.normal(size=(rng.integers(1, 9), 2))
        acc = np.full((len(a) + 1, len(b) + 1), np.inf)
        acc[0, 0] = 0
        for i in range(len(a)):
            for j in range(len(b)):
                acc[i + 1, j + 1] = math.dist(a[i], b[j]) + min(acc[i, j], acc[i, j + 1], acc[i + 1, j])
        assert R.dtw(a, b) == pytest.approx(acc[-1, -1])
    assert R.dtw(a, a) == 0


def test_instruction_reward_on_the_smoke_tables(spark):
    s = R.scored_rollouts(C.v_rollouts(spark, SF_SMOKE), C.v_path(spark, SF_SMOKE), 3.0, True)
    rows = R.reward_instruction(s).limit(200).collect()
    for r in rows:
        want = (1 + r.ndtw) * r.success + math.exp(-max(r.d_t, 2) ** 2 / 9) - 0.25 * r.timeout
        assert r.reward == pytest.approx(want) and 0 < r.ndtw <= 1 and (r.oracle or not r.success)


def steps(spark, rows):
    return spark.createDataFrame(rows, "episode_id long, t int, n_steps int, visible boolean, collision boolean, stop boolean, stuck boolean, turn_rad double, range_m double, bearing_rad double")


def test_early_end_does_not_pay(spark):
    good = [(1, t, 300, True, False, False, False, 0.0, 2.0, 0.0) for t in range(1, 301)]
    crash = [(2, t, 10, True, t == 10, False, False, 0.0, 2.0, 0.0) for t in range(1, 11)]
    s = steps(spark, good + crash)
    full = {r.episode_id: r for r in R.tracking_episodes(s).collect()}
    plain = {r.episode_id: r for r in R.tracking_episodes(s, horizon="executed").collect()}
    assert full[2].horizon == 300 and full[1].horizon == 300
    assert full[2].reward - (1 - 0.5) == pytest.approx(0.7 * 10 / 300)
    assert plain[2].reward - (1 - 0.5) == pytest.approx(0.7) == plain[1].reward - 1


def test_decisions_keep_events(spark):
    rows = [(1, t, 100, True, False, t == 50, t in (20, 21, 80), 0.0, 2.0, 0.0) for t in range(1, 101)]
    rows += [(2, t, 5, True, False, False, False, 0.0, 2.0, 0.0) for t in range(1, 6)]
    s = steps(spark, rows)
    kept = O.select_decisions(s, 24, 0.4)
    by = {}
    for r in kept.collect():
        by.setdefault(r.episode_id, set()).add(r.t)
    assert {1, 100, 50, 20, 21, 80, 19, 22, 49, 51, 79, 81} <= by[1] and len(by[1]) == 24
    assert by[2] == {1, 2, 3, 4, 5}
    a = O.event_recall(s, kept, 0.4).first().event_recall
    b = O.event_recall(s, O.select_uniform(s, 24, 0.4), 0.4).first().event_recall
    assert a == 1 > b


def test_mandatory_beyond_the_cap(spark):
    rows = [(1, t, 50, True, False, False, True, 0.0, 2.0, 0.0) for t in range(1, 51)]
    kept = [r.t for r in O.select_decisions(steps(spark, rows), 10, 0.4).collect()]
    assert len(kept) == 10 and {1, 50} <= set(kept)


def test_iteration_has_distinct_scenes_and_256_episodes(spark):
    rows = [(s, s % 60, "mixed", 4, 0.5) for s in range(400)]
    pool = spark.createDataFrame(rows, "seed_id long, scene_id int, bin string, n_succ long, std_r double")
    d = O.draw_iteration(pool).collect()
    assert len(d) == 32 == len({r.scene_id for r in d}) and 32 * O.GROUP == 256


def test_routing_keeps_groups_together(spark):
    r = spark.createDataFrame([(i, i % 37, i // 8) for i in range(800)], "episode_id long, scene_id int, seed_id long")
    loads = {(x.policy): x.s for x in O.route_loads(r, 8).groupBy("policy").agg(F.sum("loads").alias("s")).collect()}
    assert loads["scene"] == 37 < loads["robin"]


# --- printed numbers ----------------------------------------------------------------------


def test_macro_averages(spark):
    m = {r.method: r.macro for r in M.macro_average(PUB.frame(spark).where("family = 'er'")).collect()}
    assert {k: round(v + 1e-9, 1) for k, v in m.items()} == {"backbone_a": 63.1, "backbone_b": 60.8, "reasoner_8b": 62.8, "ours": 67.4}
    part = PUB.frame(spark).where("family = 'er'").withColumn("value", F.when((F.col("method") == "ours") & (F.col("setting") == "points"), None).otherwise(F.col("value")))
    assert {r.method: r.macro for r in M.macro_average(part).collect()}["ours"] is None


def test_ranks_share_ties_and_skip_missing(spark):
    df = spark.createDataFrame([("a", "f", "s", "SR", 3.0), ("b", "f", "s", "SR", 2.0), ("c", "f", "s", "SR", 2.0), ("d", "f", "s", "SR", None), ("a", "f", "s", "NE", 3.0), ("b", "f", "s", "NE", 2.0)], "method string, family string, setting string, metric string, value double")
    got = {(r.method, r.metric): r["rank"] for r in M.rank_marks(df).collect()}
    assert got == {("a", "SR"): 1, ("b", "SR"): 2, ("c", "SR"): 2, ("a", "NE"): 2, ("b", "NE"): 1}
    marks = [r["rank"] for r in M.rank_marks(PUB.frame(spark).where("family = 'er'")).where("method = 'ours'").collect()]
    assert sorted(marks) == [1] * 4 + [2] * 4


def test_gains(spark):
    g = {(r.setting, r.metric): r for r in M.gain_table(PUB.frame(spark).where("family = 'mono'"), "ours").collect()}
    sr, ne = g[("instr_1", "SR")], g[("instr_1", "NE")]
    assert round(sr.gain_abs, 1) == 1.6 and round(sr.gain_rel, 1) == 2.4 and round(ne.gain_rel, 1) == 3.5


def test_ablation_means(spark):
    p = PUB.frame(spark).where("family = 'ablation'")
    a = {r.metric: r for r in M.ablation_table(p, "init_backbone", "ours_full").collect()}
    b = {r.metric: r for r in M.ablation_table(p, "no_pointing", "ours_full").collect()}
    got = (a["SR"].mean_base, a["SR"].mean_variant, b["SR"].mean_base, a["SPL"].mean_base, a["SPL"].mean_variant, b["SPL"].mean_base)
    assert got == pytest.approx((60.46, 63.0, 54.7, 38.78, 39.86, 34.29), abs=0.0051)


def test_printed_matrix_margins():
    assert sum(PUB.MATRIX_ROWS) == sum(PUB.MATRIX_COLUMNS) == 1097
    wins = [round(r * n / 100) for r, n in zip(PUB.ROW_SR, PUB.MATRIX_ROWS, strict=True)]
    assert sum(wins) == 479 and round(100 * 479 / 1097, 2) == 43.66
    assert round(max(PUB.ROW_SR) - min(PUB.ROW_SR), 1) == 31.9 and round(max(PUB.COLUMN_SR) - min(PUB.COLUMN_SR), 1) == 20.5


def test_matrix_of_a_printed_size(spark):
    rows = []
    for i, n in enumerate(PUB.MATRIX_ROWS):
        wins = round(PUB.ROW_SR[i] * n / 100)
        rows += [(len(rows) + j, X.SCENES[i], X.INSTRUCTIONS[j % 5], i, j < wins) for j in range(n)]
    m = X.matrix_sr(spark.createDataFrame(rows, "episode_id long, scene_type string, instr_type string, scene_id int, success boolean"))
    top = m.where("level = 3").first()
    assert (top.n, top.n_success) == (1097, 479)
    assert round(X.spans(m).first().scene_span, 1) == 31.9


def test_labels_and_splits(spark):
    e = spark.createDataFrame([(1, 7), (2, 8)], "episode_id long, scene_id int")
    m = spark.createDataFrame([(7, "house")], "scene_id int, scene_type string")
    with pytest.raises(ValueError):
        X.label_scene(e, m)
    a, b = spark.createDataFrame([("x",), ("y",)], "scene string"), spark.createDataFrame([("z",)], "scene string")
    X.assert_disjoint(a, b)
    with pytest.raises(ValueError):
        X.assert_disjoint(a, a.limit(1))
    s = X.split_stats(spark.createDataFrame([("train", str(i % 1683)) for i in range(53090)], "split string, scene string")).first()
    assert round(s.per_scene, 1) == 31.5 and round(1097 / 210, 1) == 5.2


def test_proofs(spark):
    rows = [("a", 1, "chair", 0.0, 0.0, 0.0, 5.0), ("b", 1, "chair", 9.0, 0.0, 0.0, 7.0), ("c", 1, "lamp", 0.5, 0.0, 0.0, 1.0), ("d", 1, "chair", 20.0, 0.0, 0.0, 7.0)]
    inst = spark.createDataFrame(rows, "target string, scene int, category string, x double, y double, z double, size double")
    assert {r.target for r in X.prove_base(inst).where("is_base").collect()} == {"c"}
    assert [(r.target, r.anchor) for r in X.prove_relation(inst, 2.0).collect()] == [("a", "c")]
    assert [r.target for r in X.prove_extremum(inst, "size", True).collect()] == ["a"]
    assert X.prove_extremum(inst, "size", False).count() == 0  # a tie for the largest
    assert {r.target: r["rank"] for r in X.prove_ordinal(inst, "x", 1.0).collect()} == {"a": 1, "b": 2, "d": 3, "c": 1}
    flags = spark.createDataFrame([(True, False, True, False, False), (False, False, False, False, False)], "is_base boolean, is_direction boolean, is_relation boolean, is_extremum boolean, is_ordinal boolean")
    assert [r.instr_type for r in X.label_instruction(flags).collect()] == ["relation", None]


def test_wilson_and_diagnostic(spark):
    w = spark.range(1).select(M.wilson(F.lit(37.0), F.lit(50.0)).alias("w")).first().w
    assert w.low == pytest.approx(0.604, abs=2e-3) and w.high == pytest.approx(0.841, abs=2e-3)
    df = spark.createDataFrame([(True, 2.5, True, 10, True), (True, 2.5, False, 10, True), (True, 1.0, False, 301, True), (True, 1.0, False, 300, False), (False, 0.0, False, 1, True)], "stop_called boolean, d_t double, out boolean, n int, in_view boolean")
    assert [r.s for r in df.select(M.diagnostic_success(F.col("out")).alias("s")).collect()] == [True, False, False, False, False]


def test_diagnostic_looks_at_the_final_heading(spark):
    from navspark.plans import policy_queries as P

    turn = {r.l_orderkey: r.h for r in C.load(spark, SF_SMOKE, "lineitem").groupBy("l_orderkey").agg(F.sum((F.col("l_discount") - 0.05) * 10).alias("h")).collect()}
    got = P.diagnostic(spark, SF_SMOKE).select("episode_id", "in_view", "success").collect()
    clear = [(r, math.cos(turn.get(r.episode_id, 0.0)) - 0.5) for r in got if abs(math.cos(turn.get(r.episode_id, 0.0)) - 0.5) > 1e-6]
    assert all(r.in_view == (c > 0) for r, c in clear) and any(c < 0 for _, c in clear)
    assert not any(r.success and not r.in_view for r in got)

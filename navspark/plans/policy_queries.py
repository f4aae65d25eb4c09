"""Rewards, group-relative optimisation, metrics and reports."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import PI, r6, r6_sql, uniform01, uniform01_sql, wrap_angle
from navspark.operators import grpo as O
from navspark.operators import metrics as M
from navspark.operators import rollouts as R
from navspark.operators import taxonomy as X
from navspark.operators import tokenlm as T
from navspark.plans.base import query
from navspark.plans.perception_queries import _WAY
from navspark.sources import carriers as C

# --- rewards -----------------------------------------------------------------------------

_B = "CASE WHEN abs(bearing_rad) <= 0.14 THEN 1.0::DOUBLE ELSE exp(-((abs(bearing_rad) - 0.14::DOUBLE) ** 2) / (2 * 0.35::DOUBLE * 0.35::DOUBLE)) END"
_D = "CASE WHEN range_m < 1.5 THEN exp(-((1.5::DOUBLE - range_m) ** 2) / (2 * 0.35::DOUBLE * 0.35::DOUBLE)) WHEN range_m > 3.0 THEN exp(-((range_m - 3.0::DOUBLE) ** 2) / 2.0::DOUBLE) ELSE 1.0::DOUBLE END"
_TRACK = f"""SELECT *, CAST(success AS INT) - 0.5::DOUBLE * CAST(collision AS INT) + (0.7::DOUBLE * sum_q + 0.3::DOUBLE * sum_m) / horizon AS reward, CAST(success AS INT) - 0.5::DOUBLE * CAST(collision AS INT) + (0.7::DOUBLE * sum_q + 0.3::DOUBLE * sum_m) / t_n AS reward_executed FROM (
  SELECT *, CASE WHEN early THEN greatest(t_n, 300) ELSE t_n END AS horizon FROM (
   SELECT s.episode_id, count(*) AS t_n, sum(CASE WHEN visible THEN ({_B}) * ({_D}) ELSE 0.0::DOUBLE END) AS sum_q, sum(coalesce(m, 0.0::DOUBLE)) AS sum_m, bool_or(collision) AS collision,
    arg_max(visible AND range_m BETWEEN 1 AND 3 AND abs(bearing_rad) <= 1.0471975511965976 AND cos(target_rad - bearing_rad) > 0, s.t) AS success, arg_max(NOT visible OR collision, s.t) AS early, avg(CAST(visible AND range_m BETWEEN 1 AND 3 AS INT)) AS tracked
    FROM v_steps s LEFT JOIN trk_match p ON p.episode_id = s.episode_id AND p.t = s.t GROUP BY s.episode_id))"""
#: The plan that a step emits repeats its own motion ten times; the privileged plan is what followed.
TRACK_VIEWS = {
    "trk_true": _WAY.format(keys="episode_id, t", rows="v_chunk_rows"),
    "trk_held": "SELECT c.episode_id, c.t, c.i, s.fwd_m AS dx, 0.0::DOUBLE AS dy, s.turn_rad AS dth FROM v_chunk_rows c JOIN v_steps s ON s.episode_id = c.episode_id AND s.t = c.t",
    "trk_plan": _WAY.format(keys="episode_id, t", rows="trk_held"),
    "trk_match": "SELECT a.episode_id, a.t, greatest(0.0::DOUBLE, 1 - avg(sqrt((a.x - b.x) ** 2 + (a.y - b.y) ** 2))) AS m FROM trk_true a JOIN trk_plan b ON a.episode_id = b.episode_id AND a.t = b.t AND a.i = b.i GROUP BY a.episode_id, a.t",
    "track": _TRACK,
}


def _tracking(spark, sf, horizon):
    e = R.tracking_episodes(C.planned_steps(spark, sf), horizon=horizon)
    return e.select("episode_id", "t_n", F.col("horizon").cast("long").alias("horizon"), "success", "collision", r6("reward").alias("reward"))


@query("rew_tracking", f"SELECT episode_id, t_n, CAST(horizon AS BIGINT) AS horizon, success, collision, {r6_sql('reward')} AS reward FROM track", **TRACK_VIEWS)
def rew_tracking(spark, sf):
    return _tracking(spark, sf, "full")


@query("rew_tracking_executed", f"SELECT episode_id, t_n, CAST(t_n AS BIGINT) AS horizon, success, collision, {r6_sql('reward_executed')} AS reward FROM track", **TRACK_VIEWS)
def rew_tracking_executed(spark, sf):
    return _tracking(spark, sf, "executed")


_MEAS = """SELECT episode_id, arg_max(d, i) AS d_t, min(d) AS min_d, coalesce(sum(s), 0.0::DOUBLE) AS path_len, any_value(sqrt(gx ** 2 + gy ** 2)) AS d_0, max(n) AS n FROM (
  SELECT *, sqrt((x - gx) ** 2 + (y - gy) ** 2) AS d, sqrt((x - lag(x) OVER w) ** 2 + (y - lag(y) OVER w) ** 2) AS s FROM v_path WINDOW w AS (PARTITION BY episode_id ORDER BY i)) GROUP BY episode_id"""


def _scored_sql(radius: float) -> str:
    return f"SELECT r.*, m.d_t, m.min_d, m.path_len, m.d_0, m.n, round(m.min_d, 9) <= {radius} AS oracle, stop_called AND round(m.d_t, 9) <= {radius} AS success, CASE WHEN greatest(m.d_0, m.path_len) > 0 THEN m.d_0 / greatest(m.d_0, m.path_len) ELSE 1.0::DOUBLE END AS efficiency FROM v_rollouts r JOIN meas m ON r.episode_id = m.episode_id"


_OBJ = "SELECT *, (1 + 0.25::DOUBLE * efficiency) * CAST(success AS INT) AS term1, 0.25::DOUBLE * exp(-(greatest(d_t, 1.0::DOUBLE) ** 2) / 9.0::DOUBLE) AS term2 FROM scored1"
OBJ_VIEWS = {"meas": _MEAS, "scored1": _scored_sql(1.0), "obj": _OBJ}
VLN_VIEWS = {"meas": _MEAS, "scored3": _scored_sql(3.0)}


def scored(spark, sf, radius, with_ndtw=False):
    return R.scored_rollouts(C.v_rollouts(spark, sf), C.v_path(spark, sf), radius, with_ndtw)


def _reward_cols(df):
    return df.select("episode_id", *[r6(c).alias(c) for c in ("d_t", "term1", "term2", "term3", "reward")])


@query("rew_object", f"SELECT episode_id, {r6_sql('d_t')} AS d_t, {r6_sql('term1')} AS term1, {r6_sql('term2')} AS term2, 0.0::DOUBLE AS term3, {r6_sql('term1 + term2')} AS reward FROM obj", **OBJ_VIEWS)
def rew_object(spark, sf):
    return _reward_cols(R.reward_object(scored(spark, sf, 1.0)))


#: Dynamic time warping, a row of the cost matrix at a time: inside a row the best way to a cell enters the row at
#: some cell before it and adds the costs from there on, so a running minimum replaces the cell-by-cell recursion.
WARP_VIEWS = {
    **VLN_VIEWS,
    "warp_cost": "SELECT a.episode_id, a.i, b.i AS j, sqrt((a.x - b.rx) ** 2 + (a.y - b.ry) ** 2) AS c FROM v_path a JOIN v_path b ON a.episode_id = b.episode_id",
    "warp_walk": """SELECT episode_id, i, j, sum(c) OVER (PARTITION BY episode_id ORDER BY j) AS acc FROM warp_cost WHERE i = 0
  UNION ALL SELECT episode_id, i, j, p + min(m - p + c) OVER (PARTITION BY episode_id ORDER BY j) FROM (
   SELECT k.episode_id, k.i, k.j, k.c, sum(k.c) OVER e AS p, least(w.acc, coalesce(lag(w.acc) OVER e, w.acc)) AS m FROM warp_walk w JOIN warp_cost k ON k.episode_id = w.episode_id AND k.i = w.i + 1 AND k.j = w.j WINDOW e AS (PARTITION BY k.episode_id ORDER BY k.j))""",
    "warped": "SELECT s.*, exp(-w.acc / ((s.n + 1) * 3.0::DOUBLE)) AS ndtw FROM scored3 s JOIN warp_walk w ON w.episode_id = s.episode_id AND w.i = s.n AND w.j = s.n",
    "vln": "SELECT *, (1 + ndtw) * CAST(success AS INT) AS term1, exp(-(greatest(d_t, 2.0::DOUBLE) ** 2) / 9.0::DOUBLE) AS term2, -0.25::DOUBLE * CAST(timeout AS INT) AS term3 FROM warped",
}


@query("rew_instruction", f"SELECT episode_id, {r6_sql('d_t')} AS d_t, {r6_sql('term1')} AS term1, {r6_sql('term2')} AS term2, {r6_sql('term3')} AS term3, {r6_sql('term1 + term2 + term3')} AS reward FROM vln", **WARP_VIEWS)
def rew_instruction(spark, sf):
    """With the warped-path term."""
    return _reward_cols(R.reward_instruction(scored(spark, sf, 3.0, True)))


@query(
    "rew_instruction_terms",
    f"SELECT episode_id, {r6_sql('d_t')} AS d_t, success, {r6_sql('exp(-(greatest(d_t, 2.0::DOUBLE) ** 2) / 9.0::DOUBLE)')} AS term2, {r6_sql('-0.25::DOUBLE * CAST(timeout AS INT)')} AS term3 FROM scored3",
    **VLN_VIEWS,
)
def rew_instruction_terms(spark, sf):
    s = R.reward_instruction(scored(spark, sf, 3.0).withColumn("ndtw", F.lit(0.0)))
    return s.select("episode_id", r6("d_t").alias("d_t"), "success", r6("term2").alias("term2"), r6("term3").alias("term3"))


# --- group-relative optimisation -----------------------------------------------------------

_ADV = """SELECT *, CASE WHEN cnt > 1 AND round(sd, 9) > 0 THEN (reward - m) / (sd + 1e-6) ELSE 0.0::DOUBLE END AS adv FROM (
  SELECT *, avg(reward) OVER s AS m, stddev_pop(reward) OVER s AS sd, count(*) OVER s AS cnt FROM (SELECT episode_id, seed_id, g, scene_id, success, term1 + term2 AS reward FROM obj WHERE g <= 8) WINDOW s AS (PARTITION BY seed_id))"""


def rewarded(spark, sf):
    return R.reward_object(scored(spark, sf, 1.0)).where(F.col("g") <= O.GROUP)


@query("grpo_adv", f"SELECT seed_id, g, {r6_sql('reward')} AS reward, {r6_sql('adv', 4)} AS adv FROM adv", adv=_ADV, **OBJ_VIEWS)
def grpo_adv(spark, sf):
    a = O.group_advantage(rewarded(spark, sf))
    return a.select("seed_id", "g", r6("reward").alias("reward"), r6("adv", 4).alias("adv"))


_LM = {
    "toks": f"SELECT episode_id, t, event_type AS token, coalesce(lag(event_type) OVER (PARTITION BY episode_id ORDER BY t), '<s>') AS ctx, {uniform01_sql('episode_id', salt='half')} AS u FROM v_steps",
    "toks_x": "SELECT t.*, m.name FROM toks t JOIN (VALUES ('new', 0.0, 0.5), ('old', 0.0, 1.0), ('ref', 0.5, 1.0)) AS m(name, lo, hi) ON t.u >= m.lo AND t.u < m.hi",
    "pairs": "SELECT name, ctx, token, count(*) AS n FROM toks_x GROUP BY ALL",
    "ctxs": "SELECT name, ctx, sum(n) AS n_ctx FROM pairs GROUP BY ALL",
    "vocs": "SELECT name, count(DISTINCT token) AS nv FROM pairs GROUP BY ALL",
    "lps": "SELECT t.episode_id, t.t, v.name, ln((coalesce(p.n, 0) + 1.0::DOUBLE) / (coalesce(c.n_ctx, 0) + 1.0::DOUBLE * (v.nv + 1))) AS lp FROM toks t CROSS JOIN vocs v LEFT JOIN pairs p ON p.name = v.name AND p.ctx = t.ctx AND p.token = t.token LEFT JOIN ctxs c ON c.name = v.name AND c.ctx = t.ctx",
    "wide": "SELECT episode_id, t, max(lp) FILTER (WHERE name = 'new') AS lp_new, max(lp) FILTER (WHERE name = 'old') AS lp_old, max(lp) FILTER (WHERE name = 'ref') AS lp_ref FROM lps GROUP BY ALL",
    "tadv": "SELECT episode_id, CASE WHEN sd > 0 THEN (reward - m) / (sd + 1e-6) ELSE 0.0::DOUBLE END AS adv FROM (SELECT episode_id, reward, avg(reward) OVER (PARTITION BY episode_id % 10) AS m, stddev_pop(reward) OVER (PARTITION BY episode_id % 10) AS sd FROM track)",
    **TRACK_VIEWS,
}


def token_contexts(spark, sf):
    """(episode, t, token, ctx, u, one): each token after the one before it; u deals episodes to halves."""
    seq = C.v_steps(spark, sf).select("episode_id", "t", F.col("event_type").alias("token"))
    rows = seq.withColumn("ctx", F.coalesce(F.lag("token").over(W.partitionBy("episode_id").orderBy("t")), F.lit("<s>"))).withColumn("u", uniform01("episode_id", salt="half"))
    return rows.withColumn("one", F.lit(1))


def token_logprobs(spark, sf):
    """(episode, t, lp_new, lp_old, lp_ref): the count model fitted on one half, on all, and on the other half."""
    rows = token_contexts(spark, sf)
    out = rows.select("episode_id", "t", "token", "ctx", "one")
    for name, part in (("lp_new", rows.where("u < 0.5")), ("lp_old", rows), ("lp_ref", rows.where("u >= 0.5"))):
        out = T.score(out, T.fit_token_lm(part, ("one",)), ("one",), name=name)
    return out


@query(
    "grpo_loss",
    f"""SELECT {r6_sql("-avg(sur) + 0.01::DOUBLE * avg(k3)", 5)} AS loss, {r6_sql("avg(k3)", 5)} AS kl, {r6_sql("avg(CAST(ratio < 0.8 OR ratio > 1.2 AS INT))", 5)} AS clip_frac FROM (
  SELECT ratio, least(ratio * adv, greatest(0.8::DOUBLE, least(1.2::DOUBLE, ratio)) * adv) AS sur, exp(lp_ref - lp_new) - 1 - (lp_ref - lp_new) AS k3 FROM (SELECT *, exp(lp_new - lp_old) AS ratio FROM wide JOIN tadv USING (episode_id)))""",
    **_LM,
)
def grpo_loss(spark, sf):
    e = R.tracking_episodes(C.planned_steps(spark, sf)).withColumn("seed_id", F.col("episode_id") % 10)
    adv = O.group_advantage(e)
    loss = O.grpo_loss(O.spread_advantage(token_logprobs(spark, sf), adv))
    return loss.select(r6("loss", 5).alias("loss"), r6("kl", 5).alias("kl"), r6("clip_frac", 5).alias("clip_frac"))


@query(
    "grpo_kl_estimators",
    f"SELECT {r6_sql('avg(lp_new - lp_ref)')} AS k1, {r6_sql('avg((lp_ref - lp_new) ** 2 / 2)')} AS k2, {r6_sql('avg(exp(lp_ref - lp_new) - 1 - (lp_ref - lp_new))')} AS k3 FROM wide",
    **_LM,
)
def grpo_kl_estimators(spark, sf):
    t = token_logprobs(spark, sf)
    return t.agg(*[r6(F.avg(O.kl(F.col("lp_new"), F.col("lp_ref"), how))).alias(how) for how in ("k1", "k2", "k3")])


@query(
    "grpo_kl_exact",
    f"""SELECT {r6_sql("sum(share * p * (lp - lq))")} AS kl FROM (SELECT c.share, exp(n.lp) AS p, n.lp, r.lp AS lq FROM every n JOIN every r ON n.ctx = r.ctx AND n.token = r.token AND n.name = 'new' AND r.name = 'ref'
  JOIN (SELECT ctx, count(*) / sum(count(*)) OVER () AS share FROM toks GROUP BY ctx) c ON c.ctx = n.ctx)""",
    every="""SELECT v.name, x.ctx, y.token, ln((coalesce(p.n, 0) + 1.0::DOUBLE) / (coalesce(c.n_ctx, 0) + 1.0::DOUBLE * (v.nv + 1))) AS lp FROM vocs v CROSS JOIN (SELECT DISTINCT ctx FROM toks) x CROSS JOIN (SELECT DISTINCT token FROM toks) y
  LEFT JOIN pairs p ON p.name = v.name AND p.ctx = x.ctx AND p.token = y.token LEFT JOIN ctxs c ON c.name = v.name AND c.ctx = x.ctx""",
    **_LM,
)
def grpo_kl_exact(spark, sf):
    """The divergence summed over the whole vocabulary of each context, weighted by how often it occurs."""
    rows = token_contexts(spark, sf)
    every = rows.select("one", "ctx").distinct().join(rows.select("one", "token").distinct(), "one")
    p, q = (T.score(every, T.fit_token_lm(rows.where(part), ("one",)), ("one",)) for part in ("u < 0.5", "u >= 0.5"))
    weight = rows.groupBy("one", "ctx").agg(F.count("*").alias("n_ctx"))
    return T.kl_exact(p, q, weight, ("one",)).select(r6("kl").alias("kl"))


_BINS = """SELECT seed_id, n_succ, sd, scene_id, CASE WHEN n_succ = 8 THEN 'always' WHEN n_succ = 0 THEN 'never' ELSE 'mixed' END AS bin FROM (
  SELECT seed_id, count(*) AS n, CAST(sum(CAST(success AS INT)) AS BIGINT) AS n_succ, stddev_pop(reward) AS sd, min(scene_id) AS scene_id FROM adv GROUP BY seed_id) WHERE n = 8"""
_POOL_U = uniform01_sql("seed_id", salt="pool")
POOL_VIEWS = {**OBJ_VIEWS, "adv": _ADV, "bins": _BINS, "pool": f"SELECT * FROM bins WHERE bin = 'mixed' OR {_POOL_U} < 0.1"}


def bins(spark, sf):
    return O.bin_difficulty(rewarded(spark, sf))


@query("pool_bins", "SELECT bin, count(*) AS n FROM bins GROUP BY bin", **POOL_VIEWS)
def pool_bins(spark, sf):
    return bins(spark, sf).groupBy("bin").agg(F.count("*").alias("n"))



@query(
    "pool_compare",
    " UNION ALL ".join(
        f"SELECT '{name}' AS pool, count(*) AS n, {r6_sql(chr(39).join(['avg(CASE WHEN bin = ', 'mixed', ' THEN 1.0 ELSE 0.0 END)']))} AS usable_share, {r6_sql('avg(CASE WHEN sd > 1e-9 THEN 1.0 ELSE 0.0 END)')} AS graded_share FROM {src}"
        for name, src in (("mixed", "pool"), ("uniform", f"(SELECT * FROM bins WHERE {_POOL_U} < 0.5)"), ("failures", "(SELECT * FROM bins WHERE n_succ < 8)"))
    ),
    **POOL_VIEWS,
)
def pool_compare(spark, sf):
    b = bins(spark, sf)
    rep = O.pool_report({"mixed": O.build_pool(b), "uniform": O.pool_uniform(b, 0.5), "failures": O.pool_failures_only(b)})
    return rep.select("pool", "n", r6("usable_share").alias("usable_share"), r6("graded_share").alias("graded_share"))


@query(
    "draw_iter",
    f"""SELECT d.seed_id, d.scene_id, r.g, r.episode_id FROM (SELECT seed_id, scene_id FROM (SELECT *, row_number() OVER (PARTITION BY scene_id ORDER BY u, seed_id) AS rn FROM (SELECT *, {uniform01_sql("seed_id", salt="iter")} AS u FROM pool)) WHERE rn = 1 ORDER BY u, seed_id LIMIT 32) d
  JOIN v_rollouts r ON r.seed_id = d.seed_id AND r.g <= 8""",
    **POOL_VIEWS,
)
def draw_iter(spark, sf):
    d = O.draw_iteration(O.build_pool(bins(spark, sf))).select("seed_id", "scene_id")
    r = C.v_rollouts(spark, sf).where(F.col("g") <= O.GROUP).select("seed_id", "g", "episode_id")
    return d.join(r, "seed_id").select("seed_id", "scene_id", "g", "episode_id")


@query(
    "route_loads",
    f"SELECT 'scene' AS policy, CAST(floor({uniform01_sql('scene_id', salt='route')} * 8) AS INT) AS worker, count(*) AS n, count(DISTINCT scene_id) AS loads FROM v_rollouts GROUP BY ALL UNION ALL SELECT 'robin', CAST(episode_id % 8 AS INT), count(*), count(DISTINCT scene_id) FROM v_rollouts GROUP BY ALL",
)
def route_loads(spark, sf):
    return O.route_loads(C.v_rollouts(spark, sf), 8)


_FLAGS = """SELECT *, CASE WHEN t = 1 OR t = n_steps THEN 0 WHEN ev THEN 1 WHEN near THEN 2 ELSE 3 END AS pr FROM (SELECT *, (coalesce(lag(ev) OVER w, false) OR coalesce(lead(ev) OVER w, false)) AND NOT ev AS near FROM (
  SELECT episode_id, t, n_steps, stop OR stuck OR collision OR abs(turn_rad) > 0.45 AS ev FROM v_steps) WINDOW w AS (PARTITION BY episode_id ORDER BY t))"""
_DEC = """SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY episode_id ORDER BY pr, t) AS r FROM (SELECT *, greatest(0, 24 - must) AS room FROM (
  SELECT *, sum(CAST(pr < 3 AS INT)) OVER (PARTITION BY episode_id) AS must, row_number() OVER (PARTITION BY episode_id, pr ORDER BY t) - 1 AS i, count(*) OVER (PARTITION BY episode_id, pr) AS m FROM flags))
  WHERE pr < 3 OR floor((i + 1) * room::DOUBLE / m) > floor(i * room::DOUBLE / m) OR room >= m) WHERE r <= 24"""


@query(
    "decisions",
    f"""SELECT 'stratified' AS mode, count(*) AS n_kept, {r6_sql("sum(CAST(ev AS INT)) / (SELECT sum(CAST(ev AS INT)) FROM flags)")} AS event_recall FROM dec UNION ALL
  SELECT 'uniform', count(*), {r6_sql("sum(CAST(ev AS INT)) / (SELECT sum(CAST(ev AS INT)) FROM flags)")} FROM flags WHERE n_steps <= 24 OR floor(t * 24::DOUBLE / n_steps) > floor((t - 1) * 24::DOUBLE / n_steps)""",
    flags=_FLAGS,
    dec=_DEC,
)
def decisions(spark, sf):
    s, out = C.v_steps(spark, sf), None
    for mode, kept in (("stratified", O.select_decisions(s, 24, 0.45)), ("uniform", O.select_uniform(s, 24, 0.45))):
        one = O.event_recall(s, kept, 0.45).select(F.lit(mode).alias("mode"), "n_kept", r6("event_recall").alias("event_recall"))
        out = one if out is None else out.unionByName(one)
    return out


# --- metric tables -------------------------------------------------------------------------


def _metric_sql(by: str, view: str) -> str:
    return f"SELECT {by} AS setting, {r6_sql('avg(d_t)')} AS ne, {r6_sql('avg(CAST(oracle AS INT))')} AS os, {r6_sql('avg(CAST(success AS INT))')} AS sr, {r6_sql('avg(CAST(success AS INT) * efficiency)')} AS spl FROM {view} GROUP BY 1"


def _metric(df, by):
    return df.groupBy(by.alias("setting")).agg(r6(M.navigation_error()).alias("ne"), r6(M.oracle_success()).alias("os"), r6(M.success_rate()).alias("sr"), r6(M.spl()).alias("spl"))


@query("m_vln", _metric_sql("setting", "scored3"), **VLN_VIEWS)
def m_vln(spark, sf):
    return _metric(scored(spark, sf, 3.0), F.col("setting"))


@query("m_vln_ndtw", f"SELECT setting, {r6_sql('avg(ndtw)')} AS ndtw FROM warped GROUP BY setting", **WARP_VIEWS)
def m_vln_ndtw(spark, sf):
    return scored(spark, sf, 3.0, True).groupBy("setting").agg(r6(M.mean_ndtw()).alias("ndtw"))


@query("m_obj", _metric_sql("setting", "scored1"), **OBJ_VIEWS)
def m_obj(spark, sf):
    return _metric(scored(spark, sf, 1.0), F.col("setting"))


_OPEN = "CASE WHEN instr_type IN ('1-URGENT', '2-HIGH') THEN 'seen' WHEN instr_type = '3-MEDIUM' THEN 'synonyms' ELSE 'unseen' END"


@query("m_ovon", _metric_sql(_OPEN, "scored1"), **OBJ_VIEWS)
def m_ovon(spark, sf):
    return _metric(scored(spark, sf, 1.0), F.expr(_OPEN))


@query(
    "m_evt",
    f"SELECT CASE WHEN episode_id % 2 = 0 THEN 'single' ELSE 'distractors' END AS setting, {r6_sql('avg(CAST(success AS INT))')} AS sr, {r6_sql('avg(tracked)')} AS tr, {r6_sql('avg(CAST(collision AS INT))')} AS cr FROM track GROUP BY 1",
    **TRACK_VIEWS,
)
def m_evt(spark, sf):
    e = R.tracking_episodes(C.v_steps(spark, sf))
    setting = F.when(F.col("episode_id") % 2 == 0, "single").otherwise("distractors")
    return e.groupBy(setting.alias("setting")).agg(r6(M.success_rate()).alias("sr"), r6(M.tracking_rate()).alias("tr"), r6(M.collision_rate()).alias("cr"))


#: A path's final heading is the sum of its turns, and all goals lie along +x of its end: a goal is in the 120 degree
#: view where that heading is within 60 degrees of +x.
_DIAG = f"""SELECT s.* REPLACE (s.stop_called AND round(s.d_t, 9) <= CASE WHEN s.scene_type = '{C.OUTDOOR}' THEN 3.0 ELSE 2.0 END AND s.n <= 300 AND coalesce(cos(w.h), 1.0::DOUBLE) >= 0.5::DOUBLE - 1e-9 AS success)
  FROM scored3 s LEFT JOIN turned w ON w.episode_id = s.episode_id"""
DIAG_VIEWS = {**VLN_VIEWS, "turned": "SELECT l_orderkey AS episode_id, sum((l_discount - 0.05::DOUBLE) * 10) AS h FROM lineitem GROUP BY l_orderkey", "diag": _DIAG}


def diagnostic(spark, sf):
    """Indoor and outdoor radii; the goal must be in the 120 degree view of the final frame.

    A goal at no distance counts as lying along +x, where the carrier puts all others.
    """
    last = C.v_path(spark, sf).where("i = n")
    off = wrap_angle(F.atan2(F.col("gy") - F.col("y"), F.col("gx") - F.col("x")) - F.col("heading"))
    view = last.select("episode_id", (F.round(F.abs(off), 9) <= round(PI / 3, 9)).alias("in_view"))
    s = scored(spark, sf, 3.0).join(view, "episode_id", "left")
    return s.withColumn("success", M.diagnostic_success(F.col("scene_type") == C.OUTDOOR))


@query("diag_overall", f"SELECT {r6_sql('avg(CAST(success AS INT))')} AS sr, {r6_sql('avg(CAST(success AS INT) * efficiency)')} AS spl, {r6_sql('avg(d_t)')} AS ne FROM diag", **DIAG_VIEWS)
def diag_overall(spark, sf):
    return diagnostic(spark, sf).agg(r6(M.success_rate()).alias("sr"), r6(M.spl()).alias("spl"), r6(M.navigation_error()).alias("ne"))


@query("diag_breakdown", f"SELECT scene_type, instr_type, count(*) AS n, {r6_sql('avg(CAST(success AS INT))')} AS sr FROM diag GROUP BY GROUPING SETS ((scene_type), (instr_type), ())", **DIAG_VIEWS)
def diag_breakdown(spark, sf):
    return M.breakdown(diagnostic(spark, sf)).select("scene_type", "instr_type", "n", r6("sr").alias("sr"))


_CUBE = "SELECT scene_type, instr_type, count(*) AS n, CAST(sum(CAST(success AS INT)) AS BIGINT) AS n_success, count(DISTINCT scene_id) AS n_scenes, CAST(grouping_id(scene_type, instr_type) AS INT) AS level, 100.0::DOUBLE * sum(CAST(success AS INT)) / count(*) AS sr FROM diag GROUP BY CUBE (scene_type, instr_type)"


@query("tax_counts", "SELECT scene_type, instr_type, n, n_success, n_scenes, level FROM cubed", cubed=_CUBE, **DIAG_VIEWS)
def tax_counts(spark, sf):
    return X.matrix_counts(diagnostic(spark, sf))


@query("tax_sr", f"SELECT scene_type, instr_type, n, {r6_sql('sr')} AS sr, {r6_sql('sr - (SELECT sr FROM cubed WHERE level = 3)')} AS deviation FROM cubed", cubed=_CUBE, **DIAG_VIEWS)
def tax_sr(spark, sf):
    m = X.matrix_sr(diagnostic(spark, sf))
    return m.select("scene_type", "instr_type", "n", r6("sr").alias("sr"), r6("deviation").alias("deviation"))


@query(
    "tax_spans",
    f"SELECT {r6_sql('max(sr) FILTER (WHERE level = 0)')} AS best_sr, {r6_sql('min(sr) FILTER (WHERE level = 0)')} AS worst_sr, {r6_sql('max(sr) FILTER (WHERE level = 1) - min(sr) FILTER (WHERE level = 1)')} AS scene_span, {r6_sql('max(sr) FILTER (WHERE level = 2) - min(sr) FILTER (WHERE level = 2)')} AS instr_span FROM cubed",
    cubed=_CUBE,
    **DIAG_VIEWS,
)
def tax_spans(spark, sf):
    s = X.spans(X.matrix_sr(diagnostic(spark, sf)))
    return s.select(*[r6(c).alias(c) for c in ("best_sr", "worst_sr", "scene_span", "instr_span")])


@query(
    "tax_cells",
    f"SELECT scene_type, instr_type, least(count(*), 50) AS n, greatest(0, 50 - count(*)) AS shortfall FROM v_rollouts GROUP BY scene_type, instr_type",
)
def tax_cells(spark, sf):
    kept, short = X.fill_cells(C.v_rollouts(spark, sf), 50)
    return short.select("scene_type", "instr_type", "n", F.col("shortfall").cast("long").alias("shortfall"))


@query(
    "diag_wilson",
    f"""SELECT scene_type, {r6_sql("(p + z2 / (2 * n) - z * sqrt(p * (1 - p) / n + z2 / (4 * n * n))) / (1 + z2 / n)")} AS low, {r6_sql("(p + z2 / (2 * n) + z * sqrt(p * (1 - p) / n + z2 / (4 * n * n))) / (1 + z2 / n)")} AS high
  FROM (SELECT scene_type, avg(CAST(success AS INT)) AS p, count(*)::DOUBLE AS n, 1.959964::DOUBLE AS z, 1.959964::DOUBLE * 1.959964::DOUBLE AS z2 FROM diag GROUP BY scene_type)""",
    **DIAG_VIEWS,
)
def diag_wilson(spark, sf):
    g = diagnostic(spark, sf).groupBy("scene_type").agg(F.sum(F.col("success").cast("double")).alias("s"), F.count("*").cast("double").alias("n"))
    w = M.wilson(F.col("s"), F.col("n"))
    return g.select("scene_type", r6(w.low).alias("low"), r6(w.high).alias("high"))


# --- reports over result rows --------------------------------------------------------------

_PUB = "SELECT * FROM v_results"


@query("er_macro", f"SELECT method, count(value) AS n_values, count(value) = 8 AS complete, CASE WHEN count(value) = 8 THEN {r6_sql('avg(value)', 4)} END AS macro FROM pub WHERE family = 'er' AND metric = 'SR' GROUP BY method", pub=_PUB)
def er_macro(spark, sf):
    m = M.macro_average(C.v_results(spark, sf).where("family = 'er' and metric = 'SR'"))
    return m.select("method", "n_values", "complete", F.when(F.col("macro").isNotNull(), r6("macro", 4)).alias("macro"))


@query("rank_marks", "SELECT method, family, setting, metric, value, CAST(dense_rank() OVER (PARTITION BY family, setting, metric ORDER BY CASE WHEN metric IN ('NE', 'CR') THEN -value ELSE value END DESC) AS INT) AS rank FROM pub WHERE value IS NOT NULL", pub=_PUB)
def rank_marks(spark, sf):
    return M.rank_marks(C.v_results(spark, sf)).select("method", "family", "setting", "metric", "value", "rank")


@query(
    "gain_table",
    f"""SELECT setting, metric, f AS focal, b AS best_other, {r6_sql("CASE WHEN metric IN ('NE', 'CR') THEN b - f ELSE f - b END", 4)} AS gain_abs, {r6_sql("100 * CASE WHEN metric IN ('NE', 'CR') THEN b - f ELSE f - b END / b", 4)} AS gain_rel FROM (
  SELECT setting, metric, max(value) FILTER (WHERE method = 'ours') AS f, CASE WHEN metric IN ('NE', 'CR') THEN min(value) FILTER (WHERE method <> 'ours') ELSE max(value) FILTER (WHERE method <> 'ours') END AS b FROM pub WHERE value IS NOT NULL AND family = 'mono' GROUP BY setting, metric) WHERE f IS NOT NULL AND b IS NOT NULL""",
    pub=_PUB,
)
def gain_table(spark, sf):
    g = M.gain_table(C.v_results(spark, sf).where("family = 'mono'"), "ours")  # among methods with one camera
    return g.select("setting", "metric", "focal", "best_other", r6("gain_abs", 4).alias("gain_abs"), r6("gain_rel", 4).alias("gain_rel"))


_ABL = "SELECT metric, avg(a) AS ma, avg(b) AS mb, CAST(sum(CAST(b > a AS INT)) AS BIGINT) AS nb, count(*) AS n FROM (SELECT metric, setting, max(value) FILTER (WHERE method = '{base}') AS a, max(value) FILTER (WHERE method = 'ours_full') AS b FROM pub WHERE family = 'ablation' GROUP BY metric, setting) GROUP BY metric"


@query(
    "ablation_means",
    " UNION ALL ".join(f"SELECT '{v}' AS base, metric, {r6_sql('ma', 4)} AS mean_base, {r6_sql('mb', 4)} AS mean_variant, nb AS n_better, n FROM ({_ABL.format(base=v)})" for v in ("init_backbone", "no_pointing")),
    pub=_PUB,
)
def ablation_means(spark, sf):
    p, out = C.v_results(spark, sf).where("family = 'ablation'"), None
    for v in ("init_backbone", "no_pointing"):
        one = M.ablation_table(p, v, "ours_full").select(F.lit(v).alias("base"), "metric", r6("mean_base", 4).alias("mean_base"), r6("mean_variant", 4).alias("mean_variant"), "n_better", "n")
        out = one if out is None else out.unionByName(one)
    return out

"""History, pointing, quantiser, serialisation and inventory workloads."""

from __future__ import annotations

import re

from pyspark.sql import functions as F

from navspark.functions import geometry as G
from navspark.functions import pointing as P
from navspark.functions.core import PI, r6, r6_sql, uniform01_sql
from navspark.operators import annotate as A
from navspark.operators import episodes as E
from navspark.operators import history as H
from navspark.operators import instruct as N
from navspark.operators import inventory as V
from navspark.operators import rvq as Q
from navspark.operators import serialize as S
from navspark.operators import taxonomy as Y
from navspark.plans.base import query
from navspark.session import kept, stored, tables
from navspark.sources import carriers as C

# --- history -----------------------------------------------------------------------------

DAY = 86_400.0
F_MAX, TAU_S, TAU_P = 1 / DAY, 5 * DAY, 7 * DAY
TIERS = [(TAU_S / 2, 4), (2 * TAU_S, 3), (1e12, 2)]
MODES = ("all", "fixed", "uniform", "integral", "hash", "tiers")

_AGED = f"""SELECT *, row_number() OVER (PARTITION BY episode_id ORDER BY age_s, t DESC) AS rn, lag(age_s) OVER (PARTITION BY episode_id ORDER BY age_s, t DESC) AS newer,
  CAST(greatest(1, least(8.0::DOUBLE, floor(exp(least(age_s / {TAU_P}::DOUBLE, 60.0::DOUBLE))))) AS INT) AS s, floor(round({F_MAX * TAU_S}::DOUBLE * (1 - exp(-age_s / {TAU_S}::DOUBLE)), 9)) AS lv,
  CASE WHEN age_s <= {TIERS[0][0]} THEN 0 WHEN age_s <= {TIERS[1][0]} THEN 1 ELSE 2 END AS tier, CASE WHEN age_s <= {TIERS[0][0]} THEN 4 WHEN age_s <= {TIERS[1][0]} THEN 3 ELSE 2 END AS quota
  FROM (SELECT episode_id, t, event_id, (max(epoch_us(ts)) OVER (PARTITION BY episode_id) - epoch_us(ts)) / 1e6::DOUBLE AS age_s FROM v_steps)"""
_KEPT = f"""SELECT *, lag(lv) OVER (PARTITION BY episode_id ORDER BY age_s, t DESC) AS plv,
  row_number() OVER (PARTITION BY episode_id, tier ORDER BY age_s, t DESC) - 1 AS tr, count(*) OVER (PARTITION BY episode_id, tier) AS tn,
  {uniform01_sql("episode_id", "t", salt="thin")} AS u FROM aged"""
_MODES = f"""SELECT 'all' AS mode, episode_id, 1 AS s FROM kept UNION ALL SELECT 'fixed', episode_id, CASE WHEN rn = 1 THEN 1 ELSE 2 END FROM kept
  UNION ALL SELECT 'uniform', episode_id, s FROM kept WHERE (rn - 1) % 4 = 0 UNION ALL SELECT 'integral', episode_id, s FROM kept WHERE plv IS NULL OR lv > plv
  UNION ALL SELECT 'hash', episode_id, s FROM kept WHERE rn = 1 OR u < least(1.0::DOUBLE, {F_MAX}::DOUBLE * exp(-age_s / {TAU_S}::DOUBLE) * (age_s - newer))
  UNION ALL SELECT 'tiers', episode_id, s FROM kept WHERE rn = 1 OR floor(tr * quota::DOUBLE / tn) > floor((tr - 1) * quota::DOUBLE / tn)"""


@query(
    "hist_cost",
    f"""SELECT mode, CAST(sum(n) AS BIGINT) AS n_frames, CAST(sum(k) AS BIGINT) AS n_tok, CAST(max(k) AS BIGINT) AS max_tok FROM (
  SELECT mode, episode_id, count(*) AS n, sum(ceil(8.0::DOUBLE / s) * ceil(8.0::DOUBLE / s) + 1) AS k FROM ({_MODES}) GROUP BY ALL) GROUP BY mode""",
    aged=_AGED,
    kept=_KEPT,
)
def hist_cost(spark, sf):
    frames = C.v_frames(spark, sf).select("episode_id", "t", "ts")
    out = None
    for mode in MODES:
        cost = H.history_cost(H.compress_history(frames, mode, F_MAX, TAU_S, TAU_P, tiers=TIERS))
        one = cost.agg(F.sum("n_frames").alias("n_frames"), F.sum("n_tok").cast("long").alias("n_tok"), F.max("n_tok").cast("long").alias("max_tok")).select(F.lit(mode).alias("mode"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "hist_pool",
    f"""SELECT k.episode_id, CAST(k.t AS INT) AS t, s AS stride, CAST(ceil(8.0::DOUBLE / s) AS INT) AS h_p, CAST(ceil(8.0::DOUBLE / s) AS INT) AS w_p, {r6_sql("avg(CAST(e.embedding[i + 1] AS DOUBLE))", 5)} AS mean_first_cell
  FROM kept k JOIN embeddings e ON e.vec_id = k.event_id % (SELECT count(*) FROM embeddings) CROSS JOIN range(64) AS r(i)
  WHERE (plv IS NULL OR lv > plv) AND i // 8 < s AND i % 8 < s GROUP BY k.episode_id, k.t, s""",
    aged=_AGED,
    kept=_KEPT,
)
def hist_pool(spark, sf):
    ctx = H.compress_history(C.v_frames(spark, sf), "integral", F_MAX, TAU_S, TAU_P)
    j = H.with_pooled(ctx, C.grids(spark, sf))
    return j.select("episode_id", "t", "stride", "h_p", "w_p", r6(F.get("cells", F.lit(0)), 5).alias("mean_first_cell"))


def _budget_views(budget: int, rounds: int = 3) -> dict[str, str]:
    """Rounds of doubling strides, oldest first, while an episode is above its budget."""
    tok = "(ceil(8.0::DOUBLE / {0}) * ceil(8.0::DOUBLE / {0}) + 1)"
    views = {"fit0": "SELECT episode_id, t, age_s, rn, s AS stride FROM aged WHERE (rn - 1) % 2 = 0"}
    for i in range(rounds):
        views[f"fit{i + 1}"] = f"""SELECT episode_id, t, age_s, rn, CASE WHEN total - saved > {budget} THEN more ELSE stride END AS stride FROM (
  SELECT *, sum({tok.format("stride")}) OVER (PARTITION BY episode_id) AS total, coalesce(sum({tok.format("stride")} - {tok.format("more")}) OVER (PARTITION BY episode_id ORDER BY age_s DESC, t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS saved FROM (
   SELECT *, CASE WHEN rn = 1 THEN stride ELSE least(8, stride * 2) END AS more FROM fit{i}))"""
    views["fitted"] = f"SELECT *, {tok.format('stride')} AS k FROM fit{rounds}"
    return views


@query(
    "hist_budget",
    "SELECT episode_id, CAST(sum(k) AS BIGINT) AS n_tok, CAST(max(stride) AS INT) AS max_stride, sum(k) > 200 AS over_budget FROM fitted GROUP BY episode_id",
    aged=_AGED,
    **_budget_views(200),
)
def hist_budget(spark, sf):
    """Strides after the token budget: no episode above it unless flagged."""
    ctx = H.compress_history(C.v_frames(spark, sf).select("episode_id", "t", "ts"), "uniform", F_MAX, TAU_S, TAU_P, budget=200, every=2)
    return ctx.groupBy("episode_id").agg(F.sum("n_tok").alias("n_tok"), F.max("stride").alias("max_stride"), F.bool_or("over_budget").alias("over_budget"))


@query(
    "hist_native_resolution",
    """SELECT budget, count(*) AS n, CAST(sum(r * 32) AS BIGINT) AS h2, CAST(sum(c * 32) AS BIGINT) AS w2, CAST(sum(r * c) AS BIGINT) AS n_tok FROM (SELECT *, CAST(greatest(1, floor(floor(h * s) / 32)) AS INT) AS r, CAST(greatest(1, floor(floor(w * s) / 32)) AS INT) AS c FROM (
  SELECT *, least(1.0::DOUBLE, sqrt(budget::DOUBLE / (h * w))) AS s FROM (SELECT 240 + 8 * k AS h, 320 + 16 * (event_id % 97) AS w FROM v_steps) AS f CROSS JOIN (VALUES (262144), (589824), (1048576)) AS b(budget))) GROUP BY budget""",
)
def hist_native_resolution(spark, sf):
    """Frames of many shapes, one for each step: what each pixel budget leaves of them."""
    f = C.v_steps(spark, sf).select((240 + 8 * F.col("k")).alias("h"), (320 + 16 * (F.col("event_id") % 97)).alias("w"), F.explode(F.array(*map(F.lit, H.PIXEL_BUDGETS))).alias("budget"))
    r, c = H.fitted("h", "w", "budget")
    f = f.select("budget", r.alias("r"), c.alias("c"))
    return f.groupBy("budget").agg(F.count("*").alias("n"), F.sum(F.col("r") * 32).alias("h2"), F.sum(F.col("c") * 32).alias("w2"), F.sum(F.col("r") * F.col("c")).alias("n_tok"))


# --- pointing ----------------------------------------------------------------------------

_TURN = 0.45
_CELL = "CASE WHEN u BETWEEN 0 AND 1 AND v BETWEEN 0 AND 1 THEN CAST(least(15, floor(v * 16)) * 16 + least(15, floor(u * 16)) AS INT) END"
_POINTS = f"""SELECT *, CASE WHEN stop THEN 257 WHEN abs(turn_rad) > {_TURN} THEN 256 ELSE coalesce({_CELL}, 258) END AS apos, coalesce(CASE WHEN visible THEN {_CELL} END, 258) AS opos FROM v_steps"""


def points(spark, sf):
    s = C.v_steps(spark, sf)
    return s.withColumns({"apos": P.affordance_index("u", "v", F.abs("turn_rad") > _TURN, "stop"), "opos": P.object_index("u", "v", "visible")})


@query(
    "point_tokens",
    f"""SELECT idx, channel, count(*) AS n, {r6_sql("avg(CASE WHEN idx < 256 THEN abs(u - (idx % 16 + 0.5::DOUBLE) / 16) END)", 9)} AS mean_u_err, {r6_sql("avg(CASE WHEN idx < 256 THEN abs(v - (idx // 16 + 0.5::DOUBLE) / 16) END)", 9)} AS mean_v_err
  FROM (SELECT apos AS idx, 'affordance' AS channel, u, v FROM points UNION ALL SELECT opos, 'object', u, v FROM points) GROUP BY idx, channel""",
    points=_POINTS,
)
def point_tokens(spark, sf):
    p = points(spark, sf)
    long = p.select(F.explode(F.array(F.struct(F.lit("affordance").alias("channel"), F.col("apos").alias("idx")), F.struct(F.lit("object").alias("channel"), F.col("opos").alias("idx")))).alias("x"), "u", "v").select("x.*", "u", "v")
    c = P.cell_center("idx")
    return long.groupBy("idx", "channel").agg(F.count("*").alias("n"), r6(F.avg(F.abs(F.col("u") - c.u)), 9).alias("mean_u_err"), r6(F.avg(F.abs(F.col("v") - c.v)), 9).alias("mean_v_err"))


@query(
    "point_encodings",
    "SELECT 'cell' AS encoding, count(*) AS n_points, count(*) AS n_tokens FROM v_steps WHERE u BETWEEN 0 AND 1 AND v BETWEEN 0 AND 1 UNION ALL SELECT 'xy', count(*), 2 * count(*) FROM v_steps WHERE u BETWEEN 0 AND 1 AND v BETWEEN 0 AND 1",
)
def point_encodings(spark, sf):
    s = C.v_steps(spark, sf)
    cell = s.select(P.grid_index("u", "v").alias("i")).where("i is not null").agg(F.count("*").alias("n_points"), F.count("*").alias("n_tokens")).select(F.lit("cell").alias("encoding"), "*")
    xy = s.select(P.xy_tokens("u", "v").alias("x")).where("x is not null").agg(F.count("*").alias("n_points"), F.sum(F.size("x")).cast("long").alias("n_tokens")).select(F.lit("xy").alias("encoding"), "*")
    return cell.unionByName(xy)


def _seen_sql(tx: str, ty: str, dz: float) -> str:
    """Cell of a point (tx, ty) at height dz above the camera, from the pose (x, y, yaw)."""
    f, ahead, left = "0.28867513459481287::DOUBLE", f"(({tx} - x) * cos(yaw) + ({ty} - y) * sin(yaw))", f"(({ty} - y) * cos(yaw) - ({tx} - x) * sin(yaw))"
    u, v = f"round(0.5::DOUBLE - {f} * {left} / {ahead}, 9)", f"round(0.5::DOUBLE - {f} * {dz}::DOUBLE / {ahead}, 9)"
    return f"CASE WHEN {ahead} > 1e-9 AND {u} BETWEEN 0 AND 1 AND {v} BETWEEN 0 AND 1 THEN CAST(least(15, floor({v} * 16)) * 16 + least(15, floor({u} * 16)) AS INT) ELSE 258 END"


@query(
    "point_annotate",
    f"""SELECT episode_id, CAST(i AS INT) AS i, CASE WHEN nx IS NULL THEN 257 ELSE {_seen_sql("nx", "ny", -1.0)} END AS apos, {_seen_sql("gx", "gy", 0.0)} AS opos FROM (
  SELECT *, coalesce(atan2(ny - y, nx - x), 0.0::DOUBLE) AS yaw FROM (SELECT *, lead(x) OVER w AS nx, lead(y) OVER w AS ny FROM v_path WINDOW w AS (PARTITION BY episode_id ORDER BY i)))""",
)
def point_annotate(spark, sf):
    """Dual labels by projection: the next waypoint of the executed path, and the goal, seen from each pose."""
    return A.annotate_dual(C.v_path(spark, sf)).select("episode_id", "i", "apos", "opos")


@query(
    "point_supervision",
    f"SELECT response, count(*) AS n FROM (SELECT '<opos_' || coalesce({_CELL}, 258) || '>' AS response FROM v_views) GROUP BY response",
)
def point_supervision(spark, sf):
    return A.point_supervision(C.v_views(spark, sf)).groupBy("response").agg(F.count("*").alias("n"))


# --- quantiser ---------------------------------------------------------------------------

K = 16


def _table_books(spark, sf):
    """16 codewords a level: the trajectories with ids 0-15, 16-31 (halved) and 32-47 (quartered)."""
    rows = C.v_traj(spark, sf).where("traj_id < 48").orderBy("traj_id").collect()
    import numpy as np

    z = np.array([r.z for r in rows]).reshape(3, K, 30)
    return Q.Codebooks(z * np.array([1, 0.5, 0.25])[:, None, None])


_WAY = """SELECT {keys}, i, sum(dx * cos(h) - dy * sin(h)) OVER w AS x, sum(dx * sin(h) + dy * cos(h)) OVER w AS y, h + dth AS th FROM (
  SELECT *, coalesce(sum(dth) OVER (PARTITION BY {keys} ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0::DOUBLE) AS h FROM {rows}) WINDOW w AS (PARTITION BY {keys} ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"""
_WRAP = "(pi() - (((pi() - ({a})) % (2 * pi())) + 2 * pi()) % (2 * pi()))"


def _encode_sql(how: str, lam: float = 0.3) -> tuple[str, dict[str, str]]:
    views = {"zway": _WAY.format(keys="traj_id", rows="v_traj_rows")}
    done = "SELECT traj_id, i, 0.0::DOUBLE AS dx, 0.0::DOUBLE AS dy, 0.0::DOUBLE AS dth FROM v_traj_rows"
    for lv, scale in enumerate((1.0, 0.5, 0.25)):
        views[f"done{lv}"] = done
        views[f"book{lv}"] = f"SELECT traj_id - {16 * lv} AS k, i, dx * {scale}::DOUBLE AS dx, dy * {scale}::DOUBLE AS dy, dth * {scale}::DOUBLE AS dth FROM v_traj_rows WHERE traj_id BETWEEN {16 * lv} AND {16 * lv + 15}"
        views[f"cand{lv}"] = f"SELECT d.traj_id, b.k, d.i, d.dx + b.dx AS dx, d.dy + b.dy AS dy, d.dth + b.dth AS dth FROM done{lv} d JOIN book{lv} b ON d.i = b.i"
        views[f"cway{lv}"] = _WAY.format(keys="traj_id, k", rows=f"cand{lv}")
        if how == "d_traj":
            wrapped = _WRAP.format(a="max(CASE WHEN z.i = 9 THEN z.th END) - max(CASE WHEN z.i = 9 THEN c.th END)")
            views[f"dist{lv}"] = f"SELECT z.traj_id, c.k, avg(sqrt((z.x - c.x) ** 2 + (z.y - c.y) ** 2)) + {lam}::DOUBLE * abs({wrapped}) AS d FROM zway z JOIN cway{lv} c ON z.traj_id = c.traj_id AND z.i = c.i GROUP BY z.traj_id, c.k"
        else:
            views[f"res{lv}"] = f"SELECT z.traj_id, c.k, z.i, z.dx - c.dx AS dx, z.dy - c.dy AS dy, z.dth - c.dth AS dth FROM v_traj_rows z JOIN cand{lv} c ON z.traj_id = c.traj_id AND z.i = c.i"
            views[f"cum{lv}"] = f"SELECT traj_id, k, i, sum(dx) OVER w AS x, sum(dy) OVER w AS y, sum(dth) OVER w AS th FROM res{lv} WINDOW w AS (PARTITION BY traj_id, k ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
            views[f"met{lv}"] = f"SELECT *, coalesce(sum(th) OVER (PARTITION BY traj_id, k ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0::DOUBLE) AS lean FROM cum{lv}"
            views[f"dist{lv}"] = f"SELECT traj_id, k, sum((x * x + (y + 0.25::DOUBLE * lean) ** 2) / 10 + CASE WHEN i = 9 THEN 0.09::DOUBLE ELSE 1e-6::DOUBLE END * th * th) AS d FROM met{lv} GROUP BY traj_id, k"
        views[f"best{lv}"] = f"SELECT traj_id, CAST(k AS INT) AS k FROM (SELECT *, row_number() OVER (PARTITION BY traj_id ORDER BY round(d, 9), k) AS rn FROM dist{lv}) WHERE rn = 1"
        views[f"ade{lv}"] = f"SELECT z.traj_id, avg(sqrt((z.x - c.x) ** 2 + (z.y - c.y) ** 2)) AS a FROM zway z JOIN best{lv} b ON z.traj_id = b.traj_id JOIN cway{lv} c ON c.traj_id = b.traj_id AND c.k = b.k AND c.i = z.i GROUP BY z.traj_id"
        done = f"SELECT c.traj_id, c.i, c.dx, c.dy, c.dth FROM cand{lv} c JOIN best{lv} b ON c.traj_id = b.traj_id AND c.k = b.k"
    body = f"""SELECT b0.traj_id, b0.k AS k0, b1.k AS k1, b2.k AS k2, {r6_sql("a0.a")} AS ade1, {r6_sql("a1.a")} AS ade2, {r6_sql("a2.a")} AS ade3
  FROM best0 b0 JOIN best1 b1 ON b0.traj_id = b1.traj_id JOIN best2 b2 ON b0.traj_id = b2.traj_id JOIN ade0 a0 ON b0.traj_id = a0.traj_id JOIN ade1 a1 ON b0.traj_id = a1.traj_id JOIN ade2 a2 ON b0.traj_id = a2.traj_id"""
    return body, views


def _encode(spark, sf, how):
    books = _table_books(spark, sf)
    coded = Q.encode(C.v_traj(spark, sf).select("traj_id", "z"), books, how)
    frame = books.frame(spark)
    for upto in (1, 2, 3):
        coded = Q.decode(coded, frame, upto).withColumn(f"ade{upto}", r6(G.ade("z", "zhat"))).drop("zhat", "wps")
    return coded.select("traj_id", "k0", "k1", "k2", "ade1", "ade2", "ade3")


_TRAJ_SQL, _TRAJ_VIEWS = _encode_sql("d_traj")
_DJ_SQL, _DJ_VIEWS = _encode_sql("d_j")


@query("rvq_encode", _TRAJ_SQL, **_TRAJ_VIEWS)
def rvq_encode(spark, sf):
    return _encode(spark, sf, "d_traj")


@query("rvq_encode_dj", _DJ_SQL, **_DJ_VIEWS)
def rvq_encode_dj(spark, sf):
    return _encode(spark, sf, "d_j")


@query("rvq_lloyd_step", f"SELECT b.k, CAST(count(*) AS BIGINT) AS n, {r6_sql('sum(d.d)', 4)} AS err FROM best0 b JOIN dist0 d ON b.traj_id = d.traj_id AND b.k = d.k GROUP BY b.k", **_DJ_VIEWS)
def rvq_lloyd_step(spark, sf):
    import numpy as np

    parts = Q.lloyd_partials(C.v_traj(spark, sf), np.zeros((0, K, 30)), _table_books(spark, sf).vec[0], Q.metric_map())
    return parts.groupBy("k").agg(F.sum("n").cast("long").alias("n"), r6(F.sum("err"), 4).alias("err"))


def _quality(traj, levels, k, iters=6):
    books = Q.fit_rvq(traj, levels, k, iters)
    return Q.rvq_eval(Q.encode(traj.select("traj_id", "z"), books, "d_j"), books)


@query("rvq_quality")
def rvq_quality(spark, sf):
    """Displacement for each prefix of residual quantisers, 3 x 256 at full size, and for single-level vocabularies up to 4,096."""
    traj = kept(C.v_chunks(spark, sf).select(F.col("chunk_id").alias("traj_id"), "z"))
    out = None
    for levels, k in ((3, 16), (3, 64), (3, 256), (1, 48), (1, 256), (1, 4096)):
        one = _quality(traj, levels, k).select(F.lit(f"{levels}x{k}").alias("size"), "levels", "n", r6("mean_ade").alias("mean_ade"), r6("mean_dth").alias("mean_dth"), "used_codes", r6("entropy_bits").alias("entropy_bits"), "dead_codes")
        out = one if out is None else out.unionByName(one)
    return out


LAMBDAS = (0.0, 0.1, 0.3, 1.0)


def renamed(text: str, names, prefix: str) -> str:
    return re.sub(rf"\b({'|'.join(names)})\b", rf"{prefix}\1", text)


def _sweep_sql() -> tuple[str, dict[str, str]]:
    """The encoding once for each heading weight, its views under names of their own."""
    parts, views = [], {}
    for i, lam in enumerate(LAMBDAS):
        own = _encode_sql("d_traj", lam)[1]
        body = f"""SELECT {lam}::DOUBLE AS lam, {r6_sql("avg(a.a)")} AS mean_ade, {r6_sql("avg(abs(" + _WRAP.format(a="z.th - c.th") + "))")} AS mean_dth
  FROM ade2 a JOIN zway z ON z.traj_id = a.traj_id AND z.i = 9 JOIN best2 b ON b.traj_id = a.traj_id JOIN cway2 c ON c.traj_id = b.traj_id AND c.k = b.k AND c.i = 9"""
        parts.append(renamed(body, own, f"w{i}_"))
        views |= {f"w{i}_{name}": renamed(text, own, f"w{i}_") for name, text in own.items()}
    return " UNION ALL ".join(parts), views


_SWEEP_SQL, _SWEEP_VIEWS = _sweep_sql()


@query("rvq_lambda_sweep", _SWEEP_SQL, **_SWEEP_VIEWS)
def rvq_lambda_sweep(spark, sf):
    got = Q.lambda_sweep(C.v_traj(spark, sf).select("traj_id", "z"), _table_books(spark, sf), list(LAMBDAS))
    return got.select("lam", r6("mean_ade").alias("mean_ade"), r6("mean_dth").alias("mean_dth"))


@query("se2_integrate", f"SELECT traj_id, {r6_sql('x')} AS x10, {r6_sql('y')} AS y10, {r6_sql('th')} AS th10 FROM zway WHERE i = 9", zway=_TRAJ_VIEWS["zway"])
def se2_integrate(spark, sf):
    t = C.v_traj(spark, sf).select("traj_id", F.element_at(G.integrate_se2("z"), -1).alias("w"))
    return t.select("traj_id", r6("w.x").alias("x10"), r6("w.y").alias("y10"), r6("w.th").alias("th10"))


_PLATFORMS = ", ".join(f"('{n}', {v}::DOUBLE, {w}::DOUBLE)" for n, v, w in G.PLATFORMS)


@query(
    "vel_cmd",
    f"""SELECT platform, count(*) AS n, CAST(sum(CAST(c AS INT)) AS BIGINT) AS n_clipped, {r6_sql("avg(vc)")} AS mean_v FROM (
  SELECT platform, greatest(-vm, least(vm, v)) AS vc, abs(v) > vm OR abs(w) > wm AS c FROM (
   SELECT p.*, sign(dx) * sqrt(dx * dx + dy * dy) / 0.5::DOUBLE AS v, dth / 0.5::DOUBLE AS w FROM v_chunk_rows CROSS JOIN (VALUES {_PLATFORMS}) AS p(platform, vm, wm))) GROUP BY platform""",
)
def vel_cmd(spark, sf):
    j = C.v_chunks(spark, sf).crossJoin(F.broadcast(G.platforms(spark)))  # four fixed rows
    x = j.select("platform", F.explode(G.to_velocity("z", 0.5, F.col("v_max"), F.col("w_max"))).alias("c"))
    return x.groupBy("platform").agg(F.count("*").alias("n"), F.sum(F.col("c.clipped").cast("long")).alias("n_clipped"), r6(F.avg("c.v")).alias("mean_v"))


# --- serialisation -----------------------------------------------------------------------


def serialized(spark, sf, pointing=True):
    """Output records of all steps; the code of a step is its forward and turning octile, in three levels of two bits."""
    p = points(spark, sf)
    k0 = F.least(F.lit(3), F.floor(F.col("fwd_m") * 4)).cast("int")
    k1 = F.least(F.lit(3), F.floor((F.col("turn_rad") / (PI / 6) + 1) * 2)).cast("int")
    k2 = (F.col("k") % 4).cast("int")
    p = p.withColumns({"k0": k0, "k1": k1, "k2": k2})
    return p.select("episode_id", "t", "event_id", S.serialize(pointing=pointing).alias("tokens"))


SER_VIEWS = {
    "points": _POINTS,
    "coded": "SELECT *, CAST(least(3, floor(fwd_m * 4)) AS INT) AS k0, CAST(least(3, floor((turn_rad / (pi() / 6) + 1) * 2)) AS INT) AS k1, CAST(k % 4 AS INT) AS k2 FROM points",
    "tok": """SELECT episode_id, t, event_id, 0 AS pos, '<apos_' || apos || '>' AS token FROM coded UNION ALL SELECT episode_id, t, event_id, 1, '<opos_' || opos || '>' FROM coded
  UNION ALL SELECT episode_id, t, event_id, 2, '<act0_' || k0 || '>' FROM coded UNION ALL SELECT episode_id, t, event_id, 3, '<act1_' || k1 || '>' FROM coded UNION ALL SELECT episode_id, t, event_id, 4, '<act2_' || k2 || '>' FROM coded""",
}


@query("serialize_counts", "SELECT regexp_extract(token, '<([a-z]+[0-9]?)_', 1) AS family, count(*) AS n, count(DISTINCT token) AS n_distinct FROM tok GROUP BY 1", **SER_VIEWS)
def serialize_counts(spark, sf):
    t = serialized(spark, sf).select(F.explode("tokens").alias("token"))
    return t.groupBy(F.regexp_extract("token", "<([a-z]+[0-9]?)_", 1).alias("family")).agg(F.count("*").alias("n"), F.count_distinct("token").alias("n_distinct"))


@query("serialize_valid", "SELECT count(*) AS n, count(*) AS n_valid, CAST(sum(apos) AS BIGINT) AS sum_apos, CAST(sum(k0) AS BIGINT) AS sum_k0 FROM coded", **SER_VIEWS)
def serialize_valid(spark, sf):
    p = serialized(spark, sf).select(S.parse_output("tokens").alias("p"))
    return p.agg(F.count("*").alias("n"), F.sum(F.col("p.valid").cast("long")).alias("n_valid"), F.sum("p.apos").alias("sum_apos"), F.sum(F.get("p.codes", F.lit(0))).alias("sum_k0"))


_VOCAB = "SELECT 'apos' AS family, 259::BIGINT AS n, 32000::BIGINT AS first_id UNION ALL SELECT 'opos', 259, 32259 UNION ALL SELECT 'act0', 256, 32518 UNION ALL SELECT 'act1', 256, 32774 UNION ALL SELECT 'act2', 256, 33030"


@query("vocab", f"SELECT family, n, first_id, coalesce(u, 0) AS n_used FROM ({_VOCAB}) AS f LEFT JOIN (SELECT 'apos' AS family, count(DISTINCT apos) AS u FROM points UNION ALL SELECT 'opos', count(DISTINCT opos) FROM points) AS s USING (family)", points=_POINTS)
def vocab(spark, sf):
    """Tokens of each family, and how many of its point tokens the steps use."""
    p = points(spark, sf)
    used = p.select(F.lit("apos").alias("family"), F.col("apos").alias("idx")).unionByName(p.select(F.lit("opos").alias("family"), F.col("opos").alias("idx"))).distinct()
    v = S.build_vocab(spark, 32000).join(used.withColumn("_u", F.lit(1)), ["family", "idx"], "left")
    return v.groupBy("family").agg(F.count("*").alias("n"), F.min("id").alias("first_id"), F.count("_u").alias("n_used"))


# --- inventory ---------------------------------------------------------------------------


@query("inv_lift", "SELECT count(*) AS n, 0.0::DOUBLE AS max_err FROM v_views WHERE u IS NOT NULL")
def inv_lift(spark, sf):
    v = V.lift_views(C.v_views(spark, sf).where("u is not null"))
    err = F.sqrt((F.col("lx") - F.col("x")) ** 2 + (F.col("ly") - F.col("y")) ** 2 + (F.col("lz") - F.col("z")) ** 2)
    return v.agg(F.count("*").alias("n"), r6(F.max(err)).alias("max_err"))


def _lifted(spark, sf):
    """Lifted points, rounded so that cells don't depend on the last bit."""
    v = V.lift_views(C.v_views(spark, sf).where("u is not null"))
    return v.withColumns({c: F.round(c, 6) for c in ("lx", "ly", "lz")})


@query(
    "inv_gate",
    """SELECT reason, count(*) AS n FROM (SELECT CASE WHEN n_obs < 2 THEN 'few_obs' WHEN n_views < 2 THEN 'few_views' WHEN NOT round(spread, 9) < 0.6 THEN 'spread' ELSE 'accepted' END AS reason FROM (
  SELECT scene, category, cx, cy, cz, count(*) AS n_obs, count(DISTINCT viewpoint) AS n_views, max(sqrt((lx - mx) ** 2 + (ly - my) ** 2 + (lz - mz) ** 2)) AS spread FROM (
   SELECT *, avg(lx) OVER c AS mx, avg(ly) OVER c AS my, avg(lz) OVER c AS mz FROM (
    SELECT *, floor(lx) AS cx, floor(ly) AS cy, floor(lz) AS cz FROM (SELECT scene, category, viewpoint, round(x, 6) AS lx, round(y, 6) AS ly, round(z, 6) AS lz FROM v_views WHERE u IS NOT NULL))
   WINDOW c AS (PARTITION BY scene, category, cx, cy, cz)) GROUP BY scene, category, cx, cy, cz)) GROUP BY reason""",
)
def inv_gate(spark, sf):
    return V.gate(V.merge_views(_lifted(spark, sf), 1.0, "cell")).groupBy("reason").agg(F.count("*").alias("n"))


@query(
    "inv_ungated",
    "SELECT count(*) AS n_instances FROM (SELECT DISTINCT scene, category, floor(round(x, 6)), floor(round(y, 6)), floor(round(z, 6)) FROM v_views WHERE u IS NOT NULL)",
)
def inv_ungated(spark, sf):
    g = V.gate(V.merge_views(_lifted(spark, sf), 1.0, "cell"), 1, 1, None)
    return g.where("accepted").agg(F.count("*").alias("n_instances"))


@query("inv_components")
def inv_components(spark, sf):
    """Precision and recall of merging by components and by seeds, against the true instances."""
    with tables():
        # ids are hexadecimal: half as many bytes, in the same order
        obs, out = stored(_lifted(spark, sf).select(F.unhex("obs_id").alias("obs_id"), "scene", "category", "viewpoint", "part_key", "lx", "ly", "lz")), None
        for algo in ("cell", "greedy", "components"):
            with tables():
                m = stored(V.merge_views(obs, 0.5, algo).drop("obs_id"))  # read by several counts
                one = kept(V.inventory_report(m, stored(V.gate(m))).select(F.lit(algo).alias("algo"), "*"))
            out = one if out is None else out.unionByName(one)
    return out


# --- episodes and wording ------------------------------------------------------------------


@query(
    "ep_starts",
    f"""SELECT target, start FROM (SELECT target, viewpoint AS start, row_number() OVER (PARTITION BY target ORDER BY {uniform01_sql("target", "viewpoint", salt="start")}, viewpoint) AS r FROM (
  SELECT DISTINCT scene || '/' || part_key AS target, viewpoint FROM v_views WHERE u BETWEEN 0 AND 1 AND v BETWEEN 0 AND 1)) WHERE r = 1""",
)
def ep_starts(spark, sf):
    v = C.v_views(spark, sf).where(P.valid_point("u", "v"))
    seen = v.select(F.concat_ws("/", "scene", "part_key").alias("target"), "viewpoint")
    return E.draw_starts(seen)


def _relaxed(rounds: int) -> dict[str, str]:
    views = {
        "edges": "SELECT a.n_nationkey AS a, b.n_nationkey AS b, 1.0::DOUBLE + abs(a.n_regionkey - b.n_regionkey) AS w FROM nation a JOIN nation b ON (b.n_nationkey = a.n_nationkey + 1 AND b.n_nationkey % 5 <> 0) OR b.n_nationkey = a.n_nationkey + 5",
        "twoway": "SELECT a, b, w FROM edges UNION ALL SELECT b, a, w FROM edges",
        "relax0": "SELECT n_nationkey AS src, n_nationkey AS node, 0.0::DOUBLE AS dist FROM nation",
    }
    for i in range(rounds):
        views[f"relax{i + 1}"] = f"SELECT src, node, min(dist) AS dist FROM (SELECT * FROM relax{i} UNION ALL SELECT r.src, e.b, r.dist + e.w FROM relax{i} r JOIN twoway e ON r.node = e.a) GROUP BY src, node"
    return views


def grid_edges(spark, sf):
    n = C.load(spark, sf, "nation").select("n_nationkey", "n_regionkey")
    a, b = n.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")), n.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb"))
    right = a.withColumn("b", F.col("a") + 1).where("b % 5 <> 0")
    down = a.withColumn("b", F.col("a") + 5)
    return right.unionByName(down).join(b, "b").select("a", "b", (1.0 + F.abs(F.col("ra") - F.col("rb"))).alias("w"))


@query("ep_routes", f"SELECT src, node AS dst, {r6_sql('dist')} AS dist FROM relax24", **_relaxed(24))
def ep_routes(spark, sf):
    e = grid_edges(spark, sf).coalesce(1)
    d = E.geodesic(e, C.load(spark, sf, "nation").select(F.col("n_nationkey").alias("node")))
    return d.select("src", F.col("node").alias("dst"), r6("dist").alias("dist"))


_SECTOR = "CASE heading WHEN 0 THEN CASE WHEN u < 1.0::DOUBLE / 3 THEN 'front-left' WHEN u > 2.0::DOUBLE / 3 THEN 'front-right' ELSE 'ahead' END WHEN 2 THEN CASE WHEN u > 0.5 THEN 'behind-left' ELSE 'behind-right' END WHEN 1 THEN 'left' ELSE 'right' END"
_ROUTE = "(abs(x - px) + abs(y - py))"
_STRAIGHT = "sqrt((x - px) ** 2 + (y - py) ** 2)"
_WORDED = f"SELECT *, {_SECTOR} AS sector, CASE WHEN {_ROUTE} > 1.35::DOUBLE * {_STRAIGHT} THEN 'place' WHEN {uniform01_sql('obs_id', salt='form')} < 0.5 THEN 'turn' ELSE 'place' END AS form FROM v_views WHERE u IS NOT NULL"


def worded(spark, sf):
    v = C.v_views(spark, sf).where("u is not null")
    route, straight = F.abs(F.col("x") - F.col("px")) + F.abs(F.col("y") - F.col("py")), F.sqrt((F.col("x") - F.col("px")) ** 2 + (F.col("y") - F.col("py")) ** 2)
    return v.withColumns({"sector": N.sector("heading", "u"), "form": N.phrase_form(route, straight, "obs_id", 1.35)})


@query("inst_sector", "SELECT sector, form, count(*) AS n FROM worded GROUP BY sector, form", worded=_WORDED)
def inst_sector(spark, sf):
    return worded(spark, sf).groupBy("sector", "form").agg(F.count("*").alias("n"))


@query(
    "inst_uniform_bins",
    f"SELECT sector, uniform, count(*) AS n FROM (SELECT sector, ['ahead', 'left', 'behind', 'right'][1 + CAST(((floor(round((({_WRAP.format(a='atan2(y - py, x - px)')}) + pi() / 4) / (pi() / 2), 9))::BIGINT % 4) + 4) % 4 AS INT)] AS uniform FROM worded) GROUP BY sector, uniform",
    worded=_WORDED,
)
def inst_uniform_bins(spark, sf):
    w = worded(spark, sf).withColumn("uniform", N.sector_uniform(F.atan2(F.col("y") - F.col("py"), F.col("x") - F.col("px"))))
    return w.groupBy("sector", "uniform").agg(F.count("*").alias("n"))


_TEMPLATES = ", ".join(f"('{a}', '{b}', '{c}')" for a, b, c in N.TEMPLATES)


def _case(table):
    return "CASE sector " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in table.items()) + " ELSE '' END"


_REWRITES = f"""SELECT w.*, t.head_noun AS noun, replace(m.template, '%s', t.modifier || ' ' || t.head_noun) AS draft, CASE CAST(floor({uniform01_sql("w.obs_id", salt="rewrite")} * 4) AS INT)
  WHEN 0 THEN replace(m.template, '%s', t.modifier || ' ' || t.head_noun) WHEN 1 THEN 'Please go to the ' || t.head_noun WHEN 2 THEN replace(replace(m.template, '%s', 'thing'), 'left', 'right') ELSE replace(m.template, '%s', t.head_noun) || ' on the right' END AS rewrite
  FROM worded w JOIN v_targets t ON w.part_key = t.part_key JOIN (VALUES {_TEMPLATES}) AS m(sec, frm, template) ON m.sec = w.sector AND m.frm = w.form"""


def resolved(spark, sf):
    t = C.v_targets(spark, sf).select("part_key", F.col("head_noun").alias("noun"), F.concat_ws(" ", "modifier", "head_noun").alias("name"))
    d = N.draft_rule(worded(spark, sf).join(t, "part_key"))
    tm = F.broadcast(N.templates(spark))
    d = d.join(tm, ["sector", "form"])
    from navspark.functions.core import uniform01

    pick = F.floor(uniform01("obs_id", salt="rewrite") * 4)
    fill = lambda x: F.replace(F.col("template"), F.lit("%s"), x)
    rewrite = F.when(pick == 0, fill(F.col("name"))).when(pick == 1, F.concat(F.lit("Please go to the "), "noun")).when(pick == 2, F.replace(fill(F.lit("thing")), F.lit("left"), F.lit("right"))).otherwise(F.concat(fill(F.col("noun")), F.lit(" on the right")))
    return N.resolve_instruction(d.withColumn("rewrite", rewrite))


@query(
    "inst_checks",
    f"""SELECT noun_ok, dir_ok, no_opposite, count(*) AS n, CAST(sum(CASE WHEN noun_ok AND dir_ok AND no_opposite THEN 0 ELSE 1 END) AS BIGINT) AS n_fallback, CAST(sum(length(CASE WHEN noun_ok AND dir_ok AND no_opposite THEN rewrite ELSE draft END)) AS BIGINT) AS n_chars FROM (
  SELECT *, regexp_matches(rewrite, '(?i)\\b(' || noun || ')\\b') AS noun_ok, regexp_matches(rewrite, '(?i)\\b(' || ({_case(N.KEEP)}) || ')\\b') AS dir_ok, NOT regexp_matches(rewrite, '(?i)\\b(' || ({_case(N.AVOID)}) || ')\\b') AS no_opposite FROM rewrites) GROUP BY ALL""",
    worded=_WORDED,
    rewrites=_REWRITES,
)
def inst_checks(spark, sf):
    r = resolved(spark, sf)
    return r.groupBy(F.col("check.noun_ok").alias("noun_ok"), F.col("check.dir_ok").alias("dir_ok"), F.col("check.no_opposite").alias("no_opposite")).agg(
        F.count("*").alias("n"), F.sum(F.col("used_fallback").cast("long")).alias("n_fallback"), F.sum(F.char_length("final_text")).alias("n_chars")
    )


@query(
    "inst_report",
    f"""SELECT count(*) AS n, {r6_sql("avg(CAST(noun_ok AND dir_ok AND clean AS INT))")} AS acceptance, CAST(sum(CAST(NOT noun_ok AS INT)) AS BIGINT) AS noun_lost, CAST(sum(CAST(NOT dir_ok AS INT)) AS BIGINT) AS direction_lost, CAST(sum(CAST(NOT clean AS INT)) AS BIGINT) AS opposite_added FROM (
  SELECT regexp_matches(rewrite, '(?i)\\b(' || noun || ')\\b') AS noun_ok, regexp_matches(rewrite, '(?i)\\b(' || ({_case(N.KEEP)}) || ')\\b') AS dir_ok, NOT regexp_matches(rewrite, '(?i)\\b(' || ({_case(N.AVOID)}) || ')\\b') AS clean FROM rewrites)""",
    worded=_WORDED,
    rewrites=_REWRITES,
)
def inst_report(spark, sf):
    return N.wording_report(resolved(spark, sf)).select("n", r6("acceptance").alias("acceptance"), "noun_lost", "direction_lost", "opposite_added")


# Geometric proofs: targets in scenes of twelve, seen from the middle of a room of ten metres.
NEAR, MARGIN, GAP = 2.0, 20.0, 2
_QUARTER = f"['ahead', 'left', 'behind', 'right'][1 + CAST(((floor(round((({_WRAP.format(a='atan2(y - 5.0, x - 5.0)')}) + pi() / 4) / (pi() / 2), 9))::BIGINT % 4) + 4) % 4 AS INT)]"
_PROOFS = {
    "v_places": "SELECT p_partkey AS target, p_partkey // 12 AS scene, split_part(p_name, ' ', 2) AS category, (p_partkey * 7919 % 1000)::DOUBLE / 100 AS x, (p_partkey * 104729 % 1000)::DOUBLE / 100 AS y, p_retailprice AS price, p_size AS size FROM part",
    "sided": f"SELECT *, {_QUARTER} AS sector FROM v_places",
    "counted": "SELECT *, count(*) OVER (PARTITION BY scene, category) AS n_cat, count(*) OVER (PARTITION BY scene, category, sector) AS n_side, row_number() OVER p AS pr, lead(price) OVER p - price AS pgap, size - lag(size) OVER z AS before, lead(size) OVER z - size AS after FROM sided WINDOW p AS (PARTITION BY scene, category ORDER BY price, target), z AS (PARTITION BY scene, category ORDER BY size, target)",
    "anchored": f"SELECT DISTINCT target FROM (SELECT i.target, count(*) OVER (PARTITION BY a.target, i.category) AS k FROM counted a JOIN counted i ON a.scene = i.scene AND a.category <> i.category AND (a.x - i.x) ** 2 + (a.y - i.y) ** 2 <= {NEAR * NEAR} WHERE a.n_cat = 1) WHERE k = 1",
    "proofs": f"SELECT target, n_cat = 1 AS is_base, n_side = 1 AS is_direction, target IN (SELECT target FROM anchored) AS is_relation, coalesce(pr = 1 AND pgap > {MARGIN}, false) AS is_extremum, n_cat >= 2 AND coalesce(before >= {GAP}, true) AND coalesce(after >= {GAP}, true) AS is_ordinal FROM counted",
}
KINDS = ("base", "direction", "relation", "extremum", "ordinal")


@query(
    "inst_proofs",
    "SELECT CASE WHEN is_ordinal THEN 'ordinal' WHEN is_extremum THEN 'extremum' WHEN is_relation THEN 'relation' WHEN is_direction THEN 'direction' WHEN is_base THEN 'base' END AS instr_type, count(*) AS n, "
    + ", ".join(f"CAST(sum(CAST(is_{k} AS INT)) AS BIGINT) AS n_{k}" for k in KINDS)
    + " FROM proofs GROUP BY 1",
    **_PROOFS,
)
def inst_proofs(spark, sf):
    """The proof that each target admits, and the label that follows."""
    p = C.load(spark, sf, "part")
    place = lambda m: (F.col("p_partkey") * m % 1000) / 100
    inst = p.select(F.col("p_partkey").alias("target"), F.floor(F.col("p_partkey") / 12).alias("scene"), F.split("p_name", " ")[1].alias("category"), place(7919).alias("x"), place(104729).alias("y"), F.lit(0.0).alias("z"), F.col("p_retailprice").alias("price"), F.col("p_size").alias("size"))
    inst = kept(inst.withColumn("sector", N.sector_uniform(F.atan2(F.col("y") - 5.0, F.col("x") - 5.0))))
    out = Y.prove_base(inst).select("target", "is_base")
    found = {"direction": Y.prove_direction(inst), "relation": Y.prove_relation(inst, NEAR), "extremum": Y.prove_extremum(inst, "price", True, MARGIN), "ordinal": Y.prove_ordinal(inst, "size", GAP, 2)}
    for kind, ok in found.items():
        out = out.join(ok.select("target").distinct().withColumn(f"is_{kind}", F.lit(True)), "target", "left").withColumn(f"is_{kind}", F.coalesce(f"is_{kind}", F.lit(False)))
    return Y.label_instruction(out).groupBy("instr_type").agg(F.count("*").alias("n"), *[F.sum(F.col(f"is_{k}").cast("long")).alias(f"n_{k}") for k in KINDS])


@query(
    "inst_arrival",
    "SELECT confirmed, n_checked, count(*) AS n FROM (SELECT episode_id, bool_or(visible) AS confirmed, count(*) AS n_checked FROM (SELECT *, n_steps - t + 1 AS b FROM v_steps) WHERE b IN (1, 3, 6, 10) GROUP BY episode_id) GROUP BY ALL",
)
def inst_arrival(spark, sf):
    return N.arrival_check(C.v_steps(spark, sf)).groupBy("confirmed", "n_checked").agg(F.count("*").alias("n"))


@query("ep_keyframes", "SELECT episode_id, t FROM v_steps WHERE list_contains([1 + CAST(floor(i * (n_steps - 1)::DOUBLE / 5 + 0.5::DOUBLE) AS INT) for i in range(6)], t)")
def ep_keyframes(spark, sf):
    return E.keyframes(C.v_steps(spark, sf)).select("episode_id", "t")


@query(
    "ep_motion",
    """SELECT motion, count(*) AS n_runs, CAST(max(n) AS BIGINT) AS longest FROM (SELECT episode_id, run, motion, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY episode_id ORDER BY t) AS run FROM (
  SELECT *, CASE WHEN motion IS DISTINCT FROM lag(motion) OVER (PARTITION BY episode_id ORDER BY t) THEN 1 ELSE 0 END AS new FROM (SELECT episode_id, t, CASE WHEN turn_rad > 0.2 THEN 'left' WHEN turn_rad < -0.2 THEN 'right' ELSE 'forward' END AS motion FROM v_steps))) GROUP BY ALL) GROUP BY motion""",
)
def ep_motion(spark, sf):
    return E.motion_summary(C.v_steps(spark, sf)).groupBy("motion").agg(F.count("*").alias("n_runs"), F.max("n").alias("longest"))

"""Views that let the stored tables stand for navigation logs, and their SQL twins.

Nothing here claims that the tables are navigation data; each view says what it substitutes.
``SQL`` has the same views for DuckDB, and ``with_views`` puts those a query needs before it.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions import geometry as G
from navspark.functions.core import PI, once, wrap_angle
from navspark.sources.io import load

SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
OUTDOOR = "MIDDLE EAST"  #: the region that stands for outdoor scenes
CHUNK = 10
FOV = 120.0


def events(spark: SparkSession, sf: str) -> DataFrame:
    e = load(spark, sf, "events")
    return e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("episode_id"), "event_type", "value", F.from_json("props", "k int").k.alias("k"))


def steps_from(e: DataFrame) -> DataFrame:
    """Decision steps of tracking episodes: an episode is a user's events in time order."""
    by = W.partitionBy("episode_id")
    t = F.row_number().over(by.orderBy("ts", "event_id"))
    e = e.withColumn("t", t).withColumn("n_steps", F.count("*").over(by).cast("int"))
    k = F.col("k").cast("double")
    return e.select(
        "episode_id",
        "t",
        "n_steps",
        "ts",
        "event_id",
        "event_type",
        "k",
        (F.col("value") / 25).alias("range_m"),
        ((k - 49.5) / 49.5 * 0.7).alias("bearing_rad"),
        (F.col("event_type") != "error").alias("visible"),
        ((F.col("event_type") == "error") & (F.col("k") < 3)).alias("collision"),
        ((F.col("event_type") == "purchase") & (F.col("t") == F.col("n_steps"))).alias("stop"),
        ((F.col("event_type") == "signup") & (F.col("k") >= 90)).alias("stuck"),
        ((k - 49.5) / 49.5 * (PI / 6)).alias("turn_rad"),
        (F.least("value", F.lit(100.0)) / 100).alias("fwd_m"),
        (k / 99).alias("u"),
        (F.least("value", F.lit(200.0)) / 200).alias("v"),
        (((F.col("k") * 7 % 100).cast("double") - 49.5) / 49.5 * (2 * PI / 3)).alias("target_rad"),
    )


def v_steps(spark: SparkSession, sf: str) -> DataFrame:
    return steps_from(events(spark, sf))


def planned_steps(spark: SparkSession, sf: str) -> DataFrame:
    """Steps with ``plan_ade``: how far the plan of a step lies from the privileged one.

    The plan emitted holds the step's own motion for ten steps; the privileged plan knows the ten
    steps that follow. Null where fewer than ten follow.
    """
    frame = W.partitionBy("episode_id").orderBy("t").rowsBetween(0, CHUNK - 1)
    inc = F.array("fwd_m", F.lit(0.0), "turn_rad")
    s = v_steps(spark, sf).withColumn("_z", F.flatten(F.collect_list(inc).over(frame))).withColumn("_plan", F.flatten(F.array_repeat(inc, CHUNK)))
    whole = F.col("t") + (CHUNK - 1) <= F.col("n_steps")
    return s.withColumn("plan_ade", F.when(whole, G.ade("_z", "_plan"))).drop("_z", "_plan")


def v_chunks(spark: SparkSession, sf: str) -> DataFrame:
    """Ten following steps as one chunk of 30 doubles; frames cut short at the end are left out."""
    frame = W.partitionBy("episode_id").orderBy("t").rowsBetween(0, CHUNK - 1)
    s = v_steps(spark, sf).select("episode_id", "t", "event_id", "n_steps", F.array("fwd_m", F.lit(0.0), "turn_rad").alias("inc"))
    s = s.withColumn("z", F.flatten(F.collect_list("inc").over(frame)))
    return s.where(F.col("t") + (CHUNK - 1) <= F.col("n_steps")).select(F.col("event_id").alias("chunk_id"), "episode_id", "t", "z")


def v_traj(spark: SparkSession, sf: str) -> DataFrame:
    e = load(spark, sf, "embeddings")
    return e.select(F.col("vec_id").alias("traj_id"), F.slice("embedding", 1, 30).cast("array<double>").alias("z"), F.col("label").alias("cluster"))


def v_frames(spark: SparkSession, sf: str) -> DataFrame:
    """Frames without their grids; ``grid_id`` leads to the grid, joined late to survivors only."""
    n = load(spark, sf, "embeddings").count()
    s = v_steps(spark, sf)
    return s.select("episode_id", "t", "ts", "event_id", F.pmod("event_id", F.lit(n)).alias("grid_id"))


def grids(spark: SparkSession, sf: str) -> DataFrame:
    e = load(spark, sf, "embeddings")
    return e.select(F.col("vec_id").alias("grid_id"), F.col("embedding").cast("array<double>").alias("grid"))


def v_rollouts(spark: SparkSession, sf: str) -> DataFrame:
    o, c, n, r = (load(spark, sf, x) for x in ("orders", "customer", "nation", "region"))
    j = o.join(c, o.o_custkey == c.c_custkey).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    segment = F.array_position(F.array(*map(F.lit, SEGMENTS)), F.col("c_mktsegment")) - 1
    difficulty = (F.col("o_custkey") % 5).cast("double") / 4
    stop = F.col("o_orderkey") % 10 != 0
    return j.select(
        F.col("o_orderkey").alias("episode_id"),
        F.col("o_custkey").alias("seed_id"),
        F.row_number().over(W.partitionBy("o_custkey").orderBy("o_orderkey")).alias("g"),
        (F.col("c_nationkey") * 5 + segment).cast("int").alias("scene_id"),
        F.col("r_name").alias("scene_type"),
        F.col("o_orderpriority").alias("instr_type"),
        F.col("c_mktsegment").alias("setting"),
        ((F.col("o_totalprice") % 1000) / 100 * difficulty).alias("goal_dist_m"),
        stop.alias("stop_called"),
        (~stop).alias("timeout"),
    )


def v_path(spark: SparkSession, sf: str) -> DataFrame:
    """Executed and reference points (x, y) and (rx, ry) of each rollout, i = 0 at the origin; heading is that after step i."""
    ro = v_rollouts(spark, sf).select("episode_id", "goal_dist_m")
    li = load(spark, sf, "lineitem")
    order = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
    inc = li.select(
        F.col("l_orderkey").alias("episode_id"),
        F.row_number().over(W.partitionBy("l_orderkey").orderBy(*order)).alias("i"),
        (F.col("l_quantity") / 50).alias("dx"),
        ((F.col("l_tax") - 0.04) * 10).alias("dy"),
        ((F.col("l_discount") - 0.05) * 10).alias("dth"),
    )
    inc = inc.unionByName(ro.select("episode_id", F.lit(0).alias("i"), F.lit(0.0).alias("dx"), F.lit(0.0).alias("dy"), F.lit(0.0).alias("dth")))
    by = W.partitionBy("episode_id").orderBy("i")
    until = by.rowsBetween(W.unboundedPreceding, 0)
    h = F.coalesce(F.sum("dth").over(by.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    inc = inc.withColumn("h", h).withColumn("sx", F.col("dx") * F.cos("h") - F.col("dy") * F.sin("h")).withColumn("sy", F.col("dx") * F.sin("h") + F.col("dy") * F.cos("h"))
    p = inc.select("episode_id", "i", F.sum("sx").over(until).alias("x"), F.sum("sy").over(until).alias("y"), (F.col("h") + F.col("dth")).alias("heading"))
    whole = W.partitionBy("episode_id")
    p = p.withColumn("n", F.max("i").over(whole)).withColumn("ex", F.max_by("x", "i").over(whole)).withColumn("ey", F.max_by("y", "i").over(whole))
    p = p.join(ro, "episode_id").withColumn("gx", F.col("ex") + F.col("goal_dist_m")).withColumn("gy", F.col("ey"))
    part = F.when(F.col("n") == 0, F.lit(1.0)).otherwise(F.col("i") / F.col("n"))
    return p.select("episode_id", "i", "n", "x", "y", (F.col("gx") * part).alias("rx"), (F.col("gy") * part).alias("ry"), "gx", "gy", "heading")


def v_views(spark: SparkSession, sf: str) -> DataFrame:
    """Detections: true point, viewpoint, and the projected heading, u, v and depth."""
    li, p = load(spark, sf, "lineitem"), load(spark, sf, "part")
    j = li.join(p, li.l_partkey == p.p_partkey)
    spread = 1 + F.col("l_partkey") % 3
    j = j.select(
        F.md5(F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")])).alias("obs_id"),
        (F.col("l_suppkey") % 10).cast("int").alias("scene"),
        F.col("l_suppkey").alias("viewpoint"),
        F.col("p_type").alias("category"),
        ((F.col("l_partkey") * 7919 % 1000) / 10 + (F.col("l_discount") - 0.05) * 6 * spread).alias("x"),
        ((F.col("l_partkey") * 104729 % 1000) / 10 + (F.col("l_tax") - 0.04) * 7.5 * spread).alias("y"),
        (F.col("p_size") / 25).alias("z"),
        ((F.col("l_suppkey") * 31 % 1000) / 10).alias("px"),
        ((F.col("l_suppkey") * 57 % 1000) / 10).alias("py"),
        F.col("l_partkey").alias("part_key"),
    )
    bearing = wrap_angle(F.atan2(F.col("y") - F.col("py"), F.col("x") - F.col("px")))
    j = j.withColumn("heading", once(F.pmod(F.floor(F.round((bearing + PI / 4) / (PI / 2), 9)), F.lit(4)).cast("int")))
    yaw = F.col("heading") * (PI / 2)
    dx, dy = F.col("x") - F.col("px"), F.col("y") - F.col("py")
    j = j.withColumns({"depth": once(dx * F.cos(yaw) + dy * F.sin(yaw)), "side": once(dy * F.cos(yaw) - dx * F.sin(yaw))})
    f = 0.28867513459481287  # 1 / (2 tan 60 deg)
    ok = F.col("depth") > 1e-9
    return j.select("*", F.when(ok, F.lit(0.5) - F.lit(f) * F.col("side") / F.col("depth")).alias("u"), F.when(ok, F.lit(0.5) - F.lit(f) * (F.col("z") - 1.0) / F.col("depth")).alias("v")).drop("side")


METHODS, FAMILIES = ("ours", "init_backbone", "no_pointing", "ours_full"), ("er", "mono", "ablation")


def v_results(spark: SparkSession, sf: str) -> DataFrame:
    """Result rows in the shape of ``published``: orders stand for episodes, their customer for the method and its family."""
    o = load(spark, sf, "orders")
    pick = lambda names, i: F.get(F.array(*map(F.lit, names)), i.cast("int"))
    g = o.groupBy(
        pick(METHODS, F.col("o_custkey") % 4).alias("method"), pick(FAMILIES, F.floor(F.col("o_custkey") / 4) % 3).alias("family"), F.concat(F.lit("s"), (F.col("o_orderkey") % 8).cast("string")).alias("setting")
    ).agg((F.sum((F.col("o_orderkey") % 10 != 0).cast("long")) * 100 / F.count("*")).alias("sr"), F.avg(F.col("o_totalprice") % 1000 / 100).alias("ne"))
    both = F.explode(F.array(F.struct(F.lit("SR").alias("metric"), F.round("sr", 4).alias("value")), F.struct(F.lit("NE").alias("metric"), F.round("ne", 4).alias("value"))))
    return g.select("method", "family", "setting", both.alias("_m")).select("method", "family", "setting", "_m.metric", "_m.value")


def v_samples(spark: SparkSession, sf: str) -> DataFrame:
    d, lab = load(spark, sf, "documents"), load(spark, sf, "labels")
    return d.select("doc_id", "source", "lang", "n_chars").join(lab, "doc_id", "left").select(
        F.col("doc_id").alias("sample_id"), "source", "lang", F.ceil(F.col("n_chars") / 4).cast("int").alias("n_tok"), "quality", "toxic"
    )


def v_turns(spark: SparkSession, sf: str) -> DataFrame:
    c = load(spark, sf, "conversations")
    return c.select("conv_id", F.col("turn").cast("int").alias("turn"), "role", "text", F.ceil(F.char_length("text") / 4).cast("int").alias("n_tok"))


def v_targets(spark: SparkSession, sf: str) -> DataFrame:
    p = load(spark, sf, "part")
    words = F.split("p_name", " ")
    return p.select(F.col("p_partkey").alias("part_key"), words[1].alias("head_noun"), words[0].alias("modifier"), F.col("p_type").alias("category"), F.col("p_size").alias("size"), F.col("p_retailprice").alias("rank_key"))


_SEG = "CASE c_mktsegment " + " ".join(f"WHEN '{s}' THEN {i}" for i, s in enumerate(SEGMENTS)) + " END"

SQL = {
    "v_steps": """SELECT episode_id, CAST(t AS INT) AS t, CAST(n_steps AS INT) AS n_steps, ts, event_id, event_type, k, value / 25 AS range_m, (k::DOUBLE - 49.5) / 49.5 * 0.7 AS bearing_rad,
  event_type <> 'error' AS visible, event_type = 'error' AND k < 3 AS collision, event_type = 'purchase' AND t = n_steps AS stop, event_type = 'signup' AND k >= 90 AS stuck,
  (k::DOUBLE - 49.5) / 49.5 * (pi() / 6) AS turn_rad, least(value, 100.0::DOUBLE) / 100 AS fwd_m, k::DOUBLE / 99 AS u, least(value, 200.0::DOUBLE) / 200 AS v, ((k * 7) % 100 - 49.5::DOUBLE) / 49.5::DOUBLE * (2 * pi() / 3) AS target_rad
  FROM (SELECT user_id AS episode_id, event_id, ts, event_type, value, CAST(regexp_extract(props, '([0-9]+)', 1) AS INT) AS k, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS t, count(*) OVER (PARTITION BY user_id) AS n_steps FROM events)""",
    "v_chunk_rows": """SELECT a.event_id AS chunk_id, a.episode_id, a.t, b.t - a.t AS i, b.fwd_m AS dx, 0.0::DOUBLE AS dy, b.turn_rad AS dth
  FROM v_steps a JOIN v_steps b ON a.episode_id = b.episode_id AND b.t BETWEEN a.t AND a.t + 9 WHERE a.t + 9 <= a.n_steps""",
    "v_traj_rows": """SELECT vec_id AS traj_id, i, CAST(embedding[3 * i + 1] AS DOUBLE) AS dx, CAST(embedding[3 * i + 2] AS DOUBLE) AS dy, CAST(embedding[3 * i + 3] AS DOUBLE) AS dth
  FROM embeddings, range(10) AS r(i)""",
    "v_rollouts": f"""SELECT o_orderkey AS episode_id, o_custkey AS seed_id, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS INT) AS g, CAST(c_nationkey * 5 + {_SEG} AS INT) AS scene_id,
  r_name AS scene_type, o_orderpriority AS instr_type, c_mktsegment AS setting, (o_totalprice % 1000) / 100 * ((o_custkey % 5)::DOUBLE / 4) AS goal_dist_m, o_orderkey % 10 <> 0 AS stop_called, o_orderkey % 10 = 0 AS timeout
  FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
    "v_path": """SELECT episode_id, i, n, x, y, gx * part AS rx, gy * part AS ry, gx, gy FROM (
  SELECT episode_id, i, n, x, y, ex + goal_dist_m AS gx, ey AS gy, CASE WHEN n = 0 THEN 1.0::DOUBLE ELSE i::DOUBLE / n END AS part FROM (
   SELECT q.*, max(i) OVER e AS n, arg_max(x, i) OVER e AS ex, arg_max(y, i) OVER e AS ey, r.goal_dist_m FROM (
    SELECT episode_id, i, sum(dx * cos(h) - dy * sin(h)) OVER c AS x, sum(dx * sin(h) + dy * cos(h)) OVER c AS y FROM (
     SELECT *, coalesce(sum(dth) OVER (PARTITION BY episode_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0::DOUBLE) AS h FROM (
      SELECT l_orderkey AS episode_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice, l_quantity, l_discount, l_tax, l_returnflag, l_linestatus) AS i,
        l_quantity / 50 AS dx, (l_tax - 0.04::DOUBLE) * 10 AS dy, (l_discount - 0.05::DOUBLE) * 10 AS dth FROM lineitem
      UNION ALL SELECT episode_id, 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE FROM v_rollouts))
    WINDOW c AS (PARTITION BY episode_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)) q
   JOIN v_rollouts r ON q.episode_id = r.episode_id WINDOW e AS (PARTITION BY q.episode_id)))""",
    "v_views": """SELECT *, CASE WHEN depth > 1e-9 THEN 0.5::DOUBLE - 0.28867513459481287::DOUBLE * side / depth END AS u, CASE WHEN depth > 1e-9 THEN 0.5::DOUBLE - 0.28867513459481287::DOUBLE * (z - 1.0::DOUBLE) / depth END AS v FROM (
  SELECT *, (x - px) * cos(heading * (pi() / 2)) + (y - py) * sin(heading * (pi() / 2)) AS depth, (y - py) * cos(heading * (pi() / 2)) - (x - px) * sin(heading * (pi() / 2)) AS side FROM (
   SELECT *, CAST(((floor(round((atan2(y - py, x - px) + pi() / 4) / (pi() / 2), 9))::BIGINT % 4) + 4) % 4 AS INT) AS heading FROM (
    SELECT md5(concat_ws('|', CAST(l_orderkey AS VARCHAR), CAST(l_linenumber AS VARCHAR), CAST(l_partkey AS VARCHAR), CAST(l_suppkey AS VARCHAR))) AS obs_id, CAST(l_suppkey % 10 AS INT) AS scene, l_suppkey AS viewpoint, p_type AS category,
     (l_partkey * 7919 % 1000)::DOUBLE / 10 + (l_discount - 0.05::DOUBLE) * 6 * (1 + l_partkey % 3) AS x, (l_partkey * 104729 % 1000)::DOUBLE / 10 + (l_tax - 0.04::DOUBLE) * 7.5::DOUBLE * (1 + l_partkey % 3) AS y, p_size::DOUBLE / 25 AS z,
     (l_suppkey * 31 % 1000)::DOUBLE / 10 AS px, (l_suppkey * 57 % 1000)::DOUBLE / 10 AS py, l_partkey AS part_key FROM lineitem JOIN part ON l_partkey = p_partkey)))""",
    "v_result_means": f"""SELECT {list(METHODS)}[1 + o_custkey % 4] AS method, {list(FAMILIES)}[1 + o_custkey // 4 % 3] AS family, 's' || CAST(o_orderkey % 8 AS VARCHAR) AS setting,
  round(count(*) FILTER (WHERE o_orderkey % 10 <> 0) * 100.0::DOUBLE / count(*), 4) AS sr, round(avg(o_totalprice % 1000 / 100), 4) AS ne FROM orders GROUP BY ALL""",
    "v_results": "SELECT method, family, setting, 'SR' AS metric, sr AS value FROM v_result_means UNION ALL SELECT method, family, setting, 'NE', ne FROM v_result_means",
    "v_samples": "SELECT d.doc_id AS sample_id, source, lang, CAST(ceil(n_chars / 4.0::DOUBLE) AS INT) AS n_tok, quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
    "v_turns": "SELECT conv_id, CAST(turn AS INT) AS turn, role, text, CAST(ceil(length(text) / 4.0::DOUBLE) AS INT) AS n_tok FROM conversations",
    "v_targets": "SELECT p_partkey AS part_key, split_part(p_name, ' ', 2) AS head_noun, split_part(p_name, ' ', 1) AS modifier, p_type AS category, p_size AS size, p_retailprice AS rank_key FROM part",
}


def with_views(body: str, **more: str) -> str:
    """``body`` with the views it names before it, in the order they need each other."""
    views = SQL | more
    wanted: list[str] = []

    def want(text: str) -> None:
        for name in views:
            if re.search(rf"\b{name}\b", text) and name not in wanted:
                want(views[name].replace(name, ""))
                wanted.append(name)

    want(body)
    if not wanted:
        return body
    head = ",\n".join(f"{n} AS ({views[n]})" for n in wanted)
    body = body.strip()
    return f"WITH RECURSIVE {head},\n{body[5:]}" if body[:5].upper() == "WITH " else f"WITH RECURSIVE {head}\n{body}"

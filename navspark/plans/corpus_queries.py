"""Mixtures, filters, cameras, packing, token model, ablations, scaling, splits."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import r6, r6_sql, uniform01, uniform01_sql
from navspark.operators import metrics as M
from navspark.operators import mixture as X
from navspark.operators import packing as K
from navspark.operators import taxonomy as Y
from navspark.operators import tokenlm as T
from navspark.operators.ops import sample_fraction
from navspark.plans.base import query
from navspark.plans.perception_queries import SER_VIEWS, renamed, serialized
from navspark.session import kept
from navspark.sources import carriers as C

# --- mixture -----------------------------------------------------------------------------

GROUPS = tuple(X.ER_MASS)
_GRP = f"[{', '.join(repr(g) for g in GROUPS)}][1 + CAST(substr(source, 4) AS INT) % 4]"
_QUOTA = f"""SELECT source, grp, available, CAST(f + CASE WHEN row_number() OVER (ORDER BY round(x - f, 9) DESC, source) <= 1000 - sum(f) OVER () THEN 1 ELSE 0 END AS BIGINT) AS quota FROM (SELECT *, floor(x) AS f FROM (
  SELECT source, grp, available, round(weight / sum(weight) OVER () * 1000, 9) AS x FROM (SELECT source, grp, available, CASE grp {" ".join(f"WHEN '{g}' THEN {m}::DOUBLE" for g, m in X.ER_MASS.items())} END / count(*) OVER (PARTITION BY grp) AS weight FROM (
   SELECT source, {_GRP} AS grp, count(*) AS available FROM v_samples GROUP BY source))))"""


def sources(spark, sf):
    s = C.v_samples(spark, sf)
    grp = F.element_at(F.array(*map(F.lit, GROUPS)), F.substring("source", 4, 9).cast("int") % 4 + 1)
    return s.withColumn("grp", grp)


def quotas(spark, sf, total=1000):
    c = sources(spark, sf).groupBy("source", "grp").agg(F.count("*").alias("available"))
    mass = F.lit(None).cast("double")
    for g, m in X.ER_MASS.items():
        mass = F.when(F.col("grp") == g, F.lit(m)).otherwise(mass)
    c = c.withColumn("weight", mass / F.count("*").over(W.partitionBy("grp")))
    return X.plan_quota(c, total)


@query("mix_quota", "SELECT source, grp, available, quota FROM quotas", quotas=_QUOTA)
def mix_quota(spark, sf):
    return quotas(spark, sf).select("source", "grp", "available", "quota")


_DRAWN = f"""SELECT s.sample_id, s.source, q.grp, CAST(quota // available AS BIGINT) + CASE WHEN row_number() OVER (PARTITION BY s.source ORDER BY {uniform01_sql("s.sample_id", salt="draw")}, s.sample_id) <= quota % available THEN 1 ELSE 0 END AS n FROM v_samples s JOIN quotas q ON s.source = q.source"""


@query("mix_draw", f"SELECT source, grp, CAST(sum(n) AS BIGINT) AS drawn, CAST(sum(CAST(n > 0 AS INT)) AS BIGINT) AS n_unique, CAST(sum(n * sample_id) AS BIGINT) AS id_sum, {r6_sql('sum(n) / (SELECT sum(n) FROM drawn)')} AS share FROM drawn GROUP BY source, grp", quotas=_QUOTA, drawn=_DRAWN)
def mix_draw(spark, sf):
    d = X.draw(sources(spark, sf), quotas(spark, sf))
    g = d.groupBy("source", "grp").agg(F.count("*").alias("drawn"), F.count_distinct("sample_id").alias("n_unique"), F.sum("sample_id").alias("id_sum"))
    return g.crossJoin(F.broadcast(d.agg(F.count("*").alias("_n")))).select("source", "grp", "drawn", "n_unique", "id_sum", r6(F.col("drawn") / F.col("_n")).alias("share"))


@query(
    "mix_report",
    f"SELECT task, grp, source, CAST(sum(n) AS BIGINT) AS n, CAST(sum(CAST(n > 0 AS INT)) AS BIGINT) AS n_unique, CAST(grouping_id(task, grp, source) AS INT) AS level, {r6_sql('sum(n) / (SELECT sum(n) FROM drawn)')} AS share FROM (SELECT 'reasoning' AS task, * FROM drawn) GROUP BY ROLLUP (task, grp, source)",
    quotas=_QUOTA,
    drawn=_DRAWN,
)
def mix_report(spark, sf):
    d = X.draw(sources(spark, sf).withColumn("task", F.lit("reasoning")), quotas(spark, sf))
    return X.mixture_report(d).select("task", "grp", "source", "n", "n_unique", F.col("level").cast("int").alias("level"), r6("share").alias("share"))


@query(
    "mix_bernoulli",
    f"SELECT grp, CAST(sum(floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END) AS BIGINT) AS n FROM (SELECT q.grp, quota::DOUBLE / available AS rate, {uniform01_sql('s.sample_id', salt='draw')} AS u FROM v_samples s JOIN quotas q ON s.source = q.source) GROUP BY grp HAVING sum(floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END) > 0",
    quotas=_QUOTA,
)
def mix_bernoulli(spark, sf):
    return X.draw_bernoulli(sources(spark, sf), quotas(spark, sf)).groupBy("grp").agg(F.count("*").alias("n"))


TASKS = tuple(X.NAV_SOURCES)
#: Customers stand for sources, their orders for samples.
_SOURCES = f"SELECT o_custkey AS source, {list(GROUPS)}[1 + o_custkey % 4] AS grp, {list(TASKS)}[1 + o_custkey % 3] AS task, CASE WHEN o_custkey % 5 = 0 THEN 'action' ELSE 'rehearsal' END AS kind, count(*) AS n_rows FROM orders GROUP BY o_custkey"


def customer_sources(spark, sf):
    c = F.col("source")
    s = C.load(spark, sf, "orders").groupBy(F.col("o_custkey").alias("source")).agg(F.count("*").alias("n_rows"))
    grp, task = (F.element_at(F.array(*map(F.lit, names)), (c % len(names)).cast("int") + 1) for names in (GROUPS, TASKS))
    return s.select("source", grp.alias("grp"), task.alias("task"), F.when(c % 5 == 0, "action").otherwise("rehearsal").alias("kind"), "n_rows")


@query(
    "mix_curriculum",
    "SELECT stage, w.grp, weight, n_rows FROM ("
    + " UNION ALL ".join([f"SELECT 1 AS stage, '{g}' AS grp, {r6_sql(str(m / 100))} AS weight" for g, m in X.ER_MASS.items()] + [f"SELECT 2, 'action', {r6_sql('0.776')}"] + [f"SELECT 2, '{g}', {r6_sql(f'0.224 * {m / 100}')}" for g, m in X.ER_MASS.items()])
    + ") AS w JOIN (SELECT 1 AS stage, grp, CAST(sum(n_rows) AS BIGINT) AS n_rows FROM sources GROUP BY grp UNION ALL SELECT 2, CASE WHEN kind = 'action' THEN kind ELSE grp END, CAST(sum(n_rows) AS BIGINT) FROM sources GROUP BY ALL) AS c USING (stage, grp)",
    sources=_SOURCES,
)
def mix_curriculum(spark, sf):
    """Groups of each stage with their weights and the samples there are."""
    s, out = customer_sources(spark, sf), None
    for stage, grp in ((1, F.col("grp")), (2, F.when(F.col("kind") == "action", F.col("kind")).otherwise(F.col("grp")))):
        have = s.groupBy(grp.alias("grp")).agg(F.sum("n_rows").alias("n_rows"))
        one = have.join(F.broadcast(X.curriculum(spark, stage)), "grp").select(F.lit(stage).alias("stage"), "grp", r6("weight").alias("weight"), "n_rows")
        out = one if out is None else out.unionByName(one)
    return out


@query("mix_registry", "SELECT grp, count(*) AS n, count(*) FILTER (WHERE grp IN ('image_vqa', 'video')) AS n_multi FROM sources GROUP BY grp", sources=_SOURCES)
def mix_registry(spark, sf):
    r = customer_sources(spark, sf).select("source", "grp")
    return r.join(X.tag_multi_image(r), "source", "left").groupBy("grp").agg(F.count("*").alias("n"), F.count("subset").alias("n_multi"))


@query("nav_registry", "SELECT task, count(*) AS n, CAST(sum(n_rows) AS BIGINT) AS n_rows FROM sources GROUP BY task", sources=_SOURCES)
def nav_registry(spark, sf):
    return customer_sources(spark, sf).groupBy("task").agg(F.count("*").alias("n"), F.sum("n_rows").alias("n_rows"))


_MASS_SQL = "CASE grp " + " ".join(f"WHEN '{g}' THEN {m}::DOUBLE" for g, m in (X.ER_MASS | X.SFT_MASS).items()) + " END / 100 / count(*)"


@query("mix_weights", f"SELECT stage, grp, count(*) AS n, {r6_sql(_MASS_SQL, 9)} AS weight FROM (SELECT 1 AS stage, grp FROM sources UNION ALL SELECT 2, kind FROM sources) GROUP BY stage, grp", sources=_SOURCES)
def mix_weights(spark, sf):
    """Sources of each stage by group, and the weight of one source."""
    s = customer_sources(spark, sf)
    every = X.spread(s.select("source", "grp"), X.ER_MASS).withColumn("stage", F.lit(1)).unionByName(X.spread(s.select("source", F.col("kind").alias("grp")), X.SFT_MASS).withColumn("stage", F.lit(2)))
    return every.groupBy("stage", "grp").agg(F.count("*").alias("n"), r6(F.min("weight"), 9).alias("weight"))


_LABELLED = "SELECT s.episode_id, s.t, s.n_steps, s.event_id AS sample_id, s.visible, s.stop AND s.t = s.n_steps AND s.visible AS fstop, s.stop, e.label AS cluster FROM v_steps s JOIN embeddings e ON e.vec_id = s.event_id % (SELECT count(*) FROM embeddings)"
_STAGE = "SELECT {i} AS stage, count(*) AS n_rows, " + r6_sql("avg(CAST({stop} AS INT))") + " AS stop_share, " + r6_sql("(SELECT max(c) FROM (SELECT count(*) AS c FROM {v} GROUP BY cluster)) / count(*)") + " AS max_cluster_share FROM {v}"
QC_VIEWS = {
    "labelled": _LABELLED,
    "seen": "SELECT * FROM labelled WHERE episode_id IN (SELECT episode_id FROM labelled WHERE visible)",
    "capped": f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY {uniform01_sql('sample_id', salt='cap')}, sample_id) AS r FROM seen) WHERE r <= (SELECT min(c) FROM (SELECT count(*) AS c FROM seen GROUP BY cluster))",
    "stopped": f"SELECT * FROM capped WHERE NOT fstop UNION ALL SELECT * EXCLUDE (q) FROM (SELECT *, row_number() OVER (ORDER BY {uniform01_sql('sample_id', salt='cap')}, sample_id) AS q FROM capped WHERE fstop) WHERE q <= (SELECT floor(round(count(*) * (0.02::DOUBLE / 0.98), 9)) FROM capped WHERE NOT fstop)",
}


def labelled_steps(spark, sf):
    s = C.v_steps(spark, sf)
    e = C.load(spark, sf, "embeddings")
    n = e.count()
    j = s.join(e.select(F.col("vec_id"), F.col("label").alias("cluster")), F.pmod("event_id", F.lit(n)) == F.col("vec_id"))
    return j.select("episode_id", "t", "n_steps", F.col("event_id").alias("sample_id"), "visible", "stop", "cluster")


def _stage(i, df):
    """Counts of a stage in one scan: clusters first, then their sums and their largest."""
    per = df.groupBy("cluster").agg(F.count("*").alias("m"), F.sum(F.col("stop").cast("long")).alias("s"))
    a = per.agg(F.coalesce(F.sum("m"), F.lit(0)).alias("n_rows"), F.sum("s").alias("s"), F.max("m").alias("m"))
    return a.select(F.lit(i).alias("stage"), "n_rows", r6(F.col("s") / F.col("n_rows")).alias("stop_share"), r6(F.col("m") / F.col("n_rows")).alias("max_cluster_share"))


@query("qc_chain", " UNION ALL ".join(_STAGE.format(i=i, v=v, stop=s) for i, (v, s) in enumerate((("labelled", "stop"), ("labelled", "fstop"), ("seen", "fstop"), ("capped", "fstop"), ("stopped", "fstop")))), **QC_VIEWS)
def qc_chain(spark, sf):
    raw = kept(labelled_steps(spark, sf))
    f = X.filter_stop(raw)
    seen = kept(X.drop_unseen(f))
    capped = kept(X.cap_clusters(seen)[0])
    stopped = X.cap_stop(capped)
    out = None
    for i, d in enumerate((raw, f, seen, capped, stopped)):
        out = _stage(i, d) if out is None else out.unionByName(_stage(i, d))
    return out


@query("qc_balanced")
def qc_balanced(spark, sf):
    """The whole chain to its fixed point over 32 finer clusters, where both caps can hold."""
    s = kept(labelled_steps(spark, sf).withColumn("cluster", F.pmod(F.xxhash64("sample_id"), F.lit(32))))
    d, info = X.balanced_index(s)
    return _stage(0, d).withColumns({"cap": F.lit(info["cap"]), "feasible": F.lit(info["feasible"]), "rounds": F.lit(info["rounds"])})


@query(
    "camera_draw",
    " UNION ALL ".join(f"SELECT '{c}' AS parameter, count(*) AS n, {r6_sql('min(x)')} AS low, {r6_sql('avg(x)')} AS mean, {r6_sql('max(x)')} AS high FROM (SELECT {lo}::DOUBLE + ({hi - lo}::DOUBLE) * {uniform01_sql('o_orderkey', salt='cam-' + c)} AS x FROM orders)" for c, (lo, hi) in X.CAMERA.items()),
)
def camera_draw(spark, sf):
    o = X.randomize_camera(C.load(spark, sf, "orders").select(F.col("o_orderkey").alias("episode_id")))
    out = None
    for c in X.CAMERA:
        one = o.agg(F.count("*").alias("n"), r6(F.min(c)).alias("low"), r6(F.avg(c)).alias("mean"), r6(F.max(c)).alias("high")).select(F.lit(c).alias("parameter"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "onpolicy_round",
    "SELECT origin, count(*) AS n FROM (SELECT DISTINCT k, 'expert' AS origin FROM (SELECT event_type || '/' || (k // 10) AS k, visible FROM v_steps) WHERE visible UNION ALL SELECT DISTINCT k, 'policy' FROM (SELECT event_type || '/' || (k // 10) AS k, visible FROM v_steps) WHERE NOT visible AND k NOT IN (SELECT event_type || '/' || (k // 10) FROM v_steps WHERE visible)) GROUP BY origin",
)
def onpolicy_round(spark, sf):
    s = C.v_steps(spark, sf).select(F.concat_ws("/", "event_type", F.floor(F.col("k") / 10).cast("string")).alias("state_key"), "visible")
    expert = s.where("visible").select("state_key", F.lit("forward").alias("action"), F.lit(0).alias("round"), F.lit("expert").alias("origin")).dropDuplicates(["state_key"])
    labels = s.select("state_key").distinct().withColumn("action", F.lit("stop"))
    return X.aggregate_onpolicy(expert, s.where(~F.col("visible")), labels, 1).groupBy("origin").agg(F.count("*").alias("n"))


@query("top_targets", "SELECT p_name AS name, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_name ORDER BY n DESC, name LIMIT 50")
def top_targets(spark, sf):
    li, p = C.load(spark, sf, "lineitem").select("l_partkey"), C.load(spark, sf, "part").select("p_partkey", F.col("p_name").alias("name"))
    return X.top_targets(li.join(p, li.l_partkey == p.p_partkey), "name").select("name", "n")


@query("word_counts", "SELECT word, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(p_name), '[^a-z]+')) AS word FROM part) WHERE word <> '' GROUP BY word")
def word_counts(spark, sf):
    return X.word_counts(C.load(spark, sf, "part"), "p_name")


# --- packing -----------------------------------------------------------------------------

CAPS = (8192, 10240)


@query(
    "pack_vs_pad",
    " UNION ALL ".join(f"SELECT {c} AS cap, count(*) AS n_bins, {r6_sql(f'sum(least(n_tok, {c}))::DOUBLE / (count(*) * max(least(n_tok, {c})))')} AS fill, CAST(count(*) * max(least(n_tok, {c})) - sum(least(n_tok, {c})) AS BIGINT) AS waste, CAST(ceil(sum(least(n_tok, {c}))::DOUBLE / {c}) AS BIGINT) AS lower_bound FROM v_samples" for c in CAPS),
)
def pack_vs_pad(spark, sf):
    s, out = C.v_samples(spark, sf), None
    for c in CAPS:
        low = s.agg(F.ceil(F.sum(F.least("n_tok", F.lit(c))) / c).alias("lower_bound"))
        one = K.pad_plan(s, c).crossJoin(low).select(F.lit(c).alias("cap"), "n_bins", r6("fill").alias("fill"), "waste", "lower_bound")
        out = one if out is None else out.unionByName(one)
    return out


def _pack(spark, sf, algo):
    s, out = C.v_samples(spark, sf), None
    for c in CAPS:
        st = K.pack_stats(K.pack(s, c, algo), c)
        one = st.select(F.lit(c).alias("cap"), "n_bins", r6("mean_samples").alias("mean_samples"), r6("fill").alias("fill"), F.col("waste").cast("long").alias("waste"))
        out = one if out is None else out.unionByName(one)
    return out


_NEXT = {
    "items": f"SELECT cap, row_number() OVER (PARTITION BY cap ORDER BY sample_id) AS i, least(n_tok, cap) AS n FROM v_samples CROSS JOIN (VALUES {', '.join(f'({c})' for c in CAPS)}) AS c(cap)",
    "walk": "SELECT cap, i, n AS used, 1 AS bin FROM items WHERE i = 1 UNION ALL SELECT t.cap, t.i, CASE WHEN w.used + t.n > t.cap THEN t.n ELSE w.used + t.n END, w.bin + CASE WHEN w.used + t.n > t.cap THEN 1 ELSE 0 END FROM walk w JOIN items t ON t.cap = w.cap AND t.i = w.i + 1",
}


@query(
    "pack_nextfit",
    f"SELECT w.cap, CAST(max(bin) AS BIGINT) AS n_bins, {r6_sql('count(*)::DOUBLE / max(bin)')} AS mean_samples, {r6_sql('sum(t.n)::DOUBLE / (max(bin) * w.cap::BIGINT)')} AS fill, CAST(max(bin) * w.cap::BIGINT - sum(t.n) AS BIGINT) AS waste FROM walk w JOIN items t ON t.cap = w.cap AND t.i = w.i GROUP BY w.cap",
    **_NEXT,
)
def pack_nextfit(spark, sf):
    return _pack(spark, sf, "nextfit")


@query("pack_ffd")
def pack_ffd(spark, sf):
    return _pack(spark, sf, "ffd")


@query("pack_bestfit")
def pack_bestfit(spark, sf):
    return _pack(spark, sf, "bestfit")


@query("pack_batches")
def pack_batches(spark, sf):
    """Global batches of 128 sequences and the learning rate of each."""
    p = K.batch_plan(K.pack(C.v_samples(spark, sf), 2048), 128)
    return p.groupBy("batch_id").agg(F.count("*").alias("n")).withColumn("lr", r6(K.lr_at(F.col("batch_id"), 1e-5, 0.01, 1000), 12))


# --- token model ---------------------------------------------------------------------------

_CE_ROWS = f"""SELECT 'navigation' AS task, episode_id AS id, t, pos, token, coalesce(lag(token) OVER (PARTITION BY episode_id, t ORDER BY pos), '<s>') AS ctx, {uniform01_sql("episode_id", salt="ce")} AS u FROM tok
  UNION ALL SELECT 'dialogue', conv_id, turn, i - 1, w[i], CASE WHEN i = 1 THEN '<s>' ELSE w[i - 1] END, {uniform01_sql("conv_id", salt="ce")} FROM (SELECT conv_id, turn, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT conv_id, turn, string_split(text, ' ') AS w FROM v_turns WHERE role = 'assistant'))"""


def _lm_views(rows: str, group: str, train: str = "u < 0.8") -> dict[str, str]:
    g = group + ", " if group else ""
    on = "".join(f"p.{x} = r.{x} AND " for x in group.split(", ") if x)
    onc = on.replace("p.", "c.")
    onv = " AND ".join(f"v.{x} = r.{x}" for x in group.split(", ") if x) or "true"
    return {
        "lm_pair": f"SELECT {g}ctx, token, count(*) AS n FROM {rows} WHERE {train} GROUP BY ALL",
        "lm_ctx": f"SELECT {g}ctx, sum(n) AS n_ctx FROM lm_pair GROUP BY ALL",
        "lm_voc": f"SELECT {g}count(DISTINCT token) AS nv FROM lm_pair GROUP BY ALL" if g else "SELECT count(DISTINCT token) AS nv FROM lm_pair",
        "lm_scored": f"SELECT r.*, ln((coalesce(p.n, 0) + 1.0::DOUBLE) / (coalesce(c.n_ctx, 0) + 1.0::DOUBLE * (coalesce(v.nv, 0) + 1))) AS lp FROM {rows} r LEFT JOIN lm_pair p ON {on}p.ctx = r.ctx AND p.token = r.token LEFT JOIN lm_ctx c ON {onc}c.ctx = r.ctx LEFT JOIN lm_voc v ON {onv} WHERE NOT ({train})",
    }


def ce_rows(spark, sf):
    nav = T.token_rows(serialized(spark, sf).withColumn("id", F.col("episode_id")), "id").withColumn("task", F.lit("navigation"))
    talk = C.v_turns(spark, sf).where("role = 'assistant'").select(F.col("conv_id").alias("id"), F.split("text", " ").alias("tokens"))
    talk = T.token_rows(talk, "id").withColumn("task", F.lit("dialogue"))
    return nav.unionByName(talk).withColumn("u", uniform01("id", salt="ce"))


@query("ce_by_task", f"SELECT task, count(*) AS n_tok, {r6_sql('-avg(lp)', 5)} AS ce FROM lm_scored GROUP BY task", ce_rows=_CE_ROWS, **SER_VIEWS, **_lm_views("ce_rows", "task"))
def ce_by_task(spark, sf):
    rows = ce_rows(spark, sf)
    s = T.score(rows.where("u >= 0.8"), T.fit_token_lm(rows.where("u < 0.8"), ("task",)), ("task",))
    return T.ce_loss(s, ("task",)).select("task", "n_tok", r6("ce", 5).alias("ce"))


def _pointing_rows(variant: str) -> str:
    ctx = "'<s>'" if variant == "without" else "apos"
    return f"SELECT episode_id AS id, t, token, {ctx} AS ctx, {uniform01_sql('episode_id', salt='ce')} AS u FROM (SELECT episode_id, t, '<act0_' || k0 || '>' AS token, '<apos_' || (CASE WHEN apos < 256 THEN CAST(apos // 64 * 4 + apos % 16 // 4 AS INT) ELSE apos END) || '>' AS apos FROM coded)"


def _variant(sql: str, name: str) -> str:
    return sql.replace("lm_", f"{name}_lm_").replace("abl_rows", f"{name}_rows")


_ABL_VIEWS = dict(SER_VIEWS)
for _v in ("with", "without"):
    _ABL_VIEWS[f"{_v}_rows"] = _pointing_rows(_v)
    _ABL_VIEWS |= {_variant(k, _v): _variant(q, _v) for k, q in _lm_views("abl_rows", "").items()}


@query(
    "abl_pointing",
    f"""SELECT variant, {r6_sql("ce", 5)} AS ce_action, {r6_sql("ce - min(ce) OVER ()", 5)} AS delta FROM (SELECT 'with' AS variant, -avg(lp) AS ce FROM with_lm_scored UNION ALL SELECT 'without', -avg(lp) FROM without_lm_scored)""",
    **_ABL_VIEWS,
)
def abl_pointing(spark, sf):
    """Cross-entropy of the first action code with the (coarsened) affordance cell as context, and without."""
    tok = F.col("tokens")
    base = serialized(spark, sf).select(F.col("episode_id").alias("id"), tok[2].alias("token"), F.regexp_extract(tok[0], r"_(\d+)>", 1).cast("int").alias("a"))
    cell = F.when(F.col("a") < 256, F.floor(F.col("a") / 64) * 4 + F.floor(F.col("a") % 16 / 4)).otherwise(F.col("a")).cast("int")
    base = base.withColumn("u", uniform01("id", salt="ce")).withColumn("one", F.lit(1))
    out = None
    for name, ctx in (("with", F.concat(F.lit("<apos_"), cell.cast("string"), F.lit(">"))), ("without", F.lit("<s>"))):
        rows = base.withColumn("ctx", ctx)
        s = T.score(rows.where("u >= 0.8"), T.fit_token_lm(rows.where("u < 0.8"), ("one",)), ("one",))
        one = s.agg((-F.avg("logp")).alias("ce")).select(F.lit(name).alias("variant"), "ce")
        out = one if out is None else out.unionByName(one)
    best = F.broadcast(out.agg(F.min("ce").alias("m")))
    return out.crossJoin(best).select("variant", r6("ce", 5).alias("ce_action"), r6(F.col("ce") - F.col("m"), 5).alias("delta"))


@query(
    "abl_prior",
    f"""SELECT variant, {r6_sql("ce", 5)} AS ce_action, {r6_sql("ce - min(ce) OVER ()", 5)} AS delta FROM (
  SELECT 'prior' AS variant, -avg(ln((coalesce(a.n, 0) + 8.0::DOUBLE * (coalesce(b.n, 0) + 1) / (b2.s + 4)) / (a2.s + 8.0::DOUBLE))) AS ce FROM held h LEFT JOIN small a ON a.token = h.token LEFT JOIN aux b ON b.token = h.token CROSS JOIN (SELECT sum(n) AS s FROM aux) b2 CROSS JOIN (SELECT sum(n) AS s FROM small) a2
  UNION ALL SELECT 'uniform', -avg(ln((coalesce(a.n, 0) + 8.0::DOUBLE / 4) / (a2.s + 8.0::DOUBLE))) FROM held h LEFT JOIN small a ON a.token = h.token CROSS JOIN (SELECT sum(n) AS s FROM small) a2)""",
    uu=f"SELECT '<act0_' || k0 || '>' AS token, {uniform01_sql('episode_id', salt='prior')} AS u FROM coded",
    small="SELECT token, count(*) AS n FROM uu WHERE u < 0.02 GROUP BY token",
    aux="SELECT token, count(*) AS n FROM uu WHERE u BETWEEN 0.02 AND 0.5 GROUP BY token",
    held="SELECT token FROM uu WHERE u > 0.5",
    **SER_VIEWS,
)
def abl_prior(spark, sf):
    """A model of few navigation rows, started from an auxiliary prior or from a uniform one."""
    u = serialized(spark, sf).select(F.col("tokens")[2].alias("token"), uniform01("episode_id", salt="prior").alias("u"))
    count = lambda d, n: d.groupBy("token").agg(F.count("*").alias(n))
    small, aux = count(u.where("u < 0.02"), "a"), count(u.where("u between 0.02 and 0.5"), "b")
    s = small.agg(F.sum("a").alias("sa")).crossJoin(aux.agg(F.sum("b").alias("sb")))
    h = u.where("u > 0.5").join(small, "token", "left").join(aux, "token", "left").crossJoin(F.broadcast(s)).na.fill(0)
    a = h.agg(
        (-F.avg(F.log((F.col("a") + 8.0 * (F.col("b") + 1) / (F.col("sb") + 4)) / (F.col("sa") + 8.0)))).alias("prior"),
        (-F.avg(F.log((F.col("a") + 8.0 / 4) / (F.col("sa") + 8.0)))).alias("uniform"),
    )
    low = F.least("prior", "uniform")
    rows = F.explode(F.array(*[F.struct(F.lit(v).alias("variant"), F.col(v).alias("ce"), low.alias("m")) for v in ("prior", "uniform")]))
    return a.select(rows.alias("x")).select("x.variant", r6("x.ce", 5).alias("ce_action"), r6(F.col("x.ce") - F.col("x.m"), 5).alias("delta"))


# --- scaling -----------------------------------------------------------------------------

FRACTIONS = (0.0625, 0.125, 0.25, 0.5, 1.0)


ENVIRONMENTS = (0.125, 0.25, 0.5, 1.0)


def _scale_views(key: str, fractions=FRACTIONS) -> dict[str, str]:
    return {
        "ev": f"SELECT e.episode_id, e.t, event_type AS token, {uniform01_sql(key, salt='scale')} AS us, {uniform01_sql('episode_id', salt='ce')} AS u, coalesce(lag(event_type) OVER (PARTITION BY episode_id ORDER BY t), '<s>') || '/' || (k // 20) AS ctx FROM v_steps e",
        "fr": "SELECT * FROM (VALUES " + ", ".join(f"({f}::DOUBLE)" for f in fractions) + ") AS f(fraction)",
        "pr": "SELECT fraction, ctx, token, count(*) AS n FROM ev JOIN fr ON us < fraction WHERE u < 0.8 GROUP BY ALL",
        "cx": "SELECT fraction, ctx, sum(n) AS nc FROM pr GROUP BY ALL",
        "vo": "SELECT fraction, count(DISTINCT token) AS nv FROM pr GROUP BY ALL",
        "sz": "SELECT fraction, CAST(sum(n) AS BIGINT) AS n FROM pr GROUP BY ALL",
        "curve": "SELECT v.fraction, sz.n, -avg(ln((coalesce(p.n, 0) + 1.0::DOUBLE) / (coalesce(c.nc, 0) + 1.0::DOUBLE * (v.nv + 1)))) AS ce FROM ev e CROSS JOIN vo v JOIN sz ON sz.fraction = v.fraction LEFT JOIN pr p ON p.fraction = v.fraction AND p.ctx = e.ctx AND p.token = e.token LEFT JOIN cx c ON c.fraction = v.fraction AND c.ctx = e.ctx WHERE e.u >= 0.8 GROUP BY ALL",
    }


_CURVE = f"SELECT fraction, n, {r6_sql('ce', 5)} AS ce, {r6_sql('lag(ce) OVER (ORDER BY fraction) - ce', 5)} AS gain FROM curve"


def _curve(spark, sf, key, fractions=FRACTIONS):
    """(fraction, n, ce): the model fitted on nested shares of the data, tested on the same held-out episodes."""
    s = C.v_steps(spark, sf).select("episode_id", "event_id", "t", F.col("event_type").alias("token"), "k")
    prev = F.coalesce(F.lag("token").over(W.partitionBy("episode_id").orderBy("t")), F.lit("<s>"))
    s = s.withColumn("ctx", F.concat_ws("/", prev, F.floor(F.col("k") / 20).cast("string"))).withColumn("u", uniform01("episode_id", salt="ce")).withColumn("one", F.lit(1))
    s, out = kept(s), None
    for f in fractions:
        part = sample_fraction(s.where("u < 0.8"), f, key, salt="scale")
        sc = T.score(s.where("u >= 0.8"), T.fit_token_lm(part, ("one",)), ("one",))
        one = sc.agg((-F.avg("logp")).alias("ce")).crossJoin(part.agg(F.count("*").alias("n"))).select(F.lit(f).alias("fraction"), "n", "ce")
        out = one if out is None else out.unionByName(one)
    return out


def _scaling(spark, sf, key, fractions=FRACTIONS):
    out = _curve(spark, sf, key, fractions)
    gain = F.lag("ce").over(W.orderBy("fraction")) - F.col("ce")  # five rows
    return out.withColumn("gain", gain).select("fraction", "n", r6("ce", 5).alias("ce"), F.when(F.col("gain").isNotNull(), r6("gain", 5)).alias("gain"))


@query("scale_data", _CURVE, **_scale_views("e.event_id"))
def scale_data(spark, sf):
    return _scaling(spark, sf, "event_id")


@query("scale_scene", _CURVE, **_scale_views("e.episode_id", ENVIRONMENTS))
def scale_scene(spark, sf):
    """Environments (episodes stand for them) from an eighth to all."""
    return _scaling(spark, sf, "episode_id", ENVIRONMENTS)


_MATCHED = {}
for _axis, _key in (("data", "e.event_id"), ("environments", "e.episode_id")):
    _own = _scale_views(_key, ENVIRONMENTS)
    _MATCHED |= {f"{_axis}_{k}": renamed(v, _own, f"{_axis}_") for k, v in _own.items()}


@query(
    "scale_matched",
    " UNION ALL ".join(
        f"SELECT '{axis}' AS axis, {r6_sql('sum(g)', 5)} AS gain, bool_and(coalesce(g >= 0, true)) AS monotone, count(g) AS n_steps FROM (SELECT lag(ce) OVER (ORDER BY fraction) - ce AS g FROM {axis}_curve)" for axis in ("data", "environments")
    ),
    **_MATCHED,
)
def scale_matched(spark, sf):
    """What an eighth-to-all sweep gains along either axis, and whether every step does."""
    out = None
    for axis, key in (("data", "event_id"), ("environments", "episode_id")):
        one = _curve(spark, sf, key, ENVIRONMENTS).select(F.lit(axis).alias("setting"), F.lit("CE").alias("metric"), "fraction", (-F.col("ce")).alias("value"))
        out = one if out is None else out.unionByName(one)
    g = M.scaling_gains(out)
    return g.groupBy(F.col("setting").alias("axis")).agg(r6(F.sum("gain"), 5).alias("gain"), F.bool_and("monotone").alias("monotone"), F.count("gain").alias("n_steps"))


@query("scale_capacity")
def scale_capacity(spark, sf):
    """Displacement against the size of the code: levels and codewords as the capacity axis."""
    from navspark.operators import rvq as Q

    traj, out = kept(C.v_traj(spark, sf).select("traj_id", "z")), None
    for levels, k in ((1, 4), (1, 16), (2, 16), (3, 16)):
        books = Q.fit_rvq(traj, levels, k, 4)
        e = Q.rvq_eval(Q.encode(traj, books, "d_j"), books).where(F.col("levels") == levels)
        one = e.select(F.lit(levels).alias("levels"), F.lit(k).alias("k"), r6("mean_ade").alias("mean_ade"))
        out = one if out is None else out.unionByName(one)
    return out


# --- splits ------------------------------------------------------------------------------

_HOST = "regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)"


@query(
    "split_disjoint",
    f"SELECT CAST(count(DISTINCT CASE WHEN s = 'train' THEN scene END) AS BIGINT) AS n_train, CAST(count(DISTINCT CASE WHEN s = 'eval' THEN scene END) AS BIGINT) AS n_eval, 0::BIGINT AS n_overlap FROM (SELECT scene, CASE WHEN {uniform01_sql('scene', salt='split')} < 0.2 THEN 'eval' ELSE 'train' END AS s FROM (SELECT {_HOST} AS scene FROM pages))",
)
def split_disjoint(spark, sf):
    p = Y.split_hash(C.load(spark, sf, "pages").select(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("scene")), "scene", 0.2)
    train, ev = p.where("split = 'train'"), p.where("split = 'eval'")
    n = p.agg(F.count_distinct(F.when(F.col("split") == "train", F.col("scene"))).alias("n_train"), F.count_distinct(F.when(F.col("split") == "eval", F.col("scene"))).alias("n_eval"))
    return n.crossJoin(Y.overlap(train, ev).agg(F.count("*").alias("n_overlap")))


@query(
    "split_stats",
    f"SELECT split, count(DISTINCT scene_id) AS n_scenes, count(*) AS n_episodes, {r6_sql('count(*)::DOUBLE / count(DISTINCT scene_id)')} AS per_scene FROM (SELECT scene_id, CASE WHEN {uniform01_sql('scene_id', salt='split')} < 0.15 THEN 'eval' ELSE 'train' END AS split FROM v_rollouts) GROUP BY split",
)
def split_stats(spark, sf):
    s = Y.split_stats(Y.split_hash(C.v_rollouts(spark, sf), "scene_id", 0.15), "scene_id")
    return s.select("split", "n_scenes", "n_episodes", r6("per_scene").alias("per_scene"))


@query(
    "split_contiguous",
    "SELECT source, split, count(*) AS n FROM (SELECT source, CASE WHEN row_number() OVER (PARTITION BY source ORDER BY doc_id DESC) <= 10 THEN 'eval' ELSE 'train' END AS split FROM documents) GROUP BY ROLLUP (split, source) HAVING split IS NOT NULL",
)
def split_contiguous(spark, sf):
    d = Y.split_contiguous(C.load(spark, sf, "documents").select("doc_id", "source"), 10, "doc_id", "source")
    return Y.source_composition(d).where("split is not null").select("source", "split", "n")

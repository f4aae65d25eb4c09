import random

import pytest
from pyspark.sql import functions as F

from navspark.operators import episodes as E
from navspark.operators import instruct as N
from navspark.operators import inventory as V
from navspark.operators import mixture as X
from navspark.operators import ops
from navspark.operators import packing as K
from navspark.operators import tokenlm as T


# --- mixture ---------------------------------------------------------------------------------


def test_printed_shares():
    assert round(sum(X.ER_MASS.values()), 2) == 100 and sum(X.ER_SOURCES.values()) == 36
    assert sum(X.NAV_SOURCES.values()) == X.SFT_SOURCES["action"] and round(sum(X.SFT_MASS.values()), 1) == 100


def test_quota_sums_and_repeats(spark):
    c = spark.createDataFrame([("a", 10, 35.14), ("b", 1000, 25.05), ("c", 7, 19.81), ("d", 3, 20.0)], "source string, available long, weight double")
    q = {r.source: r for r in X.plan_quota(c, 101).collect()}
    assert sum(r.quota for r in q.values()) == 101
    assert q["d"].quota == 20 and (q["d"].rep_full, q["d"].rep_rest) == (6, 2)
    rows = [(i, s) for s, n in (("a", 10), ("b", 1000), ("c", 7), ("d", 3)) for i in range(n)]
    s = spark.createDataFrame([(k, src) for k, (i, src) in enumerate(rows)], "sample_id long, source string")
    d = X.draw(s, X.plan_quota(c, 101))
    assert {r.source: r["count"] for r in d.groupBy("source").count().collect()} == {k: r.quota for k, r in q.items()}
    assert d.groupBy("sample_id", "copy_no").count().where("count > 1").count() == 0


def test_first_by_hash_is_the_exact_rank(spark):
    from pyspark.sql import Window as W

    from navspark.functions.core import uniform01

    s = spark.range(5000).select(F.col("id").alias("sample_id"), F.when(F.col("id") % 10 < 7, "hot").otherwise("cold").alias("source"))
    q = spark.createDataFrame([("hot", 333), ("cold", 5000)], "source string, quota long")
    got = {r.sample_id for r in ops.first_by_hash(s, "source", q, "sample_id", "x", 64).collect()}
    w = W.partitionBy("source").orderBy(uniform01("sample_id", salt="x"), "sample_id")
    want = s.join(q, "source").withColumn("r", F.row_number().over(w)).where("r <= quota")
    assert got == {r.sample_id for r in want.collect()}


def brute_cap(sizes, share):
    best = 0
    for c in range(1, max(sizes) + 1):
        if c <= share * sum(min(n, c) for n in sizes) + 1e-9:
            best = c
    return best


def test_cluster_cap():
    assert X.cluster_cap([500, 300] + [40] * 30) == (66, True)
    assert X.cluster_cap([50] * 10) == (50, False)
    rnd = random.Random(1)
    for _ in range(300):
        sizes = [rnd.randrange(1, 200) for _ in range(rnd.randrange(1, 60))]
        c, ok = X.cluster_cap(sizes, 0.05)
        want = brute_cap(sizes, 0.05)
        assert (c, ok) == ((want, True) if want else (min(sizes), False)), sizes


def test_balanced_index(spark):
    rows = [(e, t, 10, t % 3 != 0, e % 2 == 0 and t == 10, "instruction", e * 10 + t, (e * 7 + t) % 40) for e in range(200) for t in range(1, 11)]
    s = spark.createDataFrame(rows, "episode_id long, t int, n_steps int, visible boolean, stop boolean, task string, sample_id long, cluster int")
    out, info = X.balanced_index(s)
    n, stops = out.count(), out.where("stop").count()
    top = out.groupBy("cluster").count().agg(F.max("count")).first()[0]
    assert info["feasible"] and stops <= 0.02 * n + 1e-9 and top <= 0.05 * n + 1e-9


def test_filters_are_task_aware(spark):
    rows = [(1, 1, 2, False, True, "instruction"), (1, 2, 2, False, False, "instruction"), (2, 1, 2, False, True, "tracking"), (3, 1, 2, True, True, "object"), (3, 2, 2, True, True, "object")]
    s = spark.createDataFrame(rows, "episode_id long, t int, n_steps int, visible boolean, stop boolean, task string")
    f = {(r.episode_id, r.t): r.stop for r in X.filter_stop(s).collect()}
    assert f == {(1, 1): False, (1, 2): False, (2, 1): True, (3, 1): False, (3, 2): True}
    assert {r.episode_id for r in X.drop_unseen(s).collect()} == {2, 3}


def test_onpolicy_adds_each_state_once(spark):
    e = spark.createDataFrame([("s1", "go"), ("s2", "go")], "state_key string, action string")
    r = spark.createDataFrame([("s2",), ("s3",), ("s3",)], "state_key string")
    lab = spark.createDataFrame([("s2", "stop"), ("s3", "stop")], "state_key string, action string")
    got = {x.state_key: (x.action, x.origin) for x in X.aggregate_onpolicy(e, r, lab, 1).collect()}
    assert got == {"s1": ("go", None), "s2": ("go", None), "s3": ("stop", "policy")}


# --- packing ---------------------------------------------------------------------------------


@pytest.mark.parametrize("algo", ["nextfit", "ffd", "bestfit", "worstfit"])
def test_packing(spark, algo):
    rnd = random.Random(4)
    rows = [(i, rnd.randrange(1, 3000)) for i in range(600)] + [(1000, 99_999)]
    s = spark.createDataFrame(rows, "sample_id long, n_tok int")
    p = K.pack(s, 8192, algo, shards=3)
    got = p.collect()
    assert len(got) == 601 and sum(r.oversized for r in got) == 1
    bins = {}
    for r in got:
        bins.setdefault((r.shard, r.bin_id), []).append((r.offset, r.n_tok))
    for items in bins.values():
        at = 0
        for off, n in sorted(items):
            assert off == at
            at += n
        assert at <= 8192
    st = K.pack_stats(p, 8192).first()
    assert st.n_bins >= st.lower_bound and (algo == "nextfit" or st.fill > 0.93)
    assert K.pack(s, 8192, algo, oversize="drop").count() == 600


def test_packing_beats_padding(spark):
    s = spark.createDataFrame([(i, 100 + 37 * (i % 50)) for i in range(500)], "sample_id long, n_tok int")
    assert K.pack_stats(K.pack(s), 8192).first().fill > K.pad_plan(s, 8192).first().fill


def test_first_fit_matches_the_plain_scan():
    rnd = random.Random(5)
    for _ in range(50):
        n = sorted((rnd.randrange(1, 60) for _ in range(40)), reverse=True)
        bins, _ = K._bins(n, 64, "ffd")
        used, want = [], []
        for x in n:
            for b, u in enumerate(used):
                if u + x <= 64:
                    break
            else:
                used.append(0)
                b = len(used) - 1
            used[b] += x
            want.append(b)
        assert bins == want


def test_batches_and_schedule(spark):
    p = spark.createDataFrame([(i % 3, i // 3) for i in range(700)], "shard int, bin_id int")
    b = K.batch_plan(p, 128).groupBy("batch_id").count().collect()
    assert sorted(r["count"] for r in b) == [60, 128, 128, 128, 128, 128]
    lr = [r.x for r in spark.range(1000).select(K.lr_at(F.col("id"), 1.0, 0.01, 1000).alias("x")).orderBy("id").collect()]
    assert lr[0] == 0.1 and max(lr) == 1.0 and lr[-1] < 1e-4


# --- token model -----------------------------------------------------------------------------


def test_probabilities_sum_to_one(spark):
    seqs = spark.createDataFrame([(i, ["a", "b" if i % 3 else "c", "d"]) for i in range(30)], "id long, tokens array<string>")
    rows = T.token_rows(seqs, "id")
    m = T.fit_token_lm(rows)
    every = rows.select("pos", "ctx").distinct().join(rows.select("pos", "token").distinct(), "pos")
    s = T.score(every, m).groupBy("pos", "ctx").agg(F.sum(F.exp("logp")).alias("p"), F.count("*").alias("n"))
    for r in s.collect():
        seen = {0: 30, 1: 30, 2: 20 if r.ctx == "b" else 10}[r.pos]
        assert r.p == pytest.approx(1 - 1 / (seen + r.n + 1))  # the rest is the slot of unseen tokens
    assert T.ce_loss(T.score(rows, m), mask=F.col("pos") < 2).first().n_tok == 60


# --- inventory, episodes, wording --------------------------------------------------------------


def obs(spark, rows):
    return spark.createDataFrame(rows, "obs_id string, scene int, category string, viewpoint long, lx double, ly double, lz double")


def test_gates(spark):
    rows = [("a1", 1, "c", 1, 0.1, 0.1, 0.1), ("a2", 1, "c", 2, 0.3, 0.1, 0.1), ("b1", 1, "c", 1, 5.1, 0.0, 0.0), ("b2", 1, "c", 1, 5.2, 0.0, 0.0), ("c1", 1, "c", 1, 9.1, 0.0, 0.0), ("d1", 1, "e", 1, 20.0, 0.0, 0.0), ("d2", 1, "e", 2, 21.2, 0.0, 0.0)]
    m = V.merge_views(obs(spark, rows), 1.25, "components")
    g = {r.cluster_id: r.reason for r in V.gate(m).collect()}
    assert g == {"a1": "accepted", "b1": "few_views", "c1": "few_obs", "d1": "spread"}  # a spread of exactly 0.6 fails
    assert V.gate(m, 1, 1, None).where("accepted").count() == 4
    assert V.instances(m, V.gate(m)).first().support == [1, 2]


def test_components_equal_all_pairs(spark):
    rnd = random.Random(6)
    rows = [(f"o{i:03d}", i % 2, "c", i % 5, rnd.uniform(0, 12), rnd.uniform(0, 12), rnd.uniform(0, 2)) for i in range(150)]
    got = {r.obs_id: r.cluster_id for r in V.merge_views(obs(spark, rows), 1.0, "components").collect()}
    up = {r[0]: r[0] for r in rows}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in rows:
        for b in rows:
            if a[1] == b[1] and sum((a[k] - b[k]) ** 2 for k in (4, 5, 6)) <= 1:
                p, q = find(a[0]), find(b[0])
                up[max(p, q)] = min(p, q)
    assert got == {x: find(x) for x in up}


def test_routes(spark):
    from navspark.plans.perception_queries import grid_edges

    e = grid_edges(spark, "/root/testdata/sf0.001")
    rows = [(r.a, r.b, r.w) for r in e.collect()]
    inf, n = float("inf"), 25
    d = [[0 if i == j else inf for j in range(n)] for i in range(n)]
    for a, b, w in rows:
        d[a][b] = d[b][a] = w
    for k in range(n):
        for i in range(n):
            for j in range(n):
                d[i][j] = min(d[i][j], d[i][k] + d[k][j])
    src = spark.createDataFrame([(0,), (12,)], "node int")
    g = E.geodesic(e, src).persist()
    assert {(r.src, r.node): r.dist for r in g.collect()} == {(s, t): d[s][t] for s in (0, 12) for t in range(n)}
    route = E.route_nodes(e, g, spark.createDataFrame([(0, 24)], "src int, dst int")).orderBy("i").collect()
    assert route[0].node == 24 and route[-1].node == 0


def test_the_view_dominates_the_pixel(spark):
    import math

    df = spark.createDataFrame([(2, 0.7, math.radians(130)), (0, 0.2, 0.3), (0, 0.5, 0.0), (1, 0.9, 1.0), (3, 0.1, -1.0), (2, 0.3, -2.5)], "h int, u double, b double")
    got = [tuple(r) for r in df.select(N.sector("h", "u"), N.sector_uniform("b"), N.turn_family("h")).collect()]
    assert got[0] == ("behind-left", "left", "rear")
    assert [g[0] for g in got[1:]] == ["front-left", "ahead", "left", "right", "behind-right"]


def test_rewrites_fall_back_and_lose_no_row(spark):
    rows = [("the ring on the left", "ring", "left"), ("the thing on the left", "ring", "left"), ("the ring on the right", "ring", "left"), ("left of the rings", "ring", "left"), (None, "ring", "left"), ("left, not right, to the ring", "ring", "left")]
    df = spark.createDataFrame(rows, "rewrite string, noun string, sector string").withColumn("draft", F.lit("draft"))
    r = N.resolve_instruction(df).collect()
    assert len(r) == 6 and [x.used_fallback for x in r] == [False, True, True, True, True, True]
    assert [x.final_text for x in r] == ["the ring on the left"] + ["draft"] * 5


def test_every_draft_passes_its_own_checks(spark):
    df = N.draft_rule(spark.createDataFrame([(s, f, "red ring") for s, f, _ in N.TEMPLATES], "sector string, form string, name string"))
    assert df.where(~N.check_rewrite("draft", F.lit("ring"), "sector").accept).count() == 0


def test_arrival_of_short_clips(spark):
    df = spark.createDataFrame([(1, t, t == 2) for t in range(1, 5)] + [(2, t, t == 3) for t in range(1, 5)], "episode_id long, t int, visible boolean")
    got = {r.episode_id: (r.n_checked, r.confirmed) for r in N.arrival_check(df).collect()}
    assert got == {1: (2, True), 2: (2, False)}


def test_keyframes(spark):
    df = spark.createDataFrame([(1, t) for t in range(1, 31)] + [(2, 1), (2, 2)], "episode_id long, t int")
    got = {}
    for r in E.keyframes(df).collect():
        got.setdefault(r.episode_id, set()).add(r.t)
    assert len(got[1]) == 6 and {1, 30} <= got[1] and got[2] == {1, 2}


# --- general joins -----------------------------------------------------------------------------


def test_joins_against_all_pairs(spark):
    rnd = random.Random(7)
    a = [(i, i % 3, rnd.uniform(0, 50)) for i in range(80)]
    b = [(i, i % 3, rnd.uniform(0, 50), rnd.uniform(0, 9)) for i in range(40)]
    la, lb = spark.createDataFrame(a, "id int, k int, at double"), spark.createDataFrame([(i, k, s, s + d) for i, k, s, d in b], "sid int, k int, s double, e double")
    got = {(r.id, r.sid) for r in ops.interval_join(la, lb, "at", "s", "e", ["k"], 4.0).collect()}
    assert got == {(x[0], y[0]) for x in a for y in b if x[1] == y[1] and y[2] <= x[2] <= y[2] + y[3]}
    right = lb.select(F.col("s").alias("at"), "k", "sid")
    for tol in (None, 2.0):
        got = {r.id: r.r_sid for r in ops.asof_join(la, right, "at", ["k"], tol).collect()}
        for x in a:
            c = [(y[2], y[0]) for y in b if y[1] == x[1] and y[2] <= x[2] and (tol is None or x[2] - y[2] <= tol)]
            latest = max((y[2], y[0]) for y in b if y[1] == x[1] and y[2] <= x[2]) if any(y[1] == x[1] and y[2] <= x[2] for y in b) else None
            assert got[x[0]] == (max(c)[1] if c and max(c) == latest else None)


def test_salted_sum_and_nested_samples(spark):
    df = spark.range(1000).select("id", F.lit("hot").alias("k"), F.col("id").cast("double").alias("v"))
    r = ops.salted_sum(df, ["k"], "v").first()
    assert (r.v, r.n) == (499500.0, 1000)
    small, large = ({x.id for x in ops.sample_fraction(df, f, "id").collect()} for f in (0.1, 0.5))
    assert small < large


def test_paths_of_more_than_64_edges(spark):
    e = spark.createDataFrame([(i, i + 1, 1.0) for i in range(70)], "a int, b int, w double")
    g = E.geodesic(e, spark.createDataFrame([(0,)], "node int")).persist()
    assert {r.node: r.dist for r in g.collect()} == {i: float(i) for i in range(71)}
    route = E.route_nodes(e, g, spark.createDataFrame([(0, 70)], "src int, dst int")).collect()
    assert sorted((r.i, r.node) for r in route) == [(i, 70 - i) for i in range(71)]
    with pytest.raises(ValueError):
        E.geodesic(e, spark.createDataFrame([(0,)], "node int"), max_rounds=3)


def test_split_contamination_is_left_to_op10():
    from navspark.plans import registry

    assert "split_contamination" not in registry.queries()

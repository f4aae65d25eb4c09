"""Episode synthesis: start draws, routes on a graph, clip rows, key frames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import uniform01
from navspark.session import kept


def draw_starts(views: DataFrame, instances: DataFrame | None = None, poses: DataFrame | None = None, per_target: int = 1, seed: str = "start") -> DataFrame:
    """(target, start): poses from which the target is seen in some stored view, drawn by hash.

    ``views``: (target, viewpoint); ``instances`` (target) and ``poses`` (viewpoint) limit them where
    given. That the first forward view shows the target is not promised.
    """
    seen = views.select("target", "viewpoint").distinct()
    if instances is not None:
        seen = seen.join(instances.select("target"), "target", "left_semi")
    if poses is not None:
        seen = seen.join(poses.select("viewpoint"), "viewpoint", "left_semi")
    w = W.partitionBy("target").orderBy(uniform01("target", "viewpoint", salt=seed), "viewpoint")
    return seen.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= per_target).select("target", F.col("viewpoint").alias("start"))


def geodesic(edges: DataFrame, sources: DataFrame, max_rounds: int | None = None, checkpoint_every: int = 3) -> DataFrame:
    """(src, node, dist) of shortest paths from many sources at once.

    Rounds of relaxation: only nodes improved in the last round are extended; ends when none is.
    Paths have fewer edges than there are nodes, so more rounds than nodes (negative weights),
    or than ``max_rounds``, with nodes still improving are an error.
    """
    e = edges.select("a", "b", "w").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "w"))
    dist = sources.select(F.col("node").alias("src"), "node", F.lit(0.0).alias("dist"), F.lit(True).alias("new"))
    if max_rounds is None:
        max_rounds = e.select("a").distinct().count() + 1
    for i in range(max_rounds):
        step = dist.where("new").join(e, F.col("node") == F.col("a")).select("src", F.col("b").alias("node"), (F.col("dist") + F.col("w")).alias("d"))
        best = step.groupBy("src", "node").agg(F.min("d").alias("d"))
        j = dist.join(best, ["src", "node"], "full")
        better = F.col("d").isNotNull() & (F.col("dist").isNull() | (F.col("d") < F.col("dist") - 1e-12))
        dist = j.select("src", "node", F.when(better, F.col("d")).otherwise(F.col("dist")).alias("dist"), better.alias("new"))
        if i % checkpoint_every == 0 or i < 2:
            dist = kept(dist)
        if not dist.where("new").limit(1).count():
            break
    else:
        raise ValueError(f"distances still improve after {max_rounds} rounds")
    return dist.select("src", "node", "dist")


def plan_route(dist: DataFrame, pairs: DataFrame) -> DataFrame:
    """(src, dst, dist) for start and goal pairs; pairs without a path have no row."""
    return pairs.join(dist, (pairs.src == dist.src) & (pairs.dst == dist.node)).select(pairs.src, pairs.dst, "dist")


def route_nodes(edges: DataFrame, dist: DataFrame, pairs: DataFrame, max_len: int | None = None) -> DataFrame:
    """(src, dst, i, node): nodes of one shortest path from goal back to start, smallest node on ties.

    A path of more edges than there are nodes (edges of no weight that lead in a circle), or than
    ``max_len``, is an error.
    """
    e = edges.select("a", "b", "w").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "w"))
    before = (
        dist.alias("x").join(e.alias("e"), F.col("x.node") == F.col("e.a")).join(dist.alias("y"), (F.col("y.src") == F.col("x.src")) & (F.col("y.node") == F.col("e.b")))
        .where(F.abs(F.col("y.dist") + F.col("e.w") - F.col("x.dist")) < 1e-9).groupBy(F.col("x.src").alias("src"), F.col("x.node").alias("node")).agg(F.min("e.b").alias("prev"))
    )
    cur = pairs.select("src", "dst", F.col("dst").alias("node"))
    out, i = cur.withColumn("i", F.lit(0)), 0
    if max_len is None:
        max_len = e.select("a").distinct().count()
    while True:
        i += 1
        cur = kept(cur.where("node <> src").join(before, ["src", "node"]).select("src", "dst", F.col("prev").alias("node")))
        if not cur.limit(1).count():
            break
        if i > max_len:
            raise ValueError(f"routes of more than {max_len} edges")
        out = out.unionByName(cur.withColumn("i", F.lit(i)))
    return out


def clip_rows(routes: DataFrame, path: str = "path") -> DataFrame:
    """Step rows of a clip with the place in it."""
    return routes.select(*[c for c in routes.columns if c != path], F.posexplode(path).alias("i", "node"))


def keyframe_places(n: Column, k: int = 6) -> Column:
    """Places (from 1) of k evenly spaced frames among n; short clips repeat none."""
    return F.array_distinct(F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.floor(i * (n - 1) / (k - 1) + 0.5).cast("int") + 1))


def keyframes(steps: DataFrame, k: int = 6, key: str = "episode_id") -> DataFrame:
    n = F.count("*").over(W.partitionBy(key))
    return steps.withColumn("_n", n).where(F.array_contains(keyframe_places(F.col("_n"), k), F.col("t"))).drop("_n")


def motion_summary(steps: DataFrame, turn: float = 0.2, key: str = "episode_id") -> DataFrame:
    """Runs of like motion (left, right, forward) with their lengths: gaps and islands."""
    kind = F.when(F.col("turn_rad") > turn, "left").when(F.col("turn_rad") < -turn, "right").otherwise("forward")
    by = W.partitionBy(key).orderBy("t")
    s = steps.select(key, "t", kind.alias("motion")).withColumn("_new", (~F.col("motion").eqNullSafe(F.lag("motion").over(by))).cast("int"))
    s = s.withColumn("run", F.sum("_new").over(by))
    return s.groupBy(key, "run", "motion").agg(F.min("t").alias("t_first"), F.count("*").alias("n"))

"""Structured Streaming twins: online history, live tracking reward, windows, group completion.

Sources are file streams over ``events``; state is bounded for each episode and dropped by
event-time timers behind the watermark.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from navspark.functions import rewards as R
from navspark.functions.core import PI
from navspark.sources.io import load_stream

WATERMARK = "2 days"


def events_stream(spark: SparkSession, path: str, watermark: str = WATERMARK, files_per_trigger: int | None = 1) -> DataFrame:
    """Decision steps as they come: cast to a zoned timestamp first, then watermarked and freed of re-sent frames."""
    e = load_stream(spark, path, "events", files_per_trigger)
    e = e.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])
    k = F.from_json("props", "k int").k
    kd = k.cast("double")
    return e.select(
        "event_id", "ts", F.col("user_id").alias("episode_id"), "event_type", k.alias("k"),
        (F.col("value") / 25).alias("range_m"), ((kd - 49.5) / 49.5 * 0.7).alias("bearing_rad"),
        (F.col("event_type") != "error").alias("visible"), ((F.col("event_type") == "error") & (k < 3)).alias("collision"),
        (((k * 7 % 100).cast("double") - 49.5) / 49.5 * (2 * PI / 3)).alias("target_rad"),
    )


def _ends(pdf: pd.DataFrame) -> pd.DataFrame:
    return pdf.sort_values(["ts", "event_id"])


def live_tracking(steps: DataFrame, gap: str = "6 days") -> DataFrame:
    """One reward row an episode, emitted when its event-time timer says that it ended; without the
    plan term, as plans are not in the stream.

    State: sums and the last step, a few numbers whatever the episode's length. The order of
    arrival doesn't matter: the last step is the latest by (ts, event_id).
    """
    s = steps.withColumn("q", R.step_quality("visible", "bearing_rad", "range_m"))
    gap_ms = int(pd.Timedelta(gap).total_seconds() * 1000)

    def go(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            n, q, coll, _, _, vis, rng, bear, col, tgt = state.get
            state.remove()
            early = (not vis) or col
            ok = vis and 1 <= rng <= 3 and abs(bear) <= 1.0471975511965976 and math.cos(tgt - bear) > 0
            h = max(n, R.HORIZON) if early else n
            yield pd.DataFrame({"episode_id": [key[0]], "t_n": [n], "horizon": [h], "success": [bool(ok)], "collision": [bool(coll)], "reward": [float(ok) - R.COLLISION_COST * coll + R.QUALITY_WEIGHT * q / h]})
            return
        n, q, coll, ts, eid, vis, rng, bear, col, tgt = state.get if state.exists else (0, 0.0, False, -1, -1, False, 0.0, 0.0, False, 0.0)
        for f in frames:
            n, q, coll = n + len(f), q + float(f.q.sum()), bool(coll or f.collision.any())
            last = _ends(f).iloc[-1]
            at = (int(last.ts.value // 1000), int(last.event_id))
            if at > (ts, eid):
                ts, eid, vis, rng, bear, col, tgt = *at, bool(last.visible), float(last.range_m), float(last.bearing_rad), bool(last.collision), float(last.target_rad)
        state.update((n, q, coll, ts, eid, vis, rng, bear, col, tgt))
        state.setTimeoutTimestamp(max(ts // 1000, state.getCurrentWatermarkMs()) + gap_ms)
        yield from ()

    return s.select("episode_id", "event_id", "ts", "q", "visible", "range_m", "bearing_rad", "collision", "target_rad").groupBy("episode_id").applyInPandasWithState(
        go,
        "episode_id long, t_n long, horizon long, success boolean, collision boolean, reward double",
        "n long, q double, coll boolean, ts long, eid long, vis boolean, rng double, bear double, col boolean, tgt double",
        "append",
        GroupStateTimeout.EventTimeTimeout,
    )


def history_reach(f_max: float, tau_s: float) -> float:
    """Age in seconds of the last step of the accumulated rate: of all older frames only the newest can be kept."""
    most = math.ceil(f_max * tau_s) - 1
    return -tau_s * math.log(1 - most / (f_max * tau_s)) if most > 0 else 0.0


def online_history(steps: DataFrame, f_max: float, tau_s: float, gap: str = "60 days") -> DataFrame:
    """The kept frames of each episode after each batch (update mode): the same that the batch selector keeps.

    A frame is kept while an integer of the accumulated rate lies between its age and that of the
    next newer frame. Those integers stand at fixed ages, up to ``history_reach``, and a frame
    dropped now may be kept later, so the state has the times of all frames up to that age and the
    newest older one: bounded by the frame rate, however long the episode. An episode without
    frames for ``gap`` of event time is forgotten.
    """
    top, reach = math.ceil(f_max * tau_s) - 1, history_reach(f_max, tau_s) + 1e-3
    gap_ms = int(pd.Timedelta(gap).total_seconds() * 1000)

    def level(age: float) -> int:
        return min(top, math.floor(round(f_max * tau_s * (1 - math.exp(-age / tau_s)), 9)))

    def go(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        ts, ids = state.get if state.exists else ([], [])
        ring = list(zip(ts, ids, strict=True))
        for f in frames:
            ring += [(t.value // 1000, int(i)) for t, i in zip(f.ts, f.event_id, strict=True)]
        ring = sorted(set(ring), reverse=True)
        now, kept, before, hold = ring[0][0], [], None, []
        for t, i in ring:
            age = (now - t) / 1e6
            lv = level(age)
            if before is None or lv > before:
                kept.append((t, i))
            before = lv
            hold.append((t, i))
            if age > reach:
                break
        state.update(([t for t, _ in hold], [i for _, i in hold]))
        state.setTimeoutTimestamp(max(now // 1000, state.getCurrentWatermarkMs()) + gap_ms)
        yield pd.DataFrame({"episode_id": [key[0]], "now_us": [now], "n_kept": [len(kept)], "newest": [kept[0][1]], "oldest": [kept[-1][1]]})

    return steps.select("episode_id", "event_id", "ts").groupBy("episode_id").applyInPandasWithState(
        go, "episode_id long, now_us long, n_kept long, newest long, oldest long", "ts array<long>, ids array<long>", "update", GroupStateTimeout.EventTimeTimeout
    )


def tracking_windows(steps: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Tracking rate and visibility in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    ok = F.col("visible") & F.col("range_m").between(1, 3)
    return steps.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.avg(ok.cast("double")).alias("tracking_rate"), F.avg(F.col("visible").cast("double")).alias("visibility")).select(F.col("w.start").alias("start"), "n", "tracking_rate", "visibility")


def episode_sessions(steps: DataFrame, gap: str = "1 day") -> DataFrame:
    """Episodes found by gaps in time."""
    return steps.groupBy("episode_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("episode_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def complete_groups(rewards: DataFrame, g: int, seed: str = "seed_id", at: str | None = None, wait: str = "1 day") -> DataFrame:
    """Advantages of a group as soon as all G rewards have come (append mode).

    ``at``: a watermarked time column. With it a group that is still short ``wait`` after its last
    reward, in event time, is given up, so that lost rollouts leave no state behind.
    """
    wait_ms = int(pd.Timedelta(wait).total_seconds() * 1000)

    def go(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        eps, rs = state.get if state.exists else ([], [])
        have, last = dict(zip(eps, rs, strict=True)), 0
        for f in frames:
            have |= dict(zip(f.episode_id.tolist(), f.reward.tolist(), strict=True))
            last = max(last, int(f[at].max().value // 1_000_000)) if at else 0
        if len(have) < g:
            state.update((list(have), list(have.values())))
            if at:
                state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + wait_ms)
            return
        if state.exists:
            state.remove()
        r = pd.Series(have)
        sd = r.std(ddof=0)
        yield pd.DataFrame({"seed_id": key[0], "episode_id": list(have), "reward": r.to_numpy(), "adv": ((r - r.mean()) / (sd + 1e-6) if sd > 1e-9 else 0 * r).to_numpy()})

    timeout = GroupStateTimeout.EventTimeTimeout if at else GroupStateTimeout.NoTimeout
    return rewards.select(seed, "episode_id", "reward", *([at] if at else [])).groupBy(seed).applyInPandasWithState(
        go, "seed_id long, episode_id long, reward double, adv double", "eps array<long>, rs array<double>", "append", timeout
    )


def plan_outcome(plans: DataFrame, outcomes: DataFrame, within: str = "1 hour", watermark: str = WATERMARK) -> DataFrame:
    """Stream-stream join of plans (plan_ts) with outcomes (out_ts) of the same key soon after."""
    p, o = plans.withWatermark("plan_ts", watermark), outcomes.withWatermark("out_ts", watermark)
    return p.join(o, F.expr(f"plan_key = out_key AND out_ts >= plan_ts AND out_ts <= plan_ts + INTERVAL {within}"))


def run_available(df: DataFrame, name: str, mode: str, checkpoint: str | None = None) -> DataFrame:
    """Run all that is there into an in-memory table (tests and small demonstrations)."""
    w = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        w = w.option("checkpointLocation", checkpoint)
    w.start().awaitTermination()
    return df.sparkSession.table(name)

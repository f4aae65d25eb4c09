"""Instruction wording: sectors, phrase forms, rewrite checks, fallback, arrival."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import PI, uniform01, wrap_angle

LOW, HIGH = 1 / 3, 2 / 3  #: centre band of the image's width
DETOUR = 1.5
ARRIVAL_OFFSETS = (1, 3, 6, 10)  #: frames from the end that may confirm an arrival
FAMILIES = ("front", "left", "rear", "right")


def turn_family(heading) -> Column:
    h = F.col(heading) if isinstance(heading, str) else heading
    return F.element_at(F.array(*map(F.lit, FAMILIES)), h + 1)


def sector(heading, u, lo: float = LOW, hi: float = HIGH) -> Column:
    """The view fixes the family; the pixel refines inside it. A rear camera mirrors: its right half lies on the agent's left."""
    h, u = (F.col(c) if isinstance(c, str) else c for c in (heading, u))
    front = F.when(u < lo, "front-left").when(u > hi, "front-right").otherwise("ahead")
    rear = F.when(u > 0.5, "behind-left").otherwise("behind-right")
    return F.when(h == 0, front).when(h == 2, rear).when(h == 1, "left").otherwise("right")


UNIFORM = ("ahead", "front-left", "left", "behind-left", "behind", "behind-right", "right", "front-right")


def sector_uniform(bearing, n: int = 4) -> Column:
    """The contrast: n equal bins of the bearing, which calls a rear-left target 'left'."""
    b = F.col(bearing) if isinstance(bearing, str) else bearing
    names = UNIFORM if n == 8 else ("ahead", "left", "behind", "right")
    i = F.pmod(F.floor(F.round((wrap_angle(b) + PI / n) / (2 * PI / n), 9)), F.lit(n)).cast("int")
    return F.element_at(F.array(*map(F.lit, names)), i + 1)


#: Our own wording: sector, form, text with the target's name for %s.
TEMPLATES = [
    ("ahead", "turn", "Go straight until you reach the %s"), ("ahead", "place", "Head for the %s in front of you"),
    ("front-left", "turn", "Bear left and walk to the %s"), ("front-left", "place", "Head for the %s at your front left"),
    ("front-right", "turn", "Bear right and walk to the %s"), ("front-right", "place", "Head for the %s at your front right"),
    ("left", "turn", "Turn left and walk to the %s"), ("left", "place", "Head for the %s on your left"),
    ("right", "turn", "Turn right and walk to the %s"), ("right", "place", "Head for the %s on your right"),
    ("behind-left", "turn", "Turn around to the left and walk to the %s"), ("behind-left", "place", "Head for the %s behind you on the left"),
    ("behind-right", "turn", "Turn around to the right and walk to the %s"), ("behind-right", "place", "Head for the %s behind you on the right"),
]
#: Words that contradict each other.
OPPOSITES = [("left", "right"), ("right", "left"), ("front", "behind"), ("behind", "front"), ("hot", "cold"), ("cold", "hot"), ("old", "new"), ("new", "old"), ("large", "small"), ("small", "large")]
#: Direction words a rewrite has to keep, by sector, and those it must not have.
KEEP = {"ahead": "straight|ahead|front|forward", "front-left": "left", "front-right": "right", "left": "left", "right": "right", "behind-left": "left", "behind-right": "right"}
AVOID = {"ahead": "behind|around", "front-left": "right|behind", "front-right": "left|behind", "left": "right", "right": "left", "behind-left": "right", "behind-right": "left"}


def templates(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TEMPLATES, "sector string, form string, template string")


def phrase_form(route_len, straight, key, threshold: float = DETOUR, salt: str = "form") -> Column:
    """A detour forces the locative form; otherwise a hash picks."""
    r, s = (F.col(c) if isinstance(c, str) else c for c in (route_len, straight))
    return F.when(r > threshold * s, "place").when(uniform01(key, salt=salt) < 0.5, "turn").otherwise("place")


def draft_rule(df: DataFrame, name: str = "name") -> DataFrame:
    """Adds the draft from sector and form by a broadcast of the templates."""
    t = F.broadcast(templates(df.sparkSession))
    return df.join(t, ["sector", "form"], "left").withColumn("draft", F.replace("template", F.lit("%s"), F.col(name))).drop("template")


def assign_route(key, p: float = 0.5, salt: str = "route") -> Column:
    """Which of the two drafting routes an episode takes: rules or video."""
    return F.when(uniform01(key, salt=salt) < p, "rule").otherwise("video")


def _has(text: Column, words: Column) -> Column:
    return F.regexp_like(text, F.concat(F.lit(r"(?i)\b("), words, F.lit(r")\b")))


def _by_sector(col: Column, table: dict[str, str]) -> Column:
    out = F.lit("")
    for k, v in table.items():
        out = F.when(col == k, v).otherwise(out)
    return out


def check_rewrite(rewrite, noun, sector_col) -> Column:
    """(noun_ok, dir_ok, no_opposite, accept) of a rewrite."""
    r, n, s = (F.col(c) if isinstance(c, str) else c for c in (rewrite, noun, sector_col))
    noun_ok, dir_ok, clean = F.coalesce(_has(r, n), F.lit(False)), F.coalesce(_has(r, _by_sector(s, KEEP)), F.lit(False)), F.coalesce(~_has(r, _by_sector(s, AVOID)), F.lit(False))
    return F.struct(noun_ok.alias("noun_ok"), dir_ok.alias("dir_ok"), clean.alias("no_opposite"), (noun_ok & dir_ok & clean).alias("accept"))


def resolve_instruction(df: DataFrame, draft: str = "draft", rewrite: str = "rewrite", noun: str = "noun") -> DataFrame:
    """final_text is the rewrite where all checks hold, else the draft; no row is lost."""
    c = df.withColumn("check", check_rewrite(rewrite, noun, "sector"))
    return c.withColumn("used_fallback", ~F.col("check.accept")).withColumn("final_text", F.when(F.col("check.accept"), F.col(rewrite)).otherwise(F.col(draft)))


def arrival_check(clip: DataFrame, hit: str = "visible", offsets=ARRIVAL_OFFSETS, key: str = "episode_id") -> DataFrame:
    """(key, n_checked, confirmed): a hit on any offset from the end confirms; short clips use what they have."""
    back = F.row_number().over(W.partitionBy(key).orderBy(F.desc("t")))
    return clip.withColumn("_b", back).where(F.col("_b").isin(*offsets)).groupBy(key).agg(F.count("*").alias("n_checked"), F.bool_or(hit).alias("confirmed"))


def wording_report(resolved: DataFrame) -> DataFrame:
    """Acceptance, reasons and distinct texts before and after."""
    c = F.col("check")
    return resolved.agg(
        F.count("*").alias("n"),
        F.avg(c.accept.cast("double")).alias("acceptance"),
        F.sum((~c.noun_ok).cast("long")).alias("noun_lost"),
        F.sum((~c.dir_ok).cast("long")).alias("direction_lost"),
        F.sum((~c.no_opposite).cast("long")).alias("opposite_added"),
        F.approx_count_distinct("draft").alias("distinct_drafts"),
        F.approx_count_distinct("final_text").alias("distinct_texts"),
    )

"""Small column functions used everywhere."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PI = 3.141592653589793


def uniform01(*keys, salt: str = "") -> Column:
    """A reproducible uniform number of [0, 1): the first 32 bits of an MD5 of the keys. Any engine can repeat it."""
    parts = [k.cast("string") if isinstance(k, Column) else F.col(k).cast("string") for k in keys]
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(salt), *parts)), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def uniform01_sql(*keys: str, salt: str = "") -> str:
    """The same number in DuckDB."""
    parts = ", ".join(f"CAST({k} AS VARCHAR)" for k in keys)
    return f"(CAST(('0x' || substr(md5(concat_ws('|', '{salt}', {parts})), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE)"


def once(c: Column) -> Column:
    """The column, computed once a row. A filter on what depends on it would else be pushed below its
    projection, with the whole expression copied into the filter as often as it is named there."""
    return F.when(F.monotonically_increasing_id() >= 0, c)


def let(c, body) -> Column:
    """``body`` applied to the column, which is computed once a row: a lambda that names a column of the
    projection below gets that column's whole expression, evaluated again for every element."""
    return F.get(F.transform(F.array(F.col(c) if isinstance(c, str) else c), body), 0)


def wrap_angle(a: Column) -> Column:
    """Into (-pi, pi]."""
    return F.lit(PI) - F.pmod(F.lit(PI) - a, F.lit(2 * PI))


def r6(c, digits: int = 6) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    r = F.round(c.cast("double"), digits)
    return F.when(r == 0, F.lit(0.0)).otherwise(r)  # no negative zero


def r6_sql(e: str, digits: int = 6) -> str:
    return f"(CASE WHEN round(CAST({e} AS DOUBLE), {digits}) = 0 THEN 0.0::DOUBLE ELSE round(CAST({e} AS DOUBLE), {digits}) END)"


def token_latency_ms(n_tokens: Column, ms_per_token: float = 4.0) -> Column:
    return n_tokens * F.lit(ms_per_token)


def pad_to_multiple(n: int, m: int = 8) -> int:
    return -(-n // m) * m

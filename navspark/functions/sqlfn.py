"""The SQL surface: carrier views and functions that ``spark.sql`` can call."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from navspark.operators import rollouts, rvq
from navspark.operators.packing import _bins
from navspark.sources import carriers

#: Plain SQL functions, in the engine's own expressions.
EXPRESSIONS = {
    "wrap_angle(a DOUBLE) RETURNS DOUBLE": "pi() - pmod(pi() - a, 2 * pi())",
    "grid_index(u DOUBLE, v DOUBLE, hg INT, wg INT) RETURNS INT": "CASE WHEN u BETWEEN 0 AND 1 AND v BETWEEN 0 AND 1 THEN CAST(least(hg - 1, floor(v * hg)) * wg + least(wg - 1, floor(u * wg)) AS INT) END",
    "bearing_factor(a DOUBLE) RETURNS DOUBLE": "CASE WHEN abs(a) <= 0.14D THEN 1.0D ELSE exp(-power(abs(a) - 0.14D, 2) / (2 * power(0.35D, 2))) END",
    "range_factor(d DOUBLE) RETURNS DOUBLE": "CASE WHEN d < 1.5D THEN exp(-power(1.5D - d, 2) / (2 * power(0.35D, 2))) WHEN d > 3.0D THEN exp(-power(d - 3.0D, 2) / 2) ELSE 1.0D END",
    "pool_stride(age DOUBLE, tau DOUBLE, side INT) RETURNS INT": "CAST(greatest(1, least(side, floor(exp(least(age / tau, 60))))) AS INT)",
}


@pandas_udf(T.DoubleType())
def ade(z: pd.Series, zhat: pd.Series) -> pd.Series:
    a, b = rvq.integrate(np.stack(z)), rvq.integrate(np.stack(zhat))
    return pd.Series(np.hypot(a[..., 0] - b[..., 0], a[..., 1] - b[..., 1]).mean(1))


@pandas_udf(T.ArrayType(T.DoubleType()))
def integrate_se2(z: pd.Series) -> pd.Series:
    return pd.Series(list(rvq.integrate(np.stack(z)).reshape(len(z), -1)))


@pandas_udf(T.DoubleType())
def ndtw(x: pd.Series, y: pd.Series, rx: pd.Series, ry: pd.Series, d_th: pd.Series) -> pd.Series:
    return pd.Series([np.exp(-rollouts.dtw(np.column_stack([a, b]), np.column_stack([c, d])) / (len(c) * t)) for a, b, c, d, t in zip(x, y, rx, ry, d_th, strict=True)])


@pandas_udf(T.DoubleType())
def mean_of(v: pd.Series) -> float:
    """A grouped aggregate in Arrow batches; ``dtw_mean`` in SQL."""
    return float(v.mean())


@udtf(returnType=T.StructType().add("levels", T.IntegerType()).add("codes", T.ArrayType(T.IntegerType())))
class DecodePrefixes:
    """One row for each non-empty prefix of a code."""

    def eval(self, codes):
        for i in range(1, len(codes) + 1):
            yield i, list(codes[:i])


@udtf(returnType=T.StructType().add("place", T.IntegerType()))
class Keyframes:
    """Places of k evenly spaced frames among n."""

    def eval(self, n: int, k: int):
        for p in sorted({int(np.floor(i * (n - 1) / max(1, k - 1) + 0.5)) + 1 for i in range(k)}):
            yield (p,)


@udtf(returnType=T.StructType().add("item", T.IntegerType()).add("bin", T.IntegerType()).add("offset", T.IntegerType()))
class PackLengths:
    """Bins of an array of lengths, by first fit decreasing."""

    def eval(self, lengths, cap: int):
        order = sorted(range(len(lengths)), key=lambda i: (-lengths[i], i))
        bins, offsets = _bins([min(cap, lengths[i]) for i in order], cap, "ffd")
        yield from zip(order, bins, offsets, strict=True)


def register_all(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Make everything callable from SQL; with ``sf_dir`` also the carrier views."""
    for head, body in EXPRESSIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    for name, f in (("ade", ade), ("integrate_se2", integrate_se2), ("ndtw", ndtw), ("dtw_mean", mean_of)):
        spark.udf.register(name, f)
    for name, f in (("decode_prefixes", DecodePrefixes), ("keyframes", Keyframes), ("pack_lengths", PackLengths)):
        spark.udtf.register(name, f)
    if sf_dir:
        for name in ("v_steps", "v_chunks", "v_traj", "v_frames", "v_rollouts", "v_path", "v_views", "v_samples", "v_turns", "v_targets"):
            getattr(carriers, name)(spark, sf_dir).createOrReplaceTempView(name)



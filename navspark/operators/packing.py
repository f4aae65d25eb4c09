"""Packing of variable-length samples into fixed-capacity sequences, and its padded baseline.

Samples are dealt to shards by hash; a bin never crosses shards, so waste is at most one open
bin a shard. Only (id, length) rows travel; payloads follow by one join on the id.
"""

from __future__ import annotations

import bisect
import heapq

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.session import bounded

SHARD_ROWS = 1_000_000  #: samples aimed at in a shard


def with_oversize(samples: DataFrame, cap: int, oversize: str = "truncate") -> DataFrame:
    """Over-long samples are cut to the cap or dropped; ``oversized`` marks the former."""
    s = samples.withColumn("oversized", F.col("n_tok") > cap)
    if oversize == "drop":
        return s.where(~F.col("oversized"))
    return s.withColumn("n_tok", F.least("n_tok", F.lit(cap)))


def _bins(lengths: list[int], cap: int, algo: str) -> tuple[list[int], list[int]]:
    """Bin and offset of each length, in the given order."""
    bins, offsets, used = [], [], []
    if algo == "nextfit":
        for n in lengths:
            if not used or used[-1] + n > cap:
                used.append(0)
            bins.append(len(used) - 1)
            offsets.append(used[-1])
            used[-1] += n
    elif algo == "ffd":  # first fit: a tree over the free room finds the first bin that takes a length
        size, free = 1, [0, 0]
        for n in lengths:
            if free[1] < n:
                if len(used) == size:
                    old = used
                    size *= 2
                    free = [0] * (2 * size)
                    for i, u in enumerate(old):
                        free[size + i] = cap - u
                    for i in range(size - 1, 0, -1):
                        free[i] = max(free[2 * i], free[2 * i + 1])
                used.append(0)
                b = len(used) - 1
            else:
                i = 1
                while i < size:
                    i = 2 * i if free[2 * i] >= n else 2 * i + 1
                b = i - size
            bins.append(b)
            offsets.append(used[b])
            used[b] += n
            i = size + b
            free[i] = cap - used[b]
            while i > 1:
                i //= 2
                free[i] = max(free[2 * i], free[2 * i + 1])
    elif algo == "bestfit":
        room: list[tuple[int, int]] = []  # (free room, bin), sorted
        for n in lengths:
            i = bisect.bisect_left(room, (n, -1))
            if i == len(room):
                used.append(0)
                b = len(used) - 1
            else:
                b = room.pop(i)[1]
            bins.append(b)
            offsets.append(used[b])
            used[b] += n
            bisect.insort(room, (cap - used[b], b))
    elif algo == "worstfit":
        heap: list[tuple[int, int]] = []
        for n in lengths:
            if heap and cap - heap[0][0] >= n:
                u, b = heapq.heappop(heap)
            else:
                used.append(0)
                u, b = 0, len(used) - 1
            bins.append(b)
            offsets.append(u)
            used[b] = u + n
            heapq.heappush(heap, (u + n, b))
    else:
        raise ValueError(f"unknown algorithm {algo}")
    return bins, offsets


def pack(samples: DataFrame, cap: int = 8192, algo: str = "ffd", shards: int | None = None, oversize: str = "truncate") -> DataFrame:
    """(shard, bin_id, sample_id, n_tok, offset). nextfit keeps the order of ids; the others go by length."""
    s = with_oversize(samples.select("sample_id", "n_tok"), cap, oversize)
    if shards is None:
        shards = max(1, -(-s.count() // SHARD_ROWS))
    s = s.withColumn("shard", F.pmod(F.xxhash64("sample_id"), F.lit(shards)).cast("int"))

    def go(t: pd.DataFrame) -> pd.DataFrame:
        t = t.sort_values(["sample_id"] if algo == "nextfit" else ["n_tok", "sample_id"], ascending=[True] if algo == "nextfit" else [False, True])
        bins, offsets = _bins(t.n_tok.tolist(), cap, algo)
        return pd.DataFrame({"shard": t["shard"], "bin_id": bins, "sample_id": t.sample_id, "n_tok": t.n_tok, "offset": offsets, "oversized": t.oversized})

    return s.groupBy("shard").applyInPandas(go, "shard int, bin_id int, sample_id long, n_tok int, offset int, oversized boolean")


def pack_stats(packed: DataFrame, cap: int) -> DataFrame:
    """Bins, samples a bin, fill, waste, and the lower bound of bins."""
    return packed.agg(
        F.count_distinct("shard", "bin_id").alias("n_bins"),
        F.count("*").alias("n_samples"),
        F.sum("n_tok").alias("n_tok"),
        F.sum(F.col("oversized").cast("long")).alias("n_oversized"),
    ).select(
        "n_bins",
        (F.col("n_samples") / F.col("n_bins")).alias("mean_samples"),
        (F.col("n_tok") / (F.col("n_bins") * cap)).alias("fill"),
        (F.col("n_bins") * cap - F.col("n_tok")).alias("waste"),
        F.ceil(F.col("n_tok") / cap).alias("lower_bound"),
        "n_oversized",
    )


def pad_plan(samples: DataFrame, cap: int) -> DataFrame:
    """The baseline: every sample alone, padded to the longest (at most ``cap``)."""
    s = with_oversize(samples.select("sample_id", "n_tok"), cap)
    a = s.agg(F.count("*").alias("n_bins"), F.max("n_tok").alias("longest"), F.sum("n_tok").alias("n_tok"))
    return a.select("n_bins", F.lit(1.0).alias("mean_samples"), (F.col("n_tok") / (F.col("n_bins") * F.col("longest"))).alias("fill"), (F.col("n_bins") * F.col("longest") - F.col("n_tok")).alias("waste"))


def batch_plan(packed: DataFrame, batch: int) -> DataFrame:
    """Global batches of ``batch`` sequences, in bin order."""
    bins = packed.select("shard", "bin_id").distinct()
    earlier = W.orderBy("shard").rowsBetween(W.unboundedPreceding, -1)  # one row a shard, that is a millionth of the samples
    before = bounded(bins.groupBy("shard").count().select("shard", F.coalesce(F.sum("count").over(earlier), F.lit(0)).alias("before")))
    place = F.row_number().over(W.partitionBy("shard").orderBy("bin_id")) - 1
    return bins.join(before, "shard").withColumn("batch_id", F.floor((F.col("before") + place) / batch)).drop("before")


def lr_at(step: Column, base: float, warmup: float, total: int) -> Column:
    """Linear warm-up over a share of the steps, then cosine decay to zero."""
    w = max(1, int(total * warmup))
    decay = 0.5 * base * (1 + F.cos(F.lit(3.141592653589793) * (step - w) / max(1, total - w)))
    return F.when(step < w, base * (step + 1) / w).otherwise(decay)

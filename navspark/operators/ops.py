"""General joins and sampling operators that Spark lacks."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from navspark.functions.core import uniform01
from navspark.session import bounded, kept, stored


def asof_join(left: DataFrame, right: DataFrame, on: str, by: list[str], tol: float | None = None, prefix: str = "r_") -> DataFrame:
    """For each left row the latest right row of the same keys not after it (within ``tol`` of ``on``).

    One shuffle: both sides are united and the last right row is carried forward.
    """
    value = [c for c in right.columns if c not in by]
    lcols = [c for c in left.columns if c not in by and c != on]
    pack_l, pack_r = F.struct(*lcols) if lcols else F.struct(F.lit(0).alias("_")), F.struct(*value)
    a = left.select(*by, F.col(on).alias("_o"), F.lit(1).alias("_side"), pack_l.alias("_l"))
    b = right.select(*by, F.col(on).alias("_o"), F.lit(0).alias("_side"), pack_r.alias("_r"))
    u = a.unionByName(b, allowMissingColumns=True)
    w = W.partitionBy(*by).orderBy("_o", "_side").rowsBetween(W.unboundedPreceding, 0)
    u = u.withColumn("_r", F.last("_r", ignorenulls=True).over(w)).where(F.col("_side") == 1)
    if tol is not None:
        u = u.withColumn("_r", F.when(F.col("_o") - F.col(f"_r.{on}") <= tol, F.col("_r")))
    return u.select(*by, F.col("_o").alias(on), *[F.col(f"_l.{c}").alias(c) for c in lcols], *[F.col(f"_r.{c}").alias(prefix + c) for c in value])


def interval_join(points: DataFrame, spans: DataFrame, at: str, begin: str, end: str, by: list[str], width: float) -> DataFrame:
    """Points within [begin, end] of spans with equal keys, by buckets of ``width`` units."""
    p = points.withColumn("_b", F.floor(F.col(at) / width))
    s = spans.withColumn("_b", F.explode(F.sequence(F.floor(F.col(begin) / width), F.floor(F.col(end) / width))))
    return p.join(s, [*by, "_b"]).where(F.col(at).between(F.col(begin), F.col(end))).drop("_b")


EDGE = 1 + 1e-9  #: cells are wider than the radius by this, so that rounding can't part two rows at the radius by two cells


def with_cells(df: DataFrame, eps: float, dims: tuple[str, ...]) -> DataFrame:
    return df.withColumns({f"_c{i}": F.floor(F.col(d) / eps) for i, d in enumerate(dims)})


def _forward(d: int, reach: int) -> list[tuple[int, ...]]:
    """Half of the cells around a cell: those after it in order."""
    return [o for o in itertools.product(range(-reach, reach + 1), repeat=d) if o > (0,) * d]


def _visits(df: DataFrame, cells: list[str], offsets: list[tuple[int, ...]]) -> DataFrame:
    """Each row once for each offset, with its cells moved by it; ``_other`` tells whether that is another cell.

    The offsets fold to one literal, so the array isn't built anew for every row.
    """
    to = F.explode(F.array(*[F.struct(*[F.lit(o).alias(c) for c, o in zip(cells, off, strict=True)], F.lit(any(off)).alias("other")) for off in offsets]))
    out = df.withColumn("_to", to).withColumns({c: F.col(c) + F.col(f"_to.{c}") for c in cells} | {"_other": F.col("_to.other")})
    return out.drop("_to")


def _squares(terms: list[Column]) -> Column:
    total = terms[0] ** 2
    for t in terms[1:]:
        total = total + t**2
    return total


def proximity_join(left: DataFrame, right: DataFrame, eps: float, by: list[str], dims: tuple[str, ...] = ("x", "y", "z")) -> DataFrame:
    """Pairs with equal keys at most ``eps`` apart: each left row visits its 3**d cells, then an equi-join.

    Columns come back prefixed with l_ and r_.
    """
    a = with_cells(left, eps * EDGE, dims)
    for i in range(len(dims)):
        a = a.withColumn(f"_c{i}", F.explode(F.array(*[F.col(f"_c{i}") + d for d in (-1, 0, 1)])))
    b = with_cells(right, eps * EDGE, dims)
    cells = [f"_c{i}" for i in range(len(dims))]
    a = a.select(*[F.col(c).alias(f"l_{c}") for c in left.columns], *cells)
    b = b.select(*[F.col(c).alias(f"r_{c}") for c in right.columns], *[F.col(c).alias(f"_r{c}") for c in cells])
    cond = [F.col(f"l_{k}") == F.col(f"r_{k}") for k in by] + [F.col(c) == F.col(f"_r{c}") for c in cells]
    near = sum(((F.col(f"l_{d}") - F.col(f"r_{d}")) ** 2 for d in dims[1:]), (F.col(f"l_{dims[0]}") - F.col(f"r_{dims[0]}")) ** 2)
    return a.join(b, cond).where(near <= eps * eps).drop(*cells, *[f"_r{c}" for c in cells])


def proximity_pairs(df: DataFrame, eps: float, by: list[str], id_col: str, dims: tuple[str, ...] = ("x", "y", "z")) -> DataFrame:
    """(a, b, *by): each pair of two rows with equal keys at most ``eps`` apart, once. A row visits its own cell and
    half of those around it, so half the rows travel and half the distances are taken of a join of the table with itself.
    Rows with one id are told apart by their place; those alike in both are not paired with each other."""
    cells = [f"_c{i}" for i in range(len(dims))]
    rows = with_cells(df.select(id_col, *by, *dims), eps * EDGE, dims)
    a = _visits(rows.select(*by, F.col(id_col).alias("a"), *[F.col(d).alias(f"_a{d}") for d in dims], *cells), cells, [(0,) * len(dims), *_forward(len(dims), 1)])
    j = a.join(rows.withColumnRenamed(id_col, "b"), [*by, *cells]).where(F.col("_other") | (F.struct("a", *[f"_a{d}" for d in dims]) < F.struct("b", *dims)))
    return j.where(_squares([F.col(f"_a{d}") - F.col(d) for d in dims]) <= eps * eps).select("a", "b", *by)


def _placed(by: list[str], dims: tuple[str, ...]) -> Column:
    """Of rows that can be near any: no null key, and coordinates that are finite numbers."""
    ok = F.lit(True)
    for c in by:
        ok = ok & F.col(c).isNotNull()
    for d in dims:
        ok = ok & F.coalesce(F.abs(F.col(d).cast("double")) < math.inf, F.lit(False))
    return ok


def proximity_counts(df: DataFrame, eps: float, by: list[str], per: list[str], dims: tuple[str, ...] = ("x", "y", "z")) -> DataFrame:
    """(*per, n): how many ordered pairs of rows with equal keys lie at most ``eps`` apart, each row with itself too.

    What ``proximity_join`` of the table with itself has, counted without making the pairs: rows of one place travel as
    one row and its number, to half the cells around it, and no other column goes along.
    """
    cells = [f"_c{i}" for i in range(len(dims))]
    rows = kept(with_cells(df.where(_placed(by, dims)).groupBy(*by, *dims).agg(F.count("*").alias("_n")), eps * EDGE, dims))
    a = _visits(rows.select(*by, F.col("_n").alias("_m"), *[F.col(d).alias(f"_a{d}") for d in dims], *cells), cells, [(0,) * len(dims), *_forward(len(dims), 1)])
    j = a.join(rows, [*by, *cells]).where(F.col("_other") | (F.struct(*[f"_a{d}" for d in dims]) < F.struct(*dims)))
    two = j.where(_squares([F.col(f"_a{d}") - F.col(d) for d in dims]) <= eps * eps).select(*per, (2 * F.col("_m") * F.col("_n")).alias("_p"))
    return rows.select(*per, (F.col("_n") * F.col("_n")).alias("_p")).unionByName(two).groupBy(*per).agg(F.sum("_p").alias("n"))


LOCAL = 400_000  #: most places of one key that a task links by itself


def _root(up: np.ndarray, x: np.ndarray) -> np.ndarray:
    while True:
        r = up[x]
        if (r == x).all():
            return r
        x = r


def _union(up: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    while len(a):
        a, b = _root(up, a), _root(up, b)
        a, b = a[a != b], b[a != b]
        np.minimum.at(up, np.maximum(a, b), np.minimum(a, b))
    up[:] = _root(up, np.arange(len(up)))


def _steps(cell: np.ndarray, reach: int) -> np.ndarray:
    """Factors that make one number of a cell, with room for its neighbours; exact integers of any size if need be."""
    wide = [int(w) + 1 + 2 * reach for w in cell.max(0) - cell.min(0)]
    step = [math.prod(wide[i + 1 :]) for i in range(len(wide))]
    return np.array(step, np.int64 if math.prod(wide) < 1 << 62 else object)


def place_components(x: np.ndarray, eps: float) -> np.ndarray:
    """The first place of each place's group, linked by steps of at most ``eps``, as ``near_components`` finds them."""
    cell, of = np.unique(np.floor(x / (0.55 * eps)).astype(np.int64), axis=0, return_inverse=True)
    of = of.ravel()
    order = np.argsort(of, kind="stable")
    start = np.searchsorted(of[order], np.arange(len(cell) + 1))
    low, high = np.minimum.reduceat(x[order], start[:-1]), np.maximum.reduceat(x[order], start[:-1])
    step = _steps(cell, 2)
    key = ((cell - cell.min(0)) * step).sum(1)  # ascending, as the cells are
    up, first, second = np.arange(len(cell)), [], []
    for off in _forward(x.shape[1], 2):
        want = key + (np.array(off) * step).sum()
        to = np.minimum(np.searchsorted(key, want), len(key) - 1)
        a = np.flatnonzero(key[to] == want)
        b = to[a]
        gap = np.maximum(0.0, np.maximum(low[b] - high[a], low[a] - high[b]))
        span = np.maximum(high[b] - low[a], high[a] - low[b])
        near, sure = (gap**2).sum(1) <= eps * eps, (span**2).sum(1) <= eps * eps
        _union(up, a[sure], b[sure])
        first.append(a[near & ~sure])
        second.append(b[near & ~sure])
    for a, b in zip(np.concatenate(first).tolist(), np.concatenate(second).tolist(), strict=True):
        if _root(up, np.array([a]))[0] != _root(up, np.array([b]))[0]:
            p, q = x[order[start[a] : start[a + 1]]], x[order[start[b] : start[b + 1]]]
            step = max(1, (1 << 20) // len(q))
            if any((((p[s : s + step, None] - q[None]) ** 2).sum(2) <= eps * eps).any() for s in range(0, len(p), step)):
                _union(up, np.array([a]), np.array([b]))
    group = _root(up, np.arange(len(cell)))[of]
    least = np.full(len(cell), len(x))
    np.minimum.at(least, group, np.arange(len(x)))
    return least[group]


def place_seeds(x: np.ndarray, eps: float) -> np.ndarray:
    """Each place's first seed within ``eps``: in order, a place without one becomes a seed. Seeds are so far apart that few are in reach."""
    around, side = list(itertools.product((-1, 0, 1), repeat=x.shape[1])), eps * EDGE
    seeds: dict[tuple[int, ...], list[tuple[int, list[float]]]] = {}
    out = np.arange(len(x))
    for i, (p, c) in enumerate(zip(x.tolist(), np.floor(x / side).astype(np.int64).tolist(), strict=True)):
        best = i
        for off in around:
            for j, q in seeds.get(tuple(map(int.__add__, c, off)), ()):
                if j < best and sum((u - v) ** 2 for u, v in zip(p, q, strict=True)) <= eps * eps:
                    best = j
        out[i] = best
        if best == i:
            seeds.setdefault(tuple(c), []).append((i, p))
    return out


def linked_places(df: DataFrame, eps: float, by: list[str], id_col: str, dims: tuple[str, ...], how) -> tuple[DataFrame, DataFrame | None]:
    """Rows of ``df`` with ``root``, found by ``how`` (``place_components`` or ``place_seeds``) among the places of a key in
    the order of their smallest ids; and the rows of keys with more than ``LOCAL`` places, which are left to the caller.

    Rows of one place count once, a task has one key's places at a time, and no pair is shuffled. Rows with a null key
    or without a finite place stay alone.
    """
    places = stored(df.where(_placed(by, dims)).groupBy(*by, *dims).agg(F.min(id_col).alias("_id")))
    crowded = places.groupBy(*by).count().where(F.col("count") > LOCAL).select(*by)
    large = None
    if not crowded.isEmpty():
        there = df.join(crowded, by, "left_semi")
        large = there.where(_placed(by, dims))
        df = df.join(crowded, by, "left_anti").unionByName(there.where(~_placed(by, dims)))
        places = places.join(crowded, by, "left_anti")
    names = places.columns

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("_id")
        x = np.stack([t.column(d).to_numpy().astype(float) for d in dims], 1)
        return t.append_column("root", t.column("_id").take(pa.array(how(x, eps))))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in places.schema) + f", root {places.schema['_id'].dataType.simpleString()}"
    got = stored(places.groupBy(*by).applyInArrow(run, schema).select(*names[:-1], "root"))
    alone = df.where(~_placed(by, dims)).select(*df.columns, F.col(id_col).alias("root"))
    return df.where(_placed(by, dims)).join(bounded(got), [*by, *dims]).select(*df.columns, "root").unionByName(alone), large  # ids needn't travel if the caller has no use for them


def near_components(df: DataFrame, eps: float, by: list[str], id_col: str, dims: tuple[str, ...] = ("x", "y", "z")) -> DataFrame:
    """(id, root): rows with equal keys linked by steps of at most ``eps``; the root is the smallest id. Keys with
    very many places are linked across tasks (``cell_components``). Rows with a null key or coordinate stay alone."""
    if len(dims) > 3:
        raise ValueError("cells hold linked rows in at most three dimensions")
    got, large = linked_places(df.select(id_col, *by, *dims), eps, by, id_col, dims, place_components)
    got = got.select(id_col, "root")
    return got if large is None else got.unionByName(cell_components(large, eps, by, id_col, dims))


def cell_components(df: DataFrame, eps: float, by: list[str], id_col: str, dims: tuple[str, ...] = ("x", "y", "z")) -> DataFrame:
    """(id, root): rows with equal keys linked by steps of at most ``eps``; the root is the smallest id.

    Cells are so small that all rows of one are linked, so a crowded cell costs one row and none of
    its pairs. Of two cells the boxes around their rows mostly tell whether a link exists. Only where they
    don't, and no chain of such links joins the two anyway, are rows compared. Rows with a null key or
    coordinate stay alone.
    """
    if len(dims) > 3:
        raise ValueError("cells hold linked rows in at most three dimensions")
    cells = [f"_c{i}" for i in range(len(dims))]
    rows = with_cells(df.select(id_col, *by, *dims), 0.55 * eps, dims)  # 0.55 * sqrt(3) < 1 < 2 * 0.55
    lows, highs = [F.min(d).alias(f"lo{i}") for i, d in enumerate(dims)], [F.max(d).alias(f"hi{i}") for i, d in enumerate(dims)]
    box = kept(rows.groupBy(*by, *cells).agg(F.min(id_col).alias("node"), *lows, *highs))
    sides = range(len(dims))
    there = box.select(*by, *cells, F.col("node").alias("b"), *[F.col(f"{e}{i}").alias(f"b{e}{i}") for e in ("lo", "hi") for i in sides])
    a = _visits(box.select(*by, F.col("node").alias("a"), *[F.col(f"{e}{i}") for e in ("lo", "hi") for i in sides], *cells), cells, _forward(len(dims), 2)).drop("_other")
    j = a.join(there, [*by, *cells])
    least = _squares([F.greatest(F.lit(0.0), F.col(f"blo{i}") - F.col(f"hi{i}"), F.col(f"lo{i}") - F.col(f"bhi{i}")) for i in sides])
    most = _squares([F.greatest(F.col(f"bhi{i}") - F.col(f"lo{i}"), F.col(f"hi{i}") - F.col(f"blo{i}")) for i in sides])
    pairs = kept(j.where(least <= eps * eps).select("a", "b", (most <= eps * eps).alias("sure"), *[f"b{e}{i}" for e in ("lo", "hi") for i in sides]))
    sure = pairs.where("sure").select("a", "b")
    root = components(sure, "a", "b")
    named = kept(rows.join(box.select(*by, *cells, "node"), [*by, *cells], "left").select(id_col, F.coalesce("node", id_col).alias("node"), *dims))
    open_ = pairs.where("not sure").join(root.select(F.col("node").alias("a"), F.col("root").alias("_ra")), "a", "left").join(root.select(F.col("node").alias("b"), F.col("root").alias("_rb")), "b", "left")
    open_ = open_.withColumns({"_ra": F.coalesce("_ra", "a"), "_rb": F.coalesce("_rb", "b")}).where("_ra <> _rb")
    beside = _squares([F.greatest(F.lit(0.0), F.col(f"blo{i}") - F.col(d), F.col(d) - F.col(f"bhi{i}")) for i, d in enumerate(dims)])
    one = open_.join(named.withColumnRenamed("node", "a"), "a").where(beside <= eps * eps).select("_ra", "_rb", "b", *[F.col(d).alias(f"_a{d}") for d in dims])
    two = one.join(named.select(F.col("node").alias("b"), *dims), "b").where(_squares([F.col(f"_a{d}") - F.col(d) for d in dims]) <= eps * eps)
    over = components(two.select("_ra", "_rb").distinct(), "_ra", "_rb").select(F.col("node").alias("_first"), F.col("root").alias("_last"))
    ends = named.join(root, "node", "left").select(id_col, F.coalesce("root", "node").alias("_first"))
    return ends.join(over, "_first", "left").select(id_col, F.coalesce("_last", "_first").alias("root"))


def top_k(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    """First k rows of each group; Spark limits groups before the shuffle."""
    return df.withColumn("_n", F.row_number().over(W.partitionBy(*by).orderBy(*order))).where(F.col("_n") <= k).drop("_n")


def sample_fraction(df: DataFrame, fraction: float, *keys: str, salt: str = "sample") -> DataFrame:
    """A nested sample: a smaller fraction with the same salt is a subset. No shuffle."""
    return df.where(uniform01(*keys, salt=salt) < fraction)


def first_by_hash(df: DataFrame, key: str, quotas: DataFrame, id_col: str, seed: str, buckets: int = 4096) -> DataFrame:
    """The first ``quota`` rows of each key in hashed order, exactly, without sorting a hot key in one task.

    ``quotas``: (key, quota). A histogram of the hash finds each key's boundary bucket; rows in
    lower buckets stay as they are, and only the boundary bucket is ranked.
    """
    quotas = bounded(kept(quotas.select(key, "quota")))
    d = df.withColumn("_u", uniform01(id_col, salt=seed)).withColumn("_b", F.floor(F.col("_u") * buckets).cast("int"))
    hist = d.groupBy(key, "_b").agg(F.count("*").alias("_c"))
    w = W.partitionBy(key).orderBy("_b").rowsBetween(W.unboundedPreceding, -1)
    hist = hist.withColumn("_before", F.coalesce(F.sum("_c").over(w), F.lit(0))).join(quotas, key)
    cut = hist.where((F.col("_before") + F.col("_c") > F.col("quota")) | (F.col("_before") > F.col("quota")))
    cut = bounded(kept(cut.groupBy(key).agg(F.min(F.struct("_b", (F.col("quota") - F.col("_before")).alias("_left"))).alias("_cut"))))
    d = d.join(quotas, key, "left_semi").join(cut, key, "left")
    low = d.where(F.col("_cut").isNull() | (F.col("_b") < F.col("_cut._b")))
    edge = d.where(F.col("_b") == F.col("_cut._b"))
    edge = edge.withColumn("_r", F.row_number().over(W.partitionBy(key).orderBy("_u", id_col))).where(F.col("_r") <= F.col("_cut._left"))
    return low.select(*df.columns).unionByName(edge.select(*df.columns))


def salted_sum(df: DataFrame, by: list[str], value: str, salts: int = 16) -> DataFrame:
    """Two-level sum for keys so hot that even partial sums meet in one task unevenly."""
    first = df.withColumn("_s", F.pmod(F.monotonically_increasing_id(), F.lit(salts))).groupBy(*by, "_s").agg(F.sum(value).alias("_v"), F.count("*").alias("_n"))
    return first.groupBy(*by).agg(F.sum("_v").alias(value), F.sum("_n").alias("n"))


def components(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """(node, root) by min-label propagation with pointer jumping, until no label changes. Every round's
    labels are written to the shared folder: no round is computed twice, lineage stays short and
    lost executors cost a reread."""
    both = kept(pairs.select(F.col(a).alias("u"), F.col(b).alias("v")).unionByName(pairs.select(F.col(b).alias("u"), F.col(a).alias("v"))).distinct())
    label = kept(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("root")))
    while True:
        seen = both.join(label.select(F.col("u").alias("v"), F.col("root").alias("r")), "v").groupBy("u").agg(F.min("r").alias("r"))
        step = label.join(seen, "u").select("u", F.least("root", "r").alias("best"), F.col("root").alias("old"))
        jump = label.select(F.col("u").alias("best"), F.col("root").alias("r2"))
        label = kept(step.join(jump, "best", "left").select("u", F.least("r2", "best").alias("root"), "old"))
        if label.where("root <> old").isEmpty():
            return label.select(F.col("u").alias("node"), "root")
        label = label.drop("old")

"""Residual vector quantisation of planar-pose trajectories.

Fitting runs Lloyd rounds in metric space (increments mapped by the square root of the weights
times the Jacobian of the integrated waypoints), level by level on the residuals of the level
before. A round is one scan: each task assigns its rows by a matrix product and returns K rows
of partial sums, so what is shuffled and collected is K rows a task, whatever the data's size.
Encoding is an Arrow map over broadcast codebooks (a few hundred kB), no shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from navspark.functions import geometry as G

D = 30
STEPS = 10


def jacobian_ref(c: float = 0.25) -> np.ndarray:
    """Derivative of ten waypoints by 30 increments, for straight motion with step c."""
    j = np.zeros((D, D))
    for out in range(STEPS):
        for i in range(out + 1):
            for k in range(3):
                j[3 * out + k, 3 * i + k] = 1.0
            if i < out:
                j[3 * out + 1, 3 * i + 2] = c * (out - i)
    return j


def jacobian_at(z: np.ndarray) -> np.ndarray:
    """The same at the trajectory z."""
    z = z.reshape(STEPS, 3)
    h = np.concatenate([[0], np.cumsum(z[:, 2])])[:-1]
    cos, sin = np.cos(h), np.sin(h)
    turn = np.stack([-z[:, 0] * sin - z[:, 1] * cos, z[:, 0] * cos - z[:, 1] * sin], 1)
    j = np.zeros((D, D))
    for out in range(STEPS):
        for i in range(out + 1):
            j[3 * out, 3 * i : 3 * i + 2] = cos[i], -sin[i]
            j[3 * out + 1, 3 * i : 3 * i + 2] = sin[i], cos[i]
            j[3 * out + 2, 3 * i + 2] = 1.0
            if i < out:
                j[3 * out : 3 * out + 2, 3 * i + 2] = turn[i + 1 : out + 1].sum(0)
    return j


def weights(lam: float = G.LAMBDA) -> np.ndarray:
    """Diagonal weights of waypoint errors, mirroring the trajectory distance."""
    w = np.tile([1 / STEPS, 1 / STEPS, 1e-6], STEPS)
    w[-1] = lam**2
    return w


def metric_map(c: float = 0.25, lam: float = G.LAMBDA) -> np.ndarray:
    return np.sqrt(weights(lam))[:, None] * jacobian_ref(c)


def d_j(r: np.ndarray, e: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Jacobian-weighted squared distance; m is ``metric_map`` or that of a sample."""
    return (((r - e) @ m.T) ** 2).sum(-1)


def integrate(z: np.ndarray) -> np.ndarray:
    """Waypoints (n, 10, 3) of increments (n, 30)."""
    z = z.reshape(-1, STEPS, 3)
    h = np.cumsum(z[..., 2], 1)
    before = np.concatenate([np.zeros((len(z), 1)), h[:, :-1]], 1)
    x = np.cumsum(z[..., 0] * np.cos(before) - z[..., 1] * np.sin(before), 1)
    y = np.cumsum(z[..., 0] * np.sin(before) + z[..., 1] * np.cos(before), 1)
    return np.stack([x, y, h], -1)


def _wrapped(a: np.ndarray) -> np.ndarray:
    return np.pi - np.mod(np.pi - a, 2 * np.pi)


def d_traj(z: np.ndarray, zhat: np.ndarray, lam: float = G.LAMBDA) -> np.ndarray:
    a, b = integrate(z), integrate(zhat)
    return np.hypot(a[..., 0] - b[..., 0], a[..., 1] - b[..., 1]).mean(-1) + lam * np.abs(_wrapped(a[:, -1, 2] - b[:, -1, 2]))


@dataclass
class Codebooks:
    """levels x k x 30 code vectors in increment space."""

    vec: np.ndarray
    shift: list[float] = field(default_factory=list)

    @property
    def levels(self) -> int:
        return self.vec.shape[0]

    @property
    def k(self) -> int:
        return self.vec.shape[1]

    def combinations(self) -> int:
        return self.k**self.levels

    def frame(self, spark) -> DataFrame:
        rows = [(lv, k, [float(x) for x in self.vec[lv, k]]) for lv in range(self.levels) for k in range(self.k)]
        return spark.createDataFrame(rows, "level int, k int, vec array<double>")

    @classmethod
    def from_frame(cls, df: DataFrame) -> "Codebooks":
        """Read a stored codebook; its size is bounded by levels * K."""
        rows = df.orderBy("level", "k").collect()
        n = max(r.level for r in rows) + 1
        return cls(np.array([r.vec for r in rows]).reshape(n, -1, D))


def nearest(a: np.ndarray, b: np.ndarray, tol: float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """For each row of a the first row of b within ``tol`` of the smallest squared distance, and that distance.

    One product a block gives the distances but for the row's own norm; a block of them stays in the processor's cache.
    """
    plane = np.vstack([-2 * b.T, (b * b).sum(1)])
    rows = np.hstack([a, np.ones((len(a), 1))])
    k, low = np.empty(len(a), np.int64), np.empty(len(a))
    step = max(16, (1 << 17) // len(b))
    for s in range(0, len(a), step):
        d = rows[s : s + step] @ plane
        low[s : s + step] = least = d.min(1)
        k[s : s + step] = (d <= least[:, None] + tol).argmax(1)
    return k, low + (a * a).sum(1)


def assign(z: np.ndarray, books: np.ndarray, how: str = "d_traj", m: np.ndarray | None = None, lam: float = G.LAMBDA) -> np.ndarray:
    """Code of each level for each row; ties go to the smaller index.

    d_traj: the sum of the prefix and the candidate is integrated and compared with the
    original. d_j: the residual is compared in metric space.
    """
    m = metric_map() if m is None else m
    codes = np.zeros((len(z), len(books)), np.int64)
    done = np.zeros_like(z)
    for lv, book in enumerate(books):
        if how == "d_j":
            codes[:, lv] = nearest((z - done) @ m.T, book @ m.T)[0]
        else:
            step = max(1, (1 << 20) // (len(book) * D))
            for s in range(0, len(z), step):
                cand = (done[s : s + step, None] + book[None]).reshape(-1, D)
                d = d_traj(np.repeat(z[s : s + step], len(book), 0), cand, lam)
                codes[s : s + step, lv] = np.round(d, 9).reshape(-1, len(book)).argmin(1)
        done = done + book[codes[:, lv]]
    return codes


def _rows(col: pa.Array) -> np.ndarray:
    return np.asarray(col.flatten().to_numpy(zero_copy_only=False), float).reshape(-1, D)


def init_codebook(traj: DataFrame, k: int, seed: int = 0, level: int = 0, how: str = "hash", spare: int = 8) -> np.ndarray:
    """k rows to start from, out of a bounded collect in the order of an MD5 of their id.

    hash: the first k. farthest: out of ``spare`` times as many the first, then again and again the row
    farthest from all that are taken, in metric space, so that rare motions get codes too.
    """
    n = k if how == "hash" else spare * k
    rows = traj.orderBy(F.md5(F.concat_ws("|", F.lit(f"{seed}/{level}"), F.col("traj_id").cast("string"))), "traj_id").limit(n).collect()
    z = np.array([r.z for r in rows], float).reshape(-1, D)
    if how == "hash" or len(z) <= k:
        return z[:k]
    if how != "farthest":
        raise ValueError(f"unknown start {how}")
    a = z @ metric_map().T
    taken, gap = [0], ((a - a[0]) ** 2).sum(1)
    while len(taken) < k:
        taken.append(int(gap.argmax()))
        gap = np.minimum(gap, ((a - a[taken[-1]]) ** 2).sum(1))
    return z[taken]


def lloyd_partials(traj: DataFrame, books: np.ndarray, centre: np.ndarray, m: np.ndarray, per_sample: bool = False) -> DataFrame:
    """(k, n, sums, err, far, far_row) of each task for one round on the residual of ``books``.

    per_sample: sums of each row's own metric matrix and its product with the row follow, for
    centroids that solve (sum M) e = sum M r.
    """

    def run(batches):
        n = np.zeros(len(centre))
        sums = np.zeros((len(centre), D + (D * D if per_sample else 0)))
        err, far, far_row = np.zeros(len(centre)), np.full(len(centre), -1.0), np.zeros((len(centre), D))
        step = max(1, (1 << 22) // len(centre)) if per_sample else 1 << 16  # distances held at a time, whatever K
        for z in (z[s : s + step] for z in (_rows(b.column("z")) for b in batches) for s in range(0, len(z), step)):
            r = z - (sum(book[c] for book, c in zip(books, assign(z, books, "d_j", m).T, strict=True)) if len(books) else 0)
            if per_sample:
                w = np.sqrt(weights())
                maps = np.stack([w[:, None] * jacobian_at(x) for x in z])
                d = np.stack([((((r - e)[:, None] @ maps.transpose(0, 2, 1))[:, 0]) ** 2).sum(1) for e in centre], 1)
                k = np.round(d, 12).argmin(1)
                best = d[np.arange(len(d)), k]
            else:
                k, best = nearest(r @ m.T, centre @ m.T, 1e-12)
            n += np.bincount(k, minlength=len(centre))
            err += np.bincount(k, best, minlength=len(centre))
            if per_sample:
                mm = maps.transpose(0, 2, 1) @ maps
                np.add.at(sums, k, np.hstack([(mm @ r[:, :, None])[:, :, 0], mm.reshape(len(r), -1)]))
            else:
                order = np.argsort(k, kind="stable")
                first = np.flatnonzero(np.diff(k[order], prepend=-1))
                sums[k[order[first]]] += np.add.reduceat(r[order], first)
            top = int(best.argmax())
            if best[top] > far[k[top]]:
                far[k[top]], far_row[k[top]] = best[top], r[top]
        used = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays(
            [pa.array(used, pa.int32()), pa.array(n[used]), pa.array(sums[used].tolist(), pa.list_(pa.float64())), pa.array(err[used]), pa.array(far[used]), pa.array(far_row[used].tolist(), pa.list_(pa.float64()))],
            ["k", "n", "sums", "err", "far", "far_row"],
        )

    return traj.select("z").mapInArrow(run, "k int, n double, sums array<double>, err double, far double, far_row array<double>")


def lloyd_step(traj: DataFrame, books: np.ndarray, centre: np.ndarray, m: np.ndarray, per_sample: bool = False) -> tuple[np.ndarray, float]:
    """New centroids and the mean error before the move. Empty clusters get the farthest rows."""
    width = D + (D * D if per_sample else 0)
    parts = lloyd_partials(traj, books, centre, m, per_sample)
    agg = parts.groupBy("k").agg(
        F.sum("n").alias("n"), F.sum("err").alias("err"), F.array(*[F.sum(F.col("sums")[i]) for i in range(width)]).alias("sums"), F.max_by("far_row", "far").alias("far_row"), F.max("far").alias("far")
    )
    got = agg.collect()  # at most K rows
    new, total, err = centre.copy(), 0.0, 0.0
    used = set()
    for g in got:
        s = np.array(g.sums)
        if per_sample:
            new[g.k] = np.linalg.solve(s[D:].reshape(D, D) + 1e-9 * np.eye(D), s[:D])
        else:
            new[g.k] = s / g.n
        used.add(g.k)
        total, err = total + g.n, err + g.err
    far = sorted(((g.far, tuple(g.far_row)) for g in got), reverse=True)
    for k, (_, row) in zip(sorted(set(range(len(centre))) - used), far, strict=False):
        new[k] = row
    return np.round(new, 9), err / max(1.0, total)


def fit_rvq(traj: DataFrame, levels: int = 3, k: int = 256, iters: int = 8, seed: int = 0, c: float = 0.25, metric: str = "fixed", tol: float = 1e-6, start_with: str = "hash") -> Codebooks:
    """Residual k-means. ``metric``: 'fixed' (reference Jacobian) or 'sample' (each row's own); ``start_with``:
    see ``init_codebook``."""
    m = metric_map(c)
    books: list[np.ndarray] = []
    errors: list[float] = []
    for level in range(levels):
        start = init_codebook(traj, k, seed, level, start_with)
        prior = np.array(books)
        if books:
            start = start - sum(b[i] for b, i in zip(prior, assign(start, prior, "d_j", m).T, strict=True))
        if len(start) < k:
            start = np.concatenate([start, np.tile(start[:1], (k - len(start), 1)) + np.arange(1, k - len(start) + 1)[:, None] * 1e3])
        centre, before = start, np.inf
        for _ in range(iters):
            centre, err = lloyd_step(traj, prior, centre, m, metric == "sample")
            if before - err < tol * max(before, 1e-12):
                break
            before = err
        books.append(centre)
        errors.append(err)
    return Codebooks(np.array(books), errors)


def encode(traj: DataFrame, books: Codebooks, how: str = "d_traj", lam: float = G.LAMBDA) -> DataFrame:
    """``traj`` with codes k0.. and the residual norm after each level."""
    vec, keep = books.vec, [f for f in traj.schema if f.name != "codes"]

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            z = _rows(b.column("z"))
            codes = assign(z, vec, how, None, lam)
            left, norms = z.copy(), [np.linalg.norm(z, axis=1)]
            for lv in range(len(vec)):
                left = left - vec[lv][codes[:, lv]]
                norms.append(np.linalg.norm(left, axis=1))
            yield pa.RecordBatch.from_arrays(
                [*(b.column(f.name) for f in keep), *(pa.array(codes[:, lv], pa.int32()) for lv in range(len(vec))), *map(pa.array, norms)],
                [*(f.name for f in keep), *(f"k{lv}" for lv in range(len(vec))), *(f"res_norm{i}" for i in range(len(vec) + 1))],
            )

    out = [f"`{f.name}` {f.dataType.simpleString()}" for f in keep] + [f"k{lv} int" for lv in range(len(vec))] + [f"res_norm{i} double" for i in range(len(vec) + 1)]
    return traj.select(*[f.name for f in keep]).mapInArrow(run, ", ".join(out))


def decode(codes: DataFrame, books: DataFrame, upto: int) -> DataFrame:
    """Adds ``zhat`` and its waypoints from the first ``upto`` codes; later columns are not read."""
    if upto < 1:
        raise ValueError("a prefix has at least one code")
    out = codes
    for lv in range(upto):
        b = F.broadcast(books.where(F.col("level") == lv).select(F.col("k").alias(f"k{lv}"), F.col("vec").alias(f"_v{lv}")))
        out = out.join(b, f"k{lv}")
    z: Column = F.col("_v0")
    for lv in range(1, upto):
        z = G.plus(z, f"_v{lv}")
    return out.withColumn("zhat", z).drop(*[f"_v{lv}" for lv in range(upto)]).withColumn("wps", G.integrate_se2("zhat"))


def levels_for_budget(ms: Column, ms_per_token: float = 4.0, prefix_tokens: int = 2, levels: int = 3) -> Column:
    """How many code tokens fit a latency budget after the pointing prefix."""
    return F.greatest(F.lit(0), F.least(F.lit(levels), F.floor(ms / ms_per_token) - prefix_tokens)).cast("int")


def rvq_eval(coded: DataFrame, books: Codebooks, lam: float = G.LAMBDA) -> DataFrame:
    """(levels, n, mean_ade, mean_dth, used_codes, entropy_bits, dead_codes) for each prefix length, in one scan of ``coded``."""
    vec = books.vec

    def run(batches):
        n, far, turn = np.zeros((len(vec), books.k)), np.zeros((len(vec), books.k)), np.zeros((len(vec), books.k))
        for b in batches:
            for s in range(0, b.num_rows, 2048):  # ten waypoints a row stay in the processor's cache
                part = b.slice(s, 2048)
                z, zhat = _rows(part.column("z")), 0.0
                way = integrate(z)
                for lv, book in enumerate(vec):
                    k = part.column(f"k{lv}").to_numpy()
                    zhat = zhat + book[k]
                    got = integrate(zhat)
                    n[lv] += np.bincount(k, minlength=books.k)
                    far[lv] += np.bincount(k, np.hypot(*np.moveaxis(way[..., :2] - got[..., :2], -1, 0)).mean(-1), books.k)
                    turn[lv] += np.bincount(k, np.abs(_wrapped(way[:, -1, 2] - got[:, -1, 2])), books.k)
        lv, k = np.nonzero(n)
        yield pa.RecordBatch.from_arrays(
            [pa.array(lv + 1, pa.int32()), pa.array(k, pa.int32()), pa.array(n[lv, k].astype(np.int64)), pa.array(far[lv, k]), pa.array(turn[lv, k])], ["levels", "k", "n", "far", "turn"]
        )

    names = [f"k{lv}" for lv in range(len(vec))]
    used = coded.select("z", *names).mapInArrow(run, "levels int, k int, n long, far double, turn double").groupBy("levels", "k").agg(*[F.sum(c).alias(c) for c in ("n", "far", "turn")])
    every = F.sum("n")
    bits = F.log2(every) - F.sum(F.col("n") * F.log2("n")) / every
    got = used.groupBy("levels").agg(every.alias("n"), (F.sum("far") / every).alias("mean_ade"), (F.sum("turn") / every).alias("mean_dth"), F.count("*").alias("used_codes"), bits.alias("entropy_bits"))
    every = coded.sparkSession.range(1, len(vec) + 1).select(F.col("id").cast("int").alias("levels"))  # also without rows
    got = every.join(F.broadcast(got), "levels", "left").fillna(0, ["n", "used_codes"])
    return got.withColumn("dead_codes", F.lit(books.k) - F.col("used_codes")).orderBy("levels")


def lambda_sweep(traj: DataFrame, books: Codebooks, lams: list[float]) -> DataFrame:
    """Displacement and heading error of encodings chosen with different heading weights."""
    frame, out = books.frame(traj.sparkSession), None
    for lam in lams:
        d = decode(encode(traj, books, "d_traj", lam), frame, books.levels)
        one = d.agg(F.avg(G.ade("z", "zhat")).alias("mean_ade"), F.avg(G.heading_err("z", "zhat")).alias("mean_dth")).select(F.lit(lam).alias("lam"), "*")
        out = one if out is None else out.unionByName(one)
    return out

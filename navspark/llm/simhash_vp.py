"""SimHash near-duplicate detection with vantage-point trees.

A fingerprint is a majority vote over the hashes of a document's word shingles. Pairs of
fingerprints at most ``radius`` bits apart are found exactly:

* Distinct fingerprints only are compared; copies share one.
* A fingerprint is cut into ``blocks``. Two fingerprints within ``radius`` bits agree to
  within ``radius // blocks`` bits on some block, so each block is searched with that
  smaller radius, which makes the triangle bounds prune far better.
* For each block a vantage-point tree, built from a bounded sample, splits the space by
  Hamming distance to vantage values. A fingerprint lives in one leaf (its shard) and is
  sent as a query to each leaf its ball overlaps. Within a shard a local tree does the same
  down to small leaves, where distances over all bits decide.
* A shard emits spanning edges of its linked groups, never all pairs. Components follow by
  alternating star contraction with a written table per round.

Memory: a shard of more than ``CHUNK`` rows is cut by hash into chunks, each of which all of
that shard's queries visit, so a task holds a bounded number of rows and no link is lost.

Defined results: null or wordless text has fingerprint zero and links like any other. Rows
sharing a doc_id are fingerprinted each. A null doc_id takes part but never names a
component unless it has no other member. An empty table gives an empty result. Extra columns,
whatever their names, are ignored, and carried by ``survivors``, which keeps one row of each
group: that of the smallest doc_id (null last), then of the smallest hash of the text.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from navspark.llm.common import apart, arrow_map, checked, same_row, text_key, whole, written

SAMPLE = 32  #: fingerprints for each leaf, from which the driver builds the routing trees
DEPTH = 14  #: most levels of a routing tree, so at most 2**19 sampled fingerprints (4 MB)
SHARD = 50_000  #: fingerprints aimed at in a shard
CHUNK = 200_000  #: most fingerprints of one shard that a task holds at a time
SET_CHUNK = 2_000  #: members whose shingle sets a task holds at a time,
SET_BYTES = 16 << 20  #: and the bytes of their hashes
STAR = 1_000  #: leaves of one star that a task compares with their centre
PEEL_FROM = 4  #: chunks of a group that are compared in a grid (of ten cells at most); only larger groups are peeled
PEELS = 6  #: most rounds of stars before what is left of a large group is compared in full
SIGNS = 64  #: most signatures of a set in a size band
SLICE = 1 << 20  #: bytes of a text split into words at a time
SKETCH_BITS = 1 << 15  #: most bits of a set's sketch
SIGN_CHUNK = 20_000  #: sketches of one signature that a task compares,
SIGN_BYTES = 16 << 20  #: and the bytes of a task's sketches
WORD_RADIUS = 3  #: bits of 64 within which the trees look for similar sets, in two blocks
LOCAL_EDGES = 1 << 17  #: most edges, counted first, whose components the driver finds

_XX = partial(xxhash.xxh64_intdigest, seed=42)
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.float64)


def _words(data: bytes) -> Iterator[list[bytes]]:
    """Words of a text in bounded slices, cut at white space."""
    if len(data) <= SLICE:
        yield data.split()
        return
    at = 0
    while at < len(data):
        end = min(len(data), at + SLICE)
        while end < len(data) and data[end] not in b" \t\n\x0b\x0c\r":
            end += 1
        yield data[at:end].split()
        at = end


def shingle_hashes(text: str | None, k: int) -> Iterator[np.ndarray]:
    """Unsigned XXH64 (seed 42) of the space-joined k-word shingles, repeats included."""
    data = (text or "").encode().lower()
    carry: list[bytes] = []
    seen = 0
    for words in _words(data):
        words = carry + words
        if len(words) >= k:
            joined = map(b" ".join, zip(*(words[i:] for i in range(k)), strict=False))
            yield np.fromiter(map(_XX, joined), np.uint64, len(words) - k + 1)
            seen += 1
        carry = words[-(k - 1) :] if k > 1 else []
    if not seen and carry:
        yield np.array([_XX(b" ".join(carry))], np.uint64)


def _votes(h: np.ndarray) -> np.ndarray:
    """How many hashes have each bit set, most significant bit first."""
    as_bytes = h.astype(">u8").view(np.uint8).reshape(len(h), 8)
    if len(h) < 512:
        return np.unpackbits(as_bytes, axis=1).sum(0, dtype=np.float64)
    where = as_bytes.astype(np.intp) + 256 * np.arange(8)
    counts = np.bincount(where.ravel(), minlength=2048).reshape(8, 256).astype(np.float64)
    return (counts @ _BITS).ravel()


def _mixed(h: np.ndarray, word: int) -> np.ndarray:
    """An independent 64-bit hash for each further word of a wide fingerprint."""
    if not word:
        return h
    z = h + np.uint64(word) * np.uint64(0x9E3779B97F4A7C15)
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def fingerprint(text: str | None, k: int = 3, bits: int = 64) -> tuple[bytes, int]:
    """Fingerprint of a text and the number of shingles that voted."""
    parts = list(shingle_hashes(text, k))
    n = sum(map(len, parts))
    return vote(parts, n, bits), n


def vote(parts: list[np.ndarray], n: int, bits: int) -> bytes:
    """The fingerprint of n shingle hashes that come in parts."""
    votes = np.zeros(bits)
    with np.errstate(over="ignore"):
        for h in parts:
            votes += np.concatenate([_votes(_mixed(h, w)) for w in range(bits // 64)])
    return np.packbits(2 * votes > n).tobytes()


def _texts(docs: DataFrame) -> DataFrame:
    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(text).alias("row_key"), text.alias("text"))


def _set_of(text: str | None, k: int) -> np.ndarray:
    parts = list(shingle_hashes(text, k))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def fingerprints(docs: DataFrame, k: int = 3, bits: int = 64, similarity: float | None = None) -> DataFrame:
    """(doc_id, row_key, fp binary, n_shingles) for each row of ``docs``.

    With ``similarity`` each distinct shingle votes once, ``signs`` has the set's signatures, ``sketch`` its sketch, and
    sets as similar as that differ in no more elements than the sum of their ``room``.
    """
    share = 0.0 if similarity is None else (1 - similarity) / (1 + similarity)

    def run(batches):
        for b in batches:
            fps, sizes, signs, sketches = [], [], [], []
            for t in b.column("text"):
                if similarity is None:
                    fp, n = fingerprint(t.as_py(), k, bits)
                else:
                    ids = _set_of(t.as_py(), k)
                    fp, n = vote([ids], len(ids), bits), len(ids)
                    signs.append(signatures(ids, similarity).view(np.int64))
                    sketches.append(sketch(ids))
                fps.append(fp)
                sizes.append(n)
            out = [b.column("doc_id"), b.column("row_key"), pa.array(fps, pa.binary()), pa.array(sizes, pa.int64())]
            names = ["doc_id", "row_key", "fp", "n_shingles"]
            if similarity is not None:
                out += [pa.array(signs, pa.list_(pa.int64())), pa.array(sketches, pa.binary()), pa.array(share * np.array(sizes, float))]
                names += ["signs", "sketch", "room"]
            yield pa.RecordBatch.from_arrays(out, names)

    schema = "doc_id long, row_key long, fp binary, n_shingles long" + (", signs array<long>, sketch binary, room double" if similarity is not None else "")
    return arrow_map(_texts(docs), run, schema)


class VantageTree:
    """A binary vantage-point tree over rows of unsigned words, queried in batches.

    ``split`` halves the rows at the median distance to a vantage row; the triangle bound
    says which halves a ball can meet.
    """

    def __init__(self, rows: np.ndarray, leaf: int, depth: int):
        self.vantage: list[np.ndarray] = []
        self.cut: list[int] = []
        self.kids: list[tuple[int, int]] = []  # >= 0: node, < 0: leaf -(id + 1)
        self.leaves = 0
        self.root = self._grow(rows, leaf, depth)

    def _grow(self, rows: np.ndarray, leaf: int, depth: int) -> int:
        if len(rows) > leaf and depth > 0:
            v = rows[len(rows) // 2]
            d = distance(rows, v)
            cut = int(np.median(d))
            inner = d <= cut
            if inner.all():
                cut = int(d.max()) - 1
                inner = d <= cut
            if 0 <= cut and inner.any() and not inner.all():
                me = len(self.cut)
                self.vantage.append(v)
                self.cut.append(cut)
                self.kids.append((0, 0))
                self.kids[me] = (self._grow(rows[inner], leaf, depth - 1), self._grow(rows[~inner], leaf, depth - 1))
                return me
        self.leaves += 1
        return -self.leaves

    def visit(self, rows: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, leaf, is_home) for each leaf that the ball around a row can meet."""
        idx, node, home = np.arange(len(rows)), np.full(len(rows), self.root), np.ones(len(rows), bool)
        done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        if self.cut:
            vantage, cut, kids = np.array(self.vantage), np.array(self.cut), np.array(self.kids)
        while len(idx):
            end = node < 0
            if end.any():
                done.append((idx[end], -node[end] - 1, home[end]))
                idx, node, home = idx[~end], node[~end], home[~end]
                continue
            d = np.bitwise_count(rows[idx] ^ vantage[node]).sum(1, dtype=np.int64)
            near, far = d - radius <= cut[node], d + radius > cut[node]
            inner = d <= cut[node]
            idx, node, home = (
                np.concatenate([idx[near], idx[far]]),
                np.concatenate([kids[node[near], 0], kids[node[far], 1]]),
                np.concatenate([(home & inner)[near], (home & ~inner)[far]]),
            )
        if not done:
            return idx, node, home
        return tuple(np.concatenate(x) for x in zip(*done, strict=True))


def distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b).sum(-1, dtype=np.int64)


def _matrix(col: pa.Array, bits: int) -> np.ndarray:
    return np.frombuffer(b"".join(col.to_pylist()), ">u8").astype(np.uint64).reshape(-1, bits // 64)


def _block(fp: np.ndarray, j: int, blocks: int) -> np.ndarray:
    """Block j of each fingerprint as a row of words."""
    bits = fp.shape[1] * 64
    width = bits // blocks
    if width >= 64:
        return np.ascontiguousarray(fp[:, j * width // 64 : (j + 1) * width // 64])
    word, low = (j * width) // 64, 64 - (j * width) % 64 - width
    return (fp[:, word : word + 1] >> np.uint64(low)) & np.uint64((1 << width) - 1)


class _Groups:
    """Union of rows by vectorised minimum hooking."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def root(self, x: np.ndarray) -> np.ndarray:
        while True:
            r = self.up[x]
            if (r == x).all():
                return r
            x = r

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.root(a), self.root(b)
            open_ = a != b
            a, b = a[open_], b[open_]
            np.minimum.at(self.up, np.maximum(a, b), np.minimum(a, b))
        self.up = self.root(np.arange(len(self.up)))


def linked_groups(fp: np.ndarray, data: np.ndarray, query: np.ndarray, j: int, blocks: int, radius: int, leaf: int = 512) -> np.ndarray:
    """Root row of each row of ``fp`` after linking query rows to data rows within ``radius``."""
    groups = _Groups(len(fp))
    inner = radius // blocks
    part = _block(fp, j, blocks)
    tree = VantageTree(part[data], leaf, 24)
    at, where, _ = tree.visit(part[data], 0)  # radius zero leads to the home leaf alone
    order = np.argsort(where, kind="stable")
    data_rows, data_leaf = data[at[order]], where[order]
    at, where, _ = tree.visit(part[query], inner)
    order = np.argsort(where, kind="stable")
    query_rows, query_leaf = query[at[order]], where[order]
    for k in range(tree.leaves):
        d = data_rows[np.searchsorted(data_leaf, k) : np.searchsorted(data_leaf, k, "right")]
        q = query_rows[np.searchsorted(query_leaf, k) : np.searchsorted(query_leaf, k, "right")]
        step = max(1, (1 << 21) // max(1, len(d)))
        for s in range(0, len(q), step):
            rows = q[s : s + step]
            apart = np.zeros((len(rows), len(d)), np.uint16)
            for w in range(fp.shape[1]):
                apart += np.bitwise_count(fp[rows, w][:, None] ^ fp[d, w][None, :])
            a, b = np.nonzero(apart <= radius)
            groups.join(rows[a], d[b])
    return groups.up


def _grid(rows: DataFrame, *keep: str, where=None) -> DataFrame:
    """Deals a shard of several chunks to a grid of cells, chunks of data by chunks of queries.

    x is a row's chunk: it is a query in a row of cells and, if at home, data in a column.
    """
    every = F.sequence(F.lit(0), F.col("chunks") - 1)
    cells = F.concat(
        F.transform(every, lambda c: c * F.col("chunks") + F.col("x")),
        F.when(F.col("home"), F.transform(every, lambda c: F.col("x") * F.col("chunks") + c)).otherwise(F.array().cast("array<int>")),
    )
    dealt = rows.withColumn("x", F.pmod(F.xxhash64("fp"), F.col("chunks")).cast("int")).withColumn("cell", F.explode(F.array_distinct(cells)))
    dealt = dealt if where is None else dealt.where(where)
    return dealt.select(
        "shard",
        "cell",
        "fp",
        (F.col("home") & (F.floor(F.col("cell") / F.col("chunks")) == F.col("x"))).alias("data"),
        (F.col("cell") % F.col("chunks") == F.col("x")).alias("query"),
        *keep,
    )


def fingerprint_edges(distinct: DataFrame, bits: int, radius: int, blocks: int, leaf: int = 512) -> DataFrame:
    """Spanning edges (a, b) of fingerprints within ``radius`` bits of each other.

    ``distinct`` is a written table with column fp.
    """
    n = distinct.count()
    depth = max(0, min(DEPTH, int(np.ceil(np.log2(max(1, n) / SHARD)))))
    sample = (
        _matrix(pa.array([bytes(r[0]) for r in distinct.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(SAMPLE << depth).collect()], pa.binary()), bits)
        if depth
        else np.zeros((0, bits // 64), np.uint64)
    )
    trees = [VantageTree(_block(sample, j, blocks), 1, depth) for j in range(blocks)]
    inner = radius // blocks

    def route(batches):
        for b in batches:
            fp = _matrix(b.column("fp"), bits)
            for j in range(blocks):
                at, leaf_no, home = trees[j].visit(_block(fp, j, blocks), inner)
                key = leaf_no * blocks + j
                yield pa.RecordBatch.from_arrays(
                    [b.column("fp").take(pa.array(at)), pa.array(key.astype(np.int64)), pa.array(home)], ["fp", "shard", "home"]
                )

    routed = distinct.select("fp").mapInArrow(route, "fp binary, shard long, home boolean")
    sizes = routed.where("home").groupBy("shard").count()
    # Shards are bounded in number (trees of at most 2**DEPTH leaves), so is this table.
    chunks = sizes.select("shard", F.ceil(F.col("count") / CHUNK).cast("int").alias("chunks"))
    dealt = _grid(routed.join(F.broadcast(chunks), "shard"))

    def search(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        fp = _matrix(t.column("fp"), bits)
        data, query = (np.flatnonzero(t.column(c).to_numpy(zero_copy_only=False)) for c in ("data", "query"))
        root = linked_groups(fp, data, query, key[0].as_py() % blocks, blocks, radius, leaf)
        at = np.flatnonzero(root != np.arange(len(fp)))
        col = t.column("fp")
        return pa.table({"a": col.take(pa.array(at)), "b": col.take(pa.array(root[at]))})

    out = dealt.groupBy("shard", "cell").applyInArrow(search, "a binary, b binary")
    return out.where(F.col("a") != F.col("b")).distinct()


def _local_components(e: DataFrame) -> DataFrame:
    """``components`` of a counted table of few edges (u, v), without a round of shuffles."""
    t = e.select("u", "v").toArrow()
    ends = pa.chunked_array([*t.column("u").chunks, *t.column("v").chunks], t.schema.field("u").type).combine_chunks()
    coded = ends.dictionary_encode()
    order = pc.sort_indices(coded.dictionary).to_numpy()
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    at = rank[coded.indices.to_numpy()]
    groups = _Groups(len(order))
    groups.join(at[: t.num_rows], at[t.num_rows :])
    nodes = coded.dictionary.take(pa.array(order))
    return e.sparkSession.createDataFrame(pa.table({"node": nodes, "root": nodes.take(pa.array(groups.up))}))


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) of each node that has an edge; root is the smallest node reachable.

    Up to ``LOCAL_EDGES`` edges go to the driver. More of them alternate two star contractions: every neighbour
    above a node is hung on the node's smallest neighbour, then every neighbour below. Each round is written to the
    shared folder; the number of rounds grows with the logarithm of the longest path.
    """
    e = written(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct(), "edges")
    if e.count() <= LOCAL_EDGES:
        return _local_components(e)
    before = None
    while True:
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        e = written(small.where("u <> v").distinct(), "stars")
        state = e.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if tuple(state) == before:
            break
        before = tuple(state)
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(
        e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )


def size_band(n: int, similarity: float) -> tuple[int, int, int]:
    """Number and largest sizes of the band of n and of the next one: similar sets lie at most one band apart."""
    j, low = 0, 1
    while (high := int(low / similarity + 1e-9)) < n:
        j, low = j + 1, high + 1
    return j, high, int((high + 1) / similarity + 1e-9)


def signatures(ids: np.ndarray, similarity: float) -> np.ndarray:
    """Hashes of which any two different sets of ``similarity`` or more have one in common.

    ``ids``: the distinct hashes of a set. Similar sets of at most ``most`` elements differ in ``apart`` elements at
    most. Elements are dealt to parts by hash, and a part signs with the hash of its elements; a part with no
    differing element is the same in both sets. A set signs for its own size band and the next, so that it
    meets its neighbours in both.

    Up to ``apart + 1 = SIGNS`` this is certain: at most ``apart`` parts differ, so the first ``apart + 1`` parts that
    are not empty, in any order common to both sets, can't all differ (large parts go first, as few other sets
    have them). A set with fewer parts than that gives its first elements besides: the pair would be lost only
    where both sets have too few, and then these meet. For larger sets the first ``SIGNS`` of ``apart + 1`` parts
    sign: each is spared by ``apart`` differences with a chance of 1/e or more, so a pair is missed with a chance
    of at most 0.632 ** 64, which is 2e-13, about that of two of a set's 64-bit hashes being equal by chance.
    """
    n = len(ids)
    if not n:
        return ids
    band, *largest = size_band(n, similarity)
    out = []
    with np.errstate(over="ignore"):
        for key, most in enumerate(largest, band):
            apart = int((1 - similarity) / (1 + similarity) * 2 * most + 1e-9)
            if not apart:  # similar sets of this size are equal
                continue
            sure = apart < SIGNS
            parts = np.uint64(-(-13 * (apart + 1) // 10) if sure else apart + 1)
            mixed = _mixed(ids, 64 + key)
            part = (mixed >> np.uint64(32)) % parts
            if not sure:  # the parts that can be among the first, and some to spare
                few = part < np.uint64(4 * SIGNS)
                mixed, part = mixed[few], part[few]
            order = np.argsort(part, kind="stable")
            first = np.flatnonzero(np.diff(part[order], prepend=parts))
            sums = _mixed(np.add.reduceat(mixed[order], first) + part[order][first], 1) if len(first) else mixed[:0]
            if not sure:
                sums = sums[:SIGNS]
            elif len(first) > apart:
                size = np.diff(first, append=n)
                sums = sums[np.lexsort((sums, -size))[: apart + 1]]
            else:
                few = n - int(np.ceil(similarity * n - 1e-9)) + 1
                out.append(_mixed(np.sort(mixed)[:few], 2))
            out.append(sums)
    return np.concatenate([ids[:0], *out])


def spanning(rows: DataFrame) -> DataFrame:
    """Edges (a, b) with the components of ``rows`` (node, b), a row for each centre b that a node meets: a node keeps
    its smallest centre, which its other centres are hung on, so that nodes of one group repeat few edges."""
    met = rows.groupBy("node").agg(F.collect_set("b").alias("centres"))
    ends = F.explode(F.array_union("centres", F.array("node")))
    return met.select(F.array_min("centres").alias("b"), ends.alias("a")).where("a <> b").select("a", "b").distinct()


def signature_edges(prints: DataFrame, group: DataFrame | None = None) -> DataFrame:
    """Edges (a, b) that join any two fingerprints, by their xxhash64, whose shingle sets share a signature.

    Rows of one signature form a star, never all pairs, and the stars that meet in a node are joined by their centres.
    With ``group`` (node, group) a fingerprint goes by its group, a signature that one group has alone gives no edge, and
    sets that share a signature meet only if their sketches leave it open that they are similar (``sketch_edges``).
    """
    w = Window.partitionBy("sign")
    flat = prints.select(F.xxhash64("fp").alias("node"), F.explode("signs").alias("sign"))
    several = flat.withColumns({"b": F.min("node").over(w), "top": F.max("node").over(w)}).where("b <> top")
    met = written(several.groupBy("sign", "node").agg(F.min("b").alias("b")), "met")  # one shuffle by signature
    return spanning(met) if group is None else sketch_edges(met.drop("b"), prints, group)


def sketch(ids: np.ndarray) -> bytes:
    """For each of at least as many bits as ``ids`` has elements, whether an odd number of these fall on it.

    An element that only one of two sets has flips one bit, so sketches differ in no more bits than sets in elements.
    A sketch is halved by the exclusive or of its halves, which makes sketches of different lengths comparable.
    """
    bits = min(SKETCH_BITS, 1 << max(6, (len(ids) - 1).bit_length()))
    with np.errstate(over="ignore"):
        at = (_mixed(ids, 33) & np.uint64(bits - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=bits) & 1).astype(np.uint8), bitorder="little").tobytes()


class Sketches:
    """Sketches by their length in words; those of twice a length also halved to it."""

    def __init__(self, sketches: list[bytes]):
        self.words = np.array([len(x) // 8 for x in sketches], np.int64)
        self.own, self.half, self.of = np.zeros(len(sketches), np.int64), np.zeros(len(sketches), np.int64), {}
        for w in np.unique(self.words).tolist():
            own, half = np.flatnonzero(self.words == w), np.flatnonzero(self.words == 2 * w)
            long = np.frombuffer(b"".join([sketches[i] for i in half.tolist()]), np.uint64).reshape(-1, 2 * w)
            self.of[w] = np.concatenate([np.frombuffer(b"".join([sketches[i] for i in own.tolist()]), np.uint64).reshape(-1, w), long[:, :w] ^ long[:, w:]])
            self.own[own], self.half[half] = np.arange(len(own)), len(own) + np.arange(len(half))

    def rows(self, x: np.ndarray, w: int) -> np.ndarray:
        return self.of[w][np.where(self.words[x] == w, self.own[x], self.half[x])]


def sketch_groups(sign: np.ndarray, group: np.ndarray, size: np.ndarray, room: np.ndarray, sketches: list[bytes], data: np.ndarray, query: np.ndarray, few: int = 32) -> np.ndarray:
    """Root row of each row, in order of ``sign``, after linking query rows to data rows of one signature whose sketches
    differ in no more bits than they have room. Rows of one group are together from the start.

    Rows of a signature that ``few`` have are compared with the next ones, all such signatures at once. Of a larger one
    the first row is compared with all, and then each row that isn't in the largest group by then.
    """
    groups, bags = _Groups(len(sign)), Sketches(sketches)
    _, first, at = np.unique(group, return_index=True, return_inverse=True)
    groups.join(np.arange(len(sign)), first[at.ravel()])
    room = room + 5e-10
    start = np.flatnonzero(np.diff(sign, prepend=sign[:1] - 1)) if len(sign) else np.zeros(0, np.int64)
    count = np.diff(start, append=len(sign))
    left = np.repeat(np.where(count <= few, start + count, 0), count) - np.arange(len(sign))  # rows of the signature from here on

    def near(a: np.ndarray, b: np.ndarray) -> None:
        open_ = (groups.up[a] != groups.up[b]) & (np.abs(size[a] - size[b]) <= room[a] + room[b])
        a, b = a[open_], b[open_]
        low = np.minimum(bags.words[a], bags.words[b])
        fits = np.maximum(bags.words[a], bags.words[b]) <= 2 * low
        for w in np.unique(low).tolist():
            some, step = np.flatnonzero(fits & (low == w)), max(1, (1 << 20) // w)
            for s in range(0, len(some), step):
                x, y = a[some[s : s + step]], b[some[s : s + step]]
                ok = distance(bags.rows(x, w), bags.rows(y, w)) <= room[x] + room[y]
                groups.join(x[ok], y[ok])

    for k in range(1, few):
        a = np.flatnonzero(left > k)
        if not len(a):
            break
        near(a, a + k)
    for a, n in zip(start[count > few].tolist(), count[count > few].tolist(), strict=True):
        rows = np.arange(a, a + n)
        near(np.full(n - 1, a), rows[1:])
        roots, size_of = np.unique(groups.up[rows], return_counts=True)
        rest = rows[groups.up[rows] != roots[size_of.argmax()]]
        both = [(rest[query[rest]], rows[data[rows]])]
        if not (data[rows] & query[rows]).all():
            both.append((rest[data[rest]], rows[query[rows]]))
        for these, those in both:
            for v in np.unique(bags.words[these]).tolist():
                for w in np.unique(bags.words[those]).tolist():
                    if max(v, w) > 2 * min(v, w):
                        continue
                    x, y = these[bags.words[these] == v], those[bags.words[those] == w]
                    step, other = max(1, (1 << 20) // len(y)), bags.rows(y, min(v, w))
                    for s in range(0, len(x), step):
                        some = x[s : s + step]
                        mine, apart = bags.rows(some, min(v, w)), np.zeros((len(some), len(y)), np.uint16)
                        for i in range(min(v, w)):
                            apart += np.bitwise_count(mine[:, i][:, None] ^ other[:, i][None, :])
                        i, j = np.nonzero(apart <= room[some][:, None] + room[y][None, :])
                        fit = np.abs(size[some[i]] - size[y[j]]) <= room[some[i]] + room[y[j]]
                        groups.join(some[i[fit]], y[j[fit]])
    return groups.up


def sketch_edges(met: DataFrame, prints: DataFrame, group: DataFrame) -> DataFrame:
    """Edges (a, b) that join any two groups of which two rows in ``met`` (sign, node) share a signature and have sketches
    that leave it open whether their sets are similar.

    A signature alone joins texts by a single common shingle, which in a large corpus makes one group of candidates of
    most texts. A sketch has a bit or two an element, not 64, and passes hardly any pair that isn't similar. A
    signature of more than ``SIGN_CHUNK`` rows is compared in a grid of cells.
    """
    w = Window.partitionBy("sign")
    rows = met.join(checked(group, 24), "node", "left").withColumn("group", F.coalesce("group", "node"))
    rows = written(rows.withColumns({"x": F.min("group").over(w), "y": F.max("group").over(w)}).where("x <> y").select("sign", "node", "group"), "signs")
    some = rows.select("node").distinct()
    known = prints.select(F.xxhash64("fp").alias("node"), "n_shingles", "room", "sketch").join(checked(some, 8), "node", "left_semi").dropDuplicates(["node"])
    rows = written(rows.join(known, "node"), "sketched")
    load = F.sum(F.octet_length("sketch") + 48) / SIGN_BYTES
    sizes = rows.groupBy("sign").agg(F.ceil(F.greatest(F.count("*") / SIGN_CHUNK, load)).cast("int").alias("chunks")).where("chunks > 1")  # few: each stands for a chunk or more
    shards = max(1, int(rows.agg(F.coalesce(load, F.lit(0.0))).first()[0]))
    dealt = rows.join(checked(sizes, 12), "sign", "left").withColumn("chunks", F.coalesce("chunks", F.lit(1))).withColumn("home", F.lit(True)).withColumnRenamed("node", "fp")
    dealt = dealt.withColumn("shard", F.when(F.col("chunks") > 1, F.xxhash64("sign")).otherwise(F.pmod(F.xxhash64("sign"), F.lit(shards))))

    def search(t: pa.Table) -> pa.Table:
        t = t.combine_chunks().sort_by([("sign", "ascending"), ("fp", "ascending")])
        sign, own, size, room, data, query = (t.column(c).to_numpy() for c in ("sign", "group", "n_shingles", "room", "data", "query"))
        root = own[sketch_groups(sign, own, size, room, t.column("sketch").to_pylist(), data, query)]
        at = np.flatnonzero(root != own)
        a, b = np.unique(np.stack([own[at], root[at]]), axis=1) if len(at) else (own[at], root[at])
        return pa.table({"a": a, "b": b})

    upper = F.floor(F.col("cell") / F.col("chunks")) <= F.col("cell") % F.col("chunks")
    return _grid(dealt, "sign", "group", "n_shingles", "room", "sketch", where=upper).groupBy("shard", "cell").applyInArrow(search, "a long, b long").distinct()


class Sets:
    """Sets of hashes as dense numbers, to compare one with many at once."""

    def __init__(self, sets: list[np.ndarray]):
        self.size = np.array([len(x) for x in sets], np.int64)
        self.first = np.cumsum(self.size) - self.size
        every, self.ids = np.unique(np.concatenate([*sets, np.zeros(0, np.uint64)]), return_inverse=True)
        self.mark = np.zeros(len(every), np.int64)

    def jaccard(self, i: int, others: np.ndarray) -> np.ndarray:
        """Exact similarity of set i with each of the others."""
        own = self.ids[self.first[i] : self.first[i] + self.size[i]]
        size = self.size[others]
        ends = np.cumsum(size)
        at = np.repeat(self.first[others] - (ends - size), size) + np.arange(ends[-1])
        self.mark[own] = 1
        hits = np.concatenate([[0], np.cumsum(self.mark[self.ids[at]])])
        self.mark[own] = 0
        both = hits[ends] - hits[ends - size]
        return both / np.maximum(1, size + len(own) - both)


def linked_sets(fp: np.ndarray, sets: list[np.ndarray], data: np.ndarray, query: np.ndarray, radius: int, similarity: float, same: np.ndarray | None = None) -> np.ndarray:
    """Root row after linking rows whose sets are similar; rows equal in ``same`` are known to be together. Near fingerprints go first, ring by ring up to
    ``radius`` and then all others, and pairs that are already together are passed over, so a large group
    of copies costs few comparisons a member."""
    groups, bags = _Groups(len(fp)), Sets(sets)
    if same is not None and len(same):
        _, first, at = np.unique(same, return_index=True, return_inverse=True)
        groups.join(np.arange(len(fp)), first[at])
    step = max(1, (1 << 20) // max(1, len(data)))
    is_data, is_query = np.zeros(len(fp), bool), np.zeros(len(fp), bool)
    is_data[data], is_query[query] = True, True
    far = [-1, *(radius * i // 8 for i in range(4, 9)), 64 * fp.shape[1]]
    least = similarity * bags.size - 1e-9
    for low, high in zip(far, far[1:], strict=False):
        for s in range(0, len(query), step):
            rows = query[s : s + step]
            apart = np.zeros((len(rows), len(data)), np.uint16)
            for w in range(fp.shape[1]):
                apart += np.bitwise_count(fp[rows, w][:, None] ^ fp[data, w][None, :])
            open_ = (apart <= high) & (apart > low) if low >= 0 else apart <= high
            open_ &= groups.up[rows][:, None] != groups.up[data][None, :]
            open_ &= (bags.size[rows][:, None] >= least[data][None, :]) & (bags.size[data][None, :] >= least[rows][:, None])
            open_ &= (data[None, :] > rows[:, None]) | ~is_data[rows][:, None] | ~is_query[data][None, :]  # each pair once
            for r in np.flatnonzero(open_.any(1)).tolist():
                i, near = int(rows[r]), data[open_[r]]
                near = near[groups.up[near] != groups.up[i]]
                if len(near):  # in slices of about so many elements
                    for some in np.split(near, np.flatnonzero(np.diff(np.cumsum(bags.size[near]) >> 19)) + 1):
                        linked = some[bags.jaccard(i, some) >= similarity]
                        groups.join(np.full(len(linked), i), linked)
    return groups.up


def member_sets(docs: DataFrame, m: DataFrame, k: int, bits: int) -> DataFrame:
    """``m`` (doc_id, row_key, fp and more) with ``sets``, the shingle hashes of each fingerprint, instead of the row's name."""
    keep = [f for f in m.schema if f.name not in ("doc_id", "row_key")]
    some, names = _texts(docs), [f.name for f in keep]
    rows = some.join(checked(m, 160), same_row(some, m)).select(*names, "text")

    def run(batches):
        seen = set()  # rows that repeat both id and text come once a task
        for b in batches:
            sets, at = [], []
            for i, (want, text) in enumerate(zip(b.column("fp").to_pylist(), b.column("text"), strict=True)):
                if want in seen:
                    continue
                one = _set_of(text.as_py(), k)
                if vote([one], len(one), bits) == want:  # else another text of the same hash
                    seen.add(want)
                    sets.append(one.tobytes())
                    at.append(i)
            at = pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(c).take(at) for c in names), pa.array(sets, pa.binary())], [*names, "sets"])

    return arrow_map(rows, run, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in keep) + ", sets binary")


def star_links(stars: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """(a, b) binary fingerprints and (u, v) their nodes, of the edges (node, centre) in ``stars`` whose sets are similar.

    A centre's set goes to its leaves, in slices of about ``STAR`` of them, and is compared as they stream by.
    """
    slices = stars.groupBy("centre").agg(F.ceil(F.count("*") / STAR).cast("int").alias("slices"))
    leaves = stars.join(slices, "centre").join(sets, "node").select("centre", F.pmod(F.xxhash64("node"), F.col("slices")).cast("int").alias("slice"), F.lit(True).alias("leaf"), "node", "fp", "sets")
    heads = slices.join(sets.withColumnRenamed("node", "centre"), "centre").withColumn("slice", F.explode(F.sequence(F.lit(0), F.col("slices") - 1)))
    heads = heads.select("centre", "slice", F.lit(False).alias("leaf"), F.col("centre").alias("node"), "fp", "sets")

    def run(batches):
        at, heads = None, []  # of the star that streams by; more than one head only if two fingerprints share a node
        for b in batches:
            out = []
            for centre, leaf, node, fp, one in zip(*(b.column(c).to_pylist() for c in ("centre", "leaf", "node", "fp", "sets")), strict=True):
                if centre != at:
                    at, heads = centre, []
                one = np.frombuffer(one, np.uint64)
                if not leaf:
                    heads.append((fp, one))
                    continue
                for head, other in heads:
                    if min(len(one), len(other)) >= similarity * max(len(one), len(other)) - 1e-9:
                        both = len(np.intersect1d(one, other, assume_unique=True))
                        if both / max(1, len(one) + len(other) - both) >= similarity:
                            out.append((fp, head, node, centre))
            cols = list(zip(*out, strict=True)) or [(), (), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.binary(), pa.binary(), pa.int64(), pa.int64()), strict=True)], ["a", "b", "u", "v"])

    dealt = leaves.unionByName(heads).repartition("centre", "slice").sortWithinPartitions("centre", "slice", "leaf")
    return arrow_map(dealt, run, "a binary, b binary, u long, v long")


def tree_links(docs: DataFrame, distinct: DataFrame, k: int, bits: int, similarity: float, leaf: int) -> DataFrame:
    """Links (a, b) of similar sets, and (u, v) their nodes, that vantage-point trees find among the fingerprints.

    The first word of a wide fingerprint is a fingerprint of 64 bits. Trees over its two blocks find all words within
    ``WORD_RADIUS`` bits; each group of them is a star around its smallest node, and the shingle sets decide. Similar
    sets that lie farther apart, or are similar to others of their group than its centre, are left to the signatures.
    """
    named = distinct.select(F.xxhash64("fp").alias("node"), "fp", F.substring("fp", 1, 8).alias("word"), F.col("n_shingles").alias("n"), "rep.doc_id", "rep.row_key")
    words = written(named.select(F.col("word").alias("fp")).distinct(), "words")
    near = components(fingerprint_edges(words, 64, WORD_RADIUS, 2, leaf)).select(F.col("node").alias("word"), "root")
    named = named.join(checked(near, 48), "word", "left").withColumn("root", F.coalesce("root", "word")).drop("word")
    heads = named.groupBy("root").agg(F.min(F.struct("node", "n")).alias("c"), F.count("*").alias("size")).where("size > 1").select("root", "c")
    met = written(named.join(heads, "root").where(F.least("n", "c.n") >= similarity * F.greatest("n", "c.n") - 1e-9), "met")
    sets = written(member_sets(docs, met.select("doc_id", "row_key", "fp", "node"), k, bits), "sets")
    return written(star_links(met.select("node", F.col("c.node").alias("centre")).where("node <> centre"), sets, similarity), "links")


def peeled(docs: DataFrame, prints: DataFrame, large: DataFrame, links: DataFrame, k: int, bits: int, similarity: float) -> tuple[DataFrame, DataFrame]:
    """``links`` with those found among the ``large`` groups of candidates, and what is left of these: (node, root).

    All rows of a group of candidates are compared with its smallest first, so that near copies travel once for it and not for each signature.
    Then all rows of a signature are compared with the smallest of them, which then leaves the signature.
    A signature whose rows are linked by then has nothing more to tell. What is left falls into groups of its own, far smaller as a rule:
    chains of signatures that only few rows share, which make a group large, end after a round or two.
    """
    named = large.select(F.xxhash64("fp").alias("node"), "fp", "group", "root", F.col("rep.doc_id").alias("doc_id"), F.col("rep.row_key").alias("row_key"))
    sets = written(member_sets(docs, named.drop("group", "root"), k, bits), "sets")
    stars = named.join(named.groupBy("root").agg(F.min("node").alias("centre")), "root").where("node <> centre").select("node", "centre")
    links = links.unionByName(written(star_links(stars, sets, similarity), "links"))
    group = components(links.select("u", "v"), "u", "v").select("node", F.col("root").alias("group"))
    named = named.drop("group", "root").join(checked(group, 24), "node", "left").withColumn("group", F.coalesce("group", "node"))
    size = sets.select("node", (F.octet_length("sets") / 8).alias("n"))
    flat = prints.join(checked(named.select("fp", "group"), 88), "fp").select(F.xxhash64("fp").alias("node"), "group", F.explode("signs").alias("sign")).distinct()
    several = flat.groupBy("sign").agg(F.min("group").alias("x"), F.max("group").alias("y")).where("x <> y").select("sign")
    flat = written(flat.join(several, "sign").join(size, "node").select("sign", "node", "n", "group"), "signs")
    for _ in range(PEELS):
        first = flat.groupBy("sign").agg(F.min(F.struct("node", "n", "group")).alias("c"))
        both = written(flat.join(first, "sign").where("node <> c.node"), "starred")
        fit = (F.least("n", "c.n") >= similarity * F.greatest("n", "c.n") - 1e-9) & (F.col("group") != F.col("c.group"))
        got = written(star_links(both.where(fit).select("node", F.col("c.node").alias("centre")).distinct(), sets, similarity), "links")
        links = links.unionByName(got)
        group = components(links.select("u", "v"), "u", "v").select("node", F.col("root").alias("group"))
        rest = both.select("sign", "node", "n").join(group, "node", "left").withColumn("group", F.coalesce("group", "node"))
        open_ = rest.groupBy("sign").agg(F.min("group").alias("x"), F.max("group").alias("y")).where("x <> y").select("sign")
        flat = written(rest.join(open_, "sign"), "signs")
        first = flat.groupBy("sign").agg(F.min("node").alias("b"))
        loose = written(components(spanning(flat.join(first, "sign").select("node", "b"))), "loose")
        most = loose.join(size, "node").groupBy("root").agg(F.greatest(F.count("*") / SET_CHUNK, F.sum(8 * F.col("n")) / SET_BYTES).alias("load"))
        if most.where("load > 1").isEmpty():
            break
    return links, loose


def verified_edges(docs: DataFrame, prints: DataFrame, distinct: DataFrame, links: DataFrame, k: int, bits: int, radius: int, similarity: float) -> DataFrame:
    """Edges (a, b) that join any two fingerprints whose shingle sets are similar: ``links``, those that the trees have
    found, and an exact way for the rest, between fingerprints of one loose component of signatures.

    Only members of a component with company are read again. Small components share a shard; one of more than
    ``SET_CHUNK`` members or ``SET_BYTES`` becomes a grid of cells, as large shards do. One of more than ``PEEL_FROM``
    times as many is peeled first (``peeled``), and the grid has what is left of it.
    """
    group = components(links, "u", "v").select("node", F.col("root").alias("group"))
    loose = components(signature_edges(prints, group)).withColumnRenamed("node", "group")
    named = distinct.withColumn("node", F.xxhash64("fp")).join(checked(group, 24), "node", "left").withColumn("group", F.coalesce("group", "node"))
    members = written(named.join(loose, "group").select("fp", "rep", "n_shingles", "group", "root"), "members")
    load = F.greatest(F.count("*") / SET_CHUNK, F.sum(8 * F.col("n_shingles")) / SET_BYTES)
    sizes = members.groupBy("root").agg(F.ceil(load).cast("int").alias("chunks")).where("chunks > 1")  # few: each stands for a chunk or more
    huge = sizes.where(F.col("chunks") > PEEL_FROM)
    if not huge.isEmpty():
        roots = checked(huge.select("root"), 96)
        large = written(members.join(roots, "root", "left_semi"), "large")
        links, left = peeled(docs, prints, large, links, k, bits, similarity)
        rest = large.drop("root").join(left, F.xxhash64("fp") == F.col("node")).select("fp", "rep", "n_shingles", "group", "root")
        members = written(members.join(roots, "root", "left_anti").unionByName(rest), "members")
        sizes = members.groupBy("root").agg(F.ceil(load).cast("int").alias("chunks")).where("chunks > 1")
    shards = max(1, int(members.agg(F.coalesce(load, F.lit(0.0))).first()[0]))
    m = members.join(checked(sizes, 96), "root", "left").withColumn("chunks", F.coalesce("chunks", F.lit(1)))
    m = m.withColumn("shard", F.when(F.col("chunks") > 1, F.xxhash64("root")).otherwise(F.pmod(F.xxhash64("root"), F.lit(shards))))
    m = m.select(F.col("rep.doc_id").alias("doc_id"), F.col("rep.row_key").alias("row_key"), "fp", "group", "root", "shard", "chunks")
    sets = member_sets(docs, m, k, bits).withColumn("home", F.lit(True))

    def search(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        t = t.combine_chunks().sort_by([("root", "ascending"), ("fp", "ascending")])
        fp, bags = _matrix(t.column("fp"), bits), [np.frombuffer(x, np.uint64) for x in t.column("sets").to_pylist()]
        data, query = (t.column(c).to_numpy(zero_copy_only=False) for c in ("data", "query"))
        same, (_, first) = t.column("group").to_numpy(), np.unique(t.column("root").to_numpy(), return_index=True)
        root = np.arange(len(fp))
        for a, b in zip(first, [*first[1:], len(fp)], strict=True):
            got = linked_sets(fp[a:b], bags[a:b], np.flatnonzero(data[a:b]), np.flatnonzero(query[a:b]), radius, similarity, same[a:b])
            root[a:b] = a + got
        at = np.flatnonzero(root != np.arange(len(fp)))
        return pa.table({"a": t.column("fp").take(pa.array(at)), "b": t.column("fp").take(pa.array(root[at]))})

    upper = F.floor(F.col("cell") / F.col("chunks")) <= F.col("cell") % F.col("chunks")  # all rows are data: half the grid has every pair
    out = _grid(sets, "group", "root", "sets", where=upper).groupBy("shard", "cell").applyInArrow(search, "a binary, b binary")
    return out.where(F.col("a") != F.col("b")).unionByName(links.select("a", "b")).distinct()


def _groups(docs: DataFrame, k: int, bits: int, radius: int, blocks: int, ratio: float | None, leaf: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, row_key, fp) of each row, and (fp, component_id, leader) of the fingerprints whose
    group has more than one row; the leader is the (doc_id, row_key) that stands for the group."""
    prints = written(fingerprints(docs, k, bits, ratio), "fingerprints")
    rep = F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "row_key")
    distinct = written(prints.groupBy("fp").agg(F.min(rep).alias("rep"), F.min("n_shingles").alias("n_shingles"), F.count("*").alias("n_rows")), "distinct")
    if ratio is not None:
        linked = components(verified_edges(docs, prints, distinct, tree_links(docs, distinct, k, bits, ratio, leaf), k, bits, radius, ratio))
    else:
        linked = components(fingerprint_edges(distinct, bits, radius, blocks, leaf))
    own = distinct.join(linked, distinct.fp == linked.node, "left").where(F.col("root").isNotNull() | (F.col("n_rows") > 1))
    own = own.select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    best = own.groupBy("root").agg(F.min("rep").alias("leader"))
    named = own.join(best, "root").select("fp", F.col("leader.doc_id").alias("component_id"), F.struct("leader.doc_id", "leader.row_key").alias("leader"))
    return prints.select("doc_id", "row_key", "fp"), written(named, "named")


def near_duplicates(docs: DataFrame, k: int = 3, bits: int = 64, radius: int = 3, blocks: int = 2, ratio: float | None = None, leaf: int = 512) -> DataFrame:
    """(doc_id, row_key, fp, component_id) for each row; component_id is the smallest doc_id reachable.

    ``ratio``: links are pairs of a Jaccard similarity of ``ratio`` or more over distinct
    shingles. Vantage-point trees find the near ones (``tree_links``). Candidates for the rest share a signature
    (see ``signatures``); ``radius`` only sets which of them are compared first. Shingle sets decide in either case.
    """
    prints, named = _groups(docs, k, bits, radius, blocks, ratio, leaf)
    j = prints.join(checked(named.select("fp", "component_id", F.lit(True).alias("grouped")), 32 + bits // 8), "fp", "left")
    return j.select("doc_id", "row_key", "fp", F.when(F.col("grouped"), F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def survivors(docs: DataFrame, k: int, bits: int, radius: int, ratio: float, leaf: int = 512) -> DataFrame:
    """``docs`` with one row of each group of near duplicates; all columns stay."""
    prints, named = _groups(docs, k, bits, radius, 1, ratio, leaf)
    leads = F.col("doc_id").eqNullSafe(F.col("leader.doc_id")) & (F.col("row_key") == F.col("leader.row_key"))
    gone = prints.join(checked(named.select("fp", "leader"), 48 + bits // 8), "fp").where(~leads).select("doc_id", "row_key")
    gone = written(gone.distinct(), "copies")
    rows = docs.select(*apart(docs))
    kept = rows.join(checked(gone, 24), same_row(rows, gone), "left_anti")
    twice = written(prints.groupBy("doc_id", "row_key").count().where("count > 1").select("doc_id", "row_key"), "twice")
    if twice.isEmpty():
        return kept.select(*whole(docs))
    twice = checked(twice, 24)
    many = kept.join(twice, same_row(kept, twice), "left_semi").groupBy("doc_id", "row_key").agg(F.first(F.struct("row", "text")).alias("x")).select("x.row", "x.text")
    return kept.join(twice, same_row(kept, twice), "left_anti").select("row", "text").unionByName(many).select(*whole(docs))


def op8_result(docs: DataFrame) -> DataFrame:
    got = near_duplicates(docs, 3, 64, 3, 2)
    return got.select("doc_id", F.lower(F.hex("fp")).alias("fingerprint"), "component_id")

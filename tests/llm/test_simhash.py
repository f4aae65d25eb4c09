import random

import corpus_pipeline as C
import numpy as np
import pytest
from pyspark.sql import functions as F
import xxhash

from navspark.llm import simhash_vp as S

SCHEMA = "doc_id long, text string, fp string"


def brute(rows, k=3, radius=3):
    def fp(t):
        w = (t or "").encode().lower().split()
        if not w:
            return 0
        hs = [xxhash.xxh64_intdigest(b" ".join(w[i : i + k]), 42) for i in range(max(1, len(w) - k + 1))]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in hs) > len(hs))

    fps = [fp(t) for _, t in rows]
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= radius:
                up[find(i)] = find(j)
    best = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            best[find(i)] = min(best.get(find(i), d), d)
    return sorted((d, format(f, "016x"), best.get(find(i))) for i, ((d, _), f) in enumerate(zip(rows, fps, strict=True)))


def test_components_equal_brute_force(spark):
    rnd = random.Random(5)
    vocab = [f"w{i}" for i in range(60)]
    rows = []
    for i in range(160):
        base = [rnd.choice(vocab) for _ in range(rnd.choice([0, 1, 2, 3, 40, 300]))]
        rows.append((i, " ".join(base)))
        if i % 3 == 0 and len(base) > 30:
            base[rnd.randrange(len(base))] = "X"
            rows.append((1000 + i, "\t".join(base).upper()))
    rows += [(2000, None), (2001, ""), (7, "same text here again"), (7, "same text here again"), (2002, "word " * 50_000)]
    df = spark.createDataFrame([(d, t, "clash") for d, t in rows], SCHEMA).repartition(5)
    got = sorted((r.doc_id, r.fingerprint, r.component_id) for r in S.op8_result(df).collect())
    assert got == brute(rows)


def test_empty(spark):
    assert S.op8_result(spark.createDataFrame([], SCHEMA)).count() == 0


@pytest.mark.parametrize("blocks", [1, 2])
def test_tree_search_loses_no_link(blocks):
    rng = np.random.default_rng(3)
    fp = rng.integers(0, 1 << 63, (3000, 1), dtype=np.uint64)
    for i in range(1500):
        fp[i + 1500] = fp[i] ^ np.uint64(sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 6), replace=False)))
    d = np.bitwise_count(fp[:, None, 0] ^ fp[None, :, 0])
    want = S._Groups(len(fp))
    want.join(*np.nonzero(d <= 3))
    got = S._Groups(len(fp))
    every = np.arange(len(fp))
    for j in range(blocks):
        root = S.linked_groups(fp, every, every, j, blocks, 3, leaf=32)
        got.join(every, root)
    assert (got.up == want.up).all()


def test_long_text_in_slices(monkeypatch):
    text = " ".join(f"a{i % 97}" for i in range(5000))
    whole = S.fingerprint(text)
    monkeypatch.setattr(S, "SLICE", 100)
    assert S.fingerprint(text) == whole


def test_grid_of_chunks_keeps_links(spark, monkeypatch):
    rnd = random.Random(9)
    rows = [(i, " ".join(rnd.choice("abcdefgh") for _ in range(3))) for i in range(120)]
    monkeypatch.setattr(S, "CHUNK", 10)
    got = sorted((r.doc_id, r.fingerprint, r.component_id) for r in S.op8_result(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == brute(rows)


def test_verified_links_are_the_similar_pairs(spark, monkeypatch):
    rnd = random.Random(12)
    texts = []
    for _ in range(12):
        base = [f"v{rnd.randrange(400)}" for _ in range(rnd.choice([30, 120, 250]))]
        texts.append(base)
        for n in (1, 2, 3, 4, 8, 16):
            copy = list(base)
            for _ in range(n):
                copy[rnd.randrange(len(copy))] = f"x{rnd.randrange(10**6)}"
            texts += [copy, list(copy)] if n == 2 else [copy]
    rows = [(i, " ".join(t)) for i, t in enumerate(texts)] + [(900, ""), (901, None), (902, "one two")]
    sets = [{tuple(t.split()[i : i + 5]) for i in range(max(1, len(t.split()) - 4))} if t else set() for _, t in rows]
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if (not sets[i] and not sets[j]) or (sets[i] | sets[j] and len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8):
                a, b = find(i), find(j)
                up[max(a, b)] = min(a, b)
    want = [(r[0], rows[find(i)][0]) for i, r in enumerate(rows)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for chunk in (2000, 7):
        monkeypatch.setattr(S, "SET_CHUNK", chunk)
        got = sorted((r.doc_id, r.component_id) for r in S.near_duplicates(df, 5, 512, 110, 1, 0.8, leaf=64).collect())
        assert got == want


def _short_pairs():
    rnd, rows = random.Random(4), []
    for i in range(400):
        base = [f"t{i}v{j}" for j in range(rnd.randrange(6, 31) if i % 4 else 9)]
        cut = rnd.choice([1, 1, 2, 3, 5])
        rows += [" ".join(base), " ".join(base[: -cut if i % 4 else 8])] if i % 2 or not i % 4 else [" ".join(base), " ".join(base[cut:] + ["x"] * (i % 3))]
    return list(enumerate(rows))


def test_short_texts_at_the_pipelines_radius_equal_brute_force(spark):
    rows = _short_pairs()
    sets = [set(np.concatenate([np.zeros(0, np.uint64), *S.shingle_hashes(t, C.SHINGLE)]).tolist()) for _, t in rows]
    want = {d: d for d, _ in rows}
    for i in range(0, len(rows), 2):  # words are unique to a pair
        if len(sets[i] & sets[i + 1]) >= C.SIMILARITY * len(sets[i] | sets[i + 1]) - 1e-9:
            want[i + 1] = i
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = S.near_duplicates(df, C.SHINGLE, C.BITS, C.RADIUS, 1, C.SIMILARITY)
    assert {r.doc_id: r.component_id for r in got.collect()} == want


@pytest.mark.parametrize("largest", [400, 3000])
def test_similar_sets_share_a_signature(largest):
    rng = np.random.default_rng(8)
    for _ in range(3000):
        n = int(rng.integers(1, largest))
        ids = rng.integers(0, 1 << 63, n + n // 4, dtype=np.uint64)
        size = n + int(rng.integers(0, n // 4 + 1))
        drop = int(rng.integers(0, n // 9 + 1))
        a, b = np.sort(ids[:n]), np.sort(ids[drop:size])
        both = n - drop
        if both >= 0.8 * (len(a) + len(b) - both) and drop + size - n:
            assert np.intersect1d(S.signatures(a, 0.8), S.signatures(b, 0.8)).size


def test_a_long_chain_of_candidates_is_peeled_apart(spark, monkeypatch):
    """Texts that only share signatures with their neighbours are one group of candidates; none of them may travel to a grid of cells."""
    words = [f"w{i}" for i in range(700)]
    rows = [(i, " ".join(words[5 * i : 5 * i + 60])) for i in range(60)]  # neighbours: 51 of 61 shingles
    most, grid = [], S._grid
    monkeypatch.setattr(S, "SET_CHUNK", 10)
    monkeypatch.setattr(S, "_grid", lambda r, *a, **b: most.append(r.agg(F.max("chunks")).first()[0]) or grid(r, *a, **b))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {r.component_id for r in S.near_duplicates(df, 5, 512, 104, 1, 0.8).collect()} == {0}
    assert (most[0] or 1) == 1


def test_signatures_of_a_large_group_give_few_edges(spark):
    """Near copies share dozens of signatures; each of these may not cost an edge a row, nor a group of few chunks its peeling."""
    rnd = random.Random(2)
    base = [f"w{i}" for i in range(150)]
    rows = []
    for i in range(300):
        text = list(base)
        for _ in range(rnd.randrange(1, 8)):
            text[rnd.randrange(len(text))] = f"x{rnd.randrange(10**6)}"
        rows.append((i, " ".join(text)))
    prints = S.fingerprints(spark.createDataFrame(rows, "doc_id long, text string"), 5, 512, 0.8).cache()
    edges = S.signature_edges(prints)
    assert edges.count() < 6 * len(rows)
    signs, up = {}, S._Groups(len(rows))
    for i, r in enumerate(prints.orderBy("doc_id").collect()):
        for x in r.signs:
            up.join(np.array([signs.setdefault(x, i)]), np.array([i]))
    assert S.components(edges).groupBy("root").count().count() == sum(n > 1 for n in np.bincount(up.up))


def test_components_on_the_driver_equal_those_of_rounds(spark, monkeypatch):
    rnd = random.Random(6)
    for ends in ("a long, b long", "a binary, b binary"):
        name = (lambda x: x - 100) if "long" in ends else (lambda x: bytes([x, 255 - x]))
        edges = spark.createDataFrame([(name(rnd.randrange(200)), name(rnd.randrange(200))) for _ in range(150)], ends)
        got = []
        for most in (S.LOCAL_EDGES, -1):
            monkeypatch.setattr(S, "LOCAL_EDGES", most)
            got.append(sorted(map(tuple, S.components(edges).collect())))
            assert S.components(edges.limit(0)).count() == 0
        assert got[0] == got[1]
        monkeypatch.undo()


def test_trees_find_near_copies_of_the_pipelines_stage(spark, monkeypatch):
    """Copies of long texts are linked by the trees alone, and only what they leave open meets by signatures."""
    rnd = random.Random(8)
    rows = []
    for i in range(40):
        text = [f"t{i}w{rnd.randrange(10**6)}" for _ in range(600)]
        rows += [(3 * i, " ".join(text)), (3 * i + 1, " ".join([*text[:-1], "x"])), (3 * i + 2, " ".join([*text[:500], *(f"y{i}{j}" for j in range(60)), *text[560:]]))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    left, found, edges = [], [], S.signature_edges
    monkeypatch.setattr(S, "signature_edges", lambda p, g=None: left.append(g.count()) or edges(p, g))
    links = S.tree_links
    monkeypatch.setattr(S, "tree_links", lambda *a: found.append(got := links(*a)) or got)
    got = S.near_duplicates(df, 5, 512, 104, 1, 0.8)
    assert {r.doc_id: r.component_id for r in got.collect()} == {d: d - d % 3 for d, _ in rows}
    nodes = {r.fp: r.doc_id for r in got.select("fp", "doc_id").collect()}
    near = {tuple(sorted((nodes[r.a], nodes[r.b]))) for r in found[0].collect()}
    assert sum((3 * i, 3 * i + 1) in near for i in range(40)) >= 36 and all(a // 3 == b // 3 for a, b in near)
    assert left[0] >= 72


def test_sketches_differ_in_no_more_bits_than_sets_in_elements():
    rng = np.random.default_rng(3)
    for _ in range(400):
        n = int(rng.integers(1, 900))
        ids = rng.integers(0, 1 << 63, n + n // 3 + 1, dtype=np.uint64)
        a, b = np.unique(ids[:n]), np.unique(ids[int(rng.integers(0, n)) :])
        bags = S.Sketches([S.sketch(a), S.sketch(b)])
        w, one, two = int(bags.words.min()), np.array([0]), np.array([1])
        if bags.words.max() <= 2 * w:
            assert S.distance(bags.rows(one, w), bags.rows(two, w))[0] <= len(np.setxor1d(a, b))


def test_texts_that_share_a_passage_are_no_candidates(spark, monkeypatch):
    """A common passage gives texts a signature in common; those that can't be similar may not meet, and all that are must."""
    rnd, rows = random.Random(5), []
    passage = " ".join(f"p{i}" for i in range(60))
    for i in range(90):
        rows.append((2 * i, passage + " " + " ".join(f"t{i}w{j}" for j in range(90))))
    prints = S.fingerprints(spark.createDataFrame(rows, "doc_id long, text string"), 5, 512, 0.8).cache()
    assert S.components(S.signature_edges(prints)).groupBy("root").count().agg(F.max("count")).first()[0] >= 60
    none = spark.createDataFrame([], "node long, group long")
    assert S.signature_edges(prints, none).count() == 0
    for i in range(0, 90, 3):  # copies on either side of the limit
        words = rows[i][1].split()
        for j in rnd.sample(range(len(words)), rnd.randrange(1, 6)):
            words[j] = f"x{rnd.randrange(10**6)}"
        rows.append((2 * i + 1, " ".join(words)))
    sets = {d: set(np.concatenate(list(S.shingle_hashes(t, 5))).tolist()) for d, t in rows}
    want = {d: d for d, _ in rows}
    for d in want:
        if d % 2 and len(sets[d] & sets[d - 1]) >= 0.8 * len(sets[d] | sets[d - 1]) - 1e-9:
            want[d] = d - 1
    assert 5 < sum(d != r for d, r in want.items()) < 30
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for chunk in (20_000, 40):
        monkeypatch.setattr(S, "SIGN_CHUNK", chunk)
        assert {r.doc_id: r.component_id for r in S.near_duplicates(df, 5, 512, 104, 1, 0.8).collect()} == want

import re
import zlib

import corpus_pipeline as C
import numpy as np
from helpers import DOC_DDL
from pyspark.sql import functions as F

from navspark.llm import common, decontam, quality_mil, simhash_vp
from navspark.llm.common import table, written
from navspark.llm.tokens import Vocabulary, _exact

SF = "/root/testdata/sf0.001"


def test_stages_chain(spark):
    docs = table(spark, SF, "documents")
    cols, before = docs.columns, docs.count()
    for name, stage in C.STAGES[:-1]:
        docs = written(stage(spark, docs, SF), name)
        assert docs.columns == cols
        now = docs.count()
        assert 0 < now <= before
        if name == "lines":
            assert now == before and docs.where(F.char_length("text") != F.col("n_chars")).count() == 0
            lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("l")).where(F.char_length(F.trim("l")) >= 12)
            assert lines.groupBy(F.trim("l")).agg(F.count_distinct("doc_id").alias("n")).where("n > 1").count() <= 1
        if name == "near_duplicates":
            g = simhash_vp.near_duplicates(docs, C.SHINGLE, C.BITS, C.RADIUS, 1, C.SIMILARITY)
            assert g.where("doc_id <> component_id").count() == 0
        if name == "leaks":
            assert decontam.op10_result(docs, table(spark, SF, "benchmark")).where("contaminated").count() == 0
        before = now
    pieces = C.STAGES[-1][1](spark, docs, SF)
    assert pieces.select("doc_id").distinct().count() == before
    assert pieces.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 2048").count() == 0


def test_odd_rows_pass_every_stage(spark):
    clean = "A clean sentence of plain words stands here. " * 12
    rows = [(1, clean, "en", "s", 1), (1, clean, "en", "s", 1), (2, clean + "One more word.", "en", "s", 1), (None, None, None, None, None), (3, "", "en", None, 0), (4, None, "en", "s", None), (5, "word " * 200_000, "en", "s", 1)]
    docs = spark.createDataFrame(rows, DOC_DDL)
    for frame in (docs, docs.limit(0)):
        d = frame
        for name, stage in C.STAGES:
            d = written(stage(spark, d, SF), name)
        assert (d.count() > 0) == (frame is docs)


CLASHES = ["row_key", "gone", "lines", "score", "ROW", "fp", "leader", "hits", "spans", "w", "h1", "label", "component_id", "n_lines", "x", "rep", "node", "sign"]


def test_clashing_columns_keep_their_values(spark):
    docs = table(spark, SF, "documents").select("*", *[F.concat(F.lit(c), F.col("doc_id").cast("string")).alias(c) for c in CLASHES])
    plain, d = table(spark, SF, "documents"), docs
    for name, stage in C.STAGES[:-1]:
        d, plain = written(stage(spark, d, SF), name), written(stage(spark, plain, SF), name)
        assert d.columns == docs.columns
        for c in CLASHES:
            assert d.where(F.col(c) != F.concat(F.lit(c), F.col("doc_id").cast("string"))).count() == 0
        assert sorted(r[:5] for r in d.collect()) == sorted(tuple(r) for r in plain.collect())


def test_shuffled_branches_give_the_same_rows(spark, monkeypatch):
    docs, got = table(spark, SF, "documents"), []
    for limit in (common.BROADCAST_BYTES, -1):
        monkeypatch.setattr(common, "BROADCAST_BYTES", limit)
        d, here = docs, []
        for name, stage in C.STAGES[1:-1]:
            d = written(stage(spark, d, SF), name)
            here.append(sorted(map(tuple, d.collect())))
        here.append(sorted(map(tuple, simhash_vp.op8_result(docs).collect())))
        here.append(sorted(map(tuple, decontam.op10_result(docs, table(spark, SF, "benchmark")).collect())))
        got.append(here)
    assert got[0] == got[1]


def test_one_row_of_each_group_stays(spark):
    text = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen"
    other = "a text of its own that is nothing like the rest of them here and now"
    rows = [(None, text), (None, text), (3, text), (3, text), (3, other), (2, text + " more"), (None, other + " x y z p q r s t"), (9, None), (8, ""), (None, None)]
    docs = spark.createDataFrame([(d, t, str(i)) for i, (d, t) in enumerate(rows)], "doc_id long, text string, tag string")
    left = C.near_duplicates(spark, docs, SF).collect()
    assert sorted(((r.doc_id, r.text) for r in left), key=str) == sorted([(2, text + " more"), (3, other), (None, other + " x y z p q r s t"), (8, "")], key=str)


def _kept_lines(rows):
    """Line deduplication by the rule: a key in two documents stays with the smallest id alone."""
    key = lambda line: line.strip(" \t\n\x0b\x0c\r").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    owner = {}
    for d, t in rows:
        for line in (t or "").split("\n"):
            if len(key(line)) >= 10:
                owner[key(line)] = min(d, owner.get(key(line), d))
    return [(d, t if t is None else "\n".join(x for x in t.split("\n") if owner.get(key(x), d) >= d)) for d, t in rows]


def _one_of_each(rows):
    """All pairs of five-word shingle sets, linked from a similarity of 0.8; the smallest id of a group stays."""
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if (not a and not b) or (a and b and len(a & b) >= 0.8 * len(a | b)):
                up[find(i)] = find(j)
    best = {}
    for i, (d, _) in enumerate(rows):
        best[find(i)] = min(best.get(find(i), d), d)
    return [r for r in rows if r[0] in best.values()]


def _without_leaks(rows, items):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
    windows = set()
    for t in items:
        w = words(t)
        n = min(13, len(w))
        windows |= {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()
    out = []
    for d, t in rows:
        w, hit = words(t), set()
        for n in {len(x) for x in windows}:
            for i in range(len(w) - n + 1):
                if tuple(w[i : i + n]) in windows:
                    hit |= set(range(i, i + n))
        if not hit or 20 * len(hit) < len(w):
            out.append((d, t))
    return out


def test_pipeline_equals_brute_force(spark):
    docs = table(spark, SF, "documents")
    good = written(C.quality(spark, docs, SF), "good")
    model = quality_mil.train(docs, table(spark, SF, "labels"))
    scores = {r.doc_id: model.forward(quality_mil.encode_passages((r.text or "").encode()), np.array([0]))[0][0] for r in docs.collect()}
    rows = sorted((r.doc_id, r.text) for r in good.collect())
    assert [d for d, _ in rows] == sorted(d for d, s in scores.items() if s >= 0.5)
    rows = _without_leaks(_one_of_each(_kept_lines(rows)), [r.text for r in table(spark, SF, "benchmark").collect()])
    got = C.run(spark, SF).collect()
    tok, pieces = _exact(Vocabulary().json_path), {}
    for r in got:
        pieces.setdefault(r.doc_id, []).append(r)
    assert sorted(pieces) == [d for d, _ in rows]
    for d, t in rows:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for p in sorted(pieces[d], key=lambda p: p.start):
            assert (p.start, p.doc_tokens, p.ids_crc32) == (at, len(ids), zlib.crc32(ids[at : at + p.length].tobytes()))
            at += p.length
        assert at == len(ids)

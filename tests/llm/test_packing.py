import random
import zlib

import numpy as np
import pytest
from helpers import DOC_DDL, docs

from navspark.llm import packing_dp as P
from navspark.llm.tokens import Vocabulary, _exact


def brute(at, pen, length):
    cost = [0] + [None] * (len(at) - 1)
    for j in range(1, len(at)):
        cost[j] = pen[j] + min(cost[i] + length - (at[j] - at[i]) for i in range(j) if at[j] - at[i] <= length)
    return cost[-1]


def total(at, pen, cuts, length):
    s = 0
    for i, j in zip(cuts, cuts[1:], strict=False):
        n = at[j] - at[i]
        assert 0 < n <= length
        s += length - n + pen[j]
    return s


@pytest.mark.parametrize("seed", range(30))
def test_cuts_are_optimal(seed):
    rnd = random.Random(seed)
    length = 64
    at = np.cumsum([0] + [rnd.choice([1, 2, 3, 8, 20, 64, 63]) for _ in range(rnd.randrange(1, 70))])
    pen = np.array([rnd.choice([0, 0, 3, 9]) for _ in at])
    cuts = P.best_cuts(at, pen, length)
    assert cuts[0] == 0 and cuts[-1] == len(at) - 1
    assert total(at.tolist(), pen.tolist(), cuts, length) == brute(at.tolist(), pen.tolist(), length)


def test_little_padding_to_whole_windows(spark):
    out = P.pack(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").coalesce(1))
    seqs = out.groupBy("sequence_id").sum("length").collect()
    used = sum(r[1] for r in seqs)
    assert len(seqs) * P.LENGTH - used < 0.02 * used


def test_round_trip(spark):
    rnd = random.Random(1)
    texts = [" ".join(rnd.choice(["one", "two.", "Drei!", "cuatro\n"]) for _ in range(rnd.randrange(0, 900))) for _ in range(40)]
    data = docs([(i, t) for i, t in enumerate(texts)] + [(50, None), (51, ""), (51, ""), (None, "x"), (52, "longword" * 9000), (53, "<|endoftext|> a")])
    out = P.pack(spark.createDataFrame(data, DOC_DDL).repartition(3), block=5000).collect()
    tok = _exact(Vocabulary().json_path)
    by_doc, by_seq = {}, {}
    for r in out:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    assert {r[0] for r in data} == set(by_doc)
    for d, t, *_ in data:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], np.uint32)
        pieces = sorted(by_doc[d], key=lambda r: r.start)
        if d == 51:
            assert [(p.start, p.length, p.doc_tokens) for p in pieces] == [(0, 1, 1)] * 2
            continue
        assert pieces[0].start == 0 and sum(p.length for p in pieces) == len(ids)
        for p in pieces:
            assert p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].astype("<u4").tobytes())
    used = 0
    for rows in by_seq.values():
        rows.sort(key=lambda r: r.offset)
        at = 0
        for r in rows:
            assert r.offset == at
            at += r.length
        assert at <= 2048
        used += 1
    # Three tasks, each with a last window cut short; else hardly a window more than the ids need.
    assert used <= 1.02 * sum(r.length for r in out) / 2048 + 3


def test_empty(spark):
    assert P.pack(spark.createDataFrame([], DOC_DDL)).count() == 0


def test_fast_ids_equal_the_library():
    rnd = random.Random(7)
    v = Vocabulary()
    tok = _exact(v.json_path)
    pool = [chr(c) for c in range(0x250)] + list("ΑλφаяЁ–—’“”…€") + ["<|endoftext|>", "  ", "\r\n", "'s", "'LL", "12", "　", "漢", "😀", "​", "\x85", "\x1c"]
    for _ in range(3000):
        t = "".join(rnd.choice(pool) for _ in range(rnd.randrange(30)))
        assert v.encode(t) == tok.encode(t, add_special_tokens=False).ids, repr(t)

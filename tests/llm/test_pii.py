import random
import re

import numpy as np
import pytest
from helpers import DOC_DDL, docs

from navspark.llm import pii as P


@pytest.fixture(scope="module")
def field(spark):
    return P.train_from(P.labelled_table(spark))


PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def brute(text):
    out = []
    for kind, p in PATTERNS.items():
        for m in re.finditer(p, text):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else False, "card": 13 <= len(digits) <= 19 and P.luhn(digits), "phone": 9 <= len(digits) <= 15}[kind]
            if ok:
                out.append((kind, *m.span()))
    return out


def test_base_equals_patterns():
    rnd = random.Random(3)
    bits = ["a", "b.c", "@", ".", "-", "_", "+", "1", "25", "255", "256", " ", "(", ")", "4111111111111111", "4111-1111 1111 1111", "é", "x@y.z", "\n", "0001", "+1 (017) 555-7713"]
    for _ in range(20000):
        t = "".join(rnd.choice(bits) for _ in range(rnd.randrange(14)))
        assert P.base_spans(t) == brute(t), repr(t)


def test_base_is_linear_in_hard_texts():
    for t in ("a" * 300_000, "1" * 300_000, "1." * 150_000, "+1" + " " * 300_000, "a@" * 150_000, "@a." * 100_000):
        P.base_spans(t)


def test_pruned_decoding_is_viterbi(field):
    rng = np.random.default_rng(1)
    for n in (1, 2, 7, 60):
        for _ in range(20):
            s = rng.normal(0, 4, (n, len(P.LABELS)))
            s[:, 0] += 3
            want = field.decode(s, prune=False)
            best = field.begin + s[0]
            for t in range(1, n):
                best = (best[:, None] + field.move).max(0) + s[t]
            path = field.begin[want[0]] + s[np.arange(n), want].sum() + field.move[want[:-1], want[1:]].sum() + field.stop[want[-1]]
            assert np.isclose(path, (best + field.stop).max())
            assert (field.decode(s) == want).all()


def test_finds_held_out_and_leaves_prose_alone(field):
    hit = total = wrong = 0
    for text, spans in P.labelled_rows(400, seed=99):
        got = {(a, b) for _, a, b in P.all_spans(text, field)[1]}
        total += len(spans)
        hit += sum(any(x < b and y > a for x, y in got) for _, a, b in spans)
        wrong += sum(not any(x < b and y > a for _, a, b in spans) for x, y in got)
    assert hit / total > 0.97 and wrong / total < 0.03
    assert P.all_spans('the token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" in it', field)[1] == [("secret", 13, 53)]


def test_digits_must_bear_the_kind_out(field):
    found = lambda t: P.all_spans(t, field)[1]
    assert found("the number 9807915762804490 is no card") == []
    assert [s[0] for s in found("the card 4111 1111 1111 1111 is one")] == ["card"]
    assert found("call +1 (826) 555-4081 190.137.223 today")[0] == ("phone", 5, 22)


def test_query(spark, field):
    data = docs([(1, None), (2, ""), (3, "Äö x@y.com and +1 (017) 555-7713, 4111 1111 1111 1111 10.0.0.1"), (3, "x"), (None, "plain"), (4, "word " * 600_000 + "me@example.org")])
    df = spark.createDataFrame(data, DOC_DDL).withColumnRenamed("lang", "spans")
    got = {(r.doc_id, r.base_sha256): r for r in P.op2_result(df).collect()}
    for d, t, *_ in data:
        r = got[(d, P.sha256_of(brute(t or "")))]
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == x for k, *_ in brute(t or "")) for x in P.BASE]
        assert set(",".join(f"{k}:{a}:{b}" for k, a, b in brute(t or "")).split(",")) <= set(r.spans.split(","))
    assert P.op2_result(df.limit(0)).count() == 0


def test_slices_label_alike(field, monkeypatch):
    text = " ".join(t for t, _ in P.labelled_rows(60, seed=5))
    whole = P.added_spans(text, field)
    monkeypatch.setattr(P, "SLICE", 4000)
    part = P.added_spans(text, field)
    assert len(set(whole) ^ set(part)) <= 2 * (len(text) // 4000 + 1)

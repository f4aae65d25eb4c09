import random
import zlib

from helpers import DOC_DDL, docs

from navspark.llm import token_tree as T
from navspark.llm.tokens import Vocabulary, _fast


def test_edits_equal_full_encoding():
    rnd = random.Random(6)
    enc = _fast(Vocabulary().ranks_path)
    bits = ["a", "word", " ", "  ", "\n", "'s", "'", "re", "12", "3", "é", "!", "...", "\t", "don't", " the", "ß"]
    count = T.Counter()
    for case in range(400):
        tree = T.TokenTree("".join(rnd.choice(bits) for _ in range(rnd.choice([0, 1, 5, 40, 400]))), count, leaf=rnd.choice([1, 3, 8]))
        for _ in range(8):
            at, remove = rnd.randrange(-1, len(tree.text) + 3), rnd.choice([0, 0, 1, 3, 30, 1000])
            insert = "".join(rnd.choice(bits) for _ in range(rnd.choice([0, 1, 2, 60])))
            a = max(0, min(at, len(tree.text)))
            want = tree.text[:a] + insert + tree.text[a + min(remove, len(tree.text) - a) :]
            tree.edit(at, remove, insert)
            assert tree.text == want
            assert tree.total() == len(enc.encode_ordinary(want)), (case, want)
            assert sum(map(len, (x[0] for x in tree.leaves))) == len(T._pattern().findall(want))


def test_edits_encode_little():
    tree = T.TokenTree("some words of text " * 5000, T.Counter())
    assert tree.edit(40_000, 3, "new") < 10


def test_query(spark):
    enc = _fast(Vocabulary().ranks_path)
    data = docs([(1, None), (2, ""), (3, "plain words here, it's all " * 50), (3, "x"), (None, "y z"), (4, "long " * 200_000)])
    df = spark.createDataFrame(data, DOC_DDL).withColumnRenamed("lang", "edits")
    got = T.op7_result(df).collect()
    assert sorted(r.n_tokens for r in got) == sorted(len(enc.encode_ordinary(t or "")) for _, t, *_ in data)
    todo = {(r.doc_id, r.text): r.e for r in df.select("doc_id", "text", T.test_edits().alias("e")).collect()}
    want = []
    for d, t, *_ in data:
        s = t or ""
        for e in todo[(d, t)]:
            at = max(0, min(e["at"], len(s)))
            s = s[:at] + e["insert"] + s[at + min(e["remove"], len(s) - at) :]
        want.append((d, len(enc.encode_ordinary(s)), zlib.crc32(s.encode())))
    assert sorted(((r.doc_id, r.n_tokens_edited, r.crc32_edited) for r in got), key=str) == sorted(want, key=str)
    assert T.op7_result(df.limit(0)).count() == 0


def test_stored_trees_take_edit_after_edit(spark, tmp_path):
    enc = _fast(Vocabulary().ranks_path)
    data = docs([(1, None), (2, "plain words here, it's all " * 500), (None, "y z")])
    trees = T.store(spark.createDataFrame(data, DOC_DDL), str(tmp_path / "a"))
    for turn, todo in enumerate(([(3, 1, " new"), (0, 0, "x")], [(2000, 40, "gone!")], [])):
        put = "array(" + ", ".join(f"named_struct('at', {a}, 'remove', {r}, 'insert', '{i}')" for a, r, i in todo) + ")"
        after = T.edited(trees.selectExpr("*", f"{put} as edits"))
        assert after.where("n_encoded > 12").count() == 0
        after.drop("n_before", "n_encoded").write.parquet(str(tmp_path / f"t{turn}"))
        trees = spark.read.parquet(str(tmp_path / f"t{turn}"))
        for r in trees.collect():
            assert r.n_tokens == len(enc.encode_ordinary(r.text or ""))
            assert (bytes(r.lengths), bytes(r.counts)) == T.TokenTree(r.text or "", T.Counter()).stored()

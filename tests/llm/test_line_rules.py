import random

from helpers import DOC_DDL, DOCS, docs, duck, rows

from navspark.llm import line_rules as R

COLS = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "bad_chars", "base_failed", "kept"]


def sample():
    rnd = random.Random(8)
    lines = ["A clean line of words that ends well.", "Home | About | News | Contact", "ALL CAPS HERE!! AND MORE!!", "cookie settings", "short", "Über größe ñandú élan.", "a*b#c$d%e&f", "  ", "\t tabs\x0band\x0c more words here.", "one two three four five six seven eight."]
    out = [(i, "\n".join(rnd.choice(lines) for _ in range(rnd.randrange(1, 14)))) for i in range(120)]
    out += [(500 + i, " ".join(rnd.choice(["a", "b", "c."]) for _ in range(rnd.randrange(1, 60)))) for i in range(60)]
    return docs([*out, (900, None), (901, ""), (902, " \n\t"), (903, "word " * 30_000), (904, " ".join(f"w{i}" for i in range(30_000)))])


def test_equals_sql(spark):
    data = sample()
    df = spark.createDataFrame(data, DOC_DDL).withColumnRenamed("lang", "kept").repartition(4)
    got = rows(R.op6_result(df), COLS)
    assert got == sorted((tuple(r) for r in duck(f"select {', '.join(COLS)} from ({R.OP6_SQL})", documents=(data, DOCS))), key=str)
    assert {r[-1] for r in got} == {True, False}


def test_cleaned_text_and_empty(spark):
    text = "This is a clean sentence with many words in it.\nHome | About | News | More\n" + "And another sentence which is long enough to keep it all.\n" * 1
    df = spark.createDataFrame(docs([(1, text), (1, text), (None, "x")]), DOC_DDL)
    got = [r.text for r in R.cleaned(df).collect()]
    assert got == ["This is a clean sentence with many words in it.\nAnd another sentence which is long enough to keep it all."] * 2
    assert R.op6_result(df.limit(0)).count() == 0


def test_a_later_filter_stays_linear(spark):
    """A filter on the verdict must not copy captured arrays into lambdas, which would take hours here."""
    import time

    data = docs([(i, " ".join(f"w{j % 500}" for j in range(40_000))) for i in range(4)])
    t = time.time()
    assert R.op6_result(spark.createDataFrame(data, DOC_DDL)).where("not kept and not base_failed").count() == 0
    assert time.time() - t < 60

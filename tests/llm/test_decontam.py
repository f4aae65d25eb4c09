import random

from helpers import DOC_DDL, DOCS, ITEMS, docs, duck, rows

from navspark.llm import decontam as D

COLS = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]


def sample():
    rnd = random.Random(4)
    vocab = ["the", "Éa", "ab1", "x", "word", "zz", "q", "über"]
    items = [(i, " ".join(rnd.choice(vocab) + str(rnd.randrange(6)) for _ in range(rnd.choice([3, 5, 13, 14, 30])))) for i in range(25)]
    items += [(90, ""), (91, None), (92, items[4][1].upper().replace("É", "É"))]
    out = []
    for i in range(60):
        w = [rnd.choice(vocab) + str(rnd.randrange(6)) for _ in range(rnd.randrange(0, 120))]
        for _ in range(rnd.randrange(3)):
            at = rnd.randrange(len(w) + 1)
            w[at:at] = (rnd.choice(items)[1] or "").split()
        out.append((i, rnd.choice([" ", ", ", "\n-"]).join(w)))
    return docs([*out, (70, None), (71, ""), (72, "??"), (73, items[2][1].upper()), (74, (items[3][1] + " ") * 100)]), items


def test_equals_sql(spark):
    data, items = sample()
    items = [x for x in items if x[1] is not None or x[0] == 91]
    got = rows(D.op10_result(spark.createDataFrame(data, DOC_DDL).repartition(3), spark.createDataFrame(items, "item_id long, text string")), COLS)
    assert got == duck(D.OP10_SQL, documents=(data, DOCS), benchmark=(items, ITEMS))
    assert any(r[-1] for r in got) and not all(r[-1] for r in got)


def test_removal(spark):
    item = " ".join(f"t{i}" for i in range(13))
    data = docs([(1, f"Before it. {item.upper()}! After it"), (1, "clean words only"), (2, None), (None, item), (3, "x " * 400 + item)])
    df, bench = spark.createDataFrame(data, DOC_DDL), spark.createDataFrame([(1, item)], "item_id long, text string")
    assert rows(D.without_contaminated(df, bench), ["doc_id", "text"]) == sorted([(1, "clean words only"), (2, None), (3, "x " * 400 + item)], key=str)
    cut = rows(D.without_spans(df, bench), ["doc_id", "text"])
    assert (1, "Before it. After it") in cut and (None, "") in cut and (3, "x " * 400) in cut


def test_empty_tables(spark):
    data, items = sample()
    df, bench = spark.createDataFrame(data, DOC_DDL), spark.createDataFrame(items, "item_id long, text string")
    assert D.op10_result(df.limit(0), bench).count() == 0
    assert D.op10_result(df, bench.limit(0)).where("n_hit > 0").count() == 0


def test_items_without_id_hit(spark):
    item, other = " ".join(f"t{i}" for i in range(13)), " ".join(f"s{i}" for i in range(14))
    data = docs([(1, item), (2, other), (3, "clean"), (4, item + " " + other)])
    items = [(None, item), (None, other), (7, other)]
    got = rows(D.op10_result(spark.createDataFrame(data, DOC_DDL), spark.createDataFrame(items, "item_id long, text string")), COLS)
    assert got == duck(D.OP10_SQL, documents=(data, DOCS), benchmark=(items, ITEMS))
    assert [r[:4] for r in got] == [(1, 13, 13, 1), (2, 14, 14, 2), (3, 1, 0, 0), (4, 27, 27, 2)]

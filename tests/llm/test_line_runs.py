import random

import pytest
from helpers import DOC_DDL, DOCS, docs, duck, rows

from navspark.llm import line_runs as L

COLS = ["doc_id", "n_lines", "n_dropped", "kept_sha256"]


def sample():
    rnd = random.Random(2)
    pool = [f"Common line number {i} É" for i in range(12)] + ["short", "", "  Padded Line Here\t", "padded line here", "ÀÉ" * 6, "àé" * 6]
    out = [(i, "\n".join(rnd.choice(pool) if rnd.random() < 0.6 else f"own line {i} {rnd.random()}" for _ in range(rnd.randrange(1, 9)))) for i in range(80)]
    return docs([*out, (100, None), (101, ""), (102, "\n\n"), (103, "Common line number 1 É\n" * 3000)])


def test_equals_sql(spark):
    data = sample()
    df = spark.createDataFrame(data, DOC_DDL).withColumnRenamed("lang", "owner").repartition(3)
    assert rows(L.op9_result(df), COLS) == duck(L.OP9_SQL, documents=(data, DOCS))


def test_batches_do_not_matter(spark):
    df = spark.createDataFrame(sample(), DOC_DDL)
    want = rows(L.without_repeated_lines(df, 1), ["doc_id", "text"])
    for n in (2, 5):
        assert rows(L.without_repeated_lines(df, n), ["doc_id", "text"]) == want


def test_store_compacts_and_keeps_first_owner(spark):
    store = L.LineRuns(spark)
    for i in range(4):
        lines = spark.createDataFrame([(i * 10, 1, 1), (i * 10 + 1, 2 + i, 1)], "doc_id long, h1 long, h2 long")
        store.add(lines)
    assert sum(map(len, store.levels)) == 1
    assert {(r.h1, r.owner) for r in store.runs().collect()} == {(1, 0), (2, 1), (3, 11), (4, 21), (5, 31)}


def test_null_ids_repeats_and_empty(spark):
    df = spark.createDataFrame(docs([(None, "a line of some length"), (3, "a line of some length"), (3, "a line of some length"), (5, "a line of some length")]), DOC_DDL)
    got = rows(L.without_repeated_lines(df), ["doc_id", "text"])
    assert got == sorted([(None, "a line of some length"), (3, "a line of some length"), (3, "a line of some length"), (5, "")], key=str)
    assert L.op9_result(df.limit(0)).count() == 0


def test_runs_are_neither_shuffled_nor_sorted_again(spark):
    store = L.LineRuns(spark, fanout=9)
    for i in range(3):
        store.add(spark.createDataFrame([(i * 1000 + j, h, h) for j, h in enumerate(range(i * 5, 200))], "doc_id long, h1 long, h2 long"))
    batch = spark.createDataFrame([(9999, h, h) for h in range(300)], "doc_id long, h1 long, h2 long")
    with L._in_order(spark):
        met = store.resolve(batch)
        plan = met._jdf.queryExecution().executedPlan().toString()
        assert met.where("owner is null").count() == 100
    assert plan.count("SortMergeJoin") == 3 and "Broadcast" not in plan
    assert plan.count("Exchange hashpartitioning") == 1  # the batch's own keys
    assert plan.count("Sort [") == 1
    store.close()


def test_batches_out_of_order_are_refused(spark):
    store = L.LineRuns(spark)
    store.add(spark.createDataFrame([(5, 1, 1)], "doc_id long, h1 long, h2 long"))
    with pytest.raises(ValueError, match="doc_id 4"):
        store.add(spark.createDataFrame([(4, 1, 1)], "doc_id long, h1 long, h2 long"))
    store.close()

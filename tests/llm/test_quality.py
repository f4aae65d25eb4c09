import numpy as np
import pytest
from helpers import DOC_DDL, docs

from navspark.llm import quality_mil as Q

SF = "/root/testdata/sf0.1"


def test_gradient():
    rng = np.random.default_rng(0)
    bags = [rng.random((n, Q.WIDTH)).astype(np.float32) for n in (1, 3, 2, 5)]
    y = np.array([1.0, 0, 1, 0])
    model = Q.fit(bags, y, hidden=5, attention=3, epochs=1)
    first = np.array([0, 1, 4, 6])
    x = np.concatenate(bags).astype(np.float64)
    grad = model.gradient(x, first, y)

    def loss():
        p = model.forward(x, first)[0]
        return -np.mean(y * np.log(p) + (1 - y) * np.log(1 - p))

    for k, w in model.weights.items():
        w = model.weights[k] = np.array(w, float)
        at = tuple(rng.integers(0, s) for s in w.shape)
        old = w[at].copy()
        w[at] = old + 1e-5
        up = loss()
        w[at] = old - 1e-5
        down = loss()
        w[at] = old
        assert abs((up - down) / 2e-5 - np.asarray(grad[k])[at]) < 1e-6, k


def test_held_out_accuracy(spark):
    d, lab = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    got = Q.op3_result(d, lab).join(lab, "doc_id").where("held_out").select("score", "predicted", "quality").toPandas()
    assert got.score.between(0, 1).all()
    assert (got.predicted == got.quality).mean() > 0.97
    good, bad = got.score[got.quality == 1].to_numpy(), got.score[got.quality == 0].to_numpy()
    assert np.mean(good[:, None] > bad[None, :]) > 0.99


def test_edge_rows(spark):
    d = docs([(1, None), (2, ""), (3, "a"), (3, "a"), (None, "text " * 100), (4, "x" * 5_000_000)])
    df = spark.createDataFrame(d, DOC_DDL).withColumnRenamed("lang", "Score")
    few = spark.createDataFrame([(1, 1, 0), (2, 0, 0), (4, 0, 0), (6, 1, 0)], "doc_id long, quality int, toxic int")
    for labels in (few, few.limit(0)):
        got = Q.op3_result(df, labels).collect()
        assert len(got) == 6 and all(0 <= r.score <= 1 for r in got)
        assert Q.op3_result(df.limit(0), labels).count() == 0
    assert set(Q.good_documents(df, few.limit(0)).columns) == set(df.columns)


def test_one_class_and_bounds(spark):
    d = docs([(i, f"text number {i} " * 30) for i in range(40)] + [(1, "another text of one id")] * 30)
    df = spark.createDataFrame(d, DOC_DDL)
    for label in (0, 1):
        labels = spark.createDataFrame([(i, label, 0) for i in range(40)], "doc_id long, quality int, toxic int")
        assert {r.predicted for r in Q.op3_result(df, labels).collect()} == {label}
    bags, y = Q.training_bags(df, labels)
    assert len(bags) == len(y) == sum(1 for i in range(40) if __import__("zlib").crc32(str(i).encode()) % 3 != 1)
    assert sum(map(len, Q.training_bags(df, labels, max_total=7)[0])) <= 7
    assert len(Q.training_bags(df, labels, max_train=3)[0]) == 3


def test_taken_names(spark):
    df = spark.createDataFrame([(1, "some text", 0.25), (2, None, 0.5)], "doc_id long, text string, Score double")
    labels = spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int")
    assert sorted(Q.good_documents(df, labels).collect()) == sorted(df.collect())
    with pytest.raises(ValueError):
        Q.scored(df, 0.5)

"""Quality classifier: attention-based multiple-instance learning.

A document is a bag of passages. Every passage of the whole text is encoded (bigrams of
character classes, projected by a learned layer); gated attention weighs the passages, and
the weighted representation is scored. Only document labels are known, so the attention
learns by itself which passages decide.

The model is fitted on the driver from at most ``MAX_TRAIN`` labelled documents of at most
``MAX_PASSAGES`` passages, and no more than ``MAX_TOTAL`` passages in all (32 MB), taken in the
order of the hashes of their ids (a documented bound); scoring is one scan with an Arrow map
and covers every document and all of its text in bounded slices.

Defined results: null or empty text is one empty passage and gets the model's score for it.
With fewer than two classes among the training rows every score is the share of label 1, with
one of each class added: above 0.5 for ones alone, below for zeros alone, 0.5 without labels.
Labels, languages, sources and ids are never inputs. A doc_id with several labels counts with
the lowest, one with several texts is fitted on one of them. Repeated rows are scored each; an
empty table gives an empty result; extra columns stay, and a name that is taken is an error.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from navspark.llm.common import arrow_map, written

PASSAGE = 1024  #: bytes of a passage
SLICE = 1 << 22  #: bytes encoded at a time
MAX_TRAIN = 4000  #: labelled documents used for fitting
MAX_PASSAGES = 128  #: longer documents are left out of fitting (never of scoring)
MAX_TOTAL = 1 << 16  #: passages of all documents used for fitting
CLASSES = 16
WIDTH = CLASSES * CLASSES


def _table() -> np.ndarray:
    t = np.zeros(256, np.int64)
    for code, chars in enumerate((" \t\r\x0b\x0c", "\n", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", ".", ",;:", "!?", "|", "#*$%&", "<>[]{}()", "\"'`", "-_/\\+=~^@"), 1):
        t[[ord(c) for c in chars]] = code
    t[0x80:0xC0], t[0xC0:] = 14, 15
    return t


_CLASS = _table()


def encode_passages(data: bytes) -> np.ndarray:
    """One row for each passage: square roots of the shares of character-class bigrams."""
    out = []
    for at in range(0, max(1, len(data)), SLICE):
        c = _CLASS[np.frombuffer(data[at : at + SLICE], np.uint8)]
        n = max(1, -(-len(c) // PASSAGE))
        if len(c) < 2:
            out.append(np.zeros((1, WIDTH), np.float32))
            continue
        cell = c[:-1] * CLASSES + c[1:] + WIDTH * (np.arange(len(c) - 1) // PASSAGE)
        counts = np.bincount(cell, minlength=n * WIDTH).reshape(n, WIDTH).astype(np.float32)
        out.append(np.sqrt(counts / np.maximum(1, counts.sum(1, keepdims=True))))
    return np.concatenate(out)


def _sigmoid(x):
    return 0.5 * (1 + np.tanh(0.5 * x))


@dataclass
class GatedAttention:
    """tanh encoder, gated attention and a logistic output."""

    mean: np.ndarray
    scale: np.ndarray
    weights: dict[str, np.ndarray]

    def forward(self, x: np.ndarray, first: np.ndarray):
        """Scores of the bags whose passages start at ``first``; the parts for the gradient."""
        w = self.weights
        x = (x - self.mean) / self.scale
        h = np.tanh(x @ w["enc"] + w["enc0"])
        t, g = np.tanh(h @ w["att"]), _sigmoid(h @ w["gate"])
        e = (t * g) @ w["pick"]
        sizes = np.diff(np.append(first, len(x)))
        a = np.exp(e - np.repeat(np.maximum.reduceat(e, first), sizes))
        a = a / np.repeat(np.add.reduceat(a, first), sizes)
        z = np.add.reduceat(a[:, None] * h, first)
        return _sigmoid(z @ w["out"] + w["out0"]), (x, h, t, g, a, z, sizes)

    def gradient(self, x: np.ndarray, first: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        w = self.weights
        p, (x, h, t, g, a, z, sizes) = self.forward(x, first)
        ds = (p - y) / len(y)
        dz = np.repeat(ds[:, None] * w["out"], sizes, axis=0)
        da = (dz * h).sum(1)
        de = a * (da - np.repeat(np.add.reduceat(a * da, first), sizes))
        dt, dg = de[:, None] * w["pick"] * g * (1 - t * t), de[:, None] * w["pick"] * t * g * (1 - g)
        dh = (a[:, None] * dz + dt @ w["att"].T + dg @ w["gate"].T) * (1 - h * h)
        return {"enc": x.T @ dh, "enc0": dh.sum(0), "att": h.T @ dt, "gate": h.T @ dg, "pick": (t * g).T @ de, "out": z.T @ ds, "out0": ds.sum()}


def fit(bags: list[np.ndarray], labels: np.ndarray, hidden: int = 24, attention: int = 12, epochs: int = 40, batch: int = 128, seed: int = 1) -> GatedAttention:
    rng = np.random.default_rng(seed)
    every = np.concatenate(bags)
    mean, scale = every.mean(0), np.maximum(every.std(0), 0.02)

    def init(*shape):
        return rng.normal(0, 1 / np.sqrt(shape[0]), shape)

    w = {"enc": init(WIDTH, hidden), "enc0": np.zeros(hidden), "att": init(hidden, attention), "gate": init(hidden, attention), "pick": init(attention), "out": init(hidden), "out0": np.zeros(())}
    model = GatedAttention(mean, scale, w)
    m, v, step = {k: 0 * x for k, x in w.items()}, {k: 0 * x for k, x in w.items()}, 0
    epochs = max(epochs, -(-1500 * batch // max(1, len(bags)) // 10))
    for _ in range(min(epochs, 200)):
        order = rng.permutation(len(bags))
        for s in range(0, len(order), batch):
            some = order[s : s + batch]
            first = np.cumsum([0, *(len(bags[i]) for i in some)])[:-1]
            grad, step = model.gradient(np.concatenate([bags[i] for i in some]), first, labels[some]), step + 1
            for k in w:
                g = grad[k] + (1e-3 * w[k] if w[k].ndim > 1 else 0)
                m[k], v[k] = 0.9 * m[k] + 0.1 * g, 0.999 * v[k] + 0.001 * g * g
                w[k] = w[k] - 0.004 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
    return model


def held_out(doc_id="doc_id"):
    """Rows that never lend their labels: crc32 of the id as text leaves 1 when divided by 3."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 3, F.lit(0)) == 1


def training_bags(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN, max_passages: int = MAX_PASSAGES, max_total: int = MAX_TOTAL):
    """Bounded sample of labelled documents as bags of encoded passages."""
    marked = labels.where("doc_id is not null and quality is not null").where(~held_out()).groupBy("doc_id").agg(F.min("quality").cast("int").alias("label"))
    chosen = F.broadcast(marked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train))
    some = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).where(F.octet_length("text") <= PASSAGE * max_passages)
    one = some.join(chosen, "doc_id").groupBy("doc_id", "label").agg(F.min(F.struct(F.xxhash64("text"), "text")).alias("x"))

    def run(batches):
        for b in batches:
            got = [encode_passages(t.as_py().encode()).astype(np.float16).tobytes() for t in b.column("text")]
            size = [len(x) // (2 * WIDTH) for x in got]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("label"), pa.array(size, pa.int64()), pa.array(got, pa.binary())], ["doc_id", "label", "size", "bag"])

    bags = written(arrow_map(one.select("doc_id", "label", F.col("x.text").alias("text")), run, "doc_id long, label int, size long, bag binary"), "bags")
    so_far = F.sum("size").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id"))  # of at most max_train rows
    take = bags.select("doc_id", so_far.alias("so_far")).where(F.col("so_far") <= max_total).select("doc_id")
    rows = sorted(bags.join(F.broadcast(take), "doc_id").select("doc_id", "label", "bag").collect())
    return [np.frombuffer(r.bag, np.float16).reshape(-1, WIDTH).astype(np.float32) for r in rows], np.array([r.label for r in rows], np.float64)


def train(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN, max_passages: int = MAX_PASSAGES) -> GatedAttention | float:
    """The fitted model, or a constant score where the labels know fewer than two classes."""
    bags, y = training_bags(docs, labels, max_train, max_passages)
    return fit(bags, y) if len(set(y.tolist())) > 1 else float((y.sum() + 1) / (len(y) + 2))


def scored(docs: DataFrame, model: GatedAttention | float, name: str = "score") -> DataFrame:
    """``docs`` with the column ``name`` added; the text is read whole."""
    if name.lower() in map(str.lower, docs.columns):
        raise ValueError(f"there is a column {name} already")
    text = docs.columns.index("text")
    names = [*docs.columns, name]

    def run(batches):
        for b in batches:
            if isinstance(model, float):
                score = np.full(b.num_rows, model)
            else:
                score, texts, at = np.ones(b.num_rows), [(t.as_py() or "").encode() for t in b.column(text)], 0
                while at < len(texts):
                    end, size = at, 0
                    while end < len(texts) and (end == at or size + len(texts[end]) <= SLICE):
                        size += len(texts[end])
                        end += 1
                    bags = [encode_passages(x) for x in texts[at:end]]
                    first = np.cumsum([0, *map(len, bags)])[:-1]
                    score[at:end] = model.forward(np.concatenate(bags), first)[0]
                    at = end
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score)], names)

    return arrow_map(docs, run, StructType([*docs.schema.fields, StructField(name, DoubleType())]))


def op3_result(docs: DataFrame, labels: DataFrame) -> DataFrame:
    got = scored(docs.select("doc_id", "text"), train(docs, labels))
    return got.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def good_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Drops the documents that the classifier rejects; all columns stay."""
    name = "score"
    while name in map(str.lower, docs.columns):
        name = "_" + name
    return scored(docs, train(docs, labels), name).where(F.col(name) >= 0.5).drop(name)

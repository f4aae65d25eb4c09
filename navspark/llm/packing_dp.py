"""Order-preserving sequence packing by dynamic programming.

Documents are laid end to end in table order. Windows are cut at document or sentence
boundaries (inside a sentence only where one is longer than a window) so that the sum of
padding and truncation penalties is least. With S the token position of a cut,

    cost(j) = penalty(j) + min over cuts i within a window of cost(i) + padding(S_j - S_i)

where padding(n) = length - n, so the least cost(i) + S_i over a sliding range is wanted: a
monotone queue gives it in constant time a cut. Every window counts as padded to the whole
length, also one whose length is a power of two: a rule that spares such windows the padding
would else be met by cutting documents into many short windows.

The plan is a scan and a map: no shuffle. A task holds one block of about ``BLOCK`` tokens at
a time, packs it and goes on, so memory is bounded by a block or by the longest document. The
last window of a block goes into the next one, so only a task's very last is cut short.
Sequence ids join the partition number with a counter; a lost task repeats them exactly.

Defined results: null or empty text is the closing id alone; repeated rows are packed each; a
null doc_id is carried along; an empty table gives no pieces; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import deque

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navspark.llm.common import arrow_map
from navspark.llm.tokens import Vocabulary

LENGTH = 2048
BLOCK = 1 << 20  #: tokens packed together
SPLIT_COST = 16  #: penalty, in tokens, of cutting a document after a sentence
HARD_COST = 128  #: of cutting inside a sentence
HARD_STEP = 256  #: distance of the cuts offered inside a sentence longer than a window

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def candidates(ids: np.ndarray, doc_ends: np.ndarray, ends: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Cut positions from 0 to the end, and the penalty of each."""
    cost = np.full(len(ids) + 1, -1, np.int32)
    cost[np.flatnonzero(ends[ids]) + 1] = SPLIT_COST
    cost[doc_ends] = 0
    cost[0] = 0
    at = np.flatnonzero(cost >= 0)
    for i in np.flatnonzero(np.diff(at) > length):
        cost[at[i] + HARD_STEP : at[i + 1] : HARD_STEP] = HARD_COST
    at = np.flatnonzero(cost >= 0)
    return at, cost[at]


def best_cuts(at: np.ndarray, penalty: np.ndarray, length: int = LENGTH) -> list[int]:
    """Indices into ``at`` of the cheapest cuts, first and last position included."""
    pos, pen = at.tolist(), penalty.tolist()
    n = len(pos)
    cost, back = [0] * n, [0] * n
    queue: deque[tuple[int, int]] = deque()  # (cost(i) + S_i, i), increasing
    for j in range(1, n):
        i = j - 1
        key = cost[i] + pos[i]
        while queue and queue[-1][0] >= key:
            queue.pop()
        queue.append((key, i))
        low = pos[j] - length
        while pos[queue[0][1]] < low:
            queue.popleft()
        best, came = queue[0]
        cost[j], back[j] = best + length - pos[j] + pen[j], came
    cuts = [n - 1]
    while cuts[-1]:
        cuts.append(back[cuts[-1]])
    return cuts[::-1]


Held = tuple[int | None, np.ndarray, int, int]  #: doc_id, ids, how many ids of the document came before, and all of them


def pack_block(docs: list[Held], ends: np.ndarray, length: int, first_sequence: int, last: bool = True) -> tuple[dict, int, list[Held]]:
    """Pieces of a block of documents, the number of sequences used, and what is left for the next
    block: the ids of the last window, unless this is the ``last`` block."""
    ids = np.concatenate([d[1] for d in docs])
    doc_ends = np.cumsum([len(d[1]) for d in docs])
    starts = doc_ends - np.array([len(d[1]) for d in docs])
    at, penalty = candidates(ids, doc_ends, ends, length)
    cuts = at[best_cuts(at, penalty, length)]
    left: list[Held] = []
    if not last:
        cuts = cuts[:-1]
        for d in range(int(np.searchsorted(doc_ends, cuts[-1], "right")), len(docs)):
            doc_id, own, before, size = docs[d]
            gone = max(0, int(cuts[-1] - starts[d]))
            left.append((doc_id, own[gone:], before + gone, size))
    edges = np.union1d(cuts, doc_ends[doc_ends <= cuts[-1]])
    begin, stop = edges[:-1], edges[1:]
    doc = np.searchsorted(doc_ends, begin, "right")
    seq = np.searchsorted(cuts, begin, "right") - 1
    raw = memoryview(ids.astype("<u4").tobytes())
    return (
        {
            "doc_id": pa.array([docs[d][0] for d in doc.tolist()], pa.int64()),
            "start": begin - starts[doc] + np.array([d[2] for d in docs])[doc],
            "length": stop - begin,
            "ids_crc32": np.array([zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(begin.tolist(), stop.tolist(), strict=True)], np.int64),
            "doc_tokens": np.array([d[3] for d in docs])[doc],
            "sequence_id": seq + first_sequence,
            "offset": begin - cuts[seq],
        },
        len(cuts) - 1,
        left,
    )


def pack(docs: DataFrame, length: int = LENGTH, block: int = BLOCK, json_path: str | None = None, ranks_path: str | None = None) -> DataFrame:
    """One row for each piece of a document; the general form of the packing query."""

    def run(batches):
        vocabulary = Vocabulary(json_path, ranks_path)
        ends = vocabulary.sentence_ends()
        held: list[Held] = []
        size, sequence = 0, TaskContext.get().partitionId() << 40

        def flush(last: bool):
            nonlocal held, size, sequence
            cols, used, held = pack_block(held, ends, length, sequence, last)
            size, sequence = sum(len(d[1]) for d in held), sequence + used
            return pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) if isinstance(v, np.ndarray) else v for v in cols.values()], list(cols))

        for b in batches:
            for doc_id, text in zip(b.column("doc_id"), b.column("text"), strict=True):
                ids = vocabulary.document(text.as_py())
                held.append((doc_id.as_py(), ids, 0, len(ids)))
                size += len(ids)
                if size >= max(block, 2 * length):
                    yield flush(False)
        if held:
            yield flush(True)

    return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, SCHEMA)

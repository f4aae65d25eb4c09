"""Edit-aware token counting with stored segment trees of pre-tokens.

Byte-pair merges never cross pre-tokens, so a text's count is the sum over its pre-tokens. A
document keeps a tree whose leaves hold runs of pre-tokens (their lengths and token counts)
and whose inner nodes hold sums. An edit re-splits only from the last pre-token that cannot
have seen the edit up to the first old boundary behind it that the new split meets again;
beyond that the split, which looks only forward, must go on as before. Leaves touched are
replaced and sums on their paths updated.

``planted`` makes a table of trees, one row a document: its text and the lengths and counts of
its pre-tokens. The table is written once and read in each later run; ``edited`` takes rows of
it with their edits, encodes only what these touch, and gives rows of the same form again. Inner
sums follow from the leaves without any encoding, so they are not stored.

Defined results: null text counts as empty; positions and lengths of edits are clipped to the
text; repeated rows are counted each; null ids are carried; an empty table gives an empty
result; extra columns are ignored. Special-token strings count as ordinary text.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from navspark.llm.common import scratch, text_key
from navspark.llm.tokens import Vocabulary, _fast

LEAF = 64  #: pre-tokens of a leaf
AHEAD = 2  #: characters behind its start that a split decision may look at past a pre-token's end


@lru_cache(maxsize=1)
def _pattern():
    import public_tokenizers

    return regex.compile(public_tokenizers.PATTERN)


class Counter:
    """Token count of a pre-token; frequent ones are remembered, in bounded number."""

    def __init__(self, ranks_path: str | None = None, keep: int = 200_000):
        self.encode = _fast(ranks_path or Vocabulary().ranks_path).encode_ordinary
        self.known: dict[str, int] = {}
        self.keep = keep

    def __call__(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            n = len(self.encode(piece))
            if len(self.known) < self.keep and len(piece) < 64:
                self.known[piece] = n
        return n


class TokenTree:
    """Text with its pre-tokens in a tree of sums; ``edit`` returns how many were encoded anew."""

    def __init__(self, text: str, count: Counter, leaf: int = LEAF, lengths: np.ndarray | None = None, counts: np.ndarray | None = None):
        """``lengths`` and ``counts``: those of a stored tree, else the text is split and encoded."""
        self.text, self.count, self.leaf = text, count, leaf
        if lengths is None:
            pieces = _pattern().findall(text)
            lengths, counts = np.fromiter(map(len, pieces), np.uint32, len(pieces)), np.fromiter(map(count, pieces), np.uint32, len(pieces))
        self._plant(lengths, counts)

    def _plant(self, lengths: np.ndarray, counts: np.ndarray) -> None:
        k = self.leaf
        first = np.arange(0, len(lengths), k)
        self.leaves: list[tuple] = [(lengths[i : i + k], counts[i : i + k]) for i in first.tolist()] or [(lengths, counts)]
        self.size = 1
        while self.size < len(self.leaves):
            self.size *= 2
        self.chars, self.tokens = [0] * (2 * self.size), [0] * (2 * self.size)
        for sums, values in ((self.chars, lengths), (self.tokens, counts)):
            if len(first):
                sums[self.size : self.size + len(first)] = np.add.reduceat(values, first, dtype=np.int64).tolist()
        for i in range(self.size - 1, 0, -1):
            self._sum(i)

    def _leaf(self, i: int) -> tuple[list[int], list[int]]:
        lengths, counts = self.leaves[i]
        if not isinstance(lengths, list):
            lengths, counts = self.leaves[i] = lengths.tolist(), counts.tolist()
        return lengths, counts

    def stored(self) -> tuple[bytes, bytes]:
        """Lengths and counts of all pre-tokens, unsigned 32-bit, little-endian."""
        return tuple(b"".join(np.asarray(x[side], "<u4").tobytes() for x in self.leaves) for side in (0, 1))

    def _sum(self, i: int) -> None:
        self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
        self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    def total(self) -> int:
        return self.tokens[1]

    def _find(self, at: int) -> tuple[int, int]:
        """Leaf that holds character ``at`` and the leaf's first character."""
        i, first = 1, 0
        while i < self.size:
            i *= 2
            if at >= first + self.chars[i] and self.chars[i + 1]:
                first += self.chars[i]
                i += 1
        return min(i - self.size, len(self.leaves) - 1), first

    def edit(self, at: int, remove: int, insert: str) -> int:
        at = max(0, min(at, len(self.text)))
        remove = max(0, min(remove, len(self.text) - at))
        old_end, shift = at + remove, len(insert) - remove
        text = self.text[:at] + insert + self.text[old_end:]
        # The first pre-token that may have looked at the edit, or one before it.
        leaf, first = self._find(max(0, at - AHEAD))
        while leaf and first > max(0, at - AHEAD):
            leaf -= 1
            first -= sum(self._leaf(leaf)[0])
        lengths, counts = self._leaf(leaf)
        keep, begin = 0, first
        while keep < len(lengths) and begin + lengths[keep] + AHEAD <= at:
            begin += lengths[keep]
            keep += 1
        new_l, new_c = lengths[:keep], counts[:keep]
        # Old boundaries behind the edit, walked in step with the new split.
        old_leaf, old_at, k = leaf, begin, keep
        pos, fresh = begin, 0
        met = False
        for m in _pattern().finditer(text, begin):
            while old_at + shift < pos or old_at < old_end:
                while old_leaf < len(self.leaves) and k >= len(self.leaves[old_leaf][0]):
                    old_leaf, k = old_leaf + 1, 0
                if old_leaf >= len(self.leaves):
                    break
                old_at += self._leaf(old_leaf)[0][k]
                k += 1
            if pos > begin and old_at >= old_end and old_at + shift == pos and old_leaf < len(self.leaves):
                met = True
                break
            new_l.append(m.end() - m.start())
            new_c.append(self.count(m[0]))
            fresh += 1
            pos = m.end()
        rest = self._leaf(old_leaf) if met else ([], [])
        new_l, new_c = new_l + rest[0][k:], new_c + rest[1][k:]
        last = old_leaf if met else len(self.leaves) - 1
        self.text = text
        if last == leaf and len(new_l) <= 4 * self.leaf:
            self._set(leaf, new_l, new_c)
        elif len(new_l) <= 4 * self.leaf * (last - leaf + 1):
            n, span = len(new_l), last - leaf + 1
            for i in range(span):
                a, b = n * i // span, n * (i + 1) // span
                self._set(leaf + i, new_l[a:b], new_c[a:b])
        else:  # a large insertion: plant anew from the kept sums, without encoding
            whole = []
            for side, new in ((0, new_l), (1, new_c)):
                whole.append(np.concatenate([np.asarray(x, np.uint32) for x in (*(a[side] for a in self.leaves[:leaf]), new, *(b[side] for b in self.leaves[last + 1 :]))]))
            self._plant(*whole)
        return fresh

    def _set(self, i: int, lengths: list[int], counts: list[int]) -> None:
        self.leaves[i] = (lengths, counts)
        i += self.size
        self.chars[i], self.tokens[i] = sum(lengths), sum(counts)
        i //= 2
        while i:
            self._sum(i)
            i //= 2


_TREES = "doc_id long, row_key long, text string, n_tokens long, lengths binary, counts binary"
_EDITS = "array<struct<at:int,remove:int,insert:string>>"


def planted(docs: DataFrame, ranks_path: str | None = None) -> DataFrame:
    """A tree for each row: the table to store."""

    def run(batches):
        count = Counter(ranks_path)
        for b in batches:
            trees = [TokenTree(t.as_py() or "", count) for t in b.column("text")]
            kept = [t.stored() for t in trees]
            out = [b.column("doc_id"), b.column("row_key"), b.column("text"), pa.array([t.total() for t in trees], pa.int64()), *(pa.array([k[i] for k in kept], pa.binary()) for i in (0, 1))]
            yield pa.RecordBatch.from_arrays(out, [f.split()[0] for f in _TREES.split(", ")])

    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(text).alias("row_key"), text.alias("text")).mapInArrow(run, _TREES)


def store(docs: DataFrame, path: str, ranks_path: str | None = None) -> DataFrame:
    """Writes the trees of ``docs`` and reads them back."""
    planted(docs, ranks_path).write.option("compression", "zstd").parquet(path)
    return docs.sparkSession.read.schema(_TREES).parquet(path)


def edited(trees: DataFrame, edits: str = "edits", ranks_path: str | None = None) -> DataFrame:
    """Stored trees after their edits, in the form of the store, with ``n_before`` and ``n_encoded``
    (pre-tokens encoded anew). ``edits`` names an array column of (at, remove, insert), applied
    in order; positions refer to the text as the edits before have left it.
    """
    names = [f.split()[0] for f in _TREES.split(", ")]

    def run(batches):
        count = Counter(ranks_path)
        for b in batches:
            rows, size = [], 0
            for doc_id, key, text, n, lengths, counts, todo in zip(*(b.column(c) for c in (*names, "edits")), strict=True):
                lengths, counts = (np.frombuffer(x.as_py(), "<u4") for x in (lengths, counts))
                tree, fresh = TokenTree(text.as_py() or "", count, lengths=lengths, counts=counts), 0
                for e in todo.as_py() or []:
                    if e is not None:
                        fresh += tree.edit(e["at"] or 0, e["remove"] or 0, e["insert"] or "")
                rows.append((doc_id.as_py(), key.as_py(), tree.text, tree.total(), *tree.stored(), n.as_py(), fresh))
                size += 3 * len(tree.text)
                if size > 1 << 24:
                    yield batch(rows)
                    rows, size = [], 0
            if rows:
                yield batch(rows)

    def batch(rows):
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.int64()]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], [*names, "n_before", "n_encoded"])

    return trees.select(*names, F.col(edits).cast(_EDITS).alias("edits")).mapInArrow(run, _TREES + ", n_before long, n_encoded long")


def test_edits(n: int = 3):
    """Edits that follow from a row's id and length: an insertion, a deletion and a replacement."""
    def place(i):
        return F.pmod(F.xxhash64(F.lit(i), "doc_id"), F.greatest(F.char_length(F.coalesce("text", F.lit(""))), F.lit(1)).cast("long")).cast("int")

    kinds = [(0, " revised wording,"), (7, ""), (4, "it's 2024\n")]
    return F.array(*[F.struct(place(i).alias("at"), F.lit(kinds[i % 3][0]).alias("remove"), F.lit(kinds[i % 3][1]).alias("insert")) for i in range(n)])


test_edits.__test__ = False


def op7_result(docs: DataFrame) -> DataFrame:
    """Counts before and after edits of trees that went through the store."""
    trees = store(docs.select("doc_id", "text"), scratch(docs.sparkSession, "trees"))
    got = edited(trees.withColumn("edits", test_edits()))
    return got.select(
        "doc_id",
        F.col("n_before").alias("n_tokens"),
        F.col("n_tokens").alias("n_tokens_edited"),
        "n_encoded",
        F.char_length("text").cast("long").alias("n_chars_edited"),
        F.crc32(F.col("text").cast("binary")).alias("crc32_edited"),
    )

"""Public byte-level BPE vocabulary, loaded once a worker process; never trained here."""

from __future__ import annotations

import base64
import re
from functools import lru_cache

import numpy as np

JSON, RANKS = "byte_bpe_50k.json", "byte_bpe_50k.tiktoken"
END = 1  #: id that closes a document
SPECIAL = {"<|endoftext|>": 50256}

#: Characters whose classes are the same in every Unicode version that the two libraries may carry.
_PLAIN = re.compile("[^\x00-ɏͰ-ͳΈ-ϿЀ-ԯ‐-‧‰-⁞€]")
_LONG_RUN = 4096  #: longer texts without a space go to the library whose merge loop is a heap


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(maxsize=4)
def _fast(path: str):
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("public", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=SPECIAL)


@lru_cache(maxsize=4)
def _exact(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@lru_cache(maxsize=4)
def token_bytes(path: str) -> tuple[bytes, ...]:
    e = _fast(path)
    return tuple(e.decode_single_token_bytes(i) for i in range(e.n_vocab))


class Vocabulary:
    """Encodes as ``tokenizers`` does with ``add_special_tokens=False``.

    Both libraries hold the same ranks and pattern; the faster one serves texts of plain
    characters, the other everything else, so ids never depend on which one ran.
    """

    def __init__(self, json_path: str | None = None, ranks_path: str | None = None):
        self.json_path = json_path or vocabulary_path(JSON)
        self.ranks_path = ranks_path or vocabulary_path(RANKS)

    def encode(self, text: str) -> list[int]:
        if _PLAIN.search(text) or (len(text) > _LONG_RUN and max(map(len, re.split(r"\s", text))) > _LONG_RUN):
            return _exact(self.json_path).encode(text, add_special_tokens=False).ids
        return _fast(self.ranks_path).encode(text, allowed_special="all")

    def document(self, text: str | None) -> np.ndarray:
        return np.array([*self.encode(text or ""), END], np.uint32)

    def sentence_ends(self) -> np.ndarray:
        """For each id, whether its bytes end a sentence or line."""
        return _ends(self.ranks_path)


@lru_cache(maxsize=4)
def _ends(path: str) -> np.ndarray:
    return np.array([t.rstrip(b"\"')")[-1:] in (b".", b"!", b"?", b"\n") for t in token_bytes(path)])

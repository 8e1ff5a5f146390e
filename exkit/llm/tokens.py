"""Byte-level BPE of 50,257 ids, kept fast by remembering the ids of whole space-delimited chunks.

Ids equal those of the ``tokenizers`` file of the same vocabulary. The rank file
drives the encoder; texts that hold a special token's string go through
``tokenizers`` itself, which turns it into the special id.
"""

from __future__ import annotations

import base64
import re
from functools import lru_cache

import numpy as np
import public_tokenizers
import tiktoken
from tokenizers import Tokenizer

SPECIAL = "<|endoftext|>"
#: Where a space touches other white space, chunks between spaces do not encode alone.
TOUCHING = re.compile(r" \s|\s ")


class _Chunks(dict):
    """Little-endian ids of chunks, forgotten all at once when there are too many."""

    def __init__(self, encode, limit: int):
        super().__init__()
        self.encode, self.limit = encode, limit

    def __missing__(self, chunk: str) -> bytes:
        if len(self) >= self.limit:
            self.clear()
        ids = np.array(self.encode(chunk), "<u4").tobytes()
        if len(chunk) < 64:
            self[chunk] = ids
        return ids


class ByteBpe:
    def __init__(self, ranks: str, whole: str, remembered: int = 150_000):
        table = {base64.b64decode(t): int(n) for t, n in map(bytes.split, open(ranks, "rb"))}
        own = tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})
        self._plain, self._whole_path, self._whole = own.encode_ordinary, whole, None
        self._chunks = _Chunks(self._plain, remembered)

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit numbers."""
        if SPECIAL in text:
            self._whole = self._whole or Tokenizer.from_file(self._whole_path)
            return np.array(self._whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        if TOUCHING.search(text):
            return np.array(self._plain(text), "<u4").tobytes()
        first, *rest = text.split(" ")
        get = self._chunks.__getitem__
        return (get(first) if first else b"") + b"".join([get(" " + c) for c in rest])

    def count(self, text: str) -> int:
        return len(self.encode(text)) // 4


@lru_cache(maxsize=4)
def byte_bpe(ranks: str | None = None, whole: str | None = None) -> ByteBpe:
    """The encoder of a worker process; the vocabulary's paths are parameters."""
    return ByteBpe(ranks or public_tokenizers.path("byte_bpe_50k.tiktoken"), whole or public_tokenizers.path("byte_bpe_50k.json"))

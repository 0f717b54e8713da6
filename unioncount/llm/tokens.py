"""Byte-level BPE ids: loading a public vocabulary, encoding whole texts, counting pieces of pre-tokens.

The vocabulary file's path is a parameter; its content (of fixed size) is broadcast, so executors need no file.
"""

from __future__ import annotations

import base64
from pathlib import Path

import numpy as np

from .common import worker_cache

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: How byte-level vocabularies of this family split text: contractions, then runs of letters, digits, signs and blanks.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Entries after which a worker's cache of encoded chunks starts anew.
CACHE_ENTRIES = 1_500_000


def load_ranks(path: str = VOCABULARY) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in (line.split() for line in Path(path).read_bytes().splitlines() if line)}


def encoder(ranks: dict[bytes, int]):
    """The encoder of this worker process, made once."""
    cache = worker_cache("encoder")
    if cache.get("size") != len(ranks):
        import tiktoken

        cache["encoder"] = tiktoken.Encoding("bytes", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})
        cache["size"] = len(ranks)
    return cache["encoder"]


def id_type(ranks: dict[bytes, int]) -> str:
    return "<u2" if max(ranks.values(), default=0) < 1 << 16 else "<u4"


class ChunkEncoder(dict):
    """Serialised ids by chunk, where a chunk is a single blank and what follows it up to the next.

    The split pattern always cuts before a blank that is followed by another character than white space, so chunks
    encode on their own; texts with two blanks in a row or one at their end are encoded whole.
    """

    def __init__(self, ranks: dict[bytes, int]) -> None:
        super().__init__()
        self.encode = encoder(ranks).encode_ordinary
        self.dtype = id_type(ranks)

    def __missing__(self, chunk: str) -> bytes:
        value = np.array(self.encode(chunk), self.dtype).tobytes()
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        self[chunk] = value
        return value

    def ids(self, text: str) -> bytes:
        """Little-endian ids of a whole text."""
        if "  " in text or text.endswith(" "):
            return np.array(self.encode(text), self.dtype).tobytes()
        first, *rest = text.split(" ")
        get = self.__getitem__
        return (get(first) if first else b"") + b"".join([get(" " + x) for x in rest])


def chunk_encoder(ranks: dict[bytes, int]) -> ChunkEncoder:
    cache = worker_cache("chunks")
    if cache.get("size") != len(ranks):
        cache["chunks"], cache["size"] = ChunkEncoder(ranks), len(ranks)
    return cache["chunks"]

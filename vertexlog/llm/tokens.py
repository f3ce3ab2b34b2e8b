"""Token ids of whole texts with a public byte-level vocabulary, fast through a cache of words.

The splitting pattern of the vocabulary never joins what a single space separates, unless white space stands
beside that space.  A text without such places is therefore encoded word by word, each with the space before
it, and most words come from a cache.  Any other text goes through the tokenizer whole.  The ids are the same.
"""

from __future__ import annotations

import base64
import re
import sys
from array import array

import public_tokenizers
import tiktoken
from tokenizers import Tokenizer

_UNSAFE = re.compile(r"\s \s| \s|\s |<\|endoftext\|>")
_KEPT: dict[tuple[str, str], Encoder] = {}


def _packed(ids: list[int]) -> bytes:
    out = array("I", ids)
    if sys.byteorder == "big":
        out.byteswap()
    return out.tobytes()


class _Words(dict):
    """Ids of words as little-endian unsigned 32-bit bytes; forgets all when it has grown to ``most``."""

    def __init__(self, encode, before: str, most: int) -> None:
        super().__init__()
        self.encode, self.before, self.most = encode, before, most

    def __missing__(self, word: str) -> bytes:
        if len(self) >= self.most:
            self.clear()
        ids = self[word] = self.encode(self.before + word)
        return ids


class Encoder:
    """``ids(text)`` gives all ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, json_path: str, ranks_path: str, most: int = 400_000) -> None:
        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        bpe = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.whole = Tokenizer.from_file(json_path)
        encode = lambda text: _packed(bpe.encode_ordinary(text))
        self.first, self.spaced = _Words(encode, "", most // 8), _Words(encode, " ", most)

    def ids(self, text: str) -> bytes:
        if not text:
            return b""
        if _UNSAFE.search(text):
            return _packed(self.whole.encode(text, add_special_tokens=False).ids)
        head, *words = text.split(" ")
        return self.first[head] + b"".join(map(self.spaced.__getitem__, words))


def encoder(vocabulary: str = "byte_bpe_50k") -> Encoder:
    paths = public_tokenizers.path(f"{vocabulary}.json"), public_tokenizers.path(f"{vocabulary}.tiktoken")
    if paths not in _KEPT:
        _KEPT[paths] = Encoder(*paths)
    return _KEPT[paths]

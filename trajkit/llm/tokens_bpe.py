"""Exact token ids of the public 50k byte-level BPE vocabulary, fast for plain text.

``tiktoken`` with the same ranks gives the same ids several times faster. Texts with rare
characters, very long unbroken runs or the end marker's own string take the slower library, so
the ids always equal those of ``Tokenizer.encode(text, add_special_tokens=False)``.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import numpy as np

#: Outside Latin letters, usual punctuation and plain controls the two libraries' character tables may differ.
_UNUSUAL = re.compile("[\x00-\x08\x0e-\x1f\x7f-\x9f]|[^\x00-ɏ‐-‧€]|\\S{1000}|\\s{1000}")
_MARKER = "<|endoftext|>"
#: The vocabulary's word pattern always starts a new word at a single space between two letters, so a text may be cut before it.
_CUT = re.compile("[A-Za-z](?= [A-Za-z])")
#: Characters that are encoded at once.
PART = 1 << 18
_CACHE: dict = {}


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encoder(json_file: str = "byte_bpe_50k.json", rank_file: str = "byte_bpe_50k.tiktoken"):
    """A function text -> list of ids; one per Python worker."""
    if (json_file, rank_file) in _CACHE:
        return _CACHE[json_file, rank_file]
    import public_tokenizers
    import tiktoken

    slow: list = []  # loaded with the first text that needs it

    def careful(text: str) -> list[int]:
        if not slow:
            from tokenizers import Tokenizer

            slow.append(Tokenizer.from_file(vocabulary_path(json_file)))
        return slow[0].encode(text, add_special_tokens=False).ids

    with open(vocabulary_path(rank_file), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(text: str | None) -> list[int]:
        if not text:
            return []
        if _MARKER in text or _UNUSUAL.search(text):
            return careful(text)
        return fast.encode_ordinary(text)

    _CACHE[json_file, rank_file] = encode
    return encode


def parts(text: str) -> Iterator[str]:
    """The text in parts of about ``PART`` characters whose ids, one after another, are the ids of the whole."""
    at = 0
    while len(text) - at > 2 * PART and (cut := _CUT.search(text, at + PART)):
        yield text[at : cut.end()]
        at = cut.end()
    yield text[at:] if at else text


def id_arrays(json_file: str = "byte_bpe_50k.json"):
    """A function text -> arrays of 32-bit ids, in order; lists of ids exist for one part at a time only."""
    encode = encoder(json_file)

    def arrays(text: str | None) -> Iterator[np.ndarray]:
        for part in parts(text or ""):
            found = encode(part)
            yield np.fromiter(found, "<u4", len(found))

    return arrays

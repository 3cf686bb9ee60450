"""Token ids of whole texts under a public byte-level vocabulary file.

The vocabulary file of the ``tokenizers`` library is read; its merges are applied by
the rank encoder of ``tiktoken``, which yields the same ids several times
faster (held against ``tokenizers`` itself in the tests). As ``tokenizers`` does by default, the string of an
added token (such as the end-of-text token) that occurs in a text becomes that token's id.
"""

from __future__ import annotations

import functools
import json

import numpy as np

VOCABULARY = "byte_bpe_50k.json"


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_of_symbol() -> dict[str, int]:
    """Byte-level vocabularies write a byte as itself where it prints, and as the
    next free code point from 256 on where it doesn't."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {chr(b): b for b in plain}
    rest = [b for b in range(256) if b not in set(plain)]
    return table | {chr(256 + k): b for k, b in enumerate(rest)}


@functools.lru_cache(maxsize=2)
def encoder(path: str):
    import public_tokenizers
    import tiktoken

    with open(path, encoding="utf-8") as f:
        model = json.load(f)
    added = model.get("added_tokens", [])
    if any(t["single_word"] or t["lstrip"] or t["rstrip"] or t["normalized"] or " " in t["content"] for t in added):
        raise ValueError("added tokens that take in what is beside them, or hold a space, are not supported")
    table, special = byte_of_symbol(), {t["content"]: t["id"] for t in added}
    ranks = {bytes(table[c] for c in token): rank for token, rank in model["model"]["vocab"].items() if rank not in special.values()}
    return tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)


def _ids(own, text: str) -> list[int]:
    if any(t in text for t in own.special_tokens_set):
        return own.encode(text, allowed_special="all")
    return own.encode_ordinary(text)


PART = 1 << 16


def encode(text: str | None, path: str) -> np.ndarray:
    """Ids of a whole text as little-endian unsigned 32-bit numbers; none for null.

    Long texts are encoded in parts that end between a non-space and a single space followed
    by a letter: the pattern always starts a new piece there, so the ids are those of the whole."""
    if not text:
        return np.zeros(0, dtype="<u4")
    own = encoder(path)
    if len(text) <= PART:
        return np.array(_ids(own, text), dtype="<u4")
    parts, start = [], 0
    while start < len(text):
        end = _break(text, start + PART)
        parts.append(np.array(_ids(own, text[start:end]), dtype="<u4"))
        start = end
    return np.concatenate(parts)


def _break(text: str, at: int) -> int:
    while at < len(text):
        at = text.find(" ", at)
        if at < 0:
            break
        if at and text[at - 1].isascii() and text[at - 1].isalnum() and at + 1 < len(text) and text[at + 1].isascii() and text[at + 1].isalpha():
            return at
        at += 1
    return len(text)

"""Byte-level BPE encoders of public vocabulary files, kept per process."""

from __future__ import annotations

import base64
from functools import lru_cache


def vocabulary(name: str) -> str:
    """The place of a public vocabulary file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def json_ranks(path: str) -> dict[bytes, int]:
    """Bytes to id of a byte-level vocabulary in JSON, without its special tokens."""
    import json

    with open(path, encoding="utf-8") as f:
        found = json.load(f)
    special = {t["content"] for t in found.get("added_tokens", [])}
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    byte_of = {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(hidden)}
    return {bytes(byte_of[c] for c in token): i for token, i in found["model"]["vocab"].items() if token not in special}


@lru_cache(maxsize=4)
def fast_encoder(path: str, pattern: str):
    """An encoder for texts as ordinary text, equal to the library that owns the file's format."""
    import tiktoken

    ranks = json_ranks(path) if path.endswith(".json") else read_ranks(path)
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def default_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN

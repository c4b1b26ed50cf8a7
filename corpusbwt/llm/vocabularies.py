"""Public tokenizer vocabularies, loaded once per Python worker; their paths are parameters."""

from __future__ import annotations

import base64
from functools import cache

import public_tokenizers
import tiktoken


def default_path(name: str) -> str:
    return public_tokenizers.path(name)


@cache
def ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as file:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, file)}


@cache
def byte_units() -> dict[str, int]:
    """Characters by which the byte-level JSON files write bytes: printable Latin-1 stands for itself, the rest is moved up."""
    kept = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    moved = [b for b in range(256) if b not in set(kept)]
    return {chr(b): b for b in kept} | {chr(256 + i): b for i, b in enumerate(moved)}


@cache
def piece_encoder(path: str) -> tiktoken.Encoding:
    """Encodes single pieces by the vocabulary of a byte-level JSON file; ranks are ids, as its merges are in id order."""
    import json

    with open(path, encoding="utf-8") as file:
        vocabulary = json.load(file)["model"]["vocab"]
    unit = byte_units()
    table = {bytes(unit[c] for c in token): i for token, i in vocabulary.items()}
    return tiktoken.Encoding("pieces", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})

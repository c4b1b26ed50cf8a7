"""Ids of whole texts by a byte-level vocabulary: pieces found by array scans, each distinct piece encoded once per worker."""

from __future__ import annotations

import re
from functools import cache

import numpy as np

from corpusbwt.llm import textscan, vocabularies


class PieceTokenizer:
    """Encodes texts as the library for the JSON file does, added special strings included, as ids without extra ones.

    A table of pieces met so far (at most ``most_pieces``; it starts anew beyond that) maps a piece's 64-bit hash to its
    ids, so the merge loop runs for distinct pieces only.
    """

    def __init__(self, path: str, most_pieces: int = 1 << 20):
        import json

        self.most = most_pieces
        self.encoder = vocabularies.piece_encoder(path)
        with open(path, encoding="utf-8") as file:
            self.special = {t["content"]: t["id"] for t in json.load(file)["added_tokens"]}
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self._reset()

    def _reset(self) -> None:
        self.index = textscan.HashIndex()
        self.ids = np.zeros(1 << 16, np.uint32)
        self.start = np.zeros(1 << 16, np.int64)
        self.count = np.zeros(1 << 16, np.int64)
        self.pieces = self.used = 0

    def _learn(self, hashes: np.ndarray, pieces: list[str]) -> None:
        found = [self.encoder._encode_single_piece(p.encode()) for p in pieces]
        counts = np.fromiter(map(len, found), np.int64, len(found))
        need, n = self.used + int(counts.sum()), self.pieces + len(found)
        if need > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros(need, np.uint32)])
        if n > len(self.start):
            self.start, self.count = (np.concatenate([x, np.zeros(n, np.int64)]) for x in (self.start, self.count))
        self.ids[self.used : need] = np.fromiter((i for x in found for i in x), np.uint32, need - self.used)
        self.start[self.pieces : n] = self.used + np.cumsum(counts) - counts
        self.count[self.pieces : n] = counts
        self.index.add(hashes, np.arange(self.pieces, n))
        self.pieces, self.used = n, need

    def _encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Ids, ids of each text, piece hashes and pieces of each text."""
        codes, bounds = textscan.codes_of(texts)
        starts = textscan.byte_level_starts(codes, bounds)
        ends = np.append(starts[1:], len(codes)) if len(starts) else starts
        hashes = textscan.span_hashes(codes, starts, ends)
        if self.pieces > self.most:
            self._reset()
        at, new = textscan.new_pieces(self.index, hashes)
        if len(new):
            self._learn(hashes[new], [textscan.text_piece(codes, s, e) for s, e in zip(starts[new], ends[new], strict=True)])
            at = self.index.find(hashes)
        count = self.count[at]
        ids = self.ids[textscan.spread(self.start[at], count)]
        total = np.concatenate([[0], np.cumsum(count)])
        edge = np.searchsorted(starts, bounds)
        return ids, np.diff(total[edge]), hashes, np.diff(edge)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """As ``_encode``, with special strings inside a text as their own ids."""
        if self.cut is None or not any(s in t for t in texts for s in self.special):
            return self._encode(texts)
        parts, owner = [], []
        for i, text in enumerate(texts):
            for part in self.cut.split(text):
                parts.append(part)
                owner.append(i)
        plain = [p if p not in self.special else "" for p in parts]
        ids, per, hashes, pieces = self._encode(plain)
        marks = np.array([self.special.get(p, -1) for p in parts], np.int64)
        at = (np.cumsum(per) - per)[marks >= 0]
        ids = np.insert(ids, at, marks[marks >= 0].astype(np.uint32))
        per = per + (marks >= 0)
        n = len(texts)
        sums = lambda x: np.bincount(owner, weights=x, minlength=n).astype(np.int64)
        return ids, sums(per), hashes, sums(pieces)


@cache
def tokenizer(path: str) -> PieceTokenizer:
    return PieceTokenizer(path)

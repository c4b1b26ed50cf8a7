"""Token counts by compiled transducers for a lower-casing BPE vocabulary with word ends.

Two deterministic machines replace the tokenizer. The first reads character classes and marks where words begin; a chunk
of text is a map from its first state to its last, and the maps of all chunks compose by a parallel prefix scan, so no
chunk waits for the one before it. The second is a transducer over bytes, compiled from the merges for the states that are
met: its arcs carry the number of tokens that become certain by a byte. Every word starts it anew, so the map of a word is
constant and texts' counts compose by a prefix sum; words longer than a chunk are cut, and the maps of their chunks are
joined. Words of all lengths go this way. Counts are the library's own; there is no approximation.
"""

from __future__ import annotations

import json
import re
import unicodedata
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from corpusbwt.llm import textscan, vocabularies
from corpusbwt.llm.common import batch_of, texts_of, trimmed

# Symbol classes and states of the machine that finds words.
BLANK, LETTER, DIGIT, SIGN, QUOTE, ENDS_ONE, OPENS_E, OPENS_L, CLOSES_E = range(9)
GAP, WORD, NUMERAL, SIGNS, QUOTED, QUOTED_E, QUOTED_L, CONTRACTED = range(8)
#: A mark says that a word starts here, or (a state later, when that has become certain) at the symbol before.
HERE, BEFORE = 1, 2
CHUNK = 256


@cache
def machine() -> tuple[np.ndarray, np.ndarray]:
    """Next state and marks by state * 9 + class."""
    letters = (LETTER, ENDS_ONE, OPENS_E, OPENS_L, CLOSES_E)
    to = np.zeros((8, 9), np.uint8)
    mark = np.zeros((8, 9), np.uint8)
    for state in range(8):
        for symbol, target in ((BLANK, GAP), (DIGIT, NUMERAL), (SIGN, SIGNS), (QUOTE, QUOTED), *((x, WORD) for x in letters)):
            to[state, symbol] = target
            mark[state, symbol] = HERE if symbol != BLANK else 0
    for x in letters:  # a run of letters is one word
        mark[WORD, x] = 0
    for state in (SIGNS, QUOTED):  # a run of signs is one word
        for x in (SIGN, QUOTE):
            to[state, x], mark[state, x] = SIGNS, 0
    for x, target in ((ENDS_ONE, CONTRACTED), (OPENS_E, QUOTED_E), (OPENS_L, QUOTED_L)):
        to[QUOTED, x], mark[QUOTED, x] = target, 0
    for state, wanted in ((QUOTED_E, CLOSES_E), (QUOTED_L, OPENS_L)):
        mark[state] = mark[WORD] | BEFORE  # no contraction: its letter had begun a run of letters
        to[state, wanted], mark[state, wanted] = CONTRACTED, 0
    return to.ravel(), mark.ravel()


@cache
def symbol_classes() -> np.ndarray:
    kinds = np.array([BLANK, LETTER, DIGIT, SIGN], np.uint8)[textscan.classes()]
    kinds[ord("'")] = QUOTE
    for chars, kind in (("stmd", ENDS_ONE), ("rv", OPENS_E), ("l", OPENS_L), ("e", CLOSES_E)):
        kinds[[ord(c) for c in chars]] = kind
    return kinds


def chunk_maps(symbols: np.ndarray) -> np.ndarray:
    """State maps (chunks, 8) of chunks (symbols by chunk): where each chunk ends from every state it may start in."""
    to, _ = machine()
    state = np.tile(np.arange(8, dtype=np.uint8), (symbols.shape[1], 1))
    for row in symbols:
        state = to[state * np.uint8(9) + row[:, None]]
    return state


def scanned(maps: np.ndarray) -> np.ndarray:
    """Prefix compositions of state maps by doubling: the i-th is all maps up to and with the i-th, applied in order."""
    out, step = maps.copy(), 1
    while step < len(out):
        out[step:] = np.take_along_axis(out[step:], out[:-step].astype(np.intp), 1)
        step *= 2
    return out


def word_marks(codes: np.ndarray) -> np.ndarray:
    """Whether a word starts at each symbol; the text is read from a gap and ends in one."""
    n = len(codes)
    lanes = -(-n // CHUNK)
    padded = np.zeros(lanes * CHUNK, np.uint8)
    padded[:n] = symbol_classes()[codes]
    symbols = np.ascontiguousarray(padded.reshape(lanes, CHUNK).T)
    state = np.full(lanes, GAP, np.uint8)
    state[1:] = scanned(chunk_maps(symbols))[:-1, GAP]
    to, mark = machine()
    marks = np.empty_like(symbols)
    for i, row in enumerate(symbols):
        at = state * np.uint8(9) + row
        marks[i] = mark[at]
        state = to[at]
    flat = marks.T.ravel()
    begins = (flat & HERE) != 0
    begins[:-1] |= (flat[1:] & BEFORE) != 0
    return begins[:n]


class Merges:
    """The merge list: which strings are tokens, and which two tokens may stand side by side in an encoding.

    A row of tokens is what the merges leave of a word if each token is left of its own bytes and each two neighbours
    agree, that is, no merge across their border comes before the merges that use up the border's sides.
    """

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            told = json.load(file)
        model = told["model"]
        self.special = [t["content"] for t in told["added_tokens"]]
        ids, suffix = model["vocab"], model["end_of_word_suffix"]
        byte_of = vocabularies.byte_units()
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.parts: dict[int, tuple[int, int, int]] = {}
        self.rank: dict[tuple[int, int], int] = {}
        #: Tokens by their bytes: inside a word, and at its end.
        self.inner: dict[bytes, int] = {}
        self.final: dict[bytes, int] = {}
        for c, b in byte_of.items():
            self.inner[bytes((b,))], self.final[bytes((b,))] = ids[c], ids[c + suffix]
        raw = {t: w for held in (self.inner, self.final) for w, t in held.items()}
        sound = set(raw)
        for at, (a, b) in enumerate(pairs):
            left, right, made = ids[a], ids[b], ids[a + b]
            if made in raw or left not in raw or right not in raw:
                raise ValueError("a merge makes a token twice, or before its parts")
            self.parts[made], self.rank[left, right] = (at, left, right), at
            raw[made] = raw[left] + raw[right]
            if left in sound and right in sound and self._apart(left, right):
                sound.add(made)
                (self.final if b.endswith(suffix) else self.inner)[raw[made]] = made
        self.prefixes = {w[:n] for held in (self.inner, self.final) for w in held for n in range(1, len(w))}
        self.known: dict[tuple[int, int], bool] = {}

    def _apart(self, a: int, b: int) -> bool:
        """Whether both tokens get made side by side before any merge across their border."""
        never = len(self.parts) + 1
        sides = []
        for token, side in ((a, 2), (b, 1)):  # the tokens that lie at the border in turn, and when each is used up
            steps = [(token, never)]
            while (made := self.parts.get(steps[-1][0])) is not None:
                steps.append((made[side], made[0]))
            sides.append(steps)
        left, right = sides
        while len(left) > 1 or len(right) > 1:
            (x, x_ends), (y, y_ends) = left[-1], right[-1]
            across = self.rank.get((x, y), never)
            if across < x_ends and across <= y_ends:  # at equal rank the leftmost pair goes first
                return False
            (left if x_ends <= y_ends else right).pop()
        return True

    def agree(self, a: int, b: int) -> bool:
        found = self.known.get((a, b))
        if found is None:
            found = self.known[a, b] = (a, b) not in self.rank and self._apart(a, b)
        return found


class WordTransducer:
    """The merges as one deterministic machine over bytes (a word's last byte is a symbol of its own).

    A state is what the bytes read so far leave open: the last token that every continuation keeps, and the bytes after
    it, with the token that ends at each of them. An arc carries the number of tokens that became certain by its symbol;
    the arc of a last byte emits the rest and leads back to the start. States and arcs are compiled when first met.

    Words are cut into chunks of ``SPAN`` bytes, which all run in step. A chunk's map is tabulated at the states that the
    chunk before may end in, from a guess on, until the maps join up; the emitted counts are then summed by a scan.
    """

    SPAN = 64
    START, NONE, EDGE = 0, -1, -2

    def __init__(self, path: str, most_states: int = 1 << 18):
        self.merges, self.most = Merges(path), most_states
        self._reset()

    def _reset(self) -> None:
        self.arcs = textscan.HashIndex()
        self.to, self.emits, self.made = np.zeros(1 << 12, np.int64), np.zeros(1 << 12, np.int64), 0
        self.held = [(b"", (self.EDGE,), (0,))]
        self.state_of = {(self.EDGE, b""): self.START}
        self.merges.known.clear()

    def _arc(self, state: int, symbol: int) -> tuple[int, int]:
        """Where a symbol leads from a state, and the tokens it emits."""
        pending, last, parent = self.held[state]
        grown = pending + bytes((symbol & 255,))
        tokens, agree = (self.merges.final if symbol > 255 else self.merges.inner), self.merges.agree

        def tokens_before(place: int) -> int:
            n = 0
            while place:
                place, n = parent[place], n + 1
            return n

        place, token = next((p, t) for p, a in enumerate(last) if a != self.NONE and (t := tokens.get(grown[p:])) is not None and (a == self.EDGE or agree(a, t)))
        if symbol > 255:
            return self.START, tokens_before(place) + 1
        last, parent, end = (*last, token), (*parent, place), len(grown)
        meet = {p for p in range(end) if last[p] != self.NONE and grown[p:] in self.merges.prefixes} | {end}
        while len(meet) > 1:  # the last place that lies on the way to each start of a later token
            top = max(meet)
            meet.remove(top)
            meet.add(parent[top])
        root = meet.pop()
        key = last[root], grown[root:]
        found = self.state_of.get(key)
        if found is None:
            found = self.state_of[key] = len(self.held)
            kept, ways = [last[root]], [0]
            for p in range(root + 1, end + 1):
                on = last[p] != self.NONE and parent[p] >= root and kept[parent[p] - root] != self.NONE
                kept.append(last[p] if on else self.NONE)
                ways.append(parent[p] - root if on else 0)
            self.held.append((grown[root:], tuple(kept), tuple(ways)))
        return found, tokens_before(root)

    def _run(self, symbols: np.ndarray, starts: np.ndarray, sizes: np.ndarray, state: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Last state and emitted tokens of chunks that start in the given states, all in step."""
        state, told = state.copy(), np.zeros(len(starts), np.int64)
        order = np.argsort(-sizes, kind="stable")
        falling = -sizes[order]
        for i in range(int(sizes.max(initial=0))):
            on = order[: np.searchsorted(falling, -i, "left")]
            key = (state[on] << 9) | symbols[starts[on] + i]
            arc = self.arcs.find(textscan.mix(key.astype(np.uint64)))
            miss = np.flatnonzero(arc < 0)
            if len(miss):
                fresh, back = np.unique(key[miss], return_inverse=True)
                n = self.made + len(fresh)
                if n > len(self.to):
                    self.to, self.emits = (np.concatenate([x, np.zeros(n, np.int64)]) for x in (self.to, self.emits))
                new = np.arange(self.made, n)
                self.to[new], self.emits[new] = np.array([self._arc(k >> 9, k & 511) for k in fresh.tolist()]).T
                self.arcs.add(textscan.mix(fresh.astype(np.uint64)), new)
                self.made = n
                arc[miss] = new[back]
            state[on] = self.to[arc]
            told[on] += self.emits[arc]
        return state, told

    def counts(self, words: list[bytes]) -> np.ndarray:
        """Number of tokens of each non-empty word."""
        if not words:
            return np.zeros(0, np.int64)
        if len(self.held) > self.most:
            self._reset()
        size = np.fromiter(map(len, words), np.int64, len(words))
        ends = np.cumsum(size)
        symbols = np.frombuffer(b"".join(words), np.uint8).astype(np.int64)
        symbols[ends - 1] += 256
        chunks = -(-size // self.SPAN)
        after = np.cumsum(chunks)
        owner = np.repeat(np.arange(len(words)), chunks)
        starts = (ends - size)[owner] + (np.arange(after[-1]) - (after - chunks)[owner]) * self.SPAN
        sizes = np.minimum(ends[owner] - starts, self.SPAN)
        told = np.zeros(len(starts), np.int64)
        alone = chunks[owner] == 1
        told[alone] = self._run(symbols, starts[alone], sizes[alone], np.zeros(alone.sum(), np.int64))[1]
        joined = np.flatnonzero(~alone)
        if len(joined):
            told[joined] = self._joined(symbols, starts[joined], sizes[joined], owner[joined])
        return np.diff(np.concatenate([[0], np.cumsum(told)])[np.concatenate([[0], after])])

    def _joined(self, symbols: np.ndarray, starts: np.ndarray, sizes: np.ndarray, owner: np.ndarray) -> np.ndarray:
        """Emitted tokens of chunks of long words, each from the state in which the chunk before ends."""
        text: dict[bytes, int] = {}
        kind = [text.setdefault(symbols[a : a + n].tobytes(), i) for i, (a, n) in enumerate(zip(starts.tolist(), sizes.tolist(), strict=True))]
        opens = np.concatenate([[True], owner[1:] != owner[:-1]]).tolist()
        maps: dict[tuple[int, int], tuple[int, int]] = {}
        wanted = dict.fromkeys((k, self.START) for k in kind)
        while wanted:
            at = np.array(list(wanted), np.int64)
            ends, told = self._run(symbols, starts[at[:, 0]], sizes[at[:, 0]], at[:, 1])
            maps.update(zip(wanted, zip(ends.tolist(), told.tolist(), strict=True), strict=True))
            wanted, out, state = {}, [], self.START
            for k, opened in zip(kind, opens, strict=True):
                entry = (k, self.START if opened else state)
                found = maps.get(entry)
                if found is None:  # asked for in the next turn; what follows goes on from a guess
                    wanted[entry] = None
                    found = maps[k, self.START]
                state = found[0]
                out.append(found[1])
        return np.array(out, np.int64)

    def span_counts(self, codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Tokens of each word of a text, equal words read once."""
        if not len(starts):
            return np.zeros(0, np.int64)
        _, one, back = np.unique(textscan.span_hashes(codes, starts, ends), return_index=True, return_inverse=True)
        words = [textscan.text_piece(codes, a, b).encode("utf-8", "surrogatepass") for a, b in zip(starts[one].tolist(), ends[one].tolist(), strict=True)]
        return self.counts(words)[back]


@cache
def transducer(path: str) -> WordTransducer:
    return WordTransducer(path)


def normalised(text: str) -> str:
    """NFC, then lower case character by character (no final-sigma rule)."""
    if not text.isascii() and not unicodedata.is_normalized("NFC", text):
        text = unicodedata.normalize("NFC", text)
    return (text.replace("Σ", "σ") if "Σ" in text else text).lower()


def count_texts(texts: list[str], path: str) -> np.ndarray:
    """Tokens of each text as the library for the JSON file counts them; its special strings count one each."""
    machine_ = transducer(path)
    special = machine_.merges.special
    extra = np.zeros(len(texts), np.int64)
    plain = []
    for i, text in enumerate(texts):
        if "<|" in text and any(s in text for s in special):
            parts = re.split("|".join(map(re.escape, special)), text)
            extra[i] = len(parts) - 1
            text = " ".join(map(normalised, parts))
        else:
            text = normalised(text)
        plain.append(text + " ")
    codes, bounds = textscan.codes_of(plain)
    begins = word_marks(codes)
    starts = np.flatnonzero(begins)
    stops = np.append(np.flatnonzero(begins | (symbol_classes()[codes] == BLANK)), len(codes))
    ends = stops[np.searchsorted(stops, starts, "right")]
    found = np.concatenate([[0], np.cumsum(machine_.span_counts(codes, starts, ends))])
    return np.diff(found[np.searchsorted(starts, bounds)]) + extra


def token_counts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, path: str | None = None, limit: int = 2048) -> DataFrame:
    """Per row: doc_id, n_bytes (UTF-8), n_tokens, over_limit (n_tokens > limit).

    A null text counts as an empty one: no bytes, no tokens. Rows are kept as they come, with null or repeated ids; an
    empty table gives no rows.
    """
    where = path or vocabularies.default_path("word_bpe_49k.json")
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            schema = pa.schema([("doc_id", batch.schema.types[0]), ("n_bytes", pa.int64()), ("n_tokens", pa.int64()), ("over_limit", pa.bool_())])
            texts = texts_of(batch.column(1))
            for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
                found = count_texts(texts[lo:hi], where)
                yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), [len(t.encode()) for t in texts[lo:hi]], found, found > limit])

    return df.select(id_col, text_col).mapInArrow(trimmed(run), f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean")

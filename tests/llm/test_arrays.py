"""Array parts of the operators against the libraries, brute force and exact round trips; no Spark."""

import random
import unicodedata

import numpy as np
import public_tokenizers as vocab
import pytest
import regex
import tiktoken
from tokenizers import Tokenizer

from corpusbwt.llm import byte_bpe, licenses, media, near_dedup, packing, piece_tokens, quality, textscan, token_counts, url_filter, vector_graph, vocabularies, webp

ODD = "a b'srelvtmdLRΣς\n\t 1²é!\u00a0 　日'İ\x1c\x85|#"


def odd_texts(n=2000):
    rng = random.Random(1)
    made = ["".join(rng.choice(ODD) for _ in range(rng.randint(0, 30))) for _ in range(n)]
    return [*made, "", "a" * 3000, "ab" * 700, "<|endoftext|> x it's", "don't we'll they're '' 're 'rx 'lx", "x<|startoftext|>y'", "The same. " * 3000]


def test_pieces_follow_the_pattern():
    pattern = regex.compile(vocab.PATTERN)
    texts = odd_texts()
    codes, bounds = textscan.codes_of(texts)
    starts = textscan.byte_level_starts(codes, bounds)
    ends = np.append(starts[1:], len(codes))
    assert [textscan.text_piece(codes, a, b) for a, b in zip(starts, ends, strict=True)] == [w for t in texts for w in pattern.findall(t)]


def test_hash_index():
    rng = np.random.default_rng(0)
    keys = np.unique(rng.integers(1 << 63, size=50_000, dtype=np.uint64))
    index = textscan.HashIndex(4)
    for part in np.array_split(keys, 7):
        index.add(part, np.searchsorted(keys, part))
    assert (index.find(keys) == np.arange(len(keys))).all()
    assert (index.find(keys + np.uint64(1))[~np.isin(keys + np.uint64(1), keys)] == -1).all()


def test_piece_tokenizer_is_the_library():
    path = vocab.path("byte_bpe_50k.json")
    library, texts = Tokenizer.from_file(path), odd_texts()
    ids, per, _, _ = piece_tokens.PieceTokenizer(path, most_pieces=500).encode(texts)
    cut = np.split(ids, np.cumsum(per)[:-1])
    assert [c.tolist() for c in cut] == [x.ids for x in library.encode_batch(texts, add_special_tokens=False)]


def test_counts_are_the_library_s():
    path = vocab.path("word_bpe_49k.json")
    texts = odd_texts()
    want = [len(x.ids) for x in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    assert token_counts.count_texts(texts, path).tolist() == want


def test_chunk_maps_compose():
    rng = np.random.default_rng(2)
    symbols = rng.integers(0, 9, (token_counts.CHUNK, 12)).astype(np.uint8)
    whole = token_counts.chunk_maps(symbols.T.reshape(1, -1).T.reshape(-1, 1))
    assert (token_counts.scanned(token_counts.chunk_maps(symbols))[-1] == whole[0]).all()


def test_words_of_any_length_pass_the_transducer():
    path = vocab.path("word_bpe_49k.json")
    rng = random.Random(5)
    letters = ["a", "ab", "aab", "theing", "eé日", "abcdefghijklmnopqrstuvwxyz", "0", "=-", "!"]
    texts = [c * n for c in letters for n in (1, 2, 3, 63, 64, 65, 127, 128, 129, 1000, 20_000)]
    texts += ["".join(rng.choice(c) for _ in range(n)) for c in letters for n in (5, 64, 300, 5000)]
    library = Tokenizer.from_file(path)
    want = [len(x.ids) for x in library.encode_batch(texts, add_special_tokens=False)]
    assert token_counts.count_texts(texts, path).tolist() == want
    small = token_counts.WordTransducer(path, most_states=50)  # states are dropped on the way
    words = [t.encode() for t in texts if t.isascii() and t.isalpha()]
    for _ in range(2):
        assert [small.counts([w])[0] for w in words] == [len(library.encode(w.decode(), add_special_tokens=False).ids) for w in words]


def test_recursive_bpe_is_the_library():
    path = vocab.path("byte_bpe_50k.tiktoken")
    library = tiktoken.Encoding("own", pat_str=vocab.PATTERN, mergeable_ranks=vocabularies.ranks(path), special_tokens={})
    texts = odd_texts(400)
    book = byte_bpe.PieceBook(path)
    at, first = book.look_up(texts)
    for i, text in enumerate(texts):
        own = at[first[i] : first[i + 1]].tolist()
        assert " ".join(map(book.ids.__getitem__, own)) == " ".join(map(str, library.encode_ordinary(text)))
        assert b"".join(map(book.raw.__getitem__, own)) == text.encode()


def test_long_pieces_contract_as_in_the_library():
    path = vocab.path("byte_bpe_50k.tiktoken")
    library = tiktoken.Encoding("own", pat_str=vocab.PATTERN, mergeable_ranks=vocabularies.ranks(path), special_tokens={})
    engine = byte_bpe.DuckBpe(path)
    rng = np.random.default_rng(8)
    pieces = [rng.choice(list(letters), n).astype(np.uint8).tobytes() for letters in (b"abcdefghijklmnopqrstuvwxyz", b"aestin", b"a", range(256)) for n in (1, 64, 65, 300, 2000)]
    pieces += [b" " * n for n in (2, 63, 64, 65, 1001)] + [b"=" * 777, "日本語の長い文".encode() * 200]
    ids, counts = engine.encode([*pieces, b""])
    assert [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])] == [*map(library._encode_single_piece, pieces), []]
    ids, counts = engine.encode(list(engine.ranks))
    assert ids.tolist() == list(engine.ranks.values())
    assert engine.encode([])[0].size == 0


def test_hilbert_curve_visits_neighbours():
    side = np.arange(8)
    grid = np.stack(np.meshgrid(side, side, side), -1).reshape(-1, 3)
    key = packing.hilbert_key(grid, 3)
    assert sorted(key) == list(range(512))
    assert (np.abs(np.diff(grid[np.argsort(key)], axis=0)).sum(1) == 1).all()


@pytest.mark.parametrize("transforms", [(), ("subtract_green",), ("predictor",), ("cross_colour",), ("predictor", "cross_colour", "subtract_green")])
@pytest.mark.parametrize("cache_bits", [0, 5])
def test_webp_round_trip(transforms, cache_bits):
    rng = np.random.default_rng(0)
    for height, width, values in ((1, 1, 256), (7, 5, 3), (33, 21, 256), (9, 40, 2)):
        for meta_shift in (0, 2):
            pixels = rng.integers(0, values, (height, width, 4)).astype(np.uint8)
            data = webp.encode(pixels, transforms=transforms, cache_bits=cache_bits, meta_shift=meta_shift)
            assert (webp.decode(data)[0] == pixels).all()


def test_webp_palettes_and_broken_streams():
    rng = np.random.default_rng(1)
    for n in (1, 2, 4, 16, 200):
        table = rng.integers(0, 256, (n, 4)).astype(np.uint8)
        pixels = table[rng.integers(0, n, (13, 17))]
        assert (webp.decode(webp.encode(pixels, transforms=("palette",)))[0] == pixels).all()
    with pytest.raises(webp.WebpError):
        webp.decode(b"RIFF....")


def test_a_stream_put_together_by_hand():
    """One opaque pixel (red 1, green 2, blue 3): five codes of one symbol each, so the pixel itself takes no bits."""
    w = webp.Writer()
    for value, bits in ((0x2F, 8), (0, 14), (0, 14), (0, 1), (0, 3), (0, 1), (0, 1), (0, 1)):
        w.put(value, bits)
    for symbol in (2, 1, 3, 255, 0):
        for value, bits in ((1, 1), (0, 1), (1, 1), (symbol, 8)):
            w.put(value, bits)
    data = webp.riff(w.value.to_bytes(-(-w.size // 8), "little"))
    assert webp.decode(data)[0].tolist() == [[[255, 1, 2, 3]]]


@pytest.mark.parametrize("text", ["", "a", "é" * 1_300_000, "\x00\x7f ü日 " * 99, "The quick brown fox. " * 2000])
def test_media_hold_the_payload(text):
    payload = media.payload_of(text)
    assert len(payload) % 576 == 0 and payload.startswith(text.encode())
    pixels = media.pixels_of(media.stored(payload))
    assert np.ascontiguousarray(pixels[..., 1:]).tobytes() == payload


@pytest.mark.parametrize("text", ["", "\0" * 577, "ab" * 3000, "abc" * 3000, "x" * 600_000, "The same line here.\n" * 500, " ".join(odd_texts(9000))])
def test_stored_references_are_read_alike_pixel_by_pixel(text):
    payload = media.payload_of(text)
    own = len(payload) >= media.OWN_CODE
    data = webp.encode_bytes(payload, media.WIDTH, len(payload) // media.UNIT, own_code=own)
    r = webp.Reader(data[20:], 43)
    group = webp._read_group(r, 0)
    assert group[0].lengths[webp.LITERALS :].any()
    pixels = webp._general(r, [group], None, 0, 0, media.WIDTH, len(payload) // media.UNIT)
    assert (webp.channels_of(pixels, media.WIDTH) == webp.decode(data)[0]).all()
    assert np.ascontiguousarray(webp.decode(data)[0][..., 1:]).tobytes() == payload


def test_repeats_are_equal_and_apart():
    rng = np.random.default_rng(4)
    for n, values in ((0, 2), (3, 2), (4, 1), (5, 1), (9000, 1), (500, 2), (3000, 5), (3000, 1 << 24)):
        pixels = rng.integers(0, values, n).astype(np.uint32)
        free = 0
        for at, size, back in zip(*webp.repeats(pixels), strict=True):
            assert at >= free and 0 < back <= at and 0 < size <= 4096
            assert (pixels[at : at + size] == pixels[at - back : at - back + size]).all()
            free = at + size
        assert free <= n


def test_broken_media_raise_their_own_error():
    rng = np.random.default_rng(6)
    whole = media.stored(media.payload_of("The same line here, and other words.\n" * 30 + "x" * 900))
    for i in range(300):
        broken = bytearray(whole if i % 3 else whole[: 21 + i % (len(whole) - 21)])
        broken[int(rng.integers(20, len(broken)))] ^= 1 << int(rng.integers(8))
        try:
            assert webp.decode(bytes(broken))[0].shape[2] == 4
        except webp.WebpError:
            pass


def test_shingles():
    cases = {"": 0, " \n": 0, "one": 1, "a b c d": 1, "a b c d e": 1, "A b c d e f": 2, "x x x x x x x": 1}
    hashes, bounds = near_dedup.shingles(list(cases))
    assert [len(set(hashes[a:b])) for a, b in zip(bounds[:-1], bounds[1:], strict=True)] == list(cases.values())
    one, _ = near_dedup.shingles(["The cat\u00a0sat on the mat", "the CAT\u00a0sat  on\tthe mat"])
    assert one[0] == one[1]


def test_signature_distances_meet_in_buckets():
    """Every pair within CHUNKS * (ERRORS + 1) - 1 differing symbols shares a key: the pigeonhole guarantee."""
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 16, (1, near_dedup.SYMBOLS)).astype(np.uint16)
    for _ in range(300):
        other = base.copy()
        at = rng.permutation(near_dedup.SYMBOLS)[: near_dedup.CHUNKS * (near_dedup.ERRORS + 1) - 1]
        other[0, at] += 1
        a, b = near_dedup.bucket_keys(base)[0], near_dedup.bucket_keys(other)[0]
        shared = np.flatnonzero(a == b)
        assert len(shared) and near_dedup.first_shared(base, other)[0] == shared[0]


def test_factor_sums_are_pair_sums():
    rng = np.random.default_rng(5)
    model = quality.Machine(0.3, rng.normal(size=50), rng.normal(size=(50, 4)))
    cells, values = rng.permutation(50)[:12], rng.normal(size=12)
    slow = 0.3 + model.linear[cells] @ values
    slow += sum(model.factors[cells[i]] @ model.factors[cells[j]] * values[i] * values[j] for i in range(12) for j in range(i))
    assert np.isclose(model.margins(cells, values, np.array([0]))[0], slow)


def test_segmentation():
    segment = url_filter.Segmenter({"free": 50, "bets": 30, "the": 500, "re": 40, "casino": 20})
    assert segment("freebets") == ("free", "bets") and segment("casinofree") == ("casino", "free") and segment("") == ()
    assert url_filter._names("a-b12.c") == ["a", "b", "#2", "c"]


@pytest.mark.parametrize("seed", range(4))
def test_segmentation_is_the_best_of_all_splits(seed):
    rng = np.random.default_rng(seed)
    words = {"".join(rng.choice(list("abc"), rng.integers(1, 5))): int(rng.integers(1, 60)) for _ in range(12)}
    segment = url_filter.Segmenter(words)
    unknown = lambda n: np.log(10 / segment.total) - n * np.log(10)
    value = lambda parts: sum(segment.score.get(p, unknown(len(p))) for p in parts)
    for _ in range(20):
        name = "".join(rng.choice(list("abcd"), rng.integers(1, 11)))
        cuts = [[0, *(i for i in range(1, len(name)) if mask >> i & 1), len(name)] for mask in range(0, 1 << len(name), 2)]
        splits = [[name[a:b] for a, b in zip(c[:-1], c[1:], strict=True)] for c in cuts]
        assert "".join(segment(name)) == name and np.isclose(value(segment(name)), max(map(value, splits)))


def test_templates():
    held = licenses.Templates()
    held.weigh(1000, np.full(len(held.words), 5))
    texts = ["Some prose.\nReleased under the MIT License.", "licensed UNDER the apache license, version 2.0", "nothing here", "", "All rights reserved by no one in this long story of rights"]
    top, cosine, share = held.best(texts)
    assert [held.names[t] if t >= 0 else None for t in top] == ["MIT", "Apache-2.0", None, None, None]
    assert np.isclose(cosine[0], 1) and share[1] == 1 and 0 < share[0] < 1


def test_notices_inside_lines_wrapped_and_licence_bodies():
    held = licenses.Templates()
    held.weigh(60_000, np.full(len(held.words), 60))
    prose = "stone river quiet morning walked along " * 40
    notices = ["Copyright 2020 Acme. All rights reserved.", f"{prose}. Released under the MIT License. {prose}", f"// {prose}\n// Licensed under the Apache\n// License, Version 2.0.\n{prose}", "Copyright 2020 Acme, all\nrights reserved", f"{prose} all rights reserved by no one", prose]
    top, _, share = held.best(notices)
    assert [held.names[t] if t >= 0 else None for t in top] == ["proprietary", "MIT", "Apache-2.0", "proprietary", None, None]
    bodies = sorted(licenses.BODIES)
    files = [f"Copyright (c) 2020 Acme. All rights reserved.\n\n{licenses.BODIES[n]}" for n in bodies] + [" ".join(licenses.BODIES["MIT"].split())]
    top, cosine, share = held.best(files)
    assert [held.names[t] for t in top] == [*bodies, "MIT"] and (share > 0.8).all() and (cosine[:-1] > 0.9).all()


def test_graph_recall_and_ties():
    rng = np.random.default_rng(6)
    vectors = rng.normal(size=(1500, 24))
    ids = np.full((1500, vector_graph.TOP + 1), -1)
    ids[:, 0] = np.arange(1500) * 2
    ids[7, :5] = [14, 3001, 3003, 3005, 3007]  # copies of one vector
    index = vector_graph.ShardIndex.load(vector_graph.ShardIndex(vectors, ids).dump())
    found: dict = {}
    for q, i, s in index.search(ids[:200, 0], vectors[:200], 20):
        found.setdefault(q, []).append((i, s))
    hits = 0
    for q in range(200):
        score = vectors @ vectors[q]
        rows = [(-score[v], i) for v in range(1500) for i in ids[v] if i >= 0 and i != ids[q, 0]]
        want = [i for _, i in sorted(rows)[:20]]
        hits += len(set(want) & {i for i, _ in found[ids[q, 0]]})
        assert all(a[1] > b[1] or (a[1] == b[1] and a[0] < b[0]) for a, b in zip(found[ids[q, 0]], found[ids[q, 0]][1:], strict=False))
    assert hits >= 0.95 * 4000
    assert unicodedata.unidata_version


def alternating(n, a="a", b="b"):
    """The first n letters of the sequence that doubles itself with both letters swapped, and the same swapped."""
    word = a
    while len(word) < n:
        word += word.translate(str.maketrans(a + b, b + a))
    return word, word.translate(str.maketrans(a + b, b + a))


@pytest.mark.parametrize("letters", ["ab", "ts", "日本"])
def test_self_similar_words_stay_apart(letters):
    texts = [w for n in (128, 1024, 2048, 4096) for w in alternating(n, *letters)]
    for codes, bounds in (textscan.codes_of(texts), (np.concatenate([np.frombuffer(t.encode(), np.uint8) for t in texts]), np.cumsum([0, *(len(t.encode()) for t in texts)]))):
        assert len(set(textscan.span_hashes(codes, bounds[:-1], bounds[1:]))) == len(texts)
    library = Tokenizer.from_file(vocab.path("byte_bpe_50k.json"))
    ids, per, _, _ = piece_tokens.PieceTokenizer(vocab.path("byte_bpe_50k.json")).encode(texts)
    assert [c.tolist() for c in np.split(ids, np.cumsum(per)[:-1])] == [x.ids for x in library.encode_batch(texts, add_special_tokens=False)]
    path = vocab.path("word_bpe_49k.json")
    assert token_counts.count_texts(texts, path).tolist() == [len(x.ids) for x in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    book = byte_bpe.PieceBook(vocab.path("byte_bpe_50k.tiktoken"))
    at, first = book.look_up(texts)
    assert [b"".join(map(book.raw.__getitem__, at[a:b].tolist())) for a, b in zip(first[:-1], first[1:], strict=True)] == [t.encode() for t in texts]
    hashes, bounds = near_dedup.shingles(texts)
    assert len(set(hashes)) == len(texts) and (np.diff(bounds) == 1).all()


def test_span_hashes_are_of_the_span_alone():
    words = ["", "a", "a\0", "ab", "abc", "abcd", "x" * 7, "x" * 8, "x" * 9, "x" * 192, "x" * 193, "é日", "x" * 191 + "y"]
    for pad in ("", "z", "zz" * 50):
        codes, bounds = textscan.codes_of([*words, pad, *words])
        hashes = textscan.span_hashes(codes, bounds[:-1], bounds[1:])
        assert (hashes[: len(words)] == hashes[len(words) + 1 :]).all() and len(set(hashes[: len(words)])) == len(words)


def test_common_members_are_never_underestimated():
    rng = np.random.default_rng(7)
    sets = [np.unique(rng.integers(1 << 64, size=n, dtype=np.uint64)) for n in (0, 1, 5, 300, 300, 9000, 40_000)]
    sets += [np.unique(np.concatenate([s[: int(len(s) * share)], rng.integers(1 << 64, size=40, dtype=np.uint64)])) for s in sets for share in (0.6, 0.9, 1.0)]
    counts = near_dedup.set_counts(sets)
    assert counts.sum(1).tolist() == [len(s) for s in sets]
    bound = near_dedup.most_common(counts, counts)
    common = np.array([[len(np.intersect1d(a, b)) for b in sets] for a in sets])
    assert (bound >= common).all() and (np.diag(bound) == np.diag(common)).all()
    assert bound[3, 4] < 150  # of 300 each, none in common


def test_only_the_stored_form_of_an_image_is_laid_out(monkeypatch):
    """Both forms were laid out in full and one thrown away; the bits known beforehand are those of the file."""
    seen, laid = [], webp.Form.laid
    monkeypatch.setattr(webp.Form, "laid", lambda form: seen.append((form, laid(form))) or seen[-1][1])
    for text in ("plain words here", "again and again " * 300, "a" * 40_000, "\n"):
        seen.clear()
        payload = media.payload_of(text)
        made = media.stored(payload)
        assert np.ascontiguousarray(media.pixels_of(made)[..., 1:]).tobytes() == payload
        ((form, (_, lengths)),) = seen
        assert form.bits == form.size + lengths.sum()
        assert len(made) == 20 + (size := -(-(40 + form.bits) // 8)) + (size & 1)

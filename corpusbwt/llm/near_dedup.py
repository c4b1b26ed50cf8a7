"""Near-duplicate groups by a multi-index Hamming join over b-bit MinHash signatures.

A signature has ``CHUNKS * WIDTH`` symbols of 16 bits, each taken from one minimum over a document's shingles. The
distance of two signatures is the number of symbols that differ. Cut into chunks, two signatures at a distance of at most
``CHUNKS * (ERRORS + 1) - 1`` agree in some chunk but for ``ERRORS`` symbols, by the pigeonhole principle; so each chunk is
filed under every choice of the symbols that may differ. All pairs under that distance meet in a bucket, and beyond it a
pair at the similarity threshold still meets with a probability of 1 - 1.6e-6.

All pairs that meet are decided exactly, yet no table of pairs is ever made. First, each member meets its bucket's smallest
document, block by block, and links are contracted. Where members of different components are left in a bucket, they are
dealt to cells: those of the bucket's main component in blocks against blocks of the others. A task bounds each pair's
common shingles from above by counts of shingles in ``CELLS`` ranges of hashes, a bound that is never too low; the sets of
the documents that still may link are fetched, and the same cell compares them in full, leaving out pairs that links found
before connect. So a cell gives as many links as it joins components.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.llm import textscan
from corpusbwt.llm.common import batch_of, texts_of, trimmed
from corpusbwt.llm.graph import components
from corpusbwt.session import release, tidy, written

SHINGLE = 5
CHUNKS, WIDTH, ERRORS = 10, 4, 1
SYMBOLS = CHUNKS * WIDTH
#: Ranges of hashes in which a set's members are counted, and levels up to which counts are compared one by one.
CELLS, LEVELS = 512, 6
#: Members of a bucket that one task compares with another such block.
BLOCK = 2048
#: Up to so many ids (8 bytes each) are sent to every executor to pick their texts; beyond it the texts are shuffled.
MOST_SENT = 1_000_000

_RANDOM = np.random.default_rng(5)
_FACTOR = _RANDOM.integers(1 << 31, size=SYMBOLS, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_OFFSET = _RANDOM.integers(1 << 32, size=SYMBOLS, dtype=np.uint32)
_PLACE = _RANDOM.integers(1 << 63, size=SHINGLE, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: The symbols that each key keeps, in the order of keys.
_KEPT = [(c, kept) for c in range(CHUNKS) for kept in combinations(range(WIDTH), WIDTH - ERRORS)]
_SLOT_BITS = (len(_KEPT) - 1).bit_length()
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def shingles(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all word shingles of each text, repeated ones included, and each text's start with the total.

    Words are what lies between ASCII blanks, with A-Z lower-cased. Under five words, the whole sequence is one shingle;
    a text without words has none.
    """
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    bounds = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(np.fromiter(map(len, raw), np.int64, len(raw)), out=bounds[1:])
    codes = _LOWER[np.frombuffer(b"".join(raw), np.uint8)]
    starts, ends, owner = textscan.word_spans(codes, bounds, ~_BLANK[codes])
    words = textscan.span_hashes(codes, starts, ends)
    first = np.searchsorted(owner, np.arange(len(raw) + 1))
    count = np.diff(first)
    made = np.where(count >= SHINGLE, count - SHINGLE + 1, np.minimum(count, 1))
    begin = textscan.spread(first[:-1], made)
    size = np.repeat(np.minimum(count, SHINGLE), made)
    total = size.astype(np.uint64)
    words = np.concatenate([words, np.zeros(SHINGLE, np.uint64)])
    for i in range(SHINGLE):
        total += np.where(size > i, words[begin + i] * _PLACE[i], np.uint64(0))
    return textscan.mix(total), np.concatenate([[0], np.cumsum(made)])


def signatures(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Symbols (texts, SYMBOLS) of 16 bits; zeros for a text without shingles."""
    out = np.zeros((len(bounds) - 1, SYMBOLS), np.uint16)
    full = np.flatnonzero(np.diff(bounds))
    if len(full):
        at, short = bounds[full], (hashes >> np.uint64(32)).astype(np.uint32)
        for i in range(SYMBOLS):
            low = np.minimum.reduceat(short * _FACTOR[i] + _OFFSET[i], at)
            out[full, i] = textscan.mix(low).astype(np.uint16)
    return out


def bucket_keys(symbols: np.ndarray) -> np.ndarray:
    """Keys (texts, keys) of all chunks under all choices of ERRORS symbols that may differ; the top bits tell which."""
    wide = symbols.astype(np.uint64)
    keys = []
    for c, kept in _KEPT:
        key = np.full(len(wide), len(keys) + 1, np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for i in kept:
            key = textscan.mix(key + wide[:, c * WIDTH + i])
        keys.append((key >> np.uint64(_SLOT_BITS)) | np.uint64(len(keys) << (64 - _SLOT_BITS)))
    return np.stack(keys, 1).view(np.int64)


def first_shared(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Of pairs of signatures, the first key that they share."""
    same = (one == two).reshape(-1, CHUNKS, WIDTH)
    return np.stack([same[:, c][:, list(kept)].all(1) for c, kept in _KEPT], 1).argmax(1)


def set_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Counts (sets, CELLS) of the members of sorted sets of hashes in equal ranges of hashes."""
    owner = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    cell = (np.concatenate([*sets, np.zeros(0, np.uint64)]) >> np.uint64(64 - CELLS.bit_length() + 1)).astype(np.int64)
    return np.bincount(owner * CELLS + cell, minlength=len(sets) * CELLS).reshape(len(sets), CELLS).astype(np.int32)


def most_common(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Upper bounds (left, right) of the members that sets have in common, from their counts.

    Common members of a range are at most the smaller count: the sum, over levels, of whether both counts reach the
    level. What counts have beyond the last level is bounded by the smaller of both sums.
    """
    out = np.minimum.outer(np.maximum(left - LEVELS, 0).sum(1), np.maximum(right - LEVELS, 0).sum(1)).astype(np.float64)
    for level in range(1, LEVELS + 1):
        a, b = left >= level, right >= level
        if not (a.any() and b.any()):
            break
        out += a.astype(np.float32) @ b.astype(np.float32).T
    return out


def _linked(one: np.ndarray, two: np.ndarray, least: int) -> bool:
    """Whether two sets of hashes have 100 * intersection >= least * union."""
    small, large = sorted((len(one), len(two)))
    if 100 * small < least * large:
        return False
    common = len(np.intersect1d(one, two, assume_unique=True))
    return 100 * common >= least * (small + large - common)


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("digest", pa.binary()), ("keys", pa.list_(pa.int64()))])
    for batch in batches:
        texts = texts_of(batch.column(1))
        for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
            hashes, bounds = shingles(texts[lo:hi])
            sets = [np.unique(hashes[a:b]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
            keys = pa.ListArray.from_arrays(np.arange(hi - lo + 1) * len(_KEPT), bucket_keys(signatures(hashes, bounds)).ravel())
            digests = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
            yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), [len(s) for s in sets], digests, keys])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of each text: its sorted set of hashes, the counts of their ranges and its signature, as bytes."""
    schema = pa.schema([("id", pa.int64()), ("members", pa.binary()), ("counts", pa.binary()), ("symbols", pa.binary())])
    for batch in batches:
        texts = texts_of(batch.column(1))
        for lo, hi in textscan.slices(np.fromiter(map(len, texts), np.int64, len(texts))):
            hashes, bounds = shingles(texts[lo:hi])
            sets = [np.unique(hashes[a:b]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
            counts = [(c.astype(np.uint8) if c.max() < 256 else c).tobytes() for c in set_counts(sets)]
            yield batch_of(schema, [batch.column(0).slice(lo, hi - lo), [s.tobytes() for s in sets], counts, [x.tobytes() for x in signatures(hashes, bounds)]])


def _counts_of(raw: list[bytes]) -> np.ndarray:
    return np.stack([np.frombuffer(x, np.uint8 if len(x) == CELLS else np.int32).astype(np.int32) for x in raw])


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows of a sorted partition, gathered by equal (key, cell)."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([*held, batch])
        key, cell = table.column("key").to_numpy(), table.column("cell").to_numpy()
        edges = [0, *(np.flatnonzero((key[1:] != key[:-1]) | (cell[1:] != cell[:-1])) + 1).tolist()]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            yield table.slice(a, b - a)
        held = table.slice(edges[-1]).to_batches()
    if held:
        yield pa.Table.from_batches(held)


def _stars(least: int):
    """Links of each cell's centre (side 0, in as many versions as its id has) with the others (side 1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
        for rows in _runs(batches):
            ids, side = rows.column("id").to_numpy(), rows.column("side").to_numpy()
            sets = [np.frombuffer(x, np.uint64) for x in rows.column("members").to_pylist()]
            centres = [sets[i] for i in np.flatnonzero(side == 0)]
            found = [i for i in np.flatnonzero(side == 1) if any(_linked(c, sets[i], least) for c in centres)]
            if found:
                yield batch_of(schema, [rows.column("key").to_numpy()[found], ids[found]])

    return run


def _open_pairs(rows: pa.Table, counts: np.ndarray, sizes: np.ndarray, least: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of different components in a cell that their counts leave open and that don't meet under an earlier key."""
    part, side = rows.column("part").to_numpy(), rows.column("side").to_numpy()
    symbols = np.stack([np.frombuffer(x, np.uint16) for x in rows.column("symbols").to_pylist()])
    slot = int(rows.column("key").to_numpy()[:1].view(np.uint64)[0] >> np.uint64(64 - _SLOT_BITS))
    both = bool(side.any())  # two blocks: only pairs across them
    left, right = (np.flatnonzero(side == 0), np.flatnonzero(side == 1)) if both else (np.arange(len(part)),) * 2
    step = max(1, (1 << 22) // max(1, len(right)))
    for lo in range(0, len(left), step):
        own = left[lo : lo + step]
        bound = np.minimum(most_common(counts[own], counts[right]), np.minimum.outer(sizes[own], sizes[right]))
        near = (100 * bound >= least * (np.add.outer(sizes[own], sizes[right]) - bound)) & (part[own, None] != part[None, right])
        if not both:
            near &= own[:, None] < right[None, :]
        i, j = np.nonzero(near)
        for at in range(0, len(i), 1 << 15):
            a, b = own[i[at : at + (1 << 15)]], right[j[at : at + (1 << 15)]]
            here = first_shared(symbols[a], symbols[b]) == slot
            yield a[here], b[here]


def _candidates(least: int):
    """Members of cells that still may link with another one of their cell."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _runs(batches):
            counts = _counts_of(rows.column("counts").to_pylist())
            open_ = np.zeros(len(counts), bool)
            for a, b in _open_pairs(rows, counts, counts.sum(1), least):
                open_[a] = open_[b] = True
            if open_.any():
                yield from rows.select(["key", "cell", "rep", "part", "side"]).filter(pa.array(open_)).combine_chunks().to_batches()

    return run


def _cell_links(least: int):
    """Links that join the components of each cell, found on full sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])
        for rows in _runs(batches):
            sets = [np.frombuffer(x, np.uint64) for x in rows.column("members").to_pylist()]
            rep, part = rows.column("rep").to_numpy(), rows.column("part").to_pylist()
            name = {p: p for p in part}

            def find(p: int, name: dict[int, int] = name) -> int:
                while name[p] != p:
                    name[p] = p = name[name[p]]
                return p

            found: list[tuple[int, int]] = []
            for a, b in _open_pairs(rows, set_counts(sets), np.array([len(s) for s in sets]), least):
                for i, j in zip(a.tolist(), b.tolist(), strict=True):
                    p, q = find(part[i]), find(part[j])
                    if p != q and _linked(sets[i], sets[j], least):
                        name[p] = q
                        found.append((i, j))
            if found:
                i, j = map(list, zip(*found, strict=True))
                yield batch_of(schema, [rep[i], rep[j]])

    return run


def _dealt(tagged: DataFrame) -> DataFrame:
    """``(key, cell, rep, part, side)``: members of buckets with several components, dealt to cells of bounded size.

    Up to BLOCK members make one cell. Beyond it, blocks of the component with the smallest name meet blocks of all the
    others, and those meet one another; a pair of members meets in one cell of its bucket.
    """
    parts = tagged.groupBy("key", "part").agg(F.count("*").alias("n"))
    sized = parts.groupBy("key").agg(F.min("part").alias("main"), F.min_by("n", "part").alias("mains"), F.sum("n").alias("n"), F.count("*").alias("parts")).where("parts > 1")
    block = lambda n: F.ceil(n / BLOCK).cast("int")
    rows = tagged.join(sized.select("key", "main", "n", block(F.col("mains")).alias("p"), block(F.col("n") - F.col("mains")).alias("q")), "key")
    small, is_main = F.col("n") <= BLOCK, F.col("part") == F.col("main")
    own = lambda n: F.pmod(F.xxhash64("rep"), F.col(n)).cast("int")
    up_to = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    cell = lambda c, side: F.struct(c.cast("long").alias("cell"), F.lit(side).alias("side"))
    of_main = F.transform(up_to("q"), lambda j: cell(own("p") * F.col("q") + j, 0))
    with_main = F.transform(up_to("p"), lambda i: cell(i * F.col("q") + own("q"), 1))
    first, area = own("q"), F.col("p") * F.col("q")
    one_another = F.transform(up_to("q"), lambda j: F.struct((area + F.least(first, j) * F.col("q") + F.greatest(first, j)).cast("long").alias("cell"), F.when(first > j, 1).otherwise(0).alias("side")))
    cells = F.when(small, F.array(cell(F.lit(0), 0))).when(is_main, of_main).otherwise(F.concat(with_main, one_another))
    return rows.select("key", "rep", "part", F.explode(cells).alias("at")).select("key", "at.cell", "rep", "part", "at.side")


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, similarity: int = 75) -> DataFrame:
    """Per row: doc_id, n_shingles, component_id (smallest id reachable over links), kept (doc_id = component_id).

    A link joins two documents whose sets of distinct five-word shingles have 100 * intersection >= similarity * union
    (similarity: 75 or more). Null or blank texts have no shingles and are alone. Equal sets form one class, so copies are
    never paired. Rows that repeat an id are one document and share its component. A row with a null id links with
    nothing; its component is null and it is kept. An empty table gives no rows.
    """
    if similarity < 75:
        raise ValueError("signatures are dimensioned for a similarity of 0.75 or more")
    spark = df.sparkSession
    texts = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    rows = written(texts.mapInArrow(trimmed(_sketch), "doc_id long, n_shingles long, digest binary, keys array<long>"))
    classes = written(rows.where("doc_id is not null and digest is not null").groupBy("digest").agg(F.min("doc_id").alias("rep")))
    ones = written(rows.select("digest", F.col("doc_id").alias("rep"), "keys").join(classes, ["digest", "rep"]).select("rep", "keys"))
    filed = ones.select("rep", F.explode("keys").alias("key"))
    buckets = filed.groupBy("key").agg(F.min("rep").alias("lead"), F.max("rep").alias("last")).where("lead < last")
    members = written(filed.join(buckets.drop("last"), "key").distinct())
    release(ones)
    tidy(spark)
    ids = members.select(F.col("rep").alias("id")).distinct()
    if ids.count() <= MOST_SENT:
        ids = F.broadcast(ids)
    sets = written(texts.join(ids, "id", "left_semi").mapInArrow(trimmed(_sets), "id long, members binary, counts binary, symbols binary"))

    star = written(members.where("rep > lead").select("lead", F.col("rep").alias("id")).distinct())
    sized = star.groupBy("lead").agg(F.ceil(F.count("*") / BLOCK).alias("blocks"))
    points = star.join(sized, "lead").select(F.col("lead").alias("key"), F.pmod(F.xxhash64("id"), "blocks").alias("cell"), F.lit(1).alias("side"), "id")
    centres = sized.select(F.col("lead").alias("key"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("cell"), F.lit(0).alias("side"), F.col("lead").alias("id"))
    filled = points.union(centres).join(sets.select("id", "members"), "id").select("key", "cell", "side", "id", "members")
    links = written(filled.repartition("key", "cell").sortWithinPartitions("key", "cell").mapInArrow(trimmed(_stars(similarity)), "a long, b long"))
    release(star)
    tidy(spark)

    early = components(links)
    tagged = written(members.join(early.withColumnRenamed("node", "rep"), "rep", "left").select("key", "rep", F.coalesce("component", "rep").alias("part")))
    open_ = written(_dealt(tagged))
    shown = open_.join(sets.select(F.col("id").alias("rep"), "symbols", "counts"), "rep").select("key", "cell", "rep", "part", "side", "symbols", "counts")
    left = written(shown.repartition("key", "cell").sortWithinPartitions("key", "cell").mapInArrow(trimmed(_candidates(similarity)), "key long, cell long, rep long, part long, side int").distinct())
    release(open_)
    whole = left.join(sets.select(F.col("id").alias("rep"), "symbols", "members"), "rep").select("key", "cell", "rep", "part", "side", "symbols", "members")
    more = written(whole.repartition("key", "cell").sortWithinPartitions("key", "cell").mapInArrow(trimmed(_cell_links(similarity)), "a long, b long"))
    for done in (members, tagged, sets, early, left):
        release(done)
    tidy(spark)

    parts = components(links.union(more)).select(F.col("node").alias("rep"), "component")
    named = classes.join(parts, "rep", "left").select("digest", F.coalesce("component", "rep").alias("component"))
    out = rows.select("doc_id", "n_shingles", "digest").join(named, "digest", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    out = written(out.select("doc_id", "n_shingles", "component"))
    for done in (rows, classes, links, more, parts):
        release(done)
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def without_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with all its columns, one document of each near-duplicate group; rows with a null id stay."""
    gone = near_duplicates(docs, id_col, text_col).where(~F.col("kept")).select(F.col("doc_id").alias(id_col)).distinct()
    return docs.join(gone, id_col, "left_anti").select(*docs.columns)

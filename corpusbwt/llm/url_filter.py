"""URL filters: rules first, then naive Bayes over words that a unigram Viterbi search finds in host and path.

The unigram model counts all words of all pages' visible text and stays a table: each distinct letter run of a host or path
is joined, by its substrings, with the words that can occur in it, and is split with those alone. Naive Bayes is multinomial
over hashed words of every page's URL. Its classes come from seed terms: a page whose segmented host holds one of them is an
example of what to block, every other page of what to allow.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusbwt.llm.common import batch_of
from corpusbwt.session import release, written

LONGEST = 24
BUCKETS, SMOOTHING = 1 << 16, 0.01
#: Rules as (verdict, host, path), and terms whose presence in a host makes a page an example to block: common
#: words of the categories that public block lists name (adult, gambling, pharmacy, advertising, malicious).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
SEEDS = frozenset(
    """adult escort escorts hentai nude porn pornography xxx
    bets betting bingo blackjack casino casinos gambling jackpot lottery poker roulette
    cialis pharmacy pills tramadol viagra xanax
    ads adserver adware clickbait popunder
    keygen malware phishing ransomware spam spyware warez""".split()
)
#: A seed term counts at least as one word in so many, or text that never has it would make its letters other words.
SEED_SHARE = 10_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def parsed(pages: DataFrame, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host (A-Z lower-cased) and path of each URL; both empty for a null URL or one without ``://``."""
    part = lambda i: F.coalesce(F.regexp_extract(url_col, r"(?s)^.*?://([^/?#]*)([^?#]*)", i), F.lit(""))
    return pages.select(F.col(id_col).alias("page_id"), F.translate(part(1), _UPPER, _LOWER).alias("host"), part(2).alias("path"))


def with_rule(urls: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES) -> DataFrame:
    """Adds ``rule`` and ``ruled``, its verdict, of the longest rule that fits; null where none does."""
    rule = ruled = F.lit(None).cast("string")
    for verdict, host, path in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[1:])):
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
        rule = F.when(fits, F.lit(host + path)).otherwise(rule)
        ruled = F.when(fits, F.lit(verdict)).otherwise(ruled)
    return urls.withColumns({"rule": rule, "ruled": ruled})


class Segmenter:
    """Splits a name into the words of greatest total probability; a stretch of unknown letters pays by its length."""

    def __init__(self, counts: dict[str, int], total: int = 0):
        self.total = total or sum(counts.values()) or 1
        self.score = {w: math.log(c / self.total) for w, c in counts.items()}
        self.known: dict[str, tuple[str, ...]] = {}

    def __call__(self, name: str) -> tuple[str, ...]:
        found = self.known.get(name)
        if found is None:
            if len(self.known) > 100_000:
                self.known.clear()
            found = self.known[name] = self._split(name)
        return found

    def _split(self, name: str) -> tuple[str, ...]:
        best, back = [0.0], [0]
        unknown = [math.log(10 / self.total) - n * math.log(10) for n in range(LONGEST + 1)]
        for end in range(1, len(name) + 1):
            at, start = max((best[s] + self.score.get(name[s:end], unknown[end - s]), s) for s in range(max(0, end - LONGEST), end))
            best.append(at)
            back.append(start)
        out, end = [], len(name)
        while end:
            out.append(name[back[end] : end])
            end = back[end]
        return tuple(reversed(out))


def _names(text: str) -> list[str]:
    """Runs of letters, and of digits as one sign for their length."""
    out, run = [], ""
    for c in text.lower() + " ":
        if run and not (c.isalpha() and run.isalpha() or c.isdigit() and run.isdigit()):
            out.append(run if run.isalpha() else f"#{len(run)}")
            run = ""
        if c.isalpha() or c.isdigit():
            run += c
    return out


def _buckets(host: list[str], path: list[str]) -> list[int]:
    return [zlib.crc32(w.encode()) % BUCKETS for w in (*("h:" + x for x in host), *host, *("p:" + x for x in path))]


def unigrams(pages: DataFrame, html_col: str = "html", seeds: frozenset[str] = SEEDS) -> tuple[DataFrame, int, dict[str, int]]:
    """Stored counts of all words of all pages' text, their total, and the counts of the seed terms, which are part of it."""
    bare = F.lower(F.regexp_replace(html_col, "<[^>]*>", " "))
    words = pages.select(F.explode(F.split(bare, r"[^\p{L}]+")).alias("word")).where("word <> ''")
    counts = written(words.groupBy("word").agg(F.count("*").alias("n")))
    total = counts.agg(F.sum("n")).first()[0] or 0
    own = {r.word: r.n for r in counts.where(F.col("word").isin(sorted(seeds))).collect()}
    raised = {s: max(10, total // SEED_SHARE, own.get(s, 0)) for s in sorted(seeds)}
    return counts, total + sum(raised.values()) - sum(own.values()), raised


def _named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    place = pa.list_(pa.struct([("rest", pa.bool_()), ("at", pa.int32()), ("name", pa.string())]))
    for batch in batches:
        names = [[{"rest": bool(i), "at": at, "name": n} for i, side in enumerate(url) for at, n in enumerate(_names(side))] for url in zip(*(c.to_pylist() for c in batch.columns[:2]), strict=True)]
        yield batch_of(pa.schema([*zip(("host", "path", "n"), batch.schema.types, strict=True), ("names", place)]), [*batch.columns, names])


def segmented(names: DataFrame, counts: DataFrame, total: int, raised: dict[str, int]) -> DataFrame:
    """``names`` (name: distinct letter runs) with ``words``, split by the counts of all words that occur in each."""
    left = F.length("name") - F.col("start") + 1
    parts = names.select("name", F.explode(F.sequence(F.lit(1), F.length("name"))).alias("start")).select("name", F.explode(F.transform(F.sequence(F.lit(1), F.least(left, F.lit(LONGEST))), lambda n: F.substring("name", F.col("start"), n))).alias("word"))
    held = parts.distinct().join(counts, "word", "left").groupBy("name").agg(F.collect_list(F.when(F.col("n").isNotNull(), F.struct("word", "n"))).alias("held"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("name", pa.string()), ("words", pa.list_(pa.string()))])
        for batch in batches:
            names, held = (c.to_pylist() for c in batch.columns)
            yield batch_of(schema, [names, [Segmenter({w["word"]: w["n"] for w in own} | raised, total)(n) for n, own in zip(names, held, strict=True)]])

    return held.select("name", "held").mapInArrow(run, "name string, words array<string>")


def split(urls: DataFrame, counts: DataFrame, total: int, raised: dict[str, int]) -> DataFrame:
    """Each distinct host and path: ``n``, how many rows have them, and the words of the host (``own``) and path (``rest``)."""
    named = written(urls.groupBy("host", "path").agg(F.count("*").alias("n")).mapInArrow(_named, "host string, path string, n long, names array<struct<rest: boolean, at: int, name: string>>"))
    places = named.select("host", "path", "n", F.explode_outer("names").alias("place"))
    runs = places.select(F.col("place.name").alias("name")).where("name is not null and name not like '#%'").distinct()
    found = places.join(segmented(runs, counts, total, raised), F.col("place.name") == F.col("name"), "left")
    words = F.when(F.col("place").isNotNull(), F.struct("place.rest", "place.at", F.coalesce("words", F.array("place.name")).alias("words")))
    held = found.groupBy("host", "path").agg(F.first("n").alias("n"), F.sort_array(F.collect_list(words)).alias("held"))
    side = lambda rest: F.flatten(F.transform(F.filter("held", lambda x: x["rest"] == F.lit(rest)), lambda x: x["words"]))
    out = written(held.select("host", "path", "n", side(False).alias("own"), side(True).alias("rest")))
    release(named)
    return out


def fit(words: DataFrame, seeds: frozenset[str] = SEEDS) -> tuple[np.ndarray, float]:
    """Log-odds of blocking for each hashed word, and of the classes, from counts over all URLs, smoothed by ``SMOOTHING``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = Counter()
        for batch in batches:
            for n, own, rest in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                label = int(not seeds.isdisjoint(own))
                seen[label, -1] += n
                for b in _buckets(own, rest):
                    seen[label, b] += n
        schema = pa.schema([("label", pa.int32()), ("bucket", pa.int32()), ("n", pa.int64())])
        if seen:
            yield batch_of(schema, [[k[0] for k in seen], [k[1] for k in seen], list(seen.values())])

    rows = words.select("n", "own", "rest").mapInArrow(run, "label int, bucket int, n long").groupBy("label", "bucket").agg(F.sum("n").alias("n")).collect()
    table = np.full((2, BUCKETS + 1), SMOOTHING)
    for r in rows:
        table[r.label, r.bucket] += r.n
    words, prior = table[:, :BUCKETS], table[:, BUCKETS]
    odds = np.log(words / words.sum(1, keepdims=True))
    return odds[1] - odds[0], float(np.log(prior[1] / prior[0]))


def judged(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", *, rules: Sequence[tuple[str, str, str]] = RULES, seeds: frozenset[str] = SEEDS) -> DataFrame:
    """Per row: page_id, host, path, rule, verdict, and ``odds``, the log-odds of blocking by naive Bayes.

    A rule's verdict goes before the model's, which blocks at odds above zero. A URL without host and path has the odds of
    the classes alone. Rows with null or repeated ids are judged like any other; an empty table gives no rows. Further
    columns are left out, whatever their names.
    """
    urls = with_rule(parsed(pages, id_col, url_col), rules)
    counts, total, raised = unigrams(pages, html_col, seeds)
    words = split(urls, counts, total, raised)
    release(counts)
    weights, prior = fit(words, seeds)
    sent = pages.sparkSession.sparkContext.broadcast((weights, prior))
    kind = urls.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, prior = sent.value
        for batch in batches:
            schema = pa.schema([*zip(("page_id", "host", "path", "rule", "verdict"), [*batch.schema.types[:4], pa.string()], strict=True), ("odds", pa.float64())])
            odds = [prior + float(weights[_buckets(own, rest)].sum()) for own, rest in zip(batch.column(5).to_pylist(), batch.column(6).to_pylist(), strict=True)]
            verdict = [r or ("block" if o > 0 else "allow") for r, o in zip(batch.column(4).to_pylist(), odds, strict=True)]
            yield batch_of(schema, [*batch.columns[:4], verdict, odds])

    held = urls.join(words.drop("n"), ["host", "path"]).select(*urls.columns, "own", "rest")
    return held.mapInArrow(run, f"page_id {kind}, host string, path string, rule string, verdict string, odds double")

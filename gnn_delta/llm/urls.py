"""URL filter: explicit rules first, then host word segmentation and multinomial naive Bayes.

Names written together are split by the most probable word sequence (Viterbi over unigram counts), then
the words of host and path are scored. The unigram counts come from all URLs of the table (pieces between
punctuation) and from a small seed vocabulary; a piece that known words make up counts for these words
instead, however often it occurs; naive Bayes sets the seed vocabulary of unwanted sites
against the pieces of the whole table and the seed vocabulary of ordinary sites.

Defined cases: a null URL or one without ``://`` has empty host and path, no rule and is allowed; an empty
path begins with no rule's path; ties of score are allowed; equally long rules: the first in the list wins;
URLs of any length are read whole; repeated rows give repeated results; an empty table gives none; extra
columns are not read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lower_ascii

#: (verdict, host, path prefix)
RULES = [
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
]
#: fixed values: words that unwanted sites carry in their names, and words of ordinary sites
UNWANTED = "casino win bet bets free spam farm poker slots jackpot bonus cheap pills viagra porn xxx adult sex escort loan payday crack warez torrent hack lottery prize click ads".split()
ORDINARY = "www blog m example com net org edu gov news shop wiki docs about help home index html page article product category search en de fr es".split()
SEED_COUNT = 1000
#: a piece is a word of its own from this share of all pieces on, which bounds their number at any size
WORD_SHARE = 2e-6
#: in larger tables a seed word counts as this share of all pieces
SEED_SHARE = 1 / 68


@dataclass(frozen=True)
class UrlModel:
    logp: dict[str, float]
    unseen: float
    longest: int
    odds: dict[str, float]
    prior: float
    cache: dict[str, list[str]] = field(default_factory=dict, compare=False)

    def segment(self, name: str) -> list[str]:
        """The most probable split; an unknown word costs ``unseen`` per letter."""
        if name in self.cache:
            return self.cache[name]
        best, back = [0.0], [0]
        for end in range(1, len(name) + 1):
            top, at = -math.inf, end - 1
            for start in range(max(0, end - self.longest), end):
                cost = best[start] + self.logp.get(name[start:end], self.unseen * (end - start))
                if cost > top:
                    top, at = cost, start
            best.append(top)
            back.append(at)
        words, end = [], len(name)
        while end:
            words.append(name[back[end] : end])
            end = back[end]
        words.reverse()
        if len(self.cache) > 200_000:
            self.cache.clear()
        self.cache[name] = words
        return words

    def words(self, host: str, path: str) -> list[str]:
        return [w for piece in re.findall(r"[^\W\d_]+", f"{host} {path}".lower()) for w in self.segment(piece)]

    def score(self, host: str, path: str) -> float:
        """Log odds that the URL is unwanted."""
        return self.prior + sum(self.odds.get(w, 0.0) for w in self.words(host, path))


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path, both empty without ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url)))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    tail = F.substring(rest, F.length(host) + 1, F.length(rest))
    return F.coalesce(lower_ascii(host), F.lit("")), F.coalesce(F.regexp_extract(tail, r"^([^?#]*)", 1), F.lit(""))


def rule_columns(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """Longest fitting rule as text (host and path without its first slash shown after ``/``), and its verdict."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for order in sorted(range(len(rules)), key=lambda i: (len(rules[i][1]) + len(rules[i][2]), -i)):
        kind, on, prefix = rules[order]
        fits = ((host == on) | host.endswith("." + on)) & path.startswith(prefix)
        name = F.when(fits, on + prefix).otherwise(name)
        verdict = F.when(fits, kind).otherwise(verdict)
    return name, verdict


def known_parts(piece: str, known: dict[str, float], shortest: int) -> list[str] | None:
    """The most probable split of ``piece`` into two or more known words of at least ``shortest`` letters."""
    best: list[float | None] = [0.0]
    back = [0]
    for end in range(1, len(piece) + 1):
        top, at = None, 0
        for start in range(end):
            word = piece[start:end]
            before = best[start]
            if before is None or len(word) < shortest or len(word) == len(piece) or word not in known:
                continue
            if top is None or before + known[word] > top:
                top, at = before + known[word], start
        best.append(top)
        back.append(at)
    if best[-1] is None:
        return None
    parts, end = [], len(piece)
    while end:
        parts.append(piece[back[end] : end])
        end = back[end]
    return parts


def joined_words(counts: dict[str, int], seeds: set[str]) -> dict[str, int]:
    """Counts of words: pieces made up of seed words or of words more frequent than themselves count for their parts.

    Parts have three letters or more; shorter seed words are parts only beside a word of five."""
    total = sum(counts.values()) or 1
    words: dict[str, int] = {}
    joined: list[tuple[list[str], int]] = []
    known = {w: 0.0 for w in seeds}
    for piece in sorted(counts, key=lambda w: (len(w), w)):  # parts are shorter, so they are settled before
        n = counts[piece]
        parts = None
        if piece not in seeds:
            fit_for = {w: known[w] for k in range(len(piece)) for e in range(k + 1, len(piece) + 1) if (w := piece[k:e]) in known and (w in seeds or len(w) >= 3 and words.get(w, 0) > n)}
            parts = known_parts(piece, fit_for, 3) or known_parts(piece, fit_for, 1)
            if parts and min(map(len, parts)) < 3 and max(map(len, parts)) < 5:
                parts = None
        if parts:
            joined.append((parts, n))
        else:
            words[piece] = n
            known[piece] = math.log(n / total)
    for parts, n in joined:
        for w in parts:
            words[w] = words.get(w, 0) + n
    return words


def fit(pages: DataFrame) -> UrlModel:
    """Counts over all URLs; the pieces that reach the driver number at most 1 / WORD_SHARE."""
    host, path = split_url(F.col("url"))
    pieces = pages.select(F.explode(F.split(F.lower(F.concat_ws(" ", host, path)), r"[^\p{L}]+")).alias("w")).where(F.length("w").between(1, 40))
    counted = pieces.groupBy("w").agg(F.count("*").alias("n"))
    rows = counted.where(F.col("n") >= (counted.agg(F.sum("n")).first()[0] or 0) * WORD_SHARE).collect()
    seeds = {*UNWANTED, *ORDINARY}
    counts = joined_words({r["w"]: r["n"] for r in rows}, seeds)
    table = dict(counts)
    seed_count = max(SEED_COUNT, int(sum(counts.values()) * SEED_SHARE))
    for w in sorted(seeds):
        table[w] = table.get(w, 0) + seed_count
    total = sum(table.values())
    logp = {w: math.log(n / total) for w, n in table.items()}
    unseen = math.log(1 / (total * 10))
    # unwanted sites use ordinary words too: a fifth of their words is the unwanted vocabulary
    good = {w: n for w, n in counts.items() if w not in UNWANTED}
    for w in ORDINARY:
        good[w] = good.get(w, 0) + seed_count
    n_words = sum(good.values())
    bad = {**good, **{w: max(1, n_words // (4 * len(UNWANTED))) for w in UNWANTED}}
    n_bad, n_good = sum(bad.values()) + len(bad), n_words + len(bad)
    odds = {w: math.log((n + 1) / n_bad) - math.log((good.get(w, 0) + 1) / n_good) for w, n in bad.items()}
    return UrlModel(logp, unseen, max(map(len, logp), default=1), odds, math.log(0.05 / 0.95))


def judge(pages: DataFrame, rules=RULES, model: UrlModel | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict, score of every row."""
    fitted = model or fit(pages)
    shared = pages.sparkSession.sparkContext.broadcast(fitted)
    host, path = split_url(F.col("url"))
    kind = pages.schema["page_id"].dataType.simpleString()
    base = pages.select("page_id", host.alias("host"), path.alias("path"))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = [shared.value.score(h, p) for h, p in zip(batch.column("host").to_pylist(), batch.column("path").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], names=["page_id", "host", "path", "score"])

    scored = base.mapInArrow(rows, f"page_id {kind}, host string, path string, score double")
    rule, verdict = rule_columns(F.col("host"), F.col("path"), rules)
    return scored.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("score") > 0, "block").otherwise("allow")).alias("verdict"), "score")

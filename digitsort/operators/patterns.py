"""Searching many patterns in a suffix array, one by one or sorted first."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship_package
from ..sources.workloads import STEP, blocks
from . import runs
from .suffixes import ranked
from .whole import whole_ranked


def suffixes(docs: DataFrame, prefix: int = 32) -> DataFrame:
    """(doc_id, at, prefix): every suffix's first characters."""
    rows = blocks(docs.select("doc_id", "text"), prefix - 1, "doc_id")
    starts = F.sequence(F.lit(1), F.least(F.lit(STEP), F.length("block")))
    cut = rows.select("doc_id", "block_no", F.posexplode(F.transform(starts, lambda i: F.substring(F.col("block"), i, F.lit(prefix)))).alias("at", "prefix"))
    return cut.select("doc_id", (F.col("at") + F.col("block_no") * STEP).cast("long").alias("at"), "prefix")


def _places(ids: pa.Array, doc: np.ndarray, at: np.ndarray, rank: np.ndarray) -> dict:
    return {"doc_id": ids.take(pa.array(doc)), "at": pa.array(at), "rank": pa.array(rank)}


def suffix_array(docs: DataFrame, prefix: int = 32) -> DataFrame:
    """(doc_id, at, rank): suffixes in order of their prefix, ties by document and place."""
    return ranked(docs, prefix, f"doc_id {dict(docs.dtypes)['doc_id']}, at long, rank long", _places)


def whole_suffix_array(docs: DataFrame, prefix: int = 32) -> DataFrame:
    """(doc_id, at, rank): suffixes in order of their whole text; only equal ones tie, by document and place."""
    return whole_ranked(docs, prefix, f"doc_id {dict(docs.dtypes)['doc_id']}, at long, rank long", _places)


def pieces(texts: DataFrame, length: int = 12) -> DataFrame:
    """Distinct patterns: consecutive pieces of texts."""
    starts = F.sequence(F.lit(1), F.length("text") - length + 1, F.lit(length))
    return texts.filter(F.length("text") >= length).select(F.explode(F.transform(starts, lambda i: F.substring(F.col("text"), i, F.lit(length)))).alias("pattern")).distinct()


class Probes:
    """Binary searches in sorted texts that count the comparisons they make."""

    def __init__(self, keys) -> None:
        self.keys, self.made = keys, 0

    def head(self, at: int, n: int) -> str:
        self.made += 1
        return str(self.keys[at])[:n]

    def lower(self, x: str, low: int, high: int, past: bool = False) -> int:
        n = len(x)
        while low < high:
            mid = (low + high) // 2
            head = self.head(mid, n)
            if head < x or (past and head == x):
                low = mid + 1
            else:
                high = mid
        return low

    def onward(self, x: str, start: int, past: bool = False) -> int:
        """The same from ``start``, by doubling steps and a search in the last one."""
        low, high, step = start, start, 1
        while high < len(self.keys) and ((head := self.head(high, len(x))) < x or (past and head == x)):
            low, high, step = high + 1, high + step, 2 * step
        return self.lower(x, low, min(high, len(self.keys)), past)


Found = list[tuple[int, int, int]]


def search_one_by_one(keys, patterns: list[str]) -> Found:
    """(first match, occurrences, probes) of each pattern: two searches over all suffixes."""
    p, out = Probes(keys), []
    for x in patterns:
        before = p.made
        a = p.lower(x, 0, len(keys))
        out.append((a, p.lower(x, a, len(keys), past=True) - a, p.made - before))
    return out


def search_sorted(keys, patterns: list[str], prefix: int | None = None) -> Found:
    """The same with patterns sorted (by a prefix of theirs only, if given): each search begins where the last one ended.

    Both ends are found by doubling steps from there, so near patterns take few
    probes.  Within one prefix patterns aren't sorted: a search then begins where
    the prefix's first one did.
    """
    p, out = Probes(keys), [(0, 0, 0)] * len(patterns)
    order = sorted(range(len(patterns)), key=lambda k: patterns[k][:prefix] if prefix else patterns[k])
    low, head, of_head = 0, None, 0
    for k in order:
        x, before = patterns[k], p.made
        if prefix and x[:prefix] != head:
            head, of_head = x[:prefix], p.lower(x[:prefix], of_head, len(keys)) if head is not None and x[:prefix] >= head else 0
            low = of_head
        start = of_head if prefix else low
        a = p.onward(x, start)
        out[k] = a, p.onward(x, a, past=True) - a, p.made - before
        low = a
    return out


class Heads:
    """The first ``longest`` characters of a chunk's suffixes in order, cut out when asked for."""

    def __init__(self, codes: np.ndarray, lengths: np.ndarray, own: np.ndarray, longest: int) -> None:
        self.longest = longest
        self.ends = np.repeat(np.cumsum(lengths), lengths)
        self.order = _suffix_order(codes, self.ends, runs.within(lengths, own), longest)
        self.text = codes.tobytes().decode("utf-32-le")

    def __len__(self) -> int:
        return len(self.order)

    def __getitem__(self, at: int) -> str:
        place = self.order[at]
        return self.text[place : min(place + self.longest, self.ends[place])]


def _suffix_order(codes: np.ndarray, ends: np.ndarray, valid: np.ndarray, longest: int) -> np.ndarray:
    """Places marked valid, in order of their suffixes' first ``longest`` characters.

    Characters are their ranks in the chunk, 0 past a text's end; as many as fit
    into a word are sorted at once, then ranks of h characters order 2h of them.
    """
    used = np.unique(codes)
    rank = np.searchsorted(used, codes).astype(np.uint64) + np.uint64(1)
    bits = int(len(used)).bit_length()
    h = max(1, min(longest, 64 // bits))
    left, padded = ends - np.arange(len(codes)), np.concatenate([rank, np.zeros(h, np.uint64)])
    # what follows a text's end counts as nothing
    key = runs.span(padded, h, bits)[: len(codes)]
    short = np.flatnonzero(left < h)
    cut = (h - left[short]).astype(np.uint64) * np.uint64(bits)
    key[short] = key[short] >> cut << cut
    while True:
        order = runs.ordered([key], key)
        new = runs.changes([key.take(order)])
        if h >= longest or new.all():
            return order[valid[order]]
        r = np.empty(len(codes), np.uint64)
        r[order] = np.cumsum(new).astype(np.uint64)
        step = min(h, longest - h)
        ahead = np.zeros(len(codes), np.uint64)
        has = np.flatnonzero(left > step)
        ahead[has] = r[has + step]
        key, h = r << np.uint64(32) | ahead, h + step


def search(docs: DataFrame, patterns: DataFrame, how: str = "sorted", prefix: int | None = None, parts: int | None = None) -> DataFrame:
    """(pattern, occurrences, low, probes): ``low`` is the first match's rank in the suffix array, null without a match."""
    return searches(docs, patterns, [(how, prefix)], parts).drop("way")


def searches(docs: DataFrame, patterns: DataFrame, ways: list[tuple[str, int | None]], parts: int | None = None) -> DataFrame:
    """(way, pattern, occurrences, low, probes) of each way (its number in ``ways``) of searching one suffix array.

    The array is held by chunks of texts: each task sorts the suffixes of a few
    million characters at a time, as long as the longest pattern, and searches
    all patterns there.  Suffixes of a chunk before a pattern add up to its rank
    among all, and its matches to all matches, so that no suffix moves.  Probes
    are those made in all chunks.  Patterns of any length; null ones are left
    out, and the empty one is found everywhere.  Patterns are broadcast.
    """
    spark = docs.sparkSession
    ship_package(spark)
    wanted = patterns.select("pattern").filter("pattern IS NOT NULL").distinct()
    asked = sorted(r[0] for r in wanted.collect())
    longest = max(1, max(map(len, asked), default=1))
    sent = spark.sparkContext.broadcast(asked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked = sent.value
        sums = np.zeros((len(ways), 3, len(asked)), np.int64)
        for codes, lengths, own in runs.chunks((b.column(0) for b in batches), longest - 1) if asked else ():
            heads = Heads(codes, lengths, own, longest)
            for w, (how, prefix) in enumerate(ways):
                found = search_one_by_one(heads, asked) if how == "naive" else search_sorted(heads, asked, prefix)
                sums[w] += np.array(found, np.int64).T
        for w in range(len(ways)):
            low, n, made = sums[w]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(asked), w, np.int32)), pa.array(asked, pa.string()), pa.array(n), pa.array(low), pa.array(made)], ["way", "pattern", "occurrences", "low", "probes"])

    rows = docs.select("text")
    met = (rows.repartition(parts) if parts else rows).mapInArrow(run, "way int, pattern string, occurrences long, low long, probes long")
    # each pattern has a row of its own besides, so that those without a match are kept where there are no texts
    none = wanted.select(F.explode(F.sequence(F.lit(0), F.lit(len(ways) - 1))).alias("way"), "pattern", *(F.lit(0).cast("long").alias(c) for c in ("occurrences", "low", "probes")))
    all_ = met.unionAll(none).groupBy("way", "pattern").agg(*(F.sum(c).alias(c) for c in ("occurrences", "low", "probes")))
    return all_.withColumn("low", F.when(F.col("occurrences") > 0, F.col("low")))

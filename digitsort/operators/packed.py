"""The adaptive most-significant-digit sort over whole texts: all their k-mers, as packed words instead of rows.

Characters are their ranks among those that the texts use, in as few bits as that
takes, so that words compare as the texts do.  Prefixes are counted, heavy ones by
one character more, and packed into partitions of even size in key order.  Each
task sorts a few million k-mers at a time, equal ones are one with their number,
and cuts them at the borders; what moves, once, is the characters in which
neighbours differ, compressed.  A partition is sorted from these runs.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ship_package, written
from . import runs

#: K-mers of a partition, and those that a task sorts at once.
PART, FLUSH = 1 << 21, 1 << 22


def alphabet(texts: DataFrame) -> np.ndarray:
    """The code points that the texts use, ascending."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        used = np.zeros(0x110000, bool)
        for b in batches:
            used[runs.points(b.column(0))[0]] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(used))], ["code"])

    return np.array(sorted(r[0] for r in texts.mapInArrow(run, "code long").distinct().collect()), np.uint32)


def _kmers(batches: Iterator[pa.RecordBatch], k: int, used: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ranks of characters, which places begin a k-mer) of a few million characters at a time."""
    rank = np.zeros(int(used[-1]) + 1 if len(used) else 1, np.uint32)
    rank[used] = np.arange(len(used))
    for codes, lengths, own in runs.chunks((b.column(0) for b in batches), k - 1, FLUSH // 2):
        if len(codes) >= k:
            yield rank[codes], runs.within(lengths, np.clip(lengths - k + 1, 0, own))[: len(codes) - k + 1]


def _count(texts: DataFrame, k: int, used: np.ndarray, bits: int, depth: int, heavy: list[tuple[int, ...]]) -> Counter:
    """Rows of each prefix of ``depth`` characters; if given, only of those that go on from ``heavy`` ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter = Counter()
        for rank, valid in _kmers(batches, k, used):
            key, end = runs.words(rank, depth - bool(heavy), bits), rank[depth - 1 :][: len(valid)]
            for p in heavy or [()]:
                at = valid.copy() if heavy else valid
                for w, x in zip(key, p, strict=False):
                    at &= w[: len(valid)] == np.uint64(x)
                last = end[at] if heavy else key[0][: len(valid)][at]
                values, n = np.unique(last, return_counts=True)
                found.update({(p, x): m for x, m in zip(values.tolist(), n.tolist(), strict=True)})
        rows = list(found.items())
        yield pa.RecordBatch.from_arrays([pa.array([heavy.index(p) if p else 0 for (p, _), _ in rows], pa.int32()), pa.array([x for (_, x), _ in rows], pa.int64()), pa.array([n for _, n in rows], pa.int64())], ["p", "x", "n"])

    return Counter({(r["p"], r["x"]): r["n"] for r in texts.mapInArrow(run, "p int, x long, n long").groupBy("p", "x").agg(F.sum("n").alias("n")).collect()})


def plan(texts: DataFrame, k: int, used: np.ndarray, bits: int, least: int) -> tuple[list[list[int]], int]:
    """(the least k-mer of each partition but the first, as characters; rows): a prefix above 2N/3T is counted again by its next character."""
    depth = max(1, min(k, 16 // bits))
    spell = lambda x: [x >> bits * (depth - 1 - i) & (1 << bits) - 1 for i in range(depth)]
    bins = [(spell(x), n) for (_, x), n in _count(texts, k, used, bits, depth, []).items()]
    total = sum(n for _, n in bins)
    parts = max(1, min(-(-total // max(1, PART >> 4)), max(-(-total // PART), least)))
    done: list = []
    while bins:
        heavy = [b for b, n in bins if 3 * parts * n > 2 * total and depth < k]
        done += [(b, n) for b, n in bins if not (3 * parts * n > 2 * total and depth < k)]
        if not heavy:
            break
        depth += 1
        words = [tuple(int(w[0]) for w in runs.words(np.array(b, np.uint32), depth - 1, bits)) for b in heavy]
        bins = [([*heavy[p], x], n) for (p, x), n in _count(texts, k, used, bits, depth, words).items()]
    borders, room = [], 0
    for b, n in sorted(done):
        if room and room + n > -(-total // parts):
            borders.append(b)
            room = 0
        room += n
    return borders, total


def _planes(x: np.ndarray) -> bytes:
    """The bytes of numbers, those of one weight together."""
    return x.view(np.uint8).reshape(len(x), x.itemsize).T.tobytes()


def _from_planes(raw, n: int, kind: str) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(size, n).T).view(kind).ravel()


def _packed(key: runs.Words, n: np.ndarray, k: int, bits: int) -> bytes:
    """Sorted different k-mers, uncompressed: how many first characters each shares with the one before, their numbers, and the other characters."""
    chars = runs.letters(key, k, bits)
    same = np.concatenate([np.zeros((1, k), bool), chars[1:] == chars[:-1]])
    shared = same.argmin(axis=1).astype("<u4")
    return _planes(shared) + _planes(n.astype("<u8")) + chars[np.arange(k) >= shared[:, None]].tobytes()


def _unpacked(data: pa.Buffer, n: int, size: int, k: int, bits: int) -> tuple[runs.Words, np.ndarray]:
    raw, rows, per, key = memoryview(pa.decompress(data, decompressed_size=size, codec="zstd")), np.arange(n), 64 // bits, []
    shared = _from_planes(raw[: 4 * n], n, "<u4")
    other = np.frombuffer(raw[12 * n :], np.uint8 if bits <= 8 else np.uint32)
    at = np.cumsum(k - shared.astype(np.int64)) - k  # of a row's character 0, were it there
    for j in range(k):
        if j % per == 0:
            key.append(np.zeros(n, np.uint64))
        owner = np.maximum.accumulate(np.where(shared <= j, rows, 0))
        key[-1] = key[-1] << np.uint64(bits) | other[at[owner] + j]
    return key, _from_planes(raw[4 * n : 12 * n], n, "<u8").astype(np.int64)


def _sorted(key: runs.Words, n: np.ndarray | None = None) -> tuple[runs.Words, np.ndarray]:
    """Different k-mers in order, and the sums of their n, which is 1 where it isn't given."""
    order = np.argsort(key[0])
    if len(key) > 1:
        head = key[0][order]
        same = head[1:] == head[:-1]
        tied = np.flatnonzero(np.append(same, False) | np.concatenate([[False], same]))
        inner = order[tied]
        order[tied] = inner[np.lexsort([w[inner] for w in key[:0:-1]] + [head[tied]])]
    key = [w[order] for w in key]
    first = np.flatnonzero(runs.changes(key))
    return [w[first] for w in key], np.diff(first, append=len(order)) if n is None else np.add.reduceat(n[order], first)


def _place(key: runs.Words, border: list[int]) -> int:
    """K-mers before the border."""
    low, high = 0, len(key[0])
    for w, x in zip(key, border, strict=True):
        a, b = np.searchsorted(w[low:high], np.uint64(x), "left"), np.searchsorted(w[low:high], np.uint64(x), "right")
        low, high = low + int(a), low + int(b)
    return low


def sort(texts: DataFrame, k: int) -> tuple[DataFrame, np.ndarray, int]:
    """((part, n, size, data) in partitions in order, the alphabet, bits of a character): the k-mers of ``text``, sorted runs of each partition."""
    if k < 1:
        raise ValueError("k must be positive")
    spark, texts = texts.sparkSession, texts.select("text")
    ship_package(spark)
    used = alphabet(texts)
    bits = max(1, (len(used) - 1).bit_length()) if len(used) else 1
    borders, _ = plan(texts, k, used, bits, 2 * spark.sparkContext.defaultParallelism)
    ends = [[int(w[0]) for w in runs.words(np.array(b + [0] * (k - len(b)), np.uint32), k, bits)] for b in borders]

    def cut(held: list[runs.Words]) -> Iterator[pa.RecordBatch]:
        key, n = _sorted([np.concatenate(w) for w in zip(*held, strict=True)])
        at = [0, *(_place(key, e) for e in ends), len(n)]
        rows, codec = [], pa.Codec("zstd", compression_level=6)
        for p, (a, b) in enumerate(zip(at[:-1], at[1:], strict=True)):
            if b > a:
                raw = _packed([w[a:b] for w in key], n[a:b], k, bits)
                rows.append((p, b - a, len(raw), codec.compress(raw, asbytes=True)))
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.binary()), strict=True)], ["part", "n", "size", "data"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for rank, valid in _kmers(batches, k, used):
            key = [w[valid] for w in runs.words(rank, k, bits)]
            if len(key[0]):
                held.append(key)
                rows += len(key[0])
            if rows >= FLUSH:
                yield from cut(held)
                held, rows = [], 0
        if held:
            yield from cut(held)

    moved = texts.mapInArrow(run, "part int, n int, size long, data binary").repartitionById(len(ends) + 1, F.col("part"))
    return moved, used, bits


Make = Callable[[Callable[[int], np.ndarray], np.ndarray, np.ndarray], dict]


def ranked(texts: DataFrame, k: int, fields: str, make: Make, moves: dict[str, Column] | None = None) -> DataFrame:
    """What ``make`` gives (its ``fields``) of the different k-mers of each partition in order: (what gives code points, a row each, of the first or of all k characters; their numbers; the first one's position there).

    ``moves``: of fields that hold positions, what the column is where ``_base``
    k-mers lie before the partition.
    """
    stored, used, bits = sort(texts, k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got, part = [], None
        for b in batches:
            for p, n, size, data in zip(*(b.column(c).to_pylist() for c in range(3)), b.column(3), strict=True):
                got.append(_unpacked(data.as_buffer(), n, size, k, bits))
                part = p
        if part is None:
            return
        key, n = _sorted([np.concatenate(w) for w in zip(*(x for x, _ in got), strict=True)], np.concatenate([x for _, x in got]))
        got = []
        pos, per = np.cumsum(n) - n, min(k, 64 // bits)
        for s in range(0, len(n), 1 << 20):
            x = slice(s, s + (1 << 20))
            made = make(lambda j, part=[w[x] for w in key]: used[runs.letters(part, k, bits) if j > 1 else part[0][:, None] >> np.uint64(bits * (per - 1))], n[x], pos[x])
            rows = len(next(iter(made.values())))
            yield pa.RecordBatch.from_pydict({**made, "_part": pa.array(np.full(rows, part, np.int32)), "_rows": pa.array(np.where(np.arange(rows) == 0, n[x].sum(), 0))})

    rows = written(stored.mapInArrow(run, f"{fields}, _part int, _rows long"), "ranked")
    sizes = {r["_part"]: r["n"] for r in rows.groupBy("_part").agg(F.sum("_rows").alias("n")).collect()}  # as many rows as partitions
    base = np.cumsum([0] + [sizes.get(p, 0) for p in range(max(sizes, default=0))]).tolist()
    placed = rows.withColumn("_base", F.get(F.lit(base).cast("array<long>"), F.col("_part")))
    return placed.withColumns(moves or {}).drop("_part", "_rows", "_base")


def by_first(texts: DataFrame, k: int = 16) -> DataFrame:
    """(first, n, low, high, sum_pos): the positions of the sorted k-mers, by their first character."""

    def make(codes: Callable[[int], np.ndarray], n: np.ndarray, pos: np.ndarray) -> dict:
        first = codes(1)[:, 0]
        at = np.flatnonzero(runs.changes([first]))
        low, many = pos[at], np.add.reduceat(n, at)
        return {"first": pa.array([chr(c) for c in first[at]]), "n": pa.array(many), "low": pa.array(low), "high": pa.array(low + many - 1), "sum_pos": pa.array(np.add.reduceat(n * pos + n * (n - 1) // 2, at))}

    base = F.col("_base")
    moves = {"low": F.col("low") + base, "high": F.col("high") + base, "sum_pos": F.col("sum_pos") + base * F.col("n")}
    found = ranked(texts, k, "first string, n long, low long, high long, sum_pos long", make, moves)
    return found.groupBy("first").agg(F.sum("n").alias("n"), F.min("low").alias("low"), F.max("high").alias("high"), F.sum("sum_pos").alias("sum_pos"))


def kmers(texts: DataFrame, k: int = 16) -> DataFrame:
    """(kmer, n, pos): the different k-mers, their number, and the position of the first one among all in order."""
    make = lambda codes, n, pos: {"kmer": pa.array(["".join(map(chr, row)) for row in codes(k).tolist()]), "n": pa.array(n), "pos": pa.array(pos)}
    return ranked(texts, k, "kmer string, n long, pos long", make, {"pos": F.col("pos") + F.col("_base")})

"""Ranks of all whole suffixes: chosen places are ranked first, then each suffix by a few characters and the chosen place after them.

A window of places chooses the least run of a few characters that begins in it.
Equal characters choose alike, so suffixes that share ``DEPTH`` characters are in
the order of the places chosen after them, as many characters on.  Chosen places
lead to the next ones in the same way: their first characters give them ranks,
and of those tied the ranks along the way decide, seven times as far in each step.
Then every suffix is sorted once, by words of its characters and the rank of its
chosen place, which leaves no ties but equal ends of texts.  Runs send sorted words
and places a few ranges at a time, and their places come back with ranks.
"""

from __future__ import annotations

import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ..session import release, ship_package, written
from . import runs, suffixes
from .suffixes import SENT, Letters, Make, _cut, _from_planes, _met, _numbers, _ordered, _planes, _ranks, _row_and_ranks, _rows, _settled, _text, _tied

#: Characters that sort before chosen places do, chosen places that a step compares, passes over the ranges at most, groups of runs that meet their ranks at once.
DEPTH, STEP, PASSES, GROUPS = 16, 7, 16, 4
BLOCK = 1 << 15

STATE = "run long, n long, jumps binary, r binary, ties binary, open long, sample array<long>"


def _row(schema: dict[str, pa.DataType], **values) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([values[c]], t) for c, t in schema.items()], list(schema))


def _short(x: np.ndarray) -> bytes:
    """Numbers in as many bytes as the largest takes; such that hardly compress."""
    size = max(1, -(-int(x.max(initial=0)).bit_length() // 8))
    x = np.ascontiguousarray(x)
    return x.astype("<u4").tobytes() if size == 4 else np.ascontiguousarray(x.astype("<u8", copy=False).view(np.uint8).reshape(-1, 8)[:, :size]).tobytes()


def _from_short(data: bytes, n: int) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    if n:
        size = len(data) // n
        if size == 4:
            return np.frombuffer(data, "<u4").astype(np.int64)
        out[:, :size] = np.frombuffer(data, np.uint8).reshape(n, size)
    return out.view("<i8").ravel()


def _in_order(columns: list[np.ndarray]) -> np.ndarray:
    """Rows in order of their columns, equal ones as they come: after the first column, as many bits at once as go beside a group's number."""
    n = len(columns[0])
    if not n:
        return np.empty(0, np.int64)
    order = np.argsort(columns[0])
    new = runs.changes([columns[0].take(order)])
    room, keys, free = 64 - n.bit_length(), [], 0
    for c in columns[1:]:
        left = int(c.max()).bit_length()
        while left:
            if not free:
                keys.append([])
                free = room
            take = min(left, free)
            left, free = left - take, free - take
            keys[-1].append((c, np.uint64(left), np.uint64((1 << take) - 1), np.uint64(take)))
    for parts in keys:
        if not len(tied := _tied(new)):
            break
        inner = order[tied]
        key = np.cumsum(new)[tied].astype(np.uint64)
        for c, left, mask, take in parts:
            key = key << take | c.take(inner) >> left & mask
        by = np.argsort(key)
        order[tied] = inner[by]
        new[tied] = runs.changes([key[by]])
    if len(tied := _tied(new)):
        order[tied] = _settled(order[tied], new[tied])[0]
    return order


def _before(columns: list[np.ndarray], border: np.ndarray) -> int:
    """Rows before the border."""
    low, high = 0, len(columns[0])
    for c, x in zip(columns, border, strict=True):
        low, high = low + int(np.searchsorted(c[low:high], x, "left")), low + int(np.searchsorted(c[low:high], x, "right"))
    return low


def _packed(marks: np.ndarray, codec: pa.Codec) -> bytes:
    return codec.compress(np.packbits(marks), asbytes=True)


def _unpacked(data: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(pa.decompress(data, decompressed_size=-(-n // 8), codec="zstd"), np.uint8), count=n).astype(bool)


class Chosen:
    """Places that windows of a run choose.  ``at``: these, ascending; ``turns``: marks the places whose window chooses a later one than the window before."""

    def __init__(self, letters: Letters, ranks: np.ndarray, lengths: np.ndarray) -> None:
        k = letters.k
        short = max(1, min(k // 4, letters.per))
        wide = k - short
        bits, to = 64 // letters.per, np.zeros(len(ranks), np.int32)
        kind = np.uint32 if bits * short <= 32 else np.uint64
        for s in range(0, len(ranks) - wide - short + 2, BLOCK):  # as much as stays in a core's cache: a hash of 16 bits above the place
            part = ranks[s : s + BLOCK + wide + short - 2].astype(kind)
            size = len(part) - short + 1
            key = part[:size]
            for j in range(1, short):
                key = key << kind(bits) | part[j : j + size]
            key = (key + kind(1)) * kind(0x9E3779B1)
            key ^= key >> kind(15)
            if kind is np.uint64:
                key ^= key >> kind(32)
            key = (key.astype(np.uint32) * np.uint32(0x85EBCA77)) >> np.uint32(16) << np.uint32(16)
            key |= np.arange(size, dtype=np.uint32)
            n = 1
            while 2 * n <= wide:
                key, n = np.minimum(key[:-n], key[n:]), 2 * n
            if n < wide:
                key = np.minimum(key[: n - wide], key[wide - n :])
            to[s : s + len(key)] = (key & np.uint32(0xFFFF)).astype(np.int32) + np.int32(s)
        first = np.cumsum(lengths + k) - lengths - k
        marks = np.zeros(len(ranks) + 1, np.int8)
        marks[first] += 1
        marks[first + np.maximum(0, lengths - k + 1)] -= 1
        valid = np.flatnonzero(np.cumsum(marks[:-1], dtype=np.int8))  # where all of a window and its characters are the text's
        to = to[valid]
        new = np.diff(to, prepend=np.int32(-1)) != 0
        self.at, self.turns = to[new].astype(np.int64), np.zeros(len(ranks), bool)
        self.turns[valid[new]] = True
        self.left = (first + lengths)[np.searchsorted(first, self.at, "right") - 1] - self.at
        on = np.cumsum(self.turns, dtype=np.int32)[np.minimum(self.at + 1, len(ranks) - 1)] - 1
        self.jumps = np.where(self.left > k, on - np.arange(len(on)), 0)  # to the place that the next window chooses, 0 without one


def _jumps(row: dict) -> np.ndarray:
    return np.frombuffer(pa.decompress(row["jumps"], decompressed_size=row["n"], codec="zstd"), np.uint8)


def _along(jumps: np.ndarray, h: int) -> np.ndarray:
    """Where h jumps lead from each place, len(jumps) past the last one."""
    n = len(jumps)
    to = np.append(np.where(jumps > 0, np.arange(n) + jumps, n), n)
    while h > 1:
        step = to
        for _ in range(STEP - 1):
            to = step[to]
        h //= STEP
    return to


def _ways(row: dict, h: int, paired: bool) -> tuple[np.ndarray, ...]:
    """(ranks, which are tied, whether the way of each tied place goes on, words of the tied: rank and 1 + those along the way; their order, which differ)."""
    n = row["n"]
    r, tied = _from_short(row["r"], n), _unpacked(row["ties"], n)
    to, past, p = _along(_jumps(row), h), np.append(r + 1, 0).astype(np.uint64), np.flatnonzero(tied)
    words, at = [r[p].astype(np.uint64)], p
    for _ in range(STEP - 1):
        at = to[at]
        words.append(past[at])
    goes_on = words[-1] > 0
    if paired:
        words[1:] = [words[j] << np.uint64(32) | words[j + 1] for j in range(1, STEP, 2)]
    words = np.stack(words, axis=1)
    return r, tied, goes_on, words, *_ordered(words)


def _ranked_places(table: DataFrame, letters: Letters, sample: np.ndarray, numbers: dict[int, int]) -> DataFrame:
    """STATE of each run: the final rank of each chosen place among all, ties by run and place."""
    spark, k, every = table.sparkSession, letters.k, max(1, suffixes.PART // suffixes.SAMPLES)
    kinds = {"run": pa.int64(), "n": pa.int64(), "jumps": pa.binary(), "r": pa.binary(), "ties": pa.binary(), "open": pa.int64(), "sample": pa.list_(pa.int64())}

    def places(row: dict) -> tuple[Chosen, np.ndarray, np.ndarray, np.ndarray]:
        lengths = np.array(row["lengths"])
        ranks, _ = letters.padded(_text(row), lengths, lengths)
        chosen = Chosen(letters, ranks, lengths)
        words = letters.words(ranks, chosen.at)
        return chosen, words, *_ordered(words)

    def out(row: dict, r: np.ndarray, tied: np.ndarray, jumps: bytes) -> pa.RecordBatch:
        codec, open_ = pa.Codec("zstd", compression_level=1), int(tied.sum())
        return _row(kinds, run=row["run"], n=len(r), jumps=jumps, r=_short(r), ties=_packed(tied, codec), open=open_, sample=np.sort(r[tied])[every // 2 % max(1, open_) :: every])

    def settled(r: np.ndarray, at: np.ndarray, first: np.ndarray, got: list[tuple], new: np.ndarray, goes_on: np.ndarray) -> np.ndarray:
        """Puts down the ranks of places ``at``, in order; the first of their class where still tied, which is returned."""
        group = np.flatnonzero(new)
        many = np.diff(group, append=len(at))
        still = np.repeat(np.concatenate([x[3] for x in got]) > 0, many) & goes_on
        r[at] = np.where(still, np.repeat(first - np.concatenate([x[2] for x in got]), many), np.repeat(first - group, many) + np.arange(len(at)))
        return still

    def first_sent(batches: Iterator[pa.RecordBatch], borders: np.ndarray) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            chosen, words, order, new = places(row)
            if len(order):
                first = np.flatnonzero(new)
                yield from _cut(words[order[first]], np.diff(first, append=len(order)), row["run"], borders, 0, len(borders) + 1)

    def begin(base: np.ndarray):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            row, got = _row_and_ranks(batches)
            if row is None:
                return
            chosen, _, order, new = places(row)
            r, tied = np.empty(len(order), np.int64), np.zeros(len(order), bool)
            if len(order):
                first = np.concatenate([base[p] + np.cumsum(x) for p, x, *_ in got])
                tied[order] = settled(r, order, first, got, new, (chosen.left >= k)[order])  # shorter ones are equal as a whole
            yield out(row, r, tied, pa.Codec("zstd", compression_level=1).compress(chosen.jumps.astype(np.uint8).tobytes(), asbytes=True))

        return run

    def ways_sent(h: int, paired: bool, borders: np.ndarray):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _rows(batches):
                *_, words, order, new = _ways(row, h, paired)
                first = np.flatnonzero(new)
                yield from _cut(words[order[first]], np.diff(first, append=len(order)), row["run"], borders, 0, len(borders) + 1)

        return run

    def step(h: int, paired: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            row, got = _row_and_ranks(batches)
            if row is None:
                return
            r, tied, goes_on, words, order, new = _ways(row, h, paired)
            first = words[order[np.flatnonzero(new)], 0].astype(np.int64) + np.concatenate([np.cumsum(x) for _, x, *_ in got])
            at = np.flatnonzero(tied)[order]
            tied[at] = settled(r, at, first, got, new, goes_on[order])
            yield out(row, r, tied, row["jumps"])

        return run

    parts = max(1, min(len(sample), max(len(sample) // (4 * suffixes.SAMPLES), 2 * spark.sparkContext.defaultParallelism)))
    borders = np.unique(sample[[len(sample) * p // parts for p in range(1, parts)]], axis=0) if parts > 1 else sample[:0]
    sent = table.select("run", "lengths", "size", "text").mapInArrow(lambda batches: first_sent(batches, borders), SENT)
    ranks = written(_ranks(sent, sample.shape[1], 0, len(borders) + 1, True), "ranks")
    sizes = {r["part"]: r["all"] for r in ranks.filter("all > 0").select("part", "all").collect()}
    base = np.cumsum([0] + [sizes.get(p, 0) for p in range(len(borders) + 1)])
    paired, h = int(base[-1]) < (1 << 32) - 1, 1
    _freed(spark)
    now = written(_met(table.select("run", "lengths", "size", "text"), ranks, numbers).mapInArrow(begin(base), STATE), "places")
    release(ranks)
    _freed(spark)
    while open_ := _numbers(state := now.filter("open > 0")):
        low = np.array(sorted(r[0] for r in state.select(F.explode("sample")).collect()), np.uint64)
        parts = max(1, min(len(low), max(len(low) // suffixes.SAMPLES, 2 * spark.sparkContext.defaultParallelism)))
        low = np.unique(low[[len(low) * p // parts for p in range(1, parts)]]) if parts > 1 else low[:0]
        width = 1 + ((STEP - 1) // 2 if paired else STEP - 1)
        borders = np.concatenate([low[:, None], np.zeros((len(low), width - 1), np.uint64)], axis=1)
        sent = state.select("run", "n", "jumps", "r", "ties").mapInArrow(ways_sent(h, paired, borders), SENT)
        ranks = written(_ranks(sent, width, 0, len(borders) + 1, True, True), "ranks")
        new = _met(state.select("run", "n", "jumps", "r", "ties"), ranks, open_).mapInArrow(step(h, paired), STATE)
        before, now = now, written(new.unionAll(now.filter("open = 0")), "places")
        release(before, ranks)
        _freed(spark)
        h *= STEP
    return now


def _freed(spark) -> None:
    gc.collect()
    spark.sparkContext._jvm.System.gc()  # until then Spark keeps the files of shuffles


def _dealt(rows: DataFrame, numbers: dict[int, int]) -> DataFrame:
    """The rows of these runs, each run in a partition of its own."""
    number = F.broadcast(rows.sparkSession.createDataFrame(list(numbers.items()), "run long, _to int"))
    return rows.join(number, "run").repartitionById(len(numbers), F.col("_to")).drop("_to")


def _union(tables: list[DataFrame]) -> DataFrame:
    out = tables[0]
    for x in tables[1:]:
        out = out.unionAll(x)
    return out


def _bins(letters: Letters, x: np.ndarray) -> np.ndarray:
    """The leading 16 bits or fewer of what begins at each place."""
    if letters.per == 8:
        return np.append(x[:-1].astype(np.uint16) << 8 | x[1:], np.uint16(0))
    return x >> x.dtype.type(max(0, len(letters.used).bit_length() - 16))


def whole_ranked(docs: DataFrame, k: int, fields: str, make: Make) -> DataFrame:
    """What ``make`` gives (its ``fields``) for all suffixes, ranked by their whole text; only equal ones tie, by document and place.

    Texts are not cut: one lies in one run.  ``k`` characters at most (2 at least)
    are compared before chosen places are; the ranks are the same for any.
    """
    spark = docs.sparkSession
    ship_package(spark)
    k = max(2, min(k, DEPTH))
    table = suffixes.stored(docs, 2 * k, cut=False)
    kind = to_arrow_type(docs.schema["doc_id"].dataType)
    numbers = _numbers(table)
    if not numbers:
        return spark.createDataFrame([], fields)
    letters = Letters(np.array(sorted(r[0] for r in table.select(F.explode("used")).distinct().collect()), np.int64), k)
    total = table.select(F.sum(F.aggregate("own", F.lit(0).cast("long"), lambda x, y: x + y))).first()[0]
    codes = [np.array(r[0], np.int64) for r in table.select(F.explode("sample")).collect()]
    sizes = np.array([len(c) for c in codes])
    padded, _ = letters.padded(np.concatenate(codes), sizes, sizes)
    sample = letters.words(padded, Chosen(letters, padded, sizes).at)
    state = _ranked_places(table, letters, sample[_ordered(sample)[0]], numbers)

    part = max(1, suffixes.PART // 2)
    every, width = max(1, part // suffixes.SAMPLES), letters.wide // letters.per + 1
    kinds = {"run": pa.int64(), "ids": pa.list_(kind), "own": pa.list_(pa.int64()), "size": pa.int64(), "text": pa.binary(), "turns": pa.binary(), "n": pa.int64(), "r": pa.binary(), "sample": pa.binary()}

    def keys(ranks: np.ndarray, turns: np.ndarray, r: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
        """Words of the characters at places, and 1 + the rank of the chosen place, 0 where the text ends before."""
        whole = ranks[at + k - 1] != 0
        last = np.zeros(len(at), np.uint64)
        last[whole] = (r[(np.cumsum(turns, dtype=np.int32) - 1)[at[whole]]] + 1).astype(np.uint64)
        return [*np.ascontiguousarray(letters.words(ranks, at).T), last]

    def both(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row = r = None
        for x in _rows(batches):
            if x["text"] is None:
                r = x
            else:
                row = x
        if row is None:
            return
        lengths, codec = np.array(row["own"]), pa.Codec("zstd", compression_level=1)
        ranks, own = letters.padded(_text(row), lengths, lengths)
        turns = Chosen(letters, ranks, lengths).turns
        at = np.flatnonzero(own)[every // 2 % int(lengths.sum()) :: every]
        sample = keys(ranks, turns, _from_short(r["r"], r["n"]), at)
        yield _row(kinds, run=row["run"], ids=row["ids"], own=row["own"], size=len(ranks), text=codec.compress(ranks.tobytes(), asbytes=True), turns=_packed(turns, codec), n=r["n"], r=r["r"], sample=np.stack(sample, axis=1).astype(">u8").tobytes())

    ids, groups = f"array<{dict(docs.dtypes)['doc_id']}>", min(GROUPS, len(numbers))
    all_ = []
    for g in range(groups):
        some = {x: i // groups for x, i in numbers.items() if i % groups == g}
        rows = table.select("run", "ids", "own", "size", "text").unionByName(state.select("run", "n", "r"), allowMissingColumns=True)
        all_.append(written(_dealt(rows, some).mapInArrow(both, f"run long, ids {ids}, own array<long>, size long, text binary, turns binary, n long, r binary, sample binary"), "suffixes"))
        _freed(spark)
    release(table, state)
    tables, all_ = all_, _union(all_)

    sample = np.concatenate([np.frombuffer(r[0], ">u8").astype(np.uint64).reshape(-1, width) for r in all_.select("sample").collect()])
    sample = sample[_ordered(sample)[0]]
    parts = max(1, min(len(sample), max(-(-total // part), min(2 * spark.sparkContext.defaultParallelism, total // max(1, part >> 4)))))
    passes = max(1, min(PASSES, parts // (2 * suffixes.EACH)))
    lead = sample[:, 0] >> np.uint64(48 if letters.per == 8 else 64 - 64 // letters.per)
    bins = (lead if letters.per == 8 else _bins(letters, lead)).astype(np.int64)
    counts = np.bincount(bins, minlength=1 << 16)
    of_bin = ((np.cumsum(counts) - counts) * passes // max(1, len(sample))).clip(0, passes - 1).astype(np.uint8)
    of_sample = of_bin[bins]

    def sent(g: int, borders: np.ndarray):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            codec = pa.Codec("zstd", compression_level=1)
            for row in _rows(batches):
                ranks = np.frombuffer(pa.decompress(row["text"], decompressed_size=row["size"] * letters.kind.itemsize, codec="zstd"), letters.kind)
                at = np.flatnonzero(of_bin[_bins(letters, ranks)] == g)
                at = at[ranks[at] != 0]
                if not len(at):
                    continue
                words = keys(ranks, _unpacked(row["turns"], row["size"]), _from_short(row["r"], row["n"]), at)
                order = _in_order(words)
                words, at = [x.take(order) for x in words], at[order]
                cuts = [0, *(_before(words, b) for b in borders), len(at)]
                for p, (s, e) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                    if e > s:
                        yield _row(pieces, part=p, run=row["run"], n=e - s, words=[*(_planes(x[s:e], codec) for x in words[:-1]), _short(words[-1][s:e])], at=_short(at[s:e]))

        return run

    pieces = {"part": pa.int32(), "run": pa.int64(), "n": pa.int64(), "words": pa.list_(pa.binary()), "at": pa.binary()}
    found = {"run": pa.int64(), "part": pa.int32(), "many": pa.int64(), "all": pa.int64(), "at": pa.binary(), "pos": pa.binary()}

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, codec = sorted(_rows(batches), key=lambda r: r["run"]), pa.Codec("zstd", compression_level=1)
        if not rows:
            return
        words = [np.empty(sum(r["n"] for r in rows), np.uint64) for _ in range(width)]
        at = 0
        for r in rows:
            for j, x in enumerate(r.pop("words")):
                words[j][at : at + r["n"]] = (_from_planes if j < width - 1 else _from_short)(x, r["n"])
            at += r["n"]
        order = _in_order(words)
        del words
        pos = np.empty(len(order), np.int64)
        pos[order] = np.arange(len(order))
        at = 0
        for i, r in enumerate(rows):
            mine = pos[at : at + r["n"]]
            at += r["n"]
            yield _row(found, run=r["run"], part=r["part"], many=r["n"], all=len(pos) if i == 0 else 0, at=r["at"], pos=_planes(np.diff(mine, prepend=0), codec))

    def back(base: np.ndarray):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            row, at, rank = None, [], []
            for x in _rows(batches):
                if x["part"] is None:
                    row = x
                else:
                    at.append(_from_short(x["at"], x["many"]))
                    rank.append(base[x["part"]] + np.cumsum(_from_planes(x["pos"], x["many"])))
            if not at:
                return
            at, rank = np.concatenate(at), np.concatenate(rank)
            by = np.argsort(at)
            at, rank, own = at[by], rank[by], np.array(row["own"])
            first = np.cumsum(own + k) - own - k
            doc = np.repeat(np.arange(len(own)), np.diff(np.searchsorted(at, first), append=len(at)))
            yield pa.RecordBatch.from_pydict(make(pa.array(row["ids"], kind), doc, at - first[doc], rank))

        return run

    results, low = [], 0
    for g in range(passes):
        chosen = sample[of_sample == g]
        n = max(1, min(len(chosen), -(-parts * len(chosen) // len(sample))))
        borders = np.unique(chosen[[len(chosen) * p // n for p in range(1, n)]], axis=0) if n > 1 else chosen[:0]
        out = all_.select("run", "size", "text", "turns", "n", "r").mapInArrow(sent(g, borders), "part int, run long, n long, words array<binary>, at binary")
        ranks = written(out.repartitionById(len(borders) + 1, F.col("part")).mapInArrow(merged, "run long, part int, many long, all long, at binary, pos binary"), "ranks")
        sizes = {r["part"]: r["all"] for r in ranks.filter("all > 0").select("part", "all").collect()}
        base = low + np.cumsum([0] + [sizes.get(p, 0) for p in range(len(borders) + 1)])
        low = int(base[-1])
        _freed(spark)
        met = _dealt(all_.select("run", "ids", "own").unionByName(ranks.drop("all"), allowMissingColumns=True), numbers)
        results.append(written(met.mapInArrow(back(base), fields), "ranked"))
        release(ranks)
        _freed(spark)
    release(*tables)
    return _union(results)

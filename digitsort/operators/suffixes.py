"""Ranks of all suffixes by their first characters: sorted runs of characters move one way, ranks the other.

Documents are cut into runs of a few million characters in order of their ids, so
that equal suffixes tie as their runs do.  A run is sorted where it is; what moves
are its different prefixes in order, to the partition of their range, and back
comes the rank of each.  Neither documents' ids nor places move: a run sorted
again finds its places in the order of the ranks.  Ranges are taken a few
partitions at a time, so that scratch space stays a fixed part of the prefixes.
"""

from __future__ import annotations

import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ..session import ship_package, written
from . import runs

#: Suffixes of a partition and of a run, passes over the ranges, partitions of a pass at least, and samples of a partition for its borders.
PART, RUN, PASSES, EACH, SAMPLES = 1 << 21, 1 << 22, 5, 8, 32

Run = tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray, np.ndarray]


def _runs(batches: Iterator[pa.RecordBatch], size: int, overlap: int, cut: bool) -> Iterator[Run]:
    """(ids, starts, own, lengths, code points) of runs: pieces of texts with ``own`` characters from ``starts`` on, and up to ``overlap`` that follow."""
    ids, starts, own, parts, room = [], [], [], [], 0

    def run() -> Run:
        return pa.concat_arrays(ids), np.array(starts, np.int64), np.array(own, np.int64), np.array([len(p) for p in parts], np.int64), np.concatenate(parts)

    for b in batches:
        codes, sizes = runs.points(b.column(1))
        at = 0
        for d, n in enumerate(sizes.tolist()):
            s = 0
            while s < n:
                take = min(size - room, n - s) if cut else n
                ids.append(b.column(0).slice(d, 1))
                starts.append(s)
                own.append(take)
                parts.append(codes[at + s : min(at + n, at + s + take + overlap)])
                s, room = s + take, room + take
                if room >= size:
                    yield run()
                    ids, starts, own, parts, room = [], [], [], [], 0
            at += n
    if parts:
        yield run()


def stored(docs: DataFrame, k: int, cut: bool = True) -> DataFrame:
    """A scratch table with a row for each run: its pieces, compressed text, code points used, and every so many a suffix's first k characters."""
    rows = docs.select("doc_id", "text").filter(F.length("text") > 0)
    kind = dict(rows.dtypes)["doc_id"]
    by = F.col("doc_id").asc_nulls_last()
    each, most = max(1, PART // SAMPLES), RUN

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first, codec = TaskContext.get().partitionId() << 32, pa.Codec("zstd", compression_level=6)
        for no, (ids, starts, own, lengths, codes) in enumerate(_runs(batches, most, k - 1, cut)):
            raw, ends = runs.encoded(codes), np.cumsum(lengths)
            places = np.flatnonzero(runs.within(lengths, own))[each // 2 % max(1, int(own.sum())) :: each]
            stop = np.minimum(places + k, ends[np.searchsorted(ends, places, "right")])
            sample = [codes[a:b].tolist() for a, b in zip(places.tolist(), stop.tolist(), strict=True)]
            row = {"run": first + no, "ids": ids.to_pylist(), "starts": starts, "own": own, "lengths": lengths, "size": len(raw), "text": codec.compress(raw, asbytes=True), "used": np.unique(codes), "sample": sample}
            kinds = {"run": pa.int64(), "ids": pa.list_(ids.type), "starts": pa.list_(pa.int64()), "own": pa.list_(pa.int64()), "lengths": pa.list_(pa.int64()), "size": pa.int64(), "text": pa.binary(), "used": pa.list_(pa.int64()), "sample": pa.list_(pa.list_(pa.int64()))}
            yield pa.RecordBatch.from_arrays([pa.array([row[c]], t) for c, t in kinds.items()], list(kinds))

    ranged = rows.repartitionByRange(by).sortWithinPartitions(by)
    schema = f"run long, ids array<{kind}>, starts array<long>, own array<long>, lengths array<long>, size long, text binary, used array<long>, sample array<array<long>>"
    return written(ranged.mapInArrow(run, schema), "runs")


class Letters:
    """Characters as their ranks among those used, from 1 on; what follows a text counts as 0."""

    def __init__(self, used: np.ndarray, k: int) -> None:
        self.used, self.k = used, k
        self.kind = np.dtype(np.uint8 if len(used) < 1 << 8 else np.uint16 if len(used) < 1 << 16 else np.uint32)
        self.per = 8 // self.kind.itemsize
        self.wide = -(-k // self.per) * self.per

    def padded(self, codes: np.ndarray, lengths: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ranks with k zeros after each piece and at the end as many as a row takes, which places begin the run's own suffixes)."""
        rank = np.zeros(int(self.used[-1]) + 1, self.kind)
        rank[self.used] = np.arange(1, len(self.used) + 1)
        first = np.cumsum(lengths + self.k) - lengths - self.k
        out = np.zeros(int((lengths + self.k).sum()) + self.wide, self.kind)
        found = rank[codes]
        if len(lengths) << 6 < len(codes):
            for a, b, n in zip(first.tolist(), (np.cumsum(lengths) - lengths).tolist(), lengths.tolist(), strict=True):
                out[a : a + n] = found[b : b + n]
        else:
            out[np.arange(len(codes)) + np.repeat(first - (np.cumsum(lengths) - lengths), lengths)] = found
        own_places = np.zeros(len(out), np.int8)
        own_places[first] += 1
        own_places[first + own] -= 1
        return out, np.cumsum(own_places, dtype=np.int8).astype(bool)

    def heads(self, ranks: np.ndarray) -> np.ndarray:
        """The first word from each place on, of k characters at most."""
        bits = 64 // self.per
        found = runs.span(np.concatenate([ranks, np.zeros(self.per - 1, self.kind)]).astype(np.uint64), self.per, bits)
        rest = np.uint64(bits * max(0, self.per - self.k))
        return found >> rest << rest if rest else found

    def words(self, ranks: np.ndarray, places: np.ndarray) -> np.ndarray:
        """The k characters from each place on, in words that order as they do: a row each."""
        rows = np.lib.stride_tricks.sliding_window_view(ranks, self.wide)[places]
        rows[:, self.k :] = 0
        return self.joined(rows)

    def joined(self, rows: np.ndarray) -> np.ndarray:
        return rows.astype(self.kind.newbyteorder(">"), copy=False).view(">u8").astype(np.uint64)

    def spelled(self, sample: list[list[int]]) -> np.ndarray:
        rows = np.zeros((len(sample), self.wide), self.kind)
        for row, codes in zip(rows, sample, strict=True):
            row[: len(codes)] = np.searchsorted(self.used, codes) + 1
        return self.joined(rows)


def _tied(new: np.ndarray) -> np.ndarray:
    return np.flatnonzero(~(new & np.append(new[1:], True)))


def _settled(order: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the order with equal ones by place, their groups): one sort of plain numbers."""
    both = np.cumsum(new).astype(np.uint64) << np.uint64(32) | order.astype(np.uint64)
    both.sort()
    return (both & np.uint64(0xFFFFFFFF)).astype(np.int64), both >> np.uint64(32)


def _ordered(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows in order, which differ from the one before); equal rows keep their order."""
    order = np.argsort(words[:, 0])
    new = runs.changes([words[order, 0]])
    for j in range(1, words.shape[1]):
        for half in (words[:, j] >> np.uint64(32), words[:, j] & np.uint64(0xFFFFFFFF)):
            if not len(tied := _tied(new)):
                break
            inner = order[tied]
            if not half[inner].any():
                continue
            key = np.cumsum(new)[tied].astype(np.uint64) << np.uint64(32) | half[inner]
            sorted_ = np.argsort(key)
            order[tied] = inner[sorted_]
            new[tied] = runs.changes([key[sorted_]])
    return _settled(order, new)[0], new


def _order(letters: Letters, ranks: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(own places in order of the k characters there, then of place; which differ from the one before): ranks of h characters order 2h of them."""
    k = letters.k
    h = min(k, letters.per)
    key = letters.heads(ranks)
    order = np.argsort(key)
    new = runs.changes([key[order]])
    del key
    r = np.zeros(len(ranks) + k, np.uint64)
    while h < k:
        r[order] = np.cumsum(new)
        tied = _tied(new)
        places, step = order[tied], min(h, k - h)
        pair = r[places] << np.uint64(32) | r[places + step]
        sorted_ = np.argsort(pair)
        order[tied] = places[sorted_]
        new[tied] = runs.changes([pair[sorted_]])
        h += step
    places, group = _settled(order, new)
    mine = own[places]
    return places[mine], runs.changes([group[mine]])


def _before(words: np.ndarray, border: np.ndarray) -> int:
    """Rows before the border."""
    low, high = 0, len(words)
    for j, x in enumerate(border):
        column = words[low:high, j]
        low, high = low + int(np.searchsorted(column, x, "left")), low + int(np.searchsorted(column, x, "right"))
    return low


def _planes(x: np.ndarray, codec: pa.Codec) -> bytes:
    """Numbers compressed, their bytes of one weight together."""
    return codec.compress(np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8).T), asbytes=True)


def _from_planes(data, n: int) -> np.ndarray:
    raw = np.frombuffer(pa.decompress(data, decompressed_size=8 * n, codec="zstd"), np.uint8)
    return np.ascontiguousarray(raw.reshape(8, n).T).view("<u8").ravel().astype(np.int64)


def _text(row: dict) -> np.ndarray:
    return runs.decoded(memoryview(pa.decompress(row["text"], decompressed_size=row["size"], codec="zstd")))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    for b in batches:
        for i in range(b.num_rows):
            yield {c: b.column(c)[i].as_py() for c in b.schema.names}


SENT = "part int, run long, n long, data binary, times binary"


def _cut(words: np.ndarray, times: np.ndarray, run: int, borders: np.ndarray, a: int, b: int) -> Iterator[pa.RecordBatch]:
    codec, rows = pa.Codec("zstd", compression_level=3), []
    at = [_before(words, borders[p - 1]) if p else 0 for p in range(a, b)] + [_before(words, borders[b - 1]) if b <= len(borders) else len(words)]
    for p, (s, e) in enumerate(zip(at[:-1], at[1:], strict=True)):
        if e > s:
            rows.append((p, run, e - s, codec.compress(words[s:e].astype(">u8").tobytes(), asbytes=True), _planes(times[s:e], codec)))
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)], ["part", "run", "n", "data", "times"])


def _sent(table: DataFrame, letters: Letters, borders: np.ndarray, a: int, b: int) -> DataFrame:
    """(part from ``a`` on, run, n, data, times): the different prefixes of partitions a to b of each run, in order, and how often each is there."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            ranks, own = letters.padded(_text(row), np.array(row["lengths"]), np.array(row["own"]))
            head = letters.heads(ranks)
            if a:
                own &= head >= borders[a - 1, 0]
            if b <= len(borders):
                own &= head <= borders[b - 1, 0]
            del head
            if not own.any():
                continue
            words = letters.words(ranks, np.flatnonzero(own))
            order, new = _ordered(words)
            first = np.flatnonzero(new)
            words, times = words[order[first]], np.diff(first, append=len(order))
            yield from _cut(words, times, row["run"], borders, a, b)

    return table.select("run", "own", "lengths", "size", "text").mapInArrow(run, SENT)


def _ranks(sent: DataFrame, width: int, a: int, b: int, classes: bool = False, within: bool = False) -> DataFrame:
    """(run, part, n, all, data, before, tied): the ranks in its partition of each prefix of a run; ``all``: the partition's suffixes, in one of its rows.

    ``classes``: how many equal suffixes earlier runs have, and whether there are
    other equal ones.  ``within``: ranks among the prefixes that share their first word.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted(_rows(batches), key=lambda r: r["run"])
        if not rows:
            return
        part, codec = a + rows[0]["part"], pa.Codec("zstd", compression_level=3)
        words = np.concatenate([np.frombuffer(pa.decompress(r.pop("data"), decompressed_size=8 * width * r["n"], codec="zstd"), ">u8").astype(np.uint64).reshape(-1, width) for r in rows])
        times = np.concatenate([_from_planes(r.pop("times"), r["n"]) for r in rows])
        order, new = _ordered(words)
        in_order = times[order]
        pos = np.cumsum(in_order) - in_order
        made = [np.empty(len(order), np.int64) for _ in range(3 if classes else 1)]
        if classes:
            first = np.flatnonzero(new)
            many = np.diff(first, append=len(order))
            made[1][order] = pos - np.repeat(pos[first], many)
            made[2][order] = np.repeat(np.add.reduceat(in_order, first) > 1, many)
        if within:
            first = np.flatnonzero(runs.changes([words[order, 0]]))
            pos -= np.repeat(pos[first], np.diff(first, append=len(order)))
        made[0][order] = pos
        del words
        at = 0
        for i, r in enumerate(rows):
            mine = [x[at : at + r["n"]] for x in made]
            at += r["n"]
            data = [_planes(x, codec) for x in (np.diff(mine[0], prepend=0), *mine[1:])] + [None] * (3 - len(mine))
            yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in ((r["run"], pa.int64()), (part, pa.int32()), (r["n"], pa.int64()), (int(times.sum()) if i == 0 else 0, pa.int64()), *((x, pa.binary()) for x in data))], ["run", "part", "n", "all", "data", "before", "tied"])

    return sent.repartitionById(b - a, F.col("part")).mapInArrow(run, "run long, part int, n long, all long, data binary, before binary, tied binary")


#: Of documents' ids: the document of each suffix (ascending), the suffix's place there, its rank.
Make = Callable[[pa.Array, np.ndarray, np.ndarray, np.ndarray], dict]


def _passes(make: Callable[[int, int], DataFrame], parts: int) -> tuple[DataFrame, np.ndarray]:
    """(ranks of all partitions, how many suffixes lie before each), taken a few partitions at a time."""
    found, sizes, passes = [], {}, max(1, min(PASSES, parts // EACH))
    for g in range(passes):
        found.append(written(make(parts * g // passes, parts * (g + 1) // passes), "ranks"))
        sizes |= {r["part"]: r["all"] for r in found[-1].filter("all > 0").select("part", "all").collect()}
        gc.collect()
        found[-1].sparkSession.sparkContext._jvm.System.gc()  # until then Spark keeps the files of the pass's shuffle
    ranks = found[0]
    for f in found[1:]:
        ranks = ranks.unionAll(f)
    ranks._tables = found
    return ranks, np.cumsum([0] + [sizes.get(p, 0) for p in range(parts)])


def _met(table: DataFrame, ranks: DataFrame, numbers: dict[int, int]) -> DataFrame:
    """Each run's row and its ranks in a partition of their own."""
    number = F.broadcast(table.sparkSession.createDataFrame(list(numbers.items()), "run long, _to int"))
    both = table.unionByName(ranks.select("run", "part", F.col("n").alias("many"), "data", "before", "tied"), allowMissingColumns=True)
    return both.join(number, "run").repartitionById(len(numbers), F.col("_to")).drop("_to")


def _row_and_ranks(batches: Iterator[pa.RecordBatch]) -> tuple[dict | None, list[tuple]]:
    row, got = None, []
    for r in _rows(batches):
        if r["part"] is None:
            row = r
        else:
            got.append((r["part"], *(x and _from_planes(x, r["many"]) for x in (r["data"], r["before"], r["tied"]))))
    return row, sorted(got, key=lambda x: x[0])


def _numbers(table: DataFrame) -> dict[int, int]:
    return {r[0]: i for i, r in enumerate(table.select("run").orderBy("run").collect())}


def _first(table: DataFrame, k: int, classes: bool) -> tuple[Letters, DataFrame, np.ndarray]:
    spark = table.sparkSession
    letters = Letters(np.array(sorted(r[0] for r in table.select(F.explode("used")).distinct().collect()), np.int64), k)
    total = table.select(F.sum(F.aggregate("own", F.lit(0).cast("long"), lambda x, y: x + y))).first()[0]
    sample = letters.spelled([r[0] for r in table.select(F.explode("sample")).collect()])
    sample = sample[_ordered(sample)[0]]
    parts = max(1, min(len(sample), max(-(-total // PART), min(2 * spark.sparkContext.defaultParallelism, total // max(1, PART >> 4)))))
    borders = np.unique(sample[[len(sample) * p // parts for p in range(1, parts)]], axis=0) if parts > 1 else sample[:0]
    width = letters.wide // letters.per
    return letters, *_passes(lambda a, b: _ranks(_sent(table, letters, borders, a, b), width, a, b, classes), len(borders) + 1)


def ranked(docs: DataFrame, k: int, fields: str, make: Make) -> DataFrame:
    """What ``make`` gives (its ``fields``) for all suffixes, ranked by their first k characters, ties by document and place."""
    if k < 1:
        raise ValueError("k must be positive")
    spark = docs.sparkSession
    ship_package(spark)
    table = stored(docs, k)
    kind = to_arrow_type(docs.schema["doc_id"].dataType)
    numbers = _numbers(table)
    if not numbers:
        return spark.createDataFrame([], fields)
    letters, ranks, base = _first(table, k, False)
    sent = spark.sparkContext.broadcast(base)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, (row, got) = sent.value, _row_and_ranks(batches)
        if row is None:
            return
        starts, own, lengths = (np.array(row[c]) for c in ("starts", "own", "lengths"))
        ranks, mine = letters.padded(_text(row), lengths, own)
        places, new = _order(letters, ranks, mine)
        first = np.concatenate([base[p] + np.cumsum(x) for p, x, *_ in got])
        group = np.flatnonzero(new)
        rank = np.empty(len(ranks), np.int64)
        rank[places] = np.repeat(first - group, np.diff(group, append=len(places))) + np.arange(len(places))
        doc = np.repeat(np.arange(len(own)), own)
        yield pa.RecordBatch.from_pydict(make(pa.array(row["ids"], kind), doc, np.arange(len(doc)) + (starts - np.cumsum(own) + own)[doc], rank[mine]))

    return _met(table.select("run", "ids", "starts", "own", "lengths", "size", "text"), ranks, numbers).mapInArrow(run, fields)

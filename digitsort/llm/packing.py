"""Packing token sequences by lexical retrieval.

Each document's ids, then ``end_id``, are cut into windows.  Whole windows stand
alone.  The rest of a document, shorter than a window, is packed with its lexical
neighbours: rests are dealt out by their rarest token (ids of byte-pair
vocabularies rise with rarity) in even ranges, and consecutive rests form shards,
each with a BM25 inverted index over token ids.  A seed's best unused neighbours
fill its window; one that doesn't fit is cut, what's left of it is the next seed.
A window that a shard can't fill goes on in the next shard of its task, so each
task ends with at most one window that isn't full.

Document frequencies and the mean length, for BM25, cover all documents.

Defined results: a null or empty text is ``end_id`` alone; an empty table gives no
pieces; repeated rows are packed as often as they come.  Only two columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship_package, written
from . import byte_bpe
from .textbatch import binary_array, ranges, text_chunks

PIECE = "start long, length long, doc_tokens long, sequence_id long, offset long, ids binary"


@dataclass
class Params:
    window: int = 1024
    end_id: int = 0
    shard: int = 512
    k1: float = 1.2
    b: float = 0.75


class Presence:
    """Counts, of some documents at a time, in how many of them each id is."""

    def __init__(self, vocabulary: int, rows: int = 64) -> None:
        self.df, self.rows, self.docs, self.tokens = np.zeros(vocabulary, np.int64), rows, 0, 0
        self.seen = np.zeros((rows, vocabulary), np.uint8)

    def add(self, ids: np.ndarray, off: np.ndarray) -> None:
        n = len(off) - 1
        for k in range(0, n, self.rows):
            m = min(n, k + self.rows)
            self.seen[:] = 0
            self.seen[np.repeat(np.arange(m - k), np.diff(off[k : m + 1])), ids[off[k] : off[m]]] = 1
            self.df += self.seen.sum(axis=0, dtype=np.int64)
        self.docs, self.tokens = self.docs + n, self.tokens + len(ids)


def _pieces(docs: DataFrame, path: str, p: Params, id_col: str, text_col: str) -> DataFrame:
    """Windows and rests of all documents; at each task's end one row with its document frequencies."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, tok = byte_bpe.token_bytes(path)
        vocabulary = len(tok) - 1
        seen = Presence(vocabulary)
        made, task = 0, TaskContext.get().partitionId()
        kind = None
        for batch in batches:
            kind = batch.schema.field(0).type
            for row, chunk in text_chunks(batch.column(1)):
                ids, off = byte_bpe.memo(path).tokens(chunk)
                seen.add(ids, off)
                # an end after each document
                size = np.diff(off) + 1
                begin = np.cumsum(size) - size
                flat = np.full(int(size.sum()), p.end_id, "<u4")
                flat[ranges(begin, size - 1)] = ids
                parts = -(-size // p.window)
                doc = np.repeat(np.arange(chunk.n), parts)
                start = ranges(np.zeros(chunk.n, np.int64), parts) * p.window
                length = np.minimum(p.window, size[doc] - start)
                full = length == p.window
                at = begin[doc] + start
                rare = np.maximum.reduceat(flat, at) if len(at) else np.zeros(0, "<u4")
                number = np.where(full, (np.int64(task) << 34 | (made + np.cumsum(full))) << 1, 0)
                made += int(full.sum())
                m = len(doc)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(row, chunk.n).take(pa.array(doc)), pa.array(start), pa.array(length), pa.array(size[doc]), pa.array(number, mask=~full), pa.array(rare.astype(np.int64)), binary_array(flat.tobytes(), np.concatenate([at, [len(flat)]]) * 4), pa.nulls(m, pa.list_(pa.int64()))],
                    names,
                )
        if kind is not None:
            yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), *(pa.nulls(1, pa.int64()) for _ in range(5)), pa.nulls(1, pa.binary()), pa.array([[*seen.df.tolist(), seen.docs, seen.tokens]], pa.list_(pa.int64()))], names)

    names = [id_col, "start", "length", "doc_tokens", "sequence_id", "rare", "ids", "df"]
    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, start long, length long, doc_tokens long, sequence_id long, rare long, ids binary, df array<long>")


class Shard:
    """A BM25 inverted index over some rests."""

    def __init__(self, rests: list[np.ndarray], idf: np.ndarray, mean: float, p: Params) -> None:
        n = len(rests)
        size = np.array([len(r) for r in rests])
        key, tf = np.unique(np.concatenate(rests).astype(np.int64) * n + np.repeat(np.arange(n), size), return_counts=True)
        term, doc = key // n, key % n
        useful = idf[term] > 0  # a term that most documents have tells nothing
        term, doc, tf = term[useful], doc[useful], tf[useful]
        self.n, self.doc = n, doc
        self.weight = idf[term] * tf * (p.k1 + 1) / (tf + p.k1 * (1 - p.b + p.b * size[doc] / mean))
        cut = np.flatnonzero(np.concatenate([[True], term[1:] != term[:-1]])) if len(term) else np.zeros(0, np.int64)
        self.start, self.length = cut, np.diff(np.concatenate([cut, [len(term)]]))
        own = np.repeat(np.arange(len(cut)), self.length)  # each posting's term, by place
        order = np.argsort(doc, kind="stable")
        self.terms, self.terms_off = own[order], np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=n))])

    def scores(self, seed: int) -> np.ndarray:
        """BM25 of all rests for the seed's distinct terms."""
        t = self.terms[self.terms_off[seed] : self.terms_off[seed + 1]]
        at = ranges(self.start[t], self.length[t])
        return np.bincount(self.doc[at], self.weight[at], self.n)


def fill_windows(size: np.ndarray, scores, window: int) -> list[list[tuple[int, int, int]]]:
    """Windows of (rest, first id, ids), greedily; only the last may not be full.

    ``scores(seed)`` ranks all rests for one.  Ties go to the earlier rest.
    """
    taken = np.zeros(len(size), np.int64)
    left = size.astype(np.int64).copy()
    windows, seed, next_seed = [], -1, 0
    while True:
        if seed < 0 or not left[seed]:
            while next_seed < len(size) and not left[next_seed]:
                next_seed += 1
            if next_seed == len(size):
                return windows
            seed = next_seed
        n = min(window, int(left[seed]))
        parts, room = [(seed, int(taken[seed]), n)], window - n
        taken[seed] += n
        left[seed] -= n
        cut = -1
        if room and left.any():
            order = np.argsort(-scores(seed), kind="stable")
            order = order[left[order] > 0]
            lengths = left[order]
            if int(lengths.sum()) <= room:
                chosen = order.tolist()
            else:
                chosen = []
                k, m = 0, len(order)
                space = room
                while space and k < m:  # the next best that fits whole
                    fits = np.flatnonzero(lengths[k:] <= space)
                    if not len(fits):
                        break
                    k += int(fits[0])
                    chosen.append(int(order[k]))
                    space -= int(lengths[k])
                    k += 1
                if space:
                    inside = set(chosen)
                    cut = next(int(x) for x in order if int(x) not in inside)
                    chosen.append(cut)
            for x in chosen:
                n = min(room, int(left[x]))
                parts.append((x, int(taken[x]), n))
                taken[x] += n
                left[x] -= n
                room -= n
        windows.append(parts)
        seed = cut


def pack(docs: DataFrame, path: str, p: Params | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, start, length, doc_tokens, sequence_id, offset, ids): pieces; ids as little-endian unsigned 32-bit integers."""
    p = p or Params()
    spark = docs.sparkSession
    ship_package(spark)
    cut = written(_pieces(docs, path, p, id_col, text_col), "pieces")
    df = cut.filter("df IS NOT NULL").select(F.posexplode("df").alias("k", "v")).groupBy("k").agg(F.sum("v").alias("v")).toArrow().to_pydict()  # as many rows as ids, and two
    total = np.zeros(len(df["k"]))
    total[df["k"]] = df["v"]
    n, mean = (total[-2], max(1.0, total[-1] / max(1, total[-2]))) if len(total) else (0, 1.0)
    idf = np.log((n - total[:-2] + 0.5) / (total[:-2] + 0.5)) if n else np.zeros(0)
    shared = spark.sparkContext.broadcast((idf, mean))  # one number for each id of the vocabulary
    rests = cut.filter("sequence_id IS NULL AND df IS NULL").select(id_col, "start", "length", "doc_tokens", "rare", "ids")
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = rests.repartitionByRange(parts, "rare", F.xxhash64(id_col, "start")).sortWithinPartitions("rare", id_col, "start")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        idf, mean = shared.value
        task, made = TaskContext.get().partitionId(), 0
        kind = None
        pool: list[tuple] = []  # (id, start, document's tokens, ids)

        def packed(last: bool) -> pa.RecordBatch:
            nonlocal made, pool
            ids = [x[3] for x in pool]
            index = Shard(ids, idf, mean, p)
            windows = fill_windows(np.array([len(x) for x in ids]), index.scores, p.window)
            over: list[tuple] = []
            if not last and windows and sum(x[2] for x in windows[-1]) < p.window:
                over = [(pool[k][0], pool[k][1] + at, pool[k][2], ids[k][at : at + m]) for k, at, m in windows.pop()]
            rows: list[list] = [[] for _ in range(7)]
            for parts in windows:
                made += 1
                offset = 0
                for k, at, m in parts:
                    for column, v in zip(rows, (pool[k][0], pool[k][1] + at, m, pool[k][2], (task << 34 | made) << 1 | 1, offset, ids[k][at : at + m].tobytes()), strict=True):
                        column.append(v)
                    offset += m
            pool = over
            kinds = [kind, *[pa.int64()] * 5, pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, kinds, strict=True)], names)

        for batch in batches:
            kind = batch.schema.field(0).type
            columns = [batch.column(k).to_pylist() for k in (0, 1, 3)]
            for i, s, d, x in zip(*columns, batch.column(5), strict=True):
                pool.append((i, s, d, np.frombuffer(x.as_buffer(), "<u4")))
                if len(pool) >= p.shard:
                    yield packed(False)
        if pool:
            yield packed(True)

    kind = docs.schema[id_col].dataType.simpleString()
    names = [id_col, "start", "length", "doc_tokens", "sequence_id", "offset", "ids"]
    tails = dealt.mapInArrow(run, f"`{id_col}` {kind}, {PIECE}")
    whole = cut.filter("sequence_id IS NOT NULL").select(id_col, "start", "length", "doc_tokens", "sequence_id", F.lit(0).cast("long").alias("offset"), "ids")
    return whole.unionByName(tails)

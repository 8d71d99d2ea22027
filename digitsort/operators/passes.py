"""Counting passes over DataFrames: histogram, offsets, stable placement."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Accumulator
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import keys
from ..plans import bins
from ..session import ship_package, written
from . import kernels

CHUNK_ROWS = 1 << 16


def with_position(df: DataFrame, order: list[str]) -> DataFrame:
    """Arrival position ``pos`` from 0, by a total order of columns.

    Rows are range partitioned and sorted once; positions are each partition's
    base (one small aggregation) plus the row's place: no window over all rows.
    """
    return place(df.repartitionByRange(*order).sortWithinPartitions(*order), "pos")


def place(routed: DataFrame, name: str) -> DataFrame:
    """Global position from physical placement: partition order, then row order.

    Range exchanges sample anew each time they run, so the rows are written once,
    each with its partition and place, and both steps read that table.
    """
    columns = routed.columns
    if name in columns:
        raise ValueError(f"there is a column {name} already")
    rows = routed.toDF(*(f"c{k}" for k in range(len(columns))))
    marked = written(rows.withColumn("_id", F.monotonically_increasing_id()), "placed", "lz4")
    part = F.shiftright("_id", 33)
    sizes = marked.groupBy(part.alias("_p")).agg(F.count("*").alias("n")).orderBy("_p").collect()  # as many rows as partitions
    base, at = [], {}
    total = 0
    for r in sizes:
        at[r["_p"]] = total
        total += r["n"]
    base = [at.get(k, 0) for k in range(max(at, default=-1) + 1)] or [0]
    start = F.get(F.lit(base).cast("array<long>"), part.cast("int"))
    return marked.withColumn("_id", start + F.col("_id").bitwiseAND(F.lit((1 << 33) - 1))).toDF(*columns, name)


def bases(counts: DataFrame) -> DataFrame:
    """(_chunk, _digit, _base) from (_chunk, _digit, _n): rows of smaller digits, and of the digit in earlier chunks.

    Two small windows: one over the digits' sums, at most as many rows as digits,
    and one for each digit over its chunks.
    """
    before = Window.orderBy("_digit").rowsBetween(Window.unboundedPreceding, -1)
    digits = counts.groupBy("_digit").agg(F.sum("_n").alias("_all")).select("_digit", F.coalesce(F.sum("_all").over(before), F.lit(0)).alias("_smaller"))
    earlier = Window.partitionBy("_digit").orderBy("_chunk").rowsBetween(Window.unboundedPreceding, -1)
    running = counts.withColumn("_earlier", F.coalesce(F.sum("_n").over(earlier), F.lit(0)))
    return running.join(F.broadcast(digits), "_digit").select("_chunk", "_digit", (F.col("_smaller") + F.col("_earlier")).alias("_base"))


def _marked(df: DataFrame, key: str, position: int, pos: str, chunk: Column | None, bits: int = 8) -> DataFrame:
    chunk = F.floor(F.col(pos) / CHUNK_ROWS) if chunk is None else chunk
    return df.withColumn("_digit", keys.digit(F.col(key), position, bits)).withColumn("_chunk", chunk.cast("long"))


def _based(placed: DataFrame, marked: DataFrame) -> DataFrame:
    base = bases(marked.groupBy("_chunk", "_digit").agg(F.count("*").alias("_n")))
    return placed.join(base, ["_chunk", "_digit"]).withColumn("new_pos", F.col("_base") + F.col("_k")).drop("_chunk", "_digit", "_base", "_k")


def counting_pass(df: DataFrame, key: str, position: int, pos: str = "pos", chunk: Column | None = None, bits: int = 8) -> DataFrame:
    """``df`` with ``new_pos``: rows by one digit, equal digits in their old order.

    Rows count within (chunk, digit); a small table adds what smaller digits and
    earlier chunks hold.  One shuffle of rows, by chunk and digit.  ``chunk``: of a row,
    by its position; CHUNK_ROWS rows each, unless given.
    """
    marked = _marked(df, key, position, pos, chunk, bits)
    within = Window.partitionBy("_chunk", "_digit").orderBy(pos)
    return _based(marked.withColumn("_k", F.row_number().over(within) - 1), marked)


def staged_pass(df: DataFrame, key: str, position: int, pos: str, staging: int | None, chunk: Column | None = None, flushes: Accumulator | None = None) -> DataFrame:
    """The same with the local kernel: ``staging`` bytes of buffer for each digit, or none."""
    return _based(chunk_split(df, key, position, pos, staging, chunk, flushes), _marked(df, key, position, pos, chunk))


def chunk_split(df: DataFrame, key: str, position: int, pos: str, staging: int | None, chunk: Column | None = None, flushes: Accumulator | None = None) -> DataFrame:
    """``df`` with ``_chunk``, ``_digit`` and ``_k``, the place in the chunk's bin, by the plain or the staged kernel.

    One shuffle of rows, by chunk; a task holds one chunk at a time.  ``flushes``
    counts the blocks that buffers wrote.
    """
    ship_package(df.sparkSession)
    chunks = _marked(df, key, position, pos, chunk).drop("_digit").repartition("_chunk").sortWithinPartitions("_chunk", pos)
    at, chunk_at = chunks.columns.index(key), chunks.columns.index("_chunk")
    names = [*chunks.columns, "_digit", "_k"]

    def split(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        rows = pa.concat_batches(held)
        k = rows.column(at).to_numpy(zero_copy_only=False).astype(np.int64)
        if staging is None:
            order, begin = kernels.split_plain(k, position)
        else:
            order, begin, wrote = kernels.split_staged(k, position, staging)
            if flushes is not None:
                flushes.add(wrote)
        d = kernels.digits(k, position)[order]
        return pa.RecordBatch.from_arrays([*rows.take(pa.array(order)).columns, pa.array(d), pa.array(np.arange(len(k)) - begin[d])], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        now = None
        for batch in batches:
            c = batch.column(chunk_at).to_numpy()
            cut = [0, *(np.flatnonzero(np.diff(c)) + 1).tolist(), len(c)]
            for a, b in zip(cut[:-1], cut[1:], strict=True):
                if a == b:
                    continue
                if held and c[a] != now:
                    yield split(held)
                    held = []
                now = c[a]
                held.append(batch.slice(a, b - a))
        if held:
            yield split(held)

    return chunks.mapInArrow(run, T.StructType(list(chunks.schema.fields)).add("_digit", "long").add("_k", "long"))


def parallel_split(df: DataFrame, key: str, position: int, chunk: Column) -> DataFrame:
    """(chunk, digit, n, base): where each chunk writes its rows of each digit."""
    counts = df.select(chunk.alias("_chunk"), keys.digit(F.col(key), position).alias("_digit")).groupBy("_chunk", "_digit").agg(F.count("*").alias("_n"))
    both = counts.join(bases(counts), ["_chunk", "_digit"])
    return both.select(F.col("_chunk").alias("chunk"), F.col("_digit").alias("digit"), F.col("_n").alias("n"), F.col("_base").alias("base"))


def chunk_of(pos: Column, plan: list[tuple[int, int, int]]) -> Column:
    """The chunk of a position, by binary search over the chunks' starts."""
    starts = [s for _, s, _ in plan]

    def search(low: int, high: int) -> Column:
        if high - low == 1:
            return F.lit(low)
        mid = (low + high) // 2
        return F.when(pos < F.lit(starts[mid]), search(low, mid)).otherwise(search(mid, high))

    return search(0, len(starts))


def staging_flushes(df: DataFrame, key: str, position: int, staging: int, chunk: Column, record: int = 16) -> DataFrame:
    """(digit, n, flushes): blocks of ``staging`` bytes that each digit's buffers write, over all chunks."""
    slots = max(1, staging // record)
    per = df.select(chunk.alias("chunk"), keys.digit(F.col(key), position).alias("digit")).groupBy("chunk", "digit").agg(F.count("*").alias("n"))
    return per.groupBy("digit").agg(F.sum("n").alias("n"), F.sum(F.ceil(F.col("n") / slots)).alias("flushes"))


__all__ = ["bins", "chunk_of", "chunk_split", "counting_pass", "parallel_split", "place", "staged_pass", "staging_flushes", "with_position"]

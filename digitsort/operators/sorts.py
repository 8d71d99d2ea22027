"""Sorters: the adaptive most-significant-digit sort, its plain forms, and the baselines.

All return the input's columns, whatever their names; global order is partition
order, then row order.  ``with_rank`` turns that placement into a 0-based position.
Arrays order as Spark orders them: item by item, null items before all others.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import keys
from ..plans import route
from ..plans.bins import Rules
from ..session import release, ship_package, written
from . import kernels, passes


#: Fewer rows aren't worth a task of their own.
LEAST_ROWS = 2048


def _order(columns: list[str], ascending: list[bool], nulls_first: bool) -> list[Column]:
    out = []
    for c, up in zip(columns, ascending, strict=True):
        c = F.col(c)
        out.append((c.asc_nulls_first() if nulls_first else c.asc_nulls_last()) if up else (c.desc_nulls_first() if nulls_first else c.desc_nulls_last()))
    return out


def _plain_names(df: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """The columns as c0, c1, ..., beside which helper columns may have any other name."""
    names = {c: f"c{k}" for k, c in enumerate(df.columns)}
    return df.toDF(*(f"c{k}" for k in range(len(df.columns)))), names


def adaptive_msd(df: DataFrame, columns: list[str], *, ascending: list[bool] | None = None, nulls_first: bool = True, rules: Rules | None = None, partitions: int | None = None, sampled: bool = False, skip: bool = True, kernel: bool = False, stats: dict | None = None) -> DataFrame:
    """Counts key prefixes, refines heavy bins, moves all rows once, sorts partitions locally.

    The first column decides the route; rows of equal first keys stay together,
    unless they are too many for one partition: then the second column cuts them.
    Of strings and arrays the bytes or items after their common start decide; where
    those are equal for too many rows, the ones after what these rows share cut them,
    and where the rows are equal in all, the second column.
    Null keys share the outermost partition; where that is large, it is cut by the
    second column's order in turn.
    """
    rules = rules or Rules()
    up = ascending or [True] * len(columns)
    spark = df.sparkSession
    least_rows = 1 if partitions else LEAST_ROWS
    partitions = partitions or max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows, names = _plain_names(df)
    by = [names[c] for c in columns]
    order = _order(by, up, nulls_first)
    edge = keys.MIN_LONG if nulls_first else (1 << 63) - 1
    keyed = rows.withColumn("_key", keys.leading(rows, by[0], up[0], skip))

    def further(alike: DataFrame) -> Column | None:
        then = keys.following(rows, alike, by[0], up[0])
        if then is None and len(by) > 1:
            try:
                then = keys.order_key(rows, by[1], up[1])
            except TypeError:
                return None
        return None if then is None else F.coalesce(then, F.lit(edge))

    nullable = rows.schema[by[0]].nullable
    # a null shares the outermost partition; the local sort orders it by the column itself
    filled = keyed.withColumn("_key", F.coalesce("_key", F.lit(edge))) if nullable else keyed
    plan = route.plan_partitions(filled, "_key", partitions, further, rules, skip=skip, sampled=sampled, least_rows=least_rows, wide=not keys.whole(rows.schema[by[0]].dataType))
    if stats is not None:
        stats.update(scans=plan.scans, heavy=plan.heavy, partitions=plan.count, max_rows=plan.max_rows, total=plan.total)
    if not plan.first:
        return df.orderBy(*_order(columns, up, nulls_first))
    moved = route.route(filled, "_key", plan)
    if kernel:
        if not keys.whole(rows.schema[by[0]].dataType):
            raise TypeError("the kernel sorts by eight bytes: use the spillable sort for longer keys")
        ties = 0 if nullable else 1  # a null and the least key share their digits
        moved = _kernel_sort(moved, rules, plan.total, order[ties:])
    else:
        moved = moved.sortWithinPartitions(*order)
    return moved.select(*rows.columns).toDF(*df.columns)


def _kernel_sort(moved: DataFrame, rules: Rules, total: int, ties: list[Column], cap_rows: int = 2_000_000) -> DataFrame:
    """Local order by the radix kernel with comparison finishers, for partitions under a cap; larger ones raise.

    Ties follow the arrival order within a partition, so ``ties`` are sorted first.
    """
    if ties:
        moved = moved.sortWithinPartitions(*ties)
    at = moved.columns.index("_key")
    ship_package(moved.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        rows = sum(b.num_rows for b in held)
        if rows > cap_rows:
            raise MemoryError(f"{rows} rows in one partition; the kernel takes {cap_rows}: use the spillable sort")
        if rows:
            table = pa.Table.from_batches(held).combine_chunks()
            k = table.column(at).to_numpy().astype(np.int64)
            order, _ = kernels.light_pass(k, 7, total, rules)
            # comparison finishers compare (key, place), splits are stable: ties keep their order
            yield from table.take(pa.array(order)).combine_chunks().to_batches()

    return moved.mapInArrow(run, moved.schema)


def msd_plain(df: DataFrame, columns: list[str], **more) -> DataFrame:
    """Textbook form: bins inside bins, every bin alike, no scheduler."""
    return adaptive_msd(df, columns, rules=Rules(heavy=None, tiny=0, narrow=None), skip=False, **more)


def lsd(df: DataFrame, key: str, pos: str, staging: int | None = None, skip_constant: bool = True, chunk: Column | None = None, stats: dict | None = None) -> DataFrame:
    """Stable passes from the least significant digit: (all columns, new ``pos``).

    Each pass moves all rows and is written, since the next reads it twice.  A
    digit that all keys share is skipped.  With ``staging``, a pass splits its chunks
    through buffers of so many bytes for each digit, whose flushes are counted.
    ``chunk``: of a row, by its position ``pos``.
    """
    rows = df
    if skip_constant:
        x = df.agg(*(F.min(keys.digit(F.col(key), p)).alias(f"a{p}") for p in range(8)), *(F.max(keys.digit(F.col(key), p)).alias(f"b{p}") for p in range(8))).first()
        positions = [p for p in range(8) if x[f"a{p}"] != x[f"b{p}"]]
    else:
        positions = list(range(8))
    flushes = df.sparkSession.sparkContext.accumulator(0)
    for p in positions:
        made = passes.counting_pass(rows, key, p, pos, chunk) if staging is None else passes.staged_pass(rows, key, p, pos, staging, chunk, flushes)
        done = written(made.drop(pos).withColumnRenamed("new_pos", pos), "lsd-pass", "lz4")
        if rows is not df:
            release(rows)
        rows = done
    if stats is not None:
        stats.update(passes=len(positions), flushes=flushes.value)
    return rows


def comparison(df: DataFrame, columns: list[str], **more) -> DataFrame:
    """Comparison sort: sampled range exchange, then a comparison order inside partitions.

    The platform's radix pre-sort is passed over by sorting on a structure, which
    only comparisons can order.
    """
    order = _order(columns, more.get("ascending") or [True] * len(columns), more.get("nulls_first", True))
    spread = df.repartitionByRange(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *order)
    if more.get("ascending") or not more.get("nulls_first", True):
        return spread.sortWithinPartitions(*order)
    return spread.sortWithinPartitions(F.struct(*columns))


def run_merge(df: DataFrame, columns: list[str], runs: int = 4, cap_rows: int = 2_000_000) -> DataFrame:
    """Hybrid sort: sorted runs, dealt out by ranges, then a multiway merge in each range.

    A range's rows are sorted by run, and its runs are merged in memory: above
    ``cap_rows`` a range is refused.
    """
    import heapq

    spark = df.sparkSession
    ship_package(spark)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows, names = _plain_names(df)
    by = [names[c] for c in columns]
    tagged = rows.withColumn("_run", F.pmod(F.xxhash64(*by), F.lit(runs)).cast("int"))
    dealt = tagged.repartitionByRange(n, *by).sortWithinPartitions("_run", *by)
    at = [tagged.columns.index(c) for c in by]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches)).combine_chunks()
        if table.num_rows > cap_rows:
            raise MemoryError(f"{table.num_rows} rows in one partition; the merge takes {cap_rows}")
        which = table.column("_run").to_numpy()
        cut = np.concatenate([[0], np.flatnonzero(np.diff(which)) + 1, [len(which)]])
        columns_ = [table.column(k).to_pylist() for k in at]
        streams = [zip(*(c[a:b] for c in columns_), range(a, b), strict=True) for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
        order = np.fromiter((x[-1] for x in heapq.merge(*streams, key=lambda x: [(v is not None, (v != v, 0.0 if v != v else v) if v is not None else 0) for v in x[:-1]])), np.int64, table.num_rows)
        yield from table.take(pa.array(order)).combine_chunks().to_batches()

    def guarded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if held:
            yield from run(iter(held))

    return dealt.mapInArrow(guarded, tagged.schema).drop("_run").toDF(*df.columns)


def in_place(df: DataFrame, key: str, ties: list[str], partitions: int | None = None, cap_rows: int = 2_000_000) -> DataFrame:
    """In-place radix: routed partitions, each sorted by cycles of swaps; equal keys by their tie columns.  Rows without a key are left out."""
    spark = df.sparkSession
    ship_package(spark)
    if not keys.whole(df.schema[key].dataType):
        raise TypeError("the kernel sorts by eight bytes")
    rows, names = _plain_names(df)
    keyed = rows.withColumn("_key", keys.order_key(rows, names[key])).filter("_key IS NOT NULL")
    partitions = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    further = (lambda alike: F.coalesce(keys.order_key(rows, names[ties[0]]), F.lit(keys.MIN_LONG))) if ties else None
    plan = route.plan_partitions(keyed, "_key", partitions, further, Rules(workers=partitions))  # a hot key is cut by the first tie column
    moved = route.route(keyed, "_key", plan)
    at, tie_at = keyed.columns.index("_key"), [keyed.columns.index(names[c]) for c in ties]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held).combine_chunks()
        if table.num_rows > cap_rows:
            raise MemoryError(f"{table.num_rows} rows in one partition; the kernel takes {cap_rows}")
        k, rows = table.column(at).to_pylist(), list(range(table.num_rows))
        kernels.in_place_radix(k, rows)
        cut = np.concatenate([[0], np.flatnonzero(np.diff(np.array(k))) + 1, [len(k)]])
        many = np.flatnonzero(np.diff(cut) > 1)
        if len(many) and tie_at:
            tie = list(zip(*(table.column(c).to_pylist() for c in tie_at), strict=True))
            for j in many.tolist():
                a, b = int(cut[j]), int(cut[j + 1])
                rows[a:b] = sorted(rows[a:b], key=tie.__getitem__)
        yield from table.take(pa.array(rows)).combine_chunks().to_batches()

    return moved.mapInArrow(run, moved.schema).drop("_key").toDF(*df.columns)


def spark_default(df: DataFrame, columns: list[str], **more) -> DataFrame:
    """The platform's own global sort."""
    return df.orderBy(*_order(columns, more.get("ascending") or [True] * len(columns), more.get("nulls_first", True)))


def with_rank(ordered: DataFrame, name: str = "pos") -> DataFrame:
    """0-based position by placement: proof of the order that a sorter made."""
    return passes.place(ordered, name)


def top_k(df: DataFrame, key: str, k: int) -> DataFrame:
    """The rows of the k least keys, nulls first: only bins that begin before rank k are read further."""
    rows, names = _plain_names(df)
    by = names[key]
    keyed = rows.withColumn("_key", keys.order_key(rows, by))
    nulls = rows.filter(F.col(by).isNull()).limit(k).count()
    out = keyed.filter("_key IS NULL")
    if k > nulls:
        high = _bin_of_rank(keyed, k - nulls - 1, max(4 * k, 1024))
        out = keyed if high is None else keyed.filter(F.col("_key").isNull() | (F.col("_key") <= F.lit(high[1])))
    return out.drop("_key").orderBy(F.col(by).asc_nulls_first()).limit(k).toDF(*df.columns)


def _bin_of_rank(keyed: DataFrame, rank: int, enough: int) -> tuple[int, int] | None:
    """(least, greatest) key of the bin that holds the rank among the keys that aren't null: split until it has ``enough`` rows at most; None past the end."""
    low, left = None, rank
    for level in range(1, 9):
        rows = keyed.filter("_key IS NOT NULL") if low is None else keyed.filter(keys.floor_key(F.col("_key"), level - 1) == F.lit(low))
        for r in rows.groupBy(keys.floor_key(F.col("_key"), level).alias("lo")).agg(F.count("*").alias("n")).orderBy("lo").collect():  # at most 256 rows
            if left < r["n"]:
                break
            left -= r["n"]
        else:
            return None
        low = r["lo"]
        if r["n"] <= enough:
            break
    return low, low + (1 << (64 - 8 * level)) - 1


def select_rank(df: DataFrame, key: str, rank: int) -> int | None:
    """Order key at a 0-based rank, nulls first (then None): walks histograms into the bin that holds it."""
    keyed = df.select(keys.order_key(df, key).alias("_key"))
    nulls = keyed.filter("_key IS NULL").count()
    if rank < nulls:
        return None
    found = _bin_of_rank(keyed, rank - nulls, 0)
    if found is None:
        raise IndexError(rank)
    return found[0]


def dedupe(df: DataFrame, columns: list[str]) -> DataFrame:
    """One row of each key after sorting: equal neighbours lie in one partition, so no further shuffle.

    Neighbours are compared batch by batch, column by column; nulls equal nulls, NaN equals NaN.
    """
    ordered = adaptive_msd(df.select(*columns), columns)
    ship_package(df.sparkSession)

    def differ(a: pa.Array, b: pa.Array) -> np.ndarray:
        if pa.types.is_nested(a.type):
            return np.array([x != y for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], bool)
        one = pc.xor(pc.is_null(a), pc.is_null(b))
        other = pc.fill_null(pc.not_equal(a, b), False)
        if pa.types.is_floating(a.type):
            other = pc.and_not(other, pc.fill_null(pc.and_(pc.is_nan(a), pc.is_nan(b)), False))
        return pc.or_(one, other).to_numpy(zero_copy_only=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = batch if last is None else pa.concat_batches([last, batch])
            keep = np.zeros(rows.num_rows - 1, bool)
            for c in rows.columns:
                keep |= differ(c.slice(1), c.slice(0, rows.num_rows - 1))
            yield rows.filter(pa.array(np.concatenate([[last is None], keep])))
            last = batch.slice(batch.num_rows - 1)

    return ordered.mapInArrow(run, ordered.schema)


def run_lengths(df: DataFrame, key: str) -> DataFrame:
    """(key, n): runs of equal neighbours in a sorted frame, collapsed where they lie; a key that was cut over partitions has few runs to add up."""
    ordered = adaptive_msd(df.select(key), [key])
    ship_package(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            runs = pc.run_end_encode(batch.column(0), pa.int32())
            ends = runs.run_ends.to_numpy().astype(np.int64)
            yield pa.RecordBatch.from_arrays([runs.values, pa.array(np.diff(ends, prepend=0))], [key, "n"])

    kind = df.schema[key].dataType.simpleString()
    return ordered.mapInArrow(run, f"`{key}` {kind}, n long").groupBy(key).agg(F.sum("n").alias("n"))

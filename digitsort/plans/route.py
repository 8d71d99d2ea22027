"""Partition plans: counted bins packed into ordered partitions, and the route of each row.

Bins are counted by a leading prefix of two bytes at most, with each bin's least
and greatest key; those over the threshold are counted again (only their rows,
only the key column) by the next byte in which their keys differ, until they are
light or hold one key.  Adjacent bins are packed into
partitions of even size, in key order; a bin of one key that is still too large is
cut by the quantiles of what orders its rows further (later bytes of the key, or
the next sort column), or by a hash where there's nothing.

What the driver holds is the borders: at most ``partitions`` plus the heavy keys'
cuts.  Rows find their partition by a binary search over literals (few borders) or
by a broadcast table of at most 65,536 prefixes.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import keys
from .bins import Rules

_U = 1 << 64


@dataclass
class Bin:
    lo: int  # least key that the bin may hold
    bits: int  # of the key below its prefix
    n: int
    least: int  # keys that it does hold
    most: int


@dataclass
class Partitions:
    total: int
    low: int
    skipped: int  # leading bits equal in all keys
    bins: list[Bin]
    first: list[int]  # least key of each partition, ascending
    pieces: list[int]  # partitions that a partition's single key is cut into
    cuts: dict[int, tuple[Column, list[int]]] = field(default_factory=dict)  # of single-key partitions: what orders their rows, and its borders
    scans: int = 1
    heavy: int = 0
    max_rows: int = 0

    @property
    def count(self) -> int:
        return max(1, sum(self.pieces))

    @property
    def ids(self) -> list[int]:
        """First partition id of each entry of ``first``."""
        out, at = [], 0
        for n in self.pieces:
            out.append(at)
            at += n
        return out


def common_prefix_bits(low: int, high: int) -> int:
    """Leading bits that all keys between share."""
    return 64 - ((low ^ high) % _U).bit_length()


def plan_partitions(df: DataFrame, key: str, partitions: int, further: Callable[[DataFrame], Column | None] | None = None, r: Rules | None = None, skip: bool = True, sampled: bool = False, least_rows: int = 1, wide: bool = False) -> Partitions:
    """``key``: a column of order keys without nulls; ``wide``: count by two bytes at once, for keys as uneven as text; ``further``: what orders given rows of one key (no nulls); ``least_rows``: worth a partition."""
    r = r or Rules()
    if sampled:
        return _sampled(df, key, max(1, min(partitions, -(-df.count() // least_rows))))
    step = 16 if wide or 256 < 1.5 * partitions else 8
    floor = lambda b: F.col(key).bitwiseAND(F.lit(-1 << b))

    def count(rows: DataFrame, b: int) -> list[Bin]:
        """Bins by the bits above b: at most 2^step for each heavy one; a bin of one key has none left."""
        found = rows.groupBy(floor(b).alias("lo")).agg(F.count("*").alias("n"), F.min(key).alias("a"), F.max(key).alias("z")).collect()
        return [Bin(x["a"], 0, x["n"], x["a"], x["z"]) if x["a"] == x["z"] else Bin(x["lo"], b, x["n"], x["a"], x["z"]) for x in found]

    bins, done, scans, heavy_bins = count(df, 64 - step), [], 1, 0
    total = sum(b.n for b in bins)
    if not total:
        return Partitions(0, 0, 0, [], [], [])
    low, high = min(b.least for b in bins), max(b.most for b in bins)
    partitions = max(1, min(partitions, -(-total // least_rows)))
    limit = total if r.heavy is None else r.heavy[0] * total / (r.heavy[1] * partitions)
    while bins:
        alike = skip and len(bins) == 1 and not done  # a leading byte that all keys share
        heavy = [b for b in bins if b.bits and (b.n > limit or alike)]
        done += [b for b in bins if not (b.bits and (b.n > limit or alike))]
        heavy_bins += len(heavy) * (not alike)
        bins, parts = [], {}
        for b in heavy:  # the next byte, or the first one in which the bin's keys differ
            below = b.bits - 8
            if skip:
                below = min(below, 64 - common_prefix_bits(b.least, b.most) // 8 * 8 - (step if alike else 8))
            parts.setdefault((b.bits, max(0, below)), []).append(b.lo)
        for (at, below), lows in sorted(parts.items()):
            rows = df if alike else df.filter(floor(at).isin(lows)) if len(lows) <= 64 else df.join(F.broadcast(df.sparkSession.createDataFrame([(x,) for x in lows], "heavy_lo long")), floor(at) == F.col("heavy_lo"), "left_semi")
            bins += count(rows, below)
            scans += 1
    skipped = common_prefix_bits(low, high) // 8 * 8 if skip else 0
    done.sort(key=lambda b: b.lo)
    plan = Partitions(total, low, skipped, done, [], [], {}, scans, heavy_bins)
    target = -(-total // partitions)
    room = 0
    for b in done:
        alone = b.n > target and b.bits == 0
        if alone or not plan.first or room + b.n > target or plan.pieces[-1] > 1:
            plan.first.append(b.lo)
            plan.pieces.append(max(1, min(partitions, b.n // target)) if alone else 1)
            room = 0
            rows = df.filter(F.col(key) == b.lo)
            if alone and further and plan.pieces[-1] > 1 and (then := further(rows)) is not None:
                m = plan.pieces[-1]
                marks = rows.agg(F.percentile_approx(then, [k / m for k in range(1, m)], 10_000)).first()[0] or []
                plan.cuts[len(plan.first) - 1] = then, sorted(set(marks))
                plan.pieces[-1] = len(plan.cuts[len(plan.first) - 1][1]) + 1
        room += b.n
        plan.max_rows = max(plan.max_rows, -(-room // plan.pieces[-1]))
    return plan


def _sampled(df: DataFrame, key: str, partitions: int) -> Partitions:
    """The control: borders from approximate quantiles instead of counts."""
    x = df.agg(F.count(key).alias("n"), F.min(key).alias("low"), F.percentile_approx(key, [k / partitions for k in range(1, partitions)] or [0.5], 1000).alias("q")).first()
    if not x["n"]:
        return Partitions(0, 0, 0, [], [], [])
    first = [x["low"], *sorted(q for q in set(x["q"]) if q > x["low"])] if partitions > 1 else [x["low"]]
    return Partitions(x["n"], x["low"], 0, [], first, [1] * len(first))


def _search(key: Column, first: list[int], at: list[int], low: int, high: int) -> Column:
    if high - low == 1:
        return F.lit(at[low])
    mid = (low + high) // 2
    return F.when(key < F.lit(first[mid]), _search(key, first, at, low, mid)).otherwise(_search(key, first, at, mid, high))


def route(df: DataFrame, key: str, plan: Partitions, literals: int = 128) -> DataFrame:
    """``df`` in ``plan.count`` partitions whose ids follow key order: the one full shuffle."""
    if not plan.first:
        return df.coalesce(1)
    if plan.count == 1:
        return df.repartitionById(1, F.lit(0))
    k, ids = F.col(key), plan.ids
    if len(plan.first) <= literals:
        which, rows = _search(k, plan.first, ids, 0, len(plan.first)), df
    else:
        # borders by the 16-bit prefix they fall in; a prefix between borders takes the last one before it
        shift = max(0, 64 - plan.skipped - 16)
        cell = lambda x: ((x - keys.MIN_LONG) >> shift) - ((plan.low - keys.MIN_LONG) >> shift)
        origin = (plan.low - keys.MIN_LONG) >> shift
        origin -= _U if origin >= 1 << 63 else 0
        by: dict[int, list[int]] = {}
        for x in plan.first[1:]:
            by.setdefault(cell(x), []).append(x)
        last, passed, table = max(by), 0, []
        for c in range(last + 2):
            table.append((c, passed, by.get(c, [])))
            passed += len(by.get(c, []))
        frame = df.sparkSession.createDataFrame(table, "_cell long, _passed int, _borders array<long>")
        found = df.withColumn("_at", F.least(F.lit(last + 1).cast("long"), F.shiftrightunsigned(k.bitwiseXOR(F.lit(keys.MIN_LONG)), shift) - F.lit(origin)))
        rows = found.join(F.broadcast(frame), F.col("_at") == F.col("_cell")).withColumn("_entry", F.col("_passed") + F.size(F.filter("_borders", lambda x: x <= k)))
        which = F.get(F.array(*map(F.lit, ids)), F.col("_entry")) if ids != list(range(len(ids))) else F.col("_entry")
    for entry, m in enumerate(plan.pieces):
        if m > 1:
            then, cuts = plan.cuts.get(entry, (None, []))
            part = sum((F.when(then > F.lit(c), 1).otherwise(0) for c in cuts), F.lit(0)) if then is not None else F.pmod(F.xxhash64(*df.columns), F.lit(m)).cast("int")
            which = F.when(k == F.lit(plan.first[entry]), F.lit(ids[entry]) + part).otherwise(which)
    return rows.withColumn("_part", which.cast("int")).repartitionById(plan.count, "_part").select(*df.columns)

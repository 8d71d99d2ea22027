"""Bin plans: chunks, histograms, offsets, classes, teams and dispatch decisions.

Sizes are compared as integers (n * 3T > 2N rather than n > 2N / 3T).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import keys


@dataclass(frozen=True)
class Rules:
    """The method's constants; found by experiment, so all are parameters."""

    workers: int = 16
    heavy: tuple[int, int] | None = (2, 3)  # a bin is heavy above num * N / (den * workers); None: no bin is
    tiny: int = 384
    small: int = 32  # insertion up to here; also the tiny limit after a strong narrowing
    narrow: int | None = 16  # parent / bin above this is strong; None: never
    queue_div: int = 4096  # a child under N / queue_div stays with its worker
    shell: tuple[int, int] = (100, 180)  # Shell's limit for 8-byte and 16-byte keys
    team_slack: tuple[int, int] = (5, 4)
    team_rule: str = "scaled"  # literal: without the factor of all workers; one: no reservation
    levels: int = 8
    bits: int = 8


def chunk_plan(n: int, workers: int, per_worker: int = 8, first_div: int = 64, growth: str = "linear") -> list[tuple[int, int, int]]:
    """(chunk, start, length): sizes that grow linearly from n / (first_div * workers), or equal ones.

    Starts are floors of exact running sums, so lengths add up to n.
    """
    m = per_worker * workers
    if growth == "equal":
        starts = [n * k // m for k in range(m + 1)]
    else:
        # first size f = n/(first_div*workers); step d from m f + d m(m-1)/2 = n
        # running sum in units of 1/(first_div*workers*m*(m-1)): integers only
        unit = first_div * workers
        spare = unit - m  # (n - m f) in units of n / unit
        starts = [n * (k * m * (m - 1) + spare * k * (k - 1)) // (unit * m * (m - 1)) if m > 1 else n * k for k in range(m + 1)]
    return [(k, starts[k], starts[k + 1] - starts[k]) for k in range(m)]


def chunk_frame(spark: SparkSession, n: int, workers: int, **more) -> DataFrame:
    return spark.createDataFrame(chunk_plan(n, workers, **more), "chunk_id int, start long, length long")


def histogram(df: DataFrame, key: str, position: int = 7, bits: int = 8) -> DataFrame:
    """Rows by digit: partial counts in each task, then one small shuffle."""
    return df.select(keys.digit(F.col(key), position, bits).alias("digit")).groupBy("digit").agg(F.count("*").alias("n"))


def offsets(hist: DataFrame) -> DataFrame:
    """Rows of smaller digits: at most one row for each digit, so one task is enough."""
    w = Window.orderBy("digit").rowsBetween(Window.unboundedPreceding, -1)
    return hist.withColumn("base", F.coalesce(F.sum("n").over(w), F.lit(0)))


def is_heavy(n: Column, total: Column, r: Rules) -> Column:
    if r.heavy is None:
        return F.lit(False)
    return n * r.heavy[1] * r.workers > total * r.heavy[0]


def is_tiny(n: Column, parent_n: Column, r: Rules) -> Column:
    if not r.tiny:
        return F.lit(False)
    if r.narrow is None:
        return n < r.tiny
    return F.when(parent_n > n * r.narrow, n <= r.small).otherwise(n < r.tiny)


def teams(heavy_rows: int, total: int, r: Rules) -> tuple[int, int]:
    """(heavy team, light team) of the first pass."""
    if r.team_rule == "one" or not total:
        return 0, r.workers
    num, den = r.team_slack
    share = num * heavy_rows * (r.workers if r.team_rule == "scaled" else 1)
    heavy = min(r.workers, -(-share // (den * total))) if heavy_rows else 0
    return heavy, r.workers - heavy


def team_columns(heavy_rows: Column, total: Column, r: Rules) -> tuple[Column, Column]:
    num, den = r.team_slack
    share = heavy_rows * num * (r.workers if r.team_rule == "scaled" else 1)
    whole = F.expr("0") if r.team_rule == "one" else F.least(F.lit(r.workers).cast("long"), F.ceil(share / (total * den)))
    heavy = whole.cast("long")
    return heavy, F.lit(r.workers).cast("long") - heavy


def pick_split(size_bytes: int, cache_bytes: int = 256 << 10) -> str:
    """The counting split without buffers where a bin fits half the cache."""
    return "plain" if 2 * size_bytes <= cache_bytes else "staged"


def pick_tiny(n: int, key_bytes: int, r: Rules) -> str:
    if n <= r.small:
        return "insertion"
    return "shell" if n < shell_limit(key_bytes, r) else "introspective"


def shell_limit(key_bytes: int, r: Rules) -> int:
    """Linear in the key's bytes between the two ends of its range."""
    low, high = r.shell
    return max(low, min(high, low + (high - low) * (key_bytes - 8) // 8))


def level_counts(df: DataFrame, key: str, r: Rules) -> list[DataFrame]:
    """(lo, n) of every bin of each level, each from the level below: the rows are scanned once."""
    out, rows = [], df.select(F.col(key).alias("lo")).groupBy("lo").agg(F.count("*").alias("n"))
    for level in range(r.levels, 0, -1):
        if level < r.levels:
            rows = rows.groupBy(keys.floor_key(F.col("lo"), level, r.bits).alias("lo")).agg(F.sum("n").alias("n"))
        out.append(rows)
    return out[::-1]


def decisions(df: DataFrame, key: str, r: Rules, total: int) -> DataFrame:
    """What becomes of every bin that the method makes: (level, lo, n, parent_n, side, action).

    side: team (split by a whole team) or worker.  action: heavy, light (queued
    after a team's pass), queued or recursed (after a worker's), tiny, done.
    """
    counts = level_counts(df, key, r)
    size = F.lit(total).cast("long")
    split = None  # bins of the level above that are split: lo, n, by team
    levels = []
    for level, rows in enumerate(counts, 1):
        if split is None:
            made = rows.select("lo", "n", size.alias("parent_n"), F.lit(True).alias("by_team"))
        else:
            up = split.select(F.col("lo").alias("up"), F.col("n").alias("parent_n"), (F.col("action") == "heavy").alias("by_team"))
            made = rows.join(up, keys.floor_key(F.col("lo"), level - 1, r.bits) == F.col("up")).select("lo", "n", "parent_n", "by_team")
        n, parent = F.col("n"), F.col("parent_n")
        action = (
            F.when(F.lit(level == r.levels), "done")
            .when(F.col("by_team") & is_heavy(n, size, r), "heavy")
            .when(F.col("by_team"), "light")
            .when(is_tiny(n, parent, r), "tiny")
            .when(n * r.queue_div < size, "recursed")
            .otherwise("queued")
        )
        made = made.select(F.lit(level).alias("level"), "lo", "n", "parent_n", F.when(F.col("by_team"), "team").otherwise("worker").alias("side"), action.alias("action"))
        levels.append(made)
        split = made.filter(~F.col("action").isin("tiny", "done"))
    out = levels[0]
    for x in levels[1:]:
        out = out.unionAll(x)
    return out


def light_queue(bins: DataFrame) -> DataFrame:
    """Bins in the order in which workers take them: largest first, ties by key."""
    return bins.withColumn("turn", F.row_number().over(Window.orderBy(F.desc("n"), "lo")))


def longest_first(sizes: list[int], workers: int) -> list[int]:
    """Each bin's worker when idle workers take the largest bin left; deterministic."""
    import heapq

    load = [(0, w) for w in range(workers)]
    out = [0] * len(sizes)
    for k in sorted(range(len(sizes)), key=lambda k: (-sizes[k], k)):
        done, w = heapq.heappop(load)
        out[k] = w
        heapq.heappush(load, (done + sizes[k], w))
    return out


def schedule(heavy: list[int], light: list[int], total: int, r: Rules, handover: bool = True, fifo: bool = False) -> dict[str, float]:
    """Simulated finishing time, in rows moved by one worker: teams first, then the common queue.

    The heavy team takes heavy bins one after another; its members join the light
    queue when they are released (unless ``handover`` is off).
    """
    import heapq

    heavy_team, light_team = teams(sum(heavy), total, r)
    released = sum(h / max(1, heavy_team) for h in heavy)
    free = [0.0] * light_team + [released] * (heavy_team if handover or not light_team else 0)
    heapq.heapify(free)
    end = released
    for n in light if fifo else sorted(light, reverse=True):
        at = heapq.heappop(free) + n
        end = max(end, at)
        heapq.heappush(free, at)
    ideal = total / r.workers
    return {"heavy_team": heavy_team, "light_team": light_team, "released": released, "finish": end, "speedup": total / end if end else float(r.workers), "imbalance": end / ideal if ideal else 1.0}

"""Cost measures: times, speedups, ranks, balance, moves, memory, plan counts."""

from __future__ import annotations

import json
import re
import statistics
import time
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def timed(make: Callable[[], DataFrame], repeats: int = 3, warm: bool = True) -> float:
    """Median seconds to run a frame into the sink that drops rows."""
    runs = []
    for k in range(repeats + warm):
        start = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if k or not warm:
            runs.append(time.perf_counter() - start)
    return statistics.median(runs)


def stored() -> dict[str, list[dict]]:
    """Times that ``bench.py`` measured and stored beside this module: sizes, cores, records."""
    return json.loads(Path(__file__).with_name("measured.json").read_text())


def speedup(times: DataFrame) -> DataFrame:
    """times: algorithm, workers, seconds.  Adds the time of one worker over this time, for the same algorithm."""
    one = F.max(F.when(F.col("workers") == 1, F.col("seconds"))).over(Window.partitionBy("algorithm"))
    return times.withColumn("speedup", F.round(one / F.col("seconds"), 6))


def ranking(times: DataFrame) -> DataFrame:
    """times: workload, algorithm, seconds.  Adds the rank within a workload, fastest first."""
    return times.withColumn("place", F.rank().over(Window.partitionBy("workload").orderBy("seconds")))


def growth(times: DataFrame) -> DataFrame:
    """times: bytes, seconds.  Time over that of the smallest record, beside the ratio of sizes."""
    w = Window.orderBy("bytes").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return times.select("bytes", "seconds", F.round(F.col("bytes") / F.first("bytes").over(w), 6).alias("size_ratio"), F.round(F.col("seconds") / F.first("seconds").over(w), 6).alias("time_ratio"))


def throughput(rows: int, record: int, seconds: float) -> dict[str, float]:
    return {"records_per_s": rows / seconds, "bytes_per_s": rows * record / seconds}


def balance(df: DataFrame) -> DataFrame:
    """(partitions, rows, most, imbalance) of a frame's physical partitions."""
    per = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("partitions"), F.sum("n").alias("rows"), F.max("n").alias("most"), F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"))


def extra_bytes(n: Column, record: int, in_place: bool) -> Column:
    """Memory beside the records: a second array, or 256 counters of each of eight levels."""
    return F.lit(256 * 8 * 8).cast("long") if in_place else n * record


def plan_counts(df: DataFrame) -> dict[str, int]:
    """Exchanges, sorts, scans and Python operators of the executed plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    count = lambda p: len(re.findall(p, text))
    return {"exchanges": count(r"(?<!Broadcast)Exchange (?!Single)"), "broadcasts": count(r"BroadcastExchange"), "sorts": count(r"\bSort \["), "scans": count(r"FileScan"), "python": count(r"MapInArrow|MapInPandas|ArrowEvalPython")}

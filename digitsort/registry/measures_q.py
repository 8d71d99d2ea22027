"""Measures of the method, its baselines and its ablations, on plans and stored times."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import measures
from ..functions import keys
from ..operators import finishing, passes, sorts
from ..plans import bins
from ..session import table
from ..sources import workloads as wl
from . import common as c

WORKERS, POSITIONS = (1, 2, 4, 8, 16), (0, 1, 7)


def _busiest(rows: DataFrame, *by: str) -> DataFrame:
    """(by, algorithm, workers, n): the rows of the busiest worker where a digit of ``key``, by its position, deals rows out."""
    digits = F.explode(F.array(*(F.struct(F.lit(f"digit_{p}").alias("algorithm"), keys.digit(F.col("key"), p).alias("digit")) for p in POSITIONS)))
    hist = rows.select(*by, digits.alias("x")).groupBy(*by, "x.algorithm", "x.digit").agg(F.count("*").alias("n"))
    each = hist.select("*", F.explode(F.array(*map(F.lit, WORKERS))).alias("workers"))
    loads = each.groupBy(*by, "algorithm", "workers", (F.col("digit") % F.col("workers")).alias("worker")).agg(F.sum("n").alias("n"))
    return loads.groupBy(*by, "algorithm", "workers").agg(F.max("n").alias("n"))


def _scatter(spark: SparkSession, d: str) -> DataFrame:
    return wl.zipf(spark, d, scatter=True)


def _bins(source, r: bins.Rules):
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = source(spark, d)
        return bins.decisions(rows, "key", r, rows.count())

    return run


def _summary(source, r: bins.Rules):
    return lambda spark, d: _bins(source, r)(spark, d).groupBy("level", "side", "action").agg(F.count("*").alias("bins"), F.sum("n").alias("rows"))


def measure_speedup(spark: SparkSession, d: str) -> DataFrame:
    """Of a pass that deals Zipf keys out by a digit: its busiest worker's time, at a million rows a second."""
    times = _busiest(wl.zipf(spark, d).select("key")).select("algorithm", "workers", (F.col("n") / F.lit(1e6)).alias("seconds"))
    return measures.speedup(times)


def measure_ranking(spark: SparkSession, d: str) -> DataFrame:
    """The digits that deal a workload out to 16 workers, fastest first."""
    works = {"uniform": wl.uniform(spark, d), "zipf": wl.zipf(spark, d), "scatter": _scatter(spark, d)}
    rows = None
    for name, work in works.items():
        r = work.select(F.lit(name).alias("workload"), "key")
        rows = r if rows is None else rows.unionAll(r)
    times = _busiest(rows, "workload").filter(F.col("workers") == 16)
    return measures.ranking(times.select("workload", "algorithm", (F.col("n") / F.lit(1e6)).alias("seconds")))


def measure_growth(spark: SparkSession, d: str) -> DataFrame:
    """Of a pass by the leading digit on 16 workers, by the record's size: keys are read to be counted, records read and written, at a GB a second."""
    most = _busiest(wl.uniform(spark, d).select("key")).filter("workers = 16 AND algorithm = 'digit_7'")
    sizes = most.select("n", F.explode(F.array(*map(F.lit, (8, 16, 24, 32)))).alias("bytes"))
    return measures.growth(sizes.select("bytes", (F.col("n") * (8 + 2 * F.col("bytes")) / F.lit(1e9)).alias("seconds")))


def measure_passes(spark: SparkSession, d: str) -> DataFrame:
    """Digits that differ, by position: passes an LSD sort makes, two traversals each."""
    rows = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"))
    each = rows.select(F.explode(F.array(*(F.struct(F.lit(p).alias("position"), keys.digit(F.col("key"), p).alias("digit")) for p in range(8)))).alias("x")).select("x.*")
    return each.groupBy("position").agg(F.count_distinct("digit").alias("digits")).withColumn("traversals", F.when(F.col("digits") > 1, 2).otherwise(0))


def measure_balance(spark: SparkSession, d: str) -> DataFrame:
    """Largest over mean bin of each level and class."""
    rows = _bins(_scatter, bins.Rules(workers=16))(spark, d)
    return rows.groupBy("level", "action").agg(F.count("*").alias("bins"), F.max("n").alias("most"), F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"))


def measure_partition_balance(spark: SparkSession, d: str) -> DataFrame:
    """Rows of the routed partitions, counted against sampled borders: every row is in one."""
    out = None
    for name, sampled in (("counted", False), ("sampled", True)):
        b = measures.balance(sorts.adaptive_msd(wl.zipf(spark, d), ["key", *wl.TIES], sampled=sampled)).withColumn("plan", F.lit(name))
        out = b if out is None else out.unionAll(b)
    return out


def measure_queue_ops(spark: SparkSession, d: str) -> DataFrame:
    rows = _bins(_scatter, bins.Rules(workers=16))(spark, d)
    queued = F.col("action").isin("light", "queued")
    return rows.agg((F.count_if(queued) * 2).alias("queue_ops"), F.count_if(F.col("action") == "recursed").alias("spared"), F.count_if(F.col("action") == "heavy").alias("team_passes"))


def measure_moves(spark: SparkSession, d: str) -> DataFrame:
    """Rows moved: by the recursive sort (each split bin's rows, and all in the first pass), by LSD, by one routed shuffle."""
    rows = _bins(_scatter, bins.Rules(workers=16))(spark, d)
    n = table(spark, d, "lineitem").count()
    split = F.coalesce(F.sum(F.when(~F.col("action").isin("tiny", "done"), F.col("n"))), F.lit(0))
    return rows.agg((split + n).alias("msd_moves"), F.lit(8 * n).alias("lsd_moves"), F.lit(n).alias("routed_moves"))


def measure_memory(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "lineitem").agg(F.count("*").alias("n"))
    return n.select("n", (F.col("n") * 16).alias("input_bytes"), measures.extra_bytes(F.col("n"), 16, False).alias("out_of_place"), measures.extra_bytes(F.col("n"), 16, True).alias("in_place"))


def measure_kernel_counts(spark: SparkSession, d: str) -> DataFrame:
    return finishing.kernel_counts(_scatter(spark, d), "key")


def _flushes(staging: int):
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = passes.with_position(wl.uniform(spark, d), wl.TIES)
        return passes.staging_flushes(rows, "key", 7, staging, F.floor(F.col("pos") / 4096))

    return run


def wl_threads_plan(spark: SparkSession, d: str) -> DataFrame:
    """First-pass classes for each number of workers."""
    hist = bins.histogram(_scatter(spark, d), "key").select("n")
    total = hist.agg(F.sum("n").alias("total"))
    each = hist.crossJoin(F.broadcast(total)).select("n", "total", F.explode(F.array(*map(F.lit, (1, 2, 3, 4, 6, 8, 12, 16, 24)))).alias("workers"))  # total is one row
    heavy = F.col("n") * 3 * F.col("workers") > F.col("total") * 2
    return each.groupBy("workers").agg(F.count_if(heavy).alias("heavy_bins"), F.coalesce(F.sum(F.when(heavy, F.col("n"))), F.lit(0)).alias("heavy_rows"), F.count_if(~heavy).alias("light_bins"))


R = bins.Rules
ABLATIONS = {"paper": R(), "heavy": R(heavy=None), "tiny": R(tiny=0), "narrow": R(narrow=None)}
QUERIES = {f.__name__: f for f in (measure_speedup, measure_ranking, measure_growth, measure_passes, measure_balance, measure_partition_balance, measure_queue_ops, measure_moves, measure_memory, measure_kernel_counts, wl_threads_plan)} | {
    "measure_bins": _summary(_scatter, R()),
    "measure_bins_wide": _summary(lambda spark, d: wl.zipf(spark, d, universe=1 << 20), R()),
    "staging_flushes": _flushes(64),
    "staging_flushes_256": _flushes(256),
    "ablate_heavy_bins": _summary(_scatter, ABLATIONS["heavy"]),
    "ablate_tiny": _summary(_scatter, ABLATIONS["tiny"]),
    "ablate_narrow": _summary(lambda spark, d: wl.zipf(spark, d, universe=1 << 20), ABLATIONS["narrow"]),
}

_SUM = "SELECT level, side, action, count(*) AS bins, sum(n)::BIGINT AS rows FROM bins GROUP BY ALL"
_works = lambda **sources: " UNION ALL ".join(f"SELECT '{w}' AS workload, 'digit_{p}' AS algorithm, {c.digit('key', p)} AS digit, count(*) AS n FROM {source} GROUP BY ALL" for w, source in sources.items() for p in POSITIONS)
_busy = lambda **sources: f"WITH h AS ({_works(**sources)}), l AS (SELECT workload, algorithm, workers, sum(n) AS n FROM h, (SELECT unnest({list(WORKERS)}) AS workers) GROUP BY workload, algorithm, workers, digit % workers), b AS (SELECT workload, algorithm, workers, max(n) AS n FROM l GROUP BY ALL)"
_flush = lambda slots: f"SELECT digit, sum(n)::BIGINT AS n, sum((n + {slots - 1}) // {slots})::BIGINT AS flushes FROM (SELECT {c.digit('key', 7)} AS digit, pos // 4096 AS chunk, count(*) AS n FROM (SELECT *, row_number() OVER (ORDER BY {c.TIES}) - 1 AS pos FROM {c.UNIFORM}) GROUP BY ALL) GROUP BY 1"
SQL = {
    "measure_speedup": f"{_busy(zipf=c.ZIPF)}, t AS (SELECT algorithm, workers, n::DOUBLE / 1e6::DOUBLE AS seconds FROM b) SELECT algorithm, workers, seconds, round(max(CASE WHEN workers = 1 THEN seconds END) OVER (PARTITION BY algorithm) / seconds, 6) AS speedup FROM t",
    "measure_ranking": f"{_busy(uniform=c.UNIFORM, zipf=c.ZIPF, scatter=c.SCATTER)}, t AS (SELECT workload, algorithm, n::DOUBLE / 1e6::DOUBLE AS seconds FROM b WHERE workers = 16) SELECT workload, algorithm, seconds, rank() OVER (PARTITION BY workload ORDER BY seconds) AS place FROM t",
    "measure_growth": f"{_busy(uniform=c.UNIFORM)}, t AS (SELECT bytes, (n * (8 + 2 * bytes))::DOUBLE / 1e9::DOUBLE AS seconds FROM b, (SELECT unnest([8, 16, 24, 32]) AS bytes) WHERE workers = 16 AND algorithm = 'digit_7') SELECT bytes, seconds, round(bytes / min(bytes) OVER (), 6) AS size_ratio, round(seconds / first(seconds) OVER (ORDER BY bytes), 6) AS time_ratio FROM t",
    "measure_passes": " UNION ALL ".join(f"SELECT {p} AS position, count(DISTINCT {c.digit('l_orderkey', p)}) AS digits, CASE WHEN count(DISTINCT {c.digit('l_orderkey', p)}) > 1 THEN 2 ELSE 0 END AS traversals FROM lineitem" for p in range(8)),
    "measure_bins": c.decisions(c.SCATTER) + _SUM,
    "measure_bins_wide": c.decisions(c.ZIPF_WIDE) + _SUM,
    "measure_balance": c.decisions(c.SCATTER) + "SELECT level, action, count(*) AS bins, max(n) AS most, round(max(n) / avg(n), 6) AS imbalance FROM bins GROUP BY ALL",
    "measure_queue_ops": c.decisions(c.SCATTER) + "SELECT 2 * count(*) FILTER (action IN ('light', 'queued')) AS queue_ops, count(*) FILTER (action = 'recursed') AS spared, count(*) FILTER (action = 'heavy') AS team_passes FROM bins",
    "measure_moves": c.decisions(c.SCATTER) + "SELECT (coalesce(sum(n) FILTER (action NOT IN ('tiny', 'done')), 0) + any_value(total))::BIGINT AS msd_moves, any_value(total) * 8 AS lsd_moves, any_value(total) AS routed_moves FROM bins, tot",
    "measure_memory": "SELECT count(*) AS n, count(*) * 16 AS input_bytes, count(*) * 16 AS out_of_place, 16384::BIGINT AS in_place FROM lineitem",
    "staging_flushes": _flush(4),
    "staging_flushes_256": _flush(16),
    "ablate_heavy_bins": c.decisions(c.SCATTER, heavy=False) + _SUM,
    "ablate_tiny": c.decisions(c.SCATTER, tiny=0) + _SUM,
    "ablate_narrow": c.decisions(c.ZIPF_WIDE, narrow=None) + _SUM,
    "wl_threads_plan": f"WITH h AS (SELECT {c.digit('key', 7)} AS digit, count(*) AS n FROM {c.SCATTER} GROUP BY 1), t AS (SELECT sum(n)::BIGINT AS total FROM h), w AS (SELECT unnest([1, 2, 3, 4, 6, 8, 12, 16, 24]) AS workers) SELECT workers, count(*) FILTER (n * 3 * workers > total * 2) AS heavy_bins, coalesce(sum(n) FILTER (n * 3 * workers > total * 2), 0)::BIGINT AS heavy_rows, count(*) FILTER (n * 3 * workers <= total * 2) AS light_bins FROM h, t, w GROUP BY workers",
}

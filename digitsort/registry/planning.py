"""Digits, histograms, chunks, bins, classes, teams, queues and dispatch decisions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import keys
from ..operators import passes
from ..plans import bins
from ..session import table
from ..sources import workloads as wl
from . import common as c

T16 = bins.Rules(workers=16)


def _orderkeys(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"))


def digit_extract(spark: SparkSession, d: str) -> DataFrame:
    k = F.col("key")
    return wl.uniform(spark, d).select(*wl.TIES, *(keys.digit(k, p).alias(f"d{p}") for p in range(8)))


def digit_extract_bits(spark: SparkSession, d: str) -> DataFrame:
    k = F.col("key")
    return wl.uniform(spark, d).select(*wl.TIES, *(keys.digit(k, 0, b).alias(f"low{b}") for b in (1, 2, 4, 8, 11, 16)), *(keys.digit(k, 1, b).alias(f"next{b}") for b in (1, 2, 4, 8, 11, 16)))


def digit_histogram(spark: SparkSession, d: str) -> DataFrame:
    return bins.histogram(wl.uniform(spark, d), "key")


def digit_offsets(spark: SparkSession, d: str) -> DataFrame:
    return bins.offsets(bins.histogram(wl.uniform(spark, d), "key"))


def parallel_split(spark: SparkSession, d: str) -> DataFrame:
    rows = passes.with_position(wl.uniform(spark, d), wl.TIES)
    plan = bins.chunk_plan(rows.count(), 4)
    return passes.parallel_split(rows, "key", 7, passes.chunk_of(F.col("pos"), plan))


def ablate_chunks(spark: SparkSession, d: str) -> DataFrame:
    """The parallel split over equal chunks."""
    rows = passes.with_position(wl.uniform(spark, d), wl.TIES)
    plan = bins.chunk_plan(rows.count(), 4, growth="equal")
    return passes.parallel_split(rows, "key", 7, passes.chunk_of(F.col("pos"), plan))


def ablate_team(spark: SparkSession, d: str) -> DataFrame:
    """No team is reserved for heavy bins."""
    first = _first_pass(spark, d)
    heavy, light = bins.team_columns(F.col("heavy_rows"), F.col("total"), bins.Rules(workers=16, team_rule="one"))
    sums = first.agg(F.coalesce(F.sum(F.when(F.col("class") == "heavy", F.col("n"))), F.lit(0)).alias("heavy_rows"), F.sum("n").alias("total"))
    return sums.select("heavy_rows", "total", heavy.alias("heavy_team"), light.alias("light_team"))


def ablate_fifo(spark: SparkSession, d: str) -> DataFrame:
    """Light bins in the order in which they were made, instead of largest first."""
    made = _filtered("level = 1 AND action = 'light'", "lo", "n")(spark, d)
    return made.withColumn("turn", F.row_number().over(Window.orderBy("lo")))  # at most 256 bins


def chunk_plan(spark: SparkSession, d: str) -> DataFrame:
    return bins.chunk_frame(spark, table(spark, d, "lineitem").count(), 16)


def chunk_plan_equal(spark: SparkSession, d: str) -> DataFrame:
    return bins.chunk_frame(spark, table(spark, d, "lineitem").count(), 16, growth="equal")


def _decided(source, r: bins.Rules = T16):
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = source(spark, d)
        return bins.decisions(rows, "key", r, rows.count())

    return run


_scatter = lambda spark, d: wl.zipf(spark, d, scatter=True)
_wide = lambda spark, d: wl.zipf(spark, d, universe=1 << 20)


def _first_pass(spark: SparkSession, d: str) -> DataFrame:
    rows = _scatter(spark, d)
    return bins.histogram(rows, "key").withColumn("class", F.when(bins.is_heavy(F.col("n"), F.lit(rows.count()), T16), "heavy").otherwise("light"))


def team_sizes(spark: SparkSession, d: str) -> DataFrame:
    out = None
    first = _first_pass(spark, d)
    sums = first.agg(F.coalesce(F.sum(F.when(F.col("class") == "heavy", F.col("n"))), F.lit(0)).alias("heavy_rows"), F.sum("n").alias("total"))
    for rule in ("scaled", "literal"):
        heavy, light = bins.team_columns(F.col("heavy_rows"), F.col("total"), bins.Rules(workers=16, team_rule=rule))
        part = sums.select(F.lit(rule).alias("rule"), "heavy_rows", "total", heavy.alias("heavy_team"), light.alias("light_team"))
        out = part if out is None else out.unionAll(part)
    return out


def _filtered(condition: str, *columns: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return _decided(_scatter)(spark, d).filter(condition).select(*columns)

    return run


def light_queue_order(spark: SparkSession, d: str) -> DataFrame:
    return bins.light_queue(_filtered("level = 1 AND action = 'light'", "lo", "n")(spark, d))


def heavy_queue_order(spark: SparkSession, d: str) -> DataFrame:
    return bins.light_queue(_filtered("level > 1 AND side = 'team' AND action = 'light'", "level", "lo", "n")(spark, d))


def lpt_assignment(spark: SparkSession, d: str) -> DataFrame:
    first = sorted((r["lo"], r["n"]) for r in _filtered("level = 1 AND action = 'light'", "lo", "n")(spark, d).collect())  # at most 256 bins
    worker = bins.longest_first([n for _, n in first], 16)
    return spark.createDataFrame([(lo, n, w) for (lo, n), w in zip(first, worker, strict=True)], "lo long, n long, worker int")


def schedule_sim(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for name, source in (("uniform", wl.uniform), ("scatter", _scatter)):
        found = _decided(source)(spark, d).filter("side = 'team' AND level = 1").collect()  # at most 256 bins
        heavy, light = ([r["n"] for r in found if r["action"] == a] for a in ("heavy", "light"))
        total = sum(heavy) + sum(light)
        for t in (1, 2, 3, 4, 6, 8, 12, 16, 24):
            for mode in ("paper", "one_team", "fifo", "no_handover"):
                r = bins.Rules(workers=t, team_rule="one" if mode == "one_team" else "scaled")
                big = [n for n in heavy + light if n * 3 * t > 2 * total]
                small = [n for n in heavy + light if n * 3 * t <= 2 * total]
                if mode == "one_team":
                    big, small = [], heavy + light
                s = bins.schedule(big, small, total, r, handover=mode != "no_handover", fifo=mode == "fifo")
                rows.append((name, t, mode, s["heavy_team"], s["light_team"], round(s["speedup"], 6), round(s["imbalance"], 6)))
    return spark.createDataFrame(rows, "workload string, workers int, mode string, heavy_team int, light_team int, speedup double, imbalance double")


def split_choice(spark: SparkSession, d: str) -> DataFrame:
    size = F.col("n") * 16
    return _filtered("side = 'worker' OR action = 'light'", "level", "lo", "n")(spark, d).withColumn("split", F.when(size * 2 <= (256 << 10), "plain").otherwise("staged"))


def tiny_choice(spark: SparkSession, d: str) -> DataFrame:
    n = F.col("n")
    choice = lambda limit: F.when(n <= 32, "insertion").when(n < limit, "shell").otherwise("introspective")
    return _filtered("action = 'tiny'", "level", "lo", "n", "parent_n")(spark, d).select("*", choice(bins.shell_limit(8, T16)).alias("finisher8"), choice(bins.shell_limit(16, T16)).alias("finisher16"))


def narrowing_rule(spark: SparkSession, d: str) -> DataFrame:
    rows = _decided(_wide)(spark, d).filter("side = 'worker' AND action <> 'done'")
    strong = F.col("parent_n") > F.col("n") * 16
    return rows.select("level", "lo", "n", "parent_n", strong.alias("strong"), F.when(strong, 32).otherwise(384).alias("tiny_limit"), (strong & F.col("n").between(33, 383)).alias("changed"))


def last_digit_stop(spark: SparkSession, d: str) -> DataFrame:
    return _decided(wl.zipf)(spark, d).filter("action = 'done'").select("level", "lo", "n", "side")


def common_prefix(spark: SparkSession, d: str) -> DataFrame:
    from ..plans.route import common_prefix_bits

    x = _orderkeys(spark, d).agg(F.min("key").alias("low"), F.max("key").alias("high")).first()
    return spark.createDataFrame([(x["low"], x["high"], common_prefix_bits(x["low"], x["high"]) // 8)], "low long, high long, equal_bytes int")


def equal_key_bins(spark: SparkSession, d: str) -> DataFrame:
    """Bins of one key that are heavy: they can be cut anywhere."""
    rows = wl.zipf(spark, d)
    total = rows.count()
    per = rows.groupBy("key").agg(F.count("*").alias("n")).filter(bins.is_heavy(F.col("n"), F.lit(total), T16))
    return per.withColumn("pieces", F.ceil(F.col("n") * 16 / F.lit(total)))


def heavy_refine(spark: SparkSession, d: str) -> DataFrame:
    return _filtered("side = 'team' AND level > 1", "level", "lo", "n", "parent_n", "action")(spark, d)


def kernel_finishers(name: str):
    """Every tiny bin through one finisher, in groups; the order is checked by position in the bin."""
    from ..operators import finishing

    return lambda spark, d: finishing.finish_bins(_scatter(spark, d), "key", name)


QUERIES = {f.__name__: f for f in (digit_extract, digit_extract_bits, digit_histogram, digit_offsets, parallel_split, chunk_plan, chunk_plan_equal, ablate_chunks, ablate_team, ablate_fifo, team_sizes, light_queue_order, heavy_queue_order, lpt_assignment, schedule_sim, split_choice, tiny_choice, narrowing_rule, last_digit_stop, common_prefix, equal_key_bins, heavy_refine)} | {
    "first_pass_bins": _first_pass,
    "bin_classes": _decided(_scatter),
    "bin_classes_uniform": _decided(wl.uniform),
    "child_dispatch": _filtered("side = 'worker' AND action IN ('recursed', 'queued')", "level", "lo", "n", "action"),
    "tiny_bins": _filtered("action = 'tiny'", "level", "lo", "n", "parent_n"),
    "tiny_insertion": kernel_finishers("insertion"),
    "tiny_shell": kernel_finishers("shell"),
    "tiny_introspective": kernel_finishers("introspective"),
}

_bins = lambda source, select, **more: c.decisions(source, **more) + "\n" + select
_TEAM = "SELECT lo, n, row_number() OVER (ORDER BY n DESC, lo) AS turn FROM bins WHERE level = 1 AND action = 'light'"
_CHUNK = """WITH t AS (SELECT count(*)::HUGEINT AS n FROM lineitem), k AS (SELECT unnest(range(0, 129))::HUGEINT AS k),
s AS (SELECT k, {start} AS s FROM k, t)
SELECT a.k::INT AS chunk_id, a.s::BIGINT AS start, (b.s - a.s)::BIGINT AS length FROM s a JOIN s b ON b.k = a.k + 1"""
_FINISH = f"SELECT key, {c.TIES}, row_number() OVER (PARTITION BY {c.floor_key('key', 2)} ORDER BY {c.TIES}) AS arrival, row_number() OVER (PARTITION BY {c.floor_key('key', 2)} ORDER BY key, {c.TIES}) AS place FROM (SELECT *, count(*) OVER (PARTITION BY {c.floor_key('key', 2)}) AS m FROM {c.SCATTER}) WHERE m < 384"
SQL = {
    "digit_extract": f"SELECT {c.TIES}, {', '.join(f'{c.digit('key', p)} AS d{p}' for p in range(8))} FROM {c.UNIFORM}",
    "digit_extract_bits": f"SELECT {c.TIES}, {', '.join(f'{c.digit('key', 0, b)} AS low{b}, {c.digit('key', 1, b)} AS next{b}' for b in (1, 2, 4, 8, 11, 16))} FROM {c.UNIFORM}",
    "digit_histogram": f"SELECT {c.digit('key', 7)} AS digit, count(*) AS n FROM {c.UNIFORM} GROUP BY 1",
    "digit_offsets": f"SELECT digit, n, coalesce(sum(n) OVER (ORDER BY digit ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS base FROM (SELECT {c.digit('key', 7)} AS digit, count(*) AS n FROM {c.UNIFORM} GROUP BY 1)",
    "parallel_split": f"""WITH t AS (SELECT count(*)::HUGEINT AS n FROM lineitem), s AS (SELECT k::INT AS k, n * (k * 992 + 224 * k * (k - 1)) // 253952 AS s FROM (SELECT unnest(range(0, 32))::HUGEINT AS k), t),
r AS (SELECT {c.digit('key', 7)} AS digit, row_number() OVER (ORDER BY {c.TIES}) - 1 AS pos FROM {c.UNIFORM}),
g AS (SELECT k AS chunk, digit, count(*) AS n FROM (SELECT r.digit, s.k FROM r ASOF JOIN s ON r.pos >= s.s) GROUP BY ALL)
SELECT chunk, digit, n, coalesce(sum(n) OVER (ORDER BY digit, chunk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS base FROM g""",
    "ablate_chunks": f"""WITH t AS (SELECT count(*)::HUGEINT AS n FROM lineitem), s AS (SELECT k::INT AS k, n * k // 32 AS s FROM (SELECT unnest(range(0, 32))::HUGEINT AS k), t),
r AS (SELECT {c.digit('key', 7)} AS digit, row_number() OVER (ORDER BY {c.TIES}) - 1 AS pos FROM {c.UNIFORM}),
g AS (SELECT k AS chunk, digit, count(*) AS n FROM (SELECT r.digit, s.k FROM r ASOF JOIN s ON r.pos >= s.s) GROUP BY ALL)
SELECT chunk, digit, n, coalesce(sum(n) OVER (ORDER BY digit, chunk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS base FROM g""",
    "ablate_team": f"WITH h AS (SELECT {c.digit('key', 7)} AS digit, count(*) AS n FROM {c.SCATTER} GROUP BY 1), t AS (SELECT sum(n)::BIGINT AS total FROM h) SELECT coalesce(sum(n) FILTER (n * 48 > total * 2), 0)::BIGINT AS heavy_rows, any_value(total) AS total, 0::BIGINT AS heavy_team, 16::BIGINT AS light_team FROM h, t",
    "ablate_fifo": _bins(c.SCATTER, "SELECT lo, n, row_number() OVER (ORDER BY lo) AS turn FROM bins WHERE level = 1 AND action = 'light'"),
    "chunk_plan": _CHUNK.format(start="n * (k * 128 * 127 + 896 * k * (k - 1)) // (1024::HUGEINT * 128 * 127)"),
    "chunk_plan_equal": _CHUNK.format(start="n * k // 128"),
    "first_pass_bins": f"WITH h AS (SELECT {c.digit('key', 7)} AS digit, count(*) AS n FROM {c.SCATTER} GROUP BY 1) SELECT digit, n, CASE WHEN n * 48 > (SELECT count(*) FROM lineitem) * 2 THEN 'heavy' ELSE 'light' END AS class FROM h",
    "bin_classes": _bins(c.SCATTER, "SELECT * FROM bins"),
    "bin_classes_uniform": _bins(c.UNIFORM, "SELECT * FROM bins"),
    "team_sizes": f"""WITH h AS (SELECT {c.digit('key', 7)} AS digit, count(*) AS n FROM {c.SCATTER} GROUP BY 1), t AS (SELECT sum(n)::BIGINT AS total FROM h), s AS (SELECT coalesce(sum(n) FILTER (n * 48 > total * 2), 0)::BIGINT AS heavy_rows, any_value(total) AS total FROM h, t),
r AS (SELECT 'scaled' AS rule, heavy_rows, total, least(16, ceil(heavy_rows * 80 / (total * 4)::DOUBLE))::BIGINT AS heavy_team FROM s UNION ALL SELECT 'literal', heavy_rows, total, least(16, ceil(heavy_rows * 5 / (total * 4)::DOUBLE))::BIGINT FROM s) SELECT *, 16 - heavy_team AS light_team FROM r""",
    "light_queue_order": _bins(c.SCATTER, _TEAM),
    "heavy_queue_order": _bins(c.SCATTER, "SELECT level, lo, n, row_number() OVER (ORDER BY n DESC, lo) AS turn FROM bins WHERE level > 1 AND side = 'team' AND action = 'light'"),
    "split_choice": _bins(c.SCATTER, "SELECT level, lo, n, CASE WHEN n * 32 <= 262144 THEN 'plain' ELSE 'staged' END AS split FROM bins WHERE side = 'worker' OR action = 'light'"),
    "child_dispatch": _bins(c.SCATTER, "SELECT level, lo, n, action FROM bins WHERE side = 'worker' AND action IN ('recursed', 'queued')"),
    "tiny_bins": _bins(c.SCATTER, "SELECT level, lo, n, parent_n FROM bins WHERE action = 'tiny'"),
    "tiny_choice": _bins(c.SCATTER, "SELECT level, lo, n, parent_n, CASE WHEN n <= 32 THEN 'insertion' WHEN n < 100 THEN 'shell' ELSE 'introspective' END AS finisher8, CASE WHEN n <= 32 THEN 'insertion' WHEN n < 180 THEN 'shell' ELSE 'introspective' END AS finisher16 FROM bins WHERE action = 'tiny'"),
    "narrowing_rule": _bins(c.ZIPF_WIDE, "SELECT level, lo, n, parent_n, parent_n > n * 16 AS strong, CASE WHEN parent_n > n * 16 THEN 32 ELSE 384 END AS tiny_limit, parent_n > n * 16 AND n BETWEEN 33 AND 383 AS changed FROM bins WHERE side = 'worker' AND action <> 'done'"),
    "last_digit_stop": _bins(c.ZIPF, "SELECT level, lo, n, side FROM bins WHERE action = 'done'"),
    "heavy_refine": _bins(c.SCATTER, "SELECT level, lo, n, parent_n, action FROM bins WHERE side = 'team' AND level > 1"),
    "common_prefix": "SELECT min(l_orderkey) AS low, max(l_orderkey) AS high, 7 - floor(log2(xor(min(l_orderkey), max(l_orderkey))) / 8)::INT AS equal_bytes FROM lineitem",
    "equal_key_bins": f"SELECT key, n, ceil(n * 16 / total::DOUBLE)::BIGINT AS pieces FROM (SELECT key, count(*) AS n FROM {c.ZIPF} GROUP BY 1), (SELECT count(*) AS total FROM lineitem) WHERE n * 48 > total * 2",
    "tiny_insertion": _FINISH,
    "tiny_shell": _FINISH,
    "tiny_introspective": _FINISH,
}

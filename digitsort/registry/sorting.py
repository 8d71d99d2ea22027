"""Sorters on the workloads: every result carries each row's position by placement."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import keys
from ..operators import passes, sorts
from ..plans import bins
from ..plans.bins import Rules
from ..session import table
from ..sources import workloads as wl
from . import common as c

KEYS = ["key", *wl.TIES]
ORDER = f"key, {c.TIES}"


def _sorted(source: Callable, sorter: Callable = sorts.adaptive_msd, columns: list[str] = KEYS, **more) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: sorts.with_rank(sorter(source(spark, d), columns, **more))


def _lsd(staging: int | None, source: Callable = wl.uniform) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        return sorts.lsd(passes.with_position(source(spark, d), wl.TIES), "key", "pos", staging)

    return run


def _orderkey(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"), *wl.TIES)


def _wide(spark: SparkSession, d: str) -> DataFrame:
    return wl.zipf(spark, d, universe=1 << 20)


def _scatter(spark: SparkSession, d: str) -> DataFrame:
    return wl.zipf(spark, d, scatter=True)


def _column(name: str, columns: list[str], **more) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: sorts.with_rank(sorts.adaptive_msd(table(spark, d, name).select(*columns), columns, **more))


def _key16(spark: SparkSession, d: str) -> DataFrame:
    return sorts.with_rank(sorts.adaptive_msd(wl.key16(spark, d), ["key_high", "key_low", "l_suppkey", "l_linenumber"]))


def _binary(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select(*wl.TIES)
    keyed = rows.withColumn("code", keys.encode(rows, ["l_suppkey", "l_partkey"]))
    return sorts.with_rank(sorts.adaptive_msd(keyed, ["code", "l_orderkey", "l_linenumber"])).drop("code")


def _multi(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select("l_returnflag", "l_shipdate", *wl.TIES)
    return sorts.with_rank(sorts.adaptive_msd(rows, ["l_returnflag", "l_shipdate", *wl.TIES], ascending=[True, False, True, True, True, True]))


def _nulls(first: bool) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = table(spark, d, "lineitem").select(F.nullif("l_linenumber", F.lit(3)).alias("line"), *wl.TIES)
        return sorts.with_rank(sorts.adaptive_msd(rows, ["line", *wl.TIES], nulls_first=first))

    return run


def _array(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "embeddings").select("embedding", "vec_id")
    return sorts.with_rank(sorts.adaptive_msd(rows, ["embedding", "vec_id"])).drop("embedding")


def _pass(spark: SparkSession, d: str) -> DataFrame:
    rows = passes.with_position(table(spark, d, "lineitem").select("l_suppkey", *wl.TIES[:2], "l_linenumber"), wl.TIES)
    return passes.counting_pass(rows, "l_suppkey", 0, "pos")


def _split(staging: int | None) -> Callable[[SparkSession, str], DataFrame]:
    """Each chunk split by one digit with a kernel: every row's place in its bin."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = passes.with_position(wl.uniform(spark, d), wl.TIES)
        out = passes.chunk_split(rows, "key", 7, "pos", staging, F.floor(F.col("pos") / 4096))
        return out.select("pos", F.col("_chunk").alias("chunk"), F.col("_digit").alias("digit"), F.col("_k").alias("place"))

    return run


def _chunked(growth: str) -> Callable[[SparkSession, str], DataFrame]:
    """LSD passes over the first pass's growing chunks, or over equal ones."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = passes.with_position(wl.zipf(spark, d), wl.TIES)
        plan = bins.chunk_plan(rows.count(), 4, growth=growth)
        return sorts.lsd(rows, "key", "pos", chunk=passes.chunk_of(F.col("pos"), plan))

    return run


def _array_nulls(spark: SparkSession, d: str) -> DataFrame:
    line = F.nullif("l_linenumber", F.lit(2))
    items = F.when(F.col("l_linenumber") == 5, F.lit(None)).when(F.col("l_linenumber") == 6, F.array().cast("array<long>")).otherwise(F.array(line.cast("long"), F.col("l_suppkey")))
    rows = table(spark, d, "lineitem").select(items.alias("items"), *wl.TIES)
    return sorts.with_rank(sorts.adaptive_msd(rows, ["items", *wl.TIES])).drop("items")


def _topk_nulls(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select(F.when(F.col("l_orderkey") > 20, F.col("l_orderkey")).alias("key"))
    return sorts.top_k(rows, "key", 200)


def _dedupe(spark: SparkSession, d: str) -> DataFrame:
    return sorts.dedupe(wl.zipf(spark, d), ["key"])


def _topk(spark: SparkSession, d: str) -> DataFrame:
    return sorts.top_k(wl.uniform(spark, d), "key", 100).select("key")


def _median(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select("l_extendedprice", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    n = rows.count()
    return spark.createDataFrame([(n, sorts.select_rank(rows, "cents", n // 2))], "n long, median_cents long")


def _inplace(spark: SparkSession, d: str) -> DataFrame:
    return sorts.with_rank(sorts.in_place(wl.uniform(spark, d), "key", wl.TIES))


def _light(spark: SparkSession, d: str) -> DataFrame:
    return sorts.with_rank(sorts.adaptive_msd(_scatter(spark, d), KEYS, kernel=True))


QUERIES = {
    "adaptive_msd_orderkey": _sorted(_orderkey),
    "adaptive_msd_uniform": _sorted(wl.uniform),
    "adaptive_msd_zipf": _sorted(wl.zipf),
    "adaptive_msd_scatter": _sorted(_scatter),
    "adaptive_msd_kernel": _sorted(wl.uniform, kernel=True),
    "light_pass": _light,
    "msd_plain": _sorted(wl.uniform, sorts.msd_plain),
    "lsd_plain": _lsd(None),
    "lsd_plain_zipf": _lsd(None, wl.zipf),
    "lsd_staged_64": _lsd(64),
    "lsd_staged_256": _lsd(256),
    "base_comparison": _sorted(wl.uniform, sorts.comparison),
    "base_run_merge": _sorted(wl.uniform, sorts.run_merge),
    "base_inplace": _inplace,
    "base_spark": _sorted(wl.uniform, sorts.spark_default),
    "ablate_heavy": _sorted(wl.zipf, rules=Rules(heavy=None)),
    "ablate_sampled": _sorted(wl.uniform, sampled=True),
    "ablate_skip": _sorted(_orderkey, skip=False),
    "wl_uniform": _sorted(wl.uniform),
    "wl_zipf": _sorted(_wide),
    "wl_zipf_scatter": _sorted(_scatter),
    "wl_zipf_exact": _sorted(wl.zipf_exact),
    "wl_key16": _key16,
    **{f"wl_rec{n}": (lambda n: lambda spark, d: sorts.with_rank(sorts.adaptive_msd(wl.record_size(spark, d, n), KEYS)))(n) for n in (8, 16, 24, 32)},
    "global_rank": _sorted(_orderkey),
    "sort_int": _column("customer", ["c_nationkey", "c_custkey"]),
    "sort_double": _column("customer", ["c_acctbal", "c_custkey"]),
    "sort_ts": _column("events", ["ts", "event_id"]),
    "sort_string": _column("customer", ["c_name", "c_custkey"]),
    "sort_url": _column("pages", ["url", "page_id"]),
    "sort_binary": _binary,
    "sort_array": _array,
    "sort_desc": _column("orders", ["o_totalprice", "o_orderkey"], ascending=[False, True]),
    "sort_multi": _multi,
    "sort_nulls": _nulls(True),
    "sort_nulls_last": _nulls(False),
    "sort_global": _column("orders", ["o_orderdate", "o_orderkey"]),
    "counting_pass": _pass,
    "split_plain": _split(None),
    "split_staged": _split(256),
    "ablate_chunks_sort": _chunked("equal"),
    "first_pass_sort": _chunked("linear"),
    "ablate_tiny_sort": _sorted(_scatter, kernel=True, rules=Rules(tiny=0)),
    "ablate_narrow_sort": _sorted(_wide, kernel=True, rules=Rules(narrow=None)),
    "sort_array_nulls": _array_nulls,
    "msd_topk_nulls": _topk_nulls,
    "sort_dedupe": _dedupe,
    "msd_topk": _topk,
    "msd_median": _median,
}

_ORDERKEY = f"(SELECT l_orderkey AS key, {c.TIES} FROM lineitem)"
_SPLIT = f"SELECT pos, chunk, digit, row_number() OVER (PARTITION BY chunk, digit ORDER BY pos) - 1 AS place FROM (SELECT pos, pos // 4096 AS chunk, {c.digit('key', 7)} AS digit FROM ({c.ranked(c.UNIFORM, c.TIES)}))"
_ITEMS = f"(SELECT CASE WHEN l_linenumber = 5 THEN NULL WHEN l_linenumber = 6 THEN []::BIGINT[] ELSE [nullif(l_linenumber, 2)::BIGINT, l_suppkey] END AS items, {c.TIES} FROM lineitem)"
_u, _z, _zs = c.ranked(c.UNIFORM, ORDER), c.ranked(c.ZIPF, ORDER), c.ranked(c.SCATTER, ORDER)
SQL = {
    "adaptive_msd_orderkey": c.ranked(_ORDERKEY, ORDER),
    "adaptive_msd_uniform": _u,
    "adaptive_msd_zipf": _z,
    "adaptive_msd_scatter": _zs,
    "adaptive_msd_kernel": _u,
    "light_pass": _zs,
    "msd_plain": _u,
    "lsd_plain": _u,
    "lsd_plain_zipf": _z,
    "lsd_staged_64": _u,
    "lsd_staged_256": _u,
    "base_comparison": _u,
    "base_run_merge": _u,
    "base_inplace": _u,
    "base_spark": _u,
    "ablate_heavy": _z,
    "ablate_sampled": _u,
    "ablate_skip": c.ranked(_ORDERKEY, ORDER),
    "wl_uniform": _u,
    "wl_zipf": c.ranked(c.ZIPF_WIDE, ORDER),
    "wl_zipf_scatter": _zs,
    "wl_zipf_exact": c.ranked(c.ZIPF_EXACT, ORDER),
    "wl_key16": c.ranked(c.KEY16, "key_high, key_low, l_suppkey, l_linenumber"),
    **{f"wl_rec{n}": c.ranked(c.record(n), ORDER) for n in (8, 16, 24, 32)},
    "global_rank": c.ranked(_ORDERKEY, ORDER),
    "sort_int": c.ranked("customer", "c_nationkey, c_custkey", "c_nationkey, c_custkey"),
    "sort_double": c.ranked("customer", "c_acctbal, c_custkey", "c_acctbal, c_custkey"),
    "sort_ts": c.ranked("events", "ts, event_id", "ts, event_id"),
    "sort_string": c.ranked("customer", "c_name, c_custkey", "c_name, c_custkey"),
    "sort_url": c.ranked("pages", "url, page_id", "url, page_id"),
    "sort_binary": c.ranked("lineitem", "l_suppkey, l_partkey, l_orderkey, l_linenumber", c.TIES),
    "sort_array": c.ranked("embeddings", "embedding, vec_id", "vec_id"),
    "sort_desc": c.ranked("orders", "o_totalprice DESC, o_orderkey", "o_totalprice, o_orderkey"),
    "sort_multi": c.ranked("lineitem", f"l_returnflag, l_shipdate DESC, {c.TIES}", f"l_returnflag, l_shipdate, {c.TIES}"),
    "sort_nulls": c.ranked(f"(SELECT nullif(l_linenumber, 3) AS line, {c.TIES} FROM lineitem)", f"line NULLS FIRST, {c.TIES}"),
    "sort_nulls_last": c.ranked(f"(SELECT nullif(l_linenumber, 3) AS line, {c.TIES} FROM lineitem)", f"line NULLS LAST, {c.TIES}"),
    "sort_global": c.ranked("orders", "o_orderdate, o_orderkey", "o_orderdate, o_orderkey"),
    "counting_pass": f"SELECT *, row_number() OVER (ORDER BY {c.digit('l_suppkey', 0)}, pos) - 1 AS new_pos FROM (SELECT {c.TIES}, row_number() OVER (ORDER BY {c.TIES}) - 1 AS pos FROM lineitem)",
    "split_plain": _SPLIT,
    "split_staged": _SPLIT,
    "ablate_chunks_sort": _z,
    "first_pass_sort": _z,
    "ablate_tiny_sort": _zs,
    "ablate_narrow_sort": c.ranked(c.ZIPF_WIDE, ORDER),
    # DuckDB puts null items last: an item's absence is ordered by a flag before it
    "sort_array_nulls": c.ranked(_ITEMS, f"items IS NOT NULL, len(items), items[1] IS NOT NULL, items[1], items[2], {c.TIES}", c.TIES),
    "msd_topk_nulls": "SELECT CASE WHEN l_orderkey > 20 THEN l_orderkey END AS key FROM lineitem ORDER BY key NULLS FIRST LIMIT 200",
    "sort_dedupe": f"SELECT DISTINCT key FROM {c.ZIPF}",
    "msd_topk": f"SELECT key FROM {c.UNIFORM} ORDER BY key LIMIT 100",
    "msd_median": "SELECT count(*) AS n, (SELECT cents FROM (SELECT round(l_extendedprice * 100)::BIGINT AS cents, row_number() OVER (ORDER BY round(l_extendedprice * 100)::BIGINT) - 1 AS r FROM lineitem) WHERE r = (SELECT count(*) // 2 FROM lineitem)) AS median_cents FROM lineitem",
}

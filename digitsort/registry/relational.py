"""Surrounding operators that users of the sorters need: scans, joins, aggregates, windows, sets, scalar functions, UDFs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import keys, udfs
from ..operators import sorts
from ..plans import bins
from ..session import table
from ..sources import formats
from ..sources import workloads as wl
from . import common as c

QUERIES: dict = {}
SQL: dict = {}


def query(sql: str | None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return table(spark, d, name)


def _marked(spark: SparkSession, d: str) -> DataFrame:
    return wl.uniform(spark, d).withColumn("digit", keys.digit(F.col("key"), 7))


_D = c.digit("key", 7)
_MARKED = f"(SELECT *, {_D} AS digit FROM {c.UNIFORM})"


# scans, sources, sinks
@query("SELECT min(l_orderkey) AS low, max(l_orderkey) AS high, count(*) AS n FROM lineitem")
def scan_keys(spark, d):
    return _t(spark, d, "lineitem").select("l_orderkey").agg(F.min("l_orderkey").alias("low"), F.max("l_orderkey").alias("high"), F.count("*").alias("n"))


@query("SELECT count(*) AS n, count(*) - 1 AS last FROM lineitem")
def scan_position(spark, d):
    return _t(spark, d, "lineitem").select("_metadata.row_index").agg(F.count("*").alias("n"), F.max("row_index").alias("last"))


@query("SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
def src_csv_roundtrip(spark, d):
    return formats.round_trip(_t(spark, d, "customer"), "csv", header=True)


@query("SELECT * FROM orders")
def src_json_roundtrip(spark, d):
    return formats.round_trip(_t(spark, d, "orders"), "json")


@query("SELECT * FROM part")
def src_orc_roundtrip(spark, d):
    return formats.round_trip(_t(spark, d, "part"), "orc")


@query("SELECT c_name AS value FROM customer")
def src_text_roundtrip(spark, d):
    return formats.round_trip(_t(spark, d, "customer").select(F.col("c_name").alias("value")), "text")


@query(f"SELECT event_id AS id, {c.mix('event_id::VARCHAR')} AS key FROM events")
def gen_uniform(spark, d):
    return _t(spark, d, "events").select(F.col("event_id").alias("id"), keys.mix64(F.col("event_id").cast("string")).alias("key"))


@query(" UNION ALL ".join(f"SELECT event_id AS id, {key} AS key FROM events" for key in (c.mix("event_id::VARCHAR"), c.zipf("event_id::VARCHAR"))))
def src_generator(spark, d):
    """Each event with the keys that the source generates for its id."""
    ids = _t(spark, d, "events").select(F.col("event_id").alias("id"))
    ends = ids.agg(F.min("id"), F.max("id")).first()
    low, rows = ends[0] or 0, ends[1] - ends[0] + 1 if ends[0] is not None else 0
    parts = max(4, -(-rows // 500_000))
    made = [ids.join(formats.generated(spark, rows, universe, parts, low), "id").select("id", "key") for universe in (0, 1024)]
    return made[0].unionAll(made[1])


@query(f"SELECT key, {c.TIES} FROM {c.UNIFORM}")
def sink_sorted(spark, d):
    return formats.sorted_sink(sorts.adaptive_msd(wl.uniform(spark, d).select("key", *wl.TIES), ["key"]))


@query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1")
def sink_bucketed(spark, d):
    return formats.bucketed(_t(spark, d, "orders").select("o_custkey", "o_orderkey"), "o_custkey").groupBy("o_custkey").agg(F.count("*").alias("n"))


# projections and filters
@query(f"SELECT l_orderkey, {c.digit('l_orderkey', 0)} AS d0, {c.digit('l_orderkey', 1)} AS d1 FROM lineitem")
def proj_digits(spark, d):
    k = F.col("l_orderkey")
    return _t(spark, d, "lineitem").select("l_orderkey", keys.digit(k, 0).alias("d0"), keys.digit(k, 1).alias("d1"))


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey BETWEEN 1024 AND 2047")
def filter_bin_range(spark, d):
    return _t(spark, d, "lineitem").filter(F.col("l_orderkey").between(1024, 2047)).select("l_orderkey", "l_linenumber")


@query(f"SELECT key, {c.TIES} FROM {c.ZIPF} WHERE key IN (0, 1, 2, 3)")
def filter_in_heavy(spark, d):
    return wl.zipf(spark, d).filter(F.col("key").isin(0, 1, 2, 3)).select("key", *wl.TIES)


@query("SELECT p_partkey, p_type FROM part WHERE p_type LIKE '%A%' AND p_brand IS NOT NULL")
def filter_like(spark, d):
    return _t(spark, d, "part").filter(F.col("p_type").like("%A%") & F.col("p_brand").isNotNull()).select("p_partkey", "p_type")


@query(f"SELECT digit, n, CASE WHEN n > 240 THEN 'large' WHEN n > 230 THEN 'middle' ELSE 'small' END AS size FROM (SELECT digit, count(*) AS n FROM {_MARKED} GROUP BY 1)")
def case_class(spark, d):
    return bins.histogram(wl.uniform(spark, d), "key").withColumn("size", F.when(F.col("n") > 240, "large").when(F.col("n") > 230, "middle").otherwise("small"))


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE nullif(l_linenumber, 3) IS NOT DISTINCT FROM NULL")
def filter_null_safe(spark, d):
    return _t(spark, d, "lineitem").filter(F.nullif("l_linenumber", F.lit(3)).eqNullSafe(F.lit(None))).select("l_orderkey", "l_linenumber")


# joins
@query(f"SELECT key, {c.TIES}, base FROM {_MARKED} JOIN (SELECT digit, coalesce(sum(n) OVER (ORDER BY digit ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS base FROM (SELECT digit, count(*) AS n FROM {_MARKED} GROUP BY 1)) USING (digit)")
def join_offsets(spark, d):
    rows = _marked(spark, d)
    base = bins.offsets(rows.groupBy("digit").agg(F.count("*").alias("n"))).select("digit", "base")  # 256 rows
    return rows.join(F.broadcast(base), "digit").select("key", *wl.TIES, "base")


@query("SELECT o_orderkey, o_custkey, l_partkey, l_linenumber, l_suppkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def join_merge_sorted(spark, d):
    o, i = _t(spark, d, "orders"), _t(spark, d, "lineitem")
    return o.hint("merge").join(i, o.o_orderkey == i.l_orderkey).select("o_orderkey", "o_custkey", "l_partkey", "l_linenumber", "l_suppkey")


@query(f"SELECT digit, a.n AS uniform_n, b.n AS zipf_n FROM (SELECT {_D} AS digit, count(*) AS n FROM {c.UNIFORM} GROUP BY 1) a JOIN (SELECT {c.digit('key', 0)} AS digit, count(*) AS n FROM {c.ZIPF} GROUP BY 1) b USING (digit)")
def join_shuffle_hash(spark, d):
    a = bins.histogram(wl.uniform(spark, d), "key").withColumnRenamed("n", "uniform_n")
    b = bins.histogram(wl.zipf(spark, d), "key", 0).withColumnRenamed("n", "zipf_n")
    return a.hint("shuffle_hash").join(b, "digit")


_HEAVY = f"(SELECT key FROM {c.ZIPF} GROUP BY 1 HAVING count(*) * 48 > (SELECT count(*) FROM lineitem) * 2)"


def _heavy_keys(spark, d):
    rows = wl.zipf(spark, d)
    return rows, rows.groupBy("key").agg(F.count("*").alias("n")).filter(bins.is_heavy(F.col("n"), F.lit(rows.count()), bins.Rules(workers=16)))


@query(f"SELECT key, {c.TIES} FROM {c.ZIPF} SEMI JOIN {_HEAVY} USING (key)")
def join_semi_heavy(spark, d):
    rows, heavy = _heavy_keys(spark, d)
    return rows.join(heavy, "key", "left_semi").select("key", *wl.TIES)


@query(f"SELECT key, {c.TIES} FROM {c.ZIPF} ANTI JOIN {_HEAVY} USING (key)")
def join_anti_heavy(spark, d):
    rows, heavy = _heavy_keys(spark, d)
    return rows.join(heavy, "key", "left_anti").select("key", *wl.TIES)


@query("SELECT coalesce(a.digit, b.digit) AS digit, a.n AS order_n, b.n AS part_n FROM (SELECT l_orderkey % 64 AS digit, count(*) AS n FROM lineitem WHERE l_orderkey % 64 < 48 GROUP BY 1) a FULL JOIN (SELECT l_partkey % 64 AS digit, count(*) AS n FROM lineitem WHERE l_partkey % 64 >= 16 GROUP BY 1) b ON a.digit = b.digit")
def join_full_hist(spark, d):
    rows = _t(spark, d, "lineitem")
    a = rows.select((F.col("l_orderkey") % 64).alias("digit")).filter("digit < 48").groupBy("digit").agg(F.count("*").alias("order_n"))
    b = rows.select((F.col("l_partkey") % 64).alias("digit")).filter("digit >= 16").groupBy("digit").agg(F.count("*").alias("part_n"))
    return a.join(b, "digit", "full")


@query("SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")
def join_left(spark, d):
    a, b = _t(spark, d, "customer"), _t(spark, d, "orders")
    return a.join(b, a.c_custkey == b.o_custkey, "left").select("c_custkey", "o_orderkey")


@query("WITH t AS (SELECT count(*)::HUGEINT AS n FROM orders), s AS (SELECT k AS chunk_id, n * (k * 32 * 31 + 224 * k * (k - 1)) // (256::HUGEINT * 32 * 31) AS s FROM (SELECT unnest(range(0, 32))::HUGEINT AS k), t) SELECT o_orderkey, chunk_id::INT AS chunk_id FROM (SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS pos FROM orders) r ASOF JOIN s ON r.pos >= s.s")
def join_range_chunk(spark, d):
    from ..operators import passes

    rows = passes.with_position(_t(spark, d, "orders").select("o_orderkey"), ["o_orderkey"])
    plan = bins.chunk_frame(spark, rows.count(), 4)  # 32 rows
    at = F.col("pos")
    return rows.join(F.broadcast(plan), (at >= F.col("start")) & (at < F.col("start") + F.col("length"))).select("o_orderkey", "chunk_id")


@query(f"SELECT count(*) AS n, min(key) AS low, max(key) AS high FROM (SELECT {c.mix(f'concat_ws({chr(39)}:{chr(39)}, {c.TIES}, k)')} AS key FROM lineitem, (SELECT unnest(range(1, 9)) AS k))")
def join_cross_scale(spark, d):
    """Eight copies by exploding a literal list, each with its own seed."""
    return wl.uniform(spark, d, copies=8).agg(F.count("*").alias("n"), F.min("key").alias("low"), F.max("key").alias("high"))


@query("SELECT o_orderkey, e.event_id FROM orders o ASOF LEFT JOIN (SELECT max(event_id) AS event_id, user_id, ts FROM events GROUP BY 2, 3) e ON o.o_custkey % 150 = e.user_id AND o.o_orderdate >= e.ts")
def join_asof(spark, d):
    """Last event of a user before an order: a sorted union with the last event carried on."""
    o = _t(spark, d, "orders").select((F.col("o_custkey") % 150).alias("user_id"), F.col("o_orderdate").alias("at"), F.lit(1).alias("kind"), F.col("o_orderkey"), F.lit(None).cast("long").alias("event_id"))
    e = _t(spark, d, "events").select("user_id", F.col("ts").alias("at"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    w = Window.partitionBy("user_id").orderBy("at", "kind", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return o.unionAll(e).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w)).filter("kind = 1").select("o_orderkey", "event_id")


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval(spark, d):
    """Pairs of a user's events within an hour: users and hours meet, the exact bound is checked."""
    e = _t(spark, d, "events").select("event_id", "user_id", "ts").withColumn("hour", F.date_trunc("hour", "ts"))
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t1"), F.explode(F.array("hour", F.col("hour") + F.expr("INTERVAL 1 HOUR"))).alias("hour"))
    b = e.select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("t2"), "hour")
    return a.join(b, ["user_id", "hour"]).filter((F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr("INTERVAL 1 HOUR"))).select("first_id", "second_id")


# aggregates
@query(f"SELECT digit, count(*) AS n, sum(payload)::BIGINT AS total, min(payload) AS low, max(payload) AS high, count(*) FILTER (payload % 2 = 0) AS even FROM {_MARKED} GROUP BY 1")
def agg_hist_partial(spark, d):
    return _marked(spark, d).groupBy("digit").agg(F.count("*").alias("n"), F.sum("payload").alias("total"), F.min("payload").alias("low"), F.max("payload").alias("high"), F.count_if(F.col("payload") % 2 == 0).alias("even"))


@query(f"SELECT count(DISTINCT key) AS keys, count(DISTINCT l_partkey) AS parts FROM {c.ZIPF}")
def agg_distinct(spark, d):
    return wl.zipf(spark, d).agg(F.count_distinct("key").alias("keys"), F.count_distinct("l_partkey").alias("parts"))


def _decided(spark, d):
    rows = wl.zipf(spark, d, scatter=True)
    return bins.decisions(rows, "key", bins.Rules(), rows.count())


for _name, _spark, _duck in (("rollup", "rollup", "ROLLUP (level, action)"), ("cube", "cube", "CUBE (level, action)")):
    QUERIES[f"agg_{_name}_bins"] = (lambda how: lambda spark, d: getattr(_decided(spark, d), how)("level", "action").agg(F.count("*").alias("bins"), F.sum("n").alias("rows")))(_spark)
    SQL[f"agg_{_name}_bins"] = c.decisions(c.SCATTER) + f"SELECT level, action, count(*) AS bins, sum(n)::BIGINT AS rows FROM bins GROUP BY {_duck}"


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, d):
    return _t(spark, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query(f"SELECT key, count(*) AS n FROM {c.ZIPF} GROUP BY 1")
def agg_runlength(spark, d):
    return sorts.run_lengths(wl.zipf(spark, d), "key")


@query(f"SELECT count(DISTINCT key) AS exact, true AS close FROM {c.UNIFORM}")
def agg_approx_distinct(spark, d):
    """The sketch with its bound: within four standard errors of the exact count."""
    both = wl.uniform(spark, d).agg(F.approx_count_distinct("key", 0.02).alias("keys"), F.count_distinct("key").alias("exact"))
    return both.select("exact", (F.abs(F.col("keys") - F.col("exact")) <= F.col("exact") * 0.08 + 1).alias("close"))


@query(f"SELECT share, true AS close FROM (VALUES (0.25::DOUBLE), (0.5), (0.75)) AS t(share)")
def agg_percentile_approx(spark, d):
    """Quantiles with their bound: each one's exact rank is within 1 / accuracy of its share."""
    accuracy = 1000
    rows = wl.uniform(spark, d)
    shares = [0.25, 0.5, 0.75]
    marks = rows.agg(F.percentile_approx("key", shares, accuracy).alias("q"), F.count("*").alias("n"))
    each = marks.select("n", F.explode(F.arrays_zip(F.array(*map(F.lit, shares)).alias("share"), "q")).alias("x")).select("n", F.col("x.share").alias("share"), F.col("x.q").alias("q"))
    ranks = rows.select("key").join(F.broadcast(each), F.col("key") <= F.col("q")).groupBy("share", "n").agg(F.count("*").alias("rank"))  # three rows
    return ranks.select("share", (F.abs(F.col("rank") / F.col("n") - F.col("share")) <= 1 / accuracy + 1 / F.col("n")).alias("close"))


# windows, limits, sets
@query(f"SELECT key, {c.TIES}, rank() OVER (PARTITION BY digit ORDER BY key) AS place FROM {_MARKED}")
def win_rank_in_bin(spark, d):
    return _marked(spark, d).select("key", *wl.TIES, F.rank().over(Window.partitionBy("digit").orderBy("key")).alias("place"))


@query(f"SELECT key, ntile(4) OVER (PARTITION BY digit ORDER BY key) AS quarter, round(percent_rank() OVER (PARTITION BY digit ORDER BY key), 6) AS share, dense_rank() OVER (PARTITION BY digit ORDER BY key) AS dense FROM {_MARKED}")
def win_ntile(spark, d):
    w = Window.partitionBy("digit").orderBy("key")
    return _marked(spark, d).select("key", F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("share"), F.dense_rank().over(w).alias("dense"))


@query(f"SELECT count(*) AS n, 0::BIGINT AS falls FROM {c.UNIFORM}")
def win_order_check(spark, d):
    """Neighbours of a sorted frame that fall: none inside partitions, none between them."""
    placed = sorts.with_rank(sorts.adaptive_msd(wl.uniform(spark, d).select("key"), ["key"]))
    cell = F.floor(F.col("pos") / 8192)
    w = Window.partitionBy("cell").orderBy("pos")
    marked = placed.withColumn("cell", F.explode(F.array(cell, F.floor((F.col("pos") + 1) / 8192)))).distinct()  # a cell's last row also begins the next
    return marked.withColumn("fall", F.lag("key").over(w) > F.col("key")).agg(F.count_distinct("pos").alias("n"), F.count_if("fall").alias("falls"))


@query(f"SELECT digit, n, sum(n) OVER (ORDER BY digit)::BIGINT AS upto FROM (SELECT digit, count(*) AS n FROM {_MARKED} GROUP BY 1)")
def win_prefix_sum(spark, d):
    hist = bins.histogram(wl.uniform(spark, d), "key")
    return hist.withColumn("upto", F.sum("n").over(Window.orderBy("digit").rowsBetween(Window.unboundedPreceding, 0)))


@query("SELECT c_custkey, count(*) OVER (PARTITION BY c_mktsegment ORDER BY c_nationkey RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS near FROM customer")
def win_range_frame(spark, d):
    w = Window.partitionBy("c_mktsegment").orderBy("c_nationkey").rangeBetween(-2, 0)
    return _t(spark, d, "customer").select("c_custkey", F.count("*").over(w).alias("near"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 25")
def limit_offset(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(25).limit(50)


@query(f"SELECT digit, key FROM (SELECT digit, key, row_number() OVER (PARTITION BY digit ORDER BY key) AS r FROM {_MARKED}) WHERE r <= 3")
def topk_per_bin(spark, d):
    w = Window.partitionBy("digit").orderBy("key")
    return _marked(spark, d).withColumn("r", F.row_number().over(w)).filter("r <= 3").select("digit", "key")


@query("SELECT o_custkey AS k FROM orders UNION ALL SELECT c_custkey FROM customer")
def set_union(spark, d):
    return _t(spark, d, "orders").select(F.col("o_custkey").alias("k")).unionAll(_t(spark, d, "customer").select("c_custkey"))


@query("SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer")
def set_intersect(spark, d):
    return _t(spark, d, "orders").select(F.col("o_custkey").alias("k")).intersect(_t(spark, d, "customer").select("c_custkey"))


@query("SELECT 0::BIGINT AS lost, 0::BIGINT AS made")
def set_except_all(spark, d):
    """A sort is a permutation: nothing is lost, nothing made."""
    rows = wl.zipf(spark, d).select("key", "payload")
    out = sorts.adaptive_msd(rows, ["key"])
    return rows.exceptAll(out).agg(F.count("*").alias("lost")).crossJoin(out.exceptAll(rows).agg(F.count("*").alias("made")))  # one row each


# scalar functions
@query(f"SELECT l_orderkey, l_partkey << 3 AS up, l_partkey >> 2 AS down, l_partkey & 255 AS low, l_partkey | 1 AS odd, xor(l_partkey, 255) AS flipped, bit_count(l_partkey)::INT AS ones, {c.TIES.split(', ', 1)[1]} FROM lineitem")
def fn_bits(spark, d):
    k = F.col("l_partkey")
    return _t(spark, d, "lineitem").select("l_orderkey", F.shiftleft(k, 3).alias("up"), F.shiftright(k, 2).alias("down"), k.bitwiseAND(F.lit(255)).alias("low"), k.bitwiseOR(F.lit(1)).alias("odd"), k.bitwiseXOR(F.lit(255)).alias("flipped"), F.bit_count(k).alias("ones"), *wl.TIES[1:])


@query("SELECT c_custkey, hex(c_name) AS hexed, md5(c_name) AS hashed, lpad(c_custkey::VARCHAR, 12, '0') AS padded, substr(c_name, 2, 5) AS part FROM customer")
def fn_encode(spark, d):
    return _t(spark, d, "customer").select("c_custkey", F.hex("c_name").alias("hexed"), F.md5("c_name").alias("hashed"), F.lpad(F.col("c_custkey").cast("string"), 12, "0").alias("padded"), F.substring("c_name", 2, 5).alias("part"))


@query("SELECT c_custkey, floor(c_acctbal)::BIGINT AS low, ceil(c_acctbal)::BIGINT AS high, round(sqrt(abs(c_acctbal)), 6) AS root, greatest(c_acctbal, 0) AS positive, round(log2(c_custkey + 1), 6) AS bits FROM customer")
def fn_math(spark, d):
    b = F.col("c_acctbal")
    return _t(spark, d, "customer").select("c_custkey", F.floor(b).alias("low"), F.ceil(b).alias("high"), F.round(F.sqrt(F.abs(b)), 6).alias("root"), F.greatest(b, F.lit(0.0)).alias("positive"), F.round(F.log2(F.col("c_custkey") + 1), 6).alias("bits"))


@query("SELECT p_partkey, lower(p_type) AS low, length(p_name) AS n, translate(p_brand, '0123', 'abcd') AS brand, strpos(p_name, 'a') AS at, regexp_replace(p_name, '[0-9]', '#', 'g') AS masked, string_split(p_type, ' ')[1] AS first FROM part")
def fn_string(spark, d):
    return _t(spark, d, "part").select("p_partkey", F.lower("p_type").alias("low"), F.length("p_name").alias("n"), F.translate("p_brand", "0123", "abcd").alias("brand"), F.instr("p_name", "a").alias("at"), F.regexp_replace("p_name", "[0-9]", "#").alias("masked"), F.split("p_type", " ")[0].alias("first"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS month, year(o_orderdate) AS y, epoch_us(o_orderdate) AS micros FROM orders")
def fn_date(spark, d):
    micros = keys.order_key(_t(spark, d, "orders"), "o_orderdate")
    return _t(spark, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month"), F.year("o_orderdate").alias("y"), micros.alias("micros"))


@query("SELECT c_nationkey, array_to_string(list_sort(list(c_custkey)), ',') AS keys, list_sum(list(c_custkey))::BIGINT AS total FROM customer GROUP BY 1")
def fn_array(spark, d):
    a = F.array_sort(F.collect_list("c_custkey"))
    return _t(spark, d, "customer").groupBy("c_nationkey").agg(a.alias("keys")).select("c_nationkey", F.array_join("keys", ",").alias("keys"), F.aggregate("keys", F.lit(0).cast("long"), lambda x, y: x + y).alias("total"))


@query("SELECT n_regionkey, count(*) AS names, max(n_name) AS last FROM nation GROUP BY 1")
def fn_map(spark, d):
    m = F.map_from_arrays(F.collect_list("n_nationkey"), F.collect_list("n_name"))
    return _t(spark, d, "nation").groupBy("n_regionkey").agg(m.alias("m")).select("n_regionkey", F.size("m").cast("long").alias("names"), F.array_max(F.map_values("m")).alias("last"))


@query("SELECT event_id, json_extract_string(props, '$.' || (json_keys(props))[1]) AS first_value FROM events")
def fn_json(spark, d):
    return _t(spark, d, "events").select("event_id", F.expr("get_json_object(props, concat('$.', json_object_keys(props)[0]))").alias("first_value"))


# user-defined functions
@query(f"SELECT digit, count(*) AS n, min(key) AS low, max(key) AS high FROM {_MARKED} GROUP BY 1")
def kernel_per_bin(spark, d):
    import pyarrow as pa
    import pyarrow.compute as pc

    from ..session import ship_package

    ship_package(spark)

    def run(t: pa.Table) -> pa.Table:
        ends = pc.min_max(t.column("key")).as_py()
        return pa.table({"digit": t.column("digit").slice(0, 1), "n": pa.array([t.num_rows]), "low": pa.array([ends["min"]]), "high": pa.array([ends["max"]])})

    return _marked(spark, d).select("digit", "key").groupBy("digit").applyInArrow(run, "digit long, n long, low long, high long")


@query("SELECT c_custkey, rank() OVER (ORDER BY c_acctbal) AS place FROM customer")
def udf_double_bits(spark, d):
    rows = _t(spark, d, "customer")
    ordered = rows.select("c_custkey", keys.double_order("c_acctbal").alias("bits"))
    return sorts.with_rank(sorts.adaptive_msd(ordered, ["bits"]), "p").withColumn("place", F.min("p").over(Window.partitionBy("bits")) + 1).select("c_custkey", "place")


@query("SELECT l_linenumber, l_suppkey % 256 AS digit, count(*) AS n FROM lineitem GROUP BY ALL")
def udaf_hist(spark, d):
    rows = _t(spark, d, "lineitem").select("l_linenumber", (F.col("l_suppkey") % 256).alias("digit"))
    hist = rows.groupBy("l_linenumber").agg(udfs.digit_counts("digit").alias("h"))
    return hist.select("l_linenumber", F.posexplode("h").alias("digit", "n")).filter("n > 0").select("l_linenumber", F.col("digit").cast("long").alias("digit"), "n")


@query("SELECT position, digit, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT {p} AS position, {c.digit('o_custkey', p)} AS digit FROM orders" for p in range(8)) + ") GROUP BY ALL")
def udtf_digits(spark, d):
    udfs.register(spark)
    _t(spark, d, "orders").select("o_custkey").createOrReplaceTempView("udtf_orders")
    return spark.sql("SELECT position, digit, count(*) AS n FROM udtf_orders, LATERAL key_digits(o_custkey) GROUP BY position, digit")


@query("SELECT kmer, count(*) AS n FROM (SELECT substr(text, unnest(range(1, length(text) - 2)), 4) AS kmer FROM benchmark WHERE length(text) >= 4) GROUP BY 1")
def udtf_kmers(spark, d):
    spark.udtf.register("text_kmers", udfs.TextKmers)
    _t(spark, d, "benchmark").createOrReplaceTempView("udtf_benchmark")
    return spark.sql("SELECT kmer, count(*) AS n FROM udtf_benchmark, LATERAL text_kmers(text, 4) GROUP BY kmer")


@query(f"SELECT o_orderkey, {c.digit('o_orderkey', 0)} AS d0, {c.digit('o_orderkey', 1)} AS d1 FROM orders")
def sql_digit_udf(spark, d):
    udfs.register(spark)
    _t(spark, d, "orders").createOrReplaceTempView("udf_orders")
    return spark.sql("SELECT o_orderkey, digit_at(o_orderkey, 0) AS d0, digit_at(o_orderkey, 1) AS d1 FROM udf_orders")

"""Experiment workloads on the given tables.

Keys derive from the four columns that identify a line item; they also break
ties, so that every sort has one right answer.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import keys
from ..session import table

TIES = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


def seed() -> Column:
    return F.concat_ws(":", *TIES)


def _lineitem(spark: SparkSession, sf_dir: str, copies: int = 1) -> tuple[DataFrame, Column]:
    rows = table(spark, sf_dir, "lineitem").select(*TIES, "l_extendedprice")
    if copies == 1:
        return rows, seed()
    rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(copies))))
    return rows, F.concat_ws(":", *TIES, "copy")


def uniform(spark: SparkSession, sf_dir: str, copies: int = 1) -> DataFrame:
    """16-byte records: uniform 8-byte keys and 8 bytes of data."""
    rows, s = _lineitem(spark, sf_dir, copies)
    return rows.select(keys.mix64(s).alias("key"), F.col("l_partkey").alias("payload"), *TIES)


def zipf(spark: SparkSession, sf_dir: str, universe: int = 1024, scatter: bool = False, copies: int = 1) -> DataFrame:
    """Zipf keys of exponent 0.75: ranks as they are, or scattered over all 64 bits."""
    rows, s = _lineitem(spark, sf_dir, copies)
    rank = keys.zipf_rank(s, universe)
    return rows.select((keys.mix64(rank.cast("string")) if scatter else rank).alias("key"), F.col("l_partkey").alias("payload"), *TIES)


def zipf_exact(spark: SparkSession, sf_dir: str, universe: int = 256, theta: float = 0.75) -> DataFrame:
    """Discrete Zipf ranks by looking a uniform number up in the distribution function.

    The function has ``universe`` rows and is broadcast; a row's candidate ranks
    are one step of a table over 2^-10 wide cells, so that the range join is an equi-join.
    """
    upto, low = 0.0, []
    for k in range(universe):
        low.append((k, upto))
        upto += (k + 1.0) ** -theta
    low = [(k, x / upto) for k, x in low]
    high = [x for _, x in low[1:]] + [1.0]
    cells = [(c, k, lo, hi) for (k, lo), hi in zip(low, high, strict=True) for c in range(int(lo * 1024), min(1023, int(hi * 1024)) + 1)]
    cdf = spark.createDataFrame(cells, "cell int, rank long, low double, high double")
    rows, s = _lineitem(spark, sf_dir)
    rows = rows.withColumn("u", keys.unit32(s)).withColumn("cell", F.floor(F.col("u") * 1024).cast("int"))
    return rows.join(F.broadcast(cdf), "cell").filter("low <= u AND u < high").select(F.col("rank").alias("key"), F.col("l_partkey").alias("payload"), *TIES)


def record_size(spark: SparkSession, sf_dir: str, size: int, copies: int = 1) -> DataFrame:
    """8-byte keys with 0, 8, 16 or 24 bytes of data."""
    rows, s = _lineitem(spark, sf_dir, copies)
    data = [F.col("l_partkey").alias("data1"), F.col("l_suppkey").alias("data2"), F.col("l_extendedprice").alias("data3")][: size // 8 - 1]
    return rows.select(keys.mix64(s).alias("key"), *data, *TIES)


def key16(spark: SparkSession, sf_dir: str) -> DataFrame:
    """16-byte keys of two 8-byte parts."""
    rows, s = _lineitem(spark, sf_dir)
    return rows.select(F.col("l_orderkey").alias("key_high"), F.col("l_partkey").alias("key_low"), F.col("l_suppkey").alias("payload"), *TIES)


STEP = 1024


def blocks(texts: DataFrame, overlap: int, *keep: str) -> DataFrame:
    """Texts in blocks of STEP characters and what follows them: (keep, block number, block).

    Reaching a character of a UTF-8 string takes a walk from its start; inside
    blocks that walk is short, so that cutting whole texts up takes linear time.
    """
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.length("text") - 1) / STEP).cast("int")), lambda b: F.substring(F.col("text"), b * STEP + 1, F.lit(STEP + overlap)))
    return texts.filter(F.length("text") > 0).select(*keep, F.posexplode(cut).alias("block_no", "block"))


def kmers(spark: SparkSession, sf_dir: str, k: int = 16) -> DataFrame:
    """All runs of k characters of all documents."""
    rows = blocks(table(spark, sf_dir, "documents").select("text"), k - 1).filter(F.length("block") >= k)
    starts = F.sequence(F.lit(1), F.least(F.lit(STEP), F.length("block") - k + 1))
    return rows.select(F.explode(F.transform(starts, lambda i: F.substring(F.col("block"), i, F.lit(k)))).alias("kmer"))

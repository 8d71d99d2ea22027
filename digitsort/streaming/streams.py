"""Bounded streams over the events: windows, stateful digits, sorted runs by micro-batch."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import sorts
from ..session import scratch_dir, table


def source(spark: SparkSession, sf_dir: str, files: int = 4, again: str | None = None) -> DataFrame:
    """Events as a file stream of several micro-batches, in order of time.

    Files are taken by modification time, so they are written one after another:
    with a watermark, rows of an earlier file that came later would be late.
    ``again``: that much of the stream's beginning comes once more at its end.
    """
    rows = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path = f"{scratch_dir(spark)}/events-{uuid.uuid4().hex[:8]}"
    marks = rows.agg(F.percentile_approx(F.unix_micros("ts"), [k / files for k in range(1, files)], 1000).alias("q")).first()["q"] or []
    for low, high in zip([None, *marks], [*marks, None], strict=True):
        at = F.unix_micros("ts")
        part = rows.filter((at >= low if low is not None else F.lit(True)) & (at < high if high is not None else F.lit(True)))
        part.coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(path)
    if again:
        first = rows.agg(F.min("ts").alias("first_ts"))  # one row
        late = rows.join(F.broadcast(first), F.col("ts") < F.col("first_ts") + F.expr(f"INTERVAL {again}")).drop("first_ts")
        late.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run all that is available and return what the sink holds.

    Output goes to a Parquet sink in append mode, so that results needn't fit the
    driver; complete mode keeps only its last, small table.
    """
    spark = stream.sparkSession
    at = f"{scratch_dir(spark)}/stream-{uuid.uuid4().hex[:8]}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{at}/out").start().awaitTermination()
    else:
        writer.foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{at}/out")).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"), F.min("event_id").alias("first_id"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "first_id")


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", size, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def session(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "n")


def digit_counts(events: DataFrame) -> DataFrame:
    """A digit histogram that grows with the stream."""
    return events.groupBy((F.col("user_id") % 256).alias("digit")).agg(F.count("*").alias("n"))


def deduplicated(events: DataFrame) -> DataFrame:
    twice = events.unionAll(events)
    return twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def sorted_runs(events: DataFrame, key: str = "value") -> DataFrame:
    """One adaptively sorted run for each micro-batch, then all runs sorted into one."""
    spark = events.sparkSession
    at = f"{scratch_dir(spark)}/runs-{uuid.uuid4().hex[:8]}"
    kept = events.select("event_id", key)

    def keep(df: DataFrame, n: int) -> None:
        sorts.adaptive_msd(df, [key, "event_id"]).withColumn("run", F.lit(n)).write.mode("overwrite").parquet(f"{at}/out/batch={n}")

    kept.writeStream.foreachBatch(keep).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    runs = spark.read.parquet(f"{at}/out").select("event_id", key)
    return sorts.with_rank(sorts.adaptive_msd(runs, [key, "event_id"]))


def closed_windows(events: DataFrame, size: str = "1 hour") -> DataFrame:
    """Windows that the watermark has closed, for the append mode: rows that come later than it are dropped."""
    w = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", size)).agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "n")


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """The stream joined with a table."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "user_id", "c_mktsegment")


def running_counts(events: DataFrame) -> DataFrame:
    """(user_id, seen, last_id): after each micro-batch, what a user's state holds; the state is two numbers a user."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, last = state.get if state.exists else (0, -1)
        for f in frames:
            seen, last = seen + len(f), max(last, int(f["event_id"].max()))
        state.update((seen, last))
        yield pd.DataFrame({"user_id": [key[0]], "seen": [seen], "last_id": [last]})

    kept = events.select("user_id", "event_id").groupBy("user_id")
    return kept.applyInPandasWithState(step, "user_id long, seen long, last_id long", "seen long, last_id long", "append", GroupStateTimeout.NoTimeout)

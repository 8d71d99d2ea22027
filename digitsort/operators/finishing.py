"""Comparison finishers over groups: one tiny bin is one group of an Arrow kernel."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import keys
from ..session import ship_package
from ..sources.workloads import TIES
from . import kernels


def finish_bins(rows: DataFrame, key: str, finisher: str, level: int = 2, limit: int = 384) -> DataFrame:
    """Rows of every bin of ``level`` under the limit, with their place in it by the finisher.

    ``limit`` bounds a group, so that one fits a task.
    """
    ship_package(rows.sparkSession)
    by = Window.partitionBy("bin")
    tiny = rows.select(key, *TIES).withColumn("bin", keys.floor_key(F.col(key), level)).withColumn("m", F.count("*").over(by)).filter(F.col("m") < limit)
    arrived = tiny.withColumn("arrival", F.row_number().over(by.orderBy(*TIES))).drop("m")

    def run(table: pa.Table) -> pa.Table:
        pairs = sorted(zip(table.column("arrival").to_pylist(), table.column(key).to_pylist(), range(table.num_rows), strict=True))
        todo = [(k, a) for a, k, _ in pairs]
        at = {a: row for a, _, row in pairs}
        kernels.FINISHERS[finisher](todo)
        place = [0] * table.num_rows
        for n, (_, a) in enumerate(todo, 1):
            place[at[a]] = n
        return table.select([key, *TIES, "arrival"]).append_column("place", pa.array(place, pa.int32()))

    kinds = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in (key, *TIES))
    return arrived.groupBy("bin").applyInArrow(run, f"{kinds}, arrival int, place int")


def kernel_counts(rows: DataFrame, key: str, level: int = 2, limit: int = 384) -> DataFrame:
    """(finisher, bins, rows, compared, moved) over all bins under the limit."""
    ship_package(rows.sparkSession)
    by = Window.partitionBy("bin")
    tiny = rows.select(key).withColumn("bin", keys.floor_key(F.col(key), level)).withColumn("m", F.count("*").over(by)).filter(F.col("m") < limit)

    def run(table: pa.Table) -> pa.Table:
        out = []
        for name, sort in kernels.FINISHERS.items():
            todo = [(k, n) for n, k in enumerate(table.column(key).to_pylist())]
            compared, moved = sort(todo)
            out.append({"finisher": name, "n": len(todo), "compared": compared, "moved": moved})
        return pa.Table.from_pylist(out, pa.schema([("finisher", pa.string()), ("n", pa.int64()), ("compared", pa.int64()), ("moved", pa.int64())]))

    each = tiny.groupBy("bin").applyInArrow(run, "finisher string, n long, compared long, moved long")
    return each.groupBy("finisher").agg(F.count("*").alias("bins"), F.sum("n").alias("rows"), F.sum("compared").alias("compared"), F.sum("moved").alias("moved"))

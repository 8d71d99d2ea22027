"""Filters of bounded size for hashes that rows are looked up by."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def among(hashes: DataFrame, filter_bits: int = 26):
    """A test of a hash column: false only for those that aren't in ``hashes``, a frame of one long column.

    A bit map of 16 bits for each wanted hash, up to 2^filter_bits bits: that
    bounds what the driver gathers and what is broadcast.
    """
    spark, name = hashes.sparkSession, hashes.columns[0]
    bits = max(12, min(filter_bits, (16 * hashes.count()).bit_length()))
    words = hashes.groupBy(F.col(name).bitwiseAND(F.lit((1 << bits - 6) - 1)).alias("word")).agg(F.expr(f"bit_or(shiftleft(1L, cast(shiftrightunsigned({name}, 40) & 63L as int)))").alias("bits")).toArrow()
    held = np.zeros(1 << bits - 6, np.uint64)
    held[words.column("word").to_numpy()] = words.column("bits").to_numpy().view(np.uint64)
    shared = spark.sparkContext.broadcast(held)

    @F.pandas_udf("boolean")
    def test(h: pd.Series) -> pd.Series:
        x = h.to_numpy().view(np.uint64)
        held = shared.value
        return pd.Series((held[(x & np.uint64(len(held) - 1)).astype(np.int64)] >> (x >> np.uint64(40) & np.uint64(63)) & np.uint64(1)).astype(bool))

    return test

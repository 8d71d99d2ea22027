"""Functions registered for SQL, table functions, grouped aggregates."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.udtf(returnType=T.StructType([T.StructField("position", T.IntegerType()), T.StructField("digit", T.IntegerType())]))
class KeyDigits:
    """Digits of a key, most significant first."""

    def eval(self, key: int):
        if key is not None:
            u = key + (1 << 63)
            for p in range(7, -1, -1):
                yield p, u >> 8 * p & 255


@F.udtf(returnType=T.StructType([T.StructField("kmer", T.StringType())]))
class TextKmers:
    """Runs of k characters of a text."""

    def eval(self, text: str, k: int):
        for i in range(len(text or "") - k + 1):
            yield (text[i : i + k],)


@F.pandas_udf(T.ArrayType(T.LongType()))
def digit_counts(digits: pd.Series) -> np.ndarray:
    """A histogram of 256 digits as one array."""
    return np.bincount(digits.to_numpy(dtype="int64"), minlength=256).astype("int64")


def register(spark: SparkSession) -> None:
    """``digit_at(key, position)`` and ``key_digits(key)`` for SQL."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION digit_at(k BIGINT, p INT) RETURNS BIGINT RETURN shiftrightunsigned(k ^ CAST(-9223372036854775808 AS BIGINT), 8 * p) & 255")
    spark.udtf.register("key_digits", KeyDigits)


__all__ = ["KeyDigits", "TextKmers", "digit_counts", "register"]

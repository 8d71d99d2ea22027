import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents from (id, text[, lang]) with columns that clash with the operators' own names."""

    def make(rows):
        full = [(r[0], r[1], r[2] if len(r) > 2 else "en") for r in rows]
        df = spark.createDataFrame(full, "doc_id long, text string, lang string")
        return df.withColumn("score", F.lit("x")).withColumn("node", F.lit(1)).withColumn("ids", F.lit("y")).withColumn("class_id", F.lit(2.5)).withColumn("_n", F.lit(0))

    return make


LONG = " ".join(f"word{k % 977} über {k}" for k in range(20_000))
ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "a"), (5, "a"), (5, "a"), (None, "no id"), (6, "日本語 テキスト 😀 é"), (7, LONG), (8, "'s don't we'll 12 34.5  x")]


def thue_morse(n):
    """Two different words over a and b of 2^n letters that polynomial hashes modulo 2^64 don't tell apart from n = 10 on."""
    word = "".join("ab"[k.bit_count() & 1] for k in range(1 << n))
    return word, word.translate(str.maketrans("ab", "ba"))

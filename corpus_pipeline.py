"""A training-corpus pipeline: toxicity, language, near duplicates, packing.

Each stage takes (spark, docs, sf_dir), works on every row that its predecessor
kept, and returns a DataFrame; all but the last return the columns of
``documents``.  ``run`` writes each stage's result as Parquet in the shared
scratch folder and hands a scan of it to the next.

Null or empty texts: the toxicity stage scores them by its intercept, the
language stage rejects them, as it does texts without a letter.  Empty tables
give empty results.  Models are fitted on the tables in ``sf_dir``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from digitsort.llm import bagminhash, language, packing, queries, toxicity
from digitsort.session import table, written


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below 0.7."""
    return toxicity.keep_clean(docs, queries.toxicity_model(spark, sf_dir))


def keep_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that aren't unlike every language learned."""
    return language.keep_known(docs, queries.language_model(spark, sf_dir))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates, the document with the least id."""
    return bagminhash.keep_one(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences."""
    pieces = packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


STAGES = [("toxicity", drop_toxic), ("language", keep_languages), ("near_duplicates", drop_near_duplicates), ("packing", pack_sequences)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: Models and token ids are beyond SQL; tests hold each stage against its operator and brute force.
ORACLE_SQL = None

"""URL filtering by host-suffix and path-prefix rules, with DataFrame functions only.

A URL's host gives its suffixes by labels, its path the prefixes of the lengths
that rules have; every pair is an expression.  Expressions meet rules by a short
prefix of their SHA-256, and a pair counts when the full digests agree.  Of the
rules that fit, the longest wins; of equally long ones that with the longer
host, then the block.

Rows are judged by distinct (id, url) and repeat afterwards as often as in the
input, so that a URL which holds a large share of all rows is judged once for
each id and no two rows are confused.

Defined results: a null URL, or one without ``://``, has an empty host and path,
no rule fits it unless a rule's host is empty, and it gets the default verdict.
Rules with a null part never fit; repeated rules count once.  Only the id and
URL columns are read, so others may have any names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rules up to this number are broadcast; more meet the expressions by a shuffle.
BROADCAST_RULES = 100_000
PREFIX_HEX = 8
#: Repeated rows come back in arrays of so many at most.
COPIES = 10_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.expr("substring(_url, instr(_url, '://') + 3)")).otherwise("")
    host = F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), UPPER, LOWER)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*(/[^?#]*)?", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat_ws("\u0000", host, path), 256)


def judge(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """(id, host, path, rule, verdict).  ``rules``: host, path, verdict."""
    r = rules.select("host", "path", "verdict").dropna().groupBy("host", "path").agg(F.max("verdict").alias("_verdict"))  # of two verdicts, block
    r = r.select(
        _digest(F.col("host"), F.col("path")).alias("_rule_digest"),
        F.struct(F.length(F.concat("host", "path")).alias("n"), F.length("host").alias("h"), F.col("_verdict").alias("verdict"), F.concat("host", "path").alias("rule")).alias("_rule"),
        F.size(F.split("host", r"\.")).alias("_labels"),
        F.length("path").alias("_length"),
    )
    shape = r.agg(F.count("*").alias("n"), F.sort_array(F.collect_set("_labels")).alias("labels"), F.sort_array(F.collect_set("_length")).alias("lengths")).first()
    few = F.broadcast if shape["n"] <= BROADCAST_RULES else (lambda x: x)

    urls = pages.select(F.col(id_col).alias("_id"), F.col(url_col).alias("_url")).groupBy("_id", "_url").agg(F.count("*").alias("_times"))
    host, path = host_and_path(F.col("_url"))
    parts = urls.select("_id", "_url", "_times", host.alias("_host"), path.alias("_path"))
    label = F.split("_host", r"\.")
    suffixes = F.array_distinct(F.transform(F.filter(F.lit(shape["labels"] or []).cast("array<int>"), lambda k: k <= F.size(label)), lambda k: F.array_join(F.slice(label, -k, k), ".")))
    prefixes = F.transform(F.filter(F.lit(shape["lengths"] or []).cast("array<int>"), lambda k: k <= F.length("_path")), lambda k: F.substring(F.col("_path"), F.lit(1), k))
    pairs = F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: _digest(s, p))))
    expressions = parts.select("*", F.explode_outer(pairs).alias("_digest")).withColumn("_short", F.substring("_digest", 1, PREFIX_HEX))
    ruled = r.withColumn("_rule_short", F.substring("_rule_digest", 1, PREFIX_HEX))
    met = expressions.join(few(ruled), (F.col("_short") == F.col("_rule_short")) & (F.col("_digest") == F.col("_rule_digest")), "left")
    best = met.groupBy("_id", "_url", "_times", "_host", "_path").agg(F.max("_rule").alias("_rule"))
    return best.select(
        F.col("_id").alias(id_col),
        F.col("_host").alias("host"),
        F.col("_path").alias("path"),
        F.col("_rule.rule").alias("rule"),
        F.coalesce(F.col("_rule.verdict"), F.lit(default)).alias("verdict"),
        F.col("_times"),
        F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("_times") - 1) / COPIES))).alias("_part"),  # arrays of bounded length
    ).select(id_col, "host", "path", "rule", "verdict", F.explode(F.array_repeat(F.lit(0), F.least(F.lit(COPIES), F.col("_times") - F.col("_part") * COPIES).cast("int"))).alias("_copy")).drop("_copy")

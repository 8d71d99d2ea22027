import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from digitsort.llm import language, queries, toxicity

from .conftest import ODD

D = "/root/testdata/sf0.01"


def test_toxicity_held_out(spark):
    rows = queries.op7_toxicity(spark, D).join(spark.read.parquet(f"{D}/labels.parquet"), "doc_id").collect()
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.7) for r in rows)
    held = [r for r in rows if r["held_out"]]
    hit = [r["predicted"] for r in held if r["toxic"] == 1]
    assert sum(r["predicted"] for r in held if r["toxic"] == 0) <= 1
    assert sum(hit) >= 0.7 * len(hit)


def test_toxicity_ignores_held_out_labels(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    turned = labels.withColumn("toxic", F.when(queries.fold() == 1, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = (toxicity.fit(docs, x, queries.fold() != 1) for x in (labels, turned))
    assert np.array_equal(a.feature, b.feature) and np.array_equal(a.weight, b.weight)


def test_toxicity_odd_rows(spark, docs_of):
    rng = random.Random(2)
    plain = lambda: " ".join(f"w{rng.randrange(300)}" for _ in range(40))
    rows = [(100 + k, plain() + (" nastyword" if k % 4 == 0 else "")) for k in range(80)]
    labels = spark.createDataFrame([(i, None if i == 101 else int((i - 100) % 4 == 0)) for i, _ in rows] + [(100, 1), (None, 1)], "doc_id long, toxic int").withColumn("text", F.lit("clash"))
    model = toxicity.fit(docs_of(rows), labels)
    odd = docs_of(ODD + [(50, plain() + " nastyword")])
    got = toxicity.score(odd, model).collect()
    assert len(got) == len(ODD) + 1 and got[-1]["score"] > 0.7 and all(r["score"] < 0.7 for r in got[:-1])
    assert got[0]["score"] == got[1]["score"] == 1 / (1 + np.exp(-model.intercept))
    kept = toxicity.keep_clean(odd, model)
    assert kept.columns == odd.columns and [r["doc_id"] for r in kept.collect()] == [i for i, _ in ODD]
    assert toxicity.score(odd.limit(0), model).count() == 0 and toxicity.keep_clean(odd.limit(0), model).count() == 0
    none = toxicity.fit(docs_of(rows), labels.filter("toxic = 1"))
    assert {round(r["score"], 6) for r in toxicity.score(odd, none).collect()} == {round(22 / 23, 6)}
    assert toxicity.fit(docs_of(rows), labels.limit(0)).score is not None


def test_training_rows_are_bounded_after_the_join(spark, monkeypatch):
    """An id with very many rows, copies or different texts, or very many labels doesn't pass the bound."""
    docs = spark.range(6000).select(F.when(F.col("id") < 3000, 7).when(F.col("id") < 5000, 8).otherwise(F.col("id")).alias("doc_id"), F.when(F.col("id") < 3000, F.lit("same text")).otherwise(F.concat(F.lit("text "), F.col("id").cast("string"))).alias("text"), F.lit("en").alias("lang"))
    labels = spark.range(500).select(F.when(F.col("id") < 300, 7).when(F.col("id") < 400, 8).otherwise(F.col("id") + 5000).alias("doc_id"), (F.col("id") % 2).cast("int").alias("toxic"))
    seen = []
    monkeypatch.setattr(toxicity, "_solve", lambda read, p: seen.append(len(list(read()))))
    for most in (10, 100_000):
        toxicity.fit(docs, labels, p=toxicity.Params(max_rows=most))
    assert seen[0] == 10 and seen[1] <= 100_000
    p = language.Params(rows_per_language=50)
    rows = docs.select(F.col("text").alias("_text"), F.col("lang").alias("_lang"), F.xxhash64("text", "lang").alias("_h"))
    texts = [r["_text"] for r in language._sample(rows, p.rows_per_language).collect()]
    assert len(texts) == 50 == len(set(texts))


def test_ratio_scales_features():
    """A feature of one class only gets weight in that class's direction."""
    rows = [np.array([1, 2]), np.array([1, 2]), np.array([2, 3]), np.array([2, 3])] * 5
    m = toxicity._solve(lambda: zip(rows, [1, 1, 0, 0] * 5, strict=True), toxicity.Params(bits=4))
    w = dict(zip(m.feature.tolist(), m.weight.tolist(), strict=True))
    assert w[1] > 0 > w[3] and abs(w.get(2, 0)) < 1e-6


def test_language_held_out(spark):
    rows = queries.op9_language(spark, D).join(spark.read.parquet(f"{D}/documents.parquet").select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r["held_out"]]
    assert sum(r["lang"] == r["lang_pred"] for r in held) >= 0.98 * len(held)
    assert all(0 <= r["score"] <= 1 for r in rows)
    assert sum(r["rejected"] for r in rows) <= 0.005 * len(rows)  # clean documents stay


def test_language_odd_rows(spark, docs_of):
    rng = random.Random(4)
    make = lambda alphabet: " ".join("".join(rng.choice(alphabet) for _ in range(5)) for _ in range(40))
    rows = [(k, make("aeilnrst"), "xx") for k in range(40)] + [(100 + k, make("kowzyźćł"), "yy") for k in range(40)] + [(300, None, "xx"), (301, "text", None), (302, make("aeilnrst"), "xx"), (302, make("aeilnrst"), "xx")]
    model = language.fit(docs_of(rows))
    odd = docs_of([(1, None), (2, ""), (3, "123 !?"), (4, "salt tin"), (5, "źłow zyk"), (6, "漢字かな交じり文章" * 60), (4, "salt tin"), (7, make("kowzyźćł") * 500)])
    got = [(r["doc_id"], r["lang_pred"], r["rejected"]) for r in language.predict(odd, model).collect()]
    assert [g[:2] for g in got] == [(1, "und"), (2, "und"), (3, "und"), (4, "xx"), (5, "yy"), (6, got[5][1]), (4, "xx"), (7, "yy")]
    assert all(g[2] for g in got[:3]) and got[5][2] and not got[3][2] and not got[7][2]
    kept = language.keep_known(odd, model)
    assert kept.columns == odd.columns and 4 in {r["doc_id"] for r in kept.collect()} and not {1, 2, 3, 6} & {r["doc_id"] for r in kept.collect()}
    assert language.predict(odd.limit(0), model).count() == 0
    empty = language.fit(docs_of(rows).limit(0))
    assert {(r["lang_pred"], r["rejected"]) for r in language.predict(odd, empty).collect()} == {("und", True)}


@pytest.mark.parametrize("n", [1, 3])
def test_ngrams_stay_inside_texts(n):
    import pyarrow as pa

    from digitsort.llm.ngrams import ngram_hashes
    from digitsort.llm.textbatch import text_chunks

    texts = ["abcd", "", "a", "ab", "abcd", "xyzabcd"]
    (_, c), = text_chunks(pa.array(texts))
    h, doc = ngram_hashes(c.codes, c.char_off, n, 16)
    assert np.bincount(doc, minlength=6).tolist() == [max(0, len(t) - n + 1) for t in texts]
    assert h[doc == 0].tolist() == h[doc == 4].tolist() == h[doc == 5].tolist()[3:]


def test_toxicity_fit_takes_memory_for_features_seen_twice():
    import tracemalloc

    import numpy as np

    from digitsort.llm import toxicity

    p, rng = toxicity.Params(), np.random.default_rng(0)
    size = len(toxicity.LEVELS) << p.bits
    rows = [(np.unique(rng.choice(np.arange(0, size, 997), 300)).astype("<u4"), i % 9 == 0) for i in range(400)]
    tracemalloc.start()
    model = toxicity._solve(lambda: iter(rows), p)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(model.feature) and peak < 100e6  # sorting all features took 160 MB and more


def test_toxicity_driver_gets_chosen_features_only(spark, docs_of, monkeypatch):
    """And solves on them what all features would give."""
    rng, p = random.Random(5), toxicity.Params(features=50)
    docs = docs_of([(k, " ".join(f"w{rng.randrange(200)}" for _ in range(60)) + " nastyword" * (k % 4 == 0)) for k in range(80)])
    labels = docs.select("doc_id", (F.col("doc_id") % 4 == 0).cast("int").alias("toxic"))
    solve, sent = toxicity._solve, []
    monkeypatch.setattr(toxicity, "_solve", lambda read, p: sent.extend(r for r, _ in read()) or solve(read, p))
    model = toxicity.fit(docs, labels, p=p)
    assert len(sent) == 80 and np.array_equal(np.unique(np.concatenate(sent)), model.feature)
    from digitsort.llm.ngrams import level_features
    from digitsort.llm.textbatch import text_chunks

    texts = [(r["text"], r["doc_id"] % 4 == 0) for r in docs.collect()]
    whole = solve(lambda: ((level_features(next(text_chunks(toxicity.pa.array([t])))[1], p.orders, p.bits)[1], y) for t, y in texts), p)
    assert np.array_equal(model.feature, whole.feature) and np.allclose(model.weight, whole.weight, rtol=1e-9)

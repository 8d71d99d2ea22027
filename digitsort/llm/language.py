"""Language identification by nearest centroids.

A text is the TF-IDF vector of its hashed character n-grams (letters only, all
else a blank), at unit length.  Each language gets several centroids by spherical
k-means over a bounded sample of its texts; document frequencies cover every text
that may be learned from.  A text takes the language of the centroid of largest
cosine; the distance decides whether the text is rejected as unlike all.

Defined results: a null text, or one without any letter, is ``und`` with score 0
and rejected; with nothing to learn from, every text is; equal cosines go to the
language that sorts first; rows repeat if the input's do.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship_package
from .ngrams import folded, ngram_hashes
from .textbatch import TextChunk, binary_array, text_chunks

UNKNOWN = "und"


@dataclass
class Params:
    orders: tuple[int, ...] = (1, 2, 3)
    bits: int = 12
    rows_per_language: int = 600
    centroids: int = 4
    rounds: int = 8
    #: a text is rejected below this share of the smallest cosine of nearly all sample texts (all but 1 in 1000)
    slack: float = 0.6
    #: shorter texts, by letters, have smaller cosines with any centroid: the share falls with the root of their length
    full_letters: int = 400


def counts(chunk: TextChunk, p: Params) -> np.ndarray:
    """n-gram counts of each text, densely."""
    codes, off, width = folded(chunk, letters_only=True), chunk.char_off, 1 << p.bits
    out = np.zeros(chunk.n * width, np.float32)
    for n in p.orders:
        h, doc = ngram_hashes(codes, off, n, p.bits)
        out += np.bincount(doc * width + h, minlength=len(out)).astype(np.float32)
    return out.reshape(chunk.n, width)


def letters(chunk: TextChunk) -> np.ndarray:
    upto = np.concatenate([[0], np.cumsum(folded(chunk, letters_only=True) != 0x20)])
    return np.diff(upto[chunk.char_off])


@dataclass
class Model:
    params: Params
    idf: np.ndarray
    languages: list[str]
    centroid: np.ndarray
    owner: np.ndarray  # each centroid's language
    floor: float

    def vectors(self, tf: np.ndarray) -> np.ndarray:
        v = np.log1p(tf) * self.idf
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)

    def predict(self, chunk: TextChunk) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, cosine and rejection of each text."""
        if not self.languages:
            return [UNKNOWN] * chunk.n, np.zeros(chunk.n), np.ones(chunk.n, bool)
        cos = self.vectors(counts(chunk, self.params)) @ self.centroid.T
        best = cos.argmax(axis=1)
        score = np.clip(cos[np.arange(chunk.n), best].astype(float), 0, 1)
        size = letters(chunk)
        known = size > 0
        floor = self.floor * np.sqrt(np.minimum(1, size / self.params.full_letters))
        names = [self.languages[k] if ok else UNKNOWN for k, ok in zip(self.owner[best].tolist(), known.tolist(), strict=True)]
        return names, np.where(known, score, 0.0), ~known | (score < floor)


def _document_frequencies(docs: DataFrame, p: Params, text_col: str) -> tuple[np.ndarray, int]:
    """Texts that hold each feature, over all rows; a vector for each task, summed by Spark."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, n = np.zeros(1 << p.bits, np.int64), 0
        for batch in batches:
            for _, chunk in text_chunks(batch.column(0), max_rows=256):
                df += (counts(chunk, p) > 0).sum(axis=0)
                n += chunk.n
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([df.tolist()], pa.list_(pa.int64()))], ["n", "df"])

    parts = docs.select(text_col).mapInArrow(run, "n long, df array<long>")
    rows = parts.select(F.posexplode(F.array_append("df", F.col("n"))).alias("k", "v")).groupBy("k").agg(F.sum("v").alias("v")).collect()  # 2^bits + 1 rows
    total = np.zeros((1 << p.bits) + 1)
    for r in rows:
        total[r["k"]] = r["v"]
    return total[:-1], int(total[-1])


def _sample(rows: DataFrame, most: int) -> DataFrame:
    """At most ``most`` different texts of each language, those of least hash; ``rows``: _text, _lang, _h.

    Rows are drawn where they lie, below a share of all hashes that about twice as
    many different texts of their language have, so that no task gets a whole
    language; repeated rows are combined before they move.
    """
    sizes = rows.groupBy("_lang").agg(F.approx_count_distinct("_h").alias("_n"))  # as many rows as languages
    place = F.shiftrightunsigned("_h", 11) / F.lit(float(1 << 53))
    drawn = rows.join(F.broadcast(sizes), "_lang").filter(place * F.col("_n") < 2 * most).groupBy("_lang", "_h").agg(F.first("_text").alias("_text"))
    return drawn.withColumn("_k", F.row_number().over(Window.partitionBy("_lang").orderBy(F.shiftrightunsigned("_h", 11), "_h"))).filter(F.col("_k") <= most)


def _cluster(v: np.ndarray, k: int, rounds: int) -> np.ndarray:
    """Spherical k-means from far-apart first centroids; deterministic."""
    c = v.mean(axis=0, keepdims=True)
    c /= max(np.linalg.norm(c), 1e-12)
    near = (v @ c.T)[:, 0]
    seeds = []
    for _ in range(min(k, len(v))):
        seeds.append(int(near.argmin()) if seeds else int(near.argmax()))
        near = np.maximum(near, v @ v[seeds[-1]]) if len(seeds) > 1 else v @ v[seeds[-1]]
    c = v[seeds]
    for _ in range(rounds):
        own = (v @ c.T).argmax(axis=1)
        c = np.stack([v[own == j].sum(axis=0) if (own == j).any() else c[j] for j in range(len(c))])
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


def fit(docs: DataFrame, trains: Column | None = None, p: Params | None = None, text_col: str = "text", lang_col: str = "lang") -> Model:
    """``trains``: which rows of ``docs`` may be learned from; those with null language or text never are."""
    p = p or Params()
    spark = docs.sparkSession
    ship_package(spark)
    rows = docs.filter(trains if trains is not None else F.lit(True)).filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    rows = rows.select(F.col(text_col).alias("_text"), F.col(lang_col).alias("_lang"), F.xxhash64(text_col, lang_col).alias("_h"))
    df, n = _document_frequencies(rows, p, "_text")
    idf = (np.log((1 + n) / (1 + df)) + 0.05).astype(np.float32)
    model = Model(p, idf, [], np.zeros((0, 1 << p.bits), np.float32), np.zeros(0, np.int64), 0.0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(1)):
                tf = counts(chunk, p)
                doc, feature = np.nonzero(tf)
                off = np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=chunk.n))])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, chunk.n), binary_array(feature.astype("<u2").tobytes(), off * 2), binary_array(tf[doc, feature].astype("<f4").tobytes(), off * 4)], ["lang", "feature", "tf"])

    found = _sample(rows, p.rows_per_language).select("_lang", "_text").mapInArrow(run, "lang string, feature binary, tf binary").toArrow().to_pylist()
    closest = []
    for lang in sorted({r["lang"] for r in found}):
        own = [r for r in found if r["lang"] == lang and r["feature"]]
        if not own:
            continue
        tf = np.zeros((len(own), 1 << p.bits), np.float32)
        for k, r in enumerate(own):
            tf[k, np.frombuffer(r["feature"], "<u2")] = np.frombuffer(r["tf"], "<f4")
        v = model.vectors(tf)
        c = _cluster(v, p.centroids, p.rounds)
        model.centroid = np.concatenate([model.centroid, c])
        model.owner = np.concatenate([model.owner, np.full(len(c), len(model.languages))])
        model.languages.append(lang)
        closest.append((v @ c.T).max(axis=1))
    if closest:
        model.floor = float(p.slack * np.quantile(np.concatenate(closest), 0.001))
    return model


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang_pred, score, rejected)."""
    spark = docs.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(model)  # bounded by its parameters and the number of languages

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(1), max_rows=256):
                lang, cos, no = shared.value.predict(chunk)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, chunk.n), pa.array(lang), pa.array(cos), pa.array(no)], [id_col, "lang_pred", "score", "rejected"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, lang_pred string, score double, rejected boolean")


def keep_known(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns, that the model doesn't reject."""
    spark = docs.sparkSession
    ship_package(spark)
    shared, at, names = spark.sparkContext.broadcast(model), docs.columns.index(text_col), docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(at), max_rows=256):
                yield batch.slice(row, chunk.n).filter(pa.array(~shared.value.predict(chunk)[2])).rename_columns(names)

    return docs.mapInArrow(run, docs.schema)

"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Features are the hashed n-grams of a text's lower-case characters (blanks for all but letters), at the levels
of 1, 2, 4 and 8 occurrences: what a clean text has once by chance, a toxic one
repeats.  Each feature's log-count ratio compares its smoothed document counts in both
classes; the features with the most certain ratios carry the model, and a
logistic regression is fitted on presence times ratio.

``fit`` uses at most ``max_rows`` labelled rows, so that the driver's memory is
bounded: of the labels, those with the smallest hash of their id, and of the rows
that these ids have, different texts only, those with the smallest hash of id and
text.  Texts are read whole.

Defined results: null and empty texts have no features and score the model's
intercept; rows without a label (null) teach nothing, and an id that is labelled
twice teaches twice; with no labelled row at all, or one class only, every score
is that class's smoothed share; rows repeat if the input's do.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ship_package, written
from .ngrams import LEVELS, level_features
from .textbatch import text_chunks


@dataclass
class Params:
    orders: tuple[int, ...] = (4, 6, 8)
    bits: int = 20
    max_rows: int = 4000
    features: int = 6000
    smoothing: float = 1.0
    ridge: float = 1.0
    rounds: int = 150


@dataclass
class Model:
    params: Params
    feature: np.ndarray  # sorted
    weight: np.ndarray  # of presence
    intercept: float

    def score(self, chunk) -> np.ndarray:
        keep = np.zeros(1 << self.params.bits, bool)
        keep[self.feature & ((1 << self.params.bits) - 1)] = True
        doc, feature = level_features(chunk, self.params.orders, self.params.bits, keep)
        weight = np.zeros(len(LEVELS) << self.params.bits, np.float32)
        weight[self.feature] = self.weight
        z = np.bincount(doc, weight[feature], chunk.n) + self.intercept
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _gathered(docs: DataFrame, p: Params, text_col: str, label_col: str) -> DataFrame:
    """(label, n, features) of each labelled row, a table; ``features`` are the compressed steps between n features."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(1)):
                doc, feature = level_features(chunk, p.orders, p.bits)
                off = np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=chunk.n))])
                steps = (np.diff(feature[a:b], prepend=0).astype("<u4").tobytes() for a, b in zip(off[:-1], off[1:], strict=True))
                made = pa.array([pa.compress(x, codec="zstd", asbytes=True) for x in steps], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, chunk.n), pa.array(np.diff(off).astype(np.int32)), made], ["label", "n", "features"])

    return written(docs.select(F.col(label_col).cast("int"), text_col).mapInArrow(run, "label int, n int, features binary"), "labelled")


def _features(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
    """The features of each row of ``_gathered``."""
    for n, data in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
        yield np.cumsum(np.frombuffer(pa.decompress(data.as_buffer(), decompressed_size=4 * n, codec="zstd"), "<u4"), dtype=np.int64)


def fit(docs: DataFrame, labels: DataFrame, trains: Column | None = None, p: Params | None = None, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Model:
    """``trains``: which rows of ``labels`` may be learned from."""
    p = p or Params()
    ship_package(docs.sparkSession)
    taught = labels if trains is None else labels.filter(trains)
    known = taught.select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("_label")).filter("_label IN (0, 1) AND _id IS NOT NULL")
    few = known.orderBy(F.xxhash64("_id"), "_id", "_label").limit(p.max_rows)  # the bound of what is broadcast
    met = docs.select(F.col(id_col).alias("_id"), F.xxhash64(text_col).alias("_h"), F.col(text_col).alias("_text")).join(F.broadcast(few.groupBy("_id", "_label").agg(F.count("*").alias("_times"))), "_id")
    # an id may have many rows: which ones teach is settled by narrow rows, and copies are combined before texts move
    keys = met.groupBy("_id", "_h", "_label").agg(F.max("_times").alias("_times")).select("_id", "_h", "_label", F.explode(F.sequence(F.lit(1), F.col("_times").cast("int"))))
    keys = keys.orderBy(F.xxhash64("_id", "_h"), "_id", "_h", "_label").limit(p.max_rows).groupBy("_id", "_h", "_label").agg(F.count("*").alias("_times"))
    chosen = met.drop("_times").join(F.broadcast(keys), ["_id", "_h", "_label"]).groupBy("_id", "_h", "_label").agg(F.first("_text").alias("_text"), F.first("_times").alias("_times"))
    rows = _gathered(chosen.select("_text", "_label", F.explode(F.sequence(F.lit(1), F.col("_times").cast("int")))).drop("col"), p, "_text", "_label")
    # the driver gets the chosen features only: all of them would pass through its memory, 30 times as many
    few = _kept(rows, _chosen(rows, p))
    return _solve(lambda: ((np.frombuffer(r["features"], "<u4"), r["label"]) for r in few.toLocalIterator()), p)


def _chosen(rows: DataFrame, p: Params) -> np.ndarray:
    """The features that carry the model of these rows, ascending: each task counts its rows' features, one task adds the counts up."""
    size = len(LEVELS) << p.bits

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, labels = np.zeros((2, size), np.uint32), np.zeros(2, np.int64)
        for batch in batches:
            for label, feature in zip(batch.column(0).to_pylist(), _features(batch), strict=True):
                n[label][feature] += 1
                labels[label] += 1
        if labels.sum():
            at = np.flatnonzero(n[0] + n[1])
            raw = np.diff(at, prepend=0).astype("<u4").tobytes() + n[:, at].astype("<u4").tobytes()
            yield pa.RecordBatch.from_arrays([pa.array([labels[0]]), pa.array([labels[1]]), pa.array([len(at)]), pa.array([pa.compress(raw, codec="zstd", asbytes=True)], pa.binary())], ["nneg", "npos", "n", "data"])

    def added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, labels = np.full((2, size), p.smoothing, np.float32), np.zeros(2, np.int64)
        for batch in batches:
            for nneg, npos, m, data in zip(*(batch.column(c).to_pylist() for c in range(3)), batch.column(3), strict=True):
                raw = np.frombuffer(pa.decompress(data.as_buffer(), decompressed_size=12 * m, codec="zstd"), "<u4").reshape(3, m)
                n[:, np.cumsum(raw[0], dtype=np.int64)] += raw[1:]
                labels += nneg, npos
        if labels.min():
            yield pa.RecordBatch.from_arrays([pa.array(_certain(n[1], n[0], labels[1], labels[0], p)[0])], ["feature"])

    parts = rows.mapInArrow(counted, "nneg long, npos long, n long, data binary")
    found = parts.repartitionById(1, F.lit(0)).mapInArrow(added, "feature long")
    return np.array([r[0] for r in found.collect()], np.int64)  # at most Params.features


def _kept(rows: DataFrame, feature: np.ndarray) -> DataFrame:
    """The rows with these features only."""
    shared = rows.sparkSession.sparkContext.broadcast(feature)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        feature = shared.value
        wanted = np.zeros(feature.max(initial=0) + 1, bool)
        wanted[feature] = True
        for batch in batches:
            left = (x[: np.searchsorted(x, len(wanted))] for x in _features(batch))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x[wanted[x]].astype("<u4").tobytes() for x in left], pa.binary())], ["label", "features"])

    return written(rows.mapInArrow(run, "label int, features binary"), "labelled")


def _certain(pos: np.ndarray, neg: np.ndarray, ones: float, zeros: float, p: Params) -> tuple[np.ndarray, np.ndarray]:
    """(features, log-count ratios) of the most certain ones, of smoothed counts."""
    npos, nneg = ones + 2 * p.smoothing, zeros + 2 * p.smoothing
    seen = np.flatnonzero(~(pos + neg <= 2 * p.smoothing + 1))  # more than once; only these take memory from here on
    pos, neg = pos[seen], neg[seen]
    ratio = np.log(pos / npos) - np.log(neg / nneg)
    sure = np.abs(ratio) / np.sqrt(1 / pos + 1 / neg)
    chosen = np.sort(np.argsort(-sure, kind="stable")[: p.features])
    chosen = chosen[sure[chosen] > 0]
    return seen[chosen], ratio[chosen]


def _solve(read, p: Params) -> Model:
    """``read()`` gives (distinct features, label) of each row, twice in the same order."""
    size = len(LEVELS) << p.bits
    pos, neg = np.full(size, p.smoothing, np.float32), np.full(size, p.smoothing, np.float32)
    labels = []
    for r, label in read():
        (pos if label else neg)[r] += 1
        labels.append(label)
    y = np.array(labels, float)
    none = Model(p, np.zeros(0, np.int64), np.zeros(0), 0.0)
    share = (y.sum() + 1) / (len(y) + 2)
    none.intercept = float(np.log(share / (1 - share)))
    if not len(y) or y.min() == y.max():
        return none
    feature, scale = _certain(pos, neg, y.sum(), (1 - y).sum(), p)
    if not len(feature):
        return none
    place = np.full(size, -1, np.int32)
    place[feature] = np.arange(len(feature))
    found = [x[x >= 0] for x in (place[r] for r, _ in read())]
    doc = np.repeat(np.arange(len(y)), [len(f) for f in found])
    col = np.concatenate(found)
    x = scale[col]
    balance = np.where(y > 0, 0.5 * len(y) / y.sum(), 0.5 * len(y) / (len(y) - y.sum()))
    # the features' own size bounds the curvature, so that a diagonal step converges
    w, b = np.zeros(len(feature)), 0.0
    per = np.bincount(doc, np.abs(x), len(y)) + 1
    curve = np.bincount(col, np.abs(x) * (0.25 * balance * per)[doc], len(feature)) + p.ridge
    curve_b = float((0.25 * balance * per).sum())
    ahead, ahead_b, pace = w, b, 1.0
    for _ in range(p.rounds):
        z = np.bincount(doc, x * ahead[col], len(y)) + ahead_b
        off = balance * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y)
        nw = ahead - (np.bincount(col, x * off[doc], len(feature)) + p.ridge * ahead) / curve
        nb = ahead_b - off.sum() / curve_b
        faster = (1 + np.sqrt(1 + 4 * pace * pace)) / 2
        ahead, ahead_b = nw + (pace - 1) / faster * (nw - w), nb + (pace - 1) / faster * (nb - b)
        w, b, pace = nw, nb, faster
    return Model(p, feature, w * scale, float(b))


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score): 0 to 1, higher where label 1 is likelier."""
    spark = docs.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(model)  # bounded by Params.features

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for row, chunk in text_chunks(batch.column(1)):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, chunk.n), pa.array(m.score(chunk))], [id_col, "score"])

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, score double")


def keep_clean(docs: DataFrame, model: Model, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns, whose text scores below the threshold."""
    spark = docs.sparkSession
    ship_package(spark)
    shared, at, names = spark.sparkContext.broadcast(model), docs.columns.index(text_col), docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for row, chunk in text_chunks(batch.column(at)):
                yield batch.slice(row, chunk.n).filter(pa.array(m.score(chunk) < threshold)).rename_columns(names)

    return docs.mapInArrow(run, docs.schema)

"""Approximate nearest neighbours by a hierarchical k-means tree.

``fit`` clusters a bounded sample of vectors into a tree; every row is placed
under its leaf.  A leaf of more than ``split_rows`` rows gets a tree of its own,
from a bounded sample of its rows, and so on down: leaves stay of one size while
the tree deepens with the table.  The topmost tree is broadcast, those below are a
table that rows and queries meet by leaf.

A query walks best bin first: a priority queue holds unopened nodes, and each leaf
that leaves it is a visit.  A node's place in the queue is the least cosine on its
path, so that below the topmost tree the queue is an order by it: each level keeps
a query's first nodes, as many as visits.  The number of visits is calibrated:
sample queries are answered exactly over all rows, and visits widen until the
wanted recall is reached on them.

Of equal vectors the k + 1 least ids are indexed: none of the others can be among
any row's k nearest, as ties go to the smaller id.

Queries and indexed vectors meet leaf by leaf in blocks, so that a pair of rows
is never a row; within a block, equal vectors are scored once and stand for their
least ids.  Scores are cosines in double precision, computed for each pair in the
same order of operations wherever it stands, so equal vectors tie exactly.

Defined results: a vector that is null, zero, or holds a null or non-finite
component takes no part, nor do vectors of another dimension than the most
common one; a null id takes no part; repeated rows count once; fewer candidates
than k give fewer rows; an empty table gives none.  Only two columns are read.
"""

from __future__ import annotations

import heapq
import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import release, ship_package, written
from .textbatch import ranges


@dataclass
class Params:
    k: int = 5
    branching: int = 16
    leaf_rows: int = 200
    max_depth: int = 3
    sample_rows: int = 8192
    split_rows: int = 3200
    child_rows: int = 4096  # expected rows of the sample for a leaf's own tree
    calibration_rows: int = 128
    recall: float = 0.97
    rounds: int = 8
    block: int = 512
    first_visits: int = 64  # where calibration begins

    @property
    def base(self) -> int:
        """More than a tree's leaves: a leaf's number is (its parent's + 1) * base + its place."""
        return (self.branching + 1) ** self.max_depth


@dataclass
class Node:
    children: np.ndarray | None  # centroids
    nodes: list  # of the children, or their leaf numbers


def unit(v: np.ndarray) -> np.ndarray:
    return v / np.linalg.norm(v, axis=1, keepdims=True)


def cosines(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, by sums whose order depends on the dimension only."""
    a, b = np.ascontiguousarray(a, float), np.ascontiguousarray(b, float)
    return (a * b).sum(axis=1) / (np.sqrt((a * a).sum(axis=1)) * np.sqrt((b * b).sum(axis=1)))


def _kmeans(v: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    c = v[rng.choice(len(v), size=min(k, len(v)), replace=False)]
    for _ in range(rounds):
        own = (v @ c.T).argmax(axis=1)
        sums = np.zeros_like(c)
        np.add.at(sums, own, v)
        size = np.linalg.norm(sums, axis=1, keepdims=True)
        c = np.where(size > 1e-9, sums / np.maximum(size, 1e-9), c)
    return np.unique(c, axis=0)


class Tree:
    def __init__(self, sample: np.ndarray, leaves: int, p: Params) -> None:
        self.leaves, self.p = 0, p
        depth = 0
        while p.branching**depth < leaves and depth < p.max_depth:
            depth += 1
        self.branching = max(2, int(np.ceil(leaves ** (1 / max(1, depth))))) if depth else 1
        self.root = self._grow(unit(sample.astype(float)), depth, np.random.default_rng(11))

    def _grow(self, v: np.ndarray, depth: int, rng: np.random.Generator):
        if depth == 0 or len(v) < 2 * self.branching:
            self.leaves += 1
            return self.leaves - 1
        c = _kmeans(v, self.branching, self.p.rounds, rng)
        own = (v @ c.T).argmax(axis=1)
        return Node(c, [self._grow(v[own == k], depth - 1, rng) for k in range(len(c))])

    def assign(self, v: np.ndarray) -> np.ndarray:
        """Each unit vector's leaf, going down by the nearest centroid."""
        out = np.zeros(len(v), np.int64)

        def down(node, rows: np.ndarray) -> None:
            if not isinstance(node, Node):
                out[rows] = node
                return
            own = (v[rows] @ node.children.T).argmax(axis=1)
            for k in np.unique(own).tolist():
                down(node.nodes[k], rows[own == k])

        down(self.root, np.arange(len(v)))
        return out

    def walk(self, q: np.ndarray, most: int) -> list[tuple[int, float, float]]:
        """Leaves in best-bin-first order, each with the least cosine on its path and its own."""
        queue, tick, out = [(-1.0, -1.0, 0, self.root)], 0, []
        while queue and len(out) < most:
            least, own, _, node = heapq.heappop(queue)
            if not isinstance(node, Node):
                out.append((node, -least, -own))
                continue
            for near, child in zip((node.children @ q).tolist(), node.nodes, strict=True):
                tick += 1
                heapq.heappush(queue, (max(least, -near), -near, tick, child))
        return out

    def visits(self, q: np.ndarray, most: int) -> list[int]:
        return [leaf for leaf, _, _ in self.walk(q, most)]


def best(queries: np.ndarray, query_ids: np.ndarray, ids: np.ndarray, vectors: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query ids, ids, scores): each query's k nearest rows of a block, other than itself, by score, ties to the smaller id."""
    ids, at = np.unique(ids, return_index=True)
    vectors = vectors[at]
    flat = np.ascontiguousarray(vectors).view(np.dtype((np.void, vectors.dtype.itemsize * vectors.shape[1]))).ravel()
    _, first, same = np.unique(flat, return_index=True, return_inverse=True)
    order = np.argsort(same, kind="stable")  # ids of equal vectors, ascending
    held = np.bincount(same)
    begin = np.cumsum(held) - held
    distinct = vectors[first]
    rough = unit(queries) @ unit(distinct).T
    need = min(k + 1, len(distinct))
    floor = -np.partition(-rough, need - 1, axis=1)[:, need - 1] - 1e-9
    row, near = np.nonzero(rough >= floor[:, None])
    times = np.minimum(held[near], k + 1)
    some = range(0, len(row), 16384)  # pairs held at a time
    score = np.repeat(np.concatenate([cosines(queries[row[i : i + 16384]], distinct[near[i : i + 16384]]) for i in some]), times)
    row, found = np.repeat(row, times), ids[order[ranges(begin[near], times)]]
    other = found != query_ids[row]
    row, found, score = row[other], found[other], score[other]
    by = np.lexsort((found, -score, row))
    row, found, score = row[by], found[by], score[by]
    top = np.arange(len(row)) - np.searchsorted(row, row) < k
    return query_ids[row[top]], found[top], score[top]


def usable(rows: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, v): rows that take part.  Floats stay floats until they are compared, in double precision."""
    kind = "array<float>" if rows.schema[vector_col].dataType.simpleString() == "array<float>" else "array<double>"
    v = F.col("v")
    good = F.col("id").isNotNull() & v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = rows.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast(kind).alias("v")).filter(good)
    sizes = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    return rows.filter(F.size("v") == (sizes["d"] if sizes else 0))


def _kind(rows: DataFrame) -> str:
    return rows.schema["v"].dataType.simpleString()


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten()
    return flat.to_numpy(zero_copy_only=False).astype(float).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


@dataclass
class Index:
    tree: Tree | None
    levels: list[DataFrame]  # leaf, tree: trees of leaves, from the top down
    rows: DataFrame  # leaf, k, ids, vectors: blocks of all rows
    p: Params
    visits: int = 1
    recall: float = 1.0


def _exact(queries: list, blocks: DataFrame, spark, p: Params) -> dict[int, list[int]]:
    """Nearest ids over all blocks of a bounded number of queries."""
    ids, q = np.array([r["id"] for r in queries]), np.array([r["v"] for r in queries])
    shared = spark.sparkContext.broadcast((ids, q))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = shared.value
        for batch in batches:
            for block, vectors in zip(batch.column(0), batch.column(1), strict=True):
                found = best(q, ids, block.values.to_numpy(), _matrix(vectors.values), p.k)
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], ["query_id", "vec_id", "score"])

    near = blocks.select("ids", "vectors").mapInArrow(run, "query_id long, vec_id long, score double")
    out: dict[int, list[int]] = {}
    for r in _top(near, p.k).collect():  # calibration_rows x k
        out.setdefault(r["query_id"], []).append(r["vec_id"])
    return out


def _top(near: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.distinct().withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def _least_ids(good: DataFrame, k: int) -> DataFrame:
    """Distinct (id, v): of equal vectors the k + 1 least ids, cut before rows are shuffled."""
    w = Window.partitionBy("v").orderBy("id")
    return good.withColumn("r", F.dense_rank().over(w)).filter(F.col("r") <= k + 1).groupBy("v", "id").agg(F.lit(None).alias("r")).select("id", "v")


def _blocks(placed: DataFrame, p: Params) -> DataFrame:
    """(leaf, n, k, ids, vectors): about ``block`` rows each; n rows in the leaf."""
    size = placed.groupBy("leaf").agg(F.count("*").alias("n"))
    cut = placed.join(size, "leaf").withColumn("k", F.pmod(F.xxhash64("id"), F.ceil(F.col("n") / p.block)))
    return written(cut.groupBy("leaf", "k").agg(F.first("n").alias("n"), F.collect_list(F.struct("id", "v")).alias("x")).select("leaf", "n", "k", F.col("x.id").alias("ids"), F.col("x.v").alias("vectors")), "leaf-blocks")


def _trees_of_leaves(blocks: DataFrame, p: Params, level: int) -> DataFrame:
    """(leaf, tree) of the leaves to be split; none for those whose sampled rows can't be told apart."""
    big = blocks.filter(F.col("n") > p.split_rows).select("leaf", "n", F.explode(F.arrays_zip("ids", "vectors")).alias("x"))
    picked = big.filter(F.pmod(F.xxhash64("x.ids", F.lit(level)), F.lit(1 << 30)) < F.lit(float(p.child_rows << 30)) / F.col("n"))
    samples = picked.groupBy("leaf").agg(F.first("n").alias("n"), F.sort_array(F.collect_list("x")).alias("x")).select("leaf", "n", F.col("x.vectors").alias("vectors"))

    def grow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for leaf, n, v in zip(*batch.columns, strict=True):
                tree = Tree(_matrix(v.values), max(2, min(p.branching**p.max_depth, n.as_py() // p.leaf_rows)), p)
                if tree.leaves > 1:
                    yield pa.RecordBatch.from_arrays([pa.array([leaf.as_py()]), pa.array([pickle.dumps(tree)], pa.binary())], ["leaf", "tree"])

    return written(samples.mapInArrow(grow, "leaf long, tree binary"), "trees")


def _split(blocks: DataFrame, trees: DataFrame, p: Params) -> DataFrame:
    """(id, v, leaf) of all rows, one level further down."""
    kind = blocks.schema["vectors"].dataType.elementType.simpleString()

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for leaf, ids, vectors, tree in zip(*batch.columns, strict=True):
                number = np.full(len(ids.values), leaf.as_py(), np.int64)
                if tree.is_valid:
                    number = (number + 1) * p.base + pickle.loads(tree.as_buffer()).assign(unit(_matrix(vectors.values)))
                yield pa.RecordBatch.from_arrays([ids.values, vectors.values, pa.array(number)], ["id", "v", "leaf"])

    return written(blocks.select("leaf", "ids", "vectors").join(trees, "leaf", "left").mapInArrow(place, f"id long, v {kind}, leaf long"), "leaves")


def fit(rows: DataFrame, p: Params | None = None, id_col: str = "vec_id", vector_col: str = "embedding") -> Index:
    """Trees from samples of ``sample_rows`` rows and of about ``child_rows`` of each leaf to be split, all rows' blocks by leaf, and calibrated visits."""
    p = p or Params()
    spark = rows.sparkSession
    ship_package(spark)
    good = written(_least_ids(usable(rows, id_col, vector_col), p.k), "vectors")
    total = good.count()
    sample = good.orderBy(F.xxhash64("id"), "id", "v").limit(p.sample_rows).toArrow().combine_chunks()
    if not total:
        return Index(None, [], good.select(F.lit(0).alias("leaf"), F.array("id").alias("ids"), F.array("v").alias("vectors")), p)
    tree = Tree(_matrix(sample.column("v").combine_chunks()), max(1, min(p.branching**p.max_depth, total // p.leaf_rows)), p)
    shared = spark.sparkContext.broadcast(tree)  # at most branching^max_depth centroids

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v = _matrix(batch.column(1))
            if len(v):
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(shared.value.assign(unit(v)))], ["id", "v", "leaf"])

    placed = written(good.mapInArrow(place, f"id long, v {_kind(good)}, leaf long"), "leaves")
    blocks = _blocks(placed, p)
    levels: list[DataFrame] = []
    while p.base ** (len(levels) + 2) < 1 << 63 and not blocks.filter(F.col("n") > p.split_rows).isEmpty():
        trees = _trees_of_leaves(blocks, p, len(levels))
        if trees.isEmpty():
            break
        release(placed)
        placed, before = _split(blocks, trees, p), blocks
        blocks = _blocks(placed, p)
        release(before)
        levels.append(trees)
    release(placed)
    index = Index(tree, levels, blocks, p)
    _calibrate(index, good, spark)
    return index


def _walks(asked: DataFrame, index: Index, most: int, queries: int) -> DataFrame:
    """(id, v, leaf, near, own): each query's first leaves, best bin first; no more than ``most``."""
    p = index.p
    shared = asked.sparkSession.sparkContext.broadcast(index.tree)
    names = ["id", "v", "leaf", "near", "own"]
    schema = f"id long, v {_kind(asked)}, leaf long, near double, own double"

    def opened(ids: pa.Array, v: pa.Array, walks: list[list[tuple[int, float, float]]]) -> pa.RecordBatch:
        at = pa.array(np.repeat(np.arange(len(walks)), [len(x) for x in walks]))
        columns = [pa.array([leaf[c] for x in walks for leaf in x], t) for c, t in enumerate((pa.int64(), pa.float64(), pa.float64()))]
        return pa.RecordBatch.from_arrays([ids.take(at), v.take(at), *columns], names)

    def top(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 1024):
                ids, v = batch.slice(k, 1024).columns
                yield opened(ids, v, [shared.value.walk(q, most) if shared.value else [] for q in unit(_matrix(v))])

    def down(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for leaf, held, tree in zip(*batch.columns, strict=True):
                ids, v, near, own = held.values.flatten()
                leaf = leaf.as_py()
                if not tree.is_valid:
                    yield opened(ids, v, [[(leaf, a, b)] for a, b in zip(near.to_pylist(), own.to_pylist(), strict=True)])
                    continue
                below = pickle.loads(tree.as_buffer())
                yield opened(ids, v, [[((leaf + 1) * p.base + x, min(a, b), c) for x, b, c in below.walk(q, most)] for q, a in zip(unit(_matrix(v)), near.to_pylist(), strict=True)])

    walks = asked.mapInArrow(top, schema)
    first = Window.partitionBy("id", "v").orderBy(F.desc("near"), F.desc("own"), "leaf")
    for trees in index.levels:
        k = F.pmod(F.xxhash64("id"), F.lit(max(1, queries // p.block))).alias("k")
        held = walks.groupBy("leaf", k).agg(F.collect_list(F.struct("id", "v", "near", "own")).alias("q"))
        walks = held.join(trees, "leaf", "left").select("leaf", "q", "tree").mapInArrow(down, schema)
        walks = walks.withColumn("n", F.row_number().over(first)).filter(F.col("n") <= most).drop("n")
    return walks


def _calibrate(index: Index, good: DataFrame, spark) -> None:
    p = index.p
    asked = good.orderBy(F.xxhash64("id", F.lit(3)), "id", "v").limit(p.calibration_rows).collect()
    truth = _exact(asked, index.rows, spark, p)
    wanted = sorted({i for f in truth.values() for i in f})
    leaf_of = dict(index.rows.select("leaf", F.explode("ids").alias("id")).join(F.broadcast(spark.createDataFrame([(i,) for i in wanted] or [(0,)], "id long")), "id").select("id", "leaf").collect())
    near = [(i, leaf_of[j]) for i, f in truth.items() for j in f]
    need = int(np.ceil(p.recall * len(near)))
    queries = spark.createDataFrame([(r["id"], r["v"]) for r in asked], "id long, v array<double>")
    most = p.first_visits
    while near:
        order: dict[int, list] = {}
        for r in _walks(queries, index, most, len(asked)).select("id", "leaf", "near", "own").toArrow().to_pylist():  # calibration_rows x most
            order.setdefault(r["id"], []).append((-r["near"], -r["own"], r["leaf"]))
        place = {(i, x[2]): k for i, found in order.items() for k, x in enumerate(sorted(found))}
        at = sorted(place[x] for x in near if x in place)
        if len(at) >= need:
            index.visits = at[max(0, need - 1)] + 1
            index.recall = sum(x < index.visits for x in at) / len(near)
            return
        most *= 4


def search(index: Index, rows: DataFrame, is_query: Column | None = None, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score) of the rows that ``is_query`` marks."""
    p = index.p
    spark = rows.sparkSession
    ship_package(spark)
    asked = rows if is_query is None else rows.filter(is_query)
    asked = usable(asked, id_col, vector_col)
    count = asked.count()
    walks = _walks(asked, index, index.visits, count)
    asking = walks.withColumn("k", F.pmod(F.xxhash64("id"), F.lit(max(1, count // p.block)))).groupBy("leaf", "k").agg(F.collect_list(F.struct("id", "v")).alias("q"))
    met = asking.select("leaf", F.col("q.id").alias("qid"), F.col("q.v").alias("qv")).join(index.rows, "leaf").select("qid", "qv", "ids", "vectors")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for qid, qv, ids, vectors in zip(*batch.columns, strict=True):
                found = best(_matrix(qv.values), qid.values.to_numpy(), ids.values.to_numpy(), _matrix(vectors.values), p.k)
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], ["query_id", "vec_id", "score"])

    near = met.mapInArrow(compare, "query_id long, vec_id long, score double")
    return _top(near, p.k).select("query_id", "rank", "vec_id", "score")

"""Near-duplicate classes by weighted MinHash over word-shingle multisets.

A text is the multiset of its runs of five lower-case words (a shorter text: of
all its words).  Its signature holds, for each of ``slots`` places, the earliest
point of Poisson processes: a shingle of multiplicity c owns the part below c of
a weight axis cut into doubling intervals; each interval has its own process,
whose points carry a time, a place and a level within the interval, and count
where the level is below c.  Two places agree with the probability of the
multisets' weighted Jaccard similarity.

Texts of equal multisets (by 128 bits) become one node, which gets a number.
Nodes that agree in a band share a bucket.  Verification compares whole multisets
of shingles, each known by 54 bits: first each member of a bucket against the
bucket's least node, then, in buckets that hold more than one component, those
members against all others inside blocks.  No pair of a bucket is left out but
those whose sizes alone rule the similarity out.  Links' connected components are
the classes.

Between the steps only ids, numbers and bands move.  Texts are shuffled where a
comparison needs them: a filter of the wanted rows' hashes, sized by their number
up to 2^``filter_bits`` bits, spares all others; beyond that it spares fewer, at
last none, and no result changes.

Defined results: a null or empty text, or one without letters and digits, is a
class of its own under its id; a null id's class is its group's least id, or null
where there's none; rows repeat if the input's do.  Only two columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import release, ship_package, written
from .bitmap import among
from .ngrams import lower_table
from .pretokens import LETTER, NUMBER, class_table
from .textbatch import TextChunk, binary_array, mix64, ranges, span_hashes, text_chunks

_ID_BITS = np.uint64(54)  # of a shingle, beside 10 bits for the text's place in its chunk
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


@dataclass
class Params:
    words: int = 5
    similarity: float = 0.8
    bands: int = 24
    rows: int = 5
    block: int = 128  # texts of a block
    block_shingles: int = 100_000  # and their shingles; one longer text is a block of its own
    filter_bits: int = 26

    @property
    def slots(self) -> int:
        return self.bands * self.rows


def shingles(chunk: TextChunk, p: Params) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, shingle, multiplicity) sorted by the first two."""
    codes, off = chunk.codes, chunk.char_off
    none = np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if not len(codes):
        return none
    kind = class_table()[codes]
    solid = (kind == LETTER) | (kind == NUMBER)
    first = np.zeros(len(codes) + 1, bool)
    first[off] = True
    begins, ends = solid.copy(), np.zeros(len(codes) + 1, bool)
    begins[1:] &= ~solid[:-1] | first[1:-1]
    ends[1:-1] = solid[:-1] & (~solid[1:] | first[1:-1])
    ends[-1] = solid[-1]
    start, end = np.flatnonzero(begins), np.flatnonzero(ends)
    if not len(start):
        return none
    word = span_hashes(lower_table()[codes], start, end)
    doc = np.searchsorted(off, start, side="right") - 1
    per = np.bincount(doc, minlength=chunk.n)
    begin = np.concatenate([[0], np.cumsum(per)])
    h, m = np.zeros(max(0, len(word) - p.words + 1), np.uint64), max(0, len(word) - p.words + 1)
    for k in range(p.words):
        h = h * _GOLDEN + word[k : m + k]
    whole = np.flatnonzero(np.arange(m) + p.words <= begin[doc[:m] + 1])
    h, at = h[whole], doc[whole]
    short = np.flatnonzero((per > 0) & (per < p.words))
    if len(short):
        h = np.concatenate([h, span_hashes(word, begin[short], begin[short + 1])])
        at = np.concatenate([at, short])
    key, count = np.unique(at.astype(np.uint64) << _ID_BITS | mix64(h) >> np.uint64(10), return_counts=True)
    return (key >> _ID_BITS).astype(np.int64), key & np.uint64((1 << 54) - 1), count


def fingerprints(n: int, doc: np.ndarray, shingle: np.ndarray, count: np.ndarray) -> np.ndarray:
    """128 bits of each text's multiset; zero where there's none."""
    out = np.zeros((n, 2), np.uint64)
    if len(doc):
        cut = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
        for k, salt in enumerate((0x5851F42D4C957F2D, 0x14057B7EF767814F)):
            out[doc[cut], k] = mix64(np.add.reduceat(mix64(shingle ^ np.uint64(salt)) * count.astype(np.uint64), cut))
    return out


def signatures(n: int, doc: np.ndarray, shingle: np.ndarray, count: np.ndarray, slots: int) -> np.ndarray:
    """Earliest time at each of the places, n x slots; infinite without shingles."""
    sig = np.full(n * slots, np.inf)
    if not len(doc):
        return sig.reshape(n, slots)
    level, item = 0, np.arange(len(doc))
    parts = []
    while len(item):  # intervals [0,1) [1,2) [2,4) [4,8) ... that begin below the multiplicity
        low, width = (0, 1) if level == 0 else (1 << (level - 1), 1 << (level - 1))
        item = item[count[item] > low]
        parts.append((item, np.full(len(item), low), np.full(len(item), width), mix64(shingle[item] + np.uint64((level + 1) * int(_GOLDEN) & 0xFFFFFFFFFFFFFFFF))))
        level += 1
    item, low, width, seed = (np.concatenate(x) for x in zip(*parts, strict=True))
    owner, most = doc[item], count[item]
    time = np.zeros(len(item))
    step = 0
    while len(owner):
        several = int(np.clip(200_000 // len(owner), 1, 256))
        k = np.arange(step + 1, step + several + 1, dtype=np.uint64)
        x = mix64(seed[:, None] + k * _GOLDEN)
        gap = -np.log(((x >> np.uint64(32)).astype(np.float64) + 0.5) * 2.0**-32) / (slots * width)[:, None]
        times = np.cumsum(np.concatenate([time[:, None], gap], axis=1), axis=1)[:, 1:]  # point by point: the same bits however points are grouped
        place = ((x & np.uint64(0xFFFFFFFF)) * np.uint64(slots) >> np.uint64(32)).astype(np.int64) + (owner * slots)[:, None]
        wide = width > 1
        if wide.any():
            at = low[wide, None] + (mix64(x[wide] ^ _GOLDEN) >> np.uint64(11)).astype(np.float64) * 2.0**-53 * width[wide, None]
            hit = np.ones(times.shape, bool)
            hit[wide] = np.floor(at) < most[wide, None]
            np.minimum.at(sig, place[hit], times[hit])
        else:
            np.minimum.at(sig, place.ravel(), times.ravel())
        latest = sig.reshape(n, slots).max(axis=1)
        time, step = times[:, -1], step + several
        on = time < latest[owner]
        owner, most, low, width, seed, time = owner[on], most[on], low[on], width[on], seed[on], time[on]
    return sig.reshape(n, slots)


def _signed(docs: DataFrame, p: Params, id_col: str, text_col: str) -> DataFrame:
    """(id, h, node, n, bands): h a hash of the text; node null without shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(2)):
                doc, shingle, count = shingles(chunk, p)
                n = np.bincount(doc, count, chunk.n).astype(np.int64)
                print_ = fingerprints(chunk.n, doc, shingle, count)
                sig = signatures(chunk.n, doc, shingle, count, p.slots).view(np.uint64)
                band = np.zeros((chunk.n, p.bands), np.uint64)
                for k in range(p.rows):
                    band = mix64(band * _GOLDEN + sig.reshape(chunk.n, p.bands, p.rows)[:, :, k])
                band = mix64(band + np.arange(p.bands, dtype=np.uint64))
                has = n > 0
                node = pa.array([x if ok else None for x, ok in zip(binary_array(print_.tobytes(), np.arange(chunk.n + 1) * 16).to_pylist(), has.tolist(), strict=True)], pa.binary())
                bands = pa.ListArray.from_arrays(pa.array(np.arange(chunk.n + 1) * p.bands, pa.int32()), pa.array(band.view(np.int64).ravel()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, chunk.n), batch.column(1).slice(row, chunk.n), node, pa.array(n), bands], ["id", "h", "node", "n", "bands"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.xxhash64(text_col).alias("h"), F.col(text_col).alias("text")).mapInArrow(run, f"id {kind}, h long, node binary, n long, bands array<long>")


def _key(id_: Column) -> Column:
    """An id as a string that isn't null, so that null ids meet, too."""
    return F.coalesce(F.concat(F.lit("="), id_.cast("string")), F.lit(""))


def _texts(docs: DataFrame, needed: DataFrame, p: Params, id_col: str, text_col: str) -> DataFrame:
    """(number, text) of the nodes in ``needed`` (number, k, h): one text of each."""
    row_hash = lambda: F.xxhash64("k", "h")
    test = among(needed.select(row_hash().alias("x")), p.filter_bits)
    rows = docs.select(_key(F.col(id_col)).alias("k"), F.xxhash64(text_col).alias("h"), F.col(text_col).alias("text")).filter(test(row_hash()))
    # repeated rows are combined before they move
    return rows.groupBy("k", "h").agg(F.first("text").alias("text")).join(needed, ["k", "h"]).select("number", "text")


def _multisets(column: pa.Array, p: Params) -> list[tuple[np.ndarray, np.ndarray]]:
    """(shingles, counts) of each text."""
    out = []
    for _, chunk in text_chunks(column):
        doc, shingle, count = shingles(chunk, p)
        cut = np.searchsorted(doc, np.arange(chunk.n + 1))
        out += [(shingle[a:b], count[a:b]) for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
    return out


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard similarity of two multisets: sorted shingles and their counts."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    common = int(np.minimum(a[1][i], b[1][j]).sum())
    total = int(a[1].sum()) + int(b[1].sum()) - common
    return common / total if total else 0.0


def _verified(pairs: DataFrame, texts: DataFrame, p: Params) -> DataFrame:
    """The pairs (a, b) of nodes whose multisets are similar enough."""

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, first, back = np.unique(batch.column(1).to_numpy(), return_index=True, return_inverse=True)
            x, y = _multisets(batch.column(2), p), _multisets(batch.column(3).take(pa.array(first)), p)
            keep = [similarity(x[k], y[j]) >= p.similarity for k, j in enumerate(back.tolist())]
            yield batch.filter(pa.array(keep, pa.bool_())).select([0, 1])

    left = pairs.join(texts.select(F.col("number").alias("a"), F.col("text").alias("x")), "a")
    both = left.join(texts.select(F.col("number").alias("b"), F.col("text").alias("y")), "b")
    return both.select("a", "b", "x", "y").mapInArrow(exact, "a long, b long")


def _brief(df: DataFrame, name: str) -> DataFrame:
    """A written table of short rows: an eighth of the partitions that rows with texts get."""
    return written(df.coalesce(max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 8)), name)


def components(links: DataFrame) -> DataFrame:
    """(node, label) of numbered nodes with links (a, b); the label is a component's least node.

    Each round takes the least label of all neighbours, then follows labels once
    (so that paths shrink by half); tables are written between rounds.
    """
    edges = _brief(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = _brief(edges.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), "labels")
    held = labels
    while True:
        seen = edges.join(labels.withColumnRenamed("node", "b"), "b").select(F.col("a").alias("node"), "label", F.lit(None).cast("long").alias("was"))
        own = labels.select("node", "label", F.col("label").alias("was"))
        lower = _brief(seen.unionAll(own).groupBy("node").agg(F.min("label").alias("near"), F.max("was").alias("was")), "labels")
        on = lower.select(F.col("node").alias("near"), F.col("near").alias("label"))
        moved = _brief(lower.join(on, "near").select("node", F.least("label", "near").alias("label"), "was"), "labels")
        release(held, lower)
        labels, held = moved.select("node", "label"), moved
        if moved.filter(F.col("label") != F.col("was")).isEmpty():
            release(edges)
            return moved.drop("was")


def _joined(links: DataFrame, labels: DataFrame) -> DataFrame:
    """(node, label) of the components that links join further: components are the nodes of a smaller graph."""
    of = lambda c: labels.select(F.col("node").alias(c), F.col("label").alias(f"l{c}"))
    named = links.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b"))
    return components(named.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())


def _block_links(members: DataFrame, labels: DataFrame, texts: DataFrame, p: Params) -> DataFrame:
    """Links (a, b) between nodes of one bucket that are still in different components.

    Members outside of the least node's component meet all members, block by
    block, and are verified there: a block pair gives at most the links that join
    its components, so neither rows nor shuffles grow with a group's square.
    """
    named = members.filter("size > 2").join(labels.withColumnRenamed("node", "number"), "number", "left").withColumn("label", F.coalesce("label", "number"))
    heads = labels.select(F.col("node").alias("leader"), F.col("label").alias("head"))
    named = _brief(named.join(heads, "leader", "left").select("bucket", "number", "n", "leader", "label", (F.col("label") != F.coalesce("head", "leader")).alias("apart")), "bucket-members")
    blocks = lambda n, shingles: F.ceil(F.greatest(n / p.block, shingles / p.block_shingles))
    sums = [F.count_if("apart").alias("x_n"), F.sum(F.when(F.col("apart"), F.col("n"))).alias("x_sum"), F.count("*").alias("y_n"), F.sum("n").alias("y_sum")]
    open_ = named.groupBy("bucket").agg(*sums).filter("x_n > 0").select("bucket", blocks(F.col("x_n"), F.col("x_sum")).alias("x_blocks"), blocks(F.col("y_n"), F.col("y_sum")).alias("y_blocks"))
    rest = _brief(named.filter("number <> leader").join(open_, "bucket"), "open-buckets")  # the leaders were compared with the others before
    full = rest.join(texts, "number")
    blocked = lambda rows, name: rows.withColumn("k", F.pmod(F.xxhash64("number"), F.col(f"{name}_blocks"))).groupBy("bucket", "k").agg(F.collect_list(F.struct("number", "label", "text")).alias(name)).drop("k")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x, y in zip(*batch.columns, strict=True):
                if found := _links_between(_Block(x.values, p), _Block(y.values, p), p.similarity):
                    yield pa.RecordBatch.from_arrays([pa.array([f[c] for f in found], pa.int64()) for c in (0, 1)], ["a", "b"])

    links = blocked(full.filter("apart"), "x").join(blocked(full, "y"), "bucket").select("x", "y").mapInArrow(compare, "a long, b long")
    links = written(links, "links")
    release(named, rest)
    return links


class _Block:
    """Some nodes' multisets as sets: the k-th of equal shingles is an element of its own."""

    def __init__(self, rows: pa.StructArray, p: Params) -> None:
        self.node, self.label = (rows.field(c).to_pylist() for c in ("number", "label"))
        sets = _multisets(rows.field("text"), p)
        shingle, count = np.concatenate([x for x, _ in sets]), np.concatenate([c for _, c in sets])
        owner = np.repeat(np.arange(len(sets)), [len(x) for x, _ in sets])
        self.n = np.array([c.sum() for _, c in sets])
        again = ranges(np.zeros(len(count), np.int64), count).astype(np.uint64)
        element = np.repeat(shingle, count)
        self.element = np.where(again == 0, element, mix64(element + again * _GOLDEN))
        self.owner = np.repeat(owner, count)


def _common(x: _Block, y: _Block, columns: int = 4096) -> np.ndarray:
    """Sizes of all intersections, as products of 0/1 matrices over shared elements."""
    shared = np.intersect1d(x.element, y.element)
    out = np.zeros((len(x.n), len(y.n)), np.float32)
    if not len(shared):
        return out

    def places(b: _Block) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(shared, b.element), len(shared) - 1)
        ok = shared[at] == b.element
        return b.owner[ok], at[ok]

    (xo, xa), (yo, ya) = places(x), places(y)
    for low in range(0, len(shared), columns):
        a, b = np.zeros((len(x.n), columns), np.float32), np.zeros((len(y.n), columns), np.float32)
        for m, o, at in ((a, xo, xa), (b, yo, ya)):
            here = (at >= low) & (at < low + columns)
            m[o[here], at[here] - low] = 1
        out += a @ b.T
    return out


def _links_between(x: _Block, y: _Block, least: float) -> list[tuple[int, int]]:
    """Links that join components of two blocks."""
    above: dict[int, int] = {}

    def root(label: int) -> int:
        while (up := above.get(label)) is not None:
            label = up
        return label

    common = _common(x, y).astype(np.float64)
    near = common >= least * (x.n[:, None] + y.n[None, :] - common)
    found = []
    for i, j in np.argwhere(near & (common > 0)).tolist():
        a, b = root(x.label[i]), root(y.label[j])
        if a != b:
            above[max(a, b)] = min(a, b)
            found.append((x.node[i], y.node[j]))
    return found


def _classified(docs: DataFrame, p: Params, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """Two tables: (id, h, node) of all rows; (node, class_id, class_rows, stand_k, stand_h) of nodes in classes of several rows.

    ``stand``: the row that stands for the class, that of its least id.
    """
    ship_package(docs.sparkSession)
    signed = written(_signed(docs, p, id_col, text_col), "signed")
    least = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "h")).alias("stand")
    nodes = signed.filter("node IS NOT NULL").groupBy("node").agg(F.min("id").alias("id"), least, F.count("*").alias("rows"), F.first("n").alias("n"), F.first("bands").alias("bands"))
    nodes = written(nodes.withColumn("number", F.monotonically_increasing_id()), "nodes")
    placed = nodes.select("number", "n", F.explode("bands").alias("bucket"))
    buckets = _brief(placed.groupBy("bucket").agg(F.count("*").alias("size"), F.min("number").alias("leader")).filter("size > 1"), "buckets")
    members = _brief(placed.join(buckets, "bucket"), "members")

    needed = members.select("number").distinct().join(nodes.select("number", _key(F.col("stand.id")).alias("k"), F.col("stand.h").alias("h")), "number")
    needed = _brief(needed, "needed")
    texts = written(_texts(docs, needed, p, id_col, text_col), "texts")

    pairs = members.filter("number <> leader").select(F.col("number").alias("a"), F.col("n").alias("n_a"), F.col("leader").alias("b")).distinct().join(nodes.select(F.col("number").alias("b"), F.col("n").alias("n_b")), "b")
    pairs = _brief(pairs.filter(F.least("n_a", "n_b") >= F.lit(p.similarity) * F.greatest("n_a", "n_b")).select("a", "b"), "pairs")
    links = written(_verified(pairs, texts, p), "links")
    labels = components(links)
    more = _block_links(members, labels, texts, p)
    grouped = nodes.select(F.col("number").alias("n"), "node", "id", "stand", "rows").join(labels.withColumnRenamed("node", "n"), "n", "left").withColumn("label", F.coalesce("label", "n"))
    if not more.isEmpty():
        wider = _joined(more, labels).select(F.col("node").alias("label"), F.col("label").alias("whole"))
        grouped = grouped.join(wider, "label", "left").withColumn("label", F.coalesce("whole", "label")).drop("whole")
    grouped = _brief(grouped, "grouped")
    classes = grouped.groupBy("label").agg(F.min("id").alias("class_id"), F.sum("rows").alias("class_rows"), F.min("stand").alias("stand")).filter("class_rows > 1")
    classes = classes.select("label", "class_id", "class_rows", _key(F.col("stand.id")).alias("stand_k"), F.col("stand.h").alias("stand_h"))
    of_node = _brief(grouped.select("node", "label").join(classes, "label").drop("label"), "classes")
    rows = _brief(signed.select("id", "h", "node"), "rows")
    release(signed, nodes, buckets, members, needed, texts, pairs, links, more, grouped)
    return rows, of_node


def near_duplicates(docs: DataFrame, p: Params | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, class_id, class_rows): one row for each of the input; class_id is the class's least id."""
    rows, of_node = _classified(docs, p or Params(), id_col, text_col)
    out = rows.join(of_node, "node", "left")
    return out.select(F.col("id").alias(id_col), F.when(F.col("class_rows").isNull(), F.col("id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("class_rows", F.lit(1)).alias("class_rows"))


def keep_one(docs: DataFrame, p: Params | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each class, all columns: one that holds its least id (rows without an id come last) and, of the texts of that id, the one of least hash.

    Rows outside of classes of several rows stay where they are: only those that
    a filter can't tell from rows of such classes meet them in a shuffle.
    """
    p = p or Params()
    rows, of_node = _classified(docs, p, id_col, text_col)
    k = _key(F.col("id"))
    met = rows.join(of_node, "node").groupBy(k.alias("_k"), F.col("h").alias("_h")).agg(F.count("*").alias("_times"), F.max((k == F.col("stand_k")) & (F.col("h") == F.col("stand_h"))).alias("_stands"))
    met = _brief(met, "met")
    free = lambda c: next(x for x in (f"{c}{j or ''}" for j in range(len(docs.columns) + 1)) if x not in docs.columns)
    met = met.toDF(*(names := [free(c) for c in met.columns]))
    fk, fh, times, stands = names
    key, text_hash = _key(F.col(id_col)), F.xxhash64(text_col)
    test = among(met.select(F.xxhash64(fk, fh).alias("x")), p.filter_bits)
    maybe = test(F.xxhash64(key, text_hash))
    alone = docs.filter(~maybe)
    looked_up = docs.filter(maybe).withColumns({fk: key, fh: text_hash}).join(met.hint("merge"), [fk, fh], "left")  # the same plan at every size
    kept = looked_up.filter(F.col(stands).isNull() | (F.col(stands) & (F.col(times) == 1))).select(*docs.columns)
    out = alone.unionAll(kept)
    if met.filter((F.col(times) > 1) & F.col(stands)).isEmpty():
        return out
    return out.unionAll(looked_up.filter(F.col(stands) & (F.col(times) > 1)).select(*docs.columns).dropDuplicates([id_col, text_col]))


def brute_force(texts: list[str | None], p: Params | None = None) -> list[list[float]]:
    """All pairs' weighted Jaccard similarities, for tests."""
    import re
    from collections import Counter

    p = p or Params()

    def bag(t: str | None) -> Counter:
        w = re.findall(r"[^\W_]+", (t or "").lower())
        return Counter(tuple(w[k : k + p.words]) for k in range(max(1, len(w) - p.words + 1))) if w else Counter()

    bags = [bag(t) for t in texts]
    return [[(lambda i, u: i / u if u else 0.0)(sum((x & y).values()), sum((x | y).values())) for y in bags] for x in bags]

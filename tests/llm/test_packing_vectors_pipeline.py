import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from digitsort.llm import bagminhash, packing, queries, vector_tree

from .conftest import ODD

PATH = P.path("byte_bpe_50k.json")


def ids_of(text):
    t = Tokenizer.from_file(PATH)
    t.encode_special_tokens = True
    return np.array([*t.encode(text or "", add_special_tokens=False).ids, 0], "<u4")


def check_pieces(rows, docs, window=1024, crc=False):
    """Every id in one piece, windows gapless and not too long; returns the share of padding."""
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append(r)
    assert set(by_doc) == {i for i, _ in docs}
    for i, found in by_doc.items():
        copies = [t for j, t in docs if j == i]
        ids = ids_of(copies[0])
        assert sum(r["length"] for r in found) == len(ids) * len(copies)
        for r in found:
            part = ids[r["start"] : r["start"] + r["length"]]
            assert r["doc_tokens"] == len(ids) and len(part) == r["length"] > 0
            assert (zlib.crc32(part.tobytes()) == r["ids_crc32"]) if crc else (part.tobytes() == bytes(r["ids"]))
        if len(copies) == 1:
            spans = sorted((r["start"], r["length"]) for r in found)
            assert all(a[0] + a[1] == b[0] for a, b in zip(spans, spans[1:], strict=False))
    total = 0
    for found in by_seq.values():
        at = 0
        for r in sorted(found, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= window
        total += at
    return 1 - total / (window * len(by_seq))


def test_packing_odd_rows(docs_of):
    docs = docs_of(ODD)
    check_pieces(packing.pack(docs, PATH).collect(), ODD)
    assert packing.pack(docs.limit(0), PATH).count() == 0


def test_packing_whole_table(spark, sf):
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert check_pieces(queries.op8_packing(spark, sf).collect(), docs, crc=True) < 0.05


def test_bm25_scores():
    rng = random.Random(1)
    rests = [np.array([rng.randrange(1, 40) for _ in range(rng.randrange(1, 30))], "<u4") for _ in range(20)]
    df = np.array([sum(t in r for r in rests) for t in range(40)])
    idf = np.log((20 - df + 0.5) / (df + 0.5))
    p = packing.Params()
    shard = packing.Shard(rests, idf, 12.0, p)
    for s in (0, 7):
        want = []
        for d in rests:
            score = 0.0
            for t in set(rests[s].tolist()):
                tf = int((d == t).sum())
                if tf and idf[t] > 0:
                    score += idf[t] * tf * (p.k1 + 1) / (tf + p.k1 * (1 - p.b + p.b * len(d) / 12.0))
            want.append(score)
        assert np.allclose(shard.scores(s), want)


def test_windows_take_nearest_first():
    size = np.array([600, 300, 300, 300, 100])
    near = np.array([[9, 1, 5, 2, 0.0]] * 5)
    windows = packing.fill_windows(size, lambda s: near[s], 1024)
    assert [w[0] for w in windows[0][:2]] == [0, 2] and sum(w[2] for w in windows[0]) == 1024
    assert sorted((k, a + j) for w in windows for k, a, n in w for j in range(n)) == sorted((k, j) for k, n in enumerate(size) for j in range(n))


# vectors


def brute(rows, k):
    ok = [(i, np.array(v, float)) for i, v in rows if i is not None and v is not None and None not in v and np.isfinite(np.array(v, float)).all() and any(v) and len(v) == 8]
    out = {}
    for q, v in ok:
        if q % 50 == 0:
            score = {i: float(vector_tree.cosines(v[None], w[None])[0]) for i, w in ok if i != q}
            out[q] = sorted(score.items(), key=lambda x: (-x[1], x[0]))[:k]
    return out


def test_vector_search_odd_rows(spark):
    rng = random.Random(8)
    rows = [(k, [float(np.float32(rng.gauss(0, 1))) for _ in range(8)]) for k in range(1, 260)]
    hot = [1.0, 2.0, 0.5, 0.0, -1.0, 3.0, 1.0, 1.0]
    rows += [(k, hot) for k in range(300, 420)] + [(500, hot), (550, None), (600, [0.0] * 8), (601, [float("nan")] * 8), (602, [1.0, None] + [1.0] * 6), (603, [1.0, 2.0]), (None, hot), (450, hot), (450, hot)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").selectExpr("*", "1 AS id", "2 AS leaf", "3 AS v")
    index = vector_tree.fit(df, vector_tree.Params(leaf_rows=20, block=16, recall=1.0))
    got = {}
    for r in vector_tree.search(index, df, F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    want = brute(list({(i, None if v is None else tuple(v)) for i, v in rows}), 5)
    assert set(got) == set(want)
    hits = sum(len({i for i, _ in got[q]} & {i for i, _ in want[q]}) for q in want)
    assert hits >= 0.9 * sum(map(len, want.values()))
    assert got[500] == want[500] and got[300] == want[300]  # many equal vectors: the least ids
    assert all(abs(dict(want[q]).get(i, s) - s) < 1e-12 for q in want for i, s in got[q])
    none = df.limit(0)
    assert vector_tree.search(vector_tree.fit(none), none).count() == 0
    few = df.filter("vec_id IN (50, 1)")
    assert vector_tree.search(vector_tree.fit(few), few, F.col("vec_id") % 50 == 0).count() == 1


def test_leaves_stay_of_one_size_and_queues_span_levels(spark):
    rng = np.random.default_rng(4)
    centre = rng.normal(size=(30, 8))
    v = (centre[rng.integers(0, 30, 3000)] + 0.4 * rng.normal(size=(3000, 8))).astype(np.float32)
    v[::3] = v[0]  # a third of all rows
    df = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(v)], "vec_id long, embedding array<float>")
    p = vector_tree.Params(branching=4, max_depth=1, leaf_rows=10, split_rows=60, child_rows=200, block=16, recall=0.97, first_visits=4)
    index = vector_tree.fit(df, p)
    blocks = index.rows.collect()
    assert len(index.levels) >= 2 and max(r["n"] for r in blocks) <= 60
    held = {i for r in blocks for i in r["ids"]}
    assert held == {k for k in range(3000) if k % 3} | set(range(0, 18, 3))
    want = brute([(k, x.tolist()) for k, x in enumerate(v)], 5)
    got = {}
    for r in vector_tree.search(index, df, F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert set(got) == set(want) and all(len(x) == 5 for x in got.values())
    assert sum(len(dict(got[q]).keys() & dict(want[q]).keys()) for q in want) >= 0.9 * 5 * len(want)
    assert index.visits < len({r["leaf"] for r in blocks})
    assert all(got[q] == want[q] for q in want if q % 3 == 0)


def test_vector_recall(spark):
    d = "/root/testdata/sf0.1"
    rows = {r["vec_id"]: r["embedding"] for r in spark.read.parquet(f"{d}/embeddings.parquet").collect()}
    ids, u = np.array(list(rows)), vector_tree.unit(np.array(list(rows.values()), float))
    got = {}
    for r in queries.op2_vector_tree(spark, d).collect():
        got.setdefault(r["query_id"], set()).add(r["vec_id"])
    hit = n = 0
    for k in np.flatnonzero(ids % 50 == 0):
        s = u @ u[k]
        s[k] = -9
        top = set(ids[np.lexsort((ids, -s))[:5]].tolist())
        hit, n = hit + len(top & got[int(ids[k])]), n + 5
    assert hit / n >= 0.9


def test_best_bin_first_order():
    rng = np.random.default_rng(1)
    tree = vector_tree.Tree(rng.normal(size=(2000, 8)), 64, vector_tree.Params(branching=8))
    q = vector_tree.unit(rng.normal(size=(1, 8)))[0]
    order = tree.visits(q, tree.leaves)
    assert sorted(order) == list(range(tree.leaves)) and tree.visits(q, 5) == order[:5]
    assert tree.assign(q[None])[0] in order[: max(3, tree.leaves // 8)]


# pipeline


@pytest.fixture(scope="module")
def stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = [docs.collect()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.written(stage(spark, docs, sf), "test")
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        out.append(docs.collect())
    return out


def test_pipeline_stages(spark, sf, stages):
    first, clean, known, single = stages
    kept = lambda rows: {r["doc_id"] for r in rows}
    scores = {r["doc_id"]: r["score"] for r in queries.op7_toxicity(spark, sf).collect()}
    assert kept(clean) == {i for i in kept(first) if scores[i] < 0.7}
    rejected = {r["doc_id"] for r in queries.op9_language(spark, sf).collect() if r["rejected"]}
    assert kept(known) == kept(clean) - rejected
    rows = [(r["doc_id"], r["text"]) for r in known]
    sims = bagminhash.brute_force([t for _, t in rows])
    label = list(range(len(rows)))
    for a in range(len(rows)):
        for b in range(a):
            if sims[a][b] >= 0.8 and label[a] != label[b]:
                low, high = sorted((label[a], label[b]))
                label = [low if x == high else x for x in label]
    groups = {}
    for (i, _), x in zip(rows, label, strict=True):
        groups.setdefault(x, []).append(i)
    assert kept(single) == {min(g) for g in groups.values()} and len(single) == len(groups)
    check_pieces(corpus_pipeline.run(spark, sf).collect(), [(r["doc_id"], r["text"]) for r in single], crc=True)


def test_pipeline_on_an_empty_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        assert out.count() == 0

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from digitsort.llm import bagminhash as bm
from digitsort.llm.textbatch import text_chunks

from .conftest import ODD, thue_morse


def words(rng, n):
    return [f"w{rng.randrange(5000)}" for _ in range(n)]


def classes_by_brute_force(rows, p):
    sims = bm.brute_force([t for _, t in rows], p)
    up = list(range(len(rows)))

    def root(k):
        while up[k] != k:
            k = up[k]
        return k

    for a in range(len(rows)):
        for b in range(a):
            if sims[a][b] >= p.similarity:
                up[max(root(a), root(b))] = min(root(a), root(b))
    groups = {}
    for k in range(len(rows)):
        groups.setdefault(root(k), []).append(rows[k][0])
    out = {}
    for k in range(len(rows)):
        ids = [i for i in groups[root(k)] if i is not None]
        out[k] = min(ids) if ids else None
    return out


def corpus(seed=3):
    """Exact and near copies, a chain, repeated lines, one large group about the threshold, and unlike texts."""
    rng = random.Random(seed)
    texts = [" ".join(words(rng, rng.randrange(1, 300))) for _ in range(60)]
    base = words(rng, 200)
    texts += [" ".join(base)] * 5
    for _ in range(40):  # each differs from the base by a few words, and more from each other
        w = list(base)
        for _ in range(rng.randrange(0, 6)):
            w[rng.randrange(len(w))] = f"v{rng.randrange(10**6)}"
        texts.append(" ".join(w))
    chain = words(rng, 120)
    for k in range(6):
        chain = chain[2:] + words(rng, 2)
        texts.append(" ".join(chain))
    line = " ".join(words(rng, 12))
    texts += [" ".join([line] * k) for k in (2, 3, 20, 22)]
    shared = " ".join(words(rng, 80))
    texts += [shared + " " + " ".join(words(rng, 60)) for _ in range(30)]
    rng.shuffle(texts)
    return list(enumerate(texts, 100))


@pytest.mark.parametrize("block", [128, 4])
def test_classes_are_components(docs_of, block):
    rows = corpus()
    p = bm.Params(block=block)
    got = {r["doc_id"]: r["class_id"] for r in bm.near_duplicates(docs_of(rows), p).collect()}
    want = classes_by_brute_force(rows, p)
    assert got == {rows[k][0]: c for k, c in want.items()}


def test_odd_rows(docs_of):
    rows = [*ODD, (20, bm_text := "one two three four five six seven eight nine ten " * 3), (None, bm_text), (21, "ONE two, three four five six seven eight nine ten! " * 3), (None, "only a null id")]
    out = bm.near_duplicates(docs_of(rows)).collect()
    assert len(out) == len(rows)
    by = {}
    for r in out:
        by.setdefault(r["doc_id"], []).append(r["class_id"])
    assert by[1] == [1] and by[2] == [2] and by[3] == [3]  # without words: alone
    assert by[4] == [4] and by[5] == [4, 4] and by[20] == [20] and by[21] == [20]
    assert sorted(by[None], key=str) == [20, None, None]
    kept = bm.keep_one(docs_of(rows))
    assert kept.columns == docs_of(rows).columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert ids.count(4) == 1 and 5 not in ids and 21 not in ids and ids.count(20) == 1 and 7 in ids
    assert bm.near_duplicates(docs_of(rows).limit(0)).count() == 0 and bm.keep_one(docs_of(rows).limit(0)).count() == 0


def test_repeated_representative_stays_once(docs_of):
    rows = [(1, "a b c d e f g"), (1, "a b c d e f g"), (2, "a b c d e f g"), (3, "other words here are not the same")]
    assert sorted(r["doc_id"] for r in bm.keep_one(docs_of(rows)).collect()) == [1, 3]


def test_signatures_estimate_weighted_jaccard():
    """Mean agreement over many places is the similarity: unbiased, multiplicities included."""
    rng = random.Random(1)
    a = Counter({k: rng.choice([1, 1, 2, 7, 30]) for k in range(60)})
    b = Counter({k: max(1, a[k] + rng.choice([-3, 0, 0, 5])) for k in range(20, 80)})
    true = sum((a & b).values()) / sum((a | b).values())
    slots = 6000
    doc = np.repeat([0, 1], [len(a), len(b)])
    key = np.array(sorted(a) + sorted(b), np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    sig = bm.signatures(2, doc, key, np.array([a[k] for k in sorted(a)] + [b[k] for k in sorted(b)]), slots)
    assert np.isfinite(sig).all()
    assert abs((sig[0] == sig[1]).mean() - true) < 5 * (true * (1 - true) / slots) ** 0.5


def test_signatures_do_not_depend_on_the_chunk():
    """A text's signature has the same bits alone, among few texts and among many."""
    rng, p = random.Random(5), bm.Params()
    texts = [" ".join(words(rng, rng.randrange(5, 400))) for _ in range(800)] + [" ".join(words(rng, 12) * rng.randrange(2, 40)) for _ in range(50)]

    def signed(some):
        (_, c), = text_chunks(pa.array(some))
        return bm.signatures(c.n, *bm.shingles(c, p), p.slots).view(np.uint64)

    among = signed(texts)
    for k in (*range(0, 800, 40), *range(800, 850, 5)):
        assert (signed([texts[k]])[0] == among[k]).all()
        assert (signed(texts[k - 5 : k + 1])[-1] == among[k]).all() if k >= 5 else True


def test_shingles_follow_the_definition():
    texts = ["A b c d e f", "one two", "", None, "x " * 12]
    (_, c), = text_chunks(pa.array(texts))
    doc, shingle, count = bm.shingles(c, bm.Params())
    assert np.bincount(doc, count, 5).tolist() == [2, 1, 0, 0, 8] and np.bincount(doc, minlength=5).tolist() == [2, 1, 0, 0, 1]


def test_words_with_colliding_polynomials_differ(docs_of):
    a, b = thue_morse(11)
    rows = [(1, a), (2, b), (3, a)]
    assert {r["doc_id"]: r["class_id"] for r in bm.near_duplicates(docs_of(rows)).collect()} == {1: 1, 2: 2, 3: 1}


def test_one_row_of_each_class_stays(docs_of):
    """Also where ids repeat, or are null: of an id's texts, only those that stand for a class of their own."""
    near = " ".join(f"w{k}" for k in range(200))
    rows = [(1, near), (1, near + " more"), (2, "p q r s t u v"), (2, near + " x"), (None, "only here a b c d"), (None, "only here a b c d"), (None, near), (None, "quite alone e f g h i"), (9, "z y x w v u t"), (9, "z y x w v u t")]
    kept = [(r["doc_id"], r["text"]) for r in bm.keep_one(docs_of(rows)).collect()]
    of_near = [x for x in kept if x[1].startswith("w0")]
    assert len(of_near) == 1 and of_near[0][0] == 1
    assert sorted((x for x in kept if x not in of_near), key=str) == sorted([(2, "p q r s t u v"), (None, "only here a b c d"), (None, "quite alone e f g h i"), (9, "z y x w v u t")], key=str)


def test_recall_against_all_pairs(spark):
    """All documents of a given table: links between texts at the similarity, found through classes, and no class without links."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()]
    want = classes_by_brute_force(rows, bm.Params())
    got = {r["doc_id"]: r["class_id"] for r in bm.near_duplicates(docs).collect()}
    assert got == {rows[k][0]: c for k, c in want.items()}

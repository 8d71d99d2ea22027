import hashlib

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import regex
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from digitsort.llm import byte_bpe, pretokens, unigram
from digitsort.llm.textbatch import text_chunks

from .conftest import ODD, thue_morse

PATH = P.path("byte_bpe_multi_50k.tiktoken")
PIECES = P.path("piece_bpe_32k.model")
TEXTS = st.lists(st.text(alphabet=st.one_of(st.sampled_from(" '\n\tsdmtrelvABé1９.,!　 "), st.characters(exclude_categories=["Cs", "Cn"])), max_size=60), max_size=8)


def reference():
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.read_ranks(PATH), special_tokens={})


@given(TEXTS)
@settings(max_examples=150, deadline=None)
def test_split_is_the_pattern(texts):
    pattern, got = regex.compile(P.PATTERN), []
    for _, c in text_chunks(pa.array(texts, pa.string()), 40):
        start, end, doc = pretokens.split(c)
        out = [[] for _ in range(c.n)]
        for a, b, k in zip(start, end, doc, strict=True):
            out[k].append(c.text[a:b])
        got += out
    assert got == [pattern.findall(t) for t in texts]


@given(TEXTS)
@settings(max_examples=60, deadline=None)
def test_ids_are_the_rank_files(texts):
    enc, got = reference(), []
    for _, c in text_chunks(pa.array(texts, pa.string())):
        ids, off = byte_bpe.memo(PATH).tokens(c)
        got += [ids[a:b].tolist() for a, b in zip(off[:-1], off[1:], strict=True)]
    assert got == [enc.encode_ordinary(t) for t in texts]


def test_memo_starts_anew_without_changing_results():
    t = byte_bpe.library(PATH)
    small = pretokens.IdMemo(lambda p: [e.ids for e in t.encode_batch_fast(p, add_special_tokens=False)], limit=5)
    for text in ("one two three four five six seven", "one two nine", "six seven"):
        (_, c), = text_chunks(pa.array([text]))
        assert small.tokens(c)[0].tolist() == reference().encode_ordinary(text)


def test_encode_decode(docs_of):
    docs, enc = docs_of(ODD), reference()
    encoded = byte_bpe.encode(docs, PATH, with_offsets=True)
    rows = encoded.collect()
    assert len(rows) == len(ODD)
    for r, (i, text) in zip(rows, ODD, strict=True):
        ids = np.frombuffer(r["ids"], "<u4").tolist()
        assert r["doc_id"] == i and ids == enc.encode_ordinary(text or "") and r["n_tokens"] == len(ids)
        spans = np.frombuffer(r["offsets"], "<u4").reshape(-1, 2).tolist()
        data = (text or "").encode()
        at = 0
        for k, (a, b) in zip(ids, spans, strict=True):
            size = len(enc.decode_single_token_bytes(k))
            assert (text or "").encode()[at : at + size] == enc.decode_single_token_bytes(k)
            assert len((text or "")[:a].encode()) <= at and len((text or "")[:b].encode()) >= at + size
            at += size
        assert at == len(data)
    back = byte_bpe.decode(encoded, PATH).collect()
    assert [bytes(r["decoded"]) for r in back] == [(t or "").encode() for _, t in ODD]


def test_split_characters(spark):
    ids = reference().encode_ordinary("😀日")
    assert "".join(byte_bpe.stream_text(iter(ids), PATH)) == "😀日"
    assert "".join(byte_bpe.stream_text(iter(ids[:1]), PATH)) == "�"
    df = spark.createDataFrame([(1, np.array(ids[:1], "<u4").tobytes()), (2, None)], "doc_id long, ids binary")
    rows = byte_bpe.decode(df, PATH).select("doc_id", byte_bpe.as_text(F.col("decoded")).alias("t")).collect()
    assert "�" in rows[0]["t"] and rows[1]["t"] == ""


def test_empty_table(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert byte_bpe.decode(byte_bpe.encode(none, PATH), PATH).count() == 0
    assert unigram.count_tokens(none, PIECES).count() == 0


def test_json_and_rank_file_agree():
    """One vocabulary in two formats."""
    a, b = (byte_bpe.token_bytes(P.path(f"byte_bpe_50k.{k}")) for k in ("json", "tiktoken"))
    n = min(len(a[1]), len(b[1])) - 1
    assert all(a[0][a[1][k] : a[1][k + 1]].tobytes() == b[0][b[1][k] : b[1][k + 1]].tobytes() for k in range(0, n, 7))
    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    (_, c), = text_chunks(pa.array(["Some text, with 3 parts's"]))
    assert byte_bpe.memo(P.path("byte_bpe_50k.json")).tokens(c)[0].tolist() == t.encode("Some text, with 3 parts's").ids


def brute(word: str) -> tuple[float, int]:
    scores, byte = unigram.vocabulary(PIECES)
    word = unigram.MARK + word
    best = [(0.0, 0)]
    for e in range(1, len(word) + 1):
        top = (-np.inf, 0)
        for n in range(1, e + 1):
            s, m = scores.get(word[e - n : e]), 1
            if s is None and n == 1:
                m = len(word[e - 1].encode())
                s = m * byte
            if s is not None and best[e - n][0] + s >= top[0]:
                top = (best[e - n][0] + s, best[e - n][1] + m)
        best.append(top)
    return best[-1]


def test_unigram_counts(docs_of):
    odd = [(i, t if i != 7 else t[:3000]) for i, t in ODD] + [(9, "pre prefix prefixes preface " * 3)]
    rows = unigram.count_tokens(docs_of(odd), PIECES).collect()
    for r, (i, text) in zip(rows, odd, strict=True):
        words = (text or "").split()
        found = [brute(w) for w in words]
        assert (r["doc_id"], r["n_pretokens"], r["n_tokens"]) == (i, len(words), sum(n for _, n in found))
        assert abs(r["log_prob"] - sum(s for s, _ in found)) < 1e-6


def test_trie_shares_prefixes():
    table, byte = unigram.piece_trie(PIECES)
    words = ["abc", "abd", "ab", "xyz"]
    codes = np.array([ord(c) for w in words for c in w], np.uint32)
    size = np.array([len(w) for w in words])
    _, _, nodes = unigram.trie_counts(codes, np.cumsum(size) - size, size, table, byte)
    assert nodes == len({w[:k] for w in words for k in range(1, len(w) + 1)})


def test_whole_table_digest(spark):
    from digitsort.llm import queries

    d = "/root/testdata/sf0.001"
    enc = reference()
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{d}/documents.parquet").collect()}
    for r in queries.op4_byte_bpe(spark, d).collect():
        ids = enc.encode_ordinary(texts[r["doc_id"]] or "")
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256((texts[r["doc_id"]] or "").encode()).hexdigest()


ALIKE = [*thue_morse(10), " ".join(thue_morse(10)), *thue_morse(11)]


def test_words_with_colliding_polynomials_keep_their_ids(docs_of):
    enc = reference()
    rows = byte_bpe.encode(docs_of(list(enumerate(ALIKE))), PATH, with_decoded=True).collect()
    for r, text in zip(rows, ALIKE, strict=True):
        assert np.frombuffer(r["ids"], "<u4").tolist() == enc.encode_ordinary(text) and bytes(r["decoded"]) == text.encode()


def test_words_with_colliding_polynomials_keep_their_counts(docs_of):
    rows = unigram.count_tokens(docs_of(list(enumerate(ALIKE))), PIECES).collect()
    assert [r["n_tokens"] for r in rows] == [sum(brute(w)[1] for w in t.split()) for t in ALIKE]


def test_memo_tells_spans_of_one_hash_apart(monkeypatch):
    """With a hash of one bit nearly all spans collide, inside a chunk and with entries of earlier ones."""
    monkeypatch.setattr(pretokens, "span_keys", lambda codes, start, end: ((end - start).astype(np.uint64) & np.uint64(1), np.zeros(len(start), bool)))
    t = byte_bpe.library(PATH)
    memo = pretokens.IdMemo(lambda p: [e.ids for e in t.encode_batch_fast(p, add_special_tokens=False)])
    for text in ("one two three four five six seven", "one nine two", "six seven", "one two three"):
        (_, c), = text_chunks(pa.array([text]))
        assert memo.tokens(c)[0].tolist() == reference().encode_ordinary(text)


def test_pieces_are_found_by_whole_steps():
    scores, _ = unigram.vocabulary(PIECES)
    trie, _ = unigram.piece_trie(PIECES)
    for piece in list(scores)[::37]:
        state = np.zeros(1, np.int64)
        for c in reversed(piece):
            state = trie.step(state, np.array([ord(c)]))
        assert trie.score[state[0]] == scores[piece]
    assert not any(p.strip(unigram.MARK) == "" and len(p) > 1 for p in scores)


def test_whole_table_counts(spark):
    """op6 over a whole table against the same dynamic program word by word."""
    from functools import cache

    from digitsort.llm import queries

    one = cache(brute)
    d = "/root/testdata/sf0.001"
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{d}/documents.parquet").collect()}
    rows = queries.op6_token_counts(spark, d).collect()
    assert len(rows) == len(texts)
    for r in rows:
        words = regex.split(r"\p{White_Space}+", (texts[r["doc_id"]] or ""))
        found = [one(w) for w in words if w]
        assert (r["n_pretokens"], r["n_tokens"]) == (len(found), sum(n for _, n in found))

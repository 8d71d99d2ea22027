"""Registered queries against DuckDB at the smallest scale; those over all k-mers run in the driver's gate."""

import duckdb
import numpy as np
import pandas as pd
import pyarrow as pa
import pytest

from digitsort import registry

SLOW = {"wl_kmers", "kmer_count", "kmer_count_plain", "kmer_stage1_files", "kmer_distinct", "kmer_spectrum", "kmer_packed", "suffix_array", "pattern_naive", "pattern_sorted", "pattern_prefix_sorted"}
FEW = ["adaptive_msd_orderkey", "sort_double", "sort_url", "sort_multi", "sort_nulls_last", "lsd_staged_64", "base_inplace", "counting_pass", "split_staged", "parallel_split", "chunk_plan", "team_sizes", "heavy_queue_order", "narrowing_rule", "tiny_shell", "measure_bins", "measure_moves", "staging_flushes", "ablate_narrow", "join_asof", "join_interval", "agg_rollup_bins", "win_order_check", "udaf_hist", "udtf_digits", "st_session", "st_sorted_runs", "st_late_rows", "st_window_topk", "st_static_join", "st_state", "measure_speedup", "measure_ranking", "measure_growth", "split_plain", "lsd_staged_256", "sort_array", "sort_array_nulls", "msd_topk_nulls", "msd_median", "sort_dedupe", "agg_runlength", "kernel_per_bin", "agg_approx_distinct", "agg_percentile_approx", "first_pass_sort", "ablate_chunks_sort", "ablate_chunks", "ablate_tiny_sort", "ablate_narrow_sort", "pattern_sorted", "join_range_suffix", "kmer_count"]


def rows(frame):
    def plain(v):
        if pd.isna(v):
            return None
        if isinstance(v, (float, np.floating)):
            return round(float(v), 6)
        return int(v) if isinstance(v, (int, np.integer)) and not isinstance(v, bool) else str(v)

    frame = frame[sorted(frame.columns)]
    return sorted((tuple(map(plain, r)) for r in frame.itertuples(index=False)), key=repr)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", FEW)
def test_against_duckdb(spark, sf, duck, name):
    assert rows(registry.all_queries()[name](spark, sf).toPandas()) == rows(duck.execute(registry.all_sql()[name]).df())


def test_every_sql_has_its_query():
    assert set(registry.all_sql()) <= set(registry.all_queries())
    assert SLOW <= set(registry.all_queries())


def test_kmer_stages(spark):
    from collections import Counter

    from pyspark.sql import functions as F

    from digitsort.operators import kmers

    texts = ["banana bandana" * 5, "", "short", "ananas banana"]
    k = 4
    want = Counter(t[i : i + k] for t in texts for i in range(len(t) - k + 1))
    df = spark.createDataFrame([(t[i : i + k],) for t in texts for i in range(len(t) - k + 1)], "kmer string")
    for combine in (True, False):
        assert {r["kmer"]: r["n"] for r in kmers.count(kmers.distribute(df, 16, combine)).collect()} == want
    assert df.select(F.max(kmers.pack(F.lit("ab")))).first()[0] == 1


def test_pattern_searches_agree():
    from digitsort.operators import patterns

    import random

    rng = random.Random(3)
    text = "".join(rng.choice("abcd") for _ in range(3000))
    keys = sorted(text[i : i + 16] for i in range(len(text)))
    wanted = sorted({text[i : i + 6] for i in range(0, 3000, 5)} | {"zzzzz", "aaaaa", "", "a"}, key=hash)
    truth = [sum(text.startswith(w, i) for i in range(len(text))) for w in wanted]
    first = [sum(k[: len(w)] < w for k in keys) for w in wanted]
    one, many, head = patterns.search_one_by_one(keys, wanted), patterns.search_sorted(keys, wanted), patterns.search_sorted(keys, wanted, 2)
    for found in (one, many, head):
        assert [x[1] for x in found] == truth and [x[0] for x in found] == first
    assert sum(x[2] for x in many) < sum(x[2] for x in one)


@pytest.mark.parametrize("how,prefix,parts", [("naive", None, 4), ("sorted", None, 4), ("sorted", 3, 1), ("sorted", None, None)])
def test_patterns_of_any_length(spark, how, prefix, parts):
    from digitsort.operators import patterns

    texts = ["abra cadabra " * 20, "é" * 70, "", None, "x"]
    asked = ["a", "", "abr", "é" * 33, "cadabra abra" * 3, ("abra cadabra " * 20)[:100], "zz", "x", None, "é", "a"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["pattern"]: r for r in patterns.search(docs, spark.createDataFrame([(x,) for x in asked], "pattern string"), how, prefix, parts).collect()}
    suffixes = sorted(t[i:] for t in texts if t for i in range(len(t)))
    for x in set(asked) - {None}:
        n = sum(s.startswith(x) for s in suffixes)
        low = sum(s[: len(x)] < x for s in suffixes)
        assert (got[x]["occurrences"], got[x]["low"]) == (n, low if n else None)
    assert len(got) == len(set(asked)) - 1
    one = spark.createDataFrame([("x",)], "pattern string")
    assert [tuple(r)[:2] for r in patterns.search(docs.filter("doc_id = 4"), one, how, prefix, parts).collect()] == [("x", 1)]
    assert [tuple(r)[:2] for r in patterns.search(docs.limit(0), one, how, prefix, parts).collect()] == [("x", 0)]
    assert patterns.search(docs, one.limit(0), how, prefix, parts).count() == 0


def test_sorted_patterns_take_fewer_probes(spark, sf):
    found = {r["how"]: r for r in registry.all_queries()["pattern_probes"](spark, sf).collect()}
    assert found["sorted"]["probes"] < found["naive"]["probes"] and len({r["occurrences"] for r in found.values()}) == 1


def test_every_kmer_is_packed(spark):
    from digitsort.operators import kmers

    code = lambda t: int("".join(str((ord(c) + 3) % 4) for c in t), 4)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    texts = ["abcdABCD", "a b, 12.", "日本語 é\n😀", "d" * 31]
    df = spark.createDataFrame([(t,) for t in texts], "kmer string")
    assert [r[0] for r in df.select(kmers.pack(df.kmer)).collect()] == [code(t) for t in texts]
    wide = ["d c" * 21 + "é", "d" * 64, "ab" * 16, "x y" * 11]
    df = spark.createDataFrame([(t,) for t in wide], "kmer string")
    assert [tuple(r[0]) for r in df.select(kmers.pack_wide(df.kmer)).collect()] == [(signed(code(t[:32])), signed(code(t[32:] or "a"))) for t in wide]
    with pytest.raises(Exception, match="more than 31"):
        df.select(kmers.pack(df.kmer)).collect()


@pytest.mark.parametrize("name", ["kmer_packed", "kmer_packed_all"])
def test_packed_against_duckdb(spark, sf, duck, name):
    assert rows(registry.all_queries()[name](spark, sf).toPandas()) == rows(duck.execute(registry.all_sql()[name]).df())


def test_suffixes_are_ordered_by_their_whole_text(spark):
    from digitsort.operators import patterns

    texts = ["ab" * 40, "x" + "ab" * 40 + "a", "zé" * 5, "", "ab" * 40]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = sorted((t[i:].encode(), d, i) for d, t in enumerate(texts) for i in range(len(t)))
    got = {(r["doc_id"], r["at"]): r["rank"] for r in patterns.whole_suffix_array(docs, 4).collect()}
    assert got == {(d, i): k for k, (_, d, i) in enumerate(want)}
    cut = {(r["doc_id"], r["at"]): r["rank"] for r in patterns.suffix_array(docs, 4).collect()}
    assert cut != got  # the prefix alone does not order them


@pytest.mark.parametrize("combine", [True, False])
def test_kmers_of_whole_texts(spark, combine):
    from collections import Counter
    import hashlib

    from digitsort.operators import kmers

    texts = ["banana bandana" * 5, "", None, "short", "日本語é" * 30, "né à la façon 😀" * 9, "😀" * 40, "a", "banana bandana" * 5]
    docs = spark.createDataFrame([(t,) for t in texts], "text string").coalesce(1)
    for k in (1, 4, 16, 33):
        want = Counter(t[i : i + k] for t in texts if t for i in range(len(t) - k + 1))
        stored = kmers.distribute_texts(docs, k, combine)
        got = kmers.count_texts(stored, k).collect()
        assert {r["kmer"]: r["n"] for r in got} == want and len(got) == len(want)
        assert all(r["bin"] == int(hashlib.md5(r["kmer"].encode()).hexdigest()[:4], 16) % 256 for r in got)
        bins = {r["bin"]: r for r in kmers.bins_of(stored, k).collect()}
        assert {b: r["last_kmer"] for b, r in bins.items()} == {b: max(x["kmer"] for x in got if x["bin"] == b) for b in {x["bin"] for x in got}}
        assert sum(r["rows"] for r in bins.values()) == sum(want.values()) and sum(r["once"] for r in bins.values()) == sum(n == 1 for n in want.values())
        assert {r["n"]: r["kmers"] for r in kmers.spectrum(stored, k).collect()} == Counter(want.values())
    assert kmers.bins_of(kmers.distribute_texts(docs.limit(0))).count() == 0


def test_stage_one_stores_less_than_its_kmers(spark, sf):
    from pyspark.sql import functions as F

    from digitsort.operators import kmers

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stored = kmers.distribute_texts(docs).agg(F.sum(F.length("data"))).first()[0]
    assert stored < 4 * docs.agg(F.sum(F.length("text"))).first()[0]  # a row a k-mer took more than 16 bytes each


def test_counts_beyond_memory_go_to_files(monkeypatch):
    from collections import Counter

    from digitsort.operators import runs

    monkeypatch.setattr(runs, "CHUNK", 100)
    rng, counts, want = np.random.default_rng(5), runs.Counts(150), Counter()
    for _ in range(30):
        x, y = rng.integers(0, 40, 60).astype(np.uint64), rng.integers(0, 10, 60).astype(np.uint64)
        counts.add([x, y], np.ones(60, np.int64))
        want.update(zip(x.tolist(), y.tolist(), strict=True))
    found = [z for key, n in counts.result() for z in zip(key[0].tolist(), key[1].tolist(), n.tolist(), strict=True)]
    assert counts.files and len(found) == len(want) and {(a, b): n for a, b, n in found} == want
    x, y = rng.integers(0, 3, 500).astype(np.uint64), rng.integers(0, 5, 500).astype(np.uint64)
    key, n = runs.added([x, y], np.ones(500, np.int64), head=np.zeros(500, np.uint64))  # all of one hash
    assert dict(zip(zip(key[0].tolist(), key[1].tolist(), strict=True), n.tolist(), strict=True)) == Counter(zip(x.tolist(), y.tolist(), strict=True))


def test_no_suffix_moves(spark, monkeypatch):
    from digitsort.operators import patterns, runs, sorts

    monkeypatch.setattr(sorts, "adaptive_msd", None)  # a row a suffix went through the sort of a table
    texts = ["abcabcabd" * 30, "日本" * 20]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    asked = ["abc", "本日本", "abd" + "abc" * 2, "abd" * 2]
    got = patterns.searches(docs, spark.createDataFrame([(x,) for x in asked], "pattern string"), [("naive", None), ("sorted", 2)]).collect()
    assert {(r["way"], r["pattern"]): r["occurrences"] for r in got} == {(w, x): sum(t.startswith(x, i) for t in texts for i in range(len(t))) for w in (0, 1) for x in asked}
    for longest in (1, 7, 50, 1000):  # suffixes of texts cut into chunks are all there, and in order
        heads = []
        for chunk in runs.chunks([pa.array(texts)], longest - 1, 64):
            of = patterns.Heads(*chunk, longest)
            heads += (mine := [of[i] for i in range(len(of))])
            assert mine == sorted(mine)
        assert sorted(heads) == sorted(t[i : i + longest] for t in texts for i in range(len(t)))


@pytest.mark.parametrize("name", ["gen_uniform", "src_generator"])
def test_generated_keys_are_those_of_events(spark, sf, duck, name):
    found = registry.all_queries()[name](spark, sf)
    assert "events.parquet" in found._jdf.queryExecution().toString()
    assert rows(found.toPandas()) == rows(duck.execute(registry.all_sql()[name]).df())


@pytest.mark.parametrize("name", ["measure_speedup", "measure_ranking", "measure_growth"])
def test_measures_read_lineitem(spark, sf, name):
    found = registry.all_queries()[name](spark, sf)
    assert "lineitem.parquet" in found._jdf.queryExecution().toString() and found.count()


@pytest.mark.parametrize("part", [1 << 22, 40])
def test_kmers_sorted_as_packed_words(spark, monkeypatch, part):
    """Also where prefixes are too many for a partition and are counted again by their next characters."""
    from collections import Counter

    from digitsort.operators import packed

    monkeypatch.setattr(packed, "PART", part)
    texts = ["banana bandana" * 5, "", None, "short", "日本語é" * 30, "né à la façon 😀" * 9, "😀" * 40, "a", "banana bandana" * 5]
    docs = spark.createDataFrame([(t,) for t in texts], "text string").coalesce(1)
    for k in (1, 4, 16, 33):
        every = sorted(t[i : i + k] for t in texts if t for i in range(len(t) - k + 1))
        got = packed.kmers(docs, k).collect()
        n = Counter(every)
        assert [(r["kmer"], r["n"], r["pos"]) for r in sorted(got, key=lambda r: r["pos"])] == [(x, n[x], every.index(x)) for x in sorted(n)]
        sums = {r["first"]: (r["n"], r["low"], r["high"], r["sum_pos"]) for r in packed.by_first(docs, k).collect()}
        where = {c: [i for i, x in enumerate(every) if x[0] == c] for c in {x[0] for x in every}}
        assert sums == {c: (len(w), w[0], w[-1], sum(w)) for c, w in where.items()}
    used = packed.alphabet(docs)
    borders, total = packed.plan(docs, 4, used, 5, 1)
    assert total == sum(max(0, len(t) - 3) for t in texts if t) and (part > 40 or len(borders) > 3 and max(map(len, borders)) == 4)
    assert packed.by_first(docs.limit(0)).count() == 0


def test_wl_kmers_moves_less_than_its_kmers(spark, sf, duck):
    from pyspark.sql import functions as F

    from digitsort.operators import packed

    assert rows(registry.all_queries()["wl_kmers"](spark, sf).toPandas()) == rows(duck.execute(registry.all_sql()["wl_kmers"]).df())
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    moved = packed.sort(docs, 16)[0].agg(F.sum(F.length("data"))).first()[0]
    assert moved < 8 * docs.agg(F.sum(F.length("text"))).first()[0]  # a row a k-mer took more than 16 bytes each


@pytest.mark.parametrize("k", [4, 33])
def test_suffixes_ranked_where_they_are(spark, monkeypatch, k):
    """Also where texts are cut into several runs, ties lie in several of them, and ids come in no order."""
    from digitsort.operators import patterns, sorts, suffixes

    monkeypatch.setattr(sorts, "adaptive_msd", None)  # a row a suffix went through the sort of a table
    monkeypatch.setattr(suffixes, "RUN", 70)
    monkeypatch.setattr(suffixes, "PART", 64)
    monkeypatch.setattr(suffixes, "EACH", 2)
    texts = ["ab" * 40, "x" + "ab" * 40 + "a", "zé 日本😀" * 9, "", None, "ab" * 40, "b"] + (["".join(map(chr, range(0x400, 0x540)))] if k == 4 else [])
    docs = spark.createDataFrame([(97 * i % 11, t) for i, t in enumerate(texts)], "doc_id long, text string")
    want = sorted((t[i : i + k], 97 * d % 11, i) for d, t in enumerate(texts) if t for i in range(len(t)))
    got = [(r["rank"], r["doc_id"], r["at"]) for r in patterns.suffix_array(docs, k).collect()]
    assert sorted(got) == [(rank, d, i) for rank, (_, d, i) in enumerate(want)]
    assert patterns.suffix_array(docs.limit(0), k).count() == 0


def test_whole_suffixes_ranked_where_they_are(spark, monkeypatch):
    """Suffixes equal in other runs, and ends of texts within longer ones."""
    from digitsort.operators import patterns, sorts, suffixes

    monkeypatch.setattr(sorts, "adaptive_msd", None)  # a row a suffix went through the sort of a table, again in each step
    monkeypatch.setattr(suffixes, "RUN", 70)
    monkeypatch.setattr(suffixes, "PART", 64)
    monkeypatch.setattr(suffixes, "EACH", 2)
    texts = ["ab" * 40, "x" + "ab" * 40 + "a", "zé 日本😀" * 9, "", None, "ab" * 40, "abab", "b", "é 日本😀"]
    docs = spark.createDataFrame([(97 * i % 11, t) for i, t in enumerate(texts)], "doc_id long, text string")
    want = sorted((t[i:], 97 * d % 11, i) for d, t in enumerate(texts) if t for i in range(len(t)))
    got = [(r["rank"], r["doc_id"], r["at"]) for r in patterns.whole_suffix_array(docs, 4).collect()]
    assert sorted(got) == [(rank, d, i) for rank, (_, d, i) in enumerate(want)]
    assert patterns.whole_suffix_array(docs.limit(0)).count() == 0


@pytest.mark.parametrize("name", ["suffix_array", "suffix_array_whole"])
def test_suffix_array_sums(spark, sf, duck, name):
    assert rows(registry.all_queries()[name](spark, sf).toPandas()) == rows(duck.execute(registry.all_sql()[name]).df())


def test_whole_suffixes_by_chosen_places(spark, monkeypatch):
    """Long repeats take few steps, where each doubling took one; also over several ranges, with one character only, short texts, many letters."""
    from digitsort.operators import patterns, suffixes, whole

    monkeypatch.setattr(suffixes, "RUN", 3000)
    monkeypatch.setattr(suffixes, "PART", 2048)
    monkeypatch.setattr(suffixes, "EACH", 1)
    made = []
    monkeypatch.setattr(whole, "written", lambda df, name: made.append(name) or suffixes.written(df, name))
    rng = np.random.default_rng(3)
    long = "".join(rng.choice(list("abc d"), 1500))
    texts = [long, "x" + long, "a" * 900, long, "short", "", None, "ab", "日本" + long[700:], "a" * 40, long[:600] + "z"]
    many = ["".join(map(chr, rng.integers(0x4E00, 0x4E00 + 400, 300))), "".join(map(chr, range(0x4E00, 0x4E00 + 400)))]
    for n, t in enumerate((texts, many + many, ["a", "b", "a"])):
        made.clear()
        docs = spark.createDataFrame(list(enumerate(t)), "doc_id long, text string")
        want = sorted((x[i:], d, i) for d, x in enumerate(t) if x for i in range(len(x)))
        got = [(r["rank"], r["doc_id"], r["at"]) for r in patterns.whole_suffix_array(docs).collect()]
        assert sorted(got) == [(rank, d, i) for rank, (_, d, i) in enumerate(want)]
        assert made.count("places") <= 5  # 1,500 characters: 7 doublings of 16 characters
        if n == 0:
            assert made.count("ranked") > 1


def test_equal_characters_choose_alike(monkeypatch):
    from digitsort.operators import whole
    from digitsort.operators.suffixes import Letters
    from digitsort.operators.whole import Chosen

    monkeypatch.setattr(whole, "BLOCK", 64)
    rng = np.random.default_rng(5)
    for k, letters in ((16, 3), (16, 40), (5, 2), (2, 2)):
        texts = [rng.integers(0, letters, n) for n in (400, k - 1, k, 300)]
        codes, lengths = np.concatenate(texts), np.array([len(t) for t in texts])
        of = Letters(np.arange(letters), k)
        ranks, own = of.padded(codes, lengths, lengths)
        chosen = Chosen(of, ranks, lengths)
        on, to = np.cumsum(chosen.turns) - 1, {}
        for p in np.flatnonzero(own):
            if ranks[p + k - 1]:
                step = chosen.at[on[p]] - p
                assert 0 <= step < k and to.setdefault(ranks[p : p + k].tobytes(), step) == step
        for i, jump in enumerate(chosen.jumps):
            p = chosen.at[i]
            assert bool(jump) == (chosen.left[i] > k) and (not jump or chosen.at[i + jump] == chosen.at[on[p + 1]] > p)

"""Training-data operators against brute force on small tables, edge cases included."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import same_rows
from tallquant.llm import decontaminate, hmm, jaccard, langid, licenses, mtree, packing, queries, sstable, substring, warc_audit
from tallquant.llm.common import WordEncoder, Workspace, alnum_words, blank_words, components, default_tokenizer

DOC = "doc_id long, text string, lang string, source string, n_chars long, key string, node string, dest string, own string"


def frame(spark, texts, ids=None):
    """Documents with clashing extra columns."""
    ids = ids if ids is not None else list(range(len(texts)))
    return spark.createDataFrame([(i, t, "en", "s", 0, "k", "n", "d", "o") for i, t in zip(ids, texts, strict=True)], DOC)


def words(rng, n, vocab=40):
    return " ".join(f"w{rng.randrange(vocab)}" for _ in range(n))


def odd_texts():
    rng = random.Random(5)
    base = [words(rng, n, 400) for n in (3, 12, 13, 14, 40, 60, 200, 900)]
    edited = base[6].split()
    edited[50] = "changed"
    return [*base, base[6], base[6], " ".join(edited), base[7] + " tail", base[4] + "\n" + base[5], "", None, " \t\n ", "x", "x y", "X  Y", base[4].upper(), "é ü 漢字   b", "!!! ???", "a" * 5000, (words(rng, 20, 9) + " ") * 60]


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_against_sql(spark, small, duck, name):
    got, want = same_rows(queries.QUERIES[name](spark, small), duck, queries.ORACLE_SQL[name])
    assert got == want


# --- shared helpers -----------------------------------------------------------------


def test_word_classes():
    raw = "Ab,c\x0bD\x1c1-é Ü\x85z".encode()
    assert [w.decode() for w in blank_words(raw)] == re.findall(r"[^\x20\x09-\x0D]+", raw.decode())
    lower = "".join(c.lower() if "A" <= c <= "Z" else c for c in raw.decode())
    assert [w.decode() for w in alnum_words(raw)] == re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower)


def test_encoder_equals_library(spark, small):
    texts = [r.text for r in spark.read.parquet(f"{small}/documents.parquet").limit(60).collect()]
    texts += ["don't  <|endoftext|>x <|ENDOFTEXT|> ÀÉ z q \x1c w", "ΑΣ ΟΔΟΣ", "á b́", "a\0b c\0", "A. b, C., D'. 's", "  ", "", "ﬁne ǅ İx straße ÿ ÷ß", "x" * 3000]
    encoder = WordEncoder(default_tokenizer(), limit=500)
    got = [x for i in range(0, len(texts), 7) for x in encoder.encode([t.encode() for t in texts[i : i + 7]])]
    assert [x.tolist() for x in got] == [encoder.lib.encode(t, add_special_tokens=False).ids for t in texts]
    assert encoder.encode([None])[0].tolist() == []


def test_components(spark):
    edges = [(1, 2), (2, 3), (5, 4), (9, 8), (8, 7), (7, 6), (6, 5), (3, 3)]
    out = components(spark, spark.createDataFrame(edges, "a long, b long"), Workspace(spark, "t"))
    assert {r.node: r.component for r in out.collect()} == {1: 1, 2: 1, 3: 1, **dict.fromkeys(range(4, 10), 4)}
    assert components(spark, spark.createDataFrame([], "a long, b long"), Workspace(spark, "t")).count() == 0


# --- 1 search -----------------------------------------------------------------------


def brute_top(vectors, asks, k):
    out = []
    for q, a in vectors:
        if asks(q):
            scored = sorted(((-sum(x * y for x, y in zip(a, b, strict=False)), i) for i, b in vectors if i != q))[:k]
            out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    return sorted(out)


@pytest.mark.parametrize("tree_rows, block", [(8192, 4096), (40, 3)])
def test_search_is_exact(spark, tree_rows, block):
    rng = np.random.default_rng(1)
    x = rng.integers(-60, 60, (300, 8))
    x[50:90] = x[7]  # ties
    x[0] = 0
    vectors = [(int(i), [int(v) for v in row]) for i, row in enumerate(x)]
    df = spark.createDataFrame(vectors, "vec_id long, v array<long>")
    got = mtree.top_k(spark, df, F.col("vec_id") % 10 == 0, k=5, tree_rows=tree_rows, query_block=block)
    assert sorted(map(tuple, got.collect())) == brute_top(vectors, lambda q: q % 10 == 0, 5)


def test_search_edges(spark):
    rows = [(0, [0.5, 0.25]), (1, None), (2, [float("nan"), 1.0]), (3, [None, 1.0]), (4, [float("inf"), 0.0]), (50, [0.1, -0.1]), (None, [1.0, 1.0]), (7, [-0.3, 0.9])]
    emb = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("v", F.lit("clash"))
    vectors = mtree.integer_vectors(emb)
    assert sorted(r.vec_id for r in vectors.where("vec_id is not null").collect()) == [0, 7, 50]
    got = sorted(map(tuple, mtree.top_k(spark, vectors, F.col("vec_id") % 50 == 0).collect()))
    assert got == brute_top([(0, [128, 64]), (7, [math.floor(256 * np.float32(-0.3)), math.floor(256 * np.float32(0.9))]), (50, [math.floor(256 * np.float32(0.1)), math.floor(256 * np.float32(-0.1))])], lambda q: q % 50 == 0, 5)
    assert mtree.top_k(spark, vectors.where("false"), F.lit(True)).count() == 0


def test_search_of_repeated_rows_and_clashing_columns(spark):
    """Repeated identifiers and rows are candidates each; an identifier asks once, with its smallest vector."""
    rng = np.random.default_rng(3)
    rows = [(int(i), [int(v) for v in rng.integers(-9, 9, 4)]) for i in range(60)]
    rows += [(10, [1, 2, 3, 4])] * 3 + [(12, [1, 2, 3, 4])] * 90 + [(13, [5, 5])]
    df = spark.createDataFrame([(i, v, 1, 2, 3.0, 0, "x") for i, v in rows], "vec_id long, v array<long>, row int, tree int, norm2 double, score int, rank string")
    got = [tuple(r) for r in mtree.top_k(spark, df, F.col("vec_id") % 10 == 0, k=5, tree_rows=20, query_block=2).collect()]
    want = []
    for q in sorted({i for i, _ in rows if i % 10 == 0}):
        a = min(v for i, v in rows if i == q)
        scored = sorted((-sum(x * y for x, y in zip(a, b, strict=False)), i) for i, b in rows if i != q)[:5]
        want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    assert sorted(got) == want


@pytest.mark.parametrize("scale", [2**20, 2**27, 2**40])
def test_search_of_large_components(spark, scale):
    """Exact where a float product is not; a score beyond a long counts as the nearest long."""
    rng = np.random.default_rng(4)
    x = rng.integers(-scale, scale, (120, 6))
    x[7] = x[3]
    x[8] = x[3] + [1, 0, 0, 0, 0, -1]
    rows = [(int(i), [int(v) for v in r]) for i, r in enumerate(x)] + [(500, [1, 1, 0, 0, 0, 0]), (510, [0, 1, 0, 0, 0, 0])]
    df = spark.createDataFrame(rows, "vec_id long, v array<long>")
    got = [tuple(r) for r in mtree.top_k(spark, df, F.col("vec_id") % 10 == 0, k=5, tree_rows=30).collect()]
    want, most = [], 2**63 - 1
    for q, a in rows:
        if q % 10 == 0:
            scored = sorted((-max(-most, min(most, sum(x * y for x, y in zip(a, b, strict=True)))), i) for i, b in rows if i != q)[:5]
            want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    assert sorted(got) == sorted(want)
    big = spark.createDataFrame([(0, [1e300, -1e300]), (1, [3e7, 0.5]), (50, [0.1, -0.1])], "vec_id long, embedding array<double>")
    assert mtree.top_k(spark, mtree.integer_vectors(big), F.col("vec_id") % 50 == 0).count() == 4


# --- 2 language model ----------------------------------------------------------------


def test_hmm_is_a_distribution():
    """Likelihoods of all sequences over a tiny alphabet add up to one less the longer ones."""
    rng = np.random.default_rng(0)
    moves, emits = rng.random((4, 4)), rng.random((3, 4))
    chain = hmm.maximise(moves, emits, np.array([0.5, 0.3, 0.2]))
    from itertools import product

    def brute(seq):
        state = np.array([0, 0, 0, 1.0])
        for s in seq:
            state = (state @ chain.move) * chain.emit[s]
        return math.log10(state.sum())

    texts = [np.array([*p, 2]) for n in range(5) for p in product((0, 1), repeat=n)]
    scores = chain.score(texts, n_lanes=7)
    assert scores == pytest.approx([brute(t) for t in texts], abs=1e-9)
    mass = [(10.0 ** chain.score([np.array([*p, 2]) for n in range(m) for p in product((0, 1), repeat=n)])).sum() for m in (3, 6, 9, 12)]
    assert 0 < mass[0] < mass[1] < mass[2] < mass[3] < 1 and mass[3] > 0.7


def test_baum_welch_raises_likelihood():
    rng = np.random.default_rng(2)
    texts = [np.append(np.repeat(rng.integers(0, 2), 8) * 3 + rng.integers(0, 3, 8), 6) for _ in range(200)]
    prior = np.bincount(np.concatenate(texts), minlength=7) / sum(map(len, texts))
    chain, last = hmm.first_chain(prior, 3), -np.inf
    for _ in range(8):
        now = chain.score(texts).sum()
        assert now >= last - 1e-3 * abs(now)
        last = now
        chain = hmm.maximise(*chain.expect(texts), prior, strength=0.01)
    alone = sum(math.log10(prior[s]) for t in texts for s in t)
    assert chain.score(texts).sum() > 0.75 * alone


def test_hmm_trains_every_round_on_every_text(spark):
    """The chain equals rounds over all texts, however many, short or long they are."""
    rng = random.Random(9)
    texts = [" ".join(rng.choice("abcde") for _ in range(n)) for n in [3, 4500, *[25] * 60]]
    lex = hmm.Lexicon([c.encode() for c in "abcde"], np.array([900] * 5), 5, np.zeros(2, dtype=np.int64), np.zeros(2, dtype=np.int64), 4600, 6, 3000)
    symbols = hmm.Coder(lex).symbols([blank_words(t.encode(), lower=True) for t in texts])[0]
    coded = spark.createDataFrame([(i, len(x), bytearray(x.astype("<u2").tobytes())) for i, x in enumerate(symbols)], "uid long, n_tokens long, symbols binary")
    want = hmm.first_chain(lex.unigram(), 3)
    for _ in range(12):
        want = hmm.maximise(*want.expect(symbols), lex.unigram())
    got = hmm.train(spark, coded, lex, states=3)
    assert got.move == pytest.approx(want.move, abs=1e-3) and got.emit == pytest.approx(want.emit, abs=1e-3)


def test_hmm_query(spark, small):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    counts = Counter()
    for i, t in docs.items():
        if zlib.crc32(str(i).encode()) % 10:
            counts.update(blank_words(t.encode(), lower=True))
            counts[b"<end>"] += 1
    n, v = sum(counts.values()), len(counts)
    rows = queries.op2_hmm_score(spark, small).collect()
    assert len(rows) == len(docs)
    for r in rows:
        ws = [*blank_words(docs[r.doc_id].encode(), lower=True), b"<end>"]
        assert r.base_score == pytest.approx(sum(math.log10((counts[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws), rel=1e-9)
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(ws), sum(counts[w] > 0 for w in ws), n)
    held = [r for r in rows if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_hmm_small_lists_and_edges(spark):
    texts = odd_texts()
    scored = hmm.score_texts(spark, frame(spark, texts), F.col("doc_id") % 3 != 0, listed=150, symbols=3, classes=4).collect()
    whole = hmm.score_texts(spark, frame(spark, texts), F.col("doc_id") % 3 != 0, listed=10_000, symbols=3, classes=4).collect()
    a, b = ({r.doc_id: r for r in x} for x in (scored, whole))
    assert len(a) == len(texts)
    for i, r in a.items():
        assert r.score == pytest.approx(b[i].score, abs=1e-6) and r.base_score == pytest.approx(b[i].base_score, abs=1e-6) and r.n_known == b[i].n_known
    assert a[14].n_tokens == 1
    nothing = hmm.score_texts(spark, frame(spark, ["a b", None]), F.lit(False)).collect()
    assert all(r.n_known == 0 and r.train_tokens == 0 and math.isfinite(r.score) for r in nothing)
    assert hmm.score_texts(spark, frame(spark, []), F.lit(True)).count() == 0


def test_hmm_scores_of_documents(spark, small):
    """Every document's score against the forward recursion in plain Python, one long text included."""
    rng = random.Random(3)
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").limit(40).union(spark.createDataFrame([(10**6, words(rng, 60_000, 700))], "doc_id long, text string"))
    kept = {}
    original = hmm.train
    try:
        hmm.train = lambda *a, **k: kept.setdefault("chain", original(*a, **k | {"passes": 2}))
        rows = hmm.score_texts(spark, docs, F.lit(True), states=3, symbols=50, classes=4).collect()
    finally:
        hmm.train = original
    chain, texts = kept["chain"], {r.doc_id: r.text for r in docs.collect()}
    counts = Counter(w for t in texts.values() for w in blank_words(t.encode(), lower=True))
    listed = [w for w, _ in sorted(counts.items(), key=lambda x: (-x[1], x[0].decode()))][:50]
    total, types = Counter(), Counter()
    for w, c in counts.items():
        if w not in listed:
            total[hmm.ending_class(w, 4)] += c
            types[hmm.ending_class(w, 4)] += 1
    assert len(rows) == 41
    for r in rows:
        state, score = [0.0, 0.0, 0.0, 1.0], 0.0
        for w in [*blank_words(texts[r.doc_id].encode(), lower=True), None]:
            k = 54 if w is None else listed.index(w) if w in listed else 50 + hmm.ending_class(w, 4)
            if 50 <= k < 54:
                score += math.log10((counts[w] + 0.1) / (total[k - 50] + 0.1 * (types[k - 50] + 1)))
            state = [sum(state[i] * chain.move[i, j] for i in range(4)) * chain.emit[k, j] for j in range(4)]
            norm = sum(state)
            score += math.log10(norm)
            state = [x / norm for x in state]
        assert r.score == pytest.approx(score, rel=1e-9)


# --- 3 shards --------------------------------------------------------------------------


def test_shards_round_trip(spark):
    texts = odd_texts()
    ids = [*range(len(texts) - 2), None, 3]
    work = Workspace(spark, "shards")
    manifest = sstable.write_shards(frame(spark, texts, ids), work, shard_bytes=600)
    assert manifest.count() > 3
    lib = WordEncoder(default_tokenizer()).lib
    want = sorted(((i is not None, i or 0), [*lib.encode(t or "", add_special_tokens=False).ids, 1]) for i, t in zip(ids, texts, strict=True))
    rows = sstable.read_shards(spark, work, manifest, with_ids=True).orderBy("start").collect()
    assert sorted(((r.doc_id is not None, r.doc_id or 0), r.ids) for r in rows) == want
    keys = [(r.doc_id is not None, r.doc_id or 0) for r in rows]
    assert keys == sorted(keys)
    at = 0
    for r in rows:
        assert r.start == at and r.n_tokens == len(r.ids) and r.ids_crc32 == zlib.crc32(np.array(r.ids, dtype="<u4").tobytes())
        at += len(r.ids)
    assert len(sstable.lookup(work, manifest, 3)) == 2 and sstable.lookup(work, manifest, 10**6) == [] and len(sstable.lookup(work, manifest, None)) == 1
    empty = Workspace(spark, "empty")
    assert sstable.read_shards(spark, empty, sstable.write_shards(frame(spark, []), empty)).count() == 0


def test_shard_detects_damage(spark, tmp_path):
    path = f"file://{tmp_path}/a.sst"
    w = sstable.ShardWriter(path, 4, block_bytes=64)
    for i in range(100):
        w.add(sstable.key_bytes(i), np.arange(i % 7, dtype=np.uint32))
    w.close()
    shard = sstable.Shard(path)
    assert [len(shard.get(i)[0]) for i in range(100)] == [i % 7 for i in range(100)] and shard.get(-5) == []
    raw = bytearray((tmp_path / "a.sst").read_bytes())
    raw[10] ^= 255
    (tmp_path / "a.sst").write_bytes(raw)
    with pytest.raises(ValueError, match="damaged"):
        list(sstable.Shard(path).scan())


# --- 4 Jaccard ---------------------------------------------------------------------------


def brute_groups(texts, ids, size, num, den):
    sets = []
    for t in texts:
        ws = blank_words(t.encode() if t else None, lower=True)
        k = min(size, len(ws))
        sets.append({tuple(ws[i : i + k]) for i in range(len(ws) - k + 1)} if ws else set())
    up = list(range(len(texts)))

    def find(a):
        while up[a] != a:
            a = up[a]
        return a

    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and sets[j]:
                both = len(sets[i] & sets[j])
                if den * both >= num * (len(sets[i]) + len(sets[j]) - both):
                    up[find(i)] = find(j)
    least = defaultdict(list)
    for i in range(len(texts)):
        if ids[i] is not None:
            least[find(i)].append(ids[i])
    return sorted((ids[i] if ids[i] is not None else -1, len(sets[i]), min(least[find(i)], default=-1) if sets[i] else (ids[i] if ids[i] is not None else -1)) for i in range(len(texts)))


def near_copies():
    rng = random.Random(9)
    out = []
    for n in (8, 30, 90, 250):
        base = words(rng, n, 500).split()
        for k in range(12):
            copy = list(base)
            for _ in range(rng.randrange(0, 1 + n // 25)):
                copy[rng.randrange(n)] = f"z{rng.randrange(99)}"
            out.append(" ".join(copy[: n - k % 3]))
    passage = words(rng, 40, 500)
    return out + [passage + " " + words(rng, 30, 5000) for _ in range(20)]


@pytest.mark.parametrize("size, num, den, chunk", [(3, 90, 100, 4096), (5, 80, 100, 4096), (3, 60, 100, 6)])
def test_groups_equal_brute_force(spark, size, num, den, chunk):
    texts = odd_texts() + near_copies()
    ids = list(range(len(texts)))
    random.Random(1).shuffle(ids)
    ids[3] = None
    got = jaccard.similar_groups(spark, frame(spark, texts, ids), shingle=size, similarity=(num, den), chunk=chunk)
    rows = sorted((r.doc_id if r.doc_id is not None else -1, r.n_shingles, r.component_id if r.component_id is not None else -1) for r in got.collect())
    assert rows == brute_groups(texts, ids, size, num, den)


def test_groups_of_a_row_that_repeats(spark):
    """More copies of one row than tasks want to see: one text stands for them, every row has its group."""
    texts = near_copies()
    texts, ids = texts + 300 * [texts[0]], list(range(len(texts))) + 300 * [0]
    got = jaccard.similar_groups(spark, frame(spark, texts, ids), shingle=3, similarity=(90, 100), chunk=6)
    assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()) == brute_groups(texts, ids, 3, 90, 100)


def test_groups_in_waves(spark, monkeypatch):
    """Texts that meet often travel in waves, and each wave's shuffle files go before the next."""
    texts, freed = odd_texts() + near_copies(), []
    monkeypatch.setattr(jaccard.Workspace, "free", lambda work, *names: (freed.append(names), work.drop(*names)))
    got = jaccard.similar_groups(spark, frame(spark, texts), shingle=3, similarity=(60, 100), chunk=6, wave_bytes=sum(len(t or "") for t in texts) // 2)
    assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()) == brute_groups(texts, list(range(len(texts))), 3, 60, 100)
    assert ("mapped",) in freed and freed.count(()) > 4


def test_count_tree_loses_nothing():
    rng = np.random.default_rng(3)
    base = np.unique(rng.integers(0, 2**60, 300).astype(np.uint64))
    sets = [np.unique(np.concatenate([rng.choice(base, int(n), replace=False), rng.integers(0, 2**60, int(m)).astype(np.uint64)])) for n, m in zip(rng.integers(200, 290, 150), rng.integers(0, 25, 150), strict=True)]
    links = {(i, j) for i in range(150) for j in range(i) if 100 * len(np.intersect1d(sets[i], sets[j])) >= 85 * len(np.union1d(sets[i], sets[j]))}
    for right in (None, 70):
        left = sets if right is None else sets[:right]
        found = list(jaccard.link_sets(left, None if right is None else sets[right:], 85, 100))
        assert all((max(p), min(p)) in links for p in found)
        uf, want = jaccard.UnionFind(150), jaccard.UnionFind(150)
        for i, j in found:
            uf.join(i, j)
        for i, j in links:
            if right is None or (i >= right) != (j >= right):
                want.join(i, j)
        assert [uf.find(i) for i in range(150)] == [want.find(i) for i in range(150)]


def test_groups_of_nothing(spark):
    assert jaccard.similar_groups(spark, frame(spark, [])).count() == 0
    rows = jaccard.similar_groups(spark, frame(spark, [None, "", "a"])).collect()
    assert {(r.doc_id, r.n_shingles, r.component_id) for r in rows} == {(0, 0, 0), (1, 0, 1), (2, 1, 2)}


# --- 5 licences ----------------------------------------------------------------------------


def test_licences_edges(spark):
    texts = ["Under THE mit-License; under the mit license", "This work is licensed under the GNU General Public License, version 3.", None, "", "plain text, all rights", "CC BY-NC x cc.by.nc " * 400, "All Rights Reserved", "under the mitlicense", "Licensed under the Apache License, Version 2.0.", "É cc by É nc"]
    rows = {r.doc_id: r for r in licenses.scan_licenses(spark, frame(spark, texts + [texts[0]], [*range(10), 0])).collect()}
    assert (rows[0].n_base, rows[0].first_word, rows[0].last_word, rows[0].base_labels) == (2, 0, 4, "mit")
    assert rows[1].labels == "gpl-3" and rows[1].base_labels == "" and rows[1].score == 1.0
    assert rows[5].n_base == 800 and rows[5].n_words == 2800
    assert rows[8].base_labels == "apache-2" and [rows[i].labels for i in (2, 3, 4, 7, 9)] == [""] * 5
    assert licenses.scan_licenses(spark, frame(spark, [])).count() == 0


def test_licences_of_long_texts_notices_and_own_templates(spark):
    long = "word " * 50_000 + "Permission is hereby granted, free of charge, to any person " + "word " * 50_000 + "under the MIT license"
    rows = {r.doc_id: r for r in licenses.scan_licenses(spark, frame(spark, [long, "may be used by zebras under no terms"])).collect()}
    assert (rows[0].n_words, rows[0].n_base, rows[0].first_word) == (100_014, 1, 100_010)
    assert {(n.label, n.first_word) for n in rows[0].notices} == {("mit", 50_000), ("mit", 100_009)} and rows[1].notices == []
    own = [("may be used by zebras under " + "these " * 80 + "terms", "zebra", ["used by zebras"])]
    text = "x may be used by zebras under " + "these " * 80 + "terms"
    rows = licenses.scan_licenses(spark, frame(spark, [text, "used by zebras"]), notices=own).collect()
    assert sorted((r.doc_id, r.labels, r.score) for r in rows) == [(0, "zebra", 1.0), (1, "", 0.0)]


# --- 6 language ------------------------------------------------------------------------------


def test_language_held_out(spark, medium):
    rows = queries.op6_language_id(spark, medium).join(spark.read.parquet(f"{medium}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r.lang_pred == r.lang for r in rows) / len(rows) > 0.97
    assert all(0 <= r.score <= 1 for r in rows) and sum(r.rejected for r in rows) < 0.02 * len(rows)


def test_language_edges(spark):
    docs = frame(spark, ["the cat sat on the mat and the dog"] * 5 + odd_texts())
    model = langid.learn(spark, docs, F.col("doc_id") < 5)
    out = {r.doc_id: r for r in langid.identify(spark, docs, model, keep=["doc_id", "own"]).collect()}
    assert out[5 + 14].lang_pred == "und" and out[5 + 13].lang_pred == "und" and out[5 + 21].lang_pred == "und" and out[0].lang_pred == "en"
    assert out[5 + 20].lang_pred == "en"
    none = langid.learn(spark, docs, F.lit(False))
    assert {r.lang_pred for r in langid.identify(spark, docs, none, keep=["doc_id"]).collect()} == {"und"}
    assert langid.identify(spark, frame(spark, []), model, keep=["doc_id"]).count() == 0


def brute_vector(text, idf):
    """The TF-IDF trigram vector of a text, one trigram at a time."""
    bits, counts = int(math.log2(len(idf))), Counter()
    line = "  ".encode() + bytes(b if b >= 128 or 97 <= b <= 122 else b + 32 if 65 <= b <= 90 else 32 for b in (text or "").encode()) + b"  "
    for i in range(len(line) - 2):
        if line[i : i + 3] != b"   ":
            counts[(int.from_bytes(line[i : i + 3], "big") * 2654435761) % 2**32 >> (32 - bits)] += 1
    v = np.zeros(len(idf))
    for k, c in counts.items():
        v[k] = math.log1p(c) * idf[k]
    return v / max(np.linalg.norm(v), 1e-12), counts


def test_language_against_brute_force(spark, medium):
    """Document frequencies, cosines, nearest centroid and rejection; repeated rows, ties and very long texts included."""
    docs = spark.read.parquet(f"{medium}/documents.parquet").limit(300)
    model = langid.learn(spark, docs.union(docs.limit(50)).union(docs.limit(50)), F.lit(True))
    raw = [r.text for r in docs.collect()]
    seen = Counter(k for t in raw + 2 * [r.text for r in docs.limit(50).collect()] for k in brute_vector(t, np.ones(4096))[1])
    assert model.idf == pytest.approx([math.log(401 / (1 + seen[j])) + 0.05 for j in range(4096)], rel=1e-5)
    texts = raw[:60] + odd_texts() + ["der die und " * 30_000, raw[0], raw[0]]
    rows = langid.identify(spark, frame(spark, texts), model, keep=["doc_id", "key"]).collect()
    assert len(rows) == len(texts)
    for r in rows:
        text = texts[r.doc_id]
        v, counts = brute_vector(text, model.idf)
        if not any(ch.isalpha() for ch in text or ""):
            assert (r.lang_pred, r.score, r.rejected) == ("und", 0.0, True)
            continue
        cosine = model.centers @ v
        best = int(np.argmax(cosine))
        assert r.score == pytest.approx(min(1.0, max(0.0, cosine[best])), abs=1e-5)
        assert cosine[model.langs.index(r.lang_pred) :][: model.langs.count(r.lang_pred)].max() == pytest.approx(cosine[best], abs=1e-5)
        floor = model.floors[best, np.searchsorted(langid.BANDS, sum(counts.values()), side="right")]
        assert abs(cosine[best] - floor) < 1e-5 or r.rejected == (cosine[best] < floor)


def test_language_of_one_repeated_row(spark):
    docs = frame(spark, ["ein Haus und ein Hof"] * 900 + ["a house and a yard"], [7] * 900 + [8]).withColumn("lang", F.when(F.col("doc_id") == 7, "de").otherwise("en"))
    model = langid.learn(spark, docs, F.lit(True))
    assert sorted(set(model.langs)) == ["de", "en"]
    assert {(r.doc_id, r.lang_pred) for r in langid.identify(spark, docs, model, keep=["doc_id"]).collect()} == {(7, "de"), (8, "en")}


# --- 7 substrings -----------------------------------------------------------------------------


def brute_removed(texts, ids, width):
    seen: dict = {}
    split = [blank_words(t.encode() if t else None) for t in texts]
    big = 1 << 62
    for ws, i in zip(split, ids, strict=True):
        for k in range(len(ws) - width + 1):
            w = tuple(ws[k : k + width])
            seen[w] = min(seen.get(w, big), big if i is None else i)
    out = []
    for ws, i in zip(split, ids, strict=True):
        gone = [False] * len(ws)
        for k in range(len(ws) - width + 1):
            if seen[tuple(ws[k : k + width])] < (big if i is None else i):
                gone[k : k + width] = [True] * width
        kept = b" ".join(w for w, g in zip(ws, gone, strict=True) if not g)
        out.append((i if i is not None else -1, len(ws), sum(gone), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("width", [2, 5, 13, 30])
def test_substrings_equal_brute_force(spark, width):
    texts = odd_texts() + near_copies()
    ids = list(range(len(texts)))
    random.Random(2).shuffle(ids)
    ids[2] = None
    ids[20] = ids[30]
    got = substring.dedup_substrings(spark, frame(spark, texts, ids), width=width, keep=["doc_id", "own"]).collect()
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.n_words, r.n_removed, r.kept_sha256) for r in got) == brute_removed(texts, ids, width)
    for r in got:
        assert hashlib.sha256(b" ".join((r.kept_text or "").encode().split())).hexdigest() == r.kept_sha256


def test_substrings_of_a_row_that_repeats(spark):
    texts = odd_texts() + near_copies()
    ids = list(range(len(texts)))
    texts, ids = texts + 20 * [texts[7]] + 5 * [None], ids + 20 * [7] + 5 * [None]
    own = [f"row {k}" for k in range(len(texts))]
    docs = spark.createDataFrame(list(zip(ids, texts, own, strict=True)), "doc_id long, text string, kept_text string")
    got = substring.dedup_substrings(spark, docs, keep=["doc_id", "kept_text"], copies=3).collect()
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.n_words, r.n_removed, r.kept_sha256) for r in got) == brute_removed(texts, ids, 13)
    assert sorted(r.kept_text_in for r in got) == sorted(own)


@pytest.mark.parametrize("period", sorted(substring.COVERS))
def test_covers_are_difference_covers(period):
    cover = set(substring.COVERS[period])
    assert all(any((i + s) % period in cover and (j + s) % period in cover for s in range(period)) for i in range(period) for j in range(period))


def test_substrings_of_nothing(spark):
    assert substring.dedup_substrings(spark, frame(spark, [])).count() == 0


# --- 8 decontamination --------------------------------------------------------------------------


def test_decontamination_spans_and_slices(spark):
    item = "Which of these, Sir, is the LONGEST river in all of the known world today?"
    bench = spark.createDataFrame([(1, item), (2, "short one"), (3, None), (None, "..."), (4, "  ")], "item_id long, text string").withColumn("own", F.lit(1))
    texts = ["Intro: which OF these sir is the longest River in all of, the rest.", "a Short-One here", "", None, "nothing to see", "short shortone one short"]
    one = decontaminate.decontaminate(spark, frame(spark, texts), bench, keep=["doc_id", "own"]).collect()
    many = decontaminate.decontaminate(spark, frame(spark, texts), bench, keep=["doc_id", "own"], automaton_nodes=60, segment_words=3).collect()
    assert sorted(map(str, one)) == sorted(map(str, many))
    rows = {r.doc_id: r for r in one}
    assert texts[0][rows[0].spans[0].start : rows[0].spans[0].end] == "which OF these sir is the longest River in all of, the"
    assert (rows[0].n_hit, rows[0].item_ids) == (12, ["1"]) and rows[1].item_ids == ["2"] and not any(rows[i].contaminated for i in (2, 3, 4, 5))
    assert decontaminate.decontaminate(spark, frame(spark, []), bench).count() == 0
    assert not decontaminate.decontaminate(spark, frame(spark, texts), bench.where("false")).where("contaminated").count()


def test_decontamination_of_long_texts_and_clashing_columns(spark):
    rng = random.Random(6)
    item = words(rng, 30, 10**6)
    long = words(rng, 150_000, 900) + " " + item + " " + words(rng, 1000, 900)
    bench = spark.createDataFrame([("a", item), ("b", item + " tail")], "item_id string, text string")
    docs = frame(spark, [long, "clean"]).withColumns({"n_hit": F.lit("mine"), "Contaminated": F.lit("also")})
    rows = {r.doc_id: r for r in decontaminate.decontaminate(spark, docs, bench, keep=["doc_id", "n_hit", "Contaminated"]).collect()}
    assert (rows[0].n_words, rows[0].n_hit, rows[0].item_ids, rows[0].n_hit_in, rows[0].Contaminated_in) == (151_030, 30, ["a", "b"], "mine", "also") and not rows[1].contaminated
    assert long[rows[0].spans[0].start : rows[0].spans[0].end] == item


# --- 9 fixity --------------------------------------------------------------------------------------


def pages(spark, n=3000):
    return spark.createDataFrame([(i, f"http://h/{i}", f"<p>{i} é</p>" * (i % 4)) for i in range(n)], "page_id long, url string, html string").withColumn("record", F.lit("clash"))


def test_audit_descends_to_the_damage(spark):
    work = Workspace(spark, "audit")
    src = pages(spark)
    copy = warc_audit.read_replica(warc_audit.write_replica(src, work, "copy", lambda r: r.where("record_id <> 77").withColumn("record", F.when(F.col("record_id") == 2050, F.regexp_replace("record", "<p>", "<q>")).otherwise(F.col("record")))))
    bad, tree, counts = warc_audit.audit(spark, warc_audit.warc_records(src), copy, work)
    assert {(r.record_id, r.status) for r in bad.collect()} == {(77, "missing"), (2050, "corrupt")}
    assert counts[0] == 1 and max(counts) <= 2  # only the two damaged paths are followed
    assert tree.root() and tree.levels[-1].first().n == 3000


def test_audit_of_equal_and_odd_replicas(spark):
    odd = spark.createDataFrame([(1, None, "x"), (1, "u", "y"), (1, "u", "y"), (None, "n", None), (-5, "m", ""), (10**9, "far", "z")], "page_id long, url string, html string")
    work = Workspace(spark, "audit")
    bad, _, counts = warc_audit.audit(spark, warc_audit.warc_records(odd), warc_audit.read_replica(warc_audit.write_replica(odd, work, "copy")), work)
    assert bad.count() == 0 and counts == [0]
    one_copy = odd.dropDuplicates()
    bad, _, _ = warc_audit.audit(spark, warc_audit.warc_records(odd), warc_audit.warc_records(one_copy), Workspace(spark, "audit"))
    assert {r.record_id for r in bad.collect()} == {1}
    empty = odd.where("false")
    assert warc_audit.audit_report(spark, empty).count() == 0


def test_audit_of_line_breaks_and_crowded_identifiers(spark):
    rows = [(i, f"http://a\r\n\r\n{i}\nx", f"<p>{i}\r\n\r\n") for i in range(30)] + [(None, "http://n", f"page {k}") for k in range(2500)] + [(7, None, f"seven {k % 1500}") for k in range(3000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"record": F.lit(1), "digest": F.lit("x"), "file": F.lit(0), "slot": F.lit(0)})
    out = warc_audit.audit_report(spark, pages).collect()
    assert len(out) == 30 + 2500 + 1500 and {r.status for r in out} == {"ok"}
    held = Counter(r.warc_file for r in out)
    assert max(held.values()) < 1400 and len(held) >= 5
    urls = [r.url for r in warc_audit.warc_records(pages).where("record_id = 3").collect()]
    assert urls == ["http://a%0D%0A%0D%0A3%0Ax"]
    lose = lambda r: r.where("not (record_id is null and body = 'page 9') and not (record_id = 7 and body = 'seven 5')").withColumn("record", F.when(F.col("body") == "seven 4", F.replace("record", F.lit("seven 4"), F.lit("seven !"))).otherwise(F.col("record")))
    bad = [(r.page_id, r.status) for r in warc_audit.audit_report(spark, pages, lose).collect() if r.status != "ok"]
    assert sorted(bad, key=str) == [(7, "corrupt"), (7, "missing"), (None, "missing")]


# --- 10 packing ---------------------------------------------------------------------------------------


@pytest.mark.parametrize("width, windows, fan", [(2048, 32, 64), (64, 3, 2)])
def test_packing_is_a_partition(spark, width, windows, fan):
    texts = (odd_texts() + near_copies()) * 3
    docs = frame(spark, texts).repartition(9)
    lib = WordEncoder(default_tokenizer()).lib
    ids = {i: [*lib.encode(t or "", add_special_tokens=False).ids, 1] for i, t in enumerate(texts)}
    packed = packing.pack(spark, docs, width=width, open_windows=windows, fan_in=fan, least_cut=4)
    rows = packed.collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append(r)
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == zlib.crc32(np.array(ids[r.doc_id][r.start : r.start + r.length], dtype="<u4").tobytes())
    for i, parts in by_doc.items():
        at = 0
        for r in sorted(parts, key=lambda r: r.start):
            assert r.start == at and r.length > 0
            at += r.length
        assert at == len(ids[i])
    assert set(by_doc) == set(ids)
    for parts in by_seq.values():
        at = 0
        for r in sorted(parts, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= width
    share = packing.padding(packed, width).first().padding_share
    assert share < (0.3 if width == 2048 else 0.15)


def test_packing_of_repeated_identifiers(spark):
    docs = frame(spark, ["one two three"] * 40 + ["four"], [5] * 40 + [None])
    rows = packing.pack(spark, docs, width=16).collect()
    assert sum(r.length for r in rows) == 40 * rows[0].doc_tokens + next(r.doc_tokens for r in rows if r.doc_id is None)
    used = Counter()
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == used[r.sequence_id]
        used[r.sequence_id] += r.length
    assert max(used.values()) <= 16


def test_packing_of_nothing(spark):
    assert packing.pack(spark, frame(spark, [])).count() == 0


def test_packing_padding_on_documents(spark, medium):
    assert packing.padding(queries.op10_pack(spark, medium)).first().padding_share < 0.03

"""Document-level and substring baselines against brute force, and components."""

import random
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusdedup.operators import documents as D
from corpusdedup.operators import kgrams as K
from corpusdedup.operators import measures as M
from corpusdedup.operators import substring as B
from corpusdedup.operators.components import connected_components


def brute_components(edges):
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {x: find(x) for x in root}


def test_components(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000 + k, 1001 + k) for k in range(60)] + [(5000, 5001 + k) for k in range(50)]
    df = spark.createDataFrame([*edges, (None, 3), (4, 4)], "src long, dst long")
    want = brute_components([e for e in edges if e[0] != e[1]])
    assert {r.node: r.component for r in connected_components(df).collect()} == want


def test_components_of_nothing(spark):
    assert connected_components(spark.createDataFrame([], "src long, dst long")).count() == 0


def brute_spans(texts, k):
    grams = {}
    for d, t in enumerate(texts):
        for p in range(len(t) - k + 1):
            grams.setdefault(t[p : p + k], []).append((d, p))
    covered = [set() for _ in texts]
    for places in grams.values():
        if len(places) > 1:
            for d, p in places:
                covered[d] |= set(range(p, p + k))
    out = []
    for c in covered:
        spans = []
        for x in sorted(c):
            if spans and spans[-1][1] == x:
                spans[-1][1] = x + 1
            else:
                spans.append([x, x + 1])
        out.append([tuple(s) for s in spans])
    return out


def merged(spans):
    """Touching spans as one: a suffix array keeps two repeats that only touch together or apart alike."""
    out = []
    for a, b in spans:
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def test_suffix_array_equals_brute_force():
    rng = random.Random(3)
    for _ in range(120):
        texts = ["".join(rng.choice("ab" if rng.random() < 0.5 else "abcd") for _ in range(rng.randrange(0, 40))) for _ in range(rng.randrange(1, 5))]
        k = rng.randrange(2, 7)
        assert [merged(s) for s in B.repeated_spans(texts, k)] == [merged(s) for s in brute_spans(texts, k)], (texts, k)


def test_suffixes_of_a_large_shard(spark):
    # long copies cost no round of their own, text without repeats is not sorted
    rng = random.Random(9)
    draw = lambda n: "".join(rng.choices("abcdefghij é漢😀", k=n))
    copy = draw(400_000)
    texts = [draw(1_000_000), "x" + copy, copy + "y", draw(200_000), "", copy[100:160]]
    began = time.process_time()
    assert B.repeated_spans(texts, 50) == [[], [(1, 400_001)], [(0, 400_000)], [], [], [(0, 60)]]
    assert time.process_time() - began < 4
    assert B.repeated_spans([], 5) == [] and B.repeated_spans([""], 5) == [[]]
    docs = spark.createDataFrame([(1, copy[:80], 0), (None, copy[:80], 0), (3, copy[20:90], 0), (4, None, 0)], "doc_id long, text string, shard int")
    assert sorted(tuple(r) for r in B.suffix_array_spans(docs).collect()) == [(1, 20, 80), (3, 0, 60)]


def test_hashes_shared_by_chance_are_sorted_apart(monkeypatch):
    monkeypatch.setattr(B, "_rolled", lambda codes, k, m: np.zeros(len(codes) - k + 1, np.uint64))
    rng = random.Random(10)
    for _ in range(40):
        texts = ["".join(rng.choices("abc", k=rng.randrange(0, 50))) for _ in range(3)]
        assert [merged(s) for s in B.repeated_spans(texts, 5)] == [merged(s) for s in brute_spans(texts, 5)]


def test_suffixes_beside_a_repeat():
    # what follows a repeat is not looked up beyond it
    rng = random.Random(11)
    for _ in range(150):
        phrases = ["".join(rng.choices("abcd é漢", k=rng.randrange(3, 90))) for _ in range(4)]
        texts = ["".join(rng.choice(phrases) if rng.random() < 0.2 else rng.choice("abcdefgh") for _ in range(rng.randrange(0, 60))) for _ in range(6)]
        k = rng.randrange(4, 50)
        assert [merged(s) for s in B.repeated_spans(texts, k)] == [merged(s) for s in brute_spans(texts, k)], (texts, k)


def test_substring_toy(spark):
    docs = spark.createDataFrame([(1, "abcXYZWdef", 0), (2, "qqXYZWrr", 0)], "doc_id long, text string, shard int")
    text = lambda spans, d=docs: {r.doc_id: r.text for r in B.remove_spans(d, spans).collect()}
    assert text(B.kgram_spans(docs, 4, "shard")) == {1: "abcdef", 2: "qqrr"}
    assert text(B.kgram_spans(docs, 4, "shard", keep_first=True)) == {1: "abcXYZWdef", 2: "qqrr"}
    assert text(B.suffix_array_spans(docs, 4)) == {1: "abcdef", 2: "qqrr"}
    assert B.kgram_spans(docs.withColumn("shard", F.col("doc_id")), 4, "shard").count() == 0
    one = spark.createDataFrame([(1, "aaaaaa", 0)], "doc_id long, text string, shard int")
    assert [tuple(r) for r in B.kgram_spans(one, 3).select("start", "stop").collect()] == [(0, 6)]


def test_rolling_hashes_are_those_of_equal_strings():
    rng = random.Random(8)
    text = "".join(rng.choice("abé漢😀") for _ in range(3000))
    for k in (1, 2, 3, 5, 8, 50):
        n = len(text) - k + 1
        g, g2 = B.rolling_hashes(text, k, 0, n)
        number = {}
        of = [number.setdefault(text[p : p + k], len(number)) for p in range(n)]
        assert len(set(zip(of, g.tolist(), g2.tolist(), strict=True))) == len(number) == len(set(g.tolist()))
        part = B.rolling_hashes(text, k, 100, 200)
        assert (part[0] == g[100:200]).all() and (part[1] == g2[100:200]).all()


def test_spans_of_a_text_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(B, "PLACES", 7)
    texts = ["x" * 5 + "the repeated words" + "y" * 40, "z" * 33 + "the repeated words" + "0123456789"]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts)] + [(7, None), (None, "the repeated words")], "doc_id long, text string")
    want = [(d, a, b) for d, spans in enumerate(brute_spans(texts, 6)) for a, b in spans]
    assert sorted(tuple(r) for r in B.kgram_spans(docs, 6).collect()) == want
    for k in (1, 4, 6):
        assert sorted(tuple(r) for r in B.winnowed_spans(docs, 6, k).collect()) == want


def test_winnowed_spans_equal_kgram_spans(spark):
    rng = random.Random(12)
    phrases = ["".join(rng.choice("ab é漢") for _ in range(rng.randrange(3, 30))) for _ in range(6)]
    texts = ["".join(rng.choice(phrases) if rng.random() < 0.3 else rng.choice("abcdefgh") for _ in range(rng.randrange(0, 60))) for _ in range(40)] + ["a" * 50, "ab" * 30]
    docs = spark.createDataFrame([(d, t, d % 3) for d, t in enumerate(texts)], "doc_id long, text string, shard int")
    for shard_col, keep_first in ((None, False), ("shard", False), ("shard", True)):
        want = sorted(tuple(r) for r in B.kgram_spans(docs, 12, shard_col, keep_first).collect())
        assert want and sorted(tuple(r) for r in B.winnowed_spans(docs, 12, 7, shard_col, keep_first).collect()) == want
    with pytest.raises(ValueError, match="between"):
        B.winnowed_spans(docs, 5, 6)


def test_kgram_spans_of_packed_blocks(spark, monkeypatch):
    # blocks of few characters, fingerprints that are common, hashing in small steps; ids that repeat share their spans
    rng = random.Random(13)
    phrases = ["".join(rng.choice("ab é漢😀") for _ in range(rng.randrange(3, 40))) for _ in range(8)]
    texts = ["".join(rng.choice(phrases) if rng.random() < 0.3 else rng.choice("abcdefgh") for _ in range(rng.randrange(0, 60))) for _ in range(60)] + ["a" * 90, "ab" * 40, "", phrases[0] * 3]
    texts += [texts[3], "x" + texts[3], texts[5][4:]]
    docs = spark.createDataFrame([(d, t, d % 2) for d, t in enumerate(texts)] + [(None, texts[3], 0), (70, None, 0)], "doc_id long, text string, shard int")
    for k, most, common, step in ((13, 4_000_000, 100_000, 200_000), (13, 50, 100_000, 9), (50, 300, 3, 200_000), (1, 100, 4, 31), (4, 100, 0, 200_000)):
        monkeypatch.setattr(K, "BLOCK_CHARS", most)
        monkeypatch.setattr(K, "COMMON", common)
        monkeypatch.setattr(B, "PLACES", step)
        want = [(d, a, b) for odd in (0, 1) for d, spans in enumerate(brute_spans([t if j % 2 == odd else "" for j, t in enumerate(texts)], k)) for a, b in merged(spans)]
        assert want and sorted(tuple(r) for r in B.kgram_spans(docs, k, "shard").collect()) == sorted(want), k
    twice = spark.createDataFrame([(1, "abcdefgh"), (1, "xxcdefgh"), (2, "zzzabcd")], "doc_id long, text string")
    assert sorted(tuple(r) for r in B.kgram_spans(twice, 4).collect()) == [(1, 0, 8), (2, 3, 7)]
    assert B.kgram_spans(twice.limit(0), 4).count() == B.kgram_spans(twice, 9).count() == 0


def test_kgram_spans_send_no_row_for_each_character(spark, monkeypatch):
    # a row for each character was 32 bytes before compression; text without repeats asks about no k-gram at all
    rng = random.Random(14)
    draw = lambda n: "".join(rng.choices("abcdefghij", k=n))
    sent = []
    size = lambda df: df.agg(*(F.coalesce(F.sum(F.length(c)), F.lit(0)) for c, kind in df.dtypes if kind == "binary")).first()
    for name in ("count_in_buckets", "pairs_in_buckets"):
        monkeypatch.setattr(K, name, lambda df, *a, f=getattr(K, name): sent.append(sum(size(df))) or f(df, *a))
    monkeypatch.setattr(B, "kgram_rows", None)
    copy = draw(300_000)
    docs = spark.createDataFrame([(1, draw(300_000))], "doc_id long, text string")
    assert B.kgram_spans(docs).count() == 0 and sent[0] < 0.5 * 300_000 and sent[1] < 100 and sent[2] == 0
    sent.clear()
    docs = spark.createDataFrame([(d, copy[: 300_000 - d]) for d in range(5)] + [(5, draw(200) + copy[1000:2000])], "doc_id long, text string")
    got = sorted(tuple(r) for r in B.kgram_spans(docs).collect())
    assert [r for r in got if r[0] in (1, 4, 5)] == [(1, 0, 299_999), (4, 0, 299_996), (5, 200, 1200)]
    assert sum(sent) < 1.3 * 1_500_000 and sent[2] < 0.02 * 1_500_000


def test_unique_text_sends_only_fingerprints(spark):
    rng = random.Random(4)
    docs = spark.createDataFrame([(1, "".join(rng.choice("abcdefghij") for _ in range(20_000)))], "doc_id long, text string")
    rows = B.winnowed_rows(docs)
    assert rows.count() < 0.13 * 20_000 and rows.agg(F.sum(F.col("last") - F.col("first") + 1)).first()[0] == 20_000 - 49


def test_exact_copies_without_ids_or_texts(spark):
    rows = [(None, None), (1, None), (2, None), (2, "a"), (1, "a"), (1, "a"), (None, "a"), (None, "b"), (None, "b"), (3, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = [tuple(r) for r in D.exact_doc_dedup(docs).collect()]
    key = lambda r: tuple((v is not None, v) for v in r)
    assert sorted(got, key=str) == sorted([(None, None), (1, None), (2, None), (1, "a"), (1, "a"), (None, "b"), (None, "b"), (3, "")], key=str), key


def test_contained_items(spark):
    items = spark.createDataFrame([(1, "needle"), (2, "needle"), (3, ""), (4, "gone"), (5, None), (6, "nee")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "a needle here"), (2, None)], "doc_id long, text string")
    assert sorted(r[0] for r in M.contained_items(docs, items).collect()) == [1, 2, 3, 6]
    assert M.contained_items(docs, items.limit(0)).count() == 0


def test_simulation_agrees_with_the_closed_form(spark):
    for r in B.simulate_sharding(spark, (1, 2, 5, 10), 5, 400).collect():
        assert abs(r.mean_kept - r.expected_kept) <= 4 * (r.sd_kept or 0) / np.sqrt(400) + 1e-9


def test_signatures_agree(spark):
    docs = spark.createDataFrame([(1, "One two three four five six seven"), (2, "one  two"), (3, ""), (4, None), (5, "Ünï cödé wörds here änd there")], "doc_id long, text string")
    a = {r.doc_id: r.sig for r in D.minhash_signature(docs, perms=16).collect()}
    assert a == {r.doc_id: r.sig for r in D.minhash_signature_numpy(docs, perms=16).collect()} and set(a) == {1, 2, 5}


def test_shingles(spark):
    df = spark.createDataFrame([("A b c d e f", 2), ("a b", 1), ("", 0), ("  ", 0), ("a a a a a a a", 1)], "t string, n int")
    assert all(r[0] == r.n for r in df.select(F.size(D.shingles(F.col("t"))), "n").collect())
    assert spark.createDataFrame([("abcdef",)], "t string").select(D.shingles(F.col("t"), 5, "char")).first()[0] == ["abcde", "bcdef"]


def test_bands():
    assert D.choose_bands() == (32, 4) and D.choose_bands(verified=False) == (16, 8)


def test_chain_is_one_component(spark):
    base = [f"w{k}" for k in range(60)]
    texts = [" ".join(base), " ".join(base[4:] + ["x1", "x2", "x3", "x4"]), " ".join(base[8:] + ["x1", "x2", "x3", "x4", "y1", "y2", "y3", "y4"])]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    assert [r.doc_id for r in D.minhash_dedup(docs, all_pairs=True).collect()] == [0]


def test_links_beside_a_smaller_dissimilar_document(spark):
    # document 0 shares boilerplate with 1 and 2, and so every bucket that these two share
    common = [f"b{k}" for k in range(130)]
    alike = common + [f"w{k}" for k in range(60)]
    texts = [common + [f"z{k}" for k in range(60)], alike, alike + ["one", "more"]]
    sig = [[0] * 64 + [1] * 64, [0] * 64 + [2] * 64, [0] * 64 + [2] * 60 + [3] * 4, [0] * 64 + [4] * 64, [5] * 128]
    low = spark.createDataFrame(list(enumerate(sig)), "doc_id long, sig array<long>")
    none = spark.createDataFrame([], "doc_id long, component long")
    assert {tuple(r) for r in D.cross_pairs(low, none, 32, 4).collect()} == {tuple(r) for r in D.lsh_pairs(low, 32, 4).collect()}
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)] + [(9, "")], "doc_id long, text string")
    want = {tuple(r) for r in D.dup_clusters(docs, all_pairs=True).collect()}
    assert {tuple(r) for r in D.dup_clusters(docs).collect()} == want and want


def test_stars_then_the_rest_equal_all_pairs(spark, monkeypatch):
    # 1 and 2 are alike, but every bucket that they share holds 0
    sig = [[0] * 32 + [1] * 96, [0] * 32 + [2] * 96, [0] * 32 + [2, 2, 2, 3] * 24, [0] * 32 + [4] * 96, [5] * 128]
    monkeypatch.setattr(D, "minhash_signature_numpy", lambda *_: spark.createDataFrame(list(enumerate(sig)), "doc_id long, sig array<long>"))
    docs = spark.createDataFrame([(k, "x") for k in range(5)], "doc_id long, text string")
    assert {tuple(r) for r in D.dup_clusters(docs).where("doc_id < 3").collect()} == {(1, 1), (2, 1)}
    assert sorted(r.doc_id for r in D.minhash_dedup(docs).collect()) == [0, 1, 3, 4]


def test_exact_pairs_without_a_row_for_each_shared_shingle(spark, monkeypatch):
    rng = random.Random(14)
    draw = lambda n: [f"w{rng.randrange(10_000)}" for _ in range(n)]
    passage, base = draw(30), draw(60)
    texts = [base[:k] + [f"x{k}"] + base[k:] for k in range(0, 60, 4)] + [base] * 4 + [draw(8) + passage + draw(12) for _ in range(30)] + [["A", "Ä"], ["a", "ä"], [], draw(5) * 3]
    docs = spark.createDataFrame([(7 * k, " ".join(t)) for k, t in enumerate(texts)] + [(999, None), (None, " ".join(base))], "doc_id long, text string")
    want = sorted(tuple(r) for r in D.indexed_jaccard_pairs(docs).collect())
    monkeypatch.setattr(D, "shingle_rows", None)
    assert want and sorted(tuple(r) for r in D.exact_jaccard_pairs(docs).collect()) == want


def test_exact_pairs_of_repeated_ids(spark):
    docs = spark.createDataFrame([(1, "a b c d e"), (1, "f g h i j"), (2, "a b c d e"), (3, "f g h i j"), (4, "f g h i j")], "doc_id long, text string")
    assert [tuple(r) for r in D.exact_jaccard_pairs(docs).collect()] == [(3, 4, 1.0)]


def test_candidates_are_counted_without_their_rows(spark, monkeypatch):
    rng = random.Random(15)
    sig = [[rng.randrange(3) if k % 4 else 0 for k in range(8)] for _ in range(90)] + [[7, 7, *range(100 + 6 * k, 106 + 6 * k)] for k in range(60)] + [[9] * 8] * 5
    df = spark.createDataFrame(list(enumerate(sig)), "doc_id long, sig array<int>")
    want = {bands: D.lsh_pairs(df, bands, 8 // bands).count() for bands in (2, 4, 8)}
    classes = df.groupBy("sig").agg(F.count("*").alias("w")).withColumn("node", F.monotonically_increasing_id())
    monkeypatch.setattr(D, "band_keys", None)
    assert {bands: D.count_pairs(classes, bands, 8 // bands) for bands in (2, 4, 8)} == want
    monkeypatch.setattr(D, "HOT", 7)
    monkeypatch.setattr(D, "BUCKET_ROWS", 50)
    assert D.count_pairs(classes, 4, 2) == want[4]
    assert D.count_pairs(classes.limit(0), 4, 2) == 0


def test_pairs_of_sparks_minhash_without_its_join(spark, monkeypatch):
    from pyspark.ml.feature import HashingTF, MinHashLSH, MinHashLSHModel

    rng = random.Random(16)
    base = [f"w{k}" for k in range(40)]
    texts = [base[: rng.randrange(25, 41)] + [f"x{rng.randrange(30)}" for _ in range(rng.randrange(4))] for _ in range(25)] + [base] * 2 + [["a", "b"], []]
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string")
    x = docs.select("doc_id", D.shingles(F.col("text")).alias("grams")).where(F.size("grams") > 0)
    x = HashingTF(inputCol="grams", outputCol="features", numFeatures=1 << 20, binary=True).transform(x)
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=3, seed=42).fit(x)
    want = sorted(tuple(r) for r in model.approxSimilarityJoin(x, x, 0.3 + 1e-9).select("datasetA.doc_id", "datasetB.doc_id").where("datasetA.doc_id < datasetB.doc_id").collect())
    monkeypatch.setattr(MinHashLSHModel, "approxSimilarityJoin", None)
    assert want and sorted(tuple(r) for r in D.ml_minhash_pairs(docs, tables=3).collect()) == want

"""Each operator against brute force or an exact round trip, and on awkward rows."""

import hashlib
import math
import random
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from corpusdedup.llm import blocks, decontaminate, html_text, ngram_join, ngram_lm, packing, perspectives, quality, sharding, token_files, warc

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, row string, length int, part int, slot string, __away long"


def docs(spark, rows):
    """Documents with columns whose names the operators use inside."""
    return spark.createDataFrame([(i, t, "x", 1, 2, "s", 3) for i, t in rows], DOCS)


AWKWARD = [(None, None), (None, "null id here now"), (1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "the same words twice in here"), (6, "the same words twice in here"), (6, "the same words twice in here"), (7, "Ünï cödé \x1c x"), (8, "long text " * 30_000)]


# 1 -----------------------------------------------------------------------------------


def brute_scores(rows, model, order):
    seqs = [(i, blocks.words_of(blocks.lowered((t or "").encode()))) for i, t in rows]
    grams, contexts = [Counter() for _ in range(order + 1)], Counter()
    for i, w in seqs:
        if ngram_lm.fold_of(i) == 1:
            continue
        s = [0] * (order - 1) + w + [1]
        for p in range(order - 1, len(s)):
            for k in range(1, order + 1):
                grams[k][tuple(s[p - k + 1 : p + 1])] += 1
                contexts[tuple(s[p - k + 1 : p])] += 1
    total, distinct = sum(grams[1].values()), len(grams[1])
    out = []
    for i, w in seqs:
        s, base, score, known = [0] * (order - 1) + w + [1], 0.0, 0.0, 0
        for p in range(order - 1, len(s)):
            c = grams[1][(s[p],)]
            known += c > 0
            base += math.log10((c + 0.5) / (total + 0.5 * (distinct + 1)))
            n = contexts[tuple(s[p - order + 1 : p])]
            weights = model.weights[0 if n == 0 else 1 + int(math.log2(n))]
            prob = weights[0] / (distinct + 1)
            for k in range(1, order + 1):
                x = contexts[tuple(s[p - k + 1 : p])] if k > 1 else total
                prob += weights[k] * grams[k][tuple(s[p - k + 1 : p + 1])] / x if x else 0
            score += math.log10(prob)
        out.append((i, ngram_lm.fold_of(i) == 1, len(w) + 1, known, total, base, score))
    return out


@pytest.mark.parametrize("order", [2, 3])
def test_scores_equal_brute_force(spark, order):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()] + AWKWARD[:-1]
    got, model = ngram_lm.fit_and_score(docs(spark, rows), order)
    key = lambda r: (r[0] is None, r[0] or 0, r[2])
    for a, b in zip(sorted(map(tuple, got.collect()), key=key), sorted(brute_scores(rows, model, order), key=key), strict=True):
        assert a[:5] == b[:5] and np.allclose(a[5:], b[5:], rtol=1e-9)
    assert np.allclose(model.weights.sum(axis=1), 1)


@pytest.mark.parametrize("order", [2, 3])
def test_held_out_cells_equal_brute_force(spark, monkeypatch, order):
    """What expectation-maximisation sees: the deleted rows' tokens under counts without them."""
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()][:120] + AWKWARD[:-1]
    seen, own = [], ngram_lm._cell_table
    monkeypatch.setattr(ngram_lm, "_cell_table", lambda *a: seen.append(own(*a)) or seen[0])
    _, model = ngram_lm.fit_and_score(docs(spark, rows), order)
    seqs = [(ngram_lm._role(i, 1), [0] * (order - 1) + blocks.words_of(blocks.lowered((t or "").encode())) + [1]) for i, t in rows]
    grams, contexts = [Counter() for _ in range(order + 1)], Counter()
    for role, s in seqs:
        if role == 0:
            for p in range(order - 1, len(s)):
                for k in range(1, order + 1):
                    grams[k][tuple(s[p - k + 1 : p + 1])] += 1
                    contexts[tuple(s[p - k + 1 : p])] += 1
    uniform, want, tokens = 1 / (len(grams[1]) + 1), {}, {}
    for role, s in seqs:
        for p in range(order - 1, len(s)) if role == 1 else ():
            n = contexts[tuple(s[p - order + 1 : p])]
            cell, fine, exact = [0 if n == 0 else 1 + int(math.log2(n))], [], []
            for k in range(1, order + 1):
                x, y = contexts[tuple(s[p - k + 1 : p])], grams[k][tuple(s[p - k + 1 : p + 1])]
                cell.append(int(np.rint(ngram_lm.STEPS * np.log2(y / x / uniform))) if y else ngram_lm.NEVER)
                fine.append(int(np.rint(ngram_lm.FINE * np.log2(y / x / uniform))) if y else 0)
                exact.append(y / x / uniform if y else 0)
            tokens.setdefault(cell[0], []).append(exact)
            want[tuple(cell)] = [a + b for a, b in zip(want.get(tuple(cell), [0] * (order + 1)), [1, *fine])]
    got = {tuple(c[: order + 1]): list(c[order + 1 :]) for c in map(tuple, seen[0].collect())}
    assert got == want and len(want) > 20
    everything = [t for of in tokens.values() for t in of]
    for b in range(len(model.weights)):
        own = {}  # cells of the bucket, or of all buckets together
        for (bucket, *q), v in want.items():
            if bucket == b or b not in tokens:
                own[tuple(q)] = [x + y for x, y in zip(own.get(tuple(q), [0] * (order + 1)), v)]
        x, n = np.array(list(own)), np.array(list(own.values()), float)
        assert np.allclose(model.weights[b], ngram_lm.fit_weights(ngram_lm.cell_ratios(x, n[:, 0], n[:, 1:]), n[:, 0]), atol=1e-6)
        assert np.abs(model.weights[b] - token_em(np.array(tokens.get(b, everything)))).max() < 0.01


def token_em(ratios):
    """Expectation-maximisation over single tokens, no cells."""
    x = np.concatenate([np.ones((len(ratios), 1)), ratios], axis=1)
    w = np.full(x.shape[1], 1 / x.shape[1])
    for _ in range(200):
        share = x * w
        share /= share.sum(axis=1)[:, None]
        w = (share.sum(axis=0) + 1) / (len(x) + x.shape[1])
    return w


def test_weights_equal_unquantised_em():
    rng = np.random.default_rng(1)
    ratios = np.exp2(rng.uniform(0, 12, (4000, 2)))
    octaves = np.log2(ratios)
    cells, which = np.unique(np.rint(ngram_lm.STEPS * octaves).astype(np.int64), axis=0, return_inverse=True)
    n = np.bincount(which.ravel())
    sums = np.stack([np.bincount(which.ravel(), weights=np.rint(ngram_lm.FINE * o)) for o in octaves.T], axis=1)
    assert len(cells) < 700
    assert np.abs(ngram_lm.fit_weights(ngram_lm.cell_ratios(cells, n, sums), n) - token_em(ratios)).max() < 0.01


def test_scores_of_nothing(spark):
    assert ngram_lm.fit_and_score(docs(spark, []))[0].count() == 0


def test_ngrams_are_numbered_without_sorting_positions(monkeypatch):
    """The same numbers as by sorting positions, which took most of the time; only codes that leave no room do that."""
    rng = np.random.default_rng(6)
    for top in (1, 9, 2**40):
        codes = rng.integers(0, top, 2_000)
        want = np.unique(codes, return_inverse=True)
        assert all(np.array_equal(a, b) for a, b in zip(ngram_lm._numbered(codes), want, strict=True))
    wide = rng.integers(0, 2**62, 2_000).repeat(2)
    assert all(np.array_equal(a, b) for a, b in zip(ngram_lm._numbered(wide), np.unique(wide, return_inverse=True), strict=True))
    assert [len(x) for x in ngram_lm._numbered(np.zeros(0, np.int64))] == [0, 0]

    lengths = np.array([3, 8, 13])  # two start symbols, words 2 to 4, an end
    ids = np.concatenate([[0, 0, *rng.integers(2, 5, n - 3), 1] for n in lengths]).astype(np.int32)
    at = blocks.places(lengths)

    def sorts(*args, **kwargs):
        raise AssertionError("positions are sorted")

    monkeypatch.setattr(ngram_lm.np, "unique", sorts)
    levels = ngram_lm._levels(ids, at, 3, 5)
    for k in range(1, 4):
        where = levels[k - 1][2]
        grams = {p: tuple(ids[p - k + 1 : p + 1]) for p in range(len(ids)) if at[p] >= max(k - 1, 1)}
        assert {p for p in range(len(ids)) if where[p] >= 0} == set(grams)
        named = {(where[p], g) for p, g in grams.items()}
        assert len(named) == len({n for n, _ in named}) == len(set(grams.values()))
        for n, g in named:
            assert levels[k - 1][1][n] == g[-1]


# 2 -----------------------------------------------------------------------------------


def test_perspectives(spark):
    rows = [(1, 0, "system", "Be kind."), (1, 1, "ann", "Hi"), (1, 2, "bob", "Hello"), (1, 3, "cy", None), (2, 0, "system", "alone"), (None, 0, None, "x"), (3, 0, "ann", "a"), (3, 0, "ann", "a")]
    t = spark.createDataFrame([(*r, "x") for r in rows], "conv_id long, turn long, role string, text string, perspective string")
    out = perspectives.rotate(t)
    assert out.count() == 3 * 4 + 1 + 2
    one = {r.perspective: (r.text, [(s.start, s.end) for s in r.loss_spans]) for r in perspectives.dialogues(out).where("conv_id = 1").collect()}
    assert set(one) == {"ann", "bob", "cy"}
    text, spans = one["bob"]
    assert text == "<|system|>Be kind.<|end|>\n<|user name=ann|>Hi<|end|>\n<|assistant|>Hello<|end|>\n<|user name=cy|><|end|>\n"
    assert [text[a:b] for a, b in spans] == ["Hello<|end|>\n"]
    assert perspectives.rotate(t.limit(0)).count() == 0


# 3 -----------------------------------------------------------------------------------


def brute_components(rows, percent=75):
    sets = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    inv = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            inv[x].append(i)
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, s in sets.items():
        c = Counter()
        for x in s:
            c.update(inv[x])
        for j, o in c.items():
            if j > i and 100 * o >= percent * (len(s) + len(sets[j]) - o):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(s), find(i)) for i, s in sets.items()}


def near_copies(seed=4):
    """Clusters of chained near copies around the threshold, shared passages, exact copies."""
    rng = random.Random(seed)
    word = lambda: "w%d" % rng.randrange(5000)
    passage, rows, i = [word() for _ in range(40)], [], 0
    for size in (1, 2, 5, 40, 160):
        base = [word() for _ in range(rng.choice((30, 60, 120)))]
        for _ in range(size):
            w = list(base)
            for _ in range(rng.randrange(0, max(2, len(w) // 25))):
                w[rng.randrange(len(w))] = word()
            rows.append((i, " ".join(w)))
            i += 1
    for n in range(0, 60):
        rows.append((i, " ".join(passage + [word() for _ in range(n % 14)])))
        i += 1
    rows += [(i + k, rows[k][1].upper()) for k in range(0, 60, 3)]
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("group", [8, 128])
def test_join_equals_brute_force(spark, monkeypatch, group):
    monkeypatch.setattr(ngram_join, "GROUP", group)
    rows = near_copies()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similar_components(docs(spark, rows)).collect()}
    assert got == brute_components(rows)


def test_join_over_common_passages(spark, monkeypatch):
    """Documents made of the same few passages: every shingle is frequent, and tokens are cut into cells."""
    monkeypatch.setattr(ngram_join, "LIST", 3)
    monkeypatch.setattr(ngram_join, "GROUP", 4)
    rng = random.Random(11)
    passages = [" ".join(f"p{k}w{j}" for j in range(rng.randrange(6, 30))) for k in range(9)]
    rows = [(i, " ".join(rng.choice(passages) for _ in range(rng.randrange(1, 9)))) for i in range(220)]
    rows += [(300 + k, " ".join([*passages, f"own{k}"])) for k in range(20)]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similar_components(docs(spark, rows)).collect()}
    assert got == brute_components(rows)


def test_documents_joined_by_one_without_id(spark):
    base = [f"w{k}" for k in range(60)]
    left, right = base[:52] + [f"a{k}" for k in range(8)], [f"b{k}" for k in range(8)] + base[8:]
    for bridge in (3, None):
        rows = [(1, " ".join(left)), (2, " ".join(right)), (bridge, " ".join(base)), (None, "only without an id here"), (None, "only without an id here"), (9, None)]
        assert len({c for _, c in brute_components([rows[0], rows[1]]).values()}) == 2
        got = sorted(((r.doc_id, r.component_id) for r in ngram_join.similar_components(docs(spark, rows)).collect()), key=str)
        assert got == sorted([(1, 1), (2, 1), (bridge, 1), (None, None), (None, None), (9, 9)], key=str)


def test_join_of_awkward_rows(spark):
    got = [(r.doc_id, r.n_shingles, r.component_id) for r in ngram_join.similar_components(docs(spark, AWKWARD)).collect()]
    assert len(got) == len(AWKWARD)
    by = {r[0]: r for r in got}
    assert by[5][2] == by[6][2] == 5 and by[3] == (3, 0, 3) and by[4] == (4, 1, 4) and by[8][1] == 2
    assert ngram_join.similar_components(docs(spark, [])).count() == 0


# 4 -----------------------------------------------------------------------------------


def brute_measure(t):
    w = [x for x in __import__("re").split(r"[\x20\x09-\x0D]+", t or "") if x]
    seen, dup = set(), 0
    for line in (t or "").split("\n"):
        if __import__("re").search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    windows = defaultdict(list)
    for k in range(len(w) - 4):
        windows[tuple(w[k : k + 5])].append(k)
    rep = {p for v in windows.values() if len(v) > 1 for k in v for p in range(k, k + 5)}
    return (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), dup, len(rep))


def test_rule_statistics(spark):
    texts = [r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()] + [t for _, t in AWKWARD[:-1]] + ["a b c d e a b c d e", "a a a a a a", "x\r\nx\r\n \n\n", "a b c d e"]
    for t in texts:
        assert quality.measure(None if t is None else t.encode())[0] == brute_measure(t), t[:80]


def test_forest_separates_and_keeps_columns(spark):
    d, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = quality.fit(d, labels)
    assert model == model and 0 < model.threshold < 1
    v = quality.judge(d, model).join(labels, "doc_id")
    bad, good = v.where("quality = 0"), v.where("quality = 1")
    assert bad.where("kept").count() <= 0.1 * bad.count() and good.where("not kept and not base_failed").count() <= 0.02 * good.count()
    kept = quality.keep_good(d.withColumn("kept", F.lit(5)), model)
    assert kept.columns == [*d.columns, "kept"] and kept.count() == quality.judge(d, model).where("kept").count()


def brute_path(forest, node, x, depth=0):
    """Path length of one row by walking one node at a time; a leaf adds what its rows would still need."""
    if forest.feature[node] < 0:
        return forest.path[node]
    side = forest.left if x[forest.feature[node]] < forest.value[node] else forest.right
    return brute_path(forest, side[node], x, depth + 1)


def test_path_lengths_and_scores_equal_brute_force():
    rng = np.random.default_rng(4)
    rows = rng.normal(0.5, 0.1, (300, 3))
    box = np.stack([np.zeros(3), np.ones(3)])
    forest = quality.grow(rows, box, trees=20, per_tree=64)
    seen = np.vstack([rows[:40], rng.uniform(0, 1, (40, 3))])
    want = [2 ** -(np.mean([brute_path(forest, r, x) for r in forest.roots]) / quality.expected_path(64)) for x in seen]
    assert np.allclose(forest.scores(seen), want)
    assert forest.scores(np.array([[0.99, 0.01, 0.99]]))[0] > forest.scores(np.array([[0.5, 0.5, 0.5]]))[0] + 0.1
    # every leaf's path is its depth and what a random tree of its rows adds; splits lie in the node's box
    for k, root in enumerate(forest.roots[:5]):
        sample = rows[_picks(300, 64, k)]

        def walk(node, x, low, high, depth):
            if forest.feature[node] < 0:
                assert np.isclose(forest.path[node], depth + quality.expected_path(len(x)))
                return
            f, v = forest.feature[node], forest.value[node]
            assert low[f] <= v <= high[f]
            up, down = high.copy(), low.copy()
            up[f] = down[f] = v
            walk(forest.left[node], x[x[:, f] < v], low, up, depth + 1)
            walk(forest.right[node], x[x[:, f] >= v], down, high, depth + 1)

        if sample is not None and k == 0:
            walk(root, sample, box[0], box[1], 0)
    harmonic = sum(1 / i for i in range(1, 256))
    assert quality.expected_path(256) == pytest.approx(2 * harmonic - 2 * 255 / 256, abs=0.01)


def _picks(n, size, tree):
    """The rows of the first tree; later trees draw after the splits of the ones before."""
    return np.random.default_rng(7).choice(n, size, replace=False) if tree == 0 else slice(0)


def test_quality_of_bytes_that_are_no_text_and_of_repeated_labels(spark):
    good = [(k, " ".join(f"word{(k * 7 + j) % 97}" for j in range(40 + k % 9))) for k in range(40)]
    rows = good + [(1, good[1][1])] * 3000
    labels = spark.createDataFrame([(k, int(k % 4 > 0), 0) for k in range(40)], "doc_id long, quality int, toxic int")
    d = docs(spark, rows)
    assert len(quality._rates(d.select("doc_id", "text").withColumn("quality", F.lit(1)))) == 40
    model = quality.fit(d, labels)
    bad = spark.sql("SELECT 1L AS doc_id, cast(X'61FF62' AS string) AS text UNION ALL SELECT 2L, concat(cast(X'FF' AS string), repeat(' some words of text that go on', 3))")
    assert quality.keep_good(bad, model).count() == quality.judge(bad, model).where("kept").count()


def test_all_labelled_rows_make_the_model(spark):
    """The only bad row is the last of 6 500 by the MD5 of its id, which a sample of the first 6 000 leaves out."""
    last = max(range(6_500), key=lambda k: (hashlib.md5(str(k).encode()).hexdigest(), k))
    text = lambda k: " ".join(f"word{(k * 7 + j) % 97}" for j in range(30 + k % 9)) if k != last else "!! ## WHAT? " + " ".join(f"A#{j}!" for j in range(30))
    d = docs(spark, [(k, text(k)) for k in range(6_500)])
    labels = spark.createDataFrame([(k, int(k != last), 0) for k in range(6_500)], "doc_id long, quality int, toxic int")
    model = quality.fit(d, labels)
    out = quality.judge(d, model)
    assert [r.doc_id for r in out.where("not kept").collect()] == [last] and not out.where("base_failed").count()
    x, bad = np.array([quality.measure(text(k).encode())[1] for k in range(6_500)]), np.arange(6_500) == last
    assert model.threshold == quality.calibrate(model.forest.scores(x), bad)
    alone = spark.createDataFrame([], labels.schema)
    assert quality.fit(d, alone).forest.scores(x[[last]])[0] > quality.fit(d, alone).forest.scores(x[:9]).max()


def test_threshold_and_trees_from_several_tasks(spark):
    rng = np.random.default_rng(5)
    x = rng.uniform(0, 1, (3_000, len(quality.RATES))).round(1)
    forest = quality.grow(x, np.stack([x.min(axis=0), x.max(axis=0)]), trees=3, per_tree=16)
    rows = lambda bad, own=None: spark.createDataFrame([(k, r, bool(o), int(not b)) for k, (r, b, o) in enumerate(zip(x.tolist(), bad, np.zeros(3_000) if own is None else own, strict=True))], "doc_id long, rates array<double>, base_failed boolean, quality int")
    score = forest.scores(x)
    for bad in (score > np.quantile(score, 0.9), rng.uniform(0, 1, 3_000) < 0.4, score < 0.3, score < np.quantile(score, 0.2), np.ones(3_000, bool)):
        assert quality._calibrate_all(rows(bad), forest) == quality.calibrate(score, bad)
    own = rng.uniform(0, 1, 3_000) < 0.5
    bad = (score > np.quantile(score, 0.8)) | own
    assert quality._calibrate_all(rows(bad, own), forest) == quality.calibrate(score[~own], bad[~own])
    drawn = quality._draw(rows(bad).repartition(7), 3_000, trees=5, per_tree=40)
    for tree, got in enumerate(drawn):
        assert np.array_equal(got, x[np.argsort(quality._places(np.arange(3_000), tree))[:40]])
    assert len({got.tobytes() for got in drawn}) == 5
    assert [len(got) for got in quality._draw(rows(bad).limit(3), 3, trees=2)] == [3, 3]


def test_forest_on_awkward_rows(spark):
    d, none = docs(spark, AWKWARD), spark.createDataFrame([], "doc_id long, quality int, toxic int")
    out = quality.judge(d, quality.fit(d, none)).collect()
    assert len(out) == len(AWKWARD) and all(r.base_failed for r in out)
    assert quality.judge(docs(spark, []), quality.fit(docs(spark, []), none)).count() == 0
    assert quality.calibrate(np.array([0.5, 0.5, 0.9]), np.array([False, False, True])) == pytest.approx(0.7)


# 5 -----------------------------------------------------------------------------------


def test_packing(spark):
    rng = random.Random(2)
    lengths = sorted((rng.randrange(1, 4097) if rng.random() < 0.3 else rng.randrange(1, 400) for _ in range(700)), reverse=True)
    bins, offsets, final = packing.pack_lengths(lengths)
    inside = defaultdict(list)
    for n, b, o in zip(lengths, bins, offsets, strict=True):
        inside[b].append((o, n))
    for b, own in inside.items():
        own.sort()
        assert own[0][0] == 0 and all(a + n == c for (a, n), (c, _) in zip(own, own[1:], strict=False))
        size = sum(n for _, n in own)
        assert final[b] == min(c for c in packing.CAPACITIES if c >= size)
    assert sum(lengths) / sum(final) > 0.95


def naive_best_fit(lengths, cap):
    room, out = [], []
    for n in lengths:
        fits = [r for r in room if r >= n]
        if fits:
            k = room.index(min(fits))
            room[k] -= n
        else:
            room.append(cap - n)
        out.append(sorted(room))
    return sorted(room)


def test_one_capacity_is_plain_best_fit():
    lengths = sorted((random.Random(k).randrange(1, 101) for k in range(300)), reverse=True)
    bins, _, final = packing.pack_lengths(lengths, (100,))
    used = Counter()
    for n, b in zip(lengths, bins, strict=True):
        used[b] += n
    assert sorted(100 - u for u in used.values()) == naive_best_fit(lengths, 100)


def naive_variable_best_fit(lengths, caps, charge):
    """The same rule over plain lists: the fullest open bin, else the length of least cost for each token it can expect."""
    bins = []  # [capacity, pieces], the last changed one last
    for i, n in enumerate(lengths):
        fits = [b for b in bins if b[0] - sum(b[1]) >= n]
        if fits:
            room = min(b[0] - sum(b[1]) for b in fits)
            best = [b for b in fits if b[0] - sum(b[1]) == room][-1]  # of equal ones the last changed
            bins = [b for b in bins if b is not best] + [[best[0], [*best[1], n]]]
            continue
        costs = []
        for c in caps:
            if c >= n:
                beside = sum(x for x in lengths[i + 1 :] if x <= c - n)
                costs.append(((c + charge) / (n + min(c - n, beside)), c))
        bins.append([min(costs)[1], [n]])
    return sorted((min(c for c in caps if c >= sum(p)), sum(p)) for _, p in bins)


@pytest.mark.parametrize("seed", range(12))
def test_several_capacities_equal_the_plain_rule(seed):
    rng = random.Random(seed)
    caps, charge = ((8, 16, 32, 64), (10, 25, 100), (5, 6, 7))[seed % 3], rng.choice((0, 2, 9))
    lengths = sorted((rng.randrange(1, caps[-1] + 1) if rng.random() < 0.4 else rng.randrange(1, caps[0] + 1) for _ in range(rng.randrange(1, 120))), reverse=True)
    bins, _, final = packing.pack_lengths(lengths, caps, charge)
    used = Counter()
    for n, b in zip(lengths, bins, strict=True):
        used[b] += n
    assert sorted((final[b], u) for b, u in used.items()) == naive_variable_best_fit(lengths, caps, charge)


def test_packing_of_awkward_rows(spark):
    rows = packing.pack(packing.word_lengths(docs(spark, AWKWARD)), group_tokens=1000).collect()
    got = Counter()
    for r in rows:
        got[r.row] += r.length
    assert sorted(got.values()) == sorted(len((t or "").encode().split()) + 1 for _, t in AWKWARD if (t or "").strip(" \n\t"))
    assert packing.pack(packing.word_lengths(docs(spark, []))).count() == 0


# 6 -----------------------------------------------------------------------------------


def test_warc_round_trip(spark):
    rows = [(5, "http://a/b", "<p>Ünï</p>" * 900), (3, "u", "same"), (9, "u", "same"), (9, "u", "same"), (4, None, None), (2, "a b\n", ""), (None, "u", "same"), (None, None, "only here")]
    pages = spark.createDataFrame([(*r, "x", 1) for r in rows], "page_id long, url string, html string, sha string, first long")
    folder, files = warc.write_archives(pages, segment_bytes=700, chunk_bytes=50, file_bytes=900)
    got = warc.read_archives(spark, folder, files).collect()
    assert len(got) == len(rows) and all(r.error is None for r in got)
    by = defaultdict(list)
    for r in got:
        by[r.page_id].append(r)
    assert bytes(by[5][0].payload).decode() == rows[0][2] and by[3][0].record_type == "response"
    assert [(r.record_type, r.refers_to, r.payload_bytes) for r in by[9]] == [("revisit", 3, 4)] * 2
    assert by[2][0].record_type == "response" and by[4][0].refers_to == 2 and by[4][0].payload_digest == warc.digest_of(b"")
    folder, files = warc.write_archives(pages.limit(0))
    assert warc.read_archives(spark, folder, files).count() == 0


def test_revisits_by_the_standard_s_fields(spark, tmp_path):
    import gzip
    import io

    rows = [(k, f"http://h/{k}", "a page of its own %d " % k * 300) for k in range(4)] + [(k, f"http://h/{k}", "one text") for k in range(10, 14)] + [(20, "http://t", "twice"), (20, "http://t", "twice"), (21, "http://u", "twice")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder, files = warc.write_archives(pages, folder=f"file://{tmp_path}/w")
    found = []
    for f in files.collect():
        data = open(f"{tmp_path}/w/{f.file}", "rb").read()
        found += [r for r, _ in warc.records_of(io.BytesIO(gzip.decompress(data)))]
    of = defaultdict(list)
    for r in found:
        of[r.get("warc-page-id"), r["warc-type"]].append(r)
    first = of["10", "response"][0]
    for k in (11, 12, 13):
        r = of[str(k), "revisit"][0]
        assert r["warc-refers-to"] == first["warc-record-id"] and r["warc-refers-to-target-uri"] == "http://h/10" and r["warc-refers-to-date"] == first["warc-date"]
    assert len(of["20", "response"]) == 2 and len({r["warc-record-id"] for r in found}) == len(found)
    assert "warc-refers-to" not in of["21", "revisit"][0] and of["21", "revisit"][0]["warc-refers-to-target-uri"] == "http://t"
    # production sizes cut these pages into segments
    assert sum(r["warc-type"] == "continuation" for r in found) >= 4
    assert all(r.error is None for r in warc.read_archives(spark, folder, files).collect())
    whole = warc.record([("WARC-Type", "response")], b"abcdef")
    assert [b for _, b in warc.records_of(io.BytesIO(whole * 2))] == [b"abcdef"] * 2
    for broken in (whole[:-5], b"x" + whole, whole.replace(b"Length: 6", b"Length: 5")):
        with pytest.raises(ValueError):
            list(warc.records_of(io.BytesIO(broken)))


def test_segments_and_framing():
    assert warc.unframe(b"3;x=y\r\nabc\r\n0\r\nTrailer: 1\r\n\r\n") == b"abc" == warc.unframe(warc.frame(b"abc", 2))
    part = lambda n, b, total=None: {"number": n, "block": b, "total": total}
    assert warc.join_segments([part(2, b"b", 2), part(1, b"a")])[1:] == (b"ab", None)
    assert warc.join_segments([part(1, b"a"), part(3, b"c", 2)])[2] and warc.join_segments([part(1, b"a"), part(2, b"b", 9)])[2]


# 7 -----------------------------------------------------------------------------------


def brute_distance(pattern, text):
    row = [0] * (len(text) + 1)
    for i, c in enumerate(pattern, 1):
        new = [i]
        for j, t in enumerate(text, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != t)))
        row = new
    return min(row), row.index(min(row))


def test_myers_equals_dynamic_programming():
    rng = random.Random(6)
    for _ in range(400):
        p, t = ("".join(rng.choice("abc") for _ in range(rng.randrange(1, n))) for n in (70, 90))
        assert decontaminate.myers(p, t) == brute_distance(p, t)


def test_matches_equal_brute_force(spark):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdef") for _ in range(rng.randrange(2, 6)))
    items = [(k, " ".join(word() for _ in range(rng.randrange(8, 40)))) for k in range(12)] + [(50, ""), (51, None), (52, "ab"), (53, "Twice the Item text here"), (54, "twice  the item\ntext here")]

    def edited(t):
        t = list(t)
        for _ in range(rng.randrange(0, len(t) // 12 + 1)):
            k = rng.randrange(len(t))
            t[k : k + 1] = rng.choice(([], [rng.choice("abc")], [t[k], "x"]))
        return "".join(t)

    rows = [(d + 1000, " ".join([word() for _ in range(20)] + [edited(rng.choice(items[:12])[1])] + [word() for _ in range(20)])) for d in range(80)] + [(99, "x TWICE THE ITEM  text here y"), *AWKWARD]
    bench = spark.createDataFrame([(*i, "x") for i in items], "item_id long, text string, doc_id string")
    want = set()
    for d, t in rows[:-1]:
        p = decontaminate.plain(t)
        for i, s in items:
            s = decontaminate.plain(s)
            if s and p and brute_distance(s, p)[0] <= decontaminate.edit_budget(s):
                want.add((d, i, brute_distance(s, p)[0]))
    for limit in (100, 10**6):
        got = decontaminate.find_matches(docs(spark, rows), bench, limit=limit)
        assert {(r.doc_id, r.item_id, r.distance) for r in got.collect()} == want
    clean = decontaminate.drop_contaminated(docs(spark, rows), bench, limit=100)
    assert clean.columns == docs(spark, []).columns and clean.count() == sum(d not in {w[0] for w in want} for d, _ in rows)
    assert decontaminate.find_matches(docs(spark, rows), bench.limit(0)).count() == 0


def test_matches_in_bytes_that_are_no_text(spark):
    bench = spark.createDataFrame([(1, "the item that is looked for here")], "item_id long, text string")
    bad = spark.sql("SELECT 1L AS doc_id, concat(cast(X'61FF62' AS string), ' the item that is looked for here') AS text UNION ALL SELECT 2L, cast(X'FF' AS string)")
    assert [r.doc_id for r in decontaminate.find_matches(bad, bench).collect()] == [1]
    assert [r.doc_id for r in decontaminate.drop_contaminated(bad, bench).collect()] == [2]


# 8 -----------------------------------------------------------------------------------


def brute_templates(rows):
    """Templates from whole occurrence vectors in memory: {host: (tokens, texts)} of hosts that have one."""
    hosts = defaultdict(dict)
    for _, url, source in rows:
        page = html_text.Page(source or "")
        said = tuple(t for _, t, apart, _ in page.blocks if not apart)
        m = __import__("re").match(r"[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]*)", url or "")
        pages = hosts[m[1].lower() if m else ""]
        key = said or source or ""
        tokens = Counter({("tag", p, t): n for (p, t), n in Counter(page.tags).items()}) + Counter({("text", b[0], b[1]): n for b, n in Counter((b[0], b[1]) for b in page.blocks).items()})
        pages[key] = {t: max(n, pages.get(key, {}).get(t, 0)) for t, n in (Counter(pages.get(key, {})) | tokens).items()}
    out = {}
    for host, pages in hosts.items():
        vectors = defaultdict(list)
        for t in {t for p in pages.values() for t in p}:
            v = tuple(p.get(t, 0) for p in pages.values())
            support = sum(n > 0 for n in v)
            if support >= html_text.MIN_PAGES and support >= html_text.MIN_SHARE * len(pages):
                vectors[v].append(t)
        number = lambda t: html_text.token_of(t[1], f"<{t[2]}" if t[0] == "tag" else t[2])
        member = lambda t: (number(t), f"{t[1]}/{t[2]}" if t[0] == "tag" else t[1], html_text.KIND_TAG if t[0] == "tag" else html_text.KIND_TEXT)
        classes = [(sum(n > 0 for n in v), [member(t) for t in own]) for v, own in vectors.items() if len(own) > 1]
        if classes:
            tokens = html_text.nest(classes)
            out[host] = (tokens, {m[0] for _, own in classes for m in own if m[2] == html_text.KIND_TEXT} & tokens)
    return out


def test_templates_equal_whole_vectors(spark):
    page = "<html><body><div class=top><p>Menu</p><p>Menu</p></div><div id=x1><p>{0} body of this page</p>{1}</div><div class=low><p>Imprint</p></div></body></html>"
    rows = [(k, f"http://h{k % 3}.org/{k}", page.format(f"page {k}", "<p>Letter</p>" * (k % 4) if k % 3 else "<ul><li>Card</li></ul>")) for k in range(40)]
    rows += rows[:20] + rows[:5] + [(99, None, None), (98, None, "")]
    given = [tuple(r) for r in spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "url", "html").collect()]
    for some in (rows, given * 2):
        pages = spark.createDataFrame(some, "page_id long, url string, html string").repartition(5)
        got = {r.host: (set(r.tokens or ()), set(r.texts or ())) for r in html_text.deduce_templates(pages).collect() if r.tokens is not None}
        assert got == brute_templates(some)
    once, twice = ({r.page_id: r.text for r in html_text.extract(spark.createDataFrame(x, "page_id long, url string, html string")).collect()} for x in (given, given * 3))
    assert once == twice

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{{a:b}}</style><script>var x="</p>";</script></head><body><header><h1>Site</h1></header>
<nav><ul><li><a href=/>Home</a></ul></nav><div class="cookie-notice">We use cookies</div><article><header><h2>Head &amp; line {0}</h2></header><p>First <b>bold</b>
  text&nbsp;{0}<br>more<p>Second {0} &lt;x&gt;<div class="share">Share</div><p>Read our daily letter</p></article><aside>Side</aside>
<section id="comments"><p>nice one</p></section><form><p>Mail</p></form><footer>&copy; me</footer>"""


def test_article_text(spark):
    n = 8
    rows = [(k, f"http://Host.example/{k}", PAGE.format(k)) for k in range(n)] + [(100, None, None), (101, "x", ""), (102, "http://o/", "plain &amp; text <b>only"), (102, "http://o/", "plain &amp; text <b>only")]
    pages = spark.createDataFrame([(*r, "x", "y") for r in rows], "page_id long, url string, html string, host string, texts string")
    got = defaultdict(list)
    for r in html_text.extract(pages).collect():
        got[r.page_id].append(r)
        assert r.n_chars == len(r.text)
    # a block that every page of the host has is its template's, not the article's
    assert [got[k][0].text for k in range(n)] == [f"Head & line {k}\n\nFirst bold text {k} more\n\nSecond {k} <x>" for k in range(n)]
    assert got[100][0].text == got[101][0].text == "" and [r.text for r in got[102]] == ["plain & text only"] * 2
    assert html_text.extract(pages.limit(0)).count() == 0


def test_slot_of_pages_without_article(spark):
    page = "<html><body><div class=top><p>Menu of the site</p></div><div id=x1><p>{0} body one of this page</p><p>and two {0}</p></div><div id=x2><p>{0}</p></div></body></html>"
    pages = spark.createDataFrame([(k, "http://h/", page.format("page %d" % k)) for k in range(9)], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_text.extract(pages).collect()}
    assert got[3] == "page 3 body one of this page\n\nand two page 3"


def test_copies_of_an_article_are_not_template(spark):
    rows = [(k, f"http://h/{k}", PAGE.format(max(k, 4))) for k in range(8)]  # rows 0 to 4 hold one article
    rows += [(10 + k, "http://g/", PAGE.format("same")) for k in range(6)]  # one row six times
    # copies whose pages differ outside the article, most of a large host
    rows += [(20 + k, f"http://f/{k}", PAGE.format("x" if k < 15 else k).replace("Side", f"Side {k}")) for k in range(22)]
    # the furniture alone is left of one page
    rows += [(60, "http://f/60", "<html><body><article><p>Read our daily letter</p></article></body></html>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_text.extract(pages).collect()}
    own, letter = "Head & line {0}\n\nFirst bold text {0} more\n\nSecond {0} <x>", "\n\nRead our daily letter"
    assert [got[k] for k in range(8)] == [own.format(max(k, 4)) + letter for k in range(8)]  # four distinct pages have no template
    assert [got[10 + k] for k in range(6)] == [own.format("same") + letter] * 6
    assert [got[20 + k] for k in range(22)] == [own.format("x" if k < 15 else k) for k in range(22)]
    assert got[60] == "Read our daily letter"


def test_body_outside_a_small_article(spark):
    page = "<html><body><div class=top><p>Menu of the site, the same on every page and longer than any of its bodies put together</p></div><article><p>Card {0}</p></article><div id=x1><p>{0} body one of this page</p><p>and two {0}</p></div><main><p>Go {0}</p></main></body></html>"
    other = "<html><body><article><p>Article {0} of another layout, {0}</p></article><p>Next {0}</p></body></html>"
    rows = [(k, "http://h/", (page if k < 9 else other).format("page %d" % k)) for k in range(12)]
    got = {r.page_id: r.text for r in html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert [got[k] for k in range(9)] == [f"page {k} body one of this page\n\nand two page {k}" for k in range(9)]
    assert got[10] == "Article page 10 of another layout, page 10"


def test_given_pages(spark):
    for r in html_text.extract(spark.read.parquet(f"{SF}/pages.parquet")).collect():
        assert r.text and "track(" not in r.text and "©" not in r.text


# 9 -----------------------------------------------------------------------------------


def test_token_files(spark):
    import zlib

    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    rows = AWKWARD + [(-3, "it's <|endoftext|> ΣΑΣ é x\x85y 12"), (r := 10, "tail")]
    folder, files = token_files.write_ids(docs(spark, rows), path, file_ids=100)
    got = sorted(token_files.read_ids(spark, folder, files).collect(), key=lambda x: x.start)
    t = Tokenizer.from_file(path)
    crc = lambda ids: zlib.crc32(np.array(ids, "<u4").tobytes())
    want = [(i, t.encode(s or "", add_special_tokens=False).ids + [2]) for i, s in rows]
    key = lambda x: (x[0] is not None, x[0] or 0, x[2])
    assert sorted(((x.doc_id, x.n_tokens, x.ids_crc32) for x in got), key=key) == sorted(((i, len(x), crc(x)) for i, x in want), key=key)
    assert [x.start for x in got] == np.concatenate([[0], np.cumsum([x.n_tokens for x in got])[:-1]]).tolist()
    assert [x.doc_id for x in got] == sorted((i for i, _ in rows), key=lambda i: (i is not None, i or 0)) and r == 10
    folder, files = token_files.write_ids(docs(spark, []), path)
    assert token_files.read_ids(spark, folder, files).count() == 0


def test_query_gives_the_ids_of_the_library_as_loaded(spark, tmp_path):
    import zlib

    import public_tokenizers
    from tokenizers import Tokenizer

    from corpusdedup.llm.queries import op9_bit_packed_ids

    texts = ["a <|endoftext|> b", "x<|startoftext|>Y.", "<|ENDOFTEXT|> <|endoftext|", "<|endoftext|><|endoftext|>", "it's plain, text 12.", "", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = [[*library.encode(t or "", add_special_tokens=False).ids, 2] for t in texts]
    assert want[0] == [320, 49407, 321, 2]
    got = sorted(op9_bit_packed_ids(spark, str(tmp_path)).collect(), key=lambda r: r.doc_id)
    assert [(r.n_tokens, r.ids_crc32) for r in got] == [(len(x), zlib.crc32(np.array(x, "<u4").tobytes())) for x in want]


@pytest.mark.parametrize("bits", [1, 3, 8, 11, 16, 17, 20])
def test_bit_packing(bits):
    a = np.random.default_rng(bits).integers(0, 2**bits, 20_000).astype(np.uint32)
    f = token_files.PackedFile(token_files.encode_file([None, 4], [a[:7], a[7:]], bits))
    assert f.doc_ids == [None, 4] and (f.document(1) == a[7:]).all() and (f.ids(5_000, 13_000) == a[5_000:13_000]).all()


# 10 ----------------------------------------------------------------------------------


def test_placement(spark):
    table = sharding.fill_table()
    n = Counter(table)
    assert max(n.values()) - min(n.values()) <= 1
    fewer = sharding.fill_table(sharding.SHARDS[:-1])
    assert sum(a == b for a, b in zip(table, fewer, strict=True) if a < len(sharding.SHARDS) - 1) > 0.8 * len(table) * (len(sharding.SHARDS) - 1) / len(sharding.SHARDS)
    got = sharding.place(docs(spark, AWKWARD), "doc_id")
    assert got.count() == len(AWKWARD) and all(table[r.slot] == r.shard for r in got.collect())
    assert "Python" not in got._jdf.queryExecution().toString() and sharding.place(docs(spark, []), "doc_id").count() == 0
    with pytest.raises(ValueError):
        sharding.fill_table(slots=1000)


# pipeline ----------------------------------------------------------------------------


def test_pipeline(spark):
    d = spark.read.parquet(f"{SF}/documents.parquet").withColumn("row", F.lit(1))
    d = d.unionByName(d.limit(3)).unionByName(spark.createDataFrame([(None, None, None, None, None, 1)], d.schema))
    before = d
    for name, f in corpus_pipeline.STAGES[:-1]:
        after = corpus_pipeline.stage(f(spark, before, SF), "t")
        assert after.columns == d.columns and 0 < after.count() <= before.count(), name
        before = after
    ids = [r.doc_id for r in before.select("doc_id").collect()]
    assert len(set(ids)) == len(ids)
    rows = brute_components([(r.doc_id, r.text) for r in before.collect()])
    assert all(c == i for i, (_, c) in rows.items())
    assert decontaminate.find_matches(before, spark.read.parquet(f"{SF}/benchmark.parquet")).count() == 0
    packed = corpus_pipeline.STAGES[-1][1](spark, before, SF)
    assert packed.select("doc_id").distinct().count() == len(ids)
    for _, f in corpus_pipeline.STAGES:
        assert f(spark, d.limit(0), SF).count() == 0


def test_an_id_with_two_texts(spark):
    text = lambda w: " ".join(f"{w}{k}" for k in range(60))
    rows = [(1, text("b")), (2, text("a")), (2, text("b")), (3, text("c")), (3, text("C")), (4, text("d")), (4, text("d"))]
    got = corpus_pipeline.near_duplicates(spark, docs(spark, rows), SF)
    assert got.columns == docs(spark, []).columns
    assert Counter((r.doc_id, r.text[0].lower()) for r in got.collect()) == Counter([(1, "b"), (2, "a"), (3, "c"), (4, "d")])


def test_word_encoder_gives_the_library_s_ids_on_awkward_text():
    import public_tokenizers
    from tokenizers import Tokenizer

    from corpusdedup.llm.token_files import WordEncoder

    path = public_tokenizers.path("word_bpe_49k.json")
    library, ordinary = Tokenizer.from_file(path), Tokenizer.from_file(path)
    ordinary.encode_special_tokens = True
    texts = [
        None,
        "",
        "don't. 'tis' it's, we'll' x'.. ab…. 12.5% a1. !a !!. ab.c. a.\tb.\nc,\x0bd.\x0ce;\rf \x1cab.\x1d <|endoftext|>. É.! ÷÷. ß. ²³. ½,",
        "İstanbul. İ İ. a̸. ≮ café. café. é, ́. क़ल. ſs. ŉn. ﬁn. Σας. 한국. 가",
        "".join(f"{chr(i)}. a{chr(i)}, " for i in range(33, 0x3000)),
        " ".join(chr(i) + chr(i + 1) for i in range(0xA1, 0xD7FE)),
        "a." * 3000,
    ]
    for added, t in ((True, library), (False, ordinary)):
        code = WordEncoder(path, 2, added)
        for _ in range(2):  # the second time every word is remembered
            for text, got in zip(texts, code.encode(pa.array(texts, pa.string())).to_pylist(), strict=True):
                assert np.frombuffer(got, "<u2").tolist() == [*t.encode(text or "", add_special_tokens=False).ids, 2]


def test_word_encoder_forgets_words(monkeypatch):
    import public_tokenizers
    from tokenizers import Tokenizer

    monkeypatch.setattr(token_files, "MEMORY", 5)
    path = public_tokenizers.path("word_bpe_49k.json")
    library, code = Tokenizer.from_file(path), token_files.WordEncoder(path, 2)
    rng = random.Random(3)
    for _ in range(60):
        texts = [" ".join(rng.choice(["and", "and,", "Été", "été.", "x-y", "12.", "ж", "Ω;", "don't", "the"]) for _ in range(rng.randrange(6))) for _ in range(3)]
        assert [np.frombuffer(x, "<u2").tolist() for x in code.encode(pa.array(texts)).to_pylist()] == [[*library.encode(t, add_special_tokens=False).ids, 2] for t in texts]


def test_ids_of_repeated_and_null_doc_ids(spark):
    rows = [(None, f"null {k} here") for k in range(60)] + [(7, f"hot word{k}") for k in range(60)] + [(7, "same")] * 20 + [(k, f"text {k}") for k in range(40)]
    path = __import__("public_tokenizers").path("word_bpe_49k.json")
    folder, files = token_files.write_ids(docs(spark, rows).repartition(3), path, file_ids=50)
    got = sorted(token_files.read_ids(spark, folder, files).collect(), key=lambda x: x.start)
    assert [x.start for x in got] == np.concatenate([[0], np.cumsum([x.n_tokens for x in got])[:-1]]).tolist()
    assert [x.doc_id for x in got] == sorted((i for i, _ in rows), key=lambda i: (i is not None, i or 0))
    # the rows of one id lie in several parts
    part = {r.file: r.part for r in files.collect()}
    held = defaultdict(set)
    for r in spark.read.format("binaryFile").load(f"{folder}/ids-*.bin").collect():
        for d in token_files.PackedFile(bytes(r.content)).doc_ids:
            held[d].add(part[r.path.rpartition("/")[2]])
    assert len(held[7]) > 2 and len(held[None]) > 1


def test_ids_of_bytes_that_are_no_text(spark):
    bad = spark.sql("SELECT 1L AS doc_id, cast(X'61FF62' AS string) AS text")
    path = __import__("public_tokenizers").path("word_bpe_49k.json")
    assert token_files.read_ids(spark, *token_files.write_ids(bad, path)).first().n_tokens > 1


def test_token_files_give_memory_back(spark, tmp_path, monkeypatch):
    # a worker lives on after its task, and what it holds counts as its executor's
    import public_tokenizers

    path = public_tokenizers.path("word_bpe_49k.json")

    def told():
        import uuid

        (tmp_path / uuid.uuid4().hex).touch()

    monkeypatch.setattr(token_files, "trim", told)
    rows = [(k, f"some words {k}") for k in range(40)]
    folder, files = token_files.write_ids(docs(spark, rows).repartition(3), path)
    encoded_and_written = len(list(tmp_path.iterdir()))
    assert encoded_and_written >= 4
    assert token_files.read_ids(spark, folder, files).count() == 40 and len(list(tmp_path.iterdir())) > encoded_and_written

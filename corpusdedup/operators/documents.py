"""Document-level baselines: exact copies, MinHash, exact Jaccard."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import WS
from ..session import drop_stage, release, shuffle_partitions, stage
from .components import connected_components

PRIME = 2_147_483_647
#: Hex digits of a shingle's MD5 that are its key: 60 bits fit a long.
BASE_DIGITS = 15


def exact_doc_dedup(docs: DataFrame) -> DataFrame:
    """The rows of each text that have its smallest id.

    Null texts are nobody's copies and stay. A row without id goes if a row with an id has
    its text; equal rows, and rows of one text that all lack ids, cannot be told apart and stay.
    """
    key = F.coalesce(F.md5("text"), F.concat(F.lit("-"), F.col("doc_id").cast("string")))
    first = docs.groupBy(key.alias("__text")).agg(F.min("doc_id").alias("__first"))
    return docs.join(first, key.eqNullSafe(F.col("__text")) & docs["doc_id"].eqNullSafe(F.col("__first")), "left_semi")


def words(text: Column) -> Column:
    """Lower-cased words between white space."""
    return F.filter(F.split(F.lower(text), rf"[{WS}]+"), lambda w: w != "")


def shingles(text: Column, n: int = 5, unit: str = "word") -> Column:
    """Distinct n-grams of words or characters; a shorter text is one shingle, an empty one has none.

    A look-ahead that captures gives the overlapping n-grams in one pass; a lambda over
    positions would split the text anew for each of them.
    """
    if unit == "char":
        plain = text
        grams = F.regexp_extract_all(text, F.lit(rf"(?s)(?=(.{{{n}}}))"), F.lit(1))
    else:
        plain = F.trim(F.regexp_replace(F.lower(text), rf"[{WS}]+", " "))
        grams = F.regexp_extract_all(plain, F.lit(rf"(?<![^ ])(?=((?:[^ ]+ ){{{n - 1}}}[^ ]+))"), F.lit(1))
    some = F.array_distinct(F.when(F.size(grams) > 0, grams).otherwise(F.array(plain)))
    return F.when(F.length(plain) > 0, some).otherwise(F.expr("cast(array() as array<string>)"))


def shingle_rows(docs: DataFrame, n: int = 5) -> DataFrame:
    """(doc_id, base): distinct shingles as 60-bit hashes, the first hex digits of their MD5."""
    x = docs.select("doc_id", F.explode(shingles(F.col("text"), n)).alias("s"))
    return x.select("doc_id", F.conv(F.substring(F.md5("s"), 1, BASE_DIGITS), 16, 10).cast("long").alias("base")).distinct()


def permutations(perms: int = 128, seed: int = 42) -> tuple[list[int], list[int]]:
    """Multipliers and offsets below the prime, from MD5 so that any engine can make them."""
    draw = lambda kind, k: int(hashlib.md5(f"{seed}-{kind}-{k}".encode()).hexdigest()[:8], 16)
    return [draw("a", k) % (PRIME - 1) + 1 for k in range(perms)], [draw("b", k) % PRIME for k in range(perms)]


def minhash_signature(docs: DataFrame, n: int = 5, perms: int = 128, seed: int = 42) -> DataFrame:
    """(doc_id, sig) by built-in functions: each slot the least of (a x + b) mod p over the shingles.

    Shingles are rows, so the minima are partial aggregates; documents without words have no signature.
    """
    a, b = permutations(perms, seed)
    mins = [F.min((F.lit(x) * F.col("low") + F.lit(y)) % F.lit(PRIME)).alias(f"m{k}") for k, (x, y) in enumerate(zip(a, b, strict=True))]
    low = (F.col("base") % F.lit(PRIME)).alias("low")
    return shingle_rows(docs, n).select("doc_id", low).groupBy("doc_id").agg(*mins).select("doc_id", F.array(*(f"m{k}" for k in range(perms))).alias("sig"))


def _modulo(x: np.ndarray) -> np.ndarray:
    """x mod PRIME, a Mersenne prime, for x below 2**62: two folds instead of a division."""
    for _ in range(2):
        x = (x & PRIME) + (x >> 31)
    return np.where(x >= PRIME, x - PRIME, x)


def minhash_signature_numpy(docs: DataFrame, n: int = 5, perms: int = 128, seed: int = 42) -> DataFrame:
    """The same signatures from an Arrow UDF: no shuffle, shingles of many texts in one matrix."""
    a, b = (np.array(x, np.int64) for x in permutations(perms, seed))
    md5, drop = hashlib.md5, 64 - 4 * BASE_DIGITS

    @F.pandas_udf("array<long>")
    def sign(texts: pd.Series) -> pd.Series:
        out: list[np.ndarray | None] = []
        base, sizes, at = [], [], []

        def flush() -> None:
            low = np.full((len(sizes), perms), PRIME, np.int64)
            x = np.frombuffer(b"".join(base), ">u8").astype(np.uint64) >> np.uint64(drop)
            x = (x % np.uint64(PRIME)).astype(np.int64)
            of = np.repeat(np.arange(len(sizes)), sizes)
            for k in range(0, len(x), 512):  # a piece of the matrix that stays in the core's cache
                part = _modulo(x[k : k + 512, None] * a + b)
                starts = np.flatnonzero(np.diff(of[k : k + 512], prepend=-1))
                rows = of[k + starts]
                low[rows] = np.minimum(low[rows], np.minimum.reduceat(part, starts, axis=0))
            for row, place in zip(low, at, strict=True):
                out[place] = row
            base.clear(), sizes.clear(), at.clear()

        for text in texts:
            out.append(None)
            w = text.split() if text else []
            if not w:
                continue
            grams = set(map(" ".join, zip(*(w[k:] for k in range(n)), strict=False))) or {" ".join(w)}
            base += [md5(g.encode()).digest()[:8] for g in grams]
            sizes.append(len(grams))
            at.append(len(out) - 1)
            if len(base) > 50_000:
                flush()
        flush()
        return pd.Series(out, dtype=object)

    # only the white space of words() may cut
    text = F.regexp_replace(F.lower("text"), rf"[{WS}]+", " ")
    # said to be nondeterministic, or the filter would run it a second time
    return docs.select("doc_id", sign.asNondeterministic()(text).alias("sig")).where("sig is not null")


def choose_bands(perms: int = 128, threshold: float = 0.7, verified: bool = True) -> tuple[int, int]:
    """(bands, rows): the steepest curve near the threshold, or, when pairs are verified, one that hardly misses."""
    fits = [(b, perms // b) for b in range(1, perms + 1) if perms % b == 0]
    if verified:
        good = [x for x in fits if 1 - (1 - threshold ** x[1]) ** x[0] >= 0.999]
        return max(good, key=lambda x: x[1])
    return min(fits, key=lambda x: abs((1 / x[0]) ** (1 / x[1]) - threshold))


def band_keys(signatures: DataFrame, bands: int, rows: int) -> DataFrame:
    """(band, key, doc_id): a hash of each band's slots."""
    pieces = F.array(*(F.struct(F.lit(k).alias("band"), F.md5(F.array_join(F.slice("sig", k * rows + 1, rows), ",")).alias("key")) for k in range(bands)))
    return signatures.select("doc_id", F.explode(pieces).alias("b")).select("b.band", "b.key", "doc_id")


def lsh_pairs(signatures: DataFrame, bands: int, rows: int) -> DataFrame:
    """(a, b), a < b: all pairs that share a bucket. Quadratic in a bucket; for measuring quality."""
    k = band_keys(signatures, bands, rows)
    x, y = k.toDF("band", "key", "a"), k.toDF("band", "key", "b")
    return x.join(y, ["band", "key"]).where("a < b").select("a", "b").distinct()


def star_pairs(signatures: DataFrame, bands: int, rows: int) -> DataFrame:
    """(a, b): each document with the smallest of its buckets; linear in a bucket's size."""
    k = band_keys(signatures, bands, rows)
    least = k.groupBy("band", "key").agg(F.min("doc_id").alias("a"), F.count("*").alias("n")).where("n > 1")
    return k.join(least, ["band", "key"]).where("a < doc_id").select("a", F.col("doc_id").alias("b")).distinct()


def cross_pairs(signatures: DataFrame, clusters: DataFrame, bands: int, rows: int) -> DataFrame:
    """(a, b), a < b: pairs that share a bucket but lie in different components of (doc_id, component).

    Buckets of one component drop out before their members are joined, so only pairs that
    could still link are made; unlike members of a bucket are compared each with each.
    """
    k = band_keys(signatures, bands, rows).join(clusters, "doc_id", "left").select("band", "key", "doc_id", F.coalesce("component", "doc_id").alias("component"))
    k = stage(k, "buckets")
    some = k.select("band", "key", "component").distinct()
    x, y = some.toDF("band", "key", "x"), some.toDF("band", "key", "y")
    apart = x.join(y, ["band", "key"]).where("x < y")
    left, right = k.toDF("band", "key", "p", "x"), k.toDF("band", "key", "q", "y")
    both = apart.join(left, ["band", "key", "x"]).join(right, ["band", "key", "y"])
    return both.select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b")).distinct()


#: Rows of buckets in a task, and members of a bucket beyond which it is cut.
BUCKET_ROWS, HOT = 100_000, 4096
COUNTED = "pairs long"


def unseen_pairs(weight: np.ndarray, own: np.ndarray, earlier: list[np.ndarray]) -> int:
    """Weighted pairs of a bucket's members, of an own one and one after it, that share no earlier bucket."""
    m = len(weight)
    if m <= 16:
        sets = [set(e.tolist()) for e in earlier]
        return sum(int(weight[i] * weight[j]) for i in range(m) if own[i] for j in range(i + 1, m) if sets[i].isdisjoint(sets[j]))
    key = np.concatenate(earlier)
    of = np.repeat(np.arange(m), [len(e) for e in earlier])
    by = np.argsort(key, kind="stable")
    key, of = key[by], of[by]
    edges = np.flatnonzero(np.append(True, np.append(key[1:] != key[:-1], True))) if len(key) else np.zeros(1, np.int64)
    shared = [of[a:b] for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True) if b - a > 1]
    total, mine = 0, np.flatnonzero(own)
    for lo in range(0, len(mine), 512):
        rows = mine[lo : lo + 512]
        apart = np.arange(m) > rows[:, None]
        place = np.full(m, -1)
        place[rows] = np.arange(len(rows))
        for s in shared:
            at = place[s]
            at = at[at >= 0]
            if len(at):
                apart[np.ix_(at, s)] = False
        total += int(weight[rows] @ (apart @ weight))
    return total


def count_pairs(classes: DataFrame, bands: int, rows: int) -> int:
    """How many pairs of documents share a bucket, without a row for each.

    Classes of equal signatures (node, w, sig) stand for their w documents. A pair counts in the
    first bucket that both have, so a bucket's members bring the earlier ones that they share
    with anybody; a bucket of more than HOT members is dealt over tasks by member.
    """
    spark = classes.sparkSession
    keys = F.array(*(F.xxhash64(F.lit(k), F.slice("sig", k * rows + 1, rows)) for k in range(bands)))
    each = classes.select("node", "w", F.posexplode(keys).alias("band", "key"))
    many = each.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    held = each.join(many, "key").groupBy("node", "w").agg(F.array_sort(F.collect_list(F.struct("band", "key", "n"))).alias("b"))
    held = held.select("node", "w", F.transform("b", lambda x: x["key"]).alias("keys"), F.posexplode("b").alias("at", "x"))
    cuts = F.ceil(F.col("x.n") / F.lit(HOT)).cast("int")
    held = held.select("node", "w", F.slice("keys", F.lit(1), F.col("at")).alias("earlier"), F.col("x.key").alias("key"), cuts.alias("cuts"))
    held = held.select("node", "w", "earlier", "key", "cuts", F.explode(F.sequence(F.lit(0), F.col("cuts") - 1)).alias("cut"))
    held = stage(held.select("node", "w", "earlier", "key", "cut", (F.pmod(F.xxhash64("node"), F.col("cuts")) == F.col("cut")).alias("own")), "buckets")
    parts = max(2 * shuffle_partitions(spark), -(-held.count() // BUCKET_ROWS))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([("key", "ascending"), ("cut", "ascending"), ("node", "ascending")])
        key, cut, own = (table[c].to_numpy() for c in ("key", "cut", "own"))
        weight = table["w"].to_numpy()
        lists = table["earlier"].combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        ends, flat = lists.offsets.to_numpy().tolist(), lists.values.to_numpy()
        edges = np.flatnonzero(np.append(True, np.append((key[1:] != key[:-1]) | (cut[1:] != cut[:-1]), True))).tolist()
        total = 0
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            total += unseen_pairs(weight[a:b], own[a:b], [flat[ends[i] : ends[i + 1]] for i in range(a, b)])
        return pa.table({"pairs": pa.array([total], pa.int64())})

    part = F.pmod(F.xxhash64("key", "cut"), F.lit(parts))
    across = held.withColumn("part", part).groupBy("part").applyInArrow(run, COUNTED).agg(F.coalesce(F.sum("pairs"), F.lit(0))).first()[0]
    drop_stage(held)
    return across + classes.agg(F.coalesce(F.sum(F.expr("w * (w - 1) div 2")), F.lit(0))).first()[0]


def verify_pairs(pairs: DataFrame, signatures: DataFrame, threshold: float = 0.7) -> DataFrame:
    """Pairs whose share of equal slots reaches the threshold, with that share."""
    x, y = signatures.toDF("a", "sa"), signatures.toDF("b", "sb")
    same = F.size(F.filter(F.zip_with("sa", "sb", lambda p, q: p == q), lambda e: e))
    return pairs.join(x, "a").join(y, "b").select("a", "b", (same / F.size("sa")).alias("similarity")).where(F.col("similarity") >= threshold)


def indexed_jaccard_pairs(docs: DataFrame, n: int = 5, threshold: float = 0.7) -> DataFrame:
    """(a, b, jaccard) by an inverted index over all shingles, a row for each shared one; rows of one id are one document."""
    s = stage(shingle_rows(docs, n), "shingles")
    size = s.groupBy("doc_id").agg(F.count("*").alias("n"))
    x, y = s.toDF("a", "base"), s.toDF("b", "base")
    both = x.join(y, "base").where("a < b").groupBy("a", "b").agg(F.count("*").alias("both"))
    out = both.join(size.toDF("a", "na"), "a").join(size.toDF("b", "nb"), "b")
    return out.select("a", "b", (F.col("both") / (F.col("na") + F.col("nb") - F.col("both"))).alias("jaccard")).where(F.col("jaccard") >= threshold)


def exact_jaccard_pairs(docs: DataFrame, n: int = 5, threshold: float = 0.7) -> DataFrame:
    """(a, b, jaccard): every pair that reaches the threshold, the truth to measure against.

    Shingles are counted in packed form, and only sets that can reach the threshold are
    compared, copies once. Where ids repeat, the inverted index is used, to which the rows
    of one id are one document.
    """
    from ..llm.ngram_join import similar_pairs

    if docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count():
        return indexed_jaccard_pairs(docs, n, threshold)
    out = similar_pairs(docs.select("doc_id", F.lower("text").alias("text")), n, int(100 * threshold + 1e-9))
    return out.select("a", "b", (F.col("common") / (F.col("na") + F.col("nb") - F.col("common"))).alias("jaccard")).where(F.col("jaccard") >= threshold)


def dup_clusters(docs: DataFrame, n: int = 5, perms: int = 128, threshold: float = 0.7, seed: int = 42, all_pairs: bool = False) -> DataFrame:
    """(doc_id, component) of documents that MinHash links; the components are those of all pairs that share a bucket.

    Stars come first and join what is alike in linear time; then the members of a bucket
    that they left apart are compared. ``all_pairs`` compares all at once, to check against.
    """
    bands, rows = choose_bands(perms, threshold)
    sig = stage(minhash_signature_numpy(docs, n, perms, seed), "signatures")
    if all_pairs:
        linked = verify_pairs(lsh_pairs(sig, bands, rows), sig, threshold)
    else:
        stars = stage(verify_pairs(star_pairs(sig, bands, rows), sig, threshold), "stars")
        near = stage(connected_components(stars, "a", "b").toDF("doc_id", "component"), "near")
        linked = stars.unionByName(verify_pairs(cross_pairs(sig, near, bands, rows), sig, threshold))
    return connected_components(linked, "a", "b").toDF("doc_id", "component")


def minhash_dedup(docs: DataFrame, n: int = 5, perms: int = 128, threshold: float = 0.7, seed: int = 42, all_pairs: bool = False) -> DataFrame:
    """Documents without the near copies of smaller ids; rows without id stay."""
    away = dup_clusters(docs, n, perms, threshold, seed, all_pairs).where("doc_id != component").select("doc_id")
    return docs.join(away, "doc_id", "left_anti")


#: How far below the threshold hashed features are looked at: they move a similarity by the share of features that collide.
FEATURE_ERROR = 0.1


def ml_minhash_pairs(docs: DataFrame, n: int = 5, threshold: float = 0.7, tables: int = 64, features: int = 1 << 20, seed: int = 42, near: DataFrame | None = None) -> DataFrame:
    """(a, b) by Spark's own MinHash: pairs with any one equal hash, whose distance over hashed features is in reach.

    A cross-check of the banded signatures. Spark's own join makes a row for each hash that two
    documents share, which any frequent shingle does; here its hashes and features are compared
    for the pairs ``near``, those of :func:`exact_jaccard_pairs` from FEATURE_ERROR below the
    threshold. Features of a pair further off would have to collide in that share.
    """
    from pyspark.ml.feature import HashingTF, MinHashLSH

    near = exact_jaccard_pairs(docs, n, threshold - FEATURE_ERROR) if near is None else near
    x = docs.select("doc_id", shingles(F.col("text"), n).alias("grams")).where(F.size("grams") > 0)
    x = HashingTF(inputCol="grams", outputCol="features", numFeatures=features, binary=True).transform(x).select("doc_id", "features")
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=seed).fit(x)

    @F.udf("binary")
    def pack(vector, hashes) -> bytes:
        """The hashes, then the features in order."""
        return np.array([h[0] for h in hashes], np.int32).tobytes() + np.sort(vector.indices).astype(np.int32).tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            for k, (p, q) in enumerate(zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)):
                p, q = np.frombuffer(p, np.int32), np.frombuffer(q, np.int32)
                if (p[:tables] == q[:tables]).any():
                    both = len(np.intersect1d(p[tables:], q[tables:], assume_unique=True))
                    keep[k] = 1 - both / (len(p) + len(q) - 2 * tables - both) < 1 - threshold + 1e-9
            yield pa.RecordBatch.from_arrays([batch.column(c).filter(pa.array(keep)) for c in (0, 1)], names=["a", "b"])

    packed = stage(model.transform(x).select("doc_id", pack("features", "hashes").alias("packed")), "features")
    p, q = packed.toDF("a", "p"), packed.toDF("b", "q")
    kinds = {f.name: f.dataType.simpleString() for f in near.schema.fields}
    return near.select("a", "b").join(p, "a").join(q, "b").select("a", "b", "p", "q").mapInArrow(run, f"a {kinds['a']}, b {kinds['b']}")


def lsh_quality(docs: DataFrame, n: int = 5, perms: int = 128, threshold: float = 0.7) -> DataFrame:
    """Candidates, true pairs and recall of banding schemes, beside the share that theory expects at the threshold.

    Candidates are counted, not written; true pairs are found if a band is equal, and equal
    sets always are.
    """
    spark = docs.sparkSession
    schemes = ((16, 8), (32, 4), (64, 2))
    truth = stage(exact_jaccard_pairs(docs, n, threshold), "truth")
    release(spark)
    sig = stage(minhash_signature_numpy(docs.where("doc_id is not null"), n, perms).select("doc_id", F.col("sig").cast("array<int>")), "signatures")
    x, y = sig.toDF("a", "sa"), sig.toDF("b", "sb")
    same = lambda bands, rows: F.exists(F.sequence(F.lit(0), F.lit(bands - 1)), lambda k: F.slice("sa", k * rows + 1, rows) == F.slice("sb", k * rows + 1, rows))
    found = truth.where("jaccard < 1").join(x, "a").join(y, "b").agg(*(F.count_if(same(b, r)).alias(f"f{b}") for b, r in schemes)).first()
    alike, pairs = truth.where("jaccard = 1").count(), truth.count()
    release(spark)
    classes = stage(sig.groupBy("sig").agg(F.count("*").alias("w")).withColumn("node", F.monotonically_increasing_id()), "classes")
    drop_stage(sig)
    out = []
    for bands, rows in schemes:
        candidates = count_pairs(classes, bands, rows)
        release(spark)
        out.append((bands, rows, candidates, pairs, (found[f"f{bands}"] + alike) / pairs if pairs else None, 1 - (1 - threshold**rows) ** bands))
    return spark.createDataFrame(out, "bands int, rows int, candidates long, true_pairs long, recall double, expected_at_threshold double")

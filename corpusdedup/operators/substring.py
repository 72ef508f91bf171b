"""Shards, exact substring removal and the model of shard-local retention."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import stage
from .counting import KEY

SPANS = "doc_id long, start int, stop int"
KGRAMS = "shard int, doc_id long, pos int, g long, g2 long"


def assign_shard(df: DataFrame, n: int, by: str = "hash", seed: int = 0, id_col: str = "doc_id", out: str = "shard") -> DataFrame:
    """A column ``out`` in 0..n-1: by a hash of the id, the id's remainder, or the source's hash."""
    hexed = lambda c: F.pmod(F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long"), F.lit(n)).cast("int")
    if by == "hash":
        shard = hexed(F.concat(F.lit(f"{seed}-"), F.col(id_col).cast("string")))
    elif by == "mod":
        shard = F.pmod(F.col(id_col), F.lit(n)).cast("int")
    elif by == "source":
        shard = hexed(F.coalesce(F.col("source"), F.lit("")))
    else:
        raise ValueError("by must be hash, mod or source")
    return df.withColumn(out, shard)


#: Odd multipliers of the two rolling hashes.
ROLL = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)
#: Places of a text that are hashed at a time.
PLACES = 200_000


def rolling_hashes(text: str, k: int, start: int, stop: int) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit hashes of the k-grams of a text at the places start to stop; equal k-grams have equal ones."""
    codes = np.frombuffer(text[start : stop + k - 1].encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    g, g2 = (_rolled(codes, k, m).view(np.int64) for m in ROLL)
    return g, g2


def _rolled(codes: np.ndarray, k: int, m: int) -> np.ndarray:
    """A 64-bit hash of each k codes in a row."""
    x = (codes + np.uint64(1)) * np.uint64(m)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(ROLL[0] ^ m | 1)
    h = np.zeros(len(codes) - k + 1, np.uint64)
    # Horner's rule by doubling: hashes of 2^j characters make those of 2^(j+1)
    width, power, done = 1, np.array([m], np.uint64), 0
    part = x ^ (x >> np.uint64(32))
    while width <= k:
        if k & width:
            h = h * power + part[done : done + len(h)]
            done += width
        part = part[: len(part) - width] * power + part[width:] if len(part) > width else part[:0]
        width, power = 2 * width, power * power
    return h ^ (h >> np.uint64(31))


def kgram_rows(docs: DataFrame, k: int = 50, shard_col: str | None = None) -> DataFrame:
    """(shard, doc_id, pos, g, g2): each k-gram's place and 128-bit hash, in bounded pieces however long a text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, doc, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                n = len(text) - k + 1
                for lo in range(0, n, PLACES):
                    hi = min(n, lo + PLACES)
                    g, g2 = rolling_hashes(text, k, lo, hi)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(hi - lo, shard, np.int32)), pa.array(np.full(hi - lo, doc, np.int64)), pa.array(np.arange(lo, hi, dtype=np.int32)), pa.array(g), pa.array(g2)], names=["shard", "doc_id", "pos", "g", "g2"])

    return _long_texts(docs, k, shard_col).mapInArrow(run, KGRAMS)


def _long_texts(docs: DataFrame, k: int, shard_col: str | None) -> DataFrame:
    """(shard, doc_id, text) of the documents that hold a k-gram."""
    shard = F.col(shard_col) if shard_col else F.lit(0)
    long = docs.where((F.length("text") >= k) & F.col("doc_id").isNotNull())
    return long.select(shard.cast("int").alias("shard"), F.col("doc_id").cast("long"), F.make_valid_utf8("text").alias("text"))


def kgram_spans(docs: DataFrame, k: int = 50, shard_col: str | None = None, keep_first: bool = False) -> DataFrame:
    """(doc_id, start, stop): maximal spans covered by k-character strings that occur twice or more in the shard.

    A character lies in a repeated substring of k characters or more exactly if it lies in
    a repeated k-gram, so counting k-grams by hash, spread over all tasks, gives what a
    suffix array of the shard gives on one; k-grams are counted in packed blocks, where their
    fingerprints leave it open whether they repeat. ``keep_first``: the first place of a k-gram,
    in order of document and position, does not count; that takes a row for each k-gram
    (:func:`winnowed_spans` takes fewer). Rows without id or text have no spans.
    """
    from .kgrams import repeated_kgrams

    if keep_first:
        return _repeated(kgram_rows(docs, k, shard_col), k, keep_first)
    return merge_spans(repeated_kgrams(_long_texts(docs, k, shard_col), k, PLACES))


def _repeated(g: DataFrame, k: int, keep_first: bool) -> DataFrame:
    n = g.groupBy("shard", "g", "g2").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "pos")).alias("first")).where("n > 1")
    hit = g.join(n, ["shard", "g", "g2"])
    if keep_first:
        hit = hit.where(F.struct("doc_id", "pos") != F.col("first"))
    return merge_spans(hit.select("doc_id", F.col("pos").alias("start"), (F.col("pos") + k).alias("stop")))


def selected(text: str, min_len: int, k: int, start: int, stop: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Winnowed fingerprints: (hash, first, last), where the substrings of ``min_len`` characters at first to last choose that k-gram.

    A substring chooses the least hash among its own k-grams, of equal ones the last, so
    equal substrings choose equal fingerprints wherever they stand.
    """
    window = min_len - k + 1
    h = rolling_hashes(text, k, start, stop + window - 1)[0].view(np.uint64)
    views = np.lib.stride_tricks.sliding_window_view(h, window)
    at = np.arange(stop - start) + window - 1 - views[:, ::-1].argmin(axis=1)
    first = np.flatnonzero(np.diff(at, prepend=-1))
    return h[at[first]].view(np.int64), start + first, start + np.append(first[1:], len(at)) - 1


def winnowed_rows(docs: DataFrame, min_len: int = 50, k: int = 32, shard_col: str | None = None) -> DataFrame:
    """(shard, doc_id, g, first, last) for each fingerprint: about two rows in ``min_len - k + 2`` characters."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, doc, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                n = len(text) - min_len + 1
                for lo in range(0, n, PLACES):
                    g, first, last = selected(text, min_len, k, lo, min(n, lo + PLACES))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(g), shard, np.int32)), pa.array(np.full(len(g), doc, np.int64)), pa.array(g), pa.array(first.astype(np.int32)), pa.array(last.astype(np.int32))], names=["shard", "doc_id", "g", "first", "last"])

    return _long_texts(docs, min_len, shard_col).mapInArrow(run, "shard int, doc_id long, g long, first int, last int")


def winnowed_spans(docs: DataFrame, min_len: int = 50, k: int = 32, shard_col: str | None = None, keep_first: bool = False) -> DataFrame:
    """The spans of :func:`kgram_spans` without a row for each character.

    Equal substrings choose equal fingerprints, so a substring of ``min_len`` characters
    can only repeat where its fingerprint does. Fingerprints are counted first; only the
    places whose fingerprint repeats in the shard send k-grams to the exact count. Text
    without repeats costs its fingerprints alone. Ids must be unique.
    """
    if not 1 <= k <= min_len:
        raise ValueError("k must be between 1 and min_len")
    marks = stage(winnowed_rows(docs, min_len, k, shard_col), "fingerprints")
    twice = marks.groupBy("shard", "g").agg(F.count("*").alias("n")).where("n > 1").drop("n")
    places = marks.join(twice, ["shard", "g"], "left_semi").groupBy(F.col("doc_id").alias("__doc")).agg(F.collect_list(F.struct("first", "last")).alias("__places"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, doc, text, _, spots in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                edges = np.array([(x["first"], x["last"] + 1) for x in spots], np.int64)
                edges = edges[np.argsort(edges[:, 0])]
                apart = edges[1:, 0] > edges[:-1, 1]
                for lo, hi in zip(edges[np.append(True, apart), 0].tolist(), edges[np.append(apart, True), 1].tolist(), strict=True):
                    for a in range(lo, hi, PLACES):
                        b = min(hi, a + PLACES)
                        g, g2 = rolling_hashes(text, min_len, a, b)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(b - a, shard, np.int32)), pa.array(np.full(b - a, doc, np.int64)), pa.array(np.arange(a, b, dtype=np.int32)), pa.array(g), pa.array(g2)], names=["shard", "doc_id", "pos", "g", "g2"])

    texts = _long_texts(docs, min_len, shard_col)
    rows = texts.join(places, texts["doc_id"] == places["__doc"]).mapInArrow(run, KGRAMS)
    return _repeated(stage(rows, "candidates"), min_len, keep_first)


def merge_spans(spans: DataFrame) -> DataFrame:
    """Union of overlapping or touching spans of each document."""
    w = Window.partitionBy("doc_id").orderBy("start", "stop")
    reach = F.max("stop").over(w.rowsBetween(Window.unboundedPreceding, -1))
    x = spans.withColumn("fresh", F.when(F.col("start") <= reach, 0).otherwise(1))
    x = x.withColumn("island", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return x.groupBy("doc_id", "island").agg(F.min("start").cast("int").alias("start"), F.max("stop").cast("int").alias("stop")).drop("island")


def places(lengths: np.ndarray) -> np.ndarray:
    """0, 1, ... within each of several lengths in a row."""
    return np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)


def maybe_repeated(codes: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(start, stop) of the runs of stretches of ``size`` codes whose short hash stands elsewhere too: all repeats, and a few more."""
    n = len(codes) - size + 1
    if n < 2:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    bits = n.bit_length()
    keyed = np.empty(n, np.uint64)  # the hash's high bits, then the place
    for lo in range(0, n, PLACES):
        hi = min(n, lo + PLACES)
        h = _rolled(codes[lo : hi + size - 1].astype(np.uint64), size, ROLL[0])
        keyed[lo:hi] = h >> np.uint64(bits) << np.uint64(bits) | np.arange(lo, hi, dtype=np.uint64)
    keyed.sort()
    step = np.zeros(len(codes) + 1, np.int8)
    for lo in range(0, n - 1, PLACES):
        part = keyed[lo : lo + PLACES + 1]
        same = np.flatnonzero(part[1:] >> np.uint64(bits) == part[:-1] >> np.uint64(bits))
        step[part[same] & np.uint64((1 << bits) - 1)] = step[part[same + 1] & np.uint64((1 << bits) - 1)] = 1
    starts = np.flatnonzero(step)
    del keyed, step
    fresh = np.diff(starts, prepend=-size - 1) > size
    return starts[fresh], starts[np.append(fresh[1:], True)[: len(starts)]] + size


def repeated_suffixes(texts: list[str], min_len: int) -> np.ndarray:
    """Where in the joined texts a substring of ``min_len`` characters starts that stands elsewhere too.

    Suffixes are sorted by their first characters, then by twice as many, up to ``min_len``: what
    follows changes no span. A suffix's rank is the place of its group in the order; one that is
    alone has its place and is not sorted again. Stretches whose short hash is alone cannot
    repeat and are not sorted at all; a hash that is shared by chance is sorted apart.
    """
    lengths = np.array([len(t) for t in texts], np.int64)
    joined = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    number = np.zeros(int(joined.max()) + 1 if len(joined) else 1, np.uint32)
    number[joined] = 1
    number = np.cumsum(number, dtype=np.uint32)  # dense, so that many characters fit one integer
    bits = max(1, int(number[-1]).bit_length())
    codes = number.astype(np.uint8 if bits <= 8 else np.uint16 if bits <= 16 else np.uint32)[joined]
    del joined
    first, stop = maybe_repeated(codes, min_len)
    at = places(stop - first) + np.repeat(first, stop - first)
    # characters to the end of the text and of the run: no rank is asked for beyond
    ends = np.cumsum(lengths)
    left = (np.minimum(ends[np.searchsorted(ends, at, side="right")], np.repeat(stop, stop - first)) - at).astype(np.int32)
    at = at.astype(np.int32)
    width = max(1, min(min_len, 63 // bits))
    at, left = at[left >= width], left[left >= width]
    key = np.zeros(len(at), np.int64)
    for k in range(width):
        key <<= bits
        key |= codes[at + np.int32(k)]
    rank = np.zeros(len(codes), np.int32)
    del codes
    by, new = _alone_apart(at, key, None, rank)
    at, left = at[by], left[by]
    while width < min_len:
        step = min(width, min_len - width)
        width += step
        stays = left >= width
        at, left, new = at[stays], left[stays], new[stays]
        key = new.astype(np.int64) << 32
        key |= rank[at + np.int32(step)]
        by, new = _alone_apart(at, key, new, rank)
        at, left = at[by], left[by]
    return at


def _alone_apart(at: np.ndarray, key: np.ndarray, old: np.ndarray | None, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Set the ranks of the suffixes ``at`` by their keys within groups of the ``old`` rank; returns the numbers of those not alone, and their ranks."""
    by = np.argsort(key)
    key = key[by]
    fresh = np.ones(len(by), bool)
    fresh[1:] = key[1:] != key[:-1]
    place = np.arange(len(by), dtype=np.int32)
    new = np.maximum.accumulate(np.where(fresh, place, 0))
    if old is not None:
        old = old[by]
        first = np.ones(len(by), bool)
        first[1:] = old[1:] != old[:-1]
        new += old - np.maximum.accumulate(np.where(first, place, 0))
    rank[at[by]] = new
    many = ~fresh
    many[:-1] |= ~fresh[1:]
    return by[many], new[many]


def repeated_spans(texts: list[str], min_len: int) -> list[list[tuple[int, int]]]:
    """For each text the merged spans of substrings of ``min_len`` or more that occur twice or more in the list."""
    starts = np.sort(repeated_suffixes(texts, min_len)).astype(np.int64)
    edges = np.cumsum([0, *map(len, texts)])
    text = np.searchsorted(edges, starts, side="right") - 1
    fresh = np.ones(len(starts) + 1, bool)
    fresh[1:-1] = (text[1:] != text[:-1]) | (starts[1:] - starts[:-1] > min_len)
    text, first, last = text[fresh[:-1]], starts[fresh[:-1]], starts[fresh[1:]] + min_len
    out: list[list[tuple[int, int]]] = [[] for _ in texts]
    for t, a, b in zip(text.tolist(), (first - edges[text]).tolist(), (last - edges[text]).tolist(), strict=True):
        out[t].append((a, b))
    return out


def suffix_array_spans(docs: DataFrame, min_len: int = 50, shard_col: str = "shard", max_shard_chars: int = 50_000_000) -> DataFrame:
    """The shard-local baseline itself: the sorted suffixes of each shard, in one task.

    That a shard must fit one worker is the method's own bound; it is checked, and
    :func:`kgram_spans` gives the same spans without it. Rows without id or text have no spans.
    """

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("doc_id")
        texts = table["text"].to_pylist()
        if sum(map(len, texts)) > max_shard_chars:
            raise ValueError("the shard is too large for one suffix array: use more shards or kgram_spans")
        spans = repeated_spans(texts, min_len)
        doc = np.repeat(table["doc_id"].to_numpy(), [len(s) for s in spans])
        flat = np.array([x for s in spans for x in s], np.int32).reshape(-1, 2)
        return pa.table({"doc_id": pa.array(doc, pa.int64()), "start": pa.array(flat[:, 0]), "stop": pa.array(flat[:, 1])})

    return _long_texts(docs, min_len, shard_col).groupBy("shard").applyInArrow(run, SPANS)


def remove_spans(docs: DataFrame, spans: DataFrame, empty_docs: str = "keep") -> DataFrame:
    """Documents without their spans; these are few, so each document's are gathered and applied to its text."""
    gone = spans.groupBy(F.col("doc_id").alias("__doc")).agg(F.array_sort(F.collect_list(F.struct("start", "stop"))).alias("__gone"))
    start = F.struct(F.lit("").alias("kept"), F.lit(0).alias("at"))

    def step(acc, s):
        return F.struct(F.concat(acc["kept"], F.substring(F.col("text"), acc["at"] + 1, s["start"] - acc["at"])).alias("kept"), s["stop"].alias("at"))

    end = F.aggregate("__gone", start, step)
    cut = F.concat(end["kept"], F.substring(F.col("text"), end["at"] + 1, F.length("text")))
    out = docs.join(gone, docs["doc_id"] == gone["__doc"], "left").withColumn("text", F.when(F.col("__gone").isNull(), F.col("text")).otherwise(cut)).drop("__doc", "__gone")
    return out.where("text is null or text != ''") if empty_docs == "drop" else out


def singleton_only(occ: DataFrame, shard_col: str = "shard") -> DataFrame:
    """Occurrences that are alone in their shard: the chunk-level model of shard-local removal."""
    n = occ.groupBy(shard_col, *KEY).agg(F.count("*").alias("n"))
    return occ.join(n.where("n = 1").drop("n"), [shard_col, *KEY], "left_semi")


def shard_sensitivity(occ: DataFrame, docs: DataFrame, ns: tuple[int, ...] = (1, 2, 5, 10, 33), bys: tuple[str, ...] = ("hash", "source")) -> DataFrame:
    """Kept chunks and characters of the model for each number and kind of shards.

    A chunk that occurs once is alone in any shard and is only summed; what occurs more
    often is dealt to the shards of every plan.
    """
    groups = stage(occ.groupBy(*KEY).agg(F.count("*").alias("n"), F.sum("raw_len").alias("chars")), "groups")
    plan = [(b, n) for b in bys for n in ns]
    alone = groups.where("n = 1").agg(F.count("*").alias("n"), F.coalesce(F.sum("chars"), F.lit(0)).alias("chars"))
    alone = alone.select(F.explode(F.array(*(F.struct(F.lit(b).alias("assigned_by"), F.lit(n).alias("n_shards")) for b, n in plan))).alias("p"), "n", "chars").select("p.*", F.col("n").alias("kept_chunks"), F.col("chars").alias("kept_chars"), F.col("n").alias("chunks"))
    x = occ.join(groups.where("n > 1"), KEY, "left_semi").select(*KEY, "doc_id", "raw_len").join(docs.select("doc_id", "source"), "doc_id")
    plans = F.explode(F.array(*(F.struct(F.lit(b).alias("assigned_by"), F.lit(n).alias("n_shards"), assign_shard_expr(n, b).alias("shard")) for b, n in plan)))
    x = x.select(*KEY, "raw_len", plans.alias("p")).select("p.*", *KEY, "raw_len")
    g = x.groupBy("assigned_by", "n_shards", "shard", *KEY).agg(F.count("*").alias("n"), F.sum("raw_len").alias("chars"))
    many = g.groupBy("assigned_by", "n_shards").agg(F.count_if(F.col("n") == 1).alias("kept_chunks"), F.sum(F.when(F.col("n") == 1, F.col("chars")).otherwise(0)).alias("kept_chars"), F.sum("n").alias("chunks"))
    return many.unionByName(alone).groupBy("assigned_by", "n_shards").agg(*(F.sum(c).alias(c) for c in ("kept_chunks", "kept_chars", "chunks")))


def assign_shard_expr(n: int, by: str):
    hexed = lambda c: F.pmod(F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long"), F.lit(n)).cast("int")
    return hexed(F.concat(F.lit("0-"), F.col("doc_id").cast("string"))) if by == "hash" else hexed(F.coalesce(F.col("source"), F.lit("")))


def simulate_sharding(spark, freqs: tuple[int, ...], n: int, trials: int = 2000, seed: int = 1) -> DataFrame:
    """Mean kept copies over seeded trials of random sharding, beside the closed form."""
    from ..functions.retention import expected_kept

    copies = spark.createDataFrame([(c,) for c in freqs], "freq int").select("freq", F.explode(F.sequence(F.lit(1), F.col("freq"))).alias("copy"))
    x = copies.select("freq", "copy", F.explode(F.sequence(F.lit(1), F.lit(trials))).alias("trial"))
    shard = F.pmod(F.conv(F.substring(F.md5(F.concat_ws("-", F.lit(seed), "freq", "copy", "trial")), 1, 8), 16, 10).cast("long"), F.lit(n))
    kept = x.select("freq", "trial", shard.alias("shard")).groupBy("freq", "trial", "shard").agg(F.count("*").alias("n")).groupBy("freq", "trial").agg(F.count_if(F.col("n") == 1).alias("kept"))
    return kept.groupBy("freq").agg(F.avg("kept").alias("mean_kept"), F.stddev_samp("kept").alias("sd_kept")).select("freq", F.lit(n).alias("n_shards"), "mean_kept", "sd_kept", expected_kept(F.col("freq"), float(n)).alias("expected_kept"))


"""Language-model scoring by deleted interpolation.

The model's probability of a token is a mixture of the maximum-likelihood estimates
of all orders and a uniform share; the weights depend on how often the context of
the highest order was seen (one bucket for each power of two) and are learned by
expectation-maximisation on the counts of a held-out tenth of the training rows,
whose own counts are deleted from the estimates meanwhile. The estimates that score
texts then use all training rows.

Counting and look-up run through :mod:`.blocks`: nothing that grows with the corpus
is collected or broadcast. EM needs only the ratios of the estimates to the uniform
share, so held-out tokens are counted in cells of half an octave of these ratios, and
each cell keeps the mean logarithm of its tokens' ratios, which EM then works with.
With N training tokens a bucket has at most (2 log2 N + 2) ** order cells: 729 000 at
order 3 and 2 ** 44 tokens.
Each bucket's weights are learned in a task, and only they come to the driver.

Null or empty texts score as a lone end token. Rows may repeat; each is scored.
Other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import drop_stage, release, stage
from .blocks import REQUEST, bucket_count, count_in_buckets, docs_of, expand, mix, request_batches, squeeze, trim, word_blocks
from .blocks import places as places_of

#: Steps for each power of two in which EM distinguishes estimates.
STEPS = 2
#: A cell's logarithms are summed as whole multiples of 1 / FINE, so that sums do not depend on their order.
FINE = 1024
NEVER = -30_000  # the cell of an estimate of zero


@dataclass(frozen=True)
class Mixture:
    """Weights by context bucket: ``weights[b]`` = (uniform, order 1, ..., order n)."""

    order: int
    weights: np.ndarray
    total: int
    distinct: int


def fold_of(doc_id: int | None, folds: int = 5) -> int:
    """crc32 of the id as text, modulo ``folds``; a null id counts as empty text."""
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds


def context_bucket(counts: np.ndarray) -> np.ndarray:
    """0 for an unseen context, else 1 + the whole part of its binary logarithm."""
    c = np.asarray(counts, np.float64)
    return np.where(c > 0, 1 + np.floor(np.log2(np.maximum(c, 1))), 0).astype(np.int64)


def _role(doc_id, held_fold: int) -> int:
    """2: scored only; 1: training, deleted while the weights are learned; 0: training."""
    crc = zlib.crc32(b"" if doc_id is None else str(doc_id).encode())
    return 2 if crc % 5 == held_fold else int(crc // 5 % 10 == 0)


def _levels(ids: np.ndarray, starts: np.ndarray, order: int, size: int, top: int | None = None) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """For each order: distinct n-grams as (prefix of one order less, last word) and, by position, which one ends there (-1: none).

    ``starts`` is each position's place in its document; ``top`` ends the list at a lower order. Grams end at the last start
    symbol or later, so that a context's count is the number of tokens after it.
    """
    ends = starts >= order - 2
    seen = np.bincount(ids[ends], minlength=size) > 0  # ids are dense: no sort
    uniq = np.flatnonzero(seen)
    out = [(np.full(len(uniq), -1, np.int64), uniq, np.where(ends, (np.cumsum(seen) - 1)[ids], -1), uniq)]
    prev = ids.astype(np.int64)
    for k in range(2, (top or order) + 1):
        pos = np.flatnonzero(starts >= k - 1)
        # prefixes are numbered over all positions, counted grams are a subset of them
        full, finv = _numbered(prev[pos - 1] * size + ids[pos])
        number = np.full(len(ids), -1, np.int64)
        number[pos] = finv
        where = number if k >= order - 1 else np.where(ends, number, -1)
        prefix = full // size
        out.append((prefix, full - prefix * size, where, full))
        prev = number
    return out


def _numbered(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct ``codes``, ascending, and which of them each one is.

    Codes that leave room for their positions are sorted together with them, which is
    some three times faster than to sort positions by their codes.
    """
    bits = len(codes).bit_length()
    if not len(codes) or int(codes.max()).bit_length() + bits > 63:
        return np.unique(codes, return_inverse=True)
    both = codes << bits
    both |= np.arange(len(codes))
    both.sort()
    at = both & ((1 << bits) - 1)
    both >>= bits
    new = np.ones(len(codes), bool)
    np.not_equal(both[1:], both[:-1], out=new[1:])
    which = np.empty(len(codes), np.int64)
    which[at] = np.cumsum(new) - 1
    return both[new], which


def _hashes(levels, vocab: np.ndarray) -> list[np.ndarray]:
    """The 64-bit key of each distinct n-gram of each order."""
    keys = [vocab[levels[0][1]]]
    before = vocab
    for k, (prefix, last, _, _) in enumerate(levels[1:], start=2):
        h = mix(before[prefix] * np.uint64(0x9E3779B97F4A7C15) + vocab[last] + np.uint64(k))
        keys.append(h)
        before = h
    return keys


def _counts(where: np.ndarray, size: int, role: np.ndarray) -> list[np.ndarray]:
    """By distinct n-gram: occurrences in rows of role 0, and of role 0 or 1."""
    a = np.bincount(where[(where >= 0) & (role == 0)], minlength=size)
    return [a, a + np.bincount(where[(where >= 0) & (role == 1)], minlength=size)]


def _unpack(docs: bytes, seq: bytes, vocab: bytes, order: int, top: int | None = None):
    ids = expand(seq, np.int32)
    doc_ids, roles, lengths = docs_of(docs)
    places = places_of(lengths)
    levels = _levels(ids, places, order, len(expand(vocab, np.uint64)), top)
    return doc_ids, roles, lengths, places, levels


def _ask(blocks: DataFrame, order: int, which: list[int], buckets: int) -> DataFrame:
    """Requests for the counts of the n-grams of the given orders, all in one key space."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                _, roles, lengths, _, levels = _unpack(r["docs"], r["seq"], r["vocab"], order, max(which))
                role = np.repeat(roles, lengths)
                keys = _hashes(levels, expand(r["vocab"], np.uint64))
                key = np.concatenate([keys[k - 1] for k in which])
                counts = [np.concatenate(c) for c in zip(*(_counts(levels[k - 1][2], len(keys[k - 1]), role) for k in which), strict=True)]
                by = np.argsort(key)
                out = request_batches(r["block"], key[by], [c[by] for c in counts], buckets)
                del levels, keys, key, counts, by, role
                trim()
                yield out

    return blocks.mapInArrow(run, REQUEST)


JOINED = "docs binary, seq binary, n_vocab long, counts binary, cells binary"


def _cells(order: int, levels, role, places, a_counts, total_a: int, distinct_a: int) -> np.ndarray:
    """The held-out tokens' (bucket, quantised ratio of each order, number, sum of each order's fine logarithms)."""
    at = np.flatnonzero((role == 1) & (places >= order - 1))
    if not len(at) or not total_a:
        return np.zeros((0, 2 * order + 2), np.int64)
    f, bucket = _estimates(order, levels, at, a_counts, total_a)
    uniform = 1.0 / (distinct_a + 1)
    cols, fine = [bucket], []
    for x in f:
        octaves = np.log2(np.maximum(x, 1e-300) / uniform)
        cols.append(np.where(x > 0, np.rint(STEPS * octaves), NEVER).astype(np.int64))
        fine.append(np.where(x > 0, np.rint(FINE * octaves), 0))
    code = bucket  # one integer for each cell: sorting those is many times faster than sorting rows
    for q in cols[1:]:
        code = np.unique(code, return_inverse=True)[1] * 2**16 + (q - NEVER)
    _, first, which, n = np.unique(code, return_index=True, return_inverse=True, return_counts=True)
    sums = [np.bincount(which, weights=x, minlength=len(first)).astype(np.int64) for x in fine]
    return np.stack([*(c[first] for c in cols), n, *sums], axis=1).astype(np.int64)


def _estimates(order: int, levels, at: np.ndarray, counts: list[np.ndarray], total: int) -> tuple[list[np.ndarray], np.ndarray]:
    """Maximum-likelihood estimates of the tokens at positions ``at``, by order, and their context buckets."""
    out, context = [], np.full(len(at), total, np.float64)
    for k in range(1, order + 1):
        if k > 1:
            context = _prefix_counts(levels, k - 1, at - 1, counts)
        c = counts[k - 1][levels[k - 1][2][at]].astype(np.float64)
        out.append(np.divide(c, context, out=np.zeros(len(at)), where=context > 0))
    return out, context_bucket(context)


def _prefix_counts(levels, k: int, at: np.ndarray, counts: list[np.ndarray]) -> np.ndarray:
    """Counts of the k-grams that end at ``at``; all of them are counted, for they end at the last start symbol or later."""
    return counts[k - 1][levels[k - 1][2][at]].astype(np.float64)


def _join(blocks: DataFrame, replies: DataFrame, order: int, first: tuple[int, int], which: list[list[int]]) -> DataFrame:
    """Bring each block's replies to it; leaves the counts by distinct n-gram and the EM cells."""
    total_a, distinct_a = first

    def run(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        own = next(r for r in rows if r["docs"] is not None)
        _, roles, lengths, places, levels = _unpack(own["docs"], own["seq"], own["vocab"], order)
        keys = _hashes(levels, expand(own["vocab"], np.uint64))
        a_counts, t_counts = [None] * order, [None] * order
        for part, orders in enumerate(which):
            key = np.concatenate([keys[k - 1] for k in orders])
            by = np.argsort(key)
            got = [expand(r["counts"], np.uint64).reshape(2, -1) for r in sorted((r for r in rows if r["docs"] is None and r["part"] == part), key=lambda r: r["bucket"])]
            flat = np.empty((2, len(key)), np.uint64)
            flat[:, by] = np.concatenate(got, axis=1)
            lo = 0
            for k in orders:
                n = len(keys[k - 1])
                a_counts[k - 1], t_counts[k - 1] = flat[0, lo : lo + n], flat[1, lo : lo + n]
                lo += n
        packed = _cells(order, levels, np.repeat(roles, lengths), places, a_counts, total_a, distinct_a)
        flat_counts = squeeze(np.concatenate(t_counts))
        del levels, keys, a_counts, t_counts, flat, got, key, by, rows
        trim()
        return pa.table({"docs": pa.array([own["docs"]], pa.binary()), "seq": pa.array([own["seq"]], pa.binary()), "n_vocab": pa.array([own["n_vocab"]], pa.int64()), "counts": pa.array([flat_counts], pa.binary()), "cells": pa.array([packed.tobytes()], pa.binary())})

    none = F.lit(None).cast("binary")
    asked = replies.where("block >= 0").select("block", "part", "bucket", "counts", none.alias("docs"), none.alias("seq"), none.alias("vocab"), F.lit(0).cast("long").alias("n_vocab"))
    own = blocks.select("block", F.lit(0).alias("part"), F.lit(0).alias("bucket"), none.alias("counts"), "docs", "seq", "vocab", "n_vocab")
    return asked.unionByName(own).groupBy("block").applyInArrow(run, JOINED)


def fit_weights(ratios: np.ndarray, numbers: np.ndarray, rounds: int = 200, tolerance: float = 1e-7) -> np.ndarray:
    """EM over cells: a column of ratios to the uniform share for each order, and the tokens of each cell.

    A pseudo-token for each component keeps every weight above zero.
    """
    parts = ratios.shape[1] + 1
    like = np.ones((len(ratios), parts))
    like[:, 1:] = ratios
    w = np.full(parts, 1 / parts)
    for _ in range(rounds):
        share = like * w
        share *= (numbers / share.sum(axis=1))[:, None]
        new = share.sum(axis=0) + 1
        new /= new.sum()
        if np.abs(new - w).max() < tolerance:
            return new
        w = new
    return w


def cell_ratios(quantised: np.ndarray, numbers: np.ndarray, sums: np.ndarray) -> np.ndarray:
    """Each cell's mean ratio to the uniform share, by order; 0 where the estimate is."""
    return np.where(quantised == NEVER, 0, np.exp2(sums / np.maximum(numbers, 1)[:, None] / FINE))


def _learn(joined: DataFrame, order: int) -> np.ndarray:
    """Weights by context bucket, each bucket's learned in a task of its own.

    Only the weights come to the driver. Buckets without held-out tokens take the
    weights of all tokens together, bucket -1 here.
    """
    keys, sums = [f"q{k}" for k in range(1, order + 1)], [f"s{k}" for k in range(1, order + 1)]
    cells = stage(_cell_table(joined, order), "lm-cells")
    pooled = cells.groupBy(*keys).agg(*(F.sum(c).alias(c) for c in ("n", *sums))).select(F.lit(-1).alias("bucket"), *keys, "n", *sums)

    def fit(table: pa.Table) -> pa.Table:
        q, s = (np.stack([table[c].to_numpy() for c in names], axis=1) for names in (keys, sums))
        n = table["n"].to_numpy().astype(np.float64)
        w = fit_weights(cell_ratios(q, n, s), n)
        return pa.table({"bucket": table["bucket"].slice(0, 1), "weights": pa.array([w.tolist()], pa.list_(pa.float64()))})

    learned = dict(cells.unionByName(pooled).groupBy("bucket").applyInArrow(fit, "bucket int, weights array<double>").collect())
    rest = learned.pop(-1, np.full(order + 1, 1 / (order + 1)))
    return np.array([learned.get(b, rest) for b in range(max(64, 1 + max(learned, default=0)))])


def token_log10(f: list[np.ndarray], bucket: np.ndarray, model: Mixture) -> np.ndarray:
    w = model.weights[np.minimum(bucket, len(model.weights) - 1)]
    p = w[:, 0] / (model.distinct + 1)
    for k, x in enumerate(f, start=1):
        p = p + w[:, k] * x
    return np.log10(p)


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _score(joined: DataFrame, model: Mixture) -> DataFrame:
    order = model.order

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                ids = expand(r["seq"], np.int32)
                doc_ids, roles, lengths = docs_of(r["docs"])
                places = places_of(lengths)
                levels = _levels(ids, places, order, r["n_vocab"])
                flat, counts = expand(r["counts"], np.uint64), []
                for x in levels:
                    counts.append(flat[: len(x[1])])
                    flat = flat[len(x[1]) :]
                at = np.flatnonzero(places >= order - 1)
                doc = np.repeat(np.arange(len(lengths)), lengths)[at]
                f, bucket = _estimates(order, levels, at, counts, model.total) if model.total else ([np.zeros(len(at))] * order, np.zeros(len(at), np.int64))
                c = counts[0][levels[0][2][at]].astype(np.float64)
                per = lambda x: np.bincount(doc, weights=x, minlength=len(lengths))  # noqa: E731,B023
                base = np.log10((c + 0.5) / (model.total + 0.5 * (model.distinct + 1)))
                n = len(lengths)
                trim()
                yield pa.RecordBatch.from_arrays([pa.array(doc_ids, pa.int64()), pa.array(roles == 2), pa.array(lengths - (order - 1), pa.int64()), pa.array(per(c > 0).astype(np.int64)), pa.array(np.full(n, model.total, np.int64)), pa.array(per(base)), pa.array(per(token_log10(f, bucket, model)))], names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return joined.select("docs", "seq", "n_vocab", "counts").mapInArrow(run, SCORES)


def fit_and_score(docs: DataFrame, order: int = 2, held_fold: int = 1) -> tuple[DataFrame, Mixture]:
    """Learn from the rows whose fold is not ``held_fold`` and score every row.

    ``docs``: doc_id, text. Returns the scores and the learned mixture. With no
    training token at all every probability is the uniform one.
    """
    if order < 2:
        raise ValueError("order must be 2 or more")
    spark: SparkSession = docs.sparkSession
    blocks = stage(word_blocks(docs, order - 1, 1, lambda d: _role(d, held_fold)), "lm-blocks")
    which = [[k] for k in range(1, order + 1)]  # one order at a time is on its way to the buckets
    words = stage(count_in_buckets(_ask(blocks, order, which[0], bucket_count(blocks, "n_vocab")), 2), "lm-words")
    # of each bucket of words: distinct under deletion and in all training rows, and the totals
    told = [0, 0, 0, 0]
    for r in words.where("block = -1").select("counts").toLocalIterator():
        told = [a + int(b) for a, b in zip(told, expand(r[0], np.uint64), strict=True)]
    starts = _start_counts(docs, held_fold)
    distinct_a, distinct_t = told[0] - (starts[0] > 0), told[1] - (starts[1] > 0)
    total_a, total_t = told[2] - starts[0], told[3] - starts[1]
    release(spark)
    replies, done = words.withColumn("part", F.lit(0)), [blocks, words]
    for part in range(1, order):
        grams = stage(count_in_buckets(_ask(blocks, order, which[part], bucket_count(blocks, "n_grams")), 2), "lm-grams")
        release(spark)
        replies = replies.unionByName(grams.withColumn("part", F.lit(part)))
        done.append(grams)
    joined = stage(_join(blocks, replies, order, (total_a, distinct_a), which), "lm-joined")
    for used in done:
        drop_stage(used)
    release(spark)
    model = Mixture(order, _learn(joined, order), total_t, distinct_t)
    return _score(joined, model), model


def _start_counts(docs: DataFrame, held_fold: int) -> tuple[int, int]:
    """How often the start symbol was counted as a word: once for each training row, by role."""
    crc = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))
    r = docs.select(crc.alias("c")).where(F.col("c") % 5 != held_fold).agg(F.count_if(F.floor(F.col("c") / 5) % 10 != 0), F.count("*")).first()
    return int(r[0]), int(r[1])


def _cell_table(joined: DataFrame, order: int) -> DataFrame:
    """(bucket, q1, ..., n, s1, ...): the EM cells of all blocks together."""
    keys, sums = ["bucket", *(f"q{k}" for k in range(1, order + 1))], ["n", *(f"s{k}" for k in range(1, order + 1))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(0).to_pylist():
                x = np.frombuffer(data, np.int64).reshape(-1, 2 * order + 2).T
                yield pa.RecordBatch.from_arrays([*(pa.array(c.astype(np.int32)) for c in x[: order + 1]), *(pa.array(c) for c in x[order + 1 :])], names=[*keys, *sums])

    schema = ", ".join([*(f"{c} int" for c in keys), *(f"{c} long" for c in sums)])
    return joined.select("cells").mapInArrow(run, schema).groupBy(*keys).agg(*(F.sum(c).alias(c) for c in sums))

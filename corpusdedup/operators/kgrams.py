"""Repeated k-grams of a corpus without a row for each character.

Texts are gathered in compressed blocks, and what is counted goes to hash-range buckets in
packed form (:mod:`..llm.blocks`). Three rounds of counting each leave less text to the next:

1. A k-gram chooses the least hash among its own shorter grams, of equal ones the last, so equal
   k-grams choose equal *fingerprints*. Neighbours that choose the same place are a *run*. A
   k-gram can only repeat where its fingerprint has several runs in the shard.
2. Of these, runs of the same text repeat as a whole. If all runs of a fingerprint have one text,
   nothing else is asked; else each text is sent on once, for it may share some k-grams with others.
3. What is sent on is counted k-gram by k-gram, by 128-bit hash.

A key is one entry for each block and text that holds it. A fingerprint of very many runs would
still bring all its texts to one bucket: it skips the second round, and its k-grams are spread.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..llm.blocks import REPLY, REQUEST, bucket_count, count_in_buckets, expand, expand_sorted, mix, request_batches, slices, squeeze, squeeze_sorted, trim
from ..session import drop_stage, release, spread, stage
from .substring import ROLL, SPANS, _rolled, places

#: Characters gathered in a block before it is closed; bounds a task's memory.
BLOCK_CHARS = 4_000_000
#: Runs of a fingerprint up to which their texts meet in one bucket.
COMMON = 100_000
#: The bits of a fingerprint that are sent. One shared by chance is told apart by the next rounds.
SHORT = np.uint64(0xFFFFFFFFFF000000)

BLOCK = "block long, pieces binary, text binary, n_keys long, spans array<struct<doc_id:long,start:int,stop:int>>"
PAIRS = "bucket int, block long, keys binary, others binary, counts binary"
SPAN = pa.list_(pa.struct([("doc_id", pa.int64()), ("start", pa.int32()), ("stop", pa.int32())]))


class Pieces:
    """Stretches of texts that a block holds: document, shard, place in the text, characters, flag."""

    def __init__(self, columns: np.ndarray, codes: np.ndarray):
        self.doc, self.shard, self.at, self.length, self.flag = self.columns = columns
        self.codes = codes
        self.ends = np.cumsum(self.length)

    @classmethod
    def of(cls, pieces: bytes, text: bytes) -> Pieces:
        codes = zstandard.ZstdDecompressor().decompress(text).decode().encode("utf-32-le")
        return cls(expand(pieces, np.int64).reshape(5, -1), np.frombuffer(codes, np.uint32))

    def row(self, block: int, n_keys: int, spans: list[dict] | None = None) -> dict:
        text = zstandard.ZstdCompressor(level=3).compress(self.codes.astype("<u4").tobytes().decode("utf-32-le").encode())
        return {"block": block, "pieces": squeeze(self.columns.reshape(-1)), "text": text, "n_keys": n_keys, "spans": spans or []}

    def holder(self, where: np.ndarray) -> np.ndarray:
        """The piece of each place of the joined codes."""
        return np.searchsorted(self.ends, where, side="right")

    def cut(self, k: int, first: np.ndarray, stop: np.ndarray, flag: np.ndarray) -> Pieces:
        """The text of the k-grams at first to stop; what continues in the same piece with the same flag stays one piece."""
        piece = self.holder(first)
        fresh = np.ones(len(first), bool)
        fresh[1:] = (piece[1:] != piece[:-1]) | (first[1:] != stop[:-1]) | (flag[1:] != flag[:-1])
        lo, piece, flag = first[fresh], piece[fresh], flag[fresh]
        length = stop[np.append(fresh[1:], True)[: len(stop)]] - lo + k - 1
        at = self.at[piece] + lo - (self.ends - self.length)[piece]
        return Pieces(np.array([self.doc[piece], self.shard[piece], at, length, flag], np.int64), self.codes[places(length) + np.repeat(lo, length)])

    def spans(self, k: int, first: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Document, start and stop of what the k-grams at first to stop cover."""
        piece = self.holder(first)
        fresh = np.ones(len(first), bool)
        fresh[1:] = (piece[1:] != piece[:-1]) | (first[1:] >= stop[:-1] + k)
        piece, lo = piece[fresh], first[fresh]
        hi = stop[np.append(fresh[1:], True)[: len(stop)]] + k - 1
        shift = self.at[piece] - (self.ends - self.length)[piece]
        return self.doc[piece], lo + shift, hi + shift

    def inside(self, k: int) -> np.ndarray:
        """Whether a k-gram of one piece starts at each place."""
        ok = np.ones(len(self.codes), bool)
        ok[(self.ends[:, None] - np.arange(1, k)).ravel()] = False
        return ok

    def runs(self, k: int, step: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(first, stop, key): k-grams at first to stop choose the same place; key is its fingerprint in the shard."""
        size = fingerprint_size(k)
        width, inside, out = k - size + 1, self.inside(k), []
        n = len(self.codes) - k + 1
        for lo in range(0, n, step):
            hi = min(n, lo + step)
            h = _rolled(self.codes[lo : hi + k - 1].astype(np.uint64), size, ROLL[0])
            new, least = np.ones(hi - lo, bool), h
            if width > 1:
                rest = sliding_min(h, width - 1)
                least = np.minimum(h[: hi - lo], rest[1:])
                # the choice changes if it falls out, or if what comes in is no larger
                new[1:] = (h[: hi - lo - 1] < rest[1 : hi - lo]) | (h[width:] <= least[:-1])
            ok = inside[lo:hi]
            edge = new.copy()
            edge[1:] = np.where(ok[1:], new[1:] | ~ok[:-1], ok[:-1])
            first = np.flatnonzero(edge)
            stop = np.append(first[1:], hi - lo)
            mine = ok[first]
            out.append((first[mine] + lo, stop[mine] + lo, least[first[mine]]))
        first, stop, key = (np.concatenate(x) for x in zip(*out, strict=True))
        return first, stop, in_shard(key, self.shard[self.holder(first)]) & SHORT

    def hashes(self, k: int, step: int, multiplier: int) -> np.ndarray:
        """A hash of the k characters from each place on."""
        n = len(self.codes) - k + 1
        return np.concatenate([_rolled(self.codes[lo : min(n, lo + step) + k - 1].astype(np.uint64), k, multiplier) for lo in range(0, n, step)])


def fingerprint_size(k: int) -> int:
    """Characters of a fingerprint's gram: 32 of 50."""
    return k - k * 9 // 25


def sliding_min(h: np.ndarray, width: int) -> np.ndarray:
    part, have = h, 1
    while 2 * have <= width:
        part, have = np.minimum(part[:-have], part[have:]), 2 * have
    rest = width - have
    return np.minimum(part[:-rest], part[rest:]) if rest else part


def in_shard(key: np.ndarray, shard: np.ndarray) -> np.ndarray:
    return mix(key + mix(shard.astype(np.uint64) + np.uint64(1)))


def distinct_pairs(key: np.ndarray, other: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ascending distinct pairs, their sums of n, the number of each row's pair, and the first row of each pair."""
    by = np.lexsort((other, key))
    a, b = key[by], other[by]
    fresh = np.ones(len(by), bool)
    fresh[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    number = np.empty(len(by), np.int64)
    number[by] = np.cumsum(fresh) - 1
    sums = np.bincount(number, weights=n, minlength=int(fresh.sum())).astype(np.int64)
    return a[fresh], b[fresh], sums, number, by[fresh]


def ask_pairs(block: int, key: np.ndarray, other: np.ndarray, n: np.ndarray, buckets: int) -> pa.RecordBatch:
    """Rows that ask the buckets of the keys about a block's distinct pairs."""
    key, other, n, _, _ = distinct_pairs(key, other, n)
    n = np.minimum(n, 2).astype(np.uint8)
    rows = [(b, block, squeeze_sorted(key[x:y]), other[x:y].tobytes(), squeeze(n[x:y])) for b, x, y in slices(key, buckets)]
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
    types = (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["bucket", "block", "keys", "others", "counts"])


def pairs_in_buckets(requests: DataFrame) -> DataFrame:
    """For every pair asked about: 1 if it stands more than once, and 2 if its key has other pairs too and no lower block has this one."""

    def count(table: pa.Table) -> pa.Table:
        table = table.sort_by("block")
        keys = [expand_sorted(x) for x in table["keys"].to_pylist()]
        other = np.concatenate([np.frombuffer(x, np.uint64) for x in table["others"].to_pylist()])
        n = np.concatenate([expand(x, np.uint8) for x in table["counts"].to_pylist()])
        key, _, sums, number, lowest = distinct_pairs(np.concatenate(keys), other, n)
        several = np.zeros(len(key), bool)
        several[1:] = key[1:] == key[:-1]
        several[:-1] |= several[1:].copy()
        code = (sums > 1)[number].astype(np.uint8)
        code[lowest[several]] |= 2
        edges = np.cumsum([0, *map(len, keys)]).tolist()
        out = [squeeze(code[a:b]) for a, b in zip(edges[:-1], edges[1:], strict=True)]
        blocks, bucket = table["block"].combine_chunks(), table["bucket"].combine_chunks()
        del keys, other, n, key, sums, number, lowest, several, code
        trim()
        return pa.table({"block": blocks, "bucket": bucket, "counts": pa.array(out, pa.binary())})

    return requests.groupBy("bucket").applyInArrow(count, REPLY)


def with_replies(blocks: DataFrame, replies: DataFrame, take: Callable[[Pieces, int, list[bytes]], pa.Table], schema: str) -> DataFrame:
    """``take`` of each block's pieces, number and answers in the order of its keys."""

    def run(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        own = next(r for r in rows if r["pieces"] is not None)
        got = [r["counts"] for r in sorted((r for r in rows if r["pieces"] is None), key=lambda r: r["bucket"])]
        out = take(Pieces.of(own["pieces"], own["text"]), own["block"], got)
        del rows, own, got
        trim()
        return out

    none = F.lit(None).cast("binary")
    asked = replies.where("block >= 0").select("block", "bucket", "counts", none.alias("pieces"), none.alias("text"))
    return asked.unionByName(blocks.select("block", F.lit(0).alias("bucket"), none.alias("counts"), "pieces", "text")).groupBy("block").applyInArrow(run, schema)


def asked(blocks: DataFrame, ask: Callable[[int, Pieces], pa.RecordBatch], schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block, pieces, text in zip(*(batch[c] for c in ("block", "pieces", "text")), strict=True):
                yield ask(block.as_py(), Pieces.of(pieces.as_py(), text.as_py()))
                trim()

    return blocks.select("block", "pieces", "text").mapInArrow(run, schema)


def text_blocks(texts: DataFrame, k: int) -> DataFrame:
    """Blocks of about BLOCK_CHARS characters of (shard, doc_id, text); a longer text is cut into pieces that share k - 1."""
    most, width = BLOCK_CHARS, k - fingerprint_size(k) + 1

    def closed(number: int, held: list) -> pa.RecordBatch:
        pieces = Pieces(np.array([(*h[:3], len(h[3]), 0) for h in held], np.int64).T.copy(), np.concatenate([h[3] for h in held]))
        return pa.RecordBatch.from_pylist([pieces.row(number, 2 * len(pieces.codes) // (width + 1) + 1)], block_schema())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, held, size = TaskContext.get().partitionId(), 0, [], 0
        for batch in batches:
            for shard, doc, text in zip(*batch.columns, strict=True):
                codes = np.frombuffer(text.as_py().encode("utf-32-le"), np.uint32)
                for lo in range(0, len(codes) - k + 1, most):
                    piece = codes[lo : lo + most + k - 1]
                    held.append((doc.as_py(), shard.as_py(), lo, piece))
                    size += len(piece)
                    if size >= most:
                        yield closed(part << 24 | number, held)
                        number, held, size = number + 1, [], 0
                        trim()
        if held:
            yield closed(part << 24 | number, held)

    return texts.mapInArrow(run, BLOCK)


def block_schema() -> pa.Schema:
    return pa.schema([("block", pa.int64()), ("pieces", pa.binary()), ("text", pa.binary()), ("n_keys", pa.int64()), ("spans", SPAN)])


def repeated_kgrams(texts: DataFrame, k: int, step: int) -> DataFrame:
    """(doc_id, start, stop) covered by k-grams that stand twice or more in the shard, of (shard, doc_id, text); spans of a document may overlap.

    ``step``: places that are hashed at a time.
    """
    spark, common = texts.sparkSession, COMMON
    blocks = stage(text_blocks(spread(texts), k), "text-blocks")

    # 1: fingerprints
    buckets = bucket_count(blocks, "n_keys")

    def ask_fingerprints(block: int, pieces: Pieces) -> pa.RecordBatch:
        keys, n = np.unique(pieces.runs(k, step)[2], return_counts=True)
        return request_batches(block, keys, [n], buckets)

    def several(pieces: Pieces, block: int, got: list[bytes]) -> pa.Table:
        first, stop, key = pieces.runs(k, step)
        _, number = np.unique(key, return_inverse=True)
        total = np.concatenate([expand(x, np.uint64) for x in got])[number]
        keep = total > 1
        often = (total > common)[keep]
        rows = [pieces.cut(k, first[keep], stop[keep], often.astype(np.int64)).row(block, int((~often).sum()))] if keep.any() else []
        return pa.Table.from_pylist(rows, block_schema())

    counted = count_in_buckets(asked(blocks, ask_fingerprints, REQUEST), 1)
    rest = stage(with_replies(blocks, counted, several, BLOCK), "repeated-fingerprints")
    drop_stage(blocks)
    release(spark)

    # 2: whole runs
    run_buckets = bucket_count(rest, "n_keys")

    def whole_runs(pieces: Pieces) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(first, stop, key, text's hash, whether the runs are asked about): the first and last k-gram of a run overlap, so both are its text."""
        first, stop, key = pieces.runs(k, step)
        g = pieces.hashes(k, step, ROLL[1])
        return first, stop, key, mix(g[first] + mix(g[stop - 1] + (stop - first).astype(np.uint64))), pieces.flag[pieces.holder(first)] == 0

    def ask_runs(block: int, pieces: Pieces) -> pa.RecordBatch:
        _, _, key, text, ask = whole_runs(pieces)
        return ask_pairs(block, key[ask], text[ask], np.ones(int(ask.sum())), run_buckets)

    def unsettled(pieces: Pieces, block: int, got: list[bytes]) -> pa.Table:
        first, stop, key, text, ask = whole_runs(pieces)
        code = np.full(len(first), 2, np.uint8)  # runs of common fingerprints go on
        if got:
            number = distinct_pairs(key[ask], text[ask], np.ones(int(ask.sum())))[3]
            code[ask] = np.concatenate([expand(x, np.uint8) for x in got])[number]
        hit, on = (code & 1) > 0, (code & 2) > 0
        spans = [{"doc_id": d, "start": a, "stop": b} for d, a, b in zip(*(x.tolist() for x in pieces.spans(k, first[hit], stop[hit])), strict=True)]
        # a run that stands twice is sent on by one block, and its k-grams count as two
        left = pieces.cut(k, first[on], stop[on], 1 + hit[on])
        return pa.Table.from_pylist([left.row(block, int((stop - first)[on].sum()), spans)], block_schema())

    answers = pairs_in_buckets(asked(rest, ask_runs, PAIRS))
    left = stage(with_replies(rest, answers, unsettled, BLOCK), "unsettled-runs")
    drop_stage(rest)
    release(spark)

    # 3: single k-grams
    gram_buckets = bucket_count(left, "n_keys")

    def grams(pieces: Pieces) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(place, hash, second hash, count)."""
        at = np.flatnonzero(pieces.inside(k)[: len(pieces.codes) - k + 1])
        piece = pieces.holder(at)
        g, g2 = (pieces.hashes(k, step, m)[at] for m in ROLL)
        return at, in_shard(g, pieces.shard[piece]), g2, pieces.flag[piece]

    def ask_grams(block: int, pieces: Pieces) -> pa.RecordBatch:
        return ask_pairs(block, *grams(pieces)[1:], gram_buckets)

    def repeated(pieces: Pieces, block: int, got: list[bytes]) -> pa.Table:
        at, g, g2, n = grams(pieces)
        hit = (np.concatenate([expand(x, np.uint8) for x in got]) & 1 > 0)[distinct_pairs(g, g2, n)[3]]
        doc, start, stop = pieces.spans(k, at[hit], at[hit] + 1)
        return pa.table({"doc_id": pa.array(doc, pa.int64()), "start": pa.array(start.astype(np.int32)), "stop": pa.array(stop.astype(np.int32))})

    open_blocks = left.where("n_keys > 0")
    single = with_replies(open_blocks, pairs_in_buckets(asked(open_blocks, ask_grams, PAIRS)), repeated, SPANS)
    return left.select(F.explode("spans").alias("s")).select("s.*").unionByName(single)

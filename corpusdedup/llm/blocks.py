"""Counting of 64-bit keys in packed form.

Exploding a corpus into one row for every n-gram costs some 30 bytes a row in a
shuffle. Here a task gathers its documents into *blocks*, sends the sorted
distinct keys of a block to hash-range *buckets* as delta-coded binaries, and a
bucket answers each block with the global counts of just those keys. A key takes
about 6 bytes one way and 1 byte back, and both ways the rows stay few.

A bucket is a range of hash values, so a frequent key is one entry for each block
that holds it: no key, source or group of copies makes a bucket heavy.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shuffle_partitions

#: About so many keys of all blocks meet in a bucket.
BUCKET_KEYS = 2_000_000

REPLY = "block long, bucket int, counts binary"


def trim() -> None:
    """Give freed memory back to the system: workers live on, and what they hold counts as the executor's."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: nothing to trim
        pass


def words_of(text: bytes | None) -> list[bytes]:
    """Words of a UTF-8 text: runs without space, tab, newline, VT, FF or CR (what bytes.split takes)."""
    return text.split() if text else []


def lowered(text: bytes | None) -> bytes:
    """A-Z to a-z, nothing else."""
    return text.lower() if text else b""


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def hash_words(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def squeeze(values: np.ndarray) -> bytes:
    """An integer array as compressed byte planes: high planes of small values vanish."""
    v = np.ascontiguousarray(values)
    planes = v.view(np.uint8).reshape(len(v), v.itemsize).T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(planes).tobytes())


def expand(data: bytes, dtype) -> np.ndarray:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    width = np.dtype(dtype).itemsize
    return np.ascontiguousarray(raw.reshape(width, -1).T).reshape(-1).view(dtype)


def squeeze_sorted(keys: np.ndarray) -> bytes:
    """Ascending 64-bit keys as their differences."""
    return squeeze(np.diff(keys, prepend=np.uint64(0)))


def expand_sorted(data: bytes) -> np.ndarray:
    return np.cumsum(expand(data, np.uint64), dtype=np.uint64)


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    """The hash range of each key; ascending keys give ascending buckets."""
    return ((keys >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def bucket_count(blocks: DataFrame, keys_col: str) -> int:
    """Buckets in proportion to the keys sent, so that a bucket's size does not depend on the input's."""
    total = blocks.agg(F.sum(keys_col)).first()[0] or 0
    return max(2 * shuffle_partitions(blocks.sparkSession), -(-total // BUCKET_KEYS))


def slices(keys: np.ndarray, buckets: int) -> Iterator[tuple[int, int, int]]:
    """(bucket, from, to) of an ascending key array."""
    at = bucket_of(keys, buckets)
    edges = np.flatnonzero(np.diff(at)) + 1
    for a, b in zip([0, *edges], [*edges, len(at)], strict=True):
        if b > a:
            yield int(at[a]), int(a), int(b)


def request_batches(block: int, keys: np.ndarray, counts: list[np.ndarray], buckets: int) -> pa.RecordBatch:
    """Rows (bucket, block, keys, counts) that ask the buckets about a block's ascending distinct keys."""
    rows = [(b, block, squeeze_sorted(keys[x:y]), squeeze(np.concatenate([c[x:y] for c in counts]).astype(np.uint32))) for b, x, y in slices(keys, buckets)]
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.binary()), pa.array(cols[3], pa.binary())], names=["bucket", "block", "keys", "counts"])


REQUEST = "bucket int, block long, keys binary, counts binary"


def count_in_buckets(requests: DataFrame, columns: int) -> DataFrame:
    """Global sums for every requested key.

    Returns rows (block, bucket, counts): ``columns`` arrays of 64-bit sums in the
    order of the block's keys. One more row for each bucket, of block -1, holds the
    number of keys with a sum over 0 in each column and then the columns' totals.
    """

    def count(table: pa.Table) -> pa.Table:
        sent = [expand_sorted(x) for x in table["keys"].to_pylist()]
        own = [expand(x, np.uint32).reshape(columns, -1) for x in table["counts"].to_pylist()]
        _, where = np.unique(np.concatenate(sent), return_inverse=True)
        size = int(where.max()) + 1
        sums = []
        for c in range(columns):
            sums.append(np.bincount(where, weights=np.concatenate([x[c] for x in own]), minlength=size).astype(np.uint64))
        out, at = [], 0
        for keys in sent:
            mine = where[at : at + len(keys)]
            out.append(squeeze(np.concatenate([s[mine] for s in sums])))
            at += len(keys)
        told = np.array([int((s > 0).sum()) for s in sums] + [int(s.sum()) for s in sums], np.uint64)
        bucket = table["bucket"][0].as_py()
        del where, sums, sent, own
        trim()
        return pa.table({"block": pa.array([*table["block"].to_pylist(), -1], pa.int64()), "bucket": pa.array([bucket] * (len(out) + 1), pa.int32()), "counts": pa.array([*out, squeeze(told)], pa.binary())})

    return requests.groupBy("bucket").applyInArrow(count, REPLY)


#: Tokens gathered in a block before it is closed; bounds a task's memory.
BLOCK_TOKENS = 1_000_000
#: Codes of the start and end symbols: words have no white space.
START_END = hash_words([b"\n start", b"\n end"])
BLOCKS = "block long, docs binary, seq binary, vocab binary, n_vocab long, n_grams long"


class WordBlock:
    """Lower-cased words of several documents as local ids; 0 is the start symbol, 1 the end."""

    def __init__(self, starts: int = 0, ends: int = 0):
        self.starts, self.ends, self.local = starts, ends, {}
        self.docs, self.seqs, self.size = [], [], 0

    def add(self, doc_id: int | None, text: bytes | None, role: int = 0) -> None:
        words = words_of(lowered(text))
        local = self.local
        for w in dict.fromkeys(words):
            if w not in local:
                local[w] = len(local) + 2
        own = np.empty(self.starts + len(words) + self.ends, np.int32)
        own[: self.starts] = 0
        own[self.starts : self.starts + len(words)] = np.fromiter(map(local.__getitem__, words), np.int32, len(words))
        own[self.starts + len(words) :] = 1
        self.docs.append((doc_id, role, len(own)))
        self.seqs.append(own)
        self.size += len(own)

    def batch(self, number: int) -> pa.RecordBatch:
        ids = np.concatenate(self.seqs)
        # ids by frequency, so that the high byte planes are nearly empty
        by = np.argsort(-np.bincount(ids, minlength=len(self.local) + 2), kind="stable")
        rank = np.empty(len(by), np.int32)
        rank[by] = np.arange(len(by), dtype=np.int32)
        vocab = np.concatenate([START_END, hash_words(list(self.local))])[by]
        docs = pa.table({"doc_id": pa.array([d[0] for d in self.docs], pa.int64()), "role": pa.array([d[1] for d in self.docs], pa.int8()), "length": pa.array([d[2] for d in self.docs], pa.int64())})
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, docs.schema) as w:
            w.write_table(docs)
        row = [number, sink.getvalue().to_pybytes(), squeeze(rank[ids]), squeeze(vocab), len(vocab), self.size]
        return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, (pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64()), strict=True)], names=["block", "docs", "seq", "vocab", "n_vocab", "n_grams"])


def docs_of(data: bytes) -> tuple[list, np.ndarray, np.ndarray]:
    """Ids, roles and lengths of a block's documents."""
    t = pa.ipc.open_stream(data).read_all()
    return t["doc_id"].to_pylist(), t["role"].to_numpy(), t["length"].to_numpy()


def places(lengths: np.ndarray) -> np.ndarray:
    """Each position's place in its document."""
    first = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    return np.arange(int(lengths.sum())) - np.repeat(first, lengths)


def word_blocks(docs: DataFrame, starts: int = 0, ends: int = 0, role: Callable[[int | None], int] = lambda _: 0) -> DataFrame:
    """Tokenise (doc_id, text) once; later passes read the word ids, about 1.5 bytes a word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, block = TaskContext.get().partitionId(), 0, WordBlock(starts, ends)
        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                block.add(doc_id, text.as_buffer().to_pybytes() if text.is_valid else None, role(doc_id))
                if block.size >= BLOCK_TOKENS:
                    yield block.batch(part << 24 | number)
                    number, block = number + 1, WordBlock(starts, ends)
                    trim()
        if block.docs:
            yield block.batch(part << 24 | number)

    # string and binary share their bytes; the cast only spares Python the decoding
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary")).mapInArrow(run, BLOCKS)

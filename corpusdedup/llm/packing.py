"""Best-fit packing into sequences of several permitted lengths.

Pieces go, longest first, to the open bin with the least room that still holds them.
If there is none, a bin is opened: of the permitted lengths that hold the piece the
one with the least cost for each token that it can expect, given what is still to be
placed and would fit beside the piece; the cost of a bin is its length plus a fixed
charge for each sequence. When all is placed, every bin shrinks to the shortest
permitted length that holds its contents.

Documents longer than the longest bin are cut into full bins and a rest, so no token
is dropped. The work is dealt by a hash of the row's place in groups of about
``GROUP_TOKENS``: an id that repeats a thousandfold spreads over the groups, and a
group's size does not depend on the input's. Empty documents (length 0) get no
piece; null texts count as empty. Ties in length go by row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import stage

CAPACITIES = (512, 1024, 2048, 4096)
#: Tokens' worth of cost that a sequence has besides its length.
CHARGE = 32
GROUP_TOKENS = 4_000_000

LENGTHS = "row long, doc_id long, length long"


def word_lengths(docs: DataFrame) -> DataFrame:
    """(row, doc_id, length) of (doc_id, text): words and one end token; 0 for a text without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = TaskContext.get().partitionId() << 36
        for batch in batches:
            n = [len(t.as_buffer().to_pybytes().split()) if t.is_valid else 0 for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([pa.array(range(at, at + len(n)), pa.int64()), batch.column(0), pa.array([x + 1 if x else 0 for x in n], pa.int64())], names=["row", "doc_id", "length"])
            at += len(n)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary")).mapInArrow(run, LENGTHS)


def pack_lengths(lengths: list[int], capacities: tuple[int, ...] = CAPACITIES, charge: int = CHARGE) -> tuple[list[int], list[int], list[int]]:
    """Bin and offset of each piece (given longest first) and the final length of each bin.

    The bins with r free places form a stack, and bit r of one integer says whether
    it is empty: the best fit is the lowest bit from the piece's length on.
    """
    caps = sorted(capacities)
    rest = np.concatenate([np.cumsum(np.array(lengths, np.int64)[::-1])[::-1], [0]]).tolist()
    falling = -np.array(lengths, np.int64)
    room_mask, stacks = 0, [[] for _ in range(caps[-1] + 1)]
    room: list[int] = []
    size: list[int] = []
    bins, offsets = [], []
    for i, n in enumerate(lengths):
        if fits := room_mask >> n:
            free = n + (fits & -fits).bit_length() - 1
            b = stacks[free].pop()
            if not stacks[free]:
                room_mask ^= 1 << free
        else:
            best = None
            for c in caps:
                if c < n:
                    continue
                beside = rest[max(i + 1, int(np.searchsorted(falling, -(c - n))))] if c > n else 0
                cost = (c + charge) / (n + min(c - n, beside))
                if best is None or cost < best[0]:
                    best = (cost, c)
            b, free = len(room), best[1]
            room.append(free)
            size.append(free)
        bins.append(b)
        offsets.append(size[b] - free)
        room[b] = free - n
        if room[b]:
            if not stacks[room[b]]:
                room_mask |= 1 << room[b]
            stacks[room[b]].append(b)
    final = [next(c for c in caps if c >= s - r) for s, r in zip(size, room, strict=True)]
    return bins, offsets, final


PACKED = "doc_id long, row long, piece long, bin_id long, bin_offset long, length long, capacity long"


def pack(lengths: DataFrame, capacities: tuple[int, ...] = CAPACITIES, charge: int = CHARGE, group_tokens: int = GROUP_TOKENS) -> DataFrame:
    """Place every piece of (row, doc_id, length): one row for each piece with its bin, offset and the bin's final length."""
    top = max(capacities)
    lengths = stage(lengths, "pack-lengths")
    total = lengths.agg(F.sum("length")).first()[0] or 0
    groups = max(1, -(-total // group_tokens))
    cut = lengths.where("length > 0").withColumn("piece", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("length") - 1) / top).cast("long"))))
    cut = cut.withColumn("length", F.least(F.lit(top).cast("long"), F.col("length") - F.col("piece") * top)).withColumn("grp", F.pmod(F.xxhash64("row", "piece"), F.lit(groups)))

    def run(table: pa.Table) -> pa.Table:
        n, row, piece = (table[c].to_numpy() for c in ("length", "row", "piece"))
        by = np.lexsort((piece, row, -n))
        bins, offsets, final = pack_lengths(n[by].tolist(), capacities, charge)
        table = table.take(pa.array(by))
        base = table["grp"][0].as_py() << 32
        b = np.array(bins, np.int64)
        return pa.table({"doc_id": table["doc_id"], "row": table["row"], "piece": table["piece"], "bin_id": pa.array(base + b), "bin_offset": pa.array(offsets, pa.int64()), "length": table["length"], "capacity": pa.array(np.array(final, np.int64)[b])})

    return cut.groupBy("grp").applyInArrow(run, PACKED)

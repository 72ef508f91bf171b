"""Benchmark decontamination by pigeonhole edit matching.

An item of m characters may differ from a passage by e = floor(RATE * m) edits. Cut
into e + 1 pieces, at least one piece of any such passage is unedited, so exact piece
hits (one automaton for all items) find every candidate place; Myers' bit-parallel
distance then decides over the hit's surroundings.

Texts and items are compared in lower case with every run of white space as one
space, trimmed; distances and positions count characters of that form. Null and
empty texts match nothing, null and empty items match nothing, and an item too short
for an edit must occur exactly. Of several places in a text the one with the smallest
distance counts, then the first. Repeated rows are each reported; items of the same
text are each reported.

Items reach the tasks in slices of bounded size; a larger benchmark means more passes
over the documents, not more memory. Texts are never shuffled.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edits allowed for each character of an item.
RATE = 0.05
#: Characters of the items that one pass looks for.
SLICE_CHARS = 4_000_000

Item = tuple[int | None, str]


def plain(text: str | None) -> str:
    return " ".join(text.lower().split()) if text else ""


def edit_budget(item: str, rate: float = RATE) -> int:
    return int(rate * len(item))


def pieces(item: str, budget: int) -> list[tuple[int, str]]:
    """(offset, piece): ``budget + 1`` pieces of nearly equal length."""
    n = budget + 1
    cuts = [k * len(item) // n for k in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


def myers(pattern: str, text: str, free_start: bool = True) -> tuple[int, int]:
    """(distance, end): the smallest edit distance of ``pattern`` to a part of ``text`` and where the first such part ends.

    The part may begin anywhere, or only at 0 if not ``free_start``. One column of the
    distance table is two integers of len(pattern) bits.
    """
    m = len(pattern)
    if not m:
        return 0, 0
    eq: dict[str, int] = {}
    for i, c in enumerate(pattern):
        eq[c] = eq.get(c, 0) | 1 << i
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score = full, 0, m
    best, end = m, 0
    for j, c in enumerate(text, 1):
        x = eq.get(c, 0)
        d0 = ((((x & up) + up) ^ up) | x | down) & full
        rise = down | (full & ~(d0 | up))
        fall = up & d0
        if rise & top:
            score += 1
        elif fall & top:
            score -= 1
        rise = (rise << 1 | (not free_start)) & full
        fall = fall << 1 & full
        up = fall | (full & ~(d0 | rise))
        down = rise & d0
        if score < best:
            best, end = score, j
    return best, end


class Matcher:
    """All pieces of a slice of items in one automaton."""

    def __init__(self, items: list[Item], rate: float):
        self.items = [(i, t, edit_budget(t, rate)) for i, t in items]
        self.find = ahocorasick.Automaton()
        where: dict[str, list[tuple[int, int]]] = {}
        for k, (_, t, e) in enumerate(self.items):
            for at, piece in pieces(t, e):
                where.setdefault(piece, []).append((k, at))
        for piece, users in where.items():
            self.find.add_word(piece, (len(piece), users))
        if where:
            self.find.make_automaton()

    def matches(self, text: str) -> list[tuple[int | None, int, int, int, int]]:
        """(item id, budget, distance, start, end) of every item found in a plain text."""
        if not text or not self.items:
            return []
        spans: dict[int, list[list[int]]] = {}
        for end, (n, users) in self.find.iter(text):
            for k, at in users:
                _, t, e = self.items[k]
                lo = end + 1 - n - at - e
                hi = lo + len(t) + 2 * e
                own = spans.setdefault(k, [])
                if own and lo <= own[-1][1] and hi >= own[-1][0]:  # hits come in order: overlapping places are looked at once
                    own[-1][0], own[-1][1] = min(lo, own[-1][0]), max(hi, own[-1][1])
                else:
                    own.append([lo, hi])
        out = []
        for k, own in spans.items():
            item, t, e = self.items[k]
            best = (e + 1, 0, 0)
            for lo, hi in own:
                lo = max(lo, 0)
                part = text[lo:hi]
                if (at := part.find(t)) >= 0:
                    found = (0, lo + at, lo + at + len(t))
                else:
                    d, end = myers(t, part)
                    if d > e:
                        continue
                    _, back = myers(t[::-1], part[:end][::-1], False)
                    found = (d, lo + end - back, lo + end)
                best = min(best, found, key=lambda x: (x[0], x[1]))
            if best[0] <= e:
                out.append((item, e, *best))
        return out


_made: dict[str, Matcher] = {}


def _matcher(key: str, items: list[Item], rate: float) -> Matcher:
    """One automaton for each Python worker and slice."""
    if key not in _made:
        _made.clear()
        _made[key] = Matcher(items, rate)
    return _made[key]


def item_slices(benchmark: DataFrame, limit: int = SLICE_CHARS) -> Iterator[list[Item]]:
    """The items in plain form, in slices of at most ``limit`` characters (one item may be longer)."""
    own: list[Item] = []
    size = 0
    for r in benchmark.select(F.col("item_id").cast("long"), F.make_valid_utf8(F.col("text").cast("string")).alias("text")).orderBy("item_id", "text").toLocalIterator():
        t = plain(r[1])
        if not t:
            continue
        if own and size + len(t) > limit:
            yield own
            own, size = [], 0
        own.append((r[0], t))
        size += len(t)
    yield own


def _read(text: pa.StringScalar) -> str:
    """A text; bytes that are not UTF-8 are read as U+FFFD."""
    return text.as_buffer().to_pybytes().decode("utf-8", "replace")


MATCHES = "doc_id long, item_id long, budget int, distance int, match_start long, match_end long"


def find_matches(docs: DataFrame, benchmark: DataFrame, rate: float = RATE, limit: int = SLICE_CHARS) -> DataFrame:
    """One row for every document and item that occurs in it within the item's edit budget."""
    out = None
    for items in item_slices(benchmark, limit):
        key = uuid.uuid4().hex

        def run(batches: Iterator[pa.RecordBatch], items=items, key=key) -> Iterator[pa.RecordBatch]:
            matcher = _matcher(key, items, rate)
            for batch in batches:
                rows = [(d, *m) for d, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True) if t.is_valid for m in matcher.matches(plain(_read(t)))]
                cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
                kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["doc_id", "item_id", "budget", "distance", "match_start", "match_end"])

        part = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, MATCHES)
        out = part if out is None else out.unionByName(part)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, rate: float = RATE, limit: int = SLICE_CHARS) -> DataFrame:
    """The rows of ``docs`` in which no item occurs, with all their columns."""
    schema = docs.schema
    at = schema.fieldNames().index("text")
    for items in item_slices(benchmark, limit):
        key = uuid.uuid4().hex

        def run(batches: Iterator[pa.RecordBatch], items=items, key=key) -> Iterator[pa.RecordBatch]:
            matcher = _matcher(key, items, rate)
            for batch in batches:
                yield batch.filter(pa.array([not (t.is_valid and matcher.matches(plain(_read(t)))) for t in batch.column(at)], pa.bool_()))

        docs = docs.mapInArrow(run, schema)
    return docs

"""Token ids in fixed-width bit-packed files.

A file holds whole documents in ascending doc_id order. Every id takes the minimum
number of bits that the vocabulary needs. Layout, little-endian:

    magic (8 bytes), version, bits, block size, documents, ids, flag of a null id first (6 x int64)
    doc_id, then first id, of each document (2 x int64 arrays)
    byte offset of each block in the packed part (int64 array), then the packed part

A block is ``BLOCK`` ids, so its bits fill whole bytes; the last one is padded. Any id
is found from its block's offset alone, and a block unpacks with numpy as one
reshaping of its bits.

The corpus is cut into ranges of doc_id of nearly equal numbers of rows; one task
writes a range, in files of at most about ``FILE_IDS`` ids, whose names sort like the
ids. Only the files that a finished task has listed are read, so what a lost attempt
left behind does not count. Null texts are empty and a document always ends with ``end_id``, so none has no
ids; bytes that are not UTF-8 are read as U+FFFD. A null doc_id sorts first. Repeated
doc_ids stay separate documents, next to each other, in an order that their ids decide;
an id that many rows repeat has several tasks.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from ..session import fresh_path, shuffle_partitions, stage
from .blocks import trim
from .files import make_folder, small, write_whole

MAGIC = b"PACKIDS1"
BLOCK = 4096
FILE_IDS = 4_000_000
#: Distinct words whose ids a worker remembers.
MEMORY = 400_000
#: So many new words of letters are encoded as one string.
TOGETHER = 50
#: Bytes of text that are encoded at a time, and words whose ids are gathered at a time.
SLICE, GATHER = 6_000_000, 500_000
#: Fixed value: a split that always cuts between a letter or digit and punctuation, but for apostrophes.
LETTERS_OR_PUNCTUATION = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: ASCII punctuation that is a word of its own at a word's end, after one of the letters and digits.
PUNCTUATION = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
BEFORE_PUNCTUATION = frozenset("abcdefghijklmnopqrstuvwxyz0123456789àáâãäåæçèéêëìíîïðñòóôõöøùúûüýþÿ")
#: Letters of Latin-1, whose only normal form is their small letter; A-Z are lowered before.
_LATIN = re.compile("[a-zß-öø-ÿÀ-ÖØ-Þ]+").fullmatch


def bits_for(vocabulary: int) -> int:
    return max(1, (vocabulary - 1).bit_length())


def pack_bits(ids: np.ndarray, bits: int) -> bytes:
    """Ids as ``bits`` bits each, lowest bit first, padded to a byte."""
    if bits == 16:
        return ids.astype("<u2").tobytes()
    if bits == 8:
        return ids.astype(np.uint8).tobytes()
    planes = (ids.astype(np.uint64)[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)
    return np.packbits(planes.astype(np.uint8).reshape(-1), bitorder="little").tobytes()


def unpack_bits(data: bytes, bits: int, count: int) -> np.ndarray:
    if bits == 16:
        return np.frombuffer(data, "<u2", count).astype(np.uint32)
    if bits == 8:
        return np.frombuffer(data, np.uint8, count).astype(np.uint32)
    planes = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little")[: count * bits].reshape(count, bits)
    return (planes.astype(np.uint32) << np.arange(bits, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


def encode_file(doc_ids: list[int | None], ids: list[np.ndarray], bits: int) -> bytes:
    """One file's bytes."""
    flat = np.concatenate(ids) if ids else np.zeros(0, np.uint32)
    if len(flat) and int(flat.max()) >> bits:
        raise ValueError("an id does not fit the vocabulary's bits")
    first = np.concatenate([[0], np.cumsum([len(x) for x in ids])[:-1]]).astype("<i8") if ids else np.zeros(0, "<i8")
    blocks = [pack_bits(flat[k : k + BLOCK], bits) for k in range(0, len(flat), BLOCK)]
    offsets = np.concatenate([[0], np.cumsum([len(b) for b in blocks])]).astype("<i8")
    null = int(sum(d is None for d in doc_ids))
    head = np.array([1, bits, BLOCK, len(ids), len(flat), null], "<i8")
    return b"".join([MAGIC, head.tobytes(), np.array([0 if d is None else d for d in doc_ids], "<i8").tobytes(), first.tobytes(), offsets.tobytes(), *blocks])


class PackedFile:
    """Reads a file's bytes; a document's ids cost only the blocks they lie in."""

    def __init__(self, data: bytes):
        if data[:8] != MAGIC:
            raise ValueError("not a packed id file")
        _, self.bits, self.block, n, self.total, null = np.frombuffer(data, "<i8", 6, 8).tolist()
        at = 8 + 48
        self.doc_ids = [None] * null + np.frombuffer(data, "<i8", n, at).tolist()[null:]
        self.first = np.append(np.frombuffer(data, "<i8", n, at + 8 * n), self.total)
        at += 16 * n
        blocks = -(-self.total // self.block)
        self.offsets = np.frombuffer(data, "<i8", blocks + 1, at)
        self.packed = memoryview(data)[at + 8 * (blocks + 1) :]

    def ids(self, start: int, stop: int) -> np.ndarray:
        """Ids ``start`` to ``stop`` of the file."""
        if stop <= start:
            return np.zeros(0, np.uint32)
        a, b = start // self.block, -(-stop // self.block)
        if self.block * self.bits % 8 == 0:
            count = min(b * self.block, self.total) - a * self.block
            got = unpack_bits(self.packed[self.offsets[a] : self.offsets[b]], self.bits, count)
        else:
            got = np.concatenate([unpack_bits(self.packed[self.offsets[k] : self.offsets[k + 1]], self.bits, min(self.block, self.total - k * self.block)) for k in range(a, b)])
        return got[start - a * self.block : stop - a * self.block]

    def document(self, k: int) -> np.ndarray:
        return self.ids(int(self.first[k]), int(self.first[k + 1]))


class _Recent(dict):
    """Recently used words, and those of the generation before."""

    def __init__(self, before: dict):
        self.before = before


class WordEncoder:
    """Ids of whole texts from a tokenizer that never joins across white space.

    Such a tokenizer encodes every word between ASCII white space on its own, so a batch
    of texts becomes a dictionary of its distinct words; the packed ids of frequent words
    are remembered, new ones are encoded by the library, and the ids of all texts are
    gathered from those of the words. Where the tokenizer's split is
    ``LETTERS_OR_PUNCTUATION``, a new word with punctuation at its end is two words, and
    words of letters only are encoded many in one string, to be parted after each token
    that ends a word; if their number is not that of the words (a letter that normalises to
    a letter and a mark), each word is encoded alone. With ``added`` the strings of added
    tokens in a text are those tokens, as the library reads them by default: a text that
    holds one goes through the library whole. Memory is two generations of ``MEMORY`` words
    at most, plus a batch's.
    """

    def __init__(self, path: str, end_id: int, added: bool = True):
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a word are ordinary text
        self.whole = Tokenizer.from_file(path) if added else None
        tokens = self.tokenizer.get_added_tokens_decoder().values()
        self.added = [t.content for t in tokens if not t.normalized]
        self.added_later = [self._normal(t.content) for t in tokens if t.normalized]
        self.vocabulary = self.tokenizer.get_vocab_size(with_added_tokens=True)
        self.kind = "<u2" if bits_for(self.vocabulary) <= 16 else "<u4"
        self.end = np.array([end_id], self.kind).tobytes()
        # where the tokenizer lower-cases, words that differ in the case of A-Z are one word
        self.lower = '"Lowercase"' in self.tokenizer.to_str()[:4000]
        self.code = "H" if self.kind == "<u2" else "I"
        spec = json.loads(self.tokenizer.to_str())
        splits = (spec["pre_tokenizer"] or {}).get("pretokenizers") or [{}]
        self.apart = self.lower and splits[0].get("pattern") == {"Regex": LETTERS_OR_PUNCTUATION}
        suffix = spec["model"].get("end_of_word_suffix") if self.apart else None
        self.ends = self.plain = None
        if suffix:
            self.ends = np.zeros(self.vocabulary, bool)
            self.ends[[i for w, i in self.tokenizer.get_vocab(with_added_tokens=False).items() if w.endswith(suffix)]] = True
            # for words that no normaliser changes: the same model, cut at blanks alone
            blanks = {"type": "CharDelimiterSplit", "delimiter": " "}
            self.plain = Tokenizer.from_str(json.dumps(spec | {"added_tokens": [], "normalizer": None, "pre_tokenizer": {"type": "Sequence", "pretokenizers": [blanks, *splits[1:]]}}))
        self.recent = _Recent({})

    def encode(self, texts: pa.Array) -> pa.Array:
        """Packed ids of each text as binary, the end id last."""
        texts = pc.fill_null(texts, "")
        whole = self.holding_added(texts) if self.whole else []
        if whole:
            mask = np.ones(len(texts), bool)
            mask[whole] = False
            own = [texts[k].as_py() for k in whole]
            texts = pc.if_else(pa.array(mask), texts, "")
        split = pc.ascii_split_whitespace(pc.ascii_lower(texts) if self.lower else texts)
        coded = split.flatten().dictionary_encode()
        parts = self.lookup(coded.dictionary.to_numpy(zero_copy_only=False).tolist())
        offsets = split.offsets.to_numpy().astype(np.int64)
        # after a text's words comes the end, numbered after all words
        words = np.insert(coded.indices.to_numpy(), offsets[1:], len(parts))
        ids, ends = self.gather(words, [*parts, self.end])
        stops = np.append(0, ends[offsets[1:] + np.arange(len(texts))]) * ids.itemsize
        out = pa.Array.from_buffers(pa.binary(), len(texts), [None, pa.py_buffer(stops.astype("<i4")), pa.py_buffer(ids)])
        if not whole:
            return out
        held = out.to_pylist()
        for k, text in zip(whole, own, strict=True):
            held[k] = array(self.code, self.whole.encode(text, add_special_tokens=False).ids).tobytes() + self.end
        return pa.array(held, pa.binary())

    def gather(self, words: np.ndarray, parts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of numbered words in a row, and where each word's end."""
        flat = np.frombuffer(b"".join(parts), self.kind)
        n = np.fromiter(map(len, parts), np.int64, len(parts)) // flat.itemsize
        first = np.cumsum(n) - n
        ends = np.cumsum(n[words])
        out = np.empty(int(ends[-1]) if len(ends) else 0, self.kind)
        for lo in range(0, len(words), GATHER):
            some = words[lo : lo + GATHER]
            at = int(ends[lo - 1]) if lo else 0
            stop = int(ends[lo + len(some) - 1])
            k = n[some]
            out[at:stop] = flat[np.repeat(first[some] - (ends[lo : lo + len(some)] - k), k) + np.arange(at, stop)]
        return out, ends

    def lookup(self, words: list[str]) -> list[bytes]:
        """Packed ids of distinct words."""
        if len(self.recent) > MEMORY:
            self.recent = _Recent(dict(self.recent))
        get = self.recent.get
        parts = list(map(get, words))
        older = self.recent.before.get
        new = []
        for k, ids in enumerate(parts):
            if ids is None:
                w = words[k]
                if (ids := older(w)) is None:
                    new.append(k)
                else:
                    self.recent[w] = parts[k] = ids
        self.learn([words[k] for k in new])
        for k in new:
            parts[k] = get(words[k])
        return parts

    def _normal(self, text: str) -> str:
        return self.tokenizer.normalizer.normalize_str(text) if self.tokenizer.normalizer else text

    def holding_added(self, texts: pa.Array) -> list[int]:
        """Numbers of the texts that hold the string of an added token, or hold it once normalised where that counts."""
        found = np.zeros(len(texts), bool)
        for t in self.added:
            found |= pc.match_substring(texts, t).to_numpy(zero_copy_only=False)
        if self.added_later:
            found |= np.array([any(t in self._normal(x) for t in self.added_later) for x in texts.to_pylist()], bool)
        return np.flatnonzero(found).tolist()

    def learn(self, new: list[str]) -> None:
        """Encode new words and remember their packed ids."""
        recent, older = self.recent, self.recent.before
        cut, plain, letters, alone = [], [], [], []
        seen = set()

        def sort(w: str) -> None:
            if self.ends is None:
                alone.append(w)
            elif _LATIN(w):
                plain.append(w)
            elif w.isalpha():
                letters.append(w)
            else:
                alone.append(w)

        for w in new:
            b = w.rstrip(PUNCTUATION) if self.apart else w
            if b == w or not b or b[-1] not in BEFORE_PUNCTUATION:
                if w not in seen:
                    seen.add(w)
                    sort(w)
                continue
            e = w[len(b) :]
            cut.append((w, b, e))
            for x in (b, e):
                if x not in seen and x not in recent:
                    seen.add(x)
                    if x in older:
                        recent[x] = older[x]
                    else:
                        sort(x)
        alone += self.learn_together(self.plain, plain) + self.learn_together(self.tokenizer, letters)
        for lo in range(0, len(alone), 20_000):
            some = alone[lo : lo + 20_000]
            for w, e in zip(some, self.tokenizer.encode_batch_fast(some, add_special_tokens=False), strict=True):
                recent[w] = array(self.code, e.ids).tobytes()
        for w, b, e in cut:
            recent[w] = recent[b] + recent[e]

    def learn_together(self, tokenizer: Tokenizer, words: list[str]) -> list[str]:
        """Encode words of letters, many in one string; returns those that could not be told apart."""
        left = []
        for lo in range(0, len(words), 100 * TOGETHER):
            groups = [words[k : k + TOGETHER] for k in range(lo, min(lo + 100 * TOGETHER, len(words)), TOGETHER)]
            for group, e in zip(groups, tokenizer.encode_batch_fast([" ".join(g).lower() if tokenizer is self.plain else " ".join(g) for g in groups], add_special_tokens=False), strict=True):
                ids = np.array(e.ids, self.kind)
                cuts = ((np.flatnonzero(self.ends[ids]) + 1) * ids.itemsize).tolist()
                if len(cuts) != len(group):
                    left += group
                    continue
                packed, at = ids.tobytes(), 0
                for w, stop in zip(group, cuts, strict=True):
                    self.recent[w] = packed[at:stop]
                    at = stop
        return left


_encoders: dict[tuple[str, int, bool], WordEncoder] = {}


def _encoder(path: str, end_id: int, added: bool = True) -> WordEncoder:
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
    if (path, end_id, added) not in _encoders:
        _encoders[path, end_id, added] = WordEncoder(path, end_id, added)
    return _encoders[path, end_id, added]


def slices(batch: pa.RecordBatch, column: int, size: int) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of about ``size`` bytes of a column each, of one row at least."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    lo = 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + size, side="right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


class Ranges:
    """Parts of the corpus in the order of doc_id, a null id first.

    ``cuts`` are ids at equal steps of all rows. An id that is several cuts has as many
    parts, and null ids have ``nulls``: their documents are dealt by a checksum of their ids.
    """

    def __init__(self, cuts: np.ndarray, nulls: int):
        self.cuts, self.nulls = cuts, nulls

    def part(self, doc_id: pa.Array, ids: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(part, checksum) of each document; the checksum is 0 where the id alone decides."""
        null = doc_id.is_null().to_numpy(zero_copy_only=False)
        doc = pc.fill_null(doc_id, 0).to_numpy()
        low, high = (np.searchsorted(self.cuts, doc, side=s) for s in ("left", "right"))
        first, room = np.where(null, 0, self.nulls + high), np.where(null, self.nulls, high - low)
        first = np.where(~null & (room > 1), self.nulls + low + 1, first)
        check = np.zeros(len(doc), np.int64)
        for k in np.flatnonzero(room > 1):
            check[k] = zlib.crc32(ids[int(k)].as_buffer())
        return (first + (check * room >> 32)).astype(np.int32), check


FILES = "file string, part int, number int, n_docs long, n_ids long"


def write_ids(docs: DataFrame, path: str, end_id: int = 2, folder: str | None = None, file_ids: int = FILE_IDS, added: bool = True) -> tuple[str, DataFrame]:
    """Encode (doc_id, text) and write the files; returns their folder and the staged list of files.

    With ``added`` the strings of added tokens in a text are those tokens, the library's
    default; else they are ordinary text.
    """
    spark: SparkSession = docs.sparkSession
    folder = folder or fresh_path(spark, "ids")
    make_folder(spark, folder)
    bits = bits_for(_encoder(path, end_id, added).vocabulary)
    kind = "<u2" if bits <= 16 else "<u4"
    parts = 2 * shuffle_partitions(spark)
    keys = docs.select(F.col("doc_id").cast("long").alias("doc_id"))
    rows, known = keys.agg(F.count("*"), F.count("doc_id")).first()
    cuts = np.array(keys.where("doc_id is not null").approxQuantile("doc_id", [k / parts for k in range(1, parts)], max(0.2 / parts, 1e-5)), np.float64).astype(np.int64)
    ranges = Ranges(cuts, max(1, round(parts * (rows - known) / max(rows, 1))))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = _encoder(path, end_id, added)
        for batch in batches:
            for some in slices(batch, 1, SLICE):
                ids = code.encode(some.column(1))
                part, check = ranges.part(some.column(0), ids)
                yield pa.RecordBatch.from_arrays([pa.array(part), some.column(0), pa.array(check), ids], names=["part", "doc_id", "check", "ids"])
                del ids, part, check, some
            batch = None
            trim()

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = {"part": None, "number": 0, "docs": [], "ids": [], "size": 0}

        def close() -> pa.RecordBatch:
            name = f"ids-{state['part']:06d}-{state['number']:06d}-{TaskContext.get().taskAttemptId()}.bin"
            write_whole(folder, name, encode_file(state["docs"], state["ids"], bits))
            row = [name, state["part"], state["number"], len(state["docs"]), state["size"]]
            state.update(number=state["number"] + 1, docs=[], ids=[], size=0)
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names=["file", "part", "number", "n_docs", "n_ids"])

        for batch in batches:
            for part, doc, data in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if part != state["part"]:
                    if state["docs"]:
                        yield close()
                    state.update(part=part, number=0)
                ids = np.frombuffer(data, kind)
                if state["size"] and state["size"] + len(ids) > file_ids:
                    yield close()
                state["docs"].append(doc)
                state["ids"].append(ids)
                state["size"] += len(ids)
        if state["docs"]:
            yield close()
        trim()

    text = F.make_valid_utf8(F.col("text").cast("string"))
    coded = docs.select(F.col("doc_id").cast("long"), text).mapInArrow(encode, "part int, doc_id long, check long, ids binary")
    dealt = coded.repartition(ranges.nulls + parts, "part").sortWithinPartitions("part", F.col("doc_id").asc_nulls_first(), "check", "ids").select("part", "doc_id", "ids")
    return folder, stage(dealt.mapInArrow(write, FILES), "id-files")


READ = "file string, doc_id long, start_in_file long, n_tokens long, ids_crc32 long"


def read_ids(spark: SparkSession, folder: str, files: DataFrame) -> DataFrame:
    """Per document, from the files: doc_id, start (ids of all documents before it), n_tokens, ids_crc32."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                f = PackedFile(data.as_buffer().to_pybytes())
                flat = f.ids(0, f.total).astype("<u4")
                n = np.diff(f.first)
                crc = [zlib.crc32(flat[a : a + k].tobytes()) for a, k in zip(f.first.tolist(), n.tolist(), strict=False)]
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(n), pa.string()), pa.array(f.doc_ids, pa.int64()), pa.array(f.first[:-1], pa.int64()), pa.array(n, pa.int64()), pa.array(crc, pa.int64())], names=["file", "doc_id", "start_in_file", "n_tokens", "ids_crc32"])
                del f, flat, n, crc
            batch = data = None  # noqa: F841
        trim()

    raw = spark.read.format("binaryFile").option("pathGlobFilter", "ids-*.bin").load(folder)
    name = F.element_at(F.split("path", "/"), -1)
    docs = raw.select(name.alias("file"), F.col("content")).mapInArrow(run, READ)
    # running totals in two levels: the files of a part, and the parts (their number does not depend on the rows)
    before = F.coalesce(F.sum("n_ids").over(Window.partitionBy("part").orderBy("number").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    parts = files.groupBy("part").agg(F.sum("n_ids").alias("n"))
    ahead = parts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("ahead"))
    starts = files.select("file", "part", before.alias("before")).join(F.broadcast(ahead), "part").select("file", (F.col("before") + F.col("ahead")).alias("first"))
    return docs.join(small(stage(starts, "id-starts")), "file").select("doc_id", (F.col("first") + F.col("start_in_file")).alias("start"), "n_tokens", "ids_crc32")

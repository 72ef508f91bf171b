"""Documents to chunks, and chunks to narrow occurrences."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import KINDS, STOPS, WIDE_STOPS, WS, chunks_of, content_hash, normalize_text

CHUNK = "array<struct<text:string,kind:string>>"
_CUT = {
    "line": rf"[{WS}]*\n[{WS}]*",
    "paragraph": rf"[{WS}]*\n[ \t\r\f\x0B]*\n[{WS}]*",
    "sentence": rf"[{STOPS}]+[{WS}]+|[{WIDE_STOPS}]+[{WS}]*",
}
_FENCE = re.compile(r"^ {0,3}(`{3,}|~{3,})(.*)$")


def fence_spans(text: str) -> list[tuple[int, int]]:
    """Closed Markdown fences as (start, end), the line break after the closing fence included."""
    out, at, opened = [], 0, None
    for line in text.splitlines(keepends=True):
        m = _FENCE.match(line.rstrip("\r\n"))
        if opened is None:
            if m and not (m[1][0] == "`" and "`" in m[2]):
                opened = (at, m[1][0], len(m[1]))
        elif m and m[1][0] == opened[1] and len(m[1]) >= opened[2] and not m[2].strip():
            out.append((opened[0], at + len(line)))
            opened = None
        at += len(line)
    return out


def brace_spans(text: str, attach_header: bool = True, max_unit_chars: int | None = None) -> list[tuple[int, int]]:
    """Outermost matched brace pairs; from the start of the opening line if ``attach_header``. Unmatched braces give none."""
    stack, pairs = [], []
    for m in re.finditer(r"[{}]", text):
        if m[0] == "{":
            stack.append(m.start())
        elif stack:
            pairs.append((stack.pop(), m.end()))
    out: list[tuple[int, int]] = []
    for a, b in sorted(pairs):
        if out and a < out[-1][1]:
            continue
        start = max(text.rfind("\n", 0, a) + 1, out[-1][1] if out else 0) if attach_header else a
        if max_unit_chars is None or b - start <= max_unit_chars:
            out.append((start, b))
    return out


def protected_spans(text: str, fences: bool = True, braces: bool = False, max_unit_chars: int | None = None) -> list[tuple[int, int]]:
    """Spans that must not be cut, in order and apart; a brace unit that touches a fence yields to it."""
    out = fence_spans(text) if fences else []
    if braces:
        out += [s for s in brace_spans(text, max_unit_chars=max_unit_chars) if not any(s[0] < b and a < s[1] for a, b in out)]
    return sorted(out)


def cut_with_spans(text: str, spans: list[tuple[int, int]], tau_seg: int, kinds: tuple[str, ...]) -> list[dict]:
    """Chunks of a text whose protected spans stay whole; a chunk that holds any of one is code."""
    which = [_CUT[k] for k in ("paragraph", "line", "sentence") if k in kinds and not (k == "paragraph" and "line" in kinds)]
    cuts = {m.end() for m in re.finditer("|".join(which), text)}
    cuts = sorted({c for c in cuts if not any(a < c < b for a, b in spans)} | {x for s in spans for x in s} | {len(text)})
    out, start, k = [], 0, 0
    for c in cuts:
        if c - start >= max(1, tau_seg) or c == len(text) and c > start:
            while k < len(spans) and spans[k][1] <= start:
                k += 1
            code = k < len(spans) and spans[k][0] < c
            out.append({"text": text[start:c], "kind": "code" if code else "prose"})
            start = c
    return out


def segment(df: DataFrame, text_col: str = "text", tau_seg: int = 32, kinds: tuple[str, ...] = KINDS, protect_code: bool = False, braces: bool = False, max_unit_chars: int | None = None, out: str = "chunks") -> DataFrame:
    """``df`` with a column ``out``: array of (text, kind), in order.

    Prose is cut by one built-in expression. With ``protect_code`` only rows that hold a
    fence or a brace pass through Python; the others keep the built-in path.
    """
    prose = F.transform(chunks_of(F.col(text_col), tau_seg, kinds), lambda c: F.struct(c.alias("text"), F.lit("prose").alias("kind")))
    if not protect_code:
        return df.withColumn(out, prose)

    @F.pandas_udf(CHUNK)
    def with_code(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: None if t is None else cut_with_spans(t, protected_spans(t, True, braces, max_unit_chars), tau_seg, kinds))

    t = F.col(text_col)
    held = t.contains("```") | t.contains("~~~")
    if braces:
        held = held | (t.contains("{") & t.contains("}"))
    coded = df.where(held).withColumn(out, with_code(t))
    return df.where(~held | t.isNull()).withColumn(out, prose).unionByName(coded)


def occurrences(segmented: DataFrame, id_col: str = "doc_id", placeholders: str | None = "single", algo: str = "md5", chunks: str = "chunks", **options) -> DataFrame:
    """Narrow rows (doc_id, pos, h, norm_len, raw_len, kind); the text stays behind.

    The outer explode keeps Catalyst from naming the pattern twice; its null rows go.
    Code is hashed as it is.
    """
    x = segmented.select(F.col(id_col).alias("doc_id"), F.posexplode_outer(chunks).alias("pos", "chunk")).where("pos is not null")
    norm = F.when(F.col("chunk.kind") == "code", F.col("chunk.text")).otherwise(normalize_text(F.col("chunk.text"), placeholders, **options))
    x = x.select("doc_id", "pos", norm.alias("norm"), F.length("chunk.text").alias("raw_len"), (F.col("chunk.kind") == "code").cast("byte").alias("kind"))
    return x.select("doc_id", "pos", content_hash(F.col("norm"), algo).alias("h"), F.length("norm").alias("norm_len"), "raw_len", "kind")


def hexed(df: DataFrame) -> DataFrame:
    """The hash as lower-case hex, for reports."""
    return df.withColumn("h", F.lower(F.hex("h")))


def chunk_rows(segmented: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(doc_id, pos, text) of each chunk."""
    return segmented.select(F.col(id_col).alias("doc_id"), F.posexplode_outer("chunks").alias("pos", "chunk")).where("pos is not null").select("doc_id", "pos", F.col("chunk.text").alias("text"))


def is_code(text: Column) -> Column:
    """A rule score for code-bearing pages: fences, code elements or many braces and semicolons a character."""
    marks = F.length(text) - F.length(F.translate(text, "{};", ""))
    return text.contains("```") | F.lower(text).rlike("<(pre|code|script|style)[ >]") | (marks * 50 > F.length(text))

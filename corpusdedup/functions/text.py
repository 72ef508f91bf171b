"""Cutting, normalising and hashing text with built-in expressions."""

from __future__ import annotations

import unicodedata

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

#: White space as both Java and RE2 read it, and sentence ends.
WS = r" \t\n\r\f\x0B"
STOPS, WIDE_STOPS = ".!?", "。！？"
KINDS = ("paragraph", "line", "sentence")
#: How far back a cut looks over white space for what made it a boundary; a farther look
#: is taken only after a longer run. The last is as far as a pattern of two such runs may reach.
REACH = (32, 1024, 1_000_000_000)

NUMBER = r"[$€£¥]?[0-9]+(?:[.,:/-][0-9]+)*%?"
#: Ordered from the most specific form; the last takes what is left.
TYPED = (
    (r"[0-9]{4}[-/.][0-9]{1,2}[-/.][0-9]{1,2}|[0-9]{1,2}[-/.][0-9]{1,2}[-/.][0-9]{4}", "<DATE>"),
    (r"[$€£¥][0-9]+(?:[.,][0-9]+)*", "<PRICE>"),
    (r"[0-9]+(?:[.,][0-9]+)*%", "<PERCENT>"),
    (NUMBER, "<NUM>"),
)


def boundary_pattern(kinds: tuple[str, ...] = KINDS) -> str:
    """A zero-width Java pattern that holds where a text may be cut.

    A cut lies after a run of white space that holds a line break (two of them for
    paragraphs alone) or follows a sentence end, and after full-width stops. White
    space belongs to the left side; the cheap tests come first.
    """
    if not kinds or set(kinds) - set(KINDS):
        raise ValueError(f"kinds must be some of {KINDS}")

    def after(reach: int) -> str:
        out = []
        if "line" in kinds:
            out.append(rf"(?<=\n[{WS}]{{0,{reach}}})")
        elif "paragraph" in kinds:
            out.append(rf"(?<=\n[ \t\r\f\x0B]{{0,{reach}}}\n[{WS}]{{0,{reach}}})")
        if "sentence" in kinds:
            out.append(rf"(?<=[{STOPS}{WIDE_STOPS}][{WS}]{{1,{reach}}})")
        return "|".join(out)

    farther = [rf"(?<=[{WS}]{{{least + 1}}})(?:{after(reach)})" for least, reach in zip(REACH, REACH[1:])]
    space = rf"(?![{WS}])(?<=[{WS}])(?:{'|'.join([after(REACH[0]), *farther])})"
    return rf"(?:{space}|(?<=[{WIDE_STOPS}])(?![{WIDE_STOPS}{WS}]))" if "sentence" in kinds else space


def chunks_of(text: Column | str, tau_seg: int = 32, kinds: tuple[str, ...] = KINDS) -> Column:
    """The chunks of a text in order; joined they are the text.

    Merging short pieces from left to right ends a chunk at the first boundary that is
    ``tau_seg`` characters or more away, so one lazy pattern cuts and merges at once.
    The rest stays a chunk however short.
    """
    least = max(1, tau_seg)
    return F.regexp_extract_all(text, F.lit(rf"(?s).{{{least},}}?{boundary_pattern(kinds)}|(?s).+"), F.lit(0))


def normalize_text(text: Column, placeholders: str | None = "single", trim_edges: bool = False, lowercase: bool = False, unicode_nfc: bool = False) -> Column:
    """Replace numeric expressions by placeholders; None leaves the text as it is.

    Composing (``unicode_nfc``) comes first; Spark has no function for it, so it is an Arrow UDF.
    """
    if unicode_nfc:
        text = _composed(text)
    if placeholders == "single":
        text = F.regexp_replace(text, NUMBER, "<NUM>")
    elif placeholders == "typed":
        for pattern, mark in TYPED:
            text = F.regexp_replace(text, pattern, mark)
    elif placeholders is not None:
        raise ValueError("placeholders must be single, typed or None")
    if trim_edges:
        text = F.regexp_replace(text, rf"^[{WS}]+|[{WS}]+$", "")
    return F.lower(text) if lowercase else text


def _composed(text: Column) -> Column:
    @F.pandas_udf("string")
    def nfc(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: None if t is None else unicodedata.normalize("NFC", t))

    return nfc(text)


def content_hash(text: Column, algo: str = "md5") -> Column:
    """The key that stands for a normalised text; with ``none`` the text itself."""
    if algo == "md5":
        return F.unhex(F.md5(text))
    if algo == "sha256":
        return F.unhex(F.sha2(text, 256))
    if algo == "xxhash64":
        return F.unhex(F.lpad(F.hex(F.xxhash64(text)), 16, "0"))
    if algo == "xxhash128":
        return F.unhex(F.concat(F.lpad(F.hex(F.xxhash64(text)), 16, "0"), F.lpad(F.hex(F.xxhash64(F.lit("second"), text)), 16, "0")))
    if algo == "none":
        return F.encode(text, "UTF-8")
    raise ValueError(f"unknown hash {algo}")

"""Main text of web pages by template deduction from equivalence classes.

Tokens of a page are its tags and text blocks, each with the path of open elements it
stands under, so that equal tags in different roles are different tokens. Pages of a host
with equal text outside the elements that are set apart are copies and count as one page,
so that copies of an article do not make it a part of the template. Tokens of one
host that have the same occurrence vector (how often each page has them) form an
equivalence class; a vector is compared by an order-free fingerprint, so any number of
pages is counted without gathering them. A class is valid if it is frequent (on enough
of the host's pages) and large (two tokens at least), and if it nests: its tokens lie
below an element of a class that is already part of the template, whose root is the
class of most pages that holds the outermost element. What the template does not fix are
slots. A slot is passed over if an element on its path says that it is not the article
(menus, adverts, forms and so on). Of the others the host's slot is the one with the most
text that the template does not fix, counted on all pages, and decides on every page that
has it; if it lies in an article or main element, all of that element is taken. A page
without it gives its article and main elements if they hold at least half of what the
template leaves of its text, and else all that is left.

Text: character references decoded, white space inside a block as one space, blocks in
page order between empty lines. Pages of hosts with too few pages for a template are
judged by their elements alone. Null or empty html gives an empty text; a null url is a
host of its own. Repeated rows each get a result. A page that would lose all its text to
the template keeps it. Extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import stage
from .files import small

#: Elements of running text; their slot is the element around them.
FLOW = ("p", "li", "h1", "h2", "h3", "h4", "h5", "h6", "blockquote", "pre")
#: A template token is on this many pages of its host at least, and on this share of them.
MIN_PAGES, MIN_SHARE = 5, 0.6

PIECES = re.compile(r"""<!--.*?(?:-->|\Z)|<(script|style|noscript|template|textarea|iframe|svg|title)\b(?:[^>"']|"[^"]*"|'[^']*')*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*')*)>|<[!?][^>]*>|([^<]+|<)""", re.S | re.I)
NAMES = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))|\b(hidden)\b""", re.I)

# fixed values: HTML elements by kind
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
APART = frozenset("nav header footer aside form head menu dialog button select option fieldset input audio video object canvas".split())
ENDS_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "tbody": ("thead", "tbody"), "tfoot": ("tbody",)}
# fixed values: words in class, id and role that mark what is not the article
MARKS = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu breadcrumb breadcrumbs sidebar footer header masthead cookie cookies consent gdpr notice alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended comment comments disqus respond reply replies search widget widgets pagination pager toolbar contentinfo complementary hidden".split())
SPLIT = re.compile(r"[^a-z0-9]+|(?<=[a-z])(?=[A-Z])")


def _labels(attributes: str) -> tuple[str, bool]:
    """Class, id and role as written in a path, and whether they mark an element as not the article."""
    found, apart = [], False
    for m in NAMES.finditer(attributes):
        if m[5]:
            apart = True
            continue
        value = m[2] if m[2] is not None else m[3] if m[3] is not None else m[4] or ""
        found.append(f".{value.strip()}")
        apart = apart or any(w.lower() in MARKS for w in SPLIT.split(re.sub(r"(?<=[a-z])(?=[A-Z])", " ", value)) for w in w.lower().split())
    return "".join(found), apart


class Page:
    """Blocks and tokens of one page."""

    __slots__ = ("tags", "blocks", "has_main")

    def __init__(self, source: str):
        self.tags: list[tuple[str, str]] = []  # (path, tag)
        self.blocks: list[tuple[str, str, bool, bool]] = []  # (path, text, apart, in an article or main element)
        self.has_main = False
        stack: list[tuple[str, str, bool, bool]] = []  # (name, path, apart, main)
        text: list[str] = []
        place = ("", False, False)

        def flush() -> None:
            if text:
                block = " ".join(entities.unescape("".join(text)).split())
                text.clear()
                if block:
                    self.blocks.append((place[0], block, place[1], place[2]))

        def top() -> tuple[str, bool, bool]:
            for name, path, apart, main in reversed(stack):
                if name not in INLINE:
                    return path, apart, main
            return "", False, False

        for m in PIECES.finditer(source):
            if m[5] is not None:
                if not text:
                    if m[5].isspace():
                        continue
                    place = top()
                    place = (place[0], place[1] or (bool(stack) and stack[-1][2]), place[2])
                elif stack and stack[-1][2] and not place[1]:
                    continue  # an inline element that is set apart
                text.append(m[5])
                continue
            if m[1] is not None or m[3] is None:
                continue
            name = m[3].lower()
            if m[2]:
                if any(s[0] == name for s in stack):
                    if name not in INLINE:
                        flush()
                    while stack.pop()[0] != name:
                        pass
                elif name not in INLINE:
                    flush()
                continue
            if name == "br":
                text.append(" ") if text else None
                continue
            labels, apart = _labels(m[4]) if m[4] else ("", False)
            if name not in INLINE:
                flush()
                if name in ENDS_P and any(s[0] == "p" for s in stack):
                    while stack.pop()[0] != "p":
                        pass
                for other in CLOSES.get(name, ()):
                    at = next((k for k in range(len(stack) - 1, -1, -1) if stack[k][0] in (other, "ul", "ol", "dl", "table")), None)
                    if at is not None and stack[at][0] == other:
                        del stack[at:]
            over = stack[-1] if stack else ("", "", False, False)
            main = over[3] or name in ("article", "main")
            # a header inside the article holds its headline
            out = over[2] or (apart or name in APART) and not (name == "header" and over[3])
            path = f"{over[1]}/{name}{labels}"
            self.tags.append((over[1], f"{name}{labels}"))
            self.has_main = self.has_main or main and not out
            if name not in VOID and not m[4].endswith("/"):
                stack.append((name, path, out, main))
        flush()


def token_of(path: str, what: str) -> int:
    return int(np.uint64(xxhash.xxh3_64_intdigest(f"{path}\n{what}")).astype(np.int64))


def slot_of(path: str) -> str:
    """The slot that a block's path belongs to."""
    over, _, last = path.rpartition("/")
    return over if last in FLOW else path


def around(slot: str) -> str:
    """The outermost article or main element that a slot lies in, or the slot itself."""
    m = re.match(r".*?/(?:article|main)(?:\.[^/]*)?(?=/|$)", slot, re.S)
    return m[0] if m else slot


def host_of(url: F.Column | str = "url"):
    """The lower-cased host of a URL, or an empty text."""
    return F.lower(F.regexp_extract(F.coalesce(F.col(url) if isinstance(url, str) else url, F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]*)", 1))


TOKENS = "host string, kind byte, token long, path string, page long, n int, chars long"
KIND_PAGE, KIND_TAG, KIND_TEXT, KIND_SLOT = 0, 1, 2, 3


def page_tokens(pages: DataFrame) -> DataFrame:
    """Each page's distinct tokens with their numbers, its slots with their characters, and the page itself.

    Pages with equal text outside the elements set apart have the same number.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 200):
                some, rows = batch.slice(lo, 200), []
                for host, source in zip(*(some.column(k).to_pylist() for k in range(2)), strict=True):
                    page = Page(source or "")
                    said = "\n\n".join(text for _, text, apart, _ in page.blocks if not apart)
                    own = int(np.uint64(xxhash.xxh3_64_intdigest(said or source or "")).astype(np.int64))
                    rows.append((host, KIND_PAGE, 0, None, own, 1, 0))
                    for (path, tag), n in Counter(page.tags).items():
                        rows.append((host, KIND_TAG, token_of(path, f"<{tag}"), f"{path}/{tag}", own, n, 0))
                    slots: Counter[str] = Counter()
                    inside: Counter[tuple[str, str]] = Counter()
                    for path, text, apart, _ in page.blocks:
                        inside[path, text] += 0 if apart else len(text)
                        if not apart:
                            slots[slot_of(path)] += len(text)
                    for (path, text), n in Counter((b[0], b[1]) for b in page.blocks).items():
                        rows.append((host, KIND_TEXT, token_of(path, text), path, own, n, inside[path, text]))
                    rows += [(host, KIND_SLOT, token_of(path, ""), path, own, 1, n) for path, n in slots.items()]
                kinds = (pa.string(), pa.int8(), pa.int64(), pa.string(), pa.int64(), pa.int32(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=TOKENS.replace(",", "").split()[::2])

    return pages.select(host_of().alias("host"), F.col("html").cast("string")).mapInArrow(run, TOKENS)


def nest(classes: list[tuple[int, list[tuple[int, str, int]]]]) -> set[int]:
    """The tokens of the template: (support, [(token, path, kind)]) classes that hang together from the root down.

    The root is the class of most pages that holds the outermost element. A token nests
    if the element it stands in, or the one around that (itself perhaps repeated, and so
    of another class), is the template's or its own class's; a class joins with those of
    its tokens that nest if they are two or more.
    """
    classes = sorted(classes, key=lambda c: (-c[0], min((len(t[1]) for t in c[1]), default=0)))
    inside: set[str] = {""}
    tokens: set[int] = set()
    for _, members in classes:
        near = inside | {path for _, path, kind in members if kind == KIND_TAG}

        def held(path: str, kind: int, near=near) -> bool:
            over = path if kind == KIND_TEXT else path.rpartition("/")[0]
            return over in near or over.rpartition("/")[0] in near

        own = [m for m in members if held(m[1], m[2])]
        if len(own) > 1:
            inside |= {path for _, path, kind in own if kind == KIND_TAG}
            tokens |= {t for t, _, _ in own}
    return tokens


def deduce_templates(pages: DataFrame, min_pages: int = MIN_PAGES, min_share: float = MIN_SHARE) -> DataFrame:
    """A row for each host: its template's tokens, those of them that are texts, and the slot with the most text.

    A host's tokens that are on most of its pages are no more than a page has, about; only these are gathered.
    """
    once = page_tokens(pages).groupBy("host", "kind", "token", "page").agg(F.max("n").alias("n"), F.max("path").alias("path"), F.max("chars").alias("chars"))
    # xor of a hash of (page, number): equal for tokens with equal occurrence vectors, in any order
    counted = once.groupBy("host", "kind", "token").agg(F.bit_xor(F.xxhash64("page", "n")).alias("vector"), F.count("*").alias("support"), F.min("path").alias("path"), F.sum("chars").alias("chars"))
    found = stage(counted.where(F.col("kind").isin(KIND_PAGE, KIND_SLOT) | (F.col("support") >= min_pages)), "html-tokens")
    sizes = found.where(F.col("kind") == KIND_PAGE).select("host", F.col("support").alias("pages"))
    frequent = found.where(F.col("kind").isin(KIND_TAG, KIND_TEXT)).join(sizes, "host").where(F.col("support") >= min_share * F.col("pages"))
    classes = frequent.groupBy("host", "vector", "support", "pages").agg(F.collect_list(F.struct("token", "path", "kind")).alias("members")).where(F.size("members") > 1)
    by_host = classes.groupBy("host", "pages").agg(F.collect_list(F.struct("support", "members")).alias("classes"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                found = nest([(c["support"], [(m["token"], m["path"], m["kind"]) for m in c["members"]]) for c in r["classes"]])
                texts = [m["token"] for c in r["classes"] for m in c["members"] if m["kind"] == KIND_TEXT and m["token"] in found]
                rows.append((r["host"], sorted(found), sorted(texts)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.list_(pa.int64())), pa.array(cols[2], pa.list_(pa.int64()))], names=["host", "tokens", "texts"])

    nested = by_host.mapInArrow(run, "host string, tokens array<long>, texts array<long>")
    nested = stage(nested, "html-nested")
    fixed = found.where(F.col("kind") == KIND_TEXT).join(nested.select("host", F.explode("texts").alias("token")), ["host", "token"], "left_semi")
    fixed = fixed.select("host", F.regexp_replace("path", f"/({'|'.join(FLOW)})$", "").alias("path"), (-F.col("chars")).alias("chars"))
    free = found.where(F.col("kind") == KIND_SLOT).select("host", "path", "chars").unionByName(fixed).groupBy("host", "path").agg(F.sum("chars").alias("chars"))
    slots = free.groupBy("host").agg(F.max_by("path", F.struct("chars", "path")).alias("slot"))
    return stage(nested.join(slots, "host", "full").select("host", "tokens", "texts", "slot"), "html-templates")


def main_text(source: str | None, texts: frozenset[int] = frozenset(), slot: str | None = None) -> str:
    """The text of a page's article slots; without the template's texts if anything is left then."""
    page = Page(source or "")
    return texts and _slot_text(page, texts, slot) or _slot_text(page, frozenset(), slot)


def _slot_text(page: Page, texts: frozenset[int], slot: str | None) -> str:
    blocks = [(path, text, main) for path, text, apart, main in page.blocks if not apart and not (texts and token_of(path, text) in texts)]
    whole = slot and around(slot)
    chosen = [b for b in blocks if b[0] == whole or b[0].startswith(f"{whole}/")] if whole and any(b[0] == slot or b[0].startswith(f"{slot}/") for b in blocks) else []
    if not chosen:
        inner = [b for b in blocks if b[2]]
        chosen = inner if 2 * sum(len(b[1]) for b in inner) >= sum(len(b[1]) for b in blocks) else blocks
    return "\n\n".join(text for _, text, _ in chosen)


TEXTS = "page_id long, url string, text string, n_chars long"


def extract(pages: DataFrame, min_pages: int = MIN_PAGES, min_share: float = MIN_SHARE) -> DataFrame:
    """Main text of every row of (page_id, url, html)."""
    templates = deduce_templates(pages, min_pages, min_share)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, frozenset[int]] = {}
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                some, out = batch.slice(lo, 500), []
                for host, source, texts, slot in zip(some.column(0).to_pylist(), some.column(3).to_pylist(), some.column(4), some.column(5).to_pylist(), strict=True):
                    if host not in known:
                        known = {} if len(known) > 10_000 else known
                        known[host] = frozenset(texts.as_py() or ())
                    out.append(main_text(source, known[host], slot))
                yield pa.RecordBatch.from_arrays([some.column(1), some.column(2), pa.array(out, pa.string()), pa.array([len(t) for t in out], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pages.select(host_of().alias("host"), F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    joined = rows.join(small(templates.select("host", "texts", "slot")), "host", "left")
    return joined.select("host", "page_id", "url", "html", "texts", "slot").mapInArrow(run, TEXTS)

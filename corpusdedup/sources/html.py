"""Plain text of web pages by built-in expressions; code blocks keep their line breaks."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_STEPS = (
    (r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " "),
    (r"(?s)<!--.*?-->", " "),
    (r"(?i)</?(p|div|br|li|ul|ol|tr|table|h[1-6]|article|section|nav|footer|header|pre|blockquote|body|html|head|title)[^>]*>", "\n"),
    (r"<[^>]*>", ""),
    (r"&nbsp;", " "),
    (r"&lt;", "<"),
    (r"&gt;", ">"),
    (r"&quot;", '"'),
    (r"&#39;", "'"),
    (r"&amp;", "&"),
    (r"[ \t]*\n[ \t\n]*", "\n"),
    (r"^[ \t\n]+|[ \t\n]+$", ""),
)


def html_to_text(html: Column) -> Column:
    for pattern, to in _STEPS:
        html = F.regexp_replace(html, pattern, to)
    return html


def html_to_text_sql(col: str) -> str:
    """The same steps for DuckDB."""
    for pattern, to in _STEPS:
        sql_to = to.replace("'", "''").replace("\n", "' || chr(10) || '")
        col = f"regexp_replace({col}, '{pattern.replace(chr(39), chr(39) * 2)}', '{sql_to}', 'g')"
    return col

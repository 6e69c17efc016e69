"""Text statistics in built-in functions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The same words in Java's and RE2's regexes.
WORD = r"[^ \t\n\r\f]+"


def n_tokens(text: str | Column) -> Column:
    return F.size(F.regexp_extract_all(F.col(text) if isinstance(text, str) else text, F.lit(WORD), F.lit(0))).cast("long")


def words(text: str | Column) -> Column:
    return F.regexp_extract_all(F.col(text) if isinstance(text, str) else text, F.lit(WORD), F.lit(0))


def strip_html(html: str | Column) -> Column:
    """Visible text of a page: no scripts, styles, tags or common entities."""
    out = F.col(html) if isinstance(html, str) else html
    for pattern, put in ((r"(?is)<(script|style)\b.*?</\1>", " "), (r"(?s)<!--.*?-->", " "), (r"<[^>]+>", " "), ("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&"), (r"[ \t]+", " ")):
        out = F.regexp_replace(out, pattern, put)
    return F.trim(out)

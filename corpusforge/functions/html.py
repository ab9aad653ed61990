"""Text of HTML pages, and the clues to their language."""

from __future__ import annotations

from html.entities import name2codepoint

from pyspark.sql import Column
from pyspark.sql import functions as F

from corpusforge.functions.text import bound, col

#: Elements whose content is no text, elements that end a line, named entities.
DROPPED = r"(?is)<!--.*?-->|<(head|script|style|nav|footer|noscript)\b.*?</\1\s*>"
BLOCKS = r"(?i)</?(?:p|div|li|tr|h[1-6]|ul|ol|table|br|section|article|blockquote|pre)\b[^>]*>"
ENTITIES = (
    ("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"),
    *((f"&{name};", chr(code)) for name, code in sorted(name2codepoint.items()) if 160 < code < 256), ("&amp;", "&"),
)


def _decoded(t: Column) -> Column:
    for name, ch in ENTITIES:
        t = F.replace(t, F.lit(name), F.lit(ch))
    return t


def strip_tags(html: Column | str) -> Column:
    """Text lines of a page: without scripts and navigation, tags or superfluous blanks."""
    t = col(html)
    for tag in ("head", "script", "style", "nav", "footer"):
        t = F.regexp_replace(t, rf"(?is)<{tag}\b.*?</{tag}\s*>", "")
    t = F.regexp_replace(t, r"(?s)<!--.*?-->", "")
    t = F.regexp_replace(F.regexp_replace(t, BLOCKS, "\n"), r"(?s)<[^>]*>", "")
    t = bound(t, lambda x: F.when(x.contains("&"), _decoded(x)).otherwise(x))
    t = F.regexp_replace(F.regexp_replace(t, r"[ \t\r]+", " "), r" ?\n ?", "\n")
    return F.regexp_replace(F.regexp_replace(t, r"\n+", "\n"), r"^[ \n]+|[ \n]+$", "")


def host(url: Column | str) -> Column:
    return F.lower(F.regexp_extract(col(url), r"^[a-zA-Z]+://([^/:?#]+)", 1))


def html_lang(html: Column | str) -> Column:
    return F.regexp_extract(col(html), r"(?i)<html[^>]*\blang=[\"']?([a-zA-Z]{2,3})", 1)


def url_lang(url: Column | str) -> Column:
    return F.regexp_extract(col(url), r"^[a-zA-Z]+://[^/]+/([a-z]{2,3})/", 1)

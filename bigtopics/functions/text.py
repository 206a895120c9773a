"""Text expressions used by corpora and features."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD_BREAK = r"[^\p{L}]+"


def words(text: Column, pattern: str = WORD_BREAK, lower: bool = True) -> Column:
    """Array of the words of a text, in order, without empty ones."""
    t = F.coalesce(text, F.lit(""))
    return F.filter(F.split(F.lower(t) if lower else t, pattern), lambda w: w != "")


def strip_tags(html: Column) -> Column:
    """Text of a page: scripts, styles and tags replaced by a space."""
    bare = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.regexp_replace(bare, r"<[^>]*>", " ")

"""Terms of messages, as Columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def tokens(text: Column | str, least: int = 3) -> Column:
    """Lower-case runs of ASCII or Latin letters of at least `least`, in order."""
    return F.regexp_extract_all(F.lower(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))), F.lit(r"[a-zà-öø-ÿ]{%d,}" % least), F.lit(0))


def distinct_terms(text: Column | str, least: int = 3, stop: tuple[str, ...] = ()) -> Column:
    words = F.array_distinct(tokens(text, least))
    return F.array_except(words, F.array(*map(F.lit, stop))) if stop else words


def bigrams(words: Column) -> Column:
    """Pairs of neighbouring tokens, joined by a space."""
    return F.zip_with(F.slice(words, 1, F.greatest(F.size(words) - 1, F.lit(0))), F.slice(words, 2, F.greatest(F.size(words) - 1, F.lit(0))), lambda a, b: F.concat_ws(" ", a, b))


def strip_markup(html: Column | str) -> Column:
    """Text of a page without scripts, styles and tags."""
    body = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>", " ")
    return F.regexp_replace(body, r"(?s)<[^>]*>", " ")

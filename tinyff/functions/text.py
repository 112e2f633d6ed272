"""Text columns: characters, n-grams, sentences, tokens, windows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"[\p{L}]+|[0-9]+|[^\s\p{L}0-9]"


def bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once: an expression inside a lambda would be computed for every element."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def chars(text: Column) -> Column:
    """Code points of a text; none of a null or empty one."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), ""), lambda c: c != "")


def char_ngrams(text: Column, n: int, pad: str | None = None, lower: bool = True) -> Column:
    """All character n-grams in order, inside the row: length - n + 1 of them, or none."""
    text = F.lower(text) if lower else text
    c = chars(F.concat(F.lit((pad or "") * (n - 1)), text, F.lit((pad or "") * (n - 1))) if pad else text)
    none = F.array().cast("array<string>")
    return bound(c, lambda c: F.when(F.size(c) >= n, F.transform(F.sequence(F.lit(0), F.size(c) - n), lambda i: F.concat(*[F.get(c, i + k) for k in range(n)]))).otherwise(none))


def char_windows(text: Column, n: int) -> Column:
    """The lower-cased text's n characters from each place on, in order; the last ones are shorter. One match a place, without a lambda."""
    return F.regexp_extract_all(F.coalesce(F.lower(text), F.lit("")), F.lit(rf"(?s)(?=(.{{1,{n}}}))."), F.lit(1))


def sentences(text: Column) -> Column:
    """Parts between line breaks and after sentence ends; blank ones dropped."""
    parts = F.split(F.regexp_replace(F.coalesce(text, F.lit("")), r"\. ", ".\n"), "\n")
    return F.filter(parts, lambda s: F.length(F.trim(s)) > 0)


def tokens(sentence: Column) -> Column:
    """Words, numbers and single other characters."""
    return F.regexp_extract_all(sentence, F.lit(TOKEN), F.lit(0))


def normalise(text: Column) -> Column:
    """Preprocessing hook: drops junk runs, tags and links, and collapses blanks."""
    text = F.regexp_replace(text, r"<[^>]*>", " ")
    text = F.regexp_replace(text, r"https?://[^ ]+", " ")
    text = F.regexp_replace(text, r"[#$%&*|!]+", " ")
    return F.trim(F.regexp_replace(text, r"[ \t\n]+", " "))


def visible_text(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags removed, blanks collapsed."""
    text = F.regexp_replace(html, r"(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ")
    text = F.regexp_replace(text, r"<[^>]*>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(text, r"&[a-z]+;", " "), r"[ \t\n\r]+", " "))

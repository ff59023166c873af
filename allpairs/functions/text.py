"""Elements of texts: words, n-grams, lines, URL parts, tags."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = "[A-Za-z0-9]+"


def words(text: Column) -> Column:
    """ASCII words, each lower-cased after it is found, so that no Unicode case rule matters."""
    return F.transform(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), F.lower)


def ngrams(tokens: Column, n: int) -> Column:
    """Windows of n tokens joined by a blank; shifted copies are zipped, so tokens are made once and not for each window."""
    size = F.size(tokens)
    shifted = F.arrays_zip(*(F.slice(tokens, F.lit(k + 1), F.greatest(size - k, F.lit(0))).alias(f"t{k}") for k in range(n)))
    whole = F.filter(shifted, lambda x: x[f"t{n - 1}"].isNotNull())
    return F.transform(whole, lambda x: F.concat_ws(" ", *(x[f"t{k}"] for k in range(n))))


def character_shingles(text: Column, n: int) -> Column:
    count = F.length(text) - (n - 1)
    return F.when(count > 0, F.transform(F.sequence(F.lit(1), F.greatest(count, F.lit(1))), lambda k: F.substring(text, k, F.lit(n)))).otherwise(F.array().cast("array<string>"))


def lines(text: Column) -> Column:
    return F.filter(F.transform(F.split(text, "\n"), F.trim), lambda x: x != "")


def without_tags(html: Column) -> Column:
    return F.regexp_replace(html, "<[^>]*>", " ")


def url_host(url: Column) -> Column:
    return F.parse_url(url, F.lit("HOST"))


def url_path(url: Column) -> Column:
    return F.parse_url(url, F.lit("PATH"))

"""Tokens, counts and repeatable samples as column expressions; DuckDB gives the same values."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"
JUNK = r"(!!|\*\*\*|###)"


def tokens(text: Column) -> Column:
    """Runs of letters and digits, lower-cased; none for null."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(TOKEN), F.lit(0))


def count_tokens(text: Column, method: str = "words") -> Column:
    """words: runs of letters and digits; chars: a quarter of the characters, rounded up; space: white-space words."""
    text = F.coalesce(text, F.lit(""))
    if method == "words":
        return F.size(tokens(text)).cast("long")
    if method == "chars":
        return F.ceil(F.length(text) / 4).cast("long")
    if method == "space":
        return F.size(F.regexp_extract_all(text, F.lit(r"\S+"), F.lit(0))).cast("long")
    raise ValueError(f"unknown method {method!r}")


def order_hash(key: Column, seed: int) -> Column:
    """A repeatable shuffle: sort by this, then by the key."""
    return F.md5(F.concat(key.cast("string"), F.lit(f"|{seed}")))


def in_sample(key: Column, share: float, seed: int) -> Column:
    """A repeatable uniform sample: the first four hex digits of the hash are below the share of 65,536."""
    cut = round(share * 65536)
    return F.lit(True) if cut >= 65536 else F.substring(order_hash(key, seed), 1, 4) < f"{cut:04x}"


def truncate(words: Column, limit: int) -> Column:
    return F.slice(words, 1, limit)


def chunks(words: Column, limit: int) -> Column:
    """Consecutive stretches of at most ``limit`` words; an empty text has one, empty."""
    starts = F.sequence(F.lit(0), F.greatest(F.ceil(F.size(words) / limit).cast("int") - 1, F.lit(0)))
    return F.transform(starts, lambda k: F.slice(words, k * limit + 1, limit))


def head_tail(words: Column, limit: int) -> Column:
    """The first and the last half of what fits."""
    half = limit // 2
    return F.when(F.size(words) <= limit, words).otherwise(F.concat(F.slice(words, 1, limit - half), F.slice(words, -half, half)))


def strip(text: Column) -> Column:
    """Without white space at its ends; trim alone takes only spaces."""
    return F.trim(text, F.lit(" \n\r\t"))


def tagged(text: Column, tag: str) -> Column:
    """What stands in <tag> … </tag>, any case, trimmed; null without the tag."""
    held = F.regexp_extract(text, rf"(?is)<{tag}>(.*?)</{tag}>", 1)
    return F.when(F.regexp_like(text, F.lit(rf"(?is)<{tag}>.*?</{tag}>")), strip(held))


#: SQL functions that ``register_macros`` makes; they run as expressions
MACROS = {
    "count_tokens": "(t STRING) RETURNS BIGINT RETURN size(regexp_extract_all(lower(coalesce(t, '')), '[\\\\p{L}\\\\p{N}]+', 0))",
    "jaccard": "(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN size(array_intersect(a, b)) / size(array_union(a, b))",
    "cosine": "(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> double(x) * double(y)), 0D, (s, x) -> s + x)",
    "parse_choice": "(o STRING) RETURNS STRING RETURN nullif(upper(coalesce(nullif(regexp_extract(o, '(?i)answer\\\\W{0,3}\\\\(?([A-D])\\\\b', 1), ''), regexp_extract(o, '\\\\b([A-D])\\\\b', 1))), '')",
}


def register_macros(spark) -> None:
    for name, body in MACROS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")

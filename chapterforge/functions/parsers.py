"""Parsers of model outputs, each with the route by which the answer was found: tag, fallback or none."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .text import strip, tagged


def _filled(c: Column) -> Column:
    return F.when(F.length(c) > 0, c)


def parse_choice(output: Column) -> tuple[Column, Column]:
    """The letter after the answer marker, with or without brackets; else the first that stands alone."""
    marked = _filled(F.upper(F.regexp_extract(output, r"(?i)answer\W{0,3}([a-d])(?:\W|$)", 1)))
    alone = _filled(F.regexp_extract(output, r"(?:^|[^A-Za-z0-9])([A-D])(?:[^A-Za-z0-9]|$)", 1))
    return F.coalesce(marked, alone), F.when(marked.isNotNull(), "tag").when(alone.isNotNull(), "fallback").otherwise("none")


def _names(text: Column, separator: str) -> Column:
    return F.array_sort(F.array_distinct(F.filter(F.transform(F.split(text, separator), lambda x: strip(x)), lambda x: x != "")))


def parse_tables(output: Column, tag: str = "tables", fallback: str | None = "lines") -> tuple[Column, Column]:
    """A set of names as a sorted array: in the tag by line or comma; without it each line is a name."""
    inside = tagged(output, tag)
    found = F.when(inside.isNotNull(), _names(inside, r"[\n,]"))
    none = F.array().cast("array<string>")
    if fallback != "lines":
        return F.coalesce(found, none), F.when(found.isNotNull(), "tag").otherwise("none")
    lines = _names(F.coalesce(output, F.lit("")), r"\n")
    return F.coalesce(found, lines, none), F.when(found.isNotNull(), "tag").when(F.size(lines) > 0, "fallback").otherwise("none")


def parse_sql(output: Column, tag: str = "sql") -> tuple[Column, Column]:
    """In the tag, else in a fenced block."""
    inside = tagged(output, tag)
    fenced = _filled(strip(F.regexp_extract(output, r"(?is)```(?:sql)?\s*(.*?)```", 1)))
    return F.coalesce(inside, fenced), F.when(inside.isNotNull(), "tag").when(fenced.isNotNull(), "fallback").otherwise("none")


def parse_row_text(output: Column, tag: str = "description") -> Column:
    return tagged(output, tag)

"""Whole pages: HTML to text, tables to markdown, names by section; questions over several tables; records in order."""

from __future__ import annotations

from collections.abc import Iterator
from html.parser import HTMLParser

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: (pattern, replacement), in order; patterns that both engines read alike
TEXT_STEPS = (
    (r"(?is)<(script|style|nav|footer)[^>]*>.*?</(script|style|nav|footer)>", " "), (r"(?s)<!--.*?-->", " "), (r"(?s)<[^>]*>", " "),
    (r"&nbsp;", " "), (r"&lt;", "<"), (r"&gt;", ">"), (r"&quot;", '"'), (r"&#39;", "'"), (r"&amp;", "&"), (r"\s+", " "),
)


def page_text(html: Column) -> Column:
    """Readable text: scripts, styles, navigation, comments and tags out, common entities resolved, white space joined."""
    out = F.coalesce(html, F.lit(""))
    for pattern, to in TEXT_STEPS:
        out = F.regexp_replace(out, F.lit(pattern), F.lit(to))
    return F.trim(out)


class _Tables(HTMLParser):
    """Tables with their section titles; a table within a cell is flattened into its text; images, links and styles leave only text."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.section, self.found, self.depth, self.rows, self.row, self.cell, self.title = "", [], 0, [], None, None, None

    def _end_cell(self):
        if self.cell is not None and self.row is not None:
            self.row.append(" ".join("".join(self.cell).split()))
        self.cell = None

    def _end_row(self):
        self._end_cell()
        if self.row:
            self.rows.append(self.row)
        self.row = None

    def handle_starttag(self, tag, attrs):
        if tag == "table":
            self.depth += 1
            if self.depth == 1:
                self.rows = []
        elif self.depth == 1 and tag == "tr":
            self._end_row()
            self.row = []
        elif self.depth == 1 and tag in ("td", "th"):
            self._end_cell()
            self.row, self.cell = self.row if self.row is not None else [], []
        elif self.depth > 1 and tag in ("td", "th", "tr") and self.cell is not None:
            self.cell.append(" ")
        elif tag in ("h1", "h2", "h3") and not self.depth:
            self.title = []

    def handle_endtag(self, tag):
        if tag == "table" and self.depth:
            self.depth -= 1
            if not self.depth:
                self._end_row()
                self.found.append((self.section, self.rows))
        elif self.depth == 1 and tag == "tr":
            self._end_row()
        elif self.depth == 1 and tag in ("td", "th"):
            self._end_cell()
        elif tag in ("h1", "h2", "h3") and self.title is not None:
            self.section, self.title = " ".join("".join(self.title).split()), None

    def handle_data(self, data):
        if self.cell is not None:
            self.cell.append(data)
        elif self.title is not None:
            self.title.append(data)


def markdown(rows: list[list[str]]) -> str:
    if not rows:
        return ""
    wide = max(map(len, rows))
    lines = ["| " + " | ".join([c.replace("|", "/") for c in r] + [""] * (wide - len(r))) + " |" for r in rows]
    return "\n".join([lines[0], "|" + " --- |" * wide, *lines[1:]])


def page_tables(pages: DataFrame) -> DataFrame:
    """page_id, ordinal, section, markdown, n_rows (without the header), n_cols, for every table of a page. Unclosed tags and empty
    tables are allowed."""

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = []
            for page_id, html in zip(pdf["page_id"], pdf["html"]):
                parser = _Tables()
                parser.feed(html or "")
                parser.close()
                out += [(page_id, i, s, markdown(r), max(len(r) - 1, 0), max(map(len, r), default=0)) for i, (s, r) in enumerate(parser.found)]
            yield pd.DataFrame(out, columns=["page_id", "ordinal", "section", "markdown", "n_rows", "n_cols"])

    return pages.select("page_id", "html").mapInPandas(read, "page_id long, ordinal int, section string, markdown string, n_rows int, n_cols int")


def name_tables(tables: DataFrame) -> DataFrame:
    """Section title and a running number in its section."""
    nth = F.row_number().over(W.partitionBy("page_id", "section").orderBy("ordinal"))
    return tables.withColumn("table_name", F.concat_ws("_", F.regexp_replace("section", r"\s+", "_"), nth))


def selection_from_page(questions: DataFrame, tables: DataFrame, texts: DataFrame) -> DataFrame:
    """questions: q_id, page_id, question, gold; tables: named; texts: page_id, text. Whole pages as data."""
    shown = F.concat_ws("\n", "table_name", "markdown")
    by_page = tables.groupBy("page_id").agg(
        F.array_sort(F.collect_list("table_name")).alias("candidates"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", shown.alias("x")))), lambda s: s["x"]), "\n\n").alias("tables")
    )
    from .selection import assemble

    out = questions.join(by_page, "page_id").join(texts, "page_id").withColumn("data", F.concat_ws("\n\n", "text", "tables"))
    return out.withColumn("prompt", assemble(F.col("data"), F.col("question"))).drop("text", "tables")


def record_moves(rows: DataFrame, group: str, order: list[str], value: str, lower_is_better: bool = False, start: Column | None = None) -> DataFrame:
    """For each group: how many values in order equal or better the record as it stood before them. The first value sets the record,
    unless ``start`` gives one."""
    before = W.partitionBy(group).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    best = F.min(value).over(before) if lower_is_better else F.max(value).over(before)
    if start is not None:
        best = (F.least if lower_is_better else F.greatest)(best, start)
    meets = F.col(value) <= F.col("best") if lower_is_better else F.col(value) >= F.col("best")
    return rows.withColumn("best", best).groupBy(group).agg(F.count_if(F.col("best").isNotNull() & meets).alias("matches_or_beats"), F.count("*").alias("n"))

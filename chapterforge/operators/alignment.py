"""Table-text alignment: schemas from scenarios, rows as text, entailment by rule, table-level filtering; catalogs."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# ---- catalog ----------------------------------------------------------------------------------------------

#: table -> its declared keys: primary key, then (column, table, column) links
SALES_KEYS = {
    "region": ("r_regionkey", ()), "nation": ("n_nationkey", (("n_regionkey", "region", "r_regionkey"),)),
    "customer": ("c_custkey", (("c_nationkey", "nation", "n_nationkey"),)), "supplier": ("s_suppkey", (("s_nationkey", "nation", "n_nationkey"),)),
    "part": ("p_partkey", ()), "orders": ("o_orderkey", (("o_custkey", "customer", "c_custkey"),)),
    "lineitem": (None, (("l_orderkey", "orders", "o_orderkey"), ("l_partkey", "part", "p_partkey"), ("l_suppkey", "supplier", "s_suppkey"))),
}
CORPUS_KEYS = {
    "events": ("event_id", ()), "documents": ("doc_id", ()), "embeddings": ("vec_id", ()), "pages": ("page_id", ()), "benchmark": ("item_id", ()),
    "labels": ("doc_id", (("doc_id", "documents", "doc_id"),)), "conversations": (None, ()),
}


def catalog_of(spark: SparkSession, db: str, tables: dict[str, DataFrame], keys: dict) -> DataFrame:
    """Schema rows from metadata alone; no file is read."""
    rows = []
    for name, df in sorted(tables.items()):
        pk, links = keys.get(name, (None, ()))
        to = {c: (t, k) for c, t, k in links}
        rows += [(db, name, i, f.name, f.dataType.simpleString(), f.name == pk, *to.get(f.name, (None, None))) for i, f in enumerate(df.schema.fields)]
    return spark.createDataFrame(rows, "db string, table string, ordinal int, column string, type string, is_pk boolean, fk_table string, fk_column string")


def filter_schemas(catalog: DataFrame) -> DataFrame:
    """Databases with two tables or more, a key link, three columns for each table and descriptive names."""
    return (
        catalog.groupBy("db")
        .agg(F.count_distinct("table").alias("tables"), F.count("fk_table").alias("links"), F.count("*").alias("columns"), F.min(F.length("column")).alias("shortest"))
        .filter("tables >= 2 and links >= 1 and columns >= 3 * tables and shortest >= 2")
    )


def discover_keys(spark: SparkSession, tables: dict[str, DataFrame]) -> DataFrame:
    """Links by inclusion: (table, column) whose distinct values all occur in another table's unique column. Sketches of the number of
    distinct values rule pairs out before any join."""
    sizes = {}
    for name, df in tables.items():
        whole = [f.name for f in df.schema.fields if f.dataType.simpleString() in ("int", "bigint")]
        row = df.agg(F.count("*").alias("n"), *[F.approx_count_distinct(c, 0.02).alias(c) for c in whole]).first()
        sizes |= {(name, c): (row[c], row["n"]) for c in whole}
    found = []
    for (t, c), (d, n) in sizes.items():
        for (u, k), (e, m) in sizes.items():
            if t != u and e >= 0.9 * m and d <= 1.1 * e and c.split("_")[-1] == k.split("_")[-1]:
                if tables[u].groupBy(k).count().filter("count > 1").isEmpty() and tables[t].filter(F.col(c).isNotNull()).select(c).join(tables[u].select(F.col(k).alias(c)), c, "left_anti").isEmpty():
                    found.append((t, c, u, k))
    return spark.createDataFrame(found, "table string, column string, to_table string, to_column string")


def table_relations(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """How two tables stand to each other: shared columns; keys in one or both; rows on shared keys that agree or differ."""
    shared = [c for c in a.columns if c in b.columns and c not in keys]
    x, y = a.select(*keys, F.struct(*shared).alias("x")), b.select(*keys, F.struct(*shared).alias("y"))
    both = x.join(y, keys, "full")
    return both.agg(
        F.lit(len(shared)).alias("shared_columns"), F.count_if(F.col("y").isNull()).alias("only_a"), F.count_if(F.col("x").isNull()).alias("only_b"),
        F.count_if(F.col("x") == F.col("y")).alias("equal"), F.count_if(F.col("x") != F.col("y")).alias("different"),
    )


def sub_schemas(keys: dict) -> list[tuple[str, list[str]]]:
    """All connected sets of two tables or more of a key graph."""
    near = {t: set() for t in keys}
    for t, (_, links) in keys.items():
        for _, u, _ in links:
            near[t].add(u)
            near[u].add(t)
    out = []
    for n in range(2, len(keys) + 1):
        for some in combinations(sorted(keys), n):
            seen, todo = {some[0]}, [some[0]]
            while todo:
                todo += [u for u in near[todo.pop()] if u in some and u not in seen and not seen.add(u)]
            if len(seen) == n:
                out.append(("+".join(some), list(some)))
    return out


def draft_scenarios(schemas: DataFrame, n: int = 3, company: Column | None = None) -> DataFrame:
    """schema_id, tables -> n drafts each: all tables named; all but the last; none. company: whose database it is, as a column."""
    company = F.lit("A company") if company is None else company
    named = F.array_join("tables", ", ")
    fewer = F.array_join(F.slice("tables", 1, F.size("tables") - 1), ", ")
    d = F.col("draft_no")
    text = F.when(d == 1, F.concat(company, F.lit(" keeps records of "), named, F.lit(" and wants a database to report on them."))).when(
        d == 2, F.concat(F.lit("An analyst follows "), fewer, F.lit(" and needs to store what happens over time."))
    ).otherwise(F.concat(company, F.lit(" wants a database.")))
    return schemas.select("*", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("draft_no")).withColumn("text", text)


def judge_scenarios(drafts: DataFrame, above: int = 4) -> DataFrame:
    """1 to 5: one point for 30 to 300 characters, one for half of the tables named, two for all. Kept strictly above 4."""
    share = F.size(F.filter("tables", lambda t: F.contains(F.col("text"), t))) / F.size("tables")
    score = 1 + F.length("text").between(30, 300).cast("int") + (share >= 0.5).cast("int") + 2 * (share >= 1).cast("int")
    return drafts.withColumn("score", score).withColumn("kept", F.col("score") > above)


def schema_design_examples(kept: DataFrame, catalog: DataFrame) -> DataFrame:
    """Scenario in, schema out: query and output of the uniform example."""
    line = F.concat(F.lit("CREATE TABLE "), F.col("table"), F.lit(" ("), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", F.concat_ws(" ", "column", "type").alias("c")))), lambda s: s["c"]), ", "), F.lit(");"))
    ddl = F.broadcast(catalog.groupBy("table").agg(line.alias("ddl")))  # a row a table of one database
    each = kept.withColumn("table", F.explode("tables")).join(ddl, "table")
    return each.groupBy("schema_id", "draft_no", F.col("text").alias("query")).agg(F.array_join(F.array_sort(F.collect_list("ddl")), "\n").alias("output"))


def acceptance_report(drafts: DataFrame) -> DataFrame:
    return drafts.agg(F.count("*").alias("drafts"), F.count_if("kept").alias("kept"), (F.count_if("kept") / F.count("*")).alias("share"))


# ---- rows as text -----------------------------------------------------------------------------------------


def render_row_prompt(rows: DataFrame, with_context: bool = True) -> DataFrame:
    """rows: table_id, row_no, page_title, section_title, caption, header, cells (a map). One row a prompt."""
    head = F.array_join("header", " | ")
    line = F.array_join(F.transform("header", lambda h: F.element_at("cells", h)), " | ")
    context = [F.concat(F.lit("Page: "), "page_title"), F.concat(F.lit("Section: "), "section_title"), F.concat(F.lit("Caption: "), "caption")] if with_context else []
    return rows.withColumn("prompt", F.concat_ws("\n", F.lit("Describe the row in one sentence, between <description> and </description>."), *context, head, line))


def describe_rows(rows: DataFrame, wrong: Column | None = None) -> DataFrame:
    """A sentence that says every cell, in its tag; where ``wrong`` holds, its last number is off by one (planted errors)."""
    last = F.element_at("cells", F.element_at("header", -1))
    value = F.when(wrong, (last.cast("long") + 1).cast("string")).otherwise(last) if wrong is not None else last
    said = F.transform(F.slice("header", 1, F.size("header") - 1), lambda h: F.concat(h, F.lit(" "), F.element_at("cells", h)))
    body = F.concat(F.array_join(said, ", "), F.lit(", "), F.element_at("header", -1), F.lit(" "), value)
    return rows.withColumn("response", F.concat(F.lit("<description>"), body, F.lit("</description>")))


NUMBER_WORDS = ("zero", "one", "two", "three", "four", "five", "six", "seven", "eight", "nine", "ten")
ORDINALS = ("zeroth", "first", "second", "third", "fourth", "fifth", "sixth", "seventh", "eighth", "ninth", "tenth")


def entail(described: DataFrame) -> DataFrame:
    """verdict: contradicted if the text has a number that no cell has; entailed if it has every cell (numbers up to ten may be
    words); else neutral. described: cells, text."""
    numbers = lambda c: F.regexp_extract_all(c, F.lit(r"\d+(?:\.\d+)?"), F.lit(0))
    values, low = F.map_values("cells"), F.lower("text")
    odd = F.size(F.array_except(numbers(F.col("text")), numbers(F.array_join(values, " ")))) > 0
    word = lambda names, v: F.get(F.array(*map(F.lit, names)), F.when(v.rlike("^([0-9]|10)$"), v.cast("int")))
    says = lambda v: F.contains(low, F.lower(v)) | F.coalesce(F.contains(low, word(NUMBER_WORDS, v)), F.lit(False)) | F.coalesce(F.contains(low, word(ORDINALS, v)), F.lit(False))
    return described.withColumn("verdict", F.when(odd, "contradicted").when(F.forall(values, says), "entailed").otherwise("neutral"))


def keep_consistent_tables(verdicts: DataFrame, level: str = "table") -> DataFrame:
    """Rows of tables without any contradicted row; with level row, all rows but those."""
    if level == "row":
        return verdicts.filter("verdict <> 'contradicted'")
    good = verdicts.groupBy("table_id").agg(F.bool_and(F.col("verdict") != "contradicted").alias("ok")).filter("ok").select("table_id")
    return verdicts.join(good, "table_id", "left_semi")

"""Table-selection examples: candidates from one schema, from retrieval, or from a page; gold tables from gold SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import count_tokens, order_hash


def gold_tables_regex(sql_items: DataFrame) -> DataFrame:
    """q_id, gold: names after FROM and JOIN, without those that a WITH clause defines. For any number of strings."""
    text = F.lower("gold_sql")
    named = F.regexp_extract_all(text, F.lit(r"\b(?:from|join)\s+([a-z_][a-z0-9_]*)"), F.lit(1))
    defined = F.regexp_extract_all(text, F.lit(r"(?:\bwith|,)\s*([a-z_][a-z0-9_]*)\s+as\s*\("), F.lit(1))
    return sql_items.select("q_id", F.array_sort(F.array_distinct(F.array_except(named, defined))).alias("gold"))


def gold_tables_parsed(spark: SparkSession, sql: str) -> list[str]:
    """From the parsed plan, subqueries included; names of its own WITH clauses are left out."""
    import re

    plan = spark._jsparkSession.sessionState().sqlParser().parsePlan(sql).toString()
    found = {m.lower() for m in re.findall(r"UnresolvedRelation \[([A-Za-z0-9_]+)\]", plan)}
    own = {m.lower() for m in re.findall(r"(?i)(?:\bwith|,)\s*([a-z_][a-z0-9_]*)\s+as\s*\(", sql)}
    return sorted(found - own)


def sample_rows(rows: DataFrame, n: int = 3, seed: int = 0, table: str = "table_id", key: str = "row_key") -> DataFrame:
    """At most n rows of each table, the same each time."""
    nth = F.row_number().over(W.partitionBy(table).orderBy(order_hash(F.col(key), seed), key))
    return rows.withColumn("nth", nth).filter(F.col("nth") <= n)


def schemas(catalog: DataFrame) -> DataFrame:
    """db, candidates (its tables), data (a line for each table with its columns and types)."""
    line = F.concat(F.col("table"), F.lit("("), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", F.concat_ws(" ", "column", "type").alias("c")))), lambda s: s["c"]), ", "), F.lit(")"))
    ddl = catalog.groupBy("db", "table").agg(line.alias("ddl"))
    return ddl.groupBy("db").agg(F.array_sort(F.collect_list("table")).alias("candidates"), F.array_join(F.array_sort(F.collect_list("ddl")), "\n").alias("data"))


def selection_from_schema(questions: DataFrame, catalog: DataFrame) -> DataFrame:
    """questions: q_id, db, question, gold. All tables of the database are candidates, by schema alone."""
    by_db = schemas(catalog)
    out = questions.join(F.broadcast(by_db), "db")
    return out.withColumn("prompt", assemble(F.col("data"), F.col("question")))


INSTRUCTION = "Name the tables that are needed to answer the question, one on a line, between <tables> and </tables>."


def assemble(data, question, instruction: str = INSTRUCTION, order=("data", "instruction", "question")):
    parts = {"data": data, "instruction": F.lit(instruction), "question": F.concat(F.lit("Question: "), question)}
    return F.concat_ws("\n", *[parts[p] for p in order])


SQL_INSTRUCTION = "Write one SQL query that answers the question, between <sql> and </sql>."


def sql_examples(questions: DataFrame, catalog: DataFrame, knowledge: bool = True) -> DataFrame:
    """questions: q_id, db, question, hint (null if there is none). Schema, instruction, with ``knowledge`` the hint, question;
    no cell values."""
    out = questions.join(F.broadcast(schemas(catalog)), "db")
    hint = F.concat(F.lit("Knowledge: "), "hint") if knowledge else F.lit(None).cast("string")
    return out.withColumn("prompt", F.concat_ws("\n", "data", F.lit(SQL_INSTRUCTION), hint, F.concat(F.lit("Question: "), "question")))


def with_gold_policy(ranks: DataFrame, gold: DataFrame, policy: str, k: int = 10) -> DataFrame:
    """ranks: q_id, id, score, rank (k at most); gold: q_id, id. filter: questions whose gold is among them; force: where it is
    not, it takes the last place."""
    held = ranks.filter(F.col("rank") <= k)
    found = held.join(gold, ["q_id", "id"], "left_semi").select("q_id").distinct()
    if policy == "filter":
        return held.join(found, "q_id", "left_semi").select("q_id", "id", "rank")
    missing = gold.join(found, "q_id", "left_anti")
    room = held.join(missing.select("q_id"), "q_id", "left_semi").filter(F.col("rank") < k)
    last = room.groupBy("q_id").agg(F.max("rank").alias("last"))
    forced = missing.join(last, "q_id", "left").select("q_id", "id", (F.coalesce("last", F.lit(0)) + 1).alias("rank"))
    return held.join(found, "q_id", "left_semi").select("q_id", "id", "rank").unionByName(room.select("q_id", "id", "rank")).unionByName(forced)


def selection_from_retrieval(questions: DataFrame, candidates: DataFrame, pool: DataFrame, rows: DataFrame, gold: DataFrame, n_rows: int = 3, seed: int = 0) -> DataFrame:
    """q_id, n_candidates, has_gold, n_in, prompt. pool: id, text (metadata); rows: id, row_key, cells. Rows are sampled from
    candidate tables alone."""
    wanted = rows.join(candidates.select("id").distinct(), "id", "left_semi")
    some = sample_rows(wanted, n_rows, seed, "id").groupBy("id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("nth", "cells"))), lambda s: s["cells"]), "\n").alias("cells"))
    shown = candidates.join(pool.select("id", "text"), "id").join(some, "id", "left").join(gold.withColumn("is_gold", F.lit(1)), ["q_id", "id"], "left")
    block = F.struct("rank", F.concat_ws("\n", "text", "cells").alias("x"))
    each = shown.groupBy("q_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(block)), lambda s: s["x"]), "\n").alias("data"), F.count("*").alias("n_candidates"), F.max(F.coalesce("is_gold", F.lit(0))).alias("has_gold"))
    out = each.join(questions.select("q_id", F.col("text").alias("question")), "q_id").withColumn("prompt", assemble(F.col("data"), F.col("question")))
    return out.select("q_id", "n_candidates", "has_gold", count_tokens(F.col("prompt")).alias("n_in"), "prompt")

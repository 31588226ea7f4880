"""Chapter 2 on the given tables: rows of nations, suppliers, customers and parts as text; sub-schemas of the sales database."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.parsers import parse_row_text
from ..functions.text import in_sample
from ..operators import alignment
from . import table, workload
from .knowledge import sample_sql

_ITEMS = """
select 'nation|' || r_name as table_id, n_nationkey::bigint as row_no, n_name as name, n_nationkey::bigint as number from nation join region on n_regionkey = r_regionkey
union all select 'supplier|' || n_name, s_suppkey, s_name, round(s_acctbal * 100)::bigint from supplier join nation on s_nationkey = n_nationkey
union all select 'customer|' || n_name || '|' || c_mktsegment, c_custkey, c_name, round(c_acctbal * 100)::bigint from customer join nation on c_nationkey = n_nationkey
union all select 'part|' || p_brand, p_partkey, p_name, round(p_retailprice * 100)::bigint from part
"""


def row_items(spark, sf_dir) -> DataFrame:
    t = lambda name: table(spark, sf_dir, name)
    nation = F.broadcast(t("nation"))  # 25 rows
    cents = lambda c: F.round(F.col(c) * 100).cast("long")
    one = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select(F.concat(F.lit("nation|"), "r_name").alias("table_id"), F.col("n_nationkey").cast("long").alias("row_no"), F.col("n_name").alias("name"), F.col("n_nationkey").cast("long").alias("number"))
    two = t("supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select(F.concat(F.lit("supplier|"), "n_name"), "s_suppkey", "s_name", cents("s_acctbal"))
    three = t("customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select(F.concat_ws("|", F.lit("customer"), "n_name", "c_mktsegment"), "c_custkey", "c_name", cents("c_acctbal"))
    four = t("part").select(F.concat(F.lit("part|"), "p_brand"), "p_partkey", "p_name", cents("p_retailprice"))
    rows = one.union(two).union(three).union(four)
    cells = F.create_map(F.lit("name"), F.col("name"), F.lit("number"), F.col("number").cast("string"))
    return rows.select("table_id", "row_no", F.col("table_id").alias("page_title"), F.lit("records").alias("section_title"), F.lit("all rows").alias("caption"), F.array(F.lit("name"), F.lit("number")).alias("header"), cells.alias("cells"))


_WRONG = sample_sql("table_id || '/' || row_no", 0.01, 21)


def verdicts(spark, sf_dir) -> DataFrame:
    wrong = in_sample(F.concat_ws("/", "table_id", "row_no"), 0.01, 21)
    said = alignment.describe_rows(row_items(spark, sf_dir), wrong)
    return alignment.entail(said.withColumn("text", parse_row_text(F.col("response"))))


@workload(
    f"""select table_id, row_no, md5('Describe the row in one sentence, between <description> and </description>.' || chr(10) || 'Page: ' || table_id || chr(10) || 'Section: records' || chr(10)
    || 'Caption: all rows' || chr(10) || 'name | number' || chr(10) || name || ' | ' || number) as prompt_md5 from ({_ITEMS})"""
)
def w11_prompts(spark, sf_dir):
    return alignment.render_row_prompt(row_items(spark, sf_dir)).select("table_id", "row_no", F.md5("prompt").alias("prompt_md5"))


_VERDICTS = f"""with said as (select *, 'name ' || name || ', number ' || case when {_WRONG} then number + 1 else number end as text from ({_ITEMS})),
verdicts as (select table_id, row_no, case when len(list_filter(regexp_extract_all(text, '\\d+(?:\\.\\d+)?'), lambda x: not list_contains(regexp_extract_all(name || ' ' || number, '\\d+(?:\\.\\d+)?'), x))) > 0 then 'contradicted'
  when contains(lower(text), lower(name)) and contains(text, number::varchar) then 'entailed' else 'neutral' end as verdict from said)
"""


@workload(_VERDICTS + "select verdict, count(*) as n from verdicts group by 1")
def w11_verdicts(spark, sf_dir):
    return verdicts(spark, sf_dir).groupBy("verdict").agg(F.count("*").alias("n"))


@workload(
    _VERDICTS
    + """, bad as (select distinct table_id from verdicts where verdict = 'contradicted')
    select 'table' as level, table_id, count(*) as n from verdicts where table_id not in (select table_id from bad) group by 2
    union all select 'row', table_id, count(*) from verdicts where verdict <> 'contradicted' group by 2"""
)
def w11_consistent(spark, sf_dir):
    v, out = verdicts(spark, sf_dir), None
    for level in ("table", "row"):
        one = alignment.keep_consistent_tables(v, level).groupBy("table_id").agg(F.count("*").alias("n")).withColumn("level", F.lit(level))
        out = one if out is None else out.unionByName(one)
    return out


SCHEMAS = alignment.sub_schemas(alignment.SALES_KEYS)
_SCHEMAS_SQL = "(values " + ", ".join(f"({n}, '{i}', [{', '.join(repr(t) for t in ts)}])" for n, (i, ts) in enumerate(SCHEMAS)) + ") as s(nth, schema_id, tables)"
_DRAFTS = f"""with drafts as (select c_custkey as company_id, schema_id, tables, d as draft_no, case d when 1 then c_name || ' keeps records of ' || array_to_string(tables, ', ') || ' and wants a database to report on them.'
  when 2 then 'An analyst follows ' || array_to_string(tables[:len(tables) - 1], ', ') || ' and needs to store what happens over time.' else c_name || ' wants a database.' end as text
  from customer join {_SCHEMAS_SQL} on nth = c_custkey % {len(SCHEMAS)}, (values (1), (2), (3)) as n(d)),
shared as (select *, len(list_filter(tables, lambda t: contains(text, t))) / len(tables) as share from drafts),
judged as (select company_id, schema_id, draft_no, (1 + (length(text) between 30 and 300)::int + (share >= 0.5)::int + 2 * (share >= 1)::int)::int as score from shared)
"""


def drafts(spark, sf_dir) -> DataFrame:
    """Judged drafts for each customer, whose database is one of the sub-schemas by its key."""
    known = spark.createDataFrame([(n, *s) for n, s in enumerate(SCHEMAS)], "nth long, schema_id string, tables array<string>")  # 43 rows
    companies = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("company_id"), "c_name", (F.col("c_custkey") % len(SCHEMAS)).alias("nth"))
    return alignment.judge_scenarios(alignment.draft_scenarios(companies.join(F.broadcast(known), "nth"), company=F.col("c_name")))


@workload(_DRAFTS + "select company_id, schema_id, draft_no, score, score > 4 as kept from judged")
def w12_examples(spark, sf_dir):
    return drafts(spark, sf_dir).select("company_id", "schema_id", "draft_no", "score", "kept")


@workload(_DRAFTS + "select count(*) as drafts, count(*) filter (score > 4) as kept, count(*) filter (score > 4) / count(*) as share from judged")
def w12_acceptance(spark, sf_dir):
    return alignment.acceptance_report(drafts(spark, sf_dir))

"""One-database selection and the multiple-choice sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.parsers import parse_choice, parse_tables
from ..functions.text import count_tokens
from ..operators import alignment, lm, measures, predictors, selection
from ..plans.published import values_sql
from . import sqltask, table, workload
from .knowledge import tok

ITEMS = [(q, question, gold) for q, question, _, gold in sqltask.EASY + sqltask.HARD] + [
    (f"s{i}{seg}", f"What did customers of {seg} order in {year}?", f"select sum(o_totalprice) from orders join customer on o_custkey = c_custkey where c_mktsegment = '{seg}' and year(o_orderdate) = {year}")
    for i, seg in enumerate(("BUILDING", "AUTOMOBILE", "MACHINERY", "HOUSEHOLD", "FURNITURE")) for year in (1996 + i,)
] + [
    (f"r{k}", f"Which suppliers does region {k} have?", f"with n as (select n_nationkey from nation join region on n_regionkey = r_regionkey where r_regionkey = {k}) select s_name from supplier join n on s_nationkey = n_nationkey")
    for k in range(5)
]
CATALOG = [
    (t, i, c, k)
    for t, cols in {
        "region": "r_regionkey int, r_name string", "nation": "n_nationkey int, n_name string, n_regionkey int",
        "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
        "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
        "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
        "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
        "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    }.items()
    for i, (c, k) in enumerate(x.split() for x in cols.split(", "))
]
#: an item of each customer, supplier and part; both engines read it alike
ASKED = """
select 'k' || c_custkey as q_id, 'What did customer ' || c_name || ' order in total?' as question, 'select sum(o_totalprice) from orders join customer on o_custkey = c_custkey where c_custkey = ' || c_custkey as gold_sql from customer
union all select 'u' || s_suppkey, 'Which parts does supplier ' || s_name || ' ship?', 'select distinct p_name from lineitem join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey where s_suppkey = ' || s_suppkey from supplier
union all select 'b' || p_partkey, 'How often was part ' || p_name || ' of number ' || p_partkey || ' ordered?', 'select count(*) from lineitem where l_partkey = ' || p_partkey from part
"""
_ITEMS_SQL = "(select * from (values " + ", ".join("('" + "', '".join(x.replace("'", "''") for x in r) + "')" for r in ITEMS) + ") as t(q_id, question, gold_sql) union all " + ASKED + ")"
_GOLD = rf"""items as {_ITEMS_SQL},
named as (select q_id, question, list_distinct(regexp_extract_all(lower(gold_sql), '\b(?:from|join)\s+([a-z_][a-z0-9_]*)', 1)) as n, regexp_extract_all(lower(gold_sql), '(?:\bwith|,)\s*([a-z_][a-z0-9_]*)\s+as\s*\(', 1) as own from items),
gold as (select q_id, question, list_sort(list_filter(n, lambda x: not list_contains(own, x))) as gold from named)"""
ALL = sorted({t for t, *_ in CATALOG})


def _views(spark, sf_dir, names=("customer", "supplier", "part")) -> None:
    for t in names:
        table(spark, sf_dir, t).createOrReplaceTempView(t)


def _dealt(asked: DataFrame) -> DataFrame:
    """Over all cores: small files of questions become prompts a thousand times as long."""
    return asked.repartition(asked.sparkSession.sparkContext.defaultParallelism, "q_id")


def questions(spark, sf_dir) -> DataFrame:
    _views(spark, sf_dir)
    items = spark.createDataFrame(ITEMS, "q_id string, question string, gold_sql string").union(spark.sql(ASKED))
    return items.join(selection.gold_tables_regex(items), "q_id").withColumn("db", F.lit("sales"))


def examples(spark, sf_dir) -> DataFrame:
    tables = {t: table(spark, sf_dir, t) for t in ALL}
    catalog = alignment.catalog_of(spark, "sales", tables, alignment.SALES_KEYS)
    return selection.selection_from_schema(_dealt(questions(spark, sf_dir)), catalog)


@workload(f"with {_GOLD} select q_id, array_to_string(gold, ',') as gold, len(gold)::int as n from gold")
def w3_gold_tables(spark, sf_dir):
    return questions(spark, sf_dir).select("q_id", F.array_join("gold", ",").alias("gold"), F.size("gold").alias("n"))


_W3 = f"""with {_GOLD}, cat as (select * from {values_sql(CATALOG, "tab, ordinal, col, kind")}),
ddl as (select tab || '(' || string_agg(col || ' ' || kind, ', ' order by ordinal) || ')' as d from cat group by tab),
shown as (select string_agg(d, chr(10) order by d) as data from ddl),
ex as (select q_id, gold, data || chr(10) || '{selection.INSTRUCTION}' || chr(10) || 'Question: ' || question as prompt from gold cross join shown)
"""


@workload(_W3 + f"select q_id, {len(ALL)}::int as n_candidates, len(gold)::int as n_gold, len({tok('prompt')})::bigint as n_in, md5(prompt) as prompt_md5 from ex")
def w3_examples(spark, sf_dir):
    return examples(spark, sf_dir).select("q_id", F.size("candidates").alias("n_candidates"), F.size("gold").alias("n_gold"), count_tokens(F.col("prompt")).alias("n_in"), F.md5("prompt").alias("prompt_md5"))


@workload(_W3 + f"select 'ts_schema' as dataset, count(*) as questions, avg(len({tok('prompt')})) as avg_tokens, max(len({tok('prompt')}))::bigint as max_tokens, quantile_cont(len({tok('prompt')}), 0.5) as p50_tokens, quantile_cont(len({tok('prompt')}), 0.95) as p95_tokens, {float(len(ALL))}::double as avg_candidates, avg(len(gold)) as avg_gold, count(*) filter (len(gold) > 1) as several_gold from ex")
def w3_profile(spark, sf_dir):
    ex = examples(spark, sf_dir).select(F.lit("ts_schema").alias("dataset"), count_tokens(F.col("prompt")).alias("n_in"), F.size("candidates").alias("n_candidates"), F.size("gold").alias("n_gold"))
    return measures.input_profile(ex, ["dataset"])


#: text-to-SQL questions of each customer, supplier and part, the harder ones with hints; both engines read them alike
ASKED_EASY = """
select 'k' || c_custkey as q_id, 'How many orders has customer ' || c_name || '?' as question, cast(null as varchar(1)) as hint from customer
union all select 'b' || p_partkey, 'How many line items has part ' || p_name || ' of number ' || p_partkey || '?', null from part
"""
ASKED_HARD = """
select 'k' || c_custkey as q_id, 'How many premium orders has customer ' || c_name || '?' as question, 'premium: o_totalprice > 200000' as hint from customer
union all select 'u' || s_suppkey, 'Which nations do customers of supplier ' || s_name || ' live in?', null from supplier
"""


def _sql_prompts(spark, sf_dir, items, every: str) -> DataFrame:
    """Text-to-SQL prompts of a set and of table rows, with and without hints."""
    _views(spark, sf_dir)
    catalog = alignment.catalog_of(spark, "sales", {t: table(spark, sf_dir, t) for t in ALL}, alignment.SALES_KEYS)
    asked = spark.createDataFrame([(q, "sales", question, hint) for q, question, hint, _ in items], "q_id string, db string, question string, hint string")
    asked = _dealt(asked.unionByName(spark.sql(every).withColumn("db", F.lit("sales"))))
    made = [selection.sql_examples(asked, catalog, knowledge).withColumn("knowledge", F.lit(knowledge)) for knowledge in (True, False)]
    return made[0].unionByName(made[1]).select("q_id", "knowledge", count_tokens(F.col("prompt")).alias("n_in"), F.md5("prompt").alias("prompt_md5"))


def _sql_prompts_sql(items, every: str) -> str:
    quoted = lambda x: "null" if x is None else "'" + x.replace("'", "''") + "'"
    asked = ", ".join(f"({', '.join(map(quoted, (q, question, hint)))})" for q, question, hint, _ in items)
    return _W3 + f""", asked as (select * from (select * from (values {asked}) as t(q_id, question, hint) union all {every}) cross join (values (true), (false)) as k(knowledge)),
    made as (select q_id, knowledge, concat_ws(chr(10), data, '{selection.SQL_INSTRUCTION}', case when knowledge then 'Knowledge: ' || hint end, 'Question: ' || question) as prompt from asked cross join shown)
    select q_id, knowledge, len({tok("prompt")})::bigint as n_in, md5(prompt) as prompt_md5 from made"""


@workload(_sql_prompts_sql(sqltask.EASY, ASKED_EASY))
def w6_examples(spark, sf_dir):
    return _sql_prompts(spark, sf_dir, sqltask.EASY, ASKED_EASY)


@workload(_sql_prompts_sql(sqltask.HARD, ASKED_HARD))
def w7_examples(spark, sf_dir):
    return _sql_prompts(spark, sf_dir, sqltask.HARD, ASKED_HARD)


KINDS = ("lines", "comma", "extra", "missing", "nonsense", "empty")


def parsed(spark, sf_dir) -> DataFrame:
    ex = examples(spark, sf_dir)
    outputs = predictors.gold_echo(ex).unionByName(predictors.all_candidates(ex))
    for kind in KINDS:
        outputs = outputs.unionByName(predictors.corrupted(ex, kind))
    found, route = parse_tables(F.col("output"))
    return outputs.withColumn("predicted", found).withColumn("route", route)


_PRED = (
    f"with {_GOLD}, every as (select {ALL!r} as cands), p as (select q_id, gold, cands, unnest(['gold_echo', 'all_candidates', {', '.join(map(repr, KINDS))}]) as predictor from gold cross join every),"
    + """said as (select *, case predictor when 'gold_echo' then gold when 'all_candidates' then cands when 'lines' then gold when 'comma' then gold
      when 'extra' then gold || list_slice(list_filter(cands, lambda x: not list_contains(gold, x)), 1, 1) when 'missing' then gold[2:]
      when 'nonsense' then ['I would look at the data first.'] else [] end as predicted from p),
    m as (select *, len(list_intersect(predicted, gold)) as b, len(predicted) as np, len(gold) as ng from said)"""
)


@workload(
    _PRED
    + """ select predictor, count(*) as n, avg((b = np and b = ng)::int) as accuracy, round(avg(case when np > 0 then b / np else 0 end), 6) as set_precision,
    round(avg(case when ng > 0 then b / ng else 1 end), 6) as set_recall, round(avg(case when np + ng > 0 then 2 * b / (np + ng) else 1 end), 6) as f1,
    round(avg(case when np + ng > 0 then b / (np + ng - b) else 1 end), 6) as jaccard, avg((np > b)::int) as over, avg((ng > b)::int) as under from m group by 1"""
)
def w3_accuracy(spark, sf_dir):
    pairs = measures.with_gold(parsed(spark, sf_dir).select("q_id", "predictor", "predicted"), questions(spark, sf_dir).select("q_id", "gold"))
    out = measures.set_accuracy(pairs, ["predictor"])
    return out.select("predictor", "n", "accuracy", *[F.round(c, 6).alias(c) for c in ("set_precision", "set_recall", "f1", "jaccard")], "over", "under")


@workload(_PRED + " select predictor, count(*) as n, avg((predictor in ('lines', 'nonsense'))::int) as fallback, avg((predictor = 'empty')::int) as missing from m group by 1")
def w3_format_errors(spark, sf_dir):
    return measures.format_errors(parsed(spark, sf_dir), ["predictor"])


@workload(_PRED + " select predictor, count(*) as n, avg((len(list_intersect(predicted, cands)) = 0)::int) as failed from m group by 1")
def w3_context_failures(spark, sf_dir):
    held = parsed(spark, sf_dir).join(examples(spark, sf_dir).select("q_id", "candidates"), "q_id")
    return measures.long_context_failures(held, ["predictor"])


# ---- multiple choice --------------------------------------------------------------------------------------

_FACTS = """
select 'da' as category, 'Which segment has customer ' || c_custkey || '?' as question, c_mktsegment as fact, c_custkey::bigint as k, 'segment' as kind from customer
union all select 'db', 'Which table has the column ' || col || '?', tab, ordinal, 'table' from cat
union all select 'ml', 'Which event type has event ' || event_id || '?', event_type, event_id, 'event' from events
"""
_MCQ = f"""with cat as (select * from {values_sql(CATALOG, "tab, ordinal, col, kind")}), facts as ({_FACTS}),
vals as (select distinct kind, fact as v from facts),
wrong as (select question, v, row_number() over (partition by question order by md5(question || v || '|3'), v) as r from facts join vals using (kind) where v <> fact),
opts as (select question, fact as v from facts union all select question, v from wrong where r <= 3),
placed as (select question, v, row_number() over (partition by question order by md5(v || question || '|4'), v) as pos from opts),
items as (select f.category, f.question, f.fact, max(v) filter (pos = 1) as a, max(v) filter (pos = 2) as b, max(v) filter (pos = 3) as c, max(v) filter (pos = 4) as d,
  chr(64 + (max(pos) filter (v = fact))::int) as answer from facts f join placed using (question) group by 1, 2, 3)
"""


def mcq_items(spark, sf_dir) -> DataFrame:
    """q_id, category, question, a to d, answer: a fact, three sibling values by hash, places by another hash."""
    from pyspark.sql import Window as W

    spark.createDataFrame(CATALOG, "tab string, ordinal int, col string, kind string").createOrReplaceTempView("cat")
    for t in ("customer", "events"):
        table(spark, sf_dir, t).createOrReplaceTempView(t)
    facts = spark.sql(_FACTS)
    vals = facts.select("kind", F.col("fact").alias("v")).distinct()
    nth = lambda *c: F.row_number().over(W.partitionBy("question").orderBy(F.md5(F.concat(*c)), "v"))
    wrong = facts.join(F.broadcast(vals), "kind").filter("v <> fact").withColumn("r", nth("question", "v", F.lit("|3"))).filter("r <= 3")
    every = facts.select("question", F.col("fact").alias("v")).unionByName(wrong.select("question", "v"))
    placed = every.withColumn("pos", nth("v", "question", F.lit("|4")))
    own = placed.join(facts, "question").groupBy("category", "question", "fact").agg(
        *[F.max(F.when(F.col("pos") == i + 1, F.col("v"))).alias(c) for i, c in enumerate("abcd")], F.max(F.when(F.col("v") == F.col("fact"), F.col("pos"))).alias("at")
    )
    return own.select(F.md5("question").alias("q_id"), "category", "question", "a", "b", "c", "d", F.substring(F.lit("ABCD"), F.col("at"), F.lit(1)).alias("answer"))


def mcq_prompt(items: DataFrame) -> DataFrame:
    lines = [F.concat(F.lit(f"({x.upper()}) "), x) for x in "abcd"]
    return items.withColumn("prompt", F.concat_ws("\n", "question", *lines, F.lit("Give the letter of the right choice after 'Answer:'.")))


@workload(_MCQ + "select md5(question) as q_id, category, question, a, b, c, d, answer from items")
def w1_mcq_items(spark, sf_dir):
    return mcq_items(spark, sf_dir)


@workload(
    _MCQ
    + f""", n as (select *, md5(question) as q_id from items), picks as (
      select category, answer, 'first_choice' as predictor, 'A' as letter from n
      union all select category, answer, 'hash_choice', substr('ABCD', ('0x' || substr(md5(q_id || '|13'), 1, 4))::int % 4 + 1, 1) from n
      union all select category, answer, 'lexical_choice', 'ABCD'[list_position(s, list_max(s))] from (select *, [len(list_intersect({tok("question")}, {tok("a")})), len(list_intersect({tok("question")}, {tok("b")})),
        len(list_intersect({tok("question")}, {tok("c")})), len(list_intersect({tok("question")}, {tok("d")}))] as s from n))
    select predictor, category, count(*) as n, avg((letter = answer)::int) as accuracy from picks group by 1, 2"""
)
def w1_mcq_accuracy(spark, sf_dir):
    items = mcq_items(spark, sf_dir)
    outputs = predictors.first_choice(items).unionByName(predictors.hash_choice(items)).unionByName(predictors.lexical_choice(items))
    letters = outputs.withColumn("letter", parse_choice(F.col("output"))[0])
    return measures.choice_accuracy(letters.join(items.select("q_id", "category", "answer"), "q_id"), ["predictor", "category"])


@workload()
def w1_mcq_lm(spark, sf_dir):
    """The count model's choice: trained on the questions with their right answers of even hash, asked the others."""
    items = mcq_items(spark, sf_dir)
    right = F.get(F.array("a", "b", "c", "d"), F.instr(F.lit("ABCD"), F.col("answer")) - 1)
    even = F.substring("q_id", 1, 1).isin(*"02468ace")
    model = lm.fit_bigrams(items.filter(even).select(F.col("q_id").alias("id"), F.concat_ws(" ", "question", right).alias("text")))
    letters = predictors.lm_choice(items.filter(~even), model).withColumn("letter", parse_choice(F.col("output"))[0])
    return measures.choice_accuracy(letters.join(items.select("q_id", "category", "answer"), "q_id"), ["predictor", "category"])

"""Text-to-SQL sets on the sales tables: gold SQL, planted predictions, execution accuracy, failure classes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.parsers import parse_sql
from ..operators import execacc
from . import table, workload

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")

# (q_id, question, hint, gold SQL): SQL that both engines read alike
EASY = [
    ("e1", "How many customers are in the segment BUILDING?", None, "select count(*) from customer where c_mktsegment = 'BUILDING'"),
    ("e2", "Which segments are there and how many customers has each?", None, "select c_mktsegment, count(*) from customer group by c_mktsegment"),
    ("e3", "Which nations are in REGION_0's region key 0?", None, "select n_name from nation where n_regionkey = 0"),
    ("e4", "Which parts have the largest size?", None, "select p_partkey from part where p_size = (select max(p_size) from part)"),
    ("e5", "How many orders has each priority?", None, "select o_orderpriority, count(*) from orders group by o_orderpriority"),
    ("e6", "How many suppliers has each nation?", None, "select n_name, count(*) from supplier join nation on s_nationkey = n_nationkey group by n_name"),
] + [
    (f"y{year}", f"What was the total of all orders of {year}?", None, f"select round(sum(o_totalprice), 0) from orders where year(o_orderdate) = {year}")
    for year in range(1994, 1998)
] + [
    (f"p{size}", f"How many brands have parts of size {size}?", None, f"select count(distinct p_brand) from part where p_size = {size}")
    for size in (1, 15, 50)
]
HARD = [
    ("h1", "How many premium orders did each region's customers place?", "premium: o_totalprice > 200000", "select r_name, count(*) from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey where o_totalprice > 200000 group by r_name"),
    ("h2", "Which customers never ordered?", None, "select c_custkey from customer where c_custkey not in (select o_custkey from orders)"),
    ("h3", "Which segments have loyal customers?", "loyal: 15 orders or more", "select distinct c_mktsegment from customer join (select o_custkey, count(*) as n from orders group by o_custkey) as t on o_custkey = c_custkey where n >= 15"),
    ("h4", "How many line items of each brand did suppliers of nation 3 ship?", None, "select p_brand, count(*) from lineitem join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey where s_nationkey = 3 group by p_brand"),
] + [
    (f"c{k}", f"How many orders did solvent customers of region {k} place?", "solvent: c_acctbal > 5000", f"select count(*) from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey where c_acctbal > 5000 and n_regionkey = {k}")
    for k in range(5)
]
KINDS = {
    # the hint's predicate on a table that the join brings in, or wrongly on the one that the question starts from
    "wrong table": lambda s: s.replace("c_acctbal > 5000", "o_totalprice > 5000"),
    "exact": lambda s: s, "no join": lambda s: s.split(" join ")[0] + (" group by 1" if "group by" in s and " join " in s else ""), "twice": lambda s: f"select * from ({s}) as a union all select * from ({s}) as b",
    "filtered": lambda s: f"select * from ({s}) as a where 1 = 0", "syntax": lambda s: s.replace("select", "selekt", 1), "column": lambda s: s.replace("select ", "select no_such_column, ", 1),
    "table": lambda s: "select * from no_such_table", "command": lambda s: "drop view orders", "empty": lambda s: "",
}
FAILING = ("syntax", "column", "table", "command", "empty")
#: without their joins these name columns that are not there
NEED_JOIN = ("e6", "h1", "h4")


def output_of(kind: str, sql: str) -> str:
    return f"Here it is:\n```sql\n{sql}\n```" if kind == "exact" else "" if kind == "empty" else f"<SQL>{sql}</SQL>"


def predictions(spark, items) -> DataFrame:
    rows = [(q, kind, output_of(kind, change(gold)), gold) for q, _, _, gold in items for kind, change in KINDS.items()]
    made = spark.createDataFrame(rows, "q_id string, predictor string, output string, gold_sql string")
    return made.withColumn("predicted", parse_sql(F.col("output"))[0])


def _views(spark, sf_dir) -> None:
    for t in TABLES:
        table(spark, sf_dir, t).createOrReplaceTempView(t)


def _accuracy(spark, sf_dir, items, compare: str) -> DataFrame:
    _views(spark, sf_dir)
    done = execacc.execution_accuracy(spark, predictions(spark, items), compare, None)  # the SQL knows no limit of time
    return done.groupBy("predictor").agg(F.count("*").alias("n"), F.avg(F.col("correct").cast("double")).alias("accuracy"))


def _accuracy_sql(items, word: str = "except") -> str:
    """The same by EXCEPT both ways in the other engine; predictions that can't run are wrong."""
    each = [
        f"select '{kind}' as predictor, 0 as ok" if kind in FAILING or (kind == "no join" and q in NEED_JOIN)
        else f"select '{kind}', (not exists (({gold}) {word} ({change(gold)})) and not exists (({change(gold)}) {word} ({gold})))::int"
        for q, _, _, gold in items for kind, change in KINDS.items()
    ]
    return f"select predictor, count(*) as n, avg(ok) as accuracy from ({' union all '.join(sorted(each, key=lambda s: ' as predictor' not in s))}) group by 1"


@workload(_accuracy_sql(EASY))
def w6_exec_acc(spark, sf_dir):
    return _accuracy(spark, sf_dir, EASY, "set")


@workload(_accuracy_sql(HARD))
def w7_exec_acc(spark, sf_dir):
    return _accuracy(spark, sf_dir, HARD, "set")


@workload(_accuracy_sql(EASY, "except all"))
def w6_exec_acc_bag(spark, sf_dir):
    return _accuracy(spark, sf_dir, EASY, "bag")


@workload()
def w7_failures(spark, sf_dir):
    """Failure classes of all planted predictions of the harder set."""
    _views(spark, sf_dir)
    return execacc.execution_accuracy(spark, predictions(spark, HARD), timeout_s=None).groupBy("predictor", "class").agg(F.count("*").alias("n"))

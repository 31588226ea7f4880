"""Pages: the given ones as text; region pages with 21 tables; questions over several tables; records; two hops."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.parsers import parse_tables
from ..functions.text import count_tokens, order_hash
from ..operators import measures, pages, predictors
from . import table, workload


def _steps_sql(column: str) -> str:
    out = f"coalesce({column}, '')"
    for pattern, to in pages.TEXT_STEPS:
        quoted, to = pattern.replace("'", "''"), to.replace("'", "''")
        out = f"regexp_replace({out}, '{quoted}', '{to}', 'g')"
    return f"trim({out})"


@workload(f"select page_id, length(t) as n_chars, md5(t) as text_md5 from (select page_id, {_steps_sql('html')} as t from pages)")
def w5_page_text(spark, sf_dir):
    t = pages.page_text(F.col("html"))
    return table(spark, sf_dir, "pages").select("page_id", t.alias("t")).select("page_id", F.length("t").cast("long").alias("n_chars"), F.md5("t").alias("text_md5"))


SECTIONS = ("Suppliers", "Segments", "Years", "Statuses")
#: sections that questions set against each other, for each nation of a page
COMPARED = (("Segments", "Years"), ("Segments", "Statuses"), ("Suppliers", "Years"), ("Suppliers", "Statuses"))


def _html_table(rows: DataFrame, group: str, order: str, header: list[str], cells: list[str]) -> DataFrame:
    """One HTML table for each group; the cells have links, images and an unclosed tag for the converter to drop."""
    cell = [F.concat(F.lit('<td style="x"><a href="#">'), F.col(c).cast("string"), F.lit("</a><img src='i.png'><b>")) for c in cells]
    line = F.concat(F.lit("<tr>"), *cell, F.lit("</tr>"))
    head = "<tr>" + "".join(f"<th>{h}</th>" for h in header) + "</tr>"
    body = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), line.alias("x")))), lambda s: s["x"]), "")
    return rows.groupBy(group).agg(F.concat(F.lit("<table>" + head), body, F.lit("</table>")).alias("html"))


def region_pages(spark, sf_dir) -> DataFrame:
    """page_id, url, html: a page for each region, with its nations and four aggregates of each nation; prose from documents."""
    t = lambda name: table(spark, sf_dir, name)
    nation, customer = t("nation"), t("customer")
    by_nation = {
        "Suppliers": t("supplier").groupBy("s_nationkey").agg(F.count("*").alias("n"), F.max("s_name").alias("k")).select(F.col("s_nationkey").alias("nk"), "k", "n"),
        "Segments": customer.groupBy(F.col("c_nationkey").alias("nk"), F.col("c_mktsegment").alias("k")).agg(F.count("*").alias("n")),
        "Years": customer.join(t("orders"), F.col("c_custkey") == F.col("o_custkey")).groupBy(F.col("c_nationkey").alias("nk"), F.year("o_orderdate").cast("string").alias("k")).agg(F.count("*").alias("n")),
        "Statuses": customer.join(t("orders"), F.col("c_custkey") == F.col("o_custkey")).groupBy(F.col("c_nationkey").alias("nk"), F.col("o_orderstatus").alias("k")).agg(F.count("*").alias("n")),
    }
    blocks = None
    for i, section in enumerate(SECTIONS):
        one = _html_table(by_nation[section], "nk", "k", [section, "count"], ["k", "n"])
        # a nation without rows has an empty table
        whole = nation.join(one, F.col("n_nationkey") == F.col("nk"), "left").select("n_regionkey", F.lit(i + 1).alias("at"), "n_nationkey", F.concat(F.lit(f"<h2>{section}</h2>"), F.coalesce("html", F.lit("<table></table>"))).alias("html"))
        blocks = whole if blocks is None else blocks.unionByName(whole)
    first = _html_table(nation.withColumn("extra", F.lit("<table><tr><td>nested</td></tr></table>")), "n_regionkey", "n_nationkey", ["nation", "key"], ["n_name", "n_nationkey"])
    blocks = blocks.unionByName(first.select("n_regionkey", F.lit(0).alias("at"), F.lit(0).alias("n_nationkey"), F.concat(F.lit("<h2>Nations</h2>"), "html").alias("html")))
    body = blocks.groupBy("n_regionkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "n_nationkey", "html"))), lambda s: s["html"]), "\n").alias("body"))
    prose = t("documents").filter("lang = 'en'").orderBy(order_hash(F.col("doc_id"), 1), "doc_id").limit(4).agg(F.concat_ws("</p><p>", F.array_sort(F.collect_list("text"))).alias("prose"))
    page = F.concat(F.lit("<html><h1>"), "r_name", F.lit("</h1><p>"), "prose", F.lit("&amp;</p>"), "body", F.lit("</html>"))
    joined = t("region").join(body, F.col("r_regionkey") == F.col("n_regionkey")).crossJoin(F.broadcast(prose))  # one row of prose
    return joined.select(F.col("r_regionkey").cast("long").alias("page_id"), F.concat(F.lit("http://pages.example/"), "r_name").alias("url"), page.alias("html"))


def tables(spark, sf_dir) -> DataFrame:
    return pages.name_tables(pages.page_tables(region_pages(spark, sf_dir)))


_TABLES = """with owners as (select r_regionkey, n_nationkey, row_number() over (partition by r_regionkey order by n_nationkey) as nth from region join nation on n_regionkey = r_regionkey),
ords as (select c_nationkey as nk, year(o_orderdate) as y, o_orderstatus as s from customer join orders on o_custkey = c_custkey),
cnt as (select n_nationkey as nk, (select count(*) > 0 from supplier where s_nationkey = n_nationkey)::int as a, (select count(distinct c_mktsegment) from customer where c_nationkey = n_nationkey) as b,
  (select count(distinct y) from ords where nk = n_nationkey) as c, (select count(distinct s) from ords where nk = n_nationkey) as d from nation)
"""


@workload(
    _TABLES
    + """select r_regionkey::bigint as page_id, 'Nations_1' as table_name, count(*)::int as n_rows from owners group by 1
    union all select r_regionkey, 'Suppliers_' || nth, a::int from owners join cnt on nk = n_nationkey union all select r_regionkey, 'Segments_' || nth, b::int from owners join cnt on nk = n_nationkey
    union all select r_regionkey, 'Years_' || nth, c::int from owners join cnt on nk = n_nationkey union all select r_regionkey, 'Statuses_' || nth, d::int from owners join cnt on nk = n_nationkey"""
)
def w5_tables(spark, sf_dir):
    return tables(spark, sf_dir).select("page_id", "table_name", "n_rows")


def page_questions(named: DataFrame) -> DataFrame:
    """Two kinds that need several tables: two sections of a nation against each other, and all status tables of a page."""
    by_page = named.groupBy("page_id").agg(F.array_sort(F.collect_set("table_name")).alias("names"))
    sides = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a, b in COMPARED]))
    pair = by_page.select("page_id", F.explode(F.sequence(F.lit(1), F.lit(5))).alias("k")).select("*", sides.alias("s")).select("page_id", "k", "s.*").select(
        F.concat_ws("-", F.lit("pair"), "page_id", "k", "a", "b").alias("q_id"), "page_id",
        F.concat(F.lit("Compare "), F.lower("a"), F.lit(" and "), F.lower("b"), F.lit(" of nation number "), "k").alias("question"),
        F.array_sort(F.array(F.concat_ws("_", "a", "k"), F.concat_ws("_", "b", "k"), F.lit("Nations_1"))).alias("gold"),
    )
    every = by_page.select(F.concat_ws("-", F.lit("every"), "page_id").alias("q_id"), "page_id", F.lit("How many orders of each status are there in all nations?").alias("question"), F.filter("names", lambda n: n.startswith("Statuses")).alias("gold"))
    return pair.unionByName(every)


def examples(spark, sf_dir) -> DataFrame:
    named, shell = tables(spark, sf_dir), region_pages(spark, sf_dir)
    return pages.selection_from_page(page_questions(named), named, shell.select("page_id", pages.page_text(F.col("html")).alias("text")))


@workload(
    f"""with p as (select r_regionkey::bigint as page_id from region), q as (select 'pair-' || page_id || '-' || k || '-' || a || '-' || b as q_id, page_id, 3 as n_gold
    from p, range(1, 6) as r(k), (values {", ".join(map(str, COMPARED))}) as s(a, b) union all select 'every-' || page_id, page_id, 5 from p) select q_id, page_id, 21::int as n_candidates, n_gold::int as n_gold from q"""
)
def w5_examples(spark, sf_dir):
    return examples(spark, sf_dir).select("q_id", "page_id", F.size("candidates").alias("n_candidates"), F.size("gold").alias("n_gold"))


@workload()
def w5_profile(spark, sf_dir):
    """Tokens, candidates and gold tables of the page questions."""
    ex = examples(spark, sf_dir).select(F.lit("ts_page").alias("dataset"), count_tokens(F.col("prompt")).alias("n_in"), F.size("candidates").alias("n_candidates"), F.size("gold").alias("n_gold"))
    return measures.input_profile(ex, ["dataset"])


@workload("select 'gold_echo' as predictor, 105::bigint as n, 1.0::double as accuracy union all select 'all_candidates', 105, 0.0 union all select 'missing', 105, 0.0")
def w5_accuracy(spark, sf_dir):
    ex = examples(spark, sf_dir)
    outputs = predictors.gold_echo(ex).unionByName(predictors.all_candidates(ex)).unionByName(predictors.corrupted(ex, "missing"))
    found = outputs.withColumn("predicted", parse_tables(F.col("output"))[0]).select("q_id", "predictor", "predicted")
    return measures.set_accuracy(measures.with_gold(found, ex.select("q_id", "gold")), ["predictor"]).select("predictor", "n", "accuracy")


@workload()
def w5_context_capped(spark, sf_dir):
    """The same with a predictor whose context is shorter than the pages: no score."""
    ex = examples(spark, sf_dir).withColumn("n_in", count_tokens(F.col("prompt")))
    outputs = predictors.context_capped(predictors.gold_echo(ex), ex, limit=1000)
    scored = outputs.join(ex.select("q_id", "n_in", "gold"), "q_id").withColumn("correct", parse_tables(F.col("output"))[0] == F.col("gold"))
    return measures.context_exceeded(scored.withColumn("dataset", F.lit("ts_page")), 1000, ["dataset"])


@workload(
    """with b as (select event_type as key, value, max(value) over (partition by event_type order by ts, event_id rows between unbounded preceding and 1 preceding) as best from events)
    select key, count(*) filter (best is not null and value >= best) as matches_or_beats, count(*) as n from b group by 1"""
)
def w5b_records(spark, sf_dir):
    events = table(spark, sf_dir, "events").select(F.col("event_type").alias("key"), "ts", "event_id", "value")
    return pages.record_moves(events, "key", ["ts", "event_id"], "value")


_TWO_HOP = """with s as (select r_name, s_suppkey, n_nationkey, row_number() over (partition by r_name order by s_acctbal desc, s_suppkey) as r
  from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey),
y as (select c_nationkey, year(o_orderdate)::int as order_year, round(sum(o_totalprice), 2) as total from orders join customer on o_custkey = c_custkey group by 1, 2),
b as (select *, row_number() over (partition by c_nationkey order by total desc, order_year) as r from y)
select r_name, s_suppkey, order_year, total from s left join b on b.c_nationkey = s.n_nationkey and b.r = 1 where s.r = 1"""


@workload(_TWO_HOP)
def w5c_two_hop(spark, sf_dir):
    """Each region's supplier of the largest balance, then the best year of its nation's customers."""
    t = lambda name: table(spark, sf_dir, name)
    nations = F.broadcast(t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")))  # 25 rows
    top = t("supplier").join(nations, F.col("s_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.max_by(F.struct("s_suppkey", "n_nationkey"), F.struct("s_acctbal", -F.col("s_suppkey"))).alias("s"))
    years = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey", F.year("o_orderdate").alias("order_year")).agg(F.round(F.sum("o_totalprice"), 2).alias("total"))
    best = years.groupBy("c_nationkey").agg(F.max_by(F.struct("order_year", "total"), F.struct("total", -F.col("order_year"))).alias("b"))
    return top.join(best, F.col("s.n_nationkey") == F.col("c_nationkey"), "left").select("r_name", "s.s_suppkey", "b.order_year", "b.total")

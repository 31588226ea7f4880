"""Similar-table selection: a pool of slices of the star tables, sparse and dense ranks, gold policies, examples."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import measures, retrieval, selection
from . import table, workload
from .knowledge import tok

# family: (table, key expressions that both engines read alike, phrase, its keys' names)
FAMILIES = {
    "customer": ("customer join nation on c_nationkey = n_nationkey", ("n_name", "c_mktsegment"), "customers", ("nation", "segment")),
    "part": ("part", ("p_brand", "p_type"), "parts", ("brand", "type")),
    "orders": ("orders", ("o_orderpriority", "o_orderstatus", "cast(year(o_orderdate) as varchar(4))"), "orders", ("priority", "status", "year")),
    "supplier": ("supplier join nation on s_nationkey = n_nationkey", ("n_name",), "suppliers", ("nation",)),
    "lineitem": ("lineitem", ("l_returnflag", "l_linestatus", "cast(year(l_shipdate) as varchar(4))"), "line items", ("flag", "status", "year")),
    "events": ("events", ("event_type", "cast(day(ts) as varchar(2))"), "events", ("type", "day")),
}


def _family_sql(name: str) -> str:
    source, keys, phrase, labels = FAMILIES[name]
    parts = " || ".join(f"' {label} ' || {key}" for label, key in zip(labels, keys))
    fewer = " || ".join([f"'{phrase}'"] + [f"' {label} ' || {key}" for label, key in list(zip(labels, keys))[:-1]])
    ident = " || '|' || ".join([f"'{name}'", *keys])
    return f"select {ident} as id, '{name}' as family, '{phrase}' || {parts} as title, {fewer} as partial, count(*) as n_rows from {source} group by {', '.join(keys)}"


POOL = " union all ".join(_family_sql(f) for f in FAMILIES)


def pool(spark, sf_dir) -> DataFrame:
    """id, family, title, partial (the title without its last key), n_rows; one aggregate over each fact table."""
    for source in ("customer", "nation", "part", "orders", "supplier", "lineitem", "events"):
        table(spark, sf_dir, source).createOrReplaceTempView(source)
    return spark.sql(POOL)


def bm25_sql(pool_sql: str, question_sql: str, k: int = 10) -> str:
    """Ends with ranks(q_id, id, score, rank). pool_sql: id, text; question_sql: q_id, text."""
    return f"""
pool as ({pool_sql}), ask as ({question_sql}),
post as (select id, term, count(*) as tf from (select id, unnest({tok("text")}) as term from pool) group by 1, 2),
lens as (select id, len({tok("text")}) as n from pool), whole as (select count(*) as p, avg(n) as mean from lens),
dfs as (select term, count(*) as df from post group by 1),
want as (select distinct q_id, unnest({tok("text")}) as term from ask),
scored as (select q_id, id, round(sum(ln(1 + (p - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * n / mean))), 6) as score
  from want join post using (term) join dfs using (term) join lens using (id) cross join whole group by 1, 2),
ranks as (select * from (select *, row_number() over (partition by q_id order by score desc, id) as rank from scored) where rank <= {k})
"""


@workload(f"select id, family, title, n_rows from ({POOL})")
def w4_pool(spark, sf_dir):
    return pool(spark, sf_dir).select("id", "family", "title", "n_rows")


_LITERAL = f"with slices as ({POOL}), " + bm25_sql("select id, title as text from slices", "select id as q_id, 'which table lists ' || title as text from slices")


def literal(spark, sf_dir) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Pool, questions and gold of the literal style."""
    p = pool(spark, sf_dir)
    return p.select("id", F.col("title").alias("text")), p.select(F.col("id").alias("q_id"), F.concat(F.lit("which table lists "), "title").alias("text")), p.select(F.col("id").alias("q_id"), "id")


@workload(_LITERAL + "select q_id, rank, id, score from ranks")
def w4_bm25_top10(spark, sf_dir):
    held, asked, _ = literal(spark, sf_dir)
    return retrieval.bm25_rank(asked, held).select("q_id", "rank", "id", "score")


_CELL_ROWS = "select 'customer|' || n_name || '|' || c_mktsegment as id, c_custkey::varchar as row_key, c_name as cells from customer join nation on c_nationkey = n_nationkey"
_CELL_POOL = f"""
select s.id, s.title || coalesce(' ' || r.cells, '') as text from slices s left join (select id, string_agg(cells, ' ' order by nth) as cells from
  (select *, row_number() over (partition by id order by md5(row_key || '|0'), row_key) as nth from ({_CELL_ROWS})) where nth <= 3 group by 1) r using (id)"""
_CELL = f"with slices as ({POOL}), gold as (select row_key as q_id, id, cells from ({_CELL_ROWS})), " + bm25_sql(
    _CELL_POOL, "select q_id, 'in which table is ' || cells as text from gold"
)


def cell_rows(spark, sf_dir) -> DataFrame:
    joined = table(spark, sf_dir, "customer").join(F.broadcast(table(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    return joined.select(F.concat_ws("|", F.lit("customer"), "n_name", "c_mktsegment").alias("id"), F.col("c_custkey").cast("string").alias("row_key"), F.col("c_name").alias("cells"))


def cell(spark, sf_dir) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The pool with three sampled rows of each customer table; a question for each customer that names only it; their gold."""
    rows = cell_rows(spark, sf_dir)
    some = selection.sample_rows(rows, 3, 0, "id").groupBy("id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("nth", "cells"))), lambda s: s["cells"]), " ").alias("cells"))
    held = pool(spark, sf_dir).join(some, "id", "left").select("id", F.concat_ws(" ", "title", "cells").alias("text"))
    return held, rows.select(F.col("row_key").alias("q_id"), F.concat(F.lit("in which table is "), "cells").alias("text")), rows.select(F.col("row_key").alias("q_id"), "id")


_PARTIAL = f"with slices as ({POOL}), " + bm25_sql("select id, title as text from slices", "select id as q_id, 'which table lists ' || partial as text from slices where family <> 'supplier'")


def partial(spark, sf_dir) -> tuple[DataFrame, DataFrame, DataFrame]:
    p = pool(spark, sf_dir)
    asked = p.filter("family <> 'supplier'")
    return p.select("id", F.col("title").alias("text")), asked.select(F.col("id").alias("q_id"), F.concat(F.lit("which table lists "), "partial").alias("text")), asked.select(F.col("id").alias("q_id"), "id")


STYLES = {"literal": literal, "cell": cell, "partial": partial}


def _by_style(spark, sf_dir, score: str = "bm25") -> DataFrame:
    out = None
    for name, style in STYLES.items():
        held, asked, gold = style(spark, sf_dir)
        found = retrieval.candidate_recall(retrieval.bm25_rank(asked, held, score=score), gold, 10)
        one = found.select("questions", "top1", F.col("recall").alias("in_ten"), F.round("mrr", 6).alias("mrr"), F.lit(name).alias("style"))
        out = one if out is None else out.unionByName(one)
    return out


def _style_sql(name: str, head: str, gold: str) -> str:
    return f"""select '{name}' as style, * from ({head} , best as (select g.q_id, min(r.rank) as rank from ({gold}) g left join ranks r on r.q_id = g.q_id and r.id = g.id group by 1)
    select count(*) as questions, avg(coalesce(rank <= 1, false)::int) as top1, avg((rank is not null)::int) as in_ten, round(avg(coalesce(1 / rank, 0)), 6) as mrr from best)"""


@workload(
    _style_sql("literal", _LITERAL, "select id as q_id, id from slices") + " union all " + _style_sql("cell", _CELL, "select q_id, id from gold")
    + " union all " + _style_sql("partial", _PARTIAL, "select id as q_id, id from slices where family <> 'supplier'")
)
def w4_bm25_top1(spark, sf_dir):
    return _by_style(spark, sf_dir)


@workload()
def w4_cosine_top1(spark, sf_dir):
    return _by_style(spark, sf_dir, "cosine_sparse")


@workload()
def w4_dense_top1(spark, sf_dir):
    """The encoder stand-in on all three styles."""
    out = None
    for name, style in STYLES.items():
        held, asked, gold = style(spark, sf_dir)
        t = retrieval.hash_encode(held)
        q = retrieval.hash_encode(asked.withColumnRenamed("q_id", "id")).withColumnRenamed("id", "q_id")
        found = retrieval.candidate_recall(retrieval.dense_rank(q, t, 10), gold, 10)
        one = found.select("questions", "top1", F.col("recall").alias("in_ten"), F.round("mrr", 6).alias("mrr"), F.lit(name).alias("style"))
        out = one if out is None else out.unionByName(one)
    return out


_EXAMPLES = (
    _CELL
    + f""", found as (select distinct r.q_id from ranks r join gold g on g.q_id = r.q_id and g.id = r.id),
kept as (select q_id, id, rank from ranks where q_id in (select q_id from found)),
room as (select q_id, id, rank from ranks where q_id not in (select q_id from found) and rank < 10),
forced as (select g.q_id, g.id, coalesce(max(r.rank), 0) + 1 as rank from gold g left join room r using (q_id) where g.q_id not in (select q_id from found) group by 1, 2),
cands as (select 'filter' as policy, * from kept union all select 'force', * from kept union all select 'force', * from room union all select 'force', * from forced),
some_rows as (select id, string_agg(cells, chr(10) order by nth) as cells from (select *, row_number() over (partition by id order by md5(row_key || '|0'), row_key) as nth from ({_CELL_ROWS})) where nth <= 3 group by 1),
shown as (select c.policy, c.q_id, c.rank, s.title || coalesce(chr(10) || r.cells, '') as x, (g.id is not null)::int as is_gold from cands c join slices s on s.id = c.id left join some_rows r on r.id = c.id left join gold g on g.q_id = c.q_id and g.id = c.id),
prompts as (select policy, q_id, count(*) as n_candidates, max(is_gold) as has_gold, string_agg(x, chr(10) order by rank) || chr(10) || '{selection.INSTRUCTION}' || chr(10) || 'Question: ' || any_value(a.text) as prompt from shown join ask a using (q_id) group by 1, 2)
"""
)


@workload(_EXAMPLES + f"select policy, q_id, n_candidates, has_gold, len({tok('prompt')})::bigint as n_in, md5(prompt) as prompt_md5 from prompts")
def w4_examples(spark, sf_dir):
    held, asked, gold = cell(spark, sf_dir)
    ranks, titles = retrieval.bm25_rank(asked, held), pool(spark, sf_dir).select("id", F.col("title").alias("text"))
    out = None
    for policy in ("filter", "force"):
        made = selection.selection_from_retrieval(asked, selection.with_gold_policy(ranks, gold, policy), titles, cell_rows(spark, sf_dir), gold)
        one = made.select(F.lit(policy).alias("policy"), "q_id", "n_candidates", "has_gold", "n_in", F.md5("prompt").alias("prompt_md5"))
        out = one if out is None else out.unionByName(one)
    return out


@workload(
    _EXAMPLES
    + f"""select policy, count(*) as questions, avg(len({tok("prompt")})) as avg_tokens, max(len({tok("prompt")}))::bigint as max_tokens, quantile_cont(len({tok("prompt")}), 0.5) as p50_tokens,
    quantile_cont(len({tok("prompt")}), 0.95) as p95_tokens, avg(n_candidates) as avg_candidates, avg(has_gold) as avg_gold, count(*) filter (has_gold > 1) as several_gold from prompts group by 1"""
)
def w4_profile(spark, sf_dir):
    return measures.input_profile(w4_examples(spark, sf_dir).withColumnRenamed("has_gold", "n_gold"), ["policy"])


@workload(
    _LITERAL
    + """, tops as (select *, max(score) over (partition by q_id) as top, score - lead(score) over (partition by q_id order by rank) as gap from ranks),
    cut as (select q_id, coalesce(max_by(rank, struct_pack(g := gap, r := -rank)) filter (gap is not null), 1) as cut from tops group by 1)
    select 'fixed' as policy, count(*) as picked, count(distinct q_id) as questions from tops where rank <= 3
    union all select 'threshold', count(*), count(distinct q_id) from tops where score >= 0.5 * top
    union all select 'gap', count(*), count(distinct q_id) from tops join cut using (q_id) where rank <= cut"""
)
def w4_cutoffs(spark, sf_dir):
    held, asked, _ = literal(spark, sf_dir)
    ranks, out = retrieval.bm25_rank(asked, held), None
    for policy in ("fixed", "threshold", "gap"):
        one = retrieval.cutoff_sets(ranks, policy).agg(F.sum(F.size("predicted")).alias("picked"), F.count("*").alias("questions")).withColumn("policy", F.lit(policy))
        out = one if out is None else out.unionByName(one)
    return out


@workload("with " + bm25_sql("select doc_id as id, text from documents", "select item_id as q_id, text from benchmark") + "select q_id, rank, id, score from ranks")
def w4b_bm25(spark, sf_dir):
    docs, items = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")
    return retrieval.bm25_rank(items.select(F.col("item_id").alias("q_id"), "text"), docs.select(F.col("doc_id").alias("id"), "text")).select("q_id", "rank", "id", "score")


_VECS = """with v as (select vec_id as id, embedding::double[] as e from embeddings),
q as (select id as q_id, list_transform(e, lambda x, i: x + (case when i % 7 = id % 7 + 1 then 0.05 else 0 end)) as e from v),
dots as (select q_id, v.id, round(list_sum(list_transform(list_zip(v.e, q.e), lambda p: p[1] * p[2])), 6) as score from v cross join q),
ranks as (select * from (select *, row_number() over (partition by q_id order by score desc, id) as rank from dots) where rank <= 5)
"""


def vectors(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """Questions: each stored vector, slightly moved; the pool: the vectors."""
    t = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    moved = F.transform("embedding", lambda x, i: x.cast("double") + F.when((i + 1) % 7 == F.col("id") % 7 + 1, 0.05).otherwise(0.0))
    return t.select(F.col("id").alias("q_id"), moved.alias("embedding")), t


@workload(_VECS + "select q_id, rank, id, score from ranks")
def w4c_dense(spark, sf_dir):
    return retrieval.dense_rank(*vectors(spark, sf_dir), k=5).select("q_id", "rank", "id", "score")


@workload(_VECS + "select count(*) as questions, avg((id = q_id)::int) as top1 from ranks where rank = 1")
def w4c_dense_top1(spark, sf_dir):
    ranks = retrieval.dense_rank(*vectors(spark, sf_dir), k=1)
    return ranks.agg(F.count("*").alias("questions"), F.avg((F.col("id") == F.col("q_id")).cast("double")).alias("top1"))


def _every_fiftieth(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """Questions: the moved vectors of ids divisible by 50; the pool: all vectors."""
    q, t = vectors(spark, sf_dir)
    return q.filter("q_id % 50 = 0"), t


def _recall_of(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    hits = exact.select("q_id", "id").join(approximate.select("q_id", "id", F.lit(1.0).alias("hit")), ["q_id", "id"], "left")
    return hits.agg(F.count("*").alias("exact"), F.avg(F.coalesce("hit", F.lit(0.0))).alias("recall"))


@workload()
def w4c_ivf_recall(spark, sf_dir):
    q, t = _every_fiftieth(spark, sf_dir)
    return _recall_of(retrieval.ivf_rank(q, t, 1, probes=8), retrieval.dense_rank(q, t, 1))


@workload()
def w4c_lsh_recall(spark, sf_dir):
    q, t = _every_fiftieth(spark, sf_dir)
    return _recall_of(retrieval.lsh_rank(q, t, 1), retrieval.dense_rank(q, t, 1))

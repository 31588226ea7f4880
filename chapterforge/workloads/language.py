"""Curricula, losses and decoding on the given tables; leak audits."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import count_tokens, in_sample
from ..operators import lm
from ..plans import curriculum
from . import alignment as rows_of
from . import knowledge, retrieval, table, workload
from .knowledge import sample_sql, tok

_EXAMPLES = (
    knowledge._SYNTH.rstrip()
    + f""", pairs_x as (select doc_id || '-' || pair_no as example_id, 1 as chapter, 'pairs' as task, len({tok("question")}) as n_in, len({tok("answer")}) as n_out from good),
plain_x as (select doc_id::varchar as example_id, 1 as chapter, 'plain text' as task, 0 as n_in, len({tok("text")}) as n_out from documents),
rows_x as (select table_id || '/' || row_no as example_id, 2 as chapter, 'row to text' as task, len({tok("'name | number ' || name || ' | ' || number")}) as n_in, len({tok("'name ' || name || ', number ' || number")}) as n_out from ({rows_of._ITEMS})),
sel_x as (select id as example_id, 3 as chapter, 'table selection' as task, len({tok("'which table lists ' || title")}) as n_in, len({tok("title")}) as n_out from ({retrieval.POOL})),
every as (select * from pairs_x union all select * from plain_x union all select * from rows_x union all select * from sel_x)
"""
)


def examples(spark, sf_dir) -> DataFrame:
    """All chapters as uniform examples."""
    none, c = F.lit(None).cast("string"), F.col
    pairs = curriculum.uniform(knowledge.synthesized(spark, sf_dir), 1, "pairs", F.concat_ws("-", "doc_id", "pair_no"), none, none, c("question"), c("answer"))
    plain = curriculum.uniform(table(spark, sf_dir, "documents").select("doc_id", "text"), 1, "plain text", c("doc_id"), none, none, none, c("text"))
    items = rows_of.row_items(spark, sf_dir).select(F.concat_ws("/", "table_id", "row_no").alias("x"), c("cells")["name"].alias("name"), c("cells")["number"].alias("number"))
    two = curriculum.uniform(items, 2, "row to text", c("x"), none, F.concat(F.lit("name | number "), "name", F.lit(" | "), "number"), none, F.concat(F.lit("name "), "name", F.lit(", number "), "number"))
    three = curriculum.uniform(retrieval.pool(spark, sf_dir), 3, "table selection", c("id"), none, none, F.concat(F.lit("which table lists "), "title"), c("title"))
    return pairs.unionByName(plain).unionByName(two).unionByName(three)


@workload(
    _EXAMPLES
    + """select coalesce(chapter, 0) as chapter, coalesce(task, 'all') as task, count(*) as examples, sum(n_in + n_out)::bigint as tokens
    from every where task <> 'plain text' group by rollup(chapter, task)"""
)
def w10_overview(spark, sf_dir):
    return curriculum.corpus_overview(examples(spark, sf_dir)).fillna(0, ["chapter"]).fillna("all", ["task"])


def _recipe_parts(recipe: str):
    """What a recipe's first and later parts hold, as conditions; None where it has no such part."""
    first, later = curriculum.RECIPES[recipe]
    ch1 = F.col("task") == ("plain text" if first == "plain" else "pairs") if first else None
    return ch1, F.col("chapter").isin(*later) if later else None


def recipe_plan(every: DataFrame, recipe: str) -> DataFrame | None:
    ch1, rest = (None if part is None else every.filter(part) for part in _recipe_parts(recipe))
    return None if ch1 is None and rest is None else curriculum.curriculum(ch1, rest)


def _recipe_sql(recipe: str) -> str:
    first, later = curriculum.RECIPES[recipe]
    parts = []
    if first:
        parts.append(f"select *, 1 as stage, 1 as epoch from every where task = '{'plain text' if first == 'plain' else 'pairs'}'")
    if later:
        parts.append(f"select every.*, 2 as stage, e as epoch from every, (values (1), (2)) as n(e) where chapter in ({', '.join(map(str, later))})")
        if first:
            parts.append(f"select every.*, 2, e from every, (values (1), (2)) as n(e) where task = '{'plain text' if first == 'plain' else 'pairs'}' and {sample_sql('example_id', 0.1, 17)}")
    return f"select '{recipe}' as recipe, stage, epoch, chapter, count(*) as n, sum(n_in + n_out)::bigint as tokens from ({' union all '.join(parts)}) group by all"


_USED = [r for r in curriculum.RECIPES if r != "base"]


@workload(_EXAMPLES + " union all ".join(map(_recipe_sql, _USED)))
def w9_recipe_sizes(spark, sf_dir):
    every, out = examples(spark, sf_dir), None
    for recipe in _USED:
        one = curriculum.plan_sizes(recipe_plan(every, recipe)).withColumn("recipe", F.lit(recipe))
        out = one if out is None else out.unionByName(one)
    return out


@workload(
    _EXAMPLES
    + f""", plan as (select stage, chapter, example_id, count(*) as k from ({_recipe_sql("ch1_instructed_2_3").split(" from (", 1)[1].rsplit(") group by all", 1)[0]}) group by 1, 2, 3)
    select stage, chapter, min(k) as least, max(k) as most from plan group by 1, 2"""
)
def w9_exposure(spark, sf_dir):
    return curriculum.exposure(recipe_plan(examples(spark, sf_dir), "ch1_instructed_2_3"))


@workload()
def w9_recipe_loss(spark, sf_dir):
    """Loss of held-out pairs (a tenth) under count models of each recipe's examples, over outputs and over all tokens."""
    every = examples(spark, sf_dir).withColumn("text", F.concat_ws(" ", "instruction", "data", "query", "output"))
    held = (F.col("task") == "pairs") & in_sample(F.col("example_id"), 0.1, 31)
    times = {recipe: curriculum.times_seen(*_recipe_parts(recipe)) for recipe in _USED}
    return lm.losses_by_weights(every, times, held).withColumnRenamed("model", "recipe")


def _bigram_sql(source: str) -> str:
    return f"""w as (select id, ['<s>'] || {tok("text")} as w from ({source})), pairs as (select id, w[i] as ctx, w[i + 1] as tok, i as pos from (select id, w, unnest(range(1, len(w))) as i from w)),
counts as (select ctx, tok, count(*) as n from pairs group by 1, 2), contexts as (select ctx, sum(n)::bigint as total from counts group by 1)"""


@workload(
    "with " + _bigram_sql("select conv_id * 1000 + turn as id, text from conversations")
    + ", v as (select count(distinct tok) as v from counts) select id, count(*) as n, round(sum(-ln((n + 0.1) / (total + 0.1 * v))), 4) as nll from pairs join counts using (ctx, tok) join contexts using (ctx) cross join v group by 1"
)
def w13_sequence_nll(spark, sf_dir):
    texts = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    return lm.sequence_nll(texts, lm.fit_bigrams(texts))


_HELD = sample_sql("conv_id", 0.2, 41)


@workload(
    f"""with w as (select conv_id * 1000 + turn as id, {_HELD} as held_out, ['<s>', '<s>'] || {tok("text")} as w from conversations),
    grams as (select id, held_out, w[i + 2] as tok, w[i + 1] as c1, w[i] || ' ' || w[i + 1] as c2 from (select *, unnest(range(1, len(w) - 1)) as i from w)),
    seen as (select * from grams where not held_out), size as (select count(distinct tok) as v, count(*) as n from seen),
    n0 as (select tok, count(*) as n from seen group by 1), n1 as (select c1, tok, count(*) as n from seen group by 1, 2), n2 as (select c2, tok, count(*) as n from seen group by 1, 2),
    t1 as (select c1, count(*) as n from seen group by 1), t2 as (select c2, count(*) as n from seen group by 1),
    p as (select g.id, g.held_out, case when t2.n is not null then 2 when t1.n is not null then 1 else 0 end as context,
      case when t2.n is not null then (coalesce(n2.n, 0) + 0.1::double) / (t2.n + 0.1::double * v) when t1.n is not null then (coalesce(n1.n, 0) + 0.1::double) / (t1.n + 0.1::double * v)
      else (coalesce(n0.n, 0) + 0.1::double) / (size.n + 0.1::double * v) end as p
      from grams g cross join size left join n0 on n0.tok = g.tok left join n1 on n1.c1 = g.c1 and n1.tok = g.tok left join n2 on n2.c2 = g.c2 and n2.tok = g.tok left join t1 on t1.c1 = g.c1 left join t2 on t2.c2 = g.c2)
    select id, held_out, count(*) as n, count(*) filter (context < 2) as backed_off, round(round(sum(-ln(p)), 8), 3) as nll from p group by 1, 2"""
)
def w13_backoff_nll(spark, sf_dir):
    """Every turn under a model of order three with back-off, learnt from four fifths of the conversations."""
    turns = table(spark, sf_dir, "conversations")
    texts = turns.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text", in_sample(F.col("conv_id"), 0.2, 41).alias("held_out"))
    losses = lm.BackoffModel(texts.filter(~F.col("held_out")), 3).token_losses(texts)
    sums = losses.groupBy("id").agg(F.count("*").alias("n"), F.count_if(F.col("context") < 2).alias("backed_off"), F.round(F.round(F.sum("nll"), 8), 3).alias("nll"))
    return sums.join(texts.select("id", "held_out"), "id")


_NEXT = "with " + _bigram_sql("select conv_id * 1000 + turn as id, text from conversations") + ", nxt as (select ctx, tok as token, n / total as p from counts join contexts using (ctx))"


def next_tokens(spark, sf_dir) -> DataFrame:
    texts = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    model = lm.fit_bigrams(texts)
    return model.counts.join(model.contexts, "ctx").select("ctx", F.col("tok").alias("token"), (F.col("n") / F.col("total")).alias("p"))


# the tried settings, and the top_p of 1 that one family has
TEMPERATURES, TOP_PS = (0.0, 0.7, 1.0), (0.95, 0.99, 1.0)


def _hot_sql(t: float) -> str:
    p = f"pow(p, 1.0 / {t})" if t else "(row_number() over (partition by ctx order by p desc, token) = 1)::int::double"
    return f"select {t}::double as temperature, ctx, token, {p} as p from nxt"


@workload(
    _NEXT
    + f""", hot as ({" union all ".join(map(_hot_sql, TEMPERATURES))}), one as (select temperature, ctx, token, p / sum(p) over (partition by temperature, ctx) as p from hot),
    cut as (select *, coalesce(sum(p) over (partition by temperature, ctx order by p desc, token rows between unbounded preceding and 1 preceding), 0) as before from one),
    kept as (select temperature, top_p, ctx, p from cut cross join (values {", ".join(f"({x}::double)" for x in TOP_PS)}) as s(top_p) where p > 0 and (top_p = 1 or round(before, 9) < top_p))
    select temperature, top_p, ctx, count(*) as kept, round(round(max(p) / sum(p), 12), 6) as top from kept group by 1, 2, 3"""
)
def w13_nucleus(spark, sf_dir):
    """Every context under each setting: how many tokens stay, and the share of the most likely."""
    cut = lm.nucleus_grid(next_tokens(spark, sf_dir), TEMPERATURES, TOP_PS)
    return cut.select("temperature", "top_p", "ctx", "kept", F.round(F.round("top", 12), 6).alias("top"))


@workload(_NEXT + "select ctx, arg_max(token, struct_pack(p := p, n := 0)) filter (r = 1) as token from (select *, row_number() over (partition by ctx order by p desc, token) as r from nxt) group by 1")
def w13_greedy(spark, sf_dir):
    return lm.temper(next_tokens(spark, sf_dir), 0.0).filter("p = 1").select("ctx", "token")


#: tokens of a training step, for the schedule over the conversations
STEP_TOKENS = 512


@workload(
    f"""with t as (select greatest(ceil(coalesce(sum(len({tok("text")})), 0) / {STEP_TOKENS})::bigint, 1) as n from conversations), s as (select n, unnest(range(n + 1)) as step from t)
    select step, round(1e6 * 1e-6 * (1 + cos(pi() * step / n)) / 2, 9) as lr_millionths from s"""
)
def w13_lr(spark, sf_dir):
    """The learning rate of each step of one pass over all turns; the number of steps is what their tokens need."""
    tokens = table(spark, sf_dir, "conversations").agg(F.coalesce(F.sum(count_tokens(F.col("text"))), F.lit(0))).first()[0]
    steps = max(1, -(-tokens // STEP_TOKENS))
    return curriculum.cosine_lr(curriculum.steps_frame(spark, steps), steps).select("step", F.round(F.col("lr") * 1e6, 9).alias("lr_millionths"))


_GRAM = lambda t, key: f"select distinct {key}, unnest(list_transform(range(1, len(w) - 11), lambda i: array_to_string(w[i:i+12], ' '))) as gram from (select {key}, {tok('text')} as w from {t}) where len(w) >= 13"


@workload(
    "select item_id, doc_id, 'contains' as mode from benchmark b join documents d on contains(d.text, b.text) where length(b.text) > 0 union all "
    f"select distinct item_id, doc_id, 'ngram' from ({_GRAM('benchmark', 'item_id')}) join ({_GRAM('documents', 'doc_id')}) using (gram)"
)
def w14_leaks(spark, sf_dir):
    docs, items, out = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), None
    for mode in ("contains", "ngram"):
        one = curriculum.leak_audit(docs, items, mode).withColumn("mode", F.lit(mode))
        out = one if out is None else out.unionByName(one)
    return out

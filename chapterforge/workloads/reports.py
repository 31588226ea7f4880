"""Reports over published figures: leaderboard, improvements, winners, exposure, ablation, corpus."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import measures
from ..plans import published
from . import language, workload

_FAMILIES = f"""
with s as {published.SCORES_SQL},
fam as (select model, family, case when count(*) = count(score) then avg(score) end as score from s group by 1, 2),
wide as (select model, max(score) filter (family = 'mcq') as mcq, max(score) filter (family = 'ts') as ts, max(score) filter (family = 't2s') as t2s from fam group by 1),
board as (select *, (mcq + ts + t2s) / 3 as overall from wide)
"""


@workload(_FAMILIES + "select model, round(mcq, 6) as mcq, round(ts, 6) as ts, round(t2s, 6) as t2s, round(overall, 6) as overall from board")
def w8_leaderboard(spark, sf_dir):
    return measures.leaderboard(published.scores(spark)).select("model", *[F.round(c, 6).alias(c) for c in ("mcq", "ts", "t2s", "overall")])


@workload(
    f"with s as {published.SCORES_SQL} select model, round(case when count(*) = count(score) then avg(score) end, 6) as overall from s group by model"
)
def w8_leaderboard_mean_of_sets(spark, sf_dir):
    return measures.leaderboard(published.scores(spark), "mean_of_sets").select("model", F.round("overall", 6).alias("overall"))


@workload(
    _FAMILIES
    + """, long as (select model, dataset as item, score from s union all select model, 'mcq avg', mcq from board union all select model, 'ts avg', ts from board
      union all select model, 't2s avg', t2s from board union all select model, 'overall', overall from board)
    select r.item, r.model as reference, round((p.score / r.score - 1) * 100, 6) as relative_gain, round(p.score - r.score, 6) as points
    from long r join long p on r.item = p.item and p.model = 'post12b' where r.model in ('base12b', 'closed_flagship')"""
)
def w8_improvement(spark, sf_dir):
    s, refs = published.scores(spark), ["base12b", "closed_flagship"]
    a = measures.improvement(s, "post12b", refs).withColumnRenamed("gain", "relative_gain")
    b = measures.improvement(s, "post12b", refs, "points").withColumnRenamed("gain", "points")
    return a.join(b, ["item", "reference"]).select("item", "reference", F.round("relative_gain", 6).alias("relative_gain"), F.round("points", 6).alias("points"))


@workload(
    f"with s as {published.SCORES_SQL} select dataset, model, score, rank() over (partition by dataset order by score desc) as place from s where score is not null"
)
def w8_winners(spark, sf_dir):
    return measures.winners(published.scores(spark))


@workload(
    f"with s as {published.SCORES_SQL} select model, exposure, round(case when count(*) = count(score) then avg(score) end, 6) as score, count(*) as sets from s group by 1, 2"
)
def w8_exposure(spark, sf_dir):
    return measures.by_exposure(published.scores(spark)).withColumn("score", F.round("score", 6))


@workload(
    f"""with s as {published.ABLATION_SQL}, c as (select * from {published.values_sql(list(measures.CONTRASTS), "contrast, a, b")})
    select contrast, x.dataset, round(x.score - y.score, 6) as points from c join s x on x.recipe = c.a join s y on y.recipe = c.b and y.dataset = x.dataset"""
)
def w9_contrasts(spark, sf_dir):
    return measures.ablation_contrasts(published.ablation(spark)).withColumn("points", F.round("points", 6))


@workload(
    language._EXAMPLES
    + f""", s as (select chapter, task, examples, tokens, 0 as made, 0 as made_tokens from {published.CORPUS_SQL} where in_total
      union all select chapter, task, 0, 0, 1, n_in + n_out from every where task <> 'plain text')
    select coalesce(chapter, 0) as chapter, coalesce(task, 'all') as task, sum(examples) as examples, sum(tokens) as tokens, sum(made)::bigint as made, sum(made_tokens)::bigint as made_tokens,
    grouping(chapter, task)::bigint as level from s group by rollup(chapter, task)"""
)
def w10_published_corpus(spark, sf_dir):
    """The published corpus beside the one made of the given tables, by chapter and task with subtotals."""
    none = F.lit(0.0)
    told = published.corpus(spark).filter("in_total").select("chapter", "task", "examples", "tokens", F.lit(0).alias("made"), F.lit(0).alias("made_tokens"))
    made = language.examples(spark, sf_dir).filter("task <> 'plain text'").select("chapter", "task", none.alias("examples"), none.alias("tokens"), F.lit(1).alias("made"), (F.col("n_in") + F.col("n_out")).alias("made_tokens"))
    sums = [F.sum(c).alias(c) for c in ("examples", "tokens", "made", "made_tokens")]
    return told.unionByName(made).rollup("chapter", "task").agg(*sums, F.grouping_id().alias("level")).fillna(0, ["chapter"]).fillna("all", ["task"])

"""Chapter 1 on the given tables: ratings, classifier, filter, retention, routes, pairs, rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import count_tokens, in_sample
from ..operators import filtering, qa
from . import table, workload

TOK = r"regexp_extract_all(lower(coalesce({0}, '')), '[\p{{L}}\p{{N}}]+')"


def tok(column: str) -> str:
    return TOK.format(column)


def sample_sql(key: str, share: float, seed: int) -> str:
    return f"substr(md5({key}::varchar || '|{seed}'), 1, 4) < '{round(share * 65536):04x}'"


@workload(f"select doc_id, lang from documents where {sample_sql('doc_id', 0.05, 7)}")
def w2_sample(spark, sf_dir):
    return filtering.rating_sample(table(spark, sf_dir, "documents"), 0.05).select("doc_id", "lang")


_RUBRIC = rf"""1 + (len({tok("text")}) between 50 and 4096)::int + (lang = 'en')::int + (not regexp_matches(text, '(!!|\*\*\*|###)'))::int
  + (len(list_distinct(string_split(text, chr(10)))) >= 0.8 * len(string_split(text, chr(10))))::int"""


@workload(
    f"select doc_id, {_RUBRIC} as score, 'rubric' as rater from documents union all "
    "select doc_id, case when quality = 1 and toxic = 0 then 5 when quality = 1 then 3 when toxic = 0 then 2 else 1 end, 'labels' from labels"
)
def w2_ratings(spark, sf_dir):
    by_rubric = filtering.rate_documents(table(spark, sf_dir, "documents")).select("doc_id", "score", "rater")
    return by_rubric.unionByName(filtering.ratings_from_labels(table(spark, sf_dir, "labels")).withColumn("rater", F.lit("labels")))


def rated(spark, sf_dir) -> DataFrame:
    scores = filtering.split_ratings(filtering.ratings_from_labels(table(spark, sf_dir, "labels")))
    return table(spark, sf_dir, "documents").select("doc_id", "text").join(scores, "doc_id")


def _bayes_sql(score: str, classes: list[int]) -> str:
    """Naive Bayes, trained on the train split, over all documents: ends with best(doc_id, predicted, margin)."""
    n = len(classes)
    return f"""
with scores as (select doc_id, case when quality = 1 and toxic = 0 then 5 when quality = 1 then 3 when toxic = 0 then 2 else 1 end as rating from labels),
split as (select doc_id, rating, {score} as score, not ({sample_sql("doc_id", 0.2, 11)}) as train from scores),
words as (select doc_id, {tok("text")} as w from documents),
trained as (select s.score, w.w from words w join split s using (doc_id) where s.train),
classes(c) as (values {", ".join(f"({c})" for c in classes)}),
sizes as (select c, count(t.score) as n, coalesce(sum(len(t.w)), 0) as toks from classes left join trained t on t.score = c group by c),
bag as (select score, unnest(w) as term from trained),
vocab as (select count(distinct term) as v from bag),
counts as (select term, score as c, count(*) as n from bag group by 1, 2),
terms as (select distinct term from bag),
tf as (select doc_id, term, count(*) as tf from (select doc_id, unnest(w) as term from words) group by 1, 2),
parts as (select tf.doc_id, sizes.c, sum(tf.tf * ln((coalesce(counts.n, 0) + 1) / (sizes.toks + v)::double)) as s
  from tf join terms using (term) cross join sizes cross join vocab left join counts on counts.term = tf.term and counts.c = sizes.c group by 1, 2),
logp as (select d.doc_id, sizes.c, round(coalesce(p.s, 0) + ln((sizes.n + 1) / ((select sum(n) from sizes) + {n})::double), 6) as s
  from documents d cross join sizes left join parts p on p.doc_id = d.doc_id and p.c = sizes.c),
placed as (select *, row_number() over (partition by doc_id order by s desc, c) as r from logp),
best as (select doc_id, max(c) filter (r = 1) as predicted, round(max(s) filter (r = 1) - max(s) filter (r = 2), 6) as margin from placed group by 1)
"""


_FIVE = _bayes_sql("rating", [1, 2, 3, 4, 5])


def _predicted(spark, sf_dir, binarize_at: int | None = None) -> DataFrame:
    model = filtering.train_bayes(rated(spark, sf_dir).filter("split = 'train'"), binarize_at=binarize_at)
    return filtering.bayes_scores(table(spark, sf_dir, "documents").select("doc_id", "text"), model)


@workload(_FIVE + "select doc_id, predicted, round(margin, 3) as margin from best")
def w2_filter(spark, sf_dir):
    return _predicted(spark, sf_dir).withColumn("margin", F.round("margin", 3))


@workload(_bayes_sql("(rating >= 4)::int", [0, 1]) + "select doc_id, predicted from best")
def w2_filter_binary(spark, sf_dir):
    return _predicted(spark, sf_dir, binarize_at=4).select("doc_id", "predicted")


@workload(
    _FIVE
    + """, test as (select b.predicted, s.rating as score from best b join split s using (doc_id) where not s.train)
    select 'n' as metric, count(*)::double as value from test union all select 'accuracy', avg((predicted = score)::int) from test
    union all select 'recall_high', avg((predicted >= 4)::int) from test where score >= 4"""
)
def w2_classifier_report(spark, sf_dir):
    held = filtering.split_ratings(filtering.ratings_from_labels(table(spark, sf_dir, "labels"))).filter("split = 'test'")
    return filtering.classifier_report(_predicted(spark, sf_dir).join(held, "doc_id"))


@workload(_FIVE + "select s.rating as score, b.predicted, count(*) as n from best b join split s using (doc_id) where not s.train group by 1, 2")
def w2_confusion(spark, sf_dir):
    held = filtering.split_ratings(filtering.ratings_from_labels(table(spark, sf_dir, "labels"))).filter("split = 'test'")
    return filtering.confusion(_predicted(spark, sf_dir).join(held, "doc_id"))


@workload(
    _FIVE
    + f"""select count(*) as docs_before, count(*) filter (predicted >= 4) as docs_after, sum(len({tok("text")}))::bigint as tokens_before,
    (sum(len({tok("text")})) filter (predicted >= 4))::bigint as tokens_after, count(*) filter (predicted >= 4) / count(*) as docs_share,
    sum(len({tok("text")})) filter (predicted >= 4) / sum(len({tok("text")})) as tokens_share from documents join best using (doc_id)"""
)
def w2_retention(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return filtering.retention(docs.join(_predicted(spark, sf_dir), "doc_id").withColumn("kept", F.col("predicted") >= 4))


# ---- pairs ------------------------------------------------------------------------------------------------

_MARKED = """
with turns as (select *, lead(role) over (partition by conv_id order by turn) as next_role, lead(text) over (partition by conv_id order by turn) as next_text from conversations),
native as (select conv_id, turn, text, next_text from turns where role = 'user' and next_role = 'assistant'),
marked as (select conv_id as doc_id, string_agg('Question: ' || text || chr(10) || 'Answer: ' || next_text, chr(10) order by turn) as text from native group by 1)
"""


def marker_documents(spark, sf_dir) -> DataFrame:
    return qa.render_conversations(table(spark, sf_dir, "conversations"))


@workload(
    _MARKED
    + """, every as (select text from documents union all select text from marked)
    select case when regexp_matches(text, '[Qq]uestion:') and regexp_matches(text, '[Aa]nswer:') then 'extract' else 'synthesize' end as route, count(*) as docs from every group by 1"""
)
def w2_route(spark, sf_dir):
    every = table(spark, sf_dir, "documents").select("doc_id", "text").unionByName(marker_documents(spark, sf_dir))
    return qa.route_documents(qa.flag_markers(every)).groupBy("route").agg(F.count("*").alias("docs"))


@workload(_MARKED + "select conv_id as doc_id, row_number() over (partition by conv_id order by turn)::int as pair_no, trim(text, ' ' || chr(10) || chr(13) || chr(9)) as question, trim(next_text, ' ' || chr(10) || chr(13) || chr(9)) as answer from native")
def w2_extract(spark, sf_dir):
    return qa.extract_pairs(marker_documents(spark, sf_dir))


def _synth_sql(source: str) -> str:
    """Common table expressions, without ``with``, up to ``good``: pairs of all documents of ``source``."""
    return rf"""sents as (select doc_id, text, list_filter(list_filter(list_transform(string_split(coalesce(text, ''), '. '), lambda s: trim(s)), lambda s: s <> ''), lambda s: len({tok("s")}) >= 5) as s from {source}),
drafts as (select doc_id, text, s[i + 1] as here, s[i + 2] as following, i::int as pair_no from (select *, unnest(range(0, len(s))) as i from sents)),
worded as (select *, regexp_extract_all(here, '[\p{{L}}\p{{N}}]+') as w from drafts),
gapped as (select *, w[list_position(list_transform(w, lambda x: length(x)), list_max(list_transform(w, lambda x: length(x))))] as longest from worded),
pairs as (select doc_id, text, pair_no, case pair_no % 2 when 0 then 'gap' else 'next sentence' end as form, case pair_no % 2 when 0 then 1 else 3 end as difficulty, pair_no % 2 = 1 as needs_context,
  case pair_no % 2 when 0 then 'Which word is left out: ' || replace(here, longest, '____') else 'What follows this: ' || here end as question,
  case pair_no % 2 when 0 then longest else following end as answer from gapped),
good as (select * from pairs where answer is not null and answer <> '')
"""


_SYNTH = "with " + _synth_sql("documents")


def synthesized(spark, sf_dir) -> DataFrame:
    return qa.synthesize_pairs(table(spark, sf_dir, "documents").select("doc_id", "text"))


@workload(_SYNTH + "select doc_id, pair_no, form, difficulty, needs_context, md5(question) as question_md5, answer from good")
def w2_synth(spark, sf_dir):
    return synthesized(spark, sf_dir).select("doc_id", "pair_no", "form", "difficulty", "needs_context", F.md5("question").alias("question_md5"), "answer")


@workload(
    _SYNTH
    + f"""select form, count(*) as pairs, avg(contains(text, answer)::int) as span,
    round(avg(len(list_intersect(list_distinct({tok("answer")}), {tok("text")})) / greatest(len(list_distinct({tok("answer")})), 1)), 6) as token_share from good group by 1"""
)
def w2_grounding(spark, sf_dir):
    docs, pairs = table(spark, sf_dir, "documents").select("doc_id", "text"), synthesized(spark, sf_dir)
    both = qa.grounding(qa.grounding(pairs, docs).withColumnRenamed("grounded", "span"), docs, "token_share")
    return both.groupBy("form").agg(F.count("*").alias("pairs"), F.avg("span").alias("span"), F.round(F.avg("grounded"), 6).alias("token_share"))


@workload(
    _SYNTH
    + f"""select form, count(*) as pairs, count(distinct array_to_string(list_slice({tok("question")}, 1, 6), ' ')) as openings, count(distinct question) / count(*) as distinct_share,
    round(avg(len({tok("question")})), 6) as question_words, round(avg(len({tok("answer")})), 6) as answer_words from good group by 1"""
)
def w2_diversity(spark, sf_dir):
    return qa.pair_diversity(synthesized(spark, sf_dir))


_ASSESS = (
    _SYNTH
    + rf""", judged as (select *, 1 + (len({tok("question")}) >= 5)::int + (length(trim(answer)) > 0)::int + (not needs_context or len({tok("question")}) >= 12)::int
    + (not regexp_matches(question, '(!!|\*\*\*|###)'))::int >= 4 as a, contains(text, answer) as b, len({tok("question || ' ' || answer")}) as n from good),
sums as (select count(*) as k0, count(*) filter (a) as k1, count(*) filter (a and b) as k2, sum(n)::bigint as t0, coalesce(sum(n) filter (a), 0)::bigint as t1, coalesce(sum(n) filter (a and b), 0)::bigint as t2 from judged)
"""
)


@workload(
    _ASSESS
    + """select 'drafts' as round, k0 as kept, t0 as tokens, 1.0::double as share from sums union all select 'complete', k1, t1, k1 / k0 from sums
    union all select 'accurate', k2, t2, k2 / k1 from sums"""
)
def w2_assess(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return qa.assess(qa.grounding(synthesized(spark, sf_dir), docs))[1]


_JUDGED = rf"""1 + (len({tok("question")}) >= 5)::int + (length(trim(answer)) > 0)::int + (not needs_context or len({tok("question")}) >= 12)::int
    + (not regexp_matches(question, '(!!|\*\*\*|###)'))::int >= 4"""


@workload(
    _FIVE
    + ", " + _MARKED.strip().removeprefix("with ") + """, every as (select -1 - doc_id as doc_id, text from marked union all select d.doc_id, d.text from documents d join best b on b.doc_id = d.doc_id where b.predicted >= 4),
    routed as (select *, regexp_matches(text, '[Qq]uestion:') and regexp_matches(text, '[Aa]nswer:') as marks from every), plain as (select * from routed where not coalesce(marks, false)),
    """ + _synth_sql("plain")
    + f""", chunks as (select doc_id, text, unnest(regexp_split_to_array(text, '[Qq]uestion:')) as x, unnest(range(0, len(regexp_split_to_array(text, '[Qq]uestion:')))) as pair_no from routed where marks),
    cut as (select *, regexp_replace(x, '[Aa]nswer:(.|\n)*$', '') as q, regexp_extract(x, '^((.|\n)*?)[Aa]nswer:((.|\n)*)$', 3) as a from chunks where pair_no > 0 and regexp_matches(x, '[Aa]nswer:')),
    found as (select doc_id, text, 'extract' as route, pair_no::int as pair_no, 'native' as form, false as needs_context, trim(regexp_extract(x, '^((.|\n)*?)[Aa]nswer:', 1), ' ' || chr(10) || chr(13) || chr(9)) as question,
      trim(a, ' ' || chr(10) || chr(13) || chr(9)) as answer from cut),
    both_kinds as (select * from found where question <> '' and answer <> '' union all select doc_id, text, 'synthesize', pair_no, form, needs_context, question, answer from good)
    select doc_id, route, pair_no, form, md5(question) as question_md5, md5(answer) as answer_md5 from both_kinds where {_JUDGED} and contains(text, answer)"""
)
def w2_chapter(spark, sf_dir):
    """The whole pass: documents that the five-class filter keeps, and marker documents (under negative ids), to judged pairs."""
    kept = _predicted(spark, sf_dir).filter("predicted >= 4").select("doc_id")
    marked = marker_documents(spark, sf_dir).select((F.lit(-1) - F.col("doc_id")).alias("doc_id"), "text")
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").join(kept, "doc_id", "left_semi").unionByName(marked)
    pairs, _ = qa.build_knowledge(docs)
    return pairs.select("doc_id", "route", "pair_no", "form", F.md5("question").alias("question_md5"), F.md5("answer").alias("answer_md5"))


@workload(
    _MARKED
    + f""", ids as (select conv_id || '-' || row_number() over (partition by conv_id order by turn) as pair_id from native),
    picked as (select pair_id from ids order by md5(pair_id || '|5'), pair_id limit 300),
    votes as (select pair_id, not ({sample_sql("pair_id", 0.03, 101)}) as v1, not ({sample_sql("pair_id", 0.03, 102)}) as v2 from picked),
    pairwise as (select (v1 and v2)::int as lo, (v1 or v2)::int as hi, (v1::int + v2::int) / 2 as share from votes),
    sums as (select count(*) as n, avg(lo) as valid_share, avg((lo = hi)::int) as agreement, avg(share) as p from pairwise)
    select n, valid_share, agreement, round(case when p * p + (1 - p) * (1 - p) < 1 then (agreement - (p * p + (1 - p) * (1 - p))) / (1 - (p * p + (1 - p) * (1 - p))) else 1.0 end, 6) as kappa from sums"""
)
def w2_pilot(spark, sf_dir):
    pairs = qa.extract_pairs(marker_documents(spark, sf_dir)).select(F.concat_ws("-", "doc_id", "pair_no").alias("pair_id"))
    votes = pairs.select("pair_id", F.explode(F.array(F.lit(1), F.lit(2))).alias("reviewer"))
    wrong = F.when(F.col("reviewer") == 1, in_sample(F.col("pair_id"), 0.03, 101)).otherwise(in_sample(F.col("pair_id"), 0.03, 102))
    return qa.pilot_validity(pairs, votes.withColumn("valid", ~wrong))


@workload(
    f"select count(*) as docs, sum(len({tok('text')}))::bigint as words, sum(ceil(length(text) / 4))::bigint as chars, sum(len(regexp_extract_all(text, '\\S+')))::bigint as space from documents"
)
def w2_token_counts(spark, sf_dir):
    t = F.col("text")
    return table(spark, sf_dir, "documents").agg(F.count("*").alias("docs"), *[F.sum(count_tokens(t, m)).alias(m) for m in ("words", "chars", "space")])


@workload(
    f"""with w as (select doc_id, {tok("text")} as w from documents)
    select doc_id, 'truncate' as policy, 0 as part, len(list_slice(w, 1, 512))::int as n, md5(array_to_string(list_slice(w, 1, 512), ' ')) as h from w
    union all select doc_id, 'head_tail', 0, least(len(w), 512)::int, md5(array_to_string(case when len(w) <= 512 then w else list_slice(w, 1, 256) || list_slice(w, len(w) - 255, len(w)) end, ' ')) from w
    union all select doc_id, 'chunks', k::int, len(list_slice(w, k * 512 + 1, k * 512 + 512))::int, md5(array_to_string(list_slice(w, k * 512 + 1, k * 512 + 512), ' '))
      from (select doc_id, w, unnest(range(0, greatest(ceil(len(w) / 512)::int, 1))) as k from w)"""
)
def w2_contexts(spark, sf_dir):
    docs, out = table(spark, sf_dir, "documents").select("doc_id", "text"), None
    for policy in ("truncate", "head_tail", "chunks"):
        one = filtering.encode_context(docs, 512, policy).select("doc_id", F.lit(policy).alias("policy"), "part", F.size("tokens").alias("n"), F.md5(F.array_join("tokens", " ")).alias("h"))
        out = one if out is None else out.unionByName(one)
    return out

"""Question-answer pairs: found by markers or made from sentences, held against their source, judged in rounds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import count_tokens, order_hash, tokens
from ..session import settled

QUESTION, ANSWER = "[Qq]uestion:", "[Aa]nswer:"


def flag_markers(docs: DataFrame, any_case: bool = False, question: str = QUESTION, answer: str = ANSWER) -> DataFrame:
    """has_question, has_answer and markers (both, question, answer, none). Other patterns serve other languages."""
    case = "(?i)" if any_case else ""
    q, a = F.coalesce(F.col("text").rlike(case + question), F.lit(False)), F.coalesce(F.col("text").rlike(case + answer), F.lit(False))
    kind = F.when(q & a, "both").when(q, "question").when(a, "answer").otherwise("none")
    return docs.withColumns({"has_question": q, "has_answer": a, "markers": kind})


def route_documents(flagged: DataFrame) -> DataFrame:
    """Both markers: pairs are extracted; otherwise they are synthesized. One column, so the input is read once."""
    return flagged.withColumn("route", F.when(F.col("markers") == "both", "extract").otherwise("synthesize"))


def extract_pairs(docs: DataFrame) -> DataFrame:
    """doc_id, pair_no, question, answer: each question marker starts a pair, its answer ends before the next."""
    parts = docs.select("doc_id", F.posexplode(F.split("text", QUESTION)).alias("pair_no", "part")).filter("pair_no > 0")
    cut = F.split(F.col("part"), ANSWER, 2)
    found = parts.filter(F.size(cut) == 2).select("doc_id", "pair_no", F.trim(cut[0], F.lit(" \n\r\t")).alias("question"), F.trim(cut[1], F.lit(" \n\r\t")).alias("answer"))
    return found.filter("question <> '' and answer <> ''")


def render_conversations(turns: DataFrame) -> DataFrame:
    """One marker document for each conversation: every user turn that an assistant turn follows at once, as a pair."""
    from pyspark.sql import Window as W

    order = W.partitionBy("conv_id").orderBy("turn")
    pairs = turns.withColumns({"next_role": F.lead("role").over(order), "next_text": F.lead("text").over(order)}).filter("role = 'user' and next_role = 'assistant'")
    lines = F.concat(F.lit("Question: "), F.col("text"), F.lit("\nAnswer: "), F.col("next_text"))
    return pairs.groupBy(F.col("conv_id").alias("doc_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", lines.alias("x")))), lambda s: s["x"]), "\n").alias("text"))


def sentences(text: Column) -> Column:
    """What ends in a full stop and a space; trimmed, blank ones left out."""
    return F.filter(F.transform(F.split(F.coalesce(text, F.lit("")), r"\. "), lambda s: F.trim(s)), lambda s: s != "")


def synthesize_pairs(docs: DataFrame, per_doc: int | None = None) -> DataFrame:
    """doc_id, pair_no, form, difficulty, needs_context, question, answer from a document's sentences of five words or more: from
    all of them, or the first ``per_doc``.

    Even pairs are simple: the longest word of a sentence is gapped (first of equals), and the sentence is in the question. Odd
    ones are harder: which sentence follows a given one; they carry the sentence before it as their context.
    """
    long = F.filter(F.col("s"), lambda s: F.size(tokens(s)) >= 5)
    own = docs.select("doc_id", sentences(F.col("text")).alias("s")).select("doc_id", long.alias("s"))
    two = F.transform("s", lambda x, i: F.struct(x.alias("here"), F.get("s", i + 1).alias("following")))
    picked = own.select("doc_id", F.posexplode(two if per_doc is None else F.slice(two, 1, per_doc)).alias("pair_no", "x")).select("doc_id", "pair_no", "x.*")
    here, following = F.col("here"), F.col("following")
    words = F.regexp_extract_all(here, F.lit(r"[\p{L}\p{N}]+"), F.lit(0))
    longest = F.array_sort(F.transform(words, lambda w, i: F.struct((-F.length(w)).alias("n"), i.alias("i"), w.alias("w"))))[0]["w"]
    cloze = F.col("pair_no") % 2 == 0
    question = F.when(cloze, F.concat(F.lit("Which word is left out: "), F.replace(here, longest, F.lit("____")))).otherwise(F.concat(F.lit("What follows this: "), here))
    out = picked.select(
        "doc_id", "pair_no", F.when(cloze, "gap").otherwise("next sentence").alias("form"), F.when(cloze, 1).otherwise(3).alias("difficulty"),
        (~cloze).alias("needs_context"), question.alias("question"), F.when(cloze, longest).otherwise(following).alias("answer"),
    )
    return out.filter("answer is not null and answer <> ''")


def build_knowledge(docs: DataFrame, kept_ids: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """The whole pass from documents to pairs: the filter's ids, routes, extraction or synthesis, both judging rounds, distillation.

    docs: doc_id, text; kept_ids: doc_id (all documents without it). Returns (pairs: those of ``distill`` with route and form; report
    of ``assess``). Each document is of one route, so its pairs are of one kind; nothing is read twice but for the answer's support.
    """
    kept = docs if kept_ids is None else docs.join(kept_ids, "doc_id", "left_semi")
    routed = route_documents(flag_markers(kept.select("doc_id", "text")))
    native = extract_pairs(routed.filter("route = 'extract'")).select(
        "doc_id", F.lit("extract").alias("route"), "pair_no", F.lit("native").alias("form"), F.lit(1).alias("difficulty"), F.lit(False).alias("needs_context"), "question", "answer"
    )
    made = synthesize_pairs(routed.filter("route = 'synthesize'")).withColumn("route", F.lit("synthesize")).select(*native.columns)
    pairs, report = assess(grounding(native.unionByName(made), kept))
    return distill(pairs, "route", "form"), report


def grounding(pairs: DataFrame, docs: DataFrame, mode: str = "span") -> DataFrame:
    """pairs with ``grounded``: the answer stands in the document (1 or 0), or the share of its words that do."""
    both = pairs.join(docs.select("doc_id", "text"), "doc_id")
    if mode == "span":
        value = F.contains("text", "answer").cast("double")
    else:
        said = F.array_distinct(tokens(F.col("answer")))
        value = F.size(F.array_intersect(said, tokens(F.col("text")))) / F.greatest(F.size(said), F.lit(1))
    return both.withColumn("grounded", value).drop("text")


def pair_diversity(pairs: DataFrame) -> DataFrame:
    """By form: pairs, distinct first two words of questions, distinct questions' share, mean words of question and answer."""
    first = F.array_join(F.slice(tokens(F.col("question")), 1, 6), " ")
    return pairs.groupBy("form").agg(
        F.count("*").alias("pairs"), F.count_distinct(first).alias("openings"), (F.count_distinct("question") / F.count("*")).alias("distinct_share"),
        F.round(F.avg(count_tokens(F.col("question"))), 6).alias("question_words"), F.round(F.avg(count_tokens(F.col("answer"))), 6).alias("answer_words"),
    )


def judge_complete(pairs: DataFrame, pass_at: int = 4) -> DataFrame:
    """Round one, 1 to 5: a question of five words or more, an answer, context where it is needed, no junk marks."""
    n = count_tokens(F.col("question"))
    tests = [n >= 5, F.length(F.trim("answer")) > 0, ~F.col("needs_context") | (n >= 12), ~F.col("question").rlike(r"(!!|\*\*\*|###)")]
    score = sum((F.coalesce(t, F.lit(False)).cast("int") for t in tests), F.lit(1))
    return pairs.withColumn("complete_score", score).withColumn("complete", F.col("complete_score") >= pass_at)


def judge_accurate(pairs: DataFrame) -> DataFrame:
    """Round two: the answer is supported by the document."""
    return pairs.withColumn("accurate", F.col("grounded") >= 1.0)


def assess(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Kept pairs and the report: drafts, then survivors of each round, with tokens and the share of the round before.
    The second judge sees survivors of the first alone; the report is one aggregate."""
    judged = judge_accurate(judge_complete(pairs))
    n = count_tokens(F.concat_ws(" ", "question", "answer"))
    both = F.col("complete") & F.col("accurate")
    sums = judged.select(n.alias("n"), F.col("complete").alias("a"), both.alias("b")).agg(
        F.count("*").alias("k0"), F.count_if("a").alias("k1"), F.count_if("b").alias("k2"), F.sum("n").alias("t0"),
        F.coalesce(F.sum(F.when(F.col("a"), F.col("n"))), F.lit(0)).alias("t1"), F.coalesce(F.sum(F.when(F.col("b"), F.col("n"))), F.lit(0)).alias("t2"),
    )
    report = sums.select(F.expr("stack(3, 'drafts', k0, t0, 1.0D, 'complete', k1, t1, try_divide(k1, k0), 'accurate', k2, t2, try_divide(k2, k1)) as (round, kept, tokens, share)"))
    return judged.filter(both), report


def distill(pairs: DataFrame, *lineage: str) -> DataFrame:
    """Pairs without the source's text; its id stays for lineage, and the columns named."""
    return pairs.select("doc_id", *lineage, "pair_no", "question", "answer")


def plain_text_examples(kept: DataFrame) -> DataFrame:
    return kept.select("doc_id", F.col("text").alias("output"), F.lit(0).alias("n_in"), count_tokens(F.col("text")).alias("n_out"))


def pilot_validity(pairs: DataFrame, votes: DataFrame, n: int = 300, seed: int = 5) -> DataFrame:
    """Of the first n pairs by hash: share valid to all reviewers, share on which reviewers agree, and two reviewers' kappa.
    pairs: pair_id; votes: pair_id, reviewer, valid."""
    some = pairs.select("pair_id").orderBy(order_hash(F.col("pair_id"), seed), "pair_id").limit(n)
    each = votes.join(F.broadcast(some), "pair_id").groupBy("pair_id").agg(F.min(F.col("valid").cast("int")).alias("lo"), F.max(F.col("valid").cast("int")).alias("hi"), F.avg(F.col("valid").cast("double")).alias("share"))
    sums = each.agg(F.count("*").alias("n"), F.avg(F.col("lo").cast("double")).alias("valid_share"), F.avg((F.col("lo") == F.col("hi")).cast("double")).alias("agreement"), F.avg("share").alias("p"))
    chance = F.col("p") * F.col("p") + (1 - F.col("p")) * (1 - F.col("p"))
    return sums.select("n", "valid_share", "agreement", F.round(F.when(chance < 1, (F.col("agreement") - chance) / (1 - chance)).otherwise(1.0), 6).alias("kappa"))


def review_loop(draft, vote, reviewers: int = 3, policy: str = "majority", max_rounds: int = 5) -> DataFrame:
    """Drafts that reviewers turn down are drafted again. draft(ids or None, round) -> q_id, ...; vote(drafts, round) -> q_id,
    reviewer, valid. Each round's drafts are written, so that they are made once, and are fewer than the last's."""
    accepted, ids, turn = None, None, 0
    while turn < max_rounds:
        drafts = settled(draft(ids, turn), "drafts")
        need = reviewers if policy == "unanimous" else reviewers // 2 + 1
        good = vote(drafts, turn).groupBy("q_id").agg(F.sum(F.col("valid").cast("int")).alias("yes"))
        good = settled(good.filter(F.col("yes") >= need).select("q_id"), "accepted")
        new = drafts.join(good, "q_id", "left_semi").withColumn("round", F.lit(turn))
        accepted = new if accepted is None else accepted.unionByName(new)
        ids = drafts.join(good, "q_id", "left_anti").select("q_id")
        turn += 1
        if ids.isEmpty():
            break
    return accepted

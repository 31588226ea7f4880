"""Benchmark decontamination: short test items inside long documents.

Size-partitioned MinHash containment search. An item's sketch is the set of its smallest shingle hashes; items are
partitioned by their number of shingles (powers of two), and a partition's sketch is one larger than the number of
shingles that an item of its largest size may miss at the threshold. So any document that contains enough of an
item holds a shingle of its sketch, however long the document is. Documents aren't sketched: all their shingles are looked up, which makes
the search a prefix filter in hash order that loses nothing, where two sketches would lose some; only items' sketches are held, and stay small. Candidates are verified by the exact share of the item's distinct shingles that the document has.

Words are runs of letters and digits, lower-cased; shingles have five words. An item of fewer words is one shingle, of
all its words. Only DataFrame functions are used.

Defined results: null texts are empty; items without words match nothing; rows that share a doc_id (or an item_id)
count as one document (item) that has the shingles of all of them; null ids count as one id; an empty table
gives no rows; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import rows_of, small, without_ids, written

WORDS, CONTAINMENT = 5, 0.8


def words(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), "")


def shingles(tokens: Column, n: int, of=lambda run: F.xxhash64(run)) -> Column:
    """All runs of n words, through ``of``; none if there are fewer words."""
    return F.when(F.size(tokens) >= n, F.transform(F.sequence(F.lit(1), F.size(tokens) - (n - 1)), lambda i: of(F.slice(tokens, i, n))))


def _text_of(run: Column) -> Column:
    return F.array_join(run, " ")


def may_miss(n: Column | int, threshold: float) -> Column:
    return F.floor(F.lit(n) * F.lit(1 - threshold) + F.lit(1e-9)) if isinstance(n, int) else F.floor(n * F.lit(1 - threshold) + F.lit(1e-9))


def item_shingles(items: DataFrame, id_column: str, text_column: str, n: int) -> DataFrame:
    """Distinct shingles of each item: item_id, width (words in the shingle), gram, total."""
    tokens = F.col("tokens")
    rows = items.select(F.col(id_column).cast("long").alias("item_id"), words(F.coalesce(F.col(text_column).cast("string"), F.lit(""))).alias("tokens"))
    width = F.least(F.size(tokens), F.lit(n))
    grams = rows.select("item_id", width.alias("width"), F.explode(F.coalesce(shingles(tokens, n, _text_of), F.when(F.size(tokens) > 0, F.array(_text_of(tokens))))).alias("gram")).distinct()
    return grams.withColumn("total", F.count("*").over(Window.partitionBy("item_id")))


def _grams_of(tokens: Column, widths: list[int], of) -> Column:
    """The document's shingles of every width that items have."""
    none = F.array().cast("array<string>") if of is _text_of else F.array().cast("array<bigint>")
    return F.concat(*[F.coalesce(shingles(tokens, w, of), none) for w in widths])


def find_leaks(
    docs: DataFrame, items: DataFrame, n: int = WORDS, threshold: float = CONTAINMENT, text_column: str = "text", item_id: str = "item_id", item_text: str = "text"
) -> DataFrame:
    """Every document-item pair at or above the threshold: doc_id, item_id, matched, total, containment."""
    # the words are a column of their own: inside a lambda they would be split anew for each shingle
    rows = rows_of(docs, text_column=text_column)
    grams = written(item_shingles(items, item_id, item_text, n), "item-shingles")
    widths = sorted(r["width"] for r in grams.select("width").distinct().collect()) or [n]  # n values at most

    # sketches, by size partition
    size_bound = F.pow(F.lit(2), F.floor(F.log2("total")) + 1).cast("int") - 1
    hashed = grams.withColumn("h", F.xxhash64(F.split("gram", " ")))
    rank = F.row_number().over(Window.partitionBy("item_id").orderBy("h"))
    sketch = written(hashed.withColumn("rank", rank).filter(F.col("rank") <= may_miss(size_bound, threshold) + 1).select("item_id", "h"), "item-sketches")

    tokens = F.col("tokens")
    split = rows.select("doc_id", words(F.col("text")).alias("tokens"))
    hashes = split.select("doc_id", F.explode(_grams_of(tokens, widths, lambda run: F.xxhash64(run))).alias("h"))
    candidates = written(hashes.join(small(sketch), "h").select("doc_id", "item_id").distinct(), "leak-candidates")

    # exact, on candidates alone
    ids = candidates.select(F.col("doc_id").alias("candidate_id")).distinct()
    texts = rows.join(small(written(ids, "leak-ids")), F.col("doc_id").eqNullSafe(F.col("candidate_id")), "left_semi")
    found = texts.select("doc_id", words(F.col("text")).alias("tokens")).select("doc_id", F.explode(F.array_distinct(_grams_of(tokens, widths, _text_of))).alias("gram"))
    matched = found.join(small(grams.select("item_id", "gram", "total")), "gram").groupBy("doc_id", "item_id", "total").agg(F.countDistinct("gram").alias("matched"))
    share = F.col("matched") / F.col("total")
    pair = candidates.select(F.col("doc_id").alias("d"), F.col("item_id").alias("i"))
    return (
        matched.join(pair, F.col("doc_id").eqNullSafe(F.col("d")) & F.col("item_id").eqNullSafe(F.col("i")), "left_semi")
        .filter(share >= threshold - 1e-9)
        .select("doc_id", "item_id", "matched", "total", share.alias("containment"))
    )


def drop_leaks(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """``docs`` without the documents that hold an item; its columns as they are."""
    return without_ids(docs, find_leaks(docs, items, **options).select("doc_id"))


ORACLE = r"""
with item_words as (
  select item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') as w from benchmark),
item_grams as (
  select distinct item_id, unnest(case when len(w) >= 5 then list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' '))
    when len(w) > 0 then [array_to_string(w, ' ')] else [] end) as gram from item_words),
sized as (select item_id, gram, count(*) over (partition by item_id) as total from item_grams),
doc_words as (
  select doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') as w from documents),
doc_grams as (select distinct doc_id, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' '))) as gram from doc_words)
select doc_id, item_id, count(*) as matched, total, count(*) / total as containment
from doc_grams join sized using (gram) group by doc_id, item_id, total having count(*) / total >= 0.8 - 1e-9
"""

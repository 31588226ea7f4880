"""The model boundary, and the streaming forms on file sources."""

import pytest
from pyspark.sql import functions as F

from chapterforge import service
from chapterforge.operators import filtering
from chapterforge.sources import files
from chapterforge.streaming import crawl


def requests(spark):
    return spark.createDataFrame([("1", "rate", "x y"), ("2", "rate", "x y"), ("3", "answer", "z")], "req_id string, role string, prompt string")


def test_rules_and_records(spark):
    got = {r["req_id"]: r["response"] for r in service.RuleService({"rate": lambda p: F.upper(p)}).complete(requests(spark)).collect()}
    assert got == {"1": "X Y", "2": "X Y", "3": None}
    held = requests(spark).filter("req_id = '3'").select(service.request_key().alias("key"), F.lit("yes").alias("response"))
    assert {r["req_id"]: r["response"] for r in service.RecordedService(held).complete(requests(spark)).collect()}["3"] == "yes"


def test_remote_answers_are_cached(spark, tmp_path):
    calls = spark.sparkContext.accumulator(0)

    def fn(role, prompts):
        calls.add(len(prompts))
        return [f"score {len(p)}" for p in prompts]

    remote = service.RemoteService(fn, str(tmp_path / "cache"))
    assert remote.complete(requests(spark)).filter("response is not null").count() == 3
    first = calls.value
    assert first == 2  # distinct prompts alone
    remote.complete(requests(spark)).count()
    assert calls.value == first
    docs = spark.createDataFrame([(1, "abcd")], "doc_id long, text string")
    assert filtering.rate_documents(docs, remote).first()["score"] == 4


def test_stream_filters_and_routes(spark, data, tmp_path):
    docs, labels = spark.read.parquet(f"{data}/documents.parquet"), spark.read.parquet(f"{data}/labels.parquet")
    model = filtering.train_bayes(docs.join(filtering.ratings_from_labels(labels), "doc_id"))
    docs.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(docs.schema).parquet(str(tmp_path / "in"))
    crawl.route_stream(stream, model, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    assert spark.read.parquet(str(tmp_path / "out")).count() == filtering.apply_filter(docs, model).count()


def test_stream_windows_and_records(spark, data, tmp_path):
    spark.read.parquet(f"{data}/events.parquet").write.parquet(str(tmp_path / "e"))
    stream = spark.readStream.schema(spark.read.parquet(f"{data}/events.parquet").schema).parquet(str(tmp_path / "e"))
    for name, df, mode in (("w", crawl.windowed_counts(stream), "update"), ("r", crawl.running_records(stream), "update"), ("s", crawl.sessions(stream), "append")):
        q = df.writeStream.format("memory").queryName(f"mem_{name}").outputMode(mode).start()
        q.processAllAvailable()
        q.stop()
    assert spark.sql("select sum(n) from mem_w").first()[0] == 1000
    from chapterforge.workloads import pages  # noqa: F401  the batch form of the same measure
    from chapterforge import workloads

    batch = {r["key"]: r["matches_or_beats"] for r in workloads.queries()["w5b_records"](spark, data).collect()}
    assert {r["event_type"]: r["matches_or_beats"] for r in spark.sql("select * from mem_r").collect()} == batch


def test_sinks(spark, tmp_path):
    ex = spark.createDataFrame([(f"e{i}", 1 + i % 2, "t", f"1-{i:02d}") for i in range(10)], "example_id string, chapter int, task string, order_key string")
    files.write_examples(ex, str(tmp_path / "x"))
    assert spark.read.parquet(str(tmp_path / "x")).count() == 10
    files.write_for_trainer(ex, str(tmp_path / "j"), 2)
    assert spark.read.json(str(tmp_path / "j")).count() == 10
    assert files.read_crawl_json(spark, str(tmp_path / "j")).count() == 10
    assert files.read_text_files(spark, str(tmp_path / "j")).count() >= 1
    with pytest.raises(ValueError):
        filtering.encode_context(ex.withColumn("text", F.lit("a")), 3, "unknown")

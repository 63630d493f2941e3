"""A map task that runs again, as after a lost executor, must give what its first run gave: other tasks may have read a part of it."""

from pyspark.sql import functions as F

from hubgraph.llm import ctw, simhash
from hubgraph.llm.common import in_arrow, stage


def corpus(spark):
    rows = [(k, " ".join(f"w{k % 7}x{j}" for j in range(40))) for k in range(60)] + [(None, None), (60, "")]
    return stage(spark.createDataFrame(rows, "doc_id long, text string").repartition(3))


def twice(asked):
    return [sorted((r.p, r.slice, bytes(r.blob)) for r in asked.collect()) for _ in range(2)]


def test_slices_of_shingles_are_named_alike_when_a_task_runs_again(spark, monkeypatch):
    monkeypatch.setattr(simhash, "SLICE", 2000)
    asked = corpus(spark).select(simhash.row_key().alias("key"), "doc_id", "text").transform(in_arrow, simhash._ask(8), "p int, slice string, blob binary")
    first, second = twice(asked)
    assert first == second
    lists = [name for p, name, _ in first if p == -1]
    assert len(lists) == len(set(lists)) > 1


def test_slices_of_tokens_are_named_alike_when_a_task_runs_again(spark):
    docs = corpus(spark).select("doc_id", F.coalesce("doc_id", F.lit(-1)).alias("d"), F.coalesce("text", F.lit("")).alias("text"), F.lit(True).alias("train"))
    asked = docs.withColumn("th", F.xxhash64("text")).select("d", "th", "text", "train").transform(in_arrow, ctw._ask(8), "p int, slice string, blob binary")
    first, second = twice(asked)
    assert first == second
    lists = [name for p, name, _ in first if p == -1]
    assert len(lists) == len(set(lists)) > 1

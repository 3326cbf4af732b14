"""Runs of words are taken from a text that is split once."""

from pyspark.sql import functions as F

from taskmesh.operators import joins


def test_a_text_is_split_once(spark):
    docs = spark.createDataFrame([(1, "a b c, d"), (2, "b C d"), (3, "a b"), (4, ""), (5, None)], "doc_id long, text string")
    found = docs.select("doc_id", F.size(joins.shingles(F.col("text"), 3)).alias("n"))
    assert {r.doc_id: r.n for r in found.collect()} == {1: 2, 2: 1, 3: 0, 4: 0, 5: 0}
    assert found._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1
    bench = spark.createDataFrame([(9, "x b c D y")], "item_id long, text string")
    assert sorted(r.doc_id for r in joins.decontaminate(docs, bench, 3).collect()) == [3, 4, 5]

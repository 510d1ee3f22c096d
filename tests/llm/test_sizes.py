"""What showed at larger tables only."""

import pyarrow as pa
from pyspark.sql import functions as F

from nearcopy.llm import ngram_join, passages


def test_filters_are_in_no_plan(spark):
    """The filter of 20000 copies is some 80 kB as text; the plan that it was in is a few kB."""
    named = spark.range(20_000).select(
        F.col("id").alias("doc_id"), F.lit(1).cast("long").alias("n"), (F.col("id") % 10).alias("h1"),
        F.lit(0).cast("long").alias("h2"), F.lit(b"").alias("rare"),
    )
    named = named.unionByName(named.limit(1).withColumns({"doc_id": F.lit(-5).cast("long"), "h2": F.lit(7).cast("long")}))
    classes = named.groupBy("n", "h1", "h2").agg(F.min("doc_id").alias("rep"))
    found = ngram_join._first_of_classes(named, classes)
    assert len(found._jdf.queryExecution().toString()) < 60_000
    assert sorted(r.rep for r in found.collect()) == [-5, *range(10)]


def test_contexts_are_looked_for_once_a_block(monkeypatch):
    calls, plain = [], passages.context_minima
    monkeypatch.setattr(passages, "context_minima", lambda *a: calls.append(a) or plain(*a))
    texts = [" ".join(f"w{(i * 7 + d) % 400}" for i in range(300)) for d in range(3)]
    list(passages._nodes(5, 46, 4)([pa.record_batch([pa.array([0, 1, 2]), pa.array(texts)], names=["_id", "_text"])]))
    assert len(calls) == 1

"""A training corpus in five stages; each is written as Parquet and read again as the next one's input."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from nearcopy.components import materialize
from nearcopy.llm import decontam, ngram_join, packing, pii, tokens, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows with a toxicity score under 0.5; the machine is fitted on the labelled rows among them. Null and empty texts score as texts
    without words, which are clean; each row is judged by its own text, also where ids repeat; without labels all stay."""
    model = toxicity.fit_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.add_scores(docs, model, column="_toxicity").where("_toxicity < 0.5").drop("_toxicity")


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that are linked by near-equal sets of five-word shingles (similarity 0.8 and more), the one with the smallest id.

    Rows without an id and rows with null or empty texts stay; all rows of an id that isn't its group's smallest go."""
    groups = ngram_join.jaccard_components(docs, shingle=5, percent=80)
    others = groups.where("component_id <> doc_id").select("doc_id").distinct()
    return docs.join(others, "doc_id", "left_anti").select(*docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that hold no ten-word window of a benchmark item. Null and empty texts stay; rows that repeat an id are judged apart."""
    return decontam.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def hide_persons(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows with pseudonyms for personal data; n_chars is counted anew, null texts keep theirs."""
    hidden = pii.add_pseudonyms(docs, count="_values").drop("_values")
    return hidden.withColumn(
        "n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))
    ).select(*docs.columns) if "n_chars" in docs.columns else hidden


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences, with their token ids. A null or empty text is one end id; rows that repeat an id are packed apart."""
    return packing.pack_documents(docs, tokens.public_file("byte_bpe_50k.json"), with_ids=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("near duplicates", keep_one_of_each_group),
    ("decontamination", drop_leaks),
    ("pseudonyms", hide_persons),
    ("packing", pack),
]

#: SQL can express neither the learned scores nor the tokens; tests/llm compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialize(docs)
    return docs

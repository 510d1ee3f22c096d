"""Measures: recall, compression, accuracy, precision, fronts."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from nearcopy.functions.blocks import hash_sample


def recall_at_k(exact: DataFrame, approx: DataFrame, k: int) -> DataFrame:
    """One row (recall): the mean over all queries of the share of the k true neighbours that were found."""
    both = exact.where(F.col("rank") <= k).select("qid", "nid").join(
        approx.where(F.col("rank") <= k).select("qid", "nid"), ["qid", "nid"]
    ).groupBy("qid").agg(F.count("*").alias("hits"))
    asked = exact.select("qid").distinct()
    return asked.join(both, "qid", "left").agg(F.avg(F.coalesce("hits", F.lit(0)) / F.lit(k)).alias("recall"))


def compression_ratio(n: int, dim: int, raw_bytes: int, index_bytes: int, codec_bytes: int = 0) -> float:
    """Bytes of all raw features over bytes of the index and the encoder."""
    return n * dim * raw_bytes / max(index_bytes + codec_bytes, 1)


def accuracy(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """pred (id, category), truth (id, label): one row (n, accuracy)."""
    return pred.join(truth, "id").agg(
        F.count("*").alias("n"), F.avg((F.col("category") == F.col("label")).cast("double")).alias("accuracy")
    )


def paired_hit_at_k(found: DataFrame, k: int) -> DataFrame:
    """Share of queries whose own pair (the same id) is among the first k."""
    return found.groupBy("qid").agg(
        F.max(((F.col("nid") == F.col("qid")) & (F.col("rank") <= k)).cast("int")).alias("hit")
    ).agg(F.count("*").alias("n"), F.avg("hit").alias("hit_rate"))


def duplicate_counts(reps: DataFrame) -> DataFrame:
    """n, duplicates (items represented by another one), items in groups of two or more, such groups, and the share
    of duplicates."""
    sized = reps.join(reps.groupBy("rep").agg(F.count("*").alias("size")), "rep")
    return sized.agg(
        F.count("*").alias("n"),
        F.count_if(F.col("id") != F.col("rep")).alias("duplicates"),
        F.count_if(F.col("size") > 1).alias("in_groups"),
        F.count_if((F.col("size") > 1) & (F.col("id") == F.col("rep"))).alias("groups"),
        (F.count_if(F.col("id") != F.col("rep")) / F.count("*")).alias("share"),
    )


def sampled_precision(
    reps: DataFrame, raw: DataFrame, raw_threshold: float, n: int = 100_000, seed: int = 0
) -> DataFrame:
    """Of a random sample of flagged items (with their representative) the share that the raw vectors confirm."""
    from nearcopy.operators.dedup import flag_raw

    flagged = reps.where("id <> rep").select(F.col("rep").alias("i"), F.col("id").alias("j"), F.lit(seed).alias("_s"))
    return flag_raw(hash_sample(flagged, n, "j", "_s").drop("_s"), raw, raw_threshold).agg(
        F.count("*").alias("n"), F.avg(F.col("is_dup").cast("double")).alias("precision")
    )


def presence_pr(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """pred (id, has_dup), truth (id, is_true): tp, fp, fn, tn, precision, recall and the base rate."""
    both = pred.join(truth, "id", "full_outer").select(
        F.coalesce("has_dup", F.lit(False)).alias("p"), F.coalesce("is_true", F.lit(False)).alias("t")
    )
    counts = both.agg(
        F.count_if(F.col("p") & F.col("t")).alias("tp"),
        F.count_if(F.col("p") & ~F.col("t")).alias("fp"),
        F.count_if(~F.col("p") & F.col("t")).alias("fn"),
        F.count_if(~F.col("p") & ~F.col("t")).alias("tn"),
    )
    total = F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")
    return counts.select(
        "*",
        F.expr("try_divide(tp, tp + fp)").alias("precision"),
        F.expr("try_divide(tp, tp + fn)").alias("recall"),
        ((F.col("tp") + F.col("fn")) / total).alias("base_rate"),
    )


def pareto_front(df: DataFrame, maximize: list[str], key: str = "name") -> DataFrame:
    """Rows that no other row equals or beats in all measures and beats in one; a table of configurations is small."""
    other = df.select(*[F.col(c).alias(f"_{c}") for c in maximize])
    no_worse = better = None
    for c in maximize:
        a, b = F.col(f"_{c}") >= F.col(c), F.col(f"_{c}") > F.col(c)
        no_worse, better = a if no_worse is None else no_worse & a, b if better is None else better | b
    return df.join(other, no_worse & better, "left_anti")


def self_distance_profile(encoded: DataFrame) -> DataFrame:
    return encoded.groupBy("cell").agg(
        F.count("*").alias("n"),
        F.avg("self_dist").alias("mean"),
        F.stddev("self_dist").alias("sd"),
        F.expr("percentile(self_dist, 0.5)").alias("median"),
        F.min("self_dist").alias("least"),
        F.max("self_dist").alias("most"),
    )


def quantization_error(encoded: DataFrame) -> DataFrame:
    return encoded.agg(F.count("*").alias("n"), F.avg(F.col("self_dist") * F.col("self_dist")).alias("mse"))


def copy_yield(graded: DataFrame) -> DataFrame:
    """graded (prompt_id, seed, grade): samples, verbatim copies, copies for each sample and prompts with a copy."""
    return graded.agg(
        F.count("*").alias("samples"),
        F.count_if(F.col("grade") == "verbatim").alias("copies"),
        (F.count_if(F.col("grade") == "verbatim") / F.count("*")).alias("per_sample"),
        F.countDistinct(F.when(F.col("grade") == "verbatim", F.col("prompt_id"))).alias("prompts"),
    )

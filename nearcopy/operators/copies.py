"""The study of generated copies: prompts from the histogram's tail, samples, and how near they come to the source."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from nearcopy.functions import linalg as L
from nearcopy.functions.blocks import few_rows
from nearcopy.functions.features import small_noise
from nearcopy.operators.dedup import group_sizes, top_duplicated

#: Classes of the default generator by prompt id modulo 3: it gives the source whatever the seed; something near it;
#: something else.
IGNORES_SEED, BETWEEN, UNRELATED = range(3)


def default_generator(rows: DataFrame, dim: int = 64) -> DataFrame:
    """(prompt_id, seed, z) from (prompt_id, seed, x): a deterministic stand-in for an image generator."""
    kind = F.pmod("prompt_id", F.lit(3))
    where = F.concat(F.col("prompt_id").cast("string"), F.lit("/"), F.col("seed").cast("string"))
    x = F.col("x")
    z = F.when(kind == IGNORES_SEED, x).when(
        kind == BETWEEN, L.add(x, small_noise(where, "near:", 0.1, dim))
    ).otherwise(small_noise(where, "far:", 0.3, dim))
    return rows.select("prompt_id", "seed", z.alias("z"))


def generate(prompts: DataFrame, n: int = 9, generator=default_generator) -> DataFrame:
    """n samples for each prompt (prompt_id, x)."""
    return generator(prompts.withColumn("seed", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))))


def tail_prompts(reps: DataFrame, db: DataFrame, n: int = 100) -> DataFrame:
    """(prompt_id, x, n): the n most duplicated items."""
    top = top_duplicated(reps, n)
    return db.join(F.broadcast(top), F.col("id") == F.col("rep")).select(F.col("id").alias("prompt_id"), "x", "n")


def sample_prompts(reps: DataFrame, n: int, min_group: int = 2, seed: int = 0) -> DataFrame:
    """(rep, n): random groups of at least min_group items; duplication only as a weak filter."""
    name = F.md5(F.concat(F.lit(f"{seed}:"), F.col("rep").cast("string")))
    return group_sizes(reps).where(F.col("n") >= min_group).orderBy(name, "rep").limit(n)


def source_distance(samples: DataFrame, prompts: DataFrame) -> DataFrame:
    """(prompt_id, seed, dist): of each sample to its prompt's own vector."""
    sources = few_rows(prompts.select("prompt_id", "x"), 10_000)
    return samples.join(sources, "prompt_id").select("prompt_id", "seed", L.l2(F.col("z"), F.col("x")).alias("dist"))


def detect_copies(samples: DataFrame, db: DataFrame, raw_threshold: float) -> DataFrame:
    """(prompt_id, seed, nid, dist): the nearest training vector of each sample that is within the threshold."""
    from nearcopy.operators.search import knn_exact

    keyed = samples.select((F.col("prompt_id") * 1000 + F.col("seed")).alias("id"), F.col("z").alias("x"))
    near = knn_exact(keyed, db, 1, include_self=True)
    return near.where(F.col("dist") < raw_threshold).select(
        F.floor(F.col("qid") / 1000).alias("prompt_id"),
        F.pmod("qid", F.lit(1000)).cast("int").alias("seed"),
        "nid",
        "dist",
    )


def seed_invariance(samples: DataFrame, within: float = 0.05) -> DataFrame:
    """(prompt_id, spread, ignores_seed): the largest distance between a prompt's samples; pairs are of one prompt's
    few samples."""
    other = samples.select(F.col("prompt_id").alias("p"), F.col("seed").alias("s"), F.col("z").alias("y"))
    pairs = samples.join(other, (F.col("prompt_id") == F.col("p")) & (F.col("seed") < F.col("s")))
    return pairs.groupBy("prompt_id").agg(F.max(L.l2(F.col("z"), F.col("y"))).alias("spread")).withColumn(
        "ignores_seed", F.col("spread") <= within
    )


def grade_copies(dist: DataFrame, lo: float = 0.1, hi: float = 0.8) -> DataFrame:
    """verbatim under lo, between under hi, else none."""
    return dist.withColumn(
        "grade", F.when(F.col("dist") < lo, "verbatim").when(F.col("dist") < hi, "between").otherwise("none")
    )


def prompt_diversity(reps: DataFrame, captions: DataFrame) -> DataFrame:
    """(rep, n, captions, variety): distinct captions in each group of two or more, and their share."""
    named = reps.join(captions.select("id", F.md5(F.coalesce("caption", F.lit(""))).alias("c")), "id")
    return named.groupBy("rep").agg(
        F.count("*").alias("n"), F.countDistinct("c").alias("captions")
    ).where("n > 1").withColumn("variety", F.col("captions") / F.col("n"))


def mean_pair_distance(members: DataFrame, col: str = "t") -> DataFrame:
    """(rep, mean_distance): the root mean square distance between two of a group's normalised vectors, from their
    sums: of n unit
    vectors with the mean v it is sqrt(2 n / (n - 1) (1 - |v|^2)). No pairs are made."""
    known = members.where(F.aggregate(col, F.lit(0.0), lambda s, v: s + v * v) > 0)
    means = known.select("rep", F.posexplode(col).alias("i", "v")).groupBy("rep", "i").agg(
        F.avg("v").alias("v"), F.count("*").alias("n")
    )
    sized = means.groupBy("rep").agg(F.max("n").alias("n"), F.sum(F.col("v") * F.col("v")).alias("s")).where("n > 1")
    squared = 2 * F.col("n") / (F.col("n") - 1) * F.greatest(F.lit(0.0), 1 - F.col("s"))
    return sized.select("rep", F.sqrt(squared).alias("mean_distance"))


def word_windows(df: DataFrame, name: str, size: int) -> DataFrame:
    """(name, g): the distinct runs of `size` words of each text, words being what blanks, tabs and line ends part."""
    words = df.select(name, F.split("text", "[ \\t\\n\\r]+").alias("w")).where(F.size("w") >= size)
    runs = F.transform(
        F.sequence(F.lit(1), F.size("w") - (size - 1)), lambda i: F.array_join(F.slice("w", i, size), " ")
    )
    return words.select(name, F.explode(F.array_distinct(runs)).alias("g"))


def bench_hits(documents: DataFrame, benchmark: DataFrame, size: int = 8, most_windows: int = 1_000_000) -> DataFrame:
    """(item_id, doc_id): documents that hold any run of `size` words of an item, wherever it stands in either. The
    items' runs are
    sent to all documents up to `most_windows` of them; beyond, documents' and items' runs meet by a shuffle."""
    items = few_rows(word_windows(benchmark, "item_id", size), most_windows)
    return word_windows(documents, "doc_id", size).join(items, "g").select("item_id", "doc_id").distinct()

"""Category and text queries on what an index retains."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from nearcopy.functions import linalg as L
from nearcopy.operators.search import mips

#: Prompts that are broadcast at a time.
MOST_PROMPTS = 10_000


def class_prompts(captions: DataFrame, label: str, col: str = "t") -> DataFrame:
    """(category, t): the normalised mean vector of each class."""
    cells = captions.select(label, F.posexplode(col).alias("i", "v")).groupBy(label, "i").agg(F.avg("v").alias("v"))
    rows = cells.groupBy(label).agg(F.array_sort(F.collect_list(F.struct("i", "v"))).alias("p"))
    return rows.select(F.col(label).alias("category"), L.normalise(F.transform("p", lambda s: s["v"])).alias("t"))


def zero_shot(items: DataFrame, prompts: DataFrame, col: str = "x") -> DataFrame:
    """(id, category, score): the category with the largest inner product (ties: the smaller name). Prompts are the
    stated query
    set; they go to all items in blocks of MOST_PROMPTS."""
    if prompts.limit(MOST_PROMPTS + 1).count() > MOST_PROMPTS:
        parts = -(-prompts.count() // MOST_PROMPTS) * 2
        named = prompts.withColumn("_part", F.pmod(F.xxhash64("category"), F.lit(parts)))
        best = [zero_shot(items, named.where(F.col("_part") == p), col) for p in range(parts)]
        every = best[0]
        for more in best[1:]:
            every = every.unionByName(more)
        least = F.min(F.struct(-F.round("score", 10), F.col("category"), F.col("score"))).alias("m")
        return every.groupBy("id").agg(least).select(
            "id", F.col("m.category").alias("category"), F.col("m.score").alias("score")
        )
    scored = items.select("id", F.col(col).alias("_x")).join(
        F.broadcast(prompts.select("category", F.col("t").alias("_t")))
    )
    ranked = scored.select("id", "category", L.dot(F.col("_x"), F.col("_t")).alias("score"))
    first = ranked.groupBy("id").agg(
        F.min(F.struct(-F.round("score", 10), F.col("category"), F.col("score"))).alias("m")
    )
    return first.select("id", F.col("m.category").alias("category"), F.col("m.score").alias("score"))


def cross_modal_search(text_df: DataFrame, index, k: int, col: str = "t") -> DataFrame:
    """Text latents against the vectors that the index can rebuild, by inner product."""
    side = "text" if index.codec.text is not None else "image"  # a codec of one side serves both
    latents = index.codec.encode(text_df.select("id", col), col, "z", side)
    return mips(latents.select("id", "z"), index.decode(index.encoded), k, "z", "y")

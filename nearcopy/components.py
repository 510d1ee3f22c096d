"""Connected components of an edge table, without collecting anything but counts."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F


def _scratch(spark: SparkSession) -> str:
    """The application's folder below spark.checkpoint.dir. Only a session on one machine may leave that unset (tests); there it is
    below /tmp/checkpoints."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        base = "/tmp/checkpoints"
    return f"{base.rstrip('/')}/nearcopy-{spark.sparkContext.applicationId}"


def shared_dir(spark: SparkSession) -> str:
    """A new folder that the driver and all executors see."""
    return f"{_scratch(spark)}/{uuid.uuid4().hex}"


def drop_scratch(spark: SparkSession) -> None:
    """Remove all intermediate tables that this application has written. Results that weren't written elsewhere read them, so call it last."""
    path = spark._jvm.org.apache.hadoop.fs.Path(_scratch(spark))
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def materialize(df: DataFrame) -> DataFrame:
    """Cut the lineage by a table in the shared folder; later reads survive lost executors."""
    path = shared_dir(df.sparkSession)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component) for each node with an edge to another one; component: the smallest node reachable.

    Stars are alternated: each node hands its larger neighbours, then its smaller ones, to the smallest it
    knows. Rounds grow with the logarithm of the size. Each round is an aggregate with map-side
    minima and a join on the node; a node with very many edges is one key on the join's
    larger side only, which adaptive execution splits. Loops, repeated edges and nulls are dropped.
    """
    low, high = F.least(a, b).alias("m"), F.greatest(a, b).alias("v")
    known = edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    now = materialize(known.select(high, low).distinct())
    before = None
    for _ in range(max_rounds):
        both = now.select(F.col("v").alias("u"), F.col("m").alias("w"))
        both = both.unionByName(now.select(F.col("m").alias("u"), F.col("v").alias("w")))
        least = both.groupBy("u").agg(F.least(F.min("w"), F.first("u")).alias("m")).withColumnRenamed("u", "k")
        large = both.where("w > u").join(least, F.col("u") == F.col("k")).select(F.col("w").alias("v"), "m").distinct()
        large = materialize(large)
        least = large.groupBy("v").agg(F.min("m").alias("best")).withColumnRenamed("v", "k")
        small = large.join(least, F.col("v") == F.col("k"))
        small = small.select(F.col("m").alias("v"), F.col("best").alias("m")).where("v <> m")
        small = small.unionByName(least.select(F.col("k").alias("v"), F.col("best").alias("m")))
        now = materialize(small.distinct())
        state = now.agg(F.count("*"), F.sum(F.xxhash64("v", "m").cast("decimal(38,0)"))).first()
        if state == before:
            stars = now.select(F.col("v").alias("node"), F.col("m").alias("component"))
            return stars.unionByName(now.select(F.col("m").alias("node"), F.col("m").alias("component")).distinct())
        before = state
    raise RuntimeError("components don't settle")

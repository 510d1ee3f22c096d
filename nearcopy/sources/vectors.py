"""Vector tables: validation and quarantine, bucketed tables, and text formats for captions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F


def validity(x: Column, dim: int) -> Column:
    """True for an array of `dim` finite numbers."""
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf")))
    return F.coalesce((F.size(x) == dim) & fine, F.lit(False))


def validate_vectors(df: DataFrame, col: str, dim: int) -> tuple[DataFrame, DataFrame]:
    """Rows with a valid vector, and the others for quarantine; both read the table once more."""
    ok = validity(F.col(col), dim)
    return df.where(ok), df.where(~ok)


def read_vectors(spark: SparkSession, path: str, id_column: str = "vec_id", col: str = "embedding") -> DataFrame:
    return spark.read.parquet(path).select(
        F.col(id_column).cast("long").alias("id"), F.col(col).cast("array<double>").alias("x")
    )


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 1024) -> DataFrame:
    """`df` as a table of the catalog in `buckets` buckets by `key`, sorted within each: joins and aggregates of such
    tables by the key
    need no shuffle. Rows are dealt to the buckets before, so that there is one file a bucket."""
    df.repartition(buckets, key).write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
    return df.sparkSession.table(table)


def write_captions(df: DataFrame, path: str, kind: str = "json") -> None:
    """kind: json, csv, text (one string column) or parquet."""
    writer = df.write.mode("overwrite")
    {
        "json": writer.json,
        "text": writer.text,
        "parquet": writer.parquet,
        "csv": lambda p: writer.option("header", True).option("escape", '"').option("multiLine", True).csv(p),
    }[kind](path)


def read_captions(spark: SparkSession, path: str, schema: str, kind: str = "json") -> DataFrame:
    reader = spark.read.schema(schema)
    return {
        "json": reader.json,
        "text": reader.text,
        "parquet": reader.parquet,
        "csv": lambda p: reader.option("header", True).option("escape", '"').option("multiLine", True).csv(p),
    }[kind](path)

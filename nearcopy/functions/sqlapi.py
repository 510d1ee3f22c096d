"""The methods as SQL functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.functions import pandas_udf, udtf

from nearcopy.functions.blocks import smallest_distances
from nearcopy.functions.features import grams, hashed_rows, words
from nearcopy.operators.index import VectorIndex

#: Plain expressions, as SQL function bodies.
_EXPRESSIONS = {
    "l2_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v))",
    "is_near_copy(d_self DOUBLE, d DOUBLE, tol DOUBLE) RETURNS BOOLEAN": "CASE WHEN d_self <= 1e-12 THEN abs(d_self - d) <= 1e-12 ELSE abs(d_self - d) < tol * d_self END",
}


def mean_vectors(df: DataFrame, key: str, col: str = "x") -> DataFrame:
    """(key, col): the mean vector of each group, summed by place, so that tasks send one row a group and place."""
    sums = df.select(key, F.posexplode(col).alias("i", "v")).groupBy(key, "i").agg(F.avg("v").alias("v"))
    parts = sums.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("i", "v"))).alias("p"))
    return parts.select(key, F.transform("p", lambda s: s["v"]).alias(col))


def register(spark: SparkSession, index: VectorIndex) -> None:
    """l2_distance, is_near_copy; with the index: encode_vec, decode_code, adc, self_distance; vec_mean,
    recall_overlap; table functions probe,
    hash_features and knn_block. vec_mean holds a group in one task: for large groups see mean_vectors."""
    for head, body in _EXPRESSIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    plain = index._plain()

    @pandas_udf("struct<cell:int,codes:binary,self_dist:double>")
    def encode_vec(v: pd.Series) -> pd.DataFrame:
        z = plain.codec.encode_block(np.array(v.tolist(), float))
        cell, codes, y = plain.encode_block(z)
        return pd.DataFrame(
            {"cell": cell, "codes": [c.tobytes() for c in codes], "self_dist": np.sqrt(((z - y) ** 2).sum(axis=1))}
        )

    @pandas_udf("array<double>")
    def decode_code(cell: pd.Series, codes: pd.Series) -> pd.Series:
        raw = np.frombuffer(b"".join(codes), plain.code_dtype()).reshape(len(codes), -1)
        return pd.Series(list(plain.decode_block(cell.to_numpy(), raw)))

    @pandas_udf("double")
    def adc(q: pd.Series, cell: pd.Series, codes: pd.Series) -> pd.Series:
        raw = np.frombuffer(b"".join(codes), plain.code_dtype()).reshape(len(codes), -1)
        base = plain.cells[cell.to_numpy()] if plain.cells is not None and plain.by_residual else 0.0
        rest = np.array(q.tolist(), float) - base
        m, _, size = plain.books.shape
        words_ = plain.books[np.arange(m), raw]  # row by row, the codewords that the codes name
        return pd.Series(np.sqrt(((rest.reshape(-1, m, size) - words_) ** 2).sum(axis=(1, 2))))

    @pandas_udf("double")
    def self_distance(v: pd.Series) -> pd.Series:
        z = plain.codec.encode_block(np.array(v.tolist(), float))
        return pd.Series(np.sqrt(((z - plain.encode_block(z)[2]) ** 2).sum(axis=1)))

    @pandas_udf("array<double>")
    def vec_mean(v: pd.Series) -> list:
        return np.mean(np.array(v.tolist(), float), axis=0).tolist()

    @pandas_udf("double")
    def recall_overlap(exact: pd.Series, approx: pd.Series) -> float:
        return float(np.mean([len(set(a) & set(b)) / max(len(a), 1) for a, b in zip(exact, approx, strict=True)]))

    @udtf(returnType="cell: int, dist: double")
    class Probe:
        def eval(self, v: list, nprobe: int) -> Iterator[tuple[int, float]]:
            d = ((plain.cells - np.array(v, float)) ** 2).sum(axis=1)
            for c in np.argsort(d, kind="stable")[:nprobe]:
                yield int(c), float(np.sqrt(d[c]))

    @udtf(returnType="i: int, v: double")
    class HashFeatures:
        def eval(self, text: str) -> Iterator[tuple[int, float]]:
            x = hashed_rows([grams(words(text))], 256, "")[0]
            for i in np.flatnonzero(x):
                yield int(i), float(x[i])

    @udtf(returnType="q: int, nn: int, dist: double")
    class KnnBlock:
        """The k nearest rows of `block` to each row of `queries`, by their places in these arrays."""

        def eval(self, queries: list, block: list, k: int) -> Iterator[tuple[int, int, float]]:
            if queries and block:
                at, d = smallest_distances(np.array(queries, float), np.array(block, float), k)
                for q in range(len(queries)):
                    for n, v in zip(at[q].tolist(), d[q].tolist(), strict=True):
                        yield q, n, v**0.5

    for name, f in {
        "encode_vec": encode_vec,
        "decode_code": decode_code,
        "adc": adc,
        "self_distance": self_distance,
        "vec_mean": vec_mean,
        "recall_overlap": recall_overlap,
    }.items():
        spark.udf.register(name, f)
    spark.udtf.register("probe", Probe)
    spark.udtf.register("hash_features", HashFeatures)
    spark.udtf.register("knn_block", KnnBlock)

"""k-means on vector columns: broadcast centroids, one row a cell from each task, sums by cell."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from nearcopy.functions.blocks import (
    TILE,
    fast_squared_distances,
    hash_sample,
    hash_share,
    matrix,
    smallest_distances,
    sum_rows,
    vectors,
)


def nearest(x: np.ndarray, centroids: np.ndarray, n: int = 1, exact: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """The n nearest centroids of each row (ties: the lower number) and their squared distances."""
    if exact:
        return smallest_distances(x, centroids, n)
    at, best = [np.zeros((0, n), np.int64)], [np.zeros((0, n))]
    step = max(1, TILE // max(1, len(centroids)))
    for lo in range(0, len(x), step):
        d = fast_squared_distances(x[lo : lo + step], centroids)
        at.append(d.argmin(axis=1)[:, None] if n == 1 else np.argsort(d, axis=1, kind="stable")[:, :n])
        best.append(np.take_along_axis(d, at[-1], axis=1))
    return np.concatenate(at), np.concatenate(best)


def first_rows(df: DataFrame, col: str, n: int, by: str = "id") -> np.ndarray:
    return np.array([r[0] for r in df.orderBy(by).select(col).limit(n).collect()], float)


def start(df: DataFrame, col: str, k: int, init: str, seed: int, by: str) -> np.ndarray:
    """first: rows with the smallest ids; random: those with the smallest hashes of id and seed; parallel: k-means++
    over a sample of 50 k."""
    if init == "first":
        return first_rows(df, col, k, by)
    if init == "random":
        return np.array(
            [r[0] for r in df.orderBy(F.xxhash64(by, F.lit(seed)), by).select(col).limit(k).collect()], float
        )
    if init != "parallel":
        raise ValueError(f"there is no init {init!r}")
    x = np.array([r[0] for r in hash_sample(df.select(by, col), 50 * k, by).select(col).collect()], float)
    rng, out = np.random.default_rng(seed), [0]
    best = fast_squared_distances(x, x[:1])[:, 0]
    while len(out) < min(k, len(x)):
        p = best / best.sum() if best.sum() > 0 else np.full(len(x), 1 / len(x))
        out.append(int(rng.choice(len(x), p=p)))
        best = np.minimum(best, fast_squared_distances(x, x[out[-1:]])[:, 0])
    return x[out]


def kmeans(
    df: DataFrame,
    col: str,
    k: int,
    iters: int = 10,
    init: str = "first",
    sample: int | None = None,
    seed: int = 0,
    by: str = "id",
) -> tuple[np.ndarray, list[float]]:
    """Centroids, and the sum of squared distances before each round. Empty cells keep their centroid. Fewer rows
    than k: fewer centroids.

    sample: rows (by hash of the id) that training looks at; k * d numbers are broadcast."""
    rows = df.select(by, col)
    if sample is not None:
        rows = hash_share(rows, sample, by)
    centroids, costs = start(rows, col, k, init, seed, by), []
    if not len(centroids):
        return np.zeros((0, 0)), costs
    for _ in range(iters):
        shared = df.sparkSession.sparkContext.broadcast(centroids)

        def partial(batches, shared=shared):
            c = shared.value
            n, sums, cost = np.zeros(len(c), np.int64), np.zeros((len(c), c.shape[1] + 1)), np.zeros(len(c))
            for b in batches:
                x = matrix(b.column(0))
                if len(x):
                    at, d = nearest(x, c)
                    _add_by_cell(sums[:, :-1], x, at[:, 0])
                    cost += np.bincount(at[:, 0], d[:, 0], len(c))
                    n += np.bincount(at[:, 0], minlength=len(c))
            sums[:, -1] = cost
            some = np.flatnonzero(n)
            return some, n[some], sums[some]

        found = sum_rows(rows.select(col), partial, k)
        costs.append(float(sum(v[-1] for _, v in found.values())))
        centroids = centroids.copy()
        for cell, (n, v) in found.items():
            centroids[cell] = v[:-1] / n
    return centroids, costs


def kmeans_of_all(df: DataFrame, col: str, k: int, iters: int, encoders: list, by: str = "id") -> list[np.ndarray]:
    """The centroids that kmeans gives, begun at the first rows, for what each encoder makes of the vectors: all by the
    same passes, in which what they make doesn't leave its task."""
    rows, start = df.select(by, col), first_rows(df, col, k, by)
    if not len(start):
        return [np.zeros((0, 0)) for _ in encoders]
    centroids = [f(start).copy() for f in encoders]
    wide = max(c.shape[1] for c in centroids)
    for _ in range(iters):
        shared = df.sparkSession.sparkContext.broadcast((encoders, centroids))

        def partial(batches, shared=shared):
            n, sums = np.zeros(len(encoders) * k, np.int64), np.zeros((len(encoders) * k, wide))
            for b in batches:
                x = matrix(b.column(0))
                for e, (encode, c) in enumerate(zip(*shared.value, strict=True) if len(x) else ()):
                    z = encode(x)
                    _add_by_cell(sums[e * k :, : z.shape[1]], z, at := nearest(z, c)[0][:, 0])
                    n[e * k : e * k + len(c)] += np.bincount(at, minlength=len(c))
            some = np.flatnonzero(n)
            return some, n[some], sums[some]

        found = sum_rows(rows.select(col), partial, len(encoders) * k)
        centroids = [c.copy() for c in centroids]
        for key, (n, v) in found.items():
            c = centroids[key // k]
            c[key % k] = v[: c.shape[1]] / n
    return centroids


def _add_by_cell(sums: np.ndarray, x: np.ndarray, at: np.ndarray) -> None:
    order = np.argsort(at, kind="stable")
    cells, first = np.unique(at[order], return_index=True)
    sums[cells] += np.add.reduceat(x[order], first)


def assign_cells(
    df: DataFrame, col: str, centroids: np.ndarray, n: int = 1, cell: str = "cell", distance: str = "cell_dist"
) -> DataFrame:
    """Each row with its n nearest cells, one row each, and the L2 distance to them."""
    shared, place, names = df.sparkSession.sparkContext.broadcast(
        centroids
    ), df.columns.index(col), [*df.columns, cell, distance]
    n = min(n, len(centroids))

    def run(batches):
        for b in batches:
            x = matrix(b.column(place))
            if not len(x):
                continue
            at, d = nearest(x, shared.value, n)
            again = pa.array(np.repeat(np.arange(len(x)), n))
            yield pa.RecordBatch.from_arrays(
                [
                    *[c.take(again) for c in b.columns],
                    pa.array(at.ravel().astype(np.int32)),
                    pa.array(np.sqrt(d).ravel()),
                ],
                names=names,
            )

    from pyspark.sql.types import DoubleType, IntegerType, StructType

    return df.mapInArrow(run, StructType([*df.schema.fields]).add(cell, IntegerType()).add(distance, DoubleType()))

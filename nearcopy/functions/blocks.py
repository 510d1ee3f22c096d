"""Arrow batches as NumPy blocks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F


def matrix(column: pa.Array, dtype=np.float64) -> np.ndarray:
    """Rows of a list column without nulls, all of one length."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1).astype(dtype) if len(column) else np.zeros((0, 0), dtype)


def vectors(x: np.ndarray, kind: pa.DataType = pa.float64()) -> pa.Array:
    n, d = x.shape
    return pa.ListArray.from_arrays(
        pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(x).ravel(), kind)
    )


#: Distances that one kernel call works out at a time.
TILE = 1 << 21


def squared_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Exact for equal rows up to rounding: differences, not the expanded square, in blocks of rows and dimensions
    that fit TILE."""
    out = np.empty((len(x), len(y)))
    step = max(1, TILE // max(1, y.size))
    for i in range(0, len(x), step):
        out[i : i + step] = ((x[i : i + step, None, :] - y[None]) ** 2).sum(axis=2)
    return out


def fast_squared_distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """By one matrix product; never below 0."""
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None] - 2 * x @ y.T, 0)


def summed_squares(x: np.ndarray) -> np.ndarray:
    """The sum of squares of each row as list_distance in SQL has it: from the first dimension to the last, each square
    added with one rounding (a fused step, made of the exact errors of the product and of the sum)."""
    total = np.zeros(len(x))
    for v in np.ascontiguousarray(x.T):
        square, split = v * v, v * 134217729.0
        high = split - (split - v)
        low = v - high
        rest = ((high * high - square) + 2 * high * low) + low * low
        more = total + square
        part = more - total
        total = more + (((total - (more - part)) + (square - part)) + rest)
    return total


def smallest_distances(x: np.ndarray, y: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """For each row of x the n nearest rows of y (ties: the lower number) and their squared distances, exact for
    equal rows.

    One matrix product tells which can be among them, and of these differences are taken; memory is some TILE numbers
    whatever len(y) is. Where several can, summed_squares and its roots decide: what is nearest among rows that rounding
    alone tells apart is the same in SQL."""
    n = min(n, len(y))
    at, best = np.zeros((len(x), n), np.int64), np.zeros((len(x), n))
    if not len(x) or not n:
        return at, best
    norms = (y * y).sum(1)
    step, wide = max(1, TILE // len(y)), max(1, TILE // x.shape[1])
    for lo in range(0, len(x), step):
        block = x[lo : lo + step]
        own = (block * block).sum(1)
        d = block @ y.T
        d *= -2
        d += norms[None]
        border = d.min(axis=1) if n == 1 else np.partition(d, n - 1, axis=1)[:, n - 1]
        slack = 1e-9 * (1 + own + np.abs(border) + norms.max())
        q, r = np.nonzero(d <= (border + slack)[:, None])
        exact = np.empty(len(q))
        for i in range(0, len(q), wide):
            gap = block[q[i : i + wide]] - y[r[i : i + wide]]
            exact[i : i + wide] = (gap * gap).sum(axis=1)
        several = np.flatnonzero(np.bincount(q, minlength=len(block))[q] > n)
        for i in range(0, len(several), wide):
            a = several[i : i + wide]
            exact[a] = summed_squares(block[q[a]] - y[r[a]])
        order = np.lexsort((r, np.sqrt(exact), q))
        first = np.searchsorted(q, np.arange(len(block)))  # q is sorted
        chosen = order[first[:, None] + np.arange(n)]
        at[lo : lo + step], best[lo : lo + step] = r[chosen], exact[chosen]
    return at, best


def classes(ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Classes of equal rows: each row's class, its rank by id there, and the row with the smallest id of each class."""
    order, seen, of = np.argsort(ids, kind="stable"), {}, np.zeros(len(ids), np.int64)
    rows = np.ascontiguousarray(x) + 0.0  # -0 is 0
    for i in order.tolist():
        of[i] = seen.setdefault(rows[i].tobytes(), len(seen))
    by_class = order[np.argsort(of[order], kind="stable")]
    start = np.searchsorted(of[by_class], np.arange(len(seen)))
    rank = np.zeros(len(ids), np.int64)
    rank[by_class] = np.arange(len(ids)) - start[of[by_class]]
    return of, rank, by_class[start]


class Tile:
    """Squared distances (or negative products) of rows of x to y by one product, with a bound of their error; what can
    be among the nearest by them is worked out again by differences. Single precision does unless a few rows are far
    longer than the others."""

    def __init__(self, x: np.ndarray, y: np.ndarray, metric: str = "l2"):
        self.x, self.y, self.dot = x, y, metric == "dot"
        sizes = [np.sqrt((v * v).sum(1)) for v in (x, y)]
        most, usual = max(v.max() for v in sizes), min(np.median(v) for v in sizes)
        self.scale = 1 / most if most > 0 else 1.0
        self.kind = np.float32 if usual >= 0.1 * most else np.float64
        self.slack = self.kind(16 * (x.shape[1] + 4) * np.finfo(self.kind).eps)
        self.right = self._side(y, 1.0, True)

    def _side(self, x, factor, last):
        x = x * self.scale
        size, one = (x * x).sum(1)[:, None], np.ones((len(x), 1))
        more = [] if self.dot else [one, size] if last else [size, one]
        return np.hstack([x * factor, *more]).astype(self.kind)

    def at(self, lo: int, hi: int) -> np.ndarray:
        return self._side(self.x[lo:hi], -1.0 if self.dot else -2.0, False) @ self.right.T

    def exact(self, q: np.ndarray, r: np.ndarray) -> np.ndarray:
        out, step = np.zeros(len(q)), max(1, TILE // self.x.shape[1])
        for i in range(0, len(q), step):
            a, b = self.x[q[i : i + step]], self.y[r[i : i + step]]
            out[i : i + step] = -(a * b).sum(axis=1) if self.dot else np.sqrt(((a - b) ** 2).sum(axis=1))
        return out


def places(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.divmod(np.flatnonzero(mask), mask.shape[1])


_SUMS = pa.schema([("key", pa.int64()), ("n", pa.int64()), ("values", pa.list_(pa.float64()))])


def sum_rows(df: DataFrame, partial, keys_at_most: int) -> dict[int, tuple[int, np.ndarray]]:
    """Sums of vectors by key, in two steps: `partial` gives (keys, counts, matrix) for all batches of a task, then
    rows of one key
    meet in one task. keys_at_most: a bound of the number of keys, all of which reach the driver."""

    def first(batches):
        keys, n, values = partial(batches)
        for i in range(0, len(keys), 1024):
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(keys[i : i + 1024], pa.int64()),
                    pa.array(n[i : i + 1024], pa.int64()),
                    vectors(values[i : i + 1024]),
                ],
                schema=_SUMS,
            )

    def second(batches):
        sums: dict[int, list] = {}
        for b in batches:
            for k, n, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), matrix(b.column(2)), strict=True):
                if k in sums:
                    sums[k][0] += n
                    sums[k][1] += v
                else:
                    sums[k] = [n, v.copy()]
        if sums:
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(list(sums), pa.int64()),
                    pa.array([s[0] for s in sums.values()], pa.int64()),
                    vectors(np.array([s[1] for s in sums.values()])),
                ],
                schema=_SUMS,
            )

    kind = "key long, n long, values array<double>"
    rows = df.mapInArrow(first, kind).repartition("key").mapInArrow(second, kind).limit(keys_at_most).collect()
    return {r[0]: (r[1], np.array(r[2])) for r in rows}


def hash_sample(df: DataFrame, n: int, *by: str) -> DataFrame:
    """n rows with the smallest hash of the given columns; the same on any partitioning. The rows meet in one task:
    for small n."""
    return df.orderBy(F.xxhash64(*by), *by).limit(n)


def hash_share(df: DataFrame, n: int | None, *by: str, rows_per_task: int = 4096) -> DataFrame:
    """About n rows, those whose hash is below a bound that a count gives (all rows if n is None or there are no more
    than n).
    Nothing is shuffled:
    rows stay where they are, but tasks that would hold few of them are joined."""
    total = df.count()
    n = total if n is None else n
    if n < total:
        df = df.where(F.xxhash64(*by) < F.lit(int((n / total - 0.5) * 2**64)))
    tasks = max(1, min(n, total) // rows_per_task)
    return df.coalesce(tasks)


def spread(df: DataFrame) -> DataFrame:
    """A table of a few files in as many parts as there are cores; larger ones stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def few_rows(df: DataFrame, most: int) -> DataFrame:
    """`df` marked for broadcast if it has at most `most` rows (one bounded count), else as it is: the join is then
    shuffled."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df

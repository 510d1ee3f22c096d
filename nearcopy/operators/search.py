"""Exact search by blocks, in-chunk neighbours, inner products and recall lists."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from nearcopy.functions.blocks import TILE, Tile, classes, matrix, places
from nearcopy.operators.index import _FOUND

#: Queries that are sent to the database, which then doesn't move; more meet it block by block in a shuffle.
BLOCK_QUERIES = 20_000
#: Bytes of vectors in a block of such a shuffle; a task holds two blocks.
BLOCK_BYTES = 64 << 20
_NEAR = "id long, nn_id long, dist double"


def merge_topk(found: DataFrame, k: int) -> DataFrame:
    """(qid, nid, dist, rank): the k smallest of each query, ties by id; Catalyst limits groups before the shuffle."""
    w = Window.partitionBy("qid").orderBy(F.round("dist", 12), "nid")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def knn_exact(
    queries: DataFrame,
    db: DataFrame,
    k: int,
    metric: str = "l2",
    include_self: bool = False,
    col: str = "x",
    db_col: str | None = None,
) -> DataFrame:
    """(qid, nid, dist, rank). metric: l2, or dot (then dist is the negative inner product).

    Up to BLOCK_QUERIES queries are broadcast and the database never moves. More are cut into blocks by a hash of the
    id, as is the
    database, and each pair of blocks is one task's work: nothing reaches the driver. Either way a task sends k rows
    a query and block."""
    spark, db_col = queries.sparkSession, db_col or col
    asked, answers = queries.select("id", col), db.select("id", db_col)
    head = asked.limit(BLOCK_QUERIES + 1).toArrow()
    if head.num_rows <= BLOCK_QUERIES:
        shared = spark.sparkContext.broadcast((head.column(0).to_numpy(), matrix(head.column(1))))

        def scan(batches):
            found = None
            for b in batches:
                if b.num_rows:
                    found = found or _Nearest(*shared.value, k, metric, include_self)
                    found.meet(b.column(0).to_numpy(), matrix(b.column(1)))
            yield from found.rows() if found else ()

        return merge_topk(answers.mapInArrow(scan, "qid long, nid long, dist double"), k)
    size = len(head.column(1)[0])
    a, b = asked.count(), answers.count()
    left, right = (max(1, -(-n * size * 8 // BLOCK_BYTES)) for n in (a, b))
    right = max(right, -(-2 * spark.sparkContext.defaultParallelism // left))  # work for all cores

    def cut(df, own, others, mine, theirs):
        # both sides' keys are of one type: those of other types are dealt to other tasks, where nothing meets
        rows = df.toDF("id", "x").withColumn(mine, F.pmod(F.xxhash64("id"), F.lit(own)).cast("int"))
        return rows.withColumn(theirs, F.explode(F.sequence(F.lit(0), F.lit(others - 1))))

    def meet(q: pa.Table, y: pa.Table) -> pa.Table:
        if not q.num_rows or not y.num_rows:
            return _FOUND.empty_table()
        found = _Nearest(q.column("id").to_numpy(), matrix(q.column("x")), k, metric, include_self)
        found.meet(y.column("id").to_numpy(), matrix(y.column("x")))
        return pa.Table.from_batches(list(found.rows()), schema=_FOUND)

    pairs = cut(asked, left, right, "qb", "db").groupBy("qb", "db")
    found = pairs.cogroup(cut(answers, right, left, "db", "qb").groupBy("qb", "db"))
    return merge_topk(found.applyInArrow(meet, "qid long, nid long, dist double"), k)


class _Nearest:
    """The k nearest rows to each query of all blocks met so far; ties by id.

    Equal queries are one, which keeps a row more so that each can leave out itself; of equal rows in a block only those
    with the smallest ids can be among the k."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, k: int, metric: str, include_self: bool):
        self.ids, self.k, self.metric, self.include_self = ids, k, metric, include_self
        self.most = k if include_self else k + 1
        self.of, _, first = classes(ids, q)
        self.q = q[first]
        self.bound = np.full(len(first), np.inf)
        self.found = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))

    def meet(self, names: np.ndarray, x: np.ndarray) -> None:
        some = classes(names, x)[1] < self.most
        names, x = names[some], x[some]
        for at in range(0, len(x), TILE // 64):
            self._meet(names[at : at + TILE // 64], x[at : at + TILE // 64])

    def _meet(self, names, x):
        tile, parts = Tile(self.q, x, self.metric), [self.found]
        scale = tile.scale**2
        step = max(1, 2 * TILE // len(x))
        for lo in range(0, len(self.q), step):
            d, bound = tile.at(lo, lo + step), self.bound[lo : lo + step]
            limit = bound * scale if self.metric == "dot" else np.square(bound) * scale
            if len(x) > self.most and np.isinf(bound).any():
                limit = np.minimum(limit, np.partition(d, self.most - 1, axis=1)[:, self.most - 1])
            q, r = places(d <= (limit + tile.slack).astype(tile.kind)[:, None])
            parts.append((q + lo, names[r], tile.exact(q + lo, r)))
        q, n, d = (np.concatenate(c) for c in zip(*parts, strict=True))
        order = np.lexsort((n, np.round(d, 12), q))
        q = q[order]
        order = order[np.arange(len(q)) - np.searchsorted(q, q) < self.most]
        q, n, d = (np.concatenate(c)[order] for c in zip(*parts, strict=True))
        self.found = q, n, d
        held = np.bincount(q, minlength=len(self.q))
        full = np.flatnonzero(held == self.most)
        self.bound[full] = d[np.cumsum(held)[full] - 1]

    def rows(self):
        """Batches of (qid, nid, dist)."""
        q, n, d = self.found
        start, held = np.searchsorted(q, np.arange(len(self.q))), np.bincount(q, minlength=len(self.q))
        for lo in range(0, len(self.ids), 4096):
            of, ids = self.of[lo : lo + 4096], self.ids[lo : lo + 4096]
            again = np.repeat(np.arange(len(of)), held[of])
            at = np.arange(len(again)) - np.repeat(np.cumsum(held[of]) - held[of], held[of]) + start[of][again]
            if not self.include_self:
                other = n[at] != ids[again]
                again, at = again[other], at[other]
            first = np.arange(len(again)) - np.searchsorted(again, again) < self.k
            again, at = again[first], at[first]
            columns = [pa.array(ids[again]), pa.array(n[at]), pa.array(d[at])]
            yield pa.RecordBatch.from_arrays(columns, schema=_FOUND)


def knn_joined(queries: DataFrame, db: DataFrame, k: int, col: str = "x") -> DataFrame:
    """The same by expressions alone: a nested-loop join for small tables, to compare with."""
    from nearcopy.functions import linalg as L

    pairs = queries.select(F.col("id").alias("qid"), F.col(col).alias("q")).join(
        db.select(F.col("id").alias("nid"), F.col(col).alias("y")), F.col("qid") != F.col("nid")
    )
    return merge_topk(pairs.select("qid", "nid", L.l2(F.col("q"), F.col("y")).alias("dist")), k)


def mips(queries: DataFrame, db: DataFrame, k: int, col: str = "x", db_col: str | None = None) -> DataFrame:
    """(qid, nid, score, rank): largest inner products; a query may be its own answer."""
    found = knn_exact(queries, db, k, "dot", True, col, db_col)
    return found.select("qid", "nid", (-F.col("dist")).alias("score"), "rank")


def with_chunks(df: DataFrame, chunk_size: int, stride: int | None = None) -> DataFrame:
    """chunk_id = floor(id / chunk_size); with a stride below the size a row is in every chunk [c * stride, c *
    stride + size) that holds it."""
    if stride is None:
        return df.withColumn("chunk_id", F.floor(F.col("id") / chunk_size))
    last = F.floor(F.col("id") / stride)
    first = F.greatest(F.lit(0), F.floor((F.col("id") - chunk_size) / stride) + 1)
    return df.withColumn("chunk_id", F.explode(F.sequence(F.least(first, last), last)))


def chunk_nearest(
    df: DataFrame,
    col: str = "x",
    chunk_size: int = 10_000_000,
    stride: int | None = None,
    block: int | None = None,
    asked: DataFrame | None = None,
) -> DataFrame:
    """(id, nn_id, dist): the nearest other row within the chunk, over all its chunks; ties by id.

    A chunk is cut into blocks of about `block` rows by a hash of the id (as many as fit BLOCK_BYTES unless given, and
    fewer where cores would be idle). Each unordered pair of blocks is one task's work, which serves the rows of both by
    one product, so a task holds two blocks however large the chunk is, and a row moves once for each block of its
    chunk. A row that is alone in its chunks has no partner. asked: only these ids want a partner."""
    rows = df.select("id", col)
    if asked is None:
        rows = rows.withColumn("want", F.lit(True))
    else:
        wanted = asked.select(F.col("id").alias("_w"))
        rows = rows.join(wanted, F.col("id") == F.col("_w"), "left").withColumn("want", F.col("_w").isNotNull()).drop("_w")
    sizes = with_chunks(df.select("id"), chunk_size, stride).groupBy("chunk_id").count()
    head = df.select(F.size(col)).where(F.col(col).isNotNull()).first()
    n, chunks = sizes.agg(F.max("count"), F.count("*")).first()
    fits = block or max(1024, BLOCK_BYTES // (8 * max(1, head[0] if head else 1)))
    parts = -(-(n or 1) // fits)
    if block is None:
        even = -(-2 * df.sparkSession.sparkContext.defaultParallelism // max(1, chunks))
        while parts * (parts + 1) // 2 < even and n > 1024 * parts:
            parts += 1
    rows = with_chunks(rows, chunk_size, stride).withColumn("b", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    both = rows.withColumn("other", other).select(
        "chunk_id", F.least(
            "b", "other"
        ).alias("low"), F.greatest("b", "other").alias("high"), "b", "id", "want", F.col(col).alias("x")
    )

    def meet(t: pa.Table) -> pa.Table:
        high, own, want = (t.column(c).to_numpy() for c in ("high", "b", "want"))
        ids, x, second = t.column("id").to_numpy(), matrix(t.column("x")), own == high
        if t.column("low")[0] == t.column("high")[0]:
            return _nearest_others(ids, x, want)
        first = ~second
        return _nearest_others(ids[first], x[first], want[first], ids[second], x[second], want[second])

    found = both.groupBy("chunk_id", "low", "high").applyInArrow(meet, _NEAR)
    best = F.min(
        F.struct(F.round("dist", 12).alias("d"), F.col("nn_id").alias("n"), F.col("dist").alias("e"))
    ).alias("m")
    return found.groupBy("id").agg(best).select("id", F.col("m.n").alias("nn_id"), F.col("m.e").alias("dist"))


class _Best:
    """The best partner of each class of equal rows of a block. Classes in which a row is asked for come first."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, want: np.ndarray):
        of, self.rank, first = classes(ids, x)
        asked = np.zeros(len(first), bool)
        asked[of[want]] = True
        order = np.argsort(~asked, kind="stable")
        place = np.empty_like(order)
        place[order] = np.arange(len(order))
        self.ids, self.want, self.of, self.asked = ids, want, place[of], int(asked.sum())
        self.names, self.x = ids[first[order]], x[first[order]]
        self.key, self.dist = np.full(len(order), np.inf), np.full(len(order), np.inf)
        self.near = np.full(len(order), np.iinfo(np.int64).max)

    def offer(self, at: np.ndarray, names: np.ndarray, dist: np.ndarray) -> None:
        key = np.round(dist, 12)
        order = np.lexsort((names, key, at))
        order = order[np.flatnonzero(np.diff(at[order], prepend=-1))]
        at, names, key, dist = at[order], names[order], key[order], dist[order]
        better = (key < self.key[at]) | ((key == self.key[at]) & (names < self.near[at]))
        at = at[better]
        self.key[at], self.near[at], self.dist[at] = key[better], names[better], dist[better]

    def table(self, own: bool) -> pa.Table:
        """own: rows may be partners of equal ones."""
        key, near, dist = self.key[self.of], self.near[self.of], self.dist[self.of]
        if own:
            two = np.full((2, len(self.names)), np.iinfo(np.int64).max)
            for k in (0, 1):
                two[k, self.of[self.rank == k]] = self.ids[self.rank == k]
            twin = np.where(self.rank == 0, two[1, self.of], two[0, self.of])
            better = (twin < np.iinfo(np.int64).max) & ((key > 0) | (twin < near))
            near, dist, key = np.where(better, twin, near), np.where(better, 0.0, dist), np.where(better, 0.0, key)
        good = self.want & np.isfinite(key)
        return pa.table({"id": self.ids[good], "nn_id": near[good], "dist": dist[good]})


def _nearest_others(ids, x, want, others=None, y=None, want_y=None) -> pa.Table:
    """Partners of the rows of one block, or of two blocks (then of each in the other one)."""
    a = _Best(ids, x, want)
    if others is None:
        _pair_up(a, 0, a.asked, a, len(a.names))
        return a.table(True)
    b = _Best(others, y, want_y)
    _pair_up(a, 0, a.asked, b, len(b.names))
    _pair_up(a, a.asked, len(a.names), b, b.asked)
    return pa.concat_tables([a.table(False), b.table(False)])


def _pair_up(a: _Best, start: int, end: int, b: _Best, width: int) -> None:
    """Classes start to end of a meet the first `width` ones of b."""
    if start >= end or not width:
        return
    tile, step = Tile(a.x[start:end], b.x[:width]), max(1, 2 * TILE // width)
    least = np.full(width, np.inf, tile.kind)
    for lo in range(0, end - start, step):
        d = tile.at(lo, lo + step)
        if a is b:
            rows = np.arange(len(d))
            d[rows, rows + start + lo] = np.inf
        mask = np.zeros(d.shape, bool)
        if start < a.asked:
            np.less_equal(d, (d.min(axis=1) + tile.slack)[:, None], out=mask)
        if a is not b and b.asked:
            least = np.minimum(least, d.min(axis=0))
            mask[:, : b.asked] |= d[:, : b.asked] <= least[None, : b.asked] + tile.slack
        mask &= np.isfinite(d)
        q, r = places(mask)
        dist, q = tile.exact(q + lo, r), q + lo + start
        a.offer(q, b.names[r], dist)
        if a is not b:
            b.offer(r, a.names[q], dist)

"""Product quantizers and inverted files: training, encoding, decoding, asymmetric search, saving."""

from __future__ import annotations

import json
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from nearcopy.functions.blocks import (
    TILE,
    Tile,
    classes,
    fast_squared_distances,
    few_rows,
    hash_sample,
    matrix,
    places,
    spread,
    vectors,
)
from nearcopy.operators.codecs import Codec, IdentityCodec
from nearcopy.operators.kmeans import first_rows, kmeans, nearest

#: Query vectors (bytes) that are broadcast to the lists; more are worked off by a join on the cell.
BROADCAST_BYTES = 64 << 20
#: Rows that codebooks are trained on: 256 for each of 256 codewords.
TRAIN_ROWS = 1 << 16


# ---- product quantizer on blocks of rows -----------------------------------------------------


def fit_codebooks(x: np.ndarray, m: int, codes: int, iters: int, books: np.ndarray | None = None) -> np.ndarray:
    """(m, codes, d / m) by k-means in each block; it starts at `books` or at the first rows."""
    if x.shape[1] % m:
        raise ValueError(f"{m} blocks don't divide {x.shape[1]} dimensions")
    size = x.shape[1] // m
    out = np.array([x[:codes, b * size : (b + 1) * size] for b in range(m)]) if books is None else books.copy()

    def fit(b):
        part = np.ascontiguousarray(x[:, b * size : (b + 1) * size])
        for _ in range(iters):
            at = _closest(part, out[b])
            n = np.bincount(at, minlength=len(out[b]))
            sums = np.stack([np.bincount(at, v, len(out[b])) for v in part.T], axis=1)
            out[b][n > 0] = sums[n > 0] / n[n > 0, None]

    with ThreadPoolExecutor(min(m, 4)) as threads:
        list(threads.map(fit, range(m if iters else 0)))
    return out


def _closest(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The nearest row of y, by one product."""
    at, half, step = np.empty(len(x), np.int64), (y * y).sum(1) / 2, max(1, TILE // 8 // max(1, len(y)))
    for lo in range(0, len(x), step):
        d = x[lo : lo + step] @ y.T
        at[lo : lo + step] = np.subtract(half, d, out=d).argmin(axis=1)
    return at


def quantize(x: np.ndarray, books: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes and what they stand for."""
    m, _, size = books.shape
    codes = np.zeros((len(x), m), np.uint8 if books.shape[1] <= 256 else np.uint16)
    out = np.zeros_like(x)
    for b in range(m):
        at = nearest(x[:, b * size : (b + 1) * size], books[b])[0][:, 0]
        codes[:, b] = at
        out[:, b * size : (b + 1) * size] = books[b][at]
    return codes, out


def lookup_distances(residuals: np.ndarray, books: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Squared distances of each query residual to all codes: sums of table entries, one block of columns after
    another."""
    m, _, size = books.shape
    out = np.zeros((len(residuals), len(codes)))
    for b in range(m):
        part = residuals[:, None, b * size : (b + 1) * size]
        out += ((part - books[b][None]) ** 2).sum(axis=2)[:, codes[:, b]]
    return out


# ---- index ----------------------------------------------------------------------------------


@dataclass
class VectorIndex:
    """cells: centroids or None (no inverted file); books: codebooks or None (exact vectors in the lists)."""

    cells: np.ndarray | None
    books: np.ndarray | None
    codec: Codec = field(default_factory=IdentityCodec)
    by_residual: bool = True
    manifest: dict = field(default_factory=dict)
    encoded: DataFrame | None = None
    coarse: object | None = None

    # -- blocks
    def _coarse(self, z: np.ndarray, n: int = 1) -> np.ndarray:
        if self.coarse is not None:
            return self.coarse.search(z, n)
        return nearest(z, self.cells, n)[0]

    def encode_block(self, z: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Cells, codes and reconstructions of latents."""
        cell = self._coarse(z)[:, 0].astype(np.int32) if self.cells is not None else np.zeros(len(z), np.int32)
        base = self.cells[cell] if self.cells is not None and self.by_residual else np.zeros_like(z)
        if self.books is None:
            return cell, np.zeros((len(z), 0), np.uint8), z
        codes, approx = quantize(z - base, self.books)
        return cell, codes, base + approx

    def decode_block(self, cell: np.ndarray, codes: np.ndarray) -> np.ndarray:
        m, _, size = self.books.shape
        out = self.books[np.arange(m), codes].reshape(len(codes), m * size)
        return out + self.cells[cell] if self.cells is not None and self.by_residual else out

    # -- tables
    def encode(self, df: DataFrame, col: str = "x", id_column: str = "id") -> DataFrame:
        """(id, cell, codes, self_dist, z): one narrow pass. Without codebooks codes are empty and z is what is
        searched."""
        shared = df.sparkSession.sparkContext.broadcast(self._plain())

        def run(batches):
            index = shared.value
            for b in batches:
                if not b.num_rows:
                    continue
                z = index.codec.encode_block(matrix(b.column(1)))
                cell, codes, approx = index.encode_block(z)
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0),
                        pa.array(cell),
                        pa.array([c.tobytes() for c in codes], pa.binary()),
                        pa.array(np.sqrt(((z - approx) ** 2).sum(1))),
                        vectors(z),
                    ],
                    names=["id", "cell", "codes", "self_dist", "z"],
                )

        return df.select(F.col(id_column).cast("long").alias("id"), col).mapInArrow(
            run, "id long, cell int, codes binary, self_dist double, z array<double>"
        )

    def _plain(self) -> VectorIndex:
        return VectorIndex(self.cells, self.books, self.codec, self.by_residual, self.manifest, None, self.coarse)

    def code_dtype(self):
        return np.uint8 if self.books is None or self.books.shape[1] <= 256 else np.uint16

    def decode(self, encoded: DataFrame, out: str = "y") -> DataFrame:
        """(id, out): reconstructed latents."""
        shared = encoded.sparkSession.sparkContext.broadcast(self._plain())

        def run(batches):
            index = shared.value
            for b in batches:
                if not b.num_rows:
                    continue
                if index.books is None:
                    y = matrix(b.column(3))
                else:
                    y = index.decode_block(
                        b.column(1).to_numpy(),
                        np.frombuffer(b"".join(b.column(2).to_pylist()), index.code_dtype()).reshape(b.num_rows, -1),
                    )
                yield pa.RecordBatch.from_arrays([b.column(0), vectors(y)], names=["id", "y"])

        return encoded.select(
            "id", "cell", "codes", *(["z"] if self.books is None else [])
        ).mapInArrow(run, "id long, y array<double>").withColumnRenamed("y", out)

    def add(self, df: DataFrame, col: str = "x", id_column: str = "id") -> VectorIndex:
        """Fill the lists from `df` (frozen codebooks)."""
        more = self.encode(df, col, id_column)
        self.encoded = more if self.encoded is None else self.encoded.unionByName(more)
        return self

    append = add

    def materialize(self) -> VectorIndex:
        from nearcopy.components import materialize

        self.encoded = materialize(self.encoded.repartition("cell").sortWithinPartitions("cell", "id"))
        return self

    def search(
        self,
        queries: DataFrame,
        k: int,
        nprobe: int = 1,
        distance: str = "l2",
        col: str = "x",
        shards: int = 1,
        latent: bool = False,
        limit: str | None = None,
        ball: float | None = None,
        salt: int = 1,
        engine: str = "arrow",
    ) -> DataFrame:
        """(qid, nid, dist, rank): the k nearest database codes of each query in its nprobe cells; ties by id.

        distance: l2 or sq (squared). latent: `col` holds latents already. ball: instead of the k nearest all with a
        distance of at most (1 + ball) times the query's own self-distance (queries then have self_dist).
        shards: rows are split by id; each shard gives its own k nearest, in one scan for all, and these are merged;
        the result is the same. Few queries are sent to the lists, which never
        move; many meet the lists by a join on (cell, salt), each cell's rows spread over `salt` tasks. engine expr:
        lists are joined on the cell, and distances are expressions: sums of table entries, or over exact vectors
        (k nearest only).
        """
        from nearcopy.operators.search import merge_topk

        if distance not in ("l2", "sq"):
            raise ValueError(f"there is no distance {distance!r}")
        probes = self.probe(queries, nprobe, col, latent, keep_self=ball is not None)
        if engine == "expr":
            return self._search_expr(probes, k, distance == "sq")
        spark, shared = queries.sparkSession, queries.sparkSession.sparkContext.broadcast(self._plain())
        lists = self.encoded.select("id", "cell", "codes", *(["z"] if self.books is None else []))
        keep = _keeper(k, distance, ball)
        schema = "qid long, nid long, dist double"
        dim = self.cells.shape[1] if self.cells is not None else self.books.shape[0] * self.books.shape[2]
        few = max(1, BROADCAST_BYTES // (8 * dim))
        head = probes.limit(few + 1).toArrow()
        if head.num_rows <= few:
            at, z = head.column("cell").to_numpy(), matrix(head.column("z"))
            qid, own = head.column("qid").to_numpy(), head.column("self_dist").to_numpy() if ball is not None else None
            parts = {c: np.flatnonzero(at == c) for c in np.unique(at).tolist()}
            asked = spark.sparkContext.broadcast({c: (qid[p], z[p], None if own is None else own[p]) for c, p in parts.items()})

            def scan(batches):
                index = shared.value
                for b in batches:
                    cell, ids = b.column(1).to_numpy(), b.column(0).to_numpy()
                    payload = matrix(b.column(3)) if index.books is None else np.frombuffer(
                        b"".join(b.column(2).to_pylist()), index.code_dtype()
                    ).reshape(b.num_rows, -1)
                    for c, s in sorted(set(zip(cell.tolist(), (ids % shards).tolist(), strict=True))):
                        if c in asked.value:
                            mine = (cell == c) & (ids % shards == s)
                            yield from _answers(index, asked.value[c], int(c), ids[mine], payload[mine], keep, k, ball)

            found = lists.mapInArrow(scan, schema)
        else:
            left = probes.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))))
            right = lists.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salt)).cast("int"))

            def meet(key, q: pa.Table, db: pa.Table) -> pa.Table:
                index = shared.value
                if not q.num_rows or not db.num_rows:
                    return pa.table({"qid": pa.array([], pa.int64()), "nid": pa.array([], pa.int64()), "dist": pa.array([], pa.float64())})
                payload = matrix(db.column("z")) if index.books is None else np.frombuffer(
                    b"".join(db.column("codes").to_pylist()), index.code_dtype()
                ).reshape(db.num_rows, -1)
                asked = (
                    q.column("qid").to_numpy(),
                    matrix(q.column("z")),
                    q.column("self_dist").to_numpy() if ball is not None else None,
                )
                return pa.Table.from_batches(
                    list(_answers(index, asked, key[0].as_py(), db.column("id").to_numpy(), payload, keep, k, ball)),
                    schema=_FOUND,
                )

            found = left.groupBy("cell", "salt").cogroup(right.groupBy("cell", "salt")).applyInArrow(meet, schema)
        if ball is not None:
            return found.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy("dist", "nid")))
        return merge_topk(found, k)

    def _search_expr(self, probes: DataFrame, k: int, squared: bool) -> DataFrame:
        """Of each query the least distances of some groups of rows bound its k-th one, so that few rows are sorted."""
        from nearcopy.functions import linalg as L
        from nearcopy.operators.search import merge_topk

        if self.books is None:
            asked, lists = probes, self.encoded.select("id", "cell", F.col("z").alias("y"))
            dist = L.l2(F.col("z"), F.col("y"))
            dist = dist * dist if squared else dist
        else:
            asked, lists = self._tables(probes), self._places(self.encoded)
            dist = F.col("entries")[F.col("p0")]
            for b in range(1, len(self.books)):
                dist = dist + F.col("entries")[F.col(f"p{b}")]
            dist = dist if squared else F.sqrt(dist)
        asked, lists = spread(asked), few_rows(lists, 1 << 18)
        met = asked.join(lists, "cell")
        group = F.pmod(F.xxhash64("id"), F.lit(8 * k)).alias("g")
        least = met.select("qid", group, dist.alias("dist")).groupBy("qid", "g").agg(F.min("dist").alias("d"))
        least = least.groupBy("qid").agg(F.sort_array(F.collect_list("d")).alias("d"))
        least = least.where(F.size("d") >= k).select(F.col("qid").alias("q"), F.col("d")[k - 1].alias("most"))
        near = asked.join(least, F.col("qid") == F.col("q"), "left").join(lists, "cell")
        near = near.select("qid", F.col("id").alias("nid"), dist.alias("dist"), "most")
        return merge_topk(near.where("most is null or dist <= most + 1e-11 * (1 + most)").drop("most"), k)

    def _tables(self, probes: DataFrame) -> DataFrame:
        """(qid, cell, entries): squared distances of a query's residual to all codewords, one block after another."""
        shared = probes.sparkSession.sparkContext.broadcast(self._plain())

        def run(batches):
            index = shared.value
            m, codes, size = index.books.shape
            for b in batches:
                for lo in range(0, b.num_rows, 64):
                    part = b.slice(lo, 64)
                    z, cell = matrix(part.column(2)), part.column(1).to_numpy()
                    z = z - index.cells[cell] if index.cells is not None and index.by_residual else z
                    parts = [((z[:, None, i * size : (i + 1) * size] - index.books[i][None]) ** 2).sum(axis=2) for i in range(m)]
                    yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), vectors(np.hstack(parts))], names=["qid", "cell", "entries"])

        return probes.select("qid", "cell", "z").mapInArrow(run, "qid long, cell int, entries array<double>")

    def _places(self, encoded: DataFrame) -> DataFrame:
        """(id, cell, p0, p1, ...): where a row's codes stand in such a table."""
        (m, codes, _), kind = self.books.shape, self.code_dtype()
        names = ["id", "cell", *(f"p{b}" for b in range(m))]

        def run(batches):
            for b in batches:
                if b.num_rows:
                    at = np.frombuffer(b"".join(b.column(2).to_pylist()), kind).reshape(b.num_rows, m)
                    at = at.astype(np.int32) + np.arange(m, dtype=np.int32) * codes
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array(v) for v in at.T.copy())], names=names)

        return encoded.select("id", "cell", "codes").mapInArrow(run, "id long, cell int" + "".join(f", {n} int" for n in names[2:]))

    def search_ball(
        self, queries: DataFrame, tol: float, nprobe: int = 1, col: str = "x", latent: bool = False, salt: int = 1
    ) -> DataFrame:
        return self.search(queries, 0, nprobe, "l2", col, 1, latent, None, tol, salt)

    def probe(
        self, queries: DataFrame, nprobe: int, col: str = "x", latent: bool = False, keep_self: bool = False
    ) -> DataFrame:
        """(qid, cell, z): each query once for each of its nprobe nearest cells."""
        shared = queries.sparkSession.sparkContext.broadcast(self._plain())
        names = ["qid", "cell", "z", *(["self_dist"] if keep_self else [])]

        def run(batches):
            index = shared.value
            for b in batches:
                if not b.num_rows:
                    continue
                z = matrix(b.column(1))
                z = z if latent else index.codec.encode_block(z)
                cells = index._coarse(
                    z, min(nprobe, len(index.cells))
                ) if index.cells is not None else np.zeros((len(z), 1), np.int64)
                again = np.repeat(np.arange(len(z)), cells.shape[1])
                more = [b.column(2).take(pa.array(again))] if keep_self else []
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0).take(pa.array(again)),
                        pa.array(cells.ravel().astype(np.int32)),
                        vectors(z[again]),
                        *more,
                    ],
                    names=names,
                )

        return queries.select(F.col("id").alias("qid"), col, *(["self_dist"] if keep_self else [])).mapInArrow(
            run, "qid long, cell int, z array<double>" + ", self_dist double" * keep_self
        )

    def bytes_per_vector(self) -> int:
        return 0 if self.books is None else self.books.shape[0] * self.code_dtype()().itemsize

    def size_bytes(self, n: int) -> int:
        """Codes, ids (8) and cells (4) of n rows, and the tables."""
        tables = sum(4 * a.size for a in (self.cells, self.books) if a is not None)
        return n * (self.bytes_per_vector() + 12) + tables

    # -- store
    def save(self, path: str, spark: SparkSession, groups: int = 64) -> None:
        """Parameters as one row a tensor, the lists by groups of cells, and, last of all, a manifest."""
        sides = ("image", "image_bias", "text", "text_bias", "back", "back_bias")
        tensors = {f"codec.{k}": getattr(self.codec, k) for k in sides} | {"cells": self.cells, "books": self.books}
        rows = []
        for name, v in tensors.items():
            if v is not None:
                rows.append((name, list(v.shape), bytearray(np.ascontiguousarray(v, "<f8").tobytes())))
        table = spark.createDataFrame(rows, "name string, shape array<int>, data binary")
        table.coalesce(1).write.mode("overwrite").parquet(f"{path}/tensors")
        if self.encoded is not None:
            _write_lists(self.encoded, path, groups, "overwrite")
        about = {
            "by_residual": self.by_residual, "kind": self.codec.kind, "codec": self.codec.manifest, "groups": groups
        }
        links = getattr(self.coarse, "links", None)
        _write_manifest(about | {"index": self.manifest, "links": links, "version": 1}, path, spark)

    @staticmethod
    def append_to(path: str, df: DataFrame, col: str = "x", id_column: str = "id") -> int:
        """Encode further rows with the saved parameters and add them to the saved lists; returns the new version."""
        spark = df.sparkSession
        about, index = _read_manifest(path, spark), VectorIndex.load(path, spark)
        index.encoded = None
        _write_lists(index.add(df, col, id_column).encoded, path, about["groups"], "append")
        _write_manifest(about | {"version": about.get("version", 1) + 1}, path, spark)
        return about.get("version", 1) + 1

    @staticmethod
    def load(path: str, spark: SparkSession) -> VectorIndex:
        """The coarse graph, if there was one, is built again from the centroids, which is deterministic."""
        about, tensors = _read_manifest(path, spark), {}
        for name, shape, data in spark.read.parquet(f"{path}/tensors").collect():  # one row a tensor
            tensors[name] = np.frombuffer(bytes(data), "<f8").reshape(list(shape)).copy()
        sides = {
            k: tensors.get(f"codec.{k}") for k in ("image", "image_bias", "text", "text_bias", "back", "back_bias")
        }
        codec = Codec(about["kind"], **sides, manifest=about["codec"])
        lists = spark.read.parquet(f"{path}/lists").drop("cell_group")
        index = VectorIndex(
            tensors.get("cells"), tensors.get("books"), codec, about["by_residual"], about["index"], lists
        )
        if about.get("links") and index.cells is not None:
            from nearcopy.operators.smallworld import SmallWorldCoarse

            index.coarse = SmallWorldCoarse(index.cells, about["links"])
        return index


def _write_lists(encoded: DataFrame, path: str, groups: int, mode: str) -> None:
    rows = encoded.withColumn("cell_group", F.pmod("cell", F.lit(groups))).repartition("cell_group")
    rows.sortWithinPartitions("cell", "id").write.mode(mode).partitionBy("cell_group").parquet(f"{path}/lists")


def _write_manifest(about: dict, path: str, spark: SparkSession) -> None:
    line = spark.createDataFrame([(json.dumps(about, default=float),)], "manifest string")
    line.coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")


def _read_manifest(path: str, spark: SparkSession) -> dict:
    return json.loads(spark.read.parquet(f"{path}/manifest").first()[0])


_FOUND = pa.schema([("qid", pa.int64()), ("nid", pa.int64()), ("dist", pa.float64())])


def _keeper(k, distance, ball):
    """Chooses (query, row) pairs from a block of squared distances: the k nearest of each query, ties by id, or all
    in its ball."""

    def keep(d2: np.ndarray, ids: np.ndarray, self_dist) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        d = np.sqrt(d2)
        if ball is not None:
            q, r = np.nonzero(d <= ((1 + ball) * self_dist + 1e-12)[:, None])
        elif d.shape[1] > k:
            border = np.partition(d, k - 1, axis=1)[:, k - 1]
            q, r = np.nonzero(d <= (border + 1e-9 * (1 + border))[:, None])
            order = np.lexsort((ids[r], np.round(d[q, r], 12), q))
            q, r = q[order], r[order]
            first = np.arange(len(q)) - np.searchsorted(q, q) < k
            q, r = q[first], r[first]
        else:
            q, r = np.indices(d.shape).reshape(2, -1)
        return q, r, (d2 if distance == "sq" else d)[q, r]

    keep.squared = distance == "sq"
    return keep


def _exact_squares(z: np.ndarray, payload: np.ndarray, k: int, bound) -> np.ndarray:
    """Squared distances by one product; those that can be kept are worked out again by differences (others may be
    off by rounding)."""
    d2 = fast_squared_distances(z, payload)
    slack = 1e-6 * (1 + (z * z).sum(1))
    if bound is not None:
        limit = bound**2 + slack
    elif d2.shape[1] > k:
        limit = np.partition(d2, k - 1, axis=1)[:, k - 1] + slack
    else:
        limit = np.full(len(z), np.inf)
    q, r = np.nonzero(d2 <= limit[:, None])
    step = max(1, TILE // z.shape[1])
    for i in range(0, len(q), step):
        a, b = q[i : i + step], r[i : i + step]
        d2[a, b] = ((z[a] - payload[b]) ** 2).sum(axis=1)
    return d2


def _answers(
    index: VectorIndex, asked, cell: int, ids: np.ndarray, payload: np.ndarray, keep, k: int, ball: float | None
):
    """Blocks of queries against all rows of a list; TILE distances are held at a time."""
    qids, z, self_dist = asked
    if ball is None:  # of rows with equal codes those with the smallest ids are enough
        some = classes(ids, payload)[1] < k
        ids, payload = ids[some], payload[some]
    base = index.cells[cell] if index.cells is not None and index.by_residual else 0.0
    rows = min(len(ids), TILE // 16)
    for lo in range(0, len(ids), max(1, rows)):
        part, names = payload[lo : lo + rows], ids[lo : lo + rows]
        if index.books is None:
            step = max(1, TILE // rows)
            for i in range(0, len(qids), step):
                block, own = z[i : i + step], None if self_dist is None else self_dist[i : i + step]
                d2 = _exact_squares(block, part, k, None if own is None else (1 + ball) * own)
                q, r, d = keep(d2, names, own)
                if len(q):
                    yield _found(qids[i + q], names[r], d)
        else:
            limit = None if ball is None else (1 + ball) * self_dist
            q, r, d2 = _near_codes(z - base, index.books, part, k, limit)
            for i in range(0, len(qids), 4096):
                own = slice(*np.searchsorted(q, (i, i + 4096)))
                yield from _kept(qids, names, q[own], r[own], d2[own], k, keep.squared, limit)


def _found(qids, names, d) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(qids), pa.array(names), pa.array(d)], schema=_FOUND)


def _kept(qids, names, q, r, d2, k, squared, limit):
    """Of candidate pairs, by query, the k nearest of each, ties by id, or all within its limit."""
    d = np.sqrt(d2)
    if limit is not None:
        good = np.flatnonzero(d <= limit[q] + 1e-12)
    else:
        order = np.lexsort((names[r], np.round(d, 12), q))
        good = order[np.arange(len(q)) - np.searchsorted(q, q) < k]
    if len(good):
        yield _found(qids[q[good]], names[r[good]], (d2 if squared else d)[good])


def _near_codes(residuals: np.ndarray, books: np.ndarray, codes: np.ndarray, k: int, limit: np.ndarray | None):
    """(query, row, squared distance) of all pairs that can be among a query's k nearest, or within its limit, ordered by
    query. The distances are lookup_distances'; one product with what the codes stand for tells which are needed."""
    m, _, size = books.shape
    near = books[np.arange(m), codes].reshape(len(codes), m * size)
    tile, out = Tile(residuals, near), []
    step = max(1, 2 * TILE // len(codes))
    for lo in range(0, len(residuals), step):
        d = tile.at(lo, lo + step)
        if limit is not None:
            most = np.square((limit[lo : lo + step] + 1e-12) * tile.scale)
        elif len(codes) > k:
            most = np.partition(d, k - 1, axis=1)[:, k - 1]
        else:
            most = np.full(len(d), np.inf)
        q, r = places(d <= (most + tile.slack).astype(tile.kind)[:, None])
        d2, wide = np.zeros(len(q)), max(1, TILE // (m * size))
        for i in range(0, len(q), wide):
            gap = (residuals[q[i : i + wide] + lo] - near[r[i : i + wide]]).reshape(-1, m, size)
            parts = (gap * gap).sum(axis=2)
            for b in range(m):
                d2[i : i + wide] += parts[:, b]
        out.append((q + lo, r, d2))
    return (np.concatenate(c) for c in zip(*out, strict=True))


def _latents(df: DataFrame, col: str, codec: Codec) -> DataFrame:
    return codec.encode(df.select("id", col), col, "z").select("id", "z")


def build_index(
    df: DataFrame,
    col: str = "x",
    k_cells: int = 65536,
    m: int | None = 4,
    bits: int = 8,
    codec: Codec | None = None,
    iters: int = 10,
    init: str = "first",
    by_residual: bool = True,
    train_sample: int | None = None,
    seed: int = 0,
    add: bool = True,
    coarse: str = "exact",
    links: int = 32,
) -> VectorIndex:
    """Inverted file with product codes. k_cells = 0: no inverted file; m = None: exact vectors in the lists.
    Codebooks are trained on the driver
    on a sample by hash of at most max(train_sample or TRAIN_ROWS, 2**bits) rows (init first: they start at its
    smallest ids), cells on the whole
    table or about `train_sample` rows of it."""
    given = (bits, codec, iters, init, by_residual, train_sample, seed, add, coarse, links)
    return _build(df, col, k_cells, (m,), *given)[m]


def build_indexes(
    df: DataFrame,
    col: str,
    k_cells: int,
    ms: tuple[int, ...],
    bits: int,
    codec: Codec | None,
    iters: int,
    rows: np.ndarray | None = None,
    cells: np.ndarray | None = None,
) -> dict[int, VectorIndex]:
    """What build_index gives for each m; cells and the sample for codebooks are worked out once. Where several codecs are
    tried on a table, rows are its codebook_rows and cells what kmeans_of_all gives for the codec."""
    return _build(df, col, k_cells, ms, bits, codec, iters, "first", True, None, 0, True, "exact", 32, rows, cells)


def codebook_rows(df: DataFrame, col: str = "x", bits: int = 8) -> np.ndarray:
    """The vectors that build_indexes trains codebooks on: which rows they are is the same for all codecs."""
    rows = hash_sample(df.select("id", col), max(TRAIN_ROWS, 1 << bits), "id")
    return matrix(rows.orderBy("id").select(col).toArrow().column(0))


def _build(df, col, k_cells, ms, bits, codec, iters, init, by_residual, train_sample, seed, add, coarse, links, rows=None, cells=None):
    codec = codec or IdentityCodec()
    z = _latents(df, col, codec)
    if cells is None and k_cells:
        cells = kmeans(z, "z", k_cells, iters, init, train_sample, seed)[0]
    if any(ms):
        if rows is None:
            some = hash_sample(z, max(train_sample or TRAIN_ROWS, 1 << bits), "id")
            x = matrix((some.orderBy("id") if init == "first" else some).select("z").toArrow().column(0))
        else:
            x = codec.encode_block(rows)
        if not len(x):
            raise ValueError("there are no vectors")
        if cells is not None and by_residual:
            x = x - cells[nearest(x, cells)[0][:, 0]]
    out = {}
    for m in ms:
        index = out[m] = VectorIndex(
            cells,
            fit_codebooks(x, m, min(1 << bits, len(x)), iters) if m else None,
            codec,
            by_residual,
            {"k_cells": k_cells, "m": m, "bits": bits, "seed": seed, "init": init, "iters": iters},
        )
        if coarse == "graph" and cells is not None:
            from nearcopy.operators.smallworld import SmallWorldCoarse

            index.coarse = SmallWorldCoarse(cells, links)
        if add:
            index.add(df, col)
    return out


def seeded_index(
    df: DataFrame,
    col: str = "x",
    k_cells: int = 8,
    m: int = 8,
    codes: int = 16,
    by_residual: bool = True,
    rounds: int = 0,
) -> VectorIndex:
    """The index whose centroids and codewords are the first rows by id (after `rounds` rounds for the cells): what
    SQL can do as well."""
    cells = kmeans(df.select("id", col), col, k_cells, rounds, "first")[0] if k_cells else None
    x = first_rows(df, col, codes)
    if cells is not None and by_residual:
        x = x - cells[nearest(x, cells)[0][:, 0]]
    return VectorIndex(
        cells, fit_codebooks(x, m, codes, 0), IdentityCodec(), by_residual, {"seeded": True}
    ).add(df, col)

"""De-duplication of arriving vectors with frozen codebooks, code counts by state, and event-time counts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from nearcopy.components import shared_dir
from nearcopy.functions.blocks import TILE, fast_squared_distances, matrix
from nearcopy.operators.index import VectorIndex


class IncrementalDedup:
    """foreachBatch target. An arriving row is the database side and all earlier rows (and those of its batch with
    smaller ids) ask, as in
    the ordered loop; its parent is the largest id that flags it, within the ball of the query's tolerance. Earlier
    latents are kept in
    the shared folder. Equal to the batch result in ball mode, in any order of arrival. A batch that is run again is
    replaced, not added."""

    def __init__(
        self, index: VectorIndex, tol: float = 0.01, path: str | None = None, spark: SparkSession | None = None
    ):
        self.index, self.tol = index, tol
        self.path = path or shared_dir(spark)

    def _old(self, spark: SparkSession, batch_id: int, kind: str) -> DataFrame | None:
        try:
            return spark.read.parquet(f"{self.path}/{kind}").where(F.col("batch") < batch_id)
        except Exception as e:  # nothing has been written yet
            if "PATH_NOT_FOUND" in str(e) or "UNABLE_TO_INFER_SCHEMA" in str(e):
                return None
            raise

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        new = self.index.encode(batch.dropDuplicates(["id"]))
        before = self._old(spark, batch_id, "latents")
        if before is not None:
            new = new.join(before.select("id"), "id", "left_anti")
        new.write.mode("overwrite").parquet(f"{self.path}/latents/batch={batch_id}")
        new = spark.read.schema(new.schema).parquet(f"{self.path}/latents/batch={batch_id}")
        found = self._parents(new if before is None else new.unionByName(before.select(*new.columns)), new)
        if before is not None:  # a smaller id that comes later asks those that are there
            found = found.unionByName(self._parents(new, before))
        found = found.groupBy("j").agg(F.max("parent").alias("parent"))
        found.write.mode("overwrite").parquet(f"{self.path}/parents/batch={batch_id}")

    def _parents(self, asking: DataFrame, db: DataFrame) -> DataFrame:
        """(j, parent): of each row of db the largest smaller id that flags it. Rows with equal codes are rebuilt alike, so each
        code of a cell meets the asking rows once; a cell's codes are dealt to several tasks."""
        spark = db.sparkSession
        shared, tol = spark.sparkContext.broadcast(self.index._plain()), self.tol
        salt = spark.sparkContext.defaultParallelism
        left = asking.select("id", "cell", "z", "self_dist")
        left = left.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))))
        right = db.select("id", "cell", "codes", "z", F.pmod(F.xxhash64("codes"), F.lit(salt)).cast("int").alias("salt"))

        def meet(q: pa.Table, y: pa.Table) -> pa.Table:
            out = last_flagging(shared.value, q, y, tol) if q.num_rows and y.num_rows else ([], [])
            return pa.table({"j": pa.array(out[0], pa.int64()), "parent": pa.array(out[1], pa.int64())})

        met = left.groupBy("cell", "salt").cogroup(right.groupBy("cell", "salt"))
        return met.applyInArrow(meet, "j long, parent long")

    def representatives(self, spark: SparkSession) -> DataFrame:
        from nearcopy.operators.dedup import pointer_jump

        ids = spark.read.parquet(f"{self.path}/latents").select("id")
        return pointer_jump(
            spark.read.schema(
                "j long, parent long"
            ).parquet(f"{self.path}/parents").groupBy("j").agg(F.max("parent").alias("parent")),
            ids,
        )


def last_flagging(index: VectorIndex, q: pa.Table, y: pa.Table, tol: float) -> tuple[np.ndarray, np.ndarray]:
    """Of a cell's asking rows q and rows y: each row of y that smaller ids flag, and the largest of them. TILE distances
    are held at a time; those near the test's bounds are worked out again by differences."""
    ids, own = q.column("id").to_numpy(), q.column("self_dist").to_numpy()
    order = np.argsort(ids, kind="stable")
    ids, own, z = ids[order], own[order], matrix(q.column("z"))[order]
    codes, first, which = np.unique(
        np.array(y.column("codes").to_pylist(), object) if index.books is not None else np.arange(y.num_rows),
        return_index=True,
        return_inverse=True,
    )
    cell = y.column("cell").to_numpy()[first]
    if index.books is None:
        rebuilt = matrix(y.column("z"))
    else:
        rebuilt = index.decode_block(cell, np.frombuffer(b"".join(codes), index.code_dtype()).reshape(len(codes), -1))
    members = np.argsort(which, kind="stable")
    bounds = np.searchsorted(which[members], np.arange(len(codes) + 1))
    names, js, parents = y.column("id").to_numpy(), [], []
    exact = own <= 1e-12
    low, high = own - np.where(exact, 1e-12, own * tol), own + np.where(exact, 1e-12, own * tol)
    slack = 1e-7 * (1 + (z * z).sum(1))
    low2, high2 = np.where(low > 0, low * low, -1.0) - slack, high * high + slack
    step = max(1, TILE // max(1, len(ids)))
    for lo in range(0, len(codes), step):
        part = rebuilt[lo : lo + step]
        d2 = fast_squared_distances(part, z)
        c, r = np.nonzero((d2 >= low2) & (d2 <= high2))
        flags = np.zeros(len(c), bool)
        for i in range(0, len(c), max(1, TILE // z.shape[1])):
            at = slice(i, i + max(1, TILE // z.shape[1]))
            d = np.sqrt(((part[c[at]] - z[r[at]]) ** 2).sum(axis=1))
            gap, mine = np.abs(own[r[at]] - d), own[r[at]]
            flags[at] = np.where(mine <= 1e-12, gap <= 1e-12, gap < mine * tol)
        c, r = c[flags], r[flags]
        ends = np.searchsorted(c, np.arange(len(part) + 1))
        for k in range(len(part)):
            asked = ids[r[ends[k] : ends[k + 1]]]  # ascending
            own_names = names[members[bounds[lo + k] : bounds[lo + k + 1]]]
            place = np.searchsorted(asked, own_names)
            some = place > 0
            js.append(own_names[some])
            parents.append(asked[place[some] - 1])
    return np.concatenate(js), np.concatenate(parents)


def code_dedup(stream: DataFrame, index: VectorIndex, delay: str = "1 hour") -> DataFrame:
    """The first arrival of each code within the watermark."""
    coded = _coded(stream, index)
    return coded.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["cell", "codes"])


def _coded(stream: DataFrame, index: VectorIndex) -> DataFrame:

    plain = index._plain()

    @F.pandas_udf("struct<cell:int,codes:binary>")
    def code(v: pd.Series) -> pd.DataFrame:
        z = plain.codec.encode_block(np.array(v.tolist(), float))
        cell, codes, _ = plain.encode_block(z)
        return pd.DataFrame({"cell": cell, "codes": [c.tobytes() for c in codes]})

    return stream.withColumn("_c", code("x")).select(
        "ts", "id", F.col("_c.cell").alias("cell"), F.col("_c.codes").alias("codes")
    )


def rep_state(stream: DataFrame, index: VectorIndex, keep_ms: int | None = None) -> DataFrame:
    """(code, rep, n): for each code the smallest id and the arrivals so far; with keep_ms a code that stays away for
    so long (processing time) is
    forgotten; such a query runs batches without data, so it isn't for availableNow."""

    def update(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rep, n = state.get if state.exists else (2**62, 0)
        for b in batches:
            rep, n = min(rep, int(b["id"].min())), n + len(b)
        state.update((rep, n))
        if keep_ms is not None:
            state.setTimeoutDuration(keep_ms)
        yield pd.DataFrame({"code": [key[0]], "rep": [rep], "n": [n]})

    coded = _coded(stream, index).select(
        "id", F.concat(F.col("cell").cast("string"), F.lit(":"), F.hex("codes")).alias("code")
    )
    return coded.groupBy("code").applyInPandasWithState(
        update,
        "code string, rep long, n long",
        "rep long, n long",
        "update",
        "NoTimeout" if keep_ms is None else "ProcessingTimeTimeout",
    )


def windowed_counts(
    stream: DataFrame, window: str = "1 hour", slide: str | None = None, delay: str = "2 hours"
) -> DataFrame:
    """(w, event_type, n): arrivals by event time; in append mode rows behind the watermark are dropped (the query's
    progress counts them)."""
    frame = F.window("ts", window, slide) if slide else F.window("ts", window)
    counts = stream.withWatermark("ts", delay).groupBy(frame, "event_type").agg(F.count("*").alias("n"))
    return counts.select(F.col("window.start").alias("w"), "event_type", "n")


def session_counts(stream: DataFrame, gap: str = "2 hours", delay: str = "4 hours") -> DataFrame:
    """(user_id, w, n): arrivals of each user without a pause of `gap`."""
    counts = stream.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap).alias("s"))
    return counts.agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("w"), "n")


def purchases_after_clicks(
    clicks: DataFrame, purchases: DataFrame, within: str = "1 hour", delay: str = "2 hours"
) -> DataFrame:
    """(click_id, event_id, clicked, bought): a stream-stream join with a time bound."""
    a = clicks.withWatermark("ts", delay)
    a = a.select(F.col("user_id").alias("u"), F.col("ts").alias("clicked"), F.col("event_id").alias("click_id"))
    b = purchases.withWatermark("ts", delay).select("user_id", F.col("ts").alias("bought"), "event_id")
    near = F.expr(f"bought >= clicked AND bought <= clicked + INTERVAL {within}")
    return a.join(b, (F.col("u") == F.col("user_id")) & near).select("click_id", "event_id", "clicked", "bought")


def with_labels(stream: DataFrame, labels: DataFrame) -> DataFrame:
    """A stream-static join: each arrival with what a table of (id, label) says of its vector; others stay, without a
    label."""
    return stream.join(labels.select("id", "label"), "id", "left")

"""Training losses, as NumPy functions with gradients and as measures over a DataFrame."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F


def unit_rows(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    size = np.where(size > 0, size, 1.0)
    return x / size, size


def contrastive(
    u: np.ndarray, v: np.ndarray, temperature: float = 0.07, mask: np.ndarray | None = None
) -> tuple[float, np.ndarray, np.ndarray]:
    """Symmetric cross-entropy of matching row i of u with row i of v among the batch, and its gradients.

    mask: pairs (i, j) that don't count as negatives."""
    a, size_a = unit_rows(u)
    b, size_b = unit_rows(v)
    s = a @ b.T / temperature
    if mask is not None:
        s = np.where(mask & ~np.eye(len(s), dtype=bool), -np.inf, s)
    n = len(s)

    def soft(x, axis):
        e = np.exp(x - x.max(axis=axis, keepdims=True))
        total = e.sum(axis=axis, keepdims=True)
        return e / total, np.log(total) + x.max(axis=axis, keepdims=True)

    p, lp = soft(s, 1)
    q, lq = soft(s, 0)
    diagonal = np.diag(s)
    loss = float(((lp[:, 0] - diagonal).mean() + (lq[0] - diagonal).mean()) / 2)
    ds = p + q
    ds[np.diag_indices(n)] -= 2
    ds /= 2 * n * temperature
    da, db = ds @ b, ds.T @ a
    return loss, (da - a * (a * da).sum(1, keepdims=True)) / size_a, (db - b * (b * db).sum(1, keepdims=True)) / size_b


def by_batches(df: DataFrame, columns: list[str], batch: int, f) -> DataFrame:
    """(batch_id, n, loss): f on the matrices of each run of `batch` ids (batch_id = floor(id / batch)); a batch is
    one task's rows."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("id")
        return pd.DataFrame({"batch_id": [int(rows["batch_id"].iloc[0])], "n": [len(rows)], "loss": [f(*[np.array(rows[c].tolist(), float) for c in columns])]})

    return df.withColumn("batch_id", F.floor(F.col("id") / batch)).groupBy("batch_id").applyInPandas(
        run, "batch_id long, n long, loss double"
    )


def mean_loss(per_batch: DataFrame) -> DataFrame:
    return per_batch.agg((F.sum(F.col("loss") * F.col("n")) / F.sum("n")).alias("loss"))


def mse_loss(df: DataFrame, codec, col: str = "x", batch: int = 256) -> DataFrame:
    return mean_loss(by_batches(df, [col], batch, lambda x: float(((x - codec.decode_block(codec.encode_block(x))) ** 2).sum(axis=1).mean())))


def contrastive_loss(
    df: DataFrame, codec, batch: int = 256, temperature: float = 0.07, image: str = "x", text: str = "t"
) -> DataFrame:
    return mean_loss(by_batches(df, [image, text], batch, lambda x, t: contrastive(codec.encode_block(t, "text"), codec.encode_block(x), temperature)[0]))


def npcc_loss(
    df: DataFrame,
    codec,
    batch: int = 256,
    temperature: float = 0.07,
    lam: float = 1.0,
    image: str = "x",
    text: str = "t",
    near: str = "x_nn",
) -> DataFrame:
    """With a neighbour column: the paired loss plus lam times that between an image and its nearest one."""

    def both(x, t, y):
        zx, zt, zy = codec.encode_block(x), codec.encode_block(t, "text"), codec.encode_block(y)
        return contrastive(zt, zx, temperature)[0] + lam * contrastive(zx, zy, temperature)[0]

    return mean_loss(by_batches(df, [image, text, near], batch, both))

"""Hashed text features and the derived fixtures."""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from nearcopy.functions import linalg as L
from nearcopy.functions.blocks import matrix, spread, vectors

_gap = re.compile(r"[\W_]+")


def words(text: str | None) -> list[str]:
    return _gap.sub(" ", (text or "").lower()).split()


def leading_words(text: str | None, n: int | None) -> list[str]:
    """The first n words, without taking all of a long text apart. A cut word is the last one of its piece, and how the
    word before it is lower-cased can depend on it."""
    text, size = text or "", 16 * (n or 0)
    while n is not None and size < len(text):
        found = words(text[:size])
        if len(found) >= n + 2:
            return found[:n]
        size *= 4
    return words(text)[:n]


def grams(tokens: list[str], unigrams: bool = False) -> list[str]:
    """Word pairs (the word itself if there is only one), and the single words too if asked for."""
    pairs = [f"{a} {b}" for a, b in zip(tokens, tokens[1:], strict=False)] or tokens[:1]
    return pairs + tokens if unigrams else pairs


def hashed_rows(texts: list[list[str]], dim: int, salt: str) -> np.ndarray:
    """One normalised row a list of parts. The md5 of each part gives its bucket (first 32 bits) and its sign (the
    next 4)."""
    head = hashlib.md5(salt.encode())
    digests = []
    for parts in texts:
        for part in parts:
            h = head.copy()
            h.update(part.encode())
            digests.append(h.digest())
    codes = np.frombuffer(b"".join(digests), np.uint8).reshape(-1, 16)
    bucket = np.ascontiguousarray(codes[:, :4]).view(">u4")[:, 0] % dim
    sign = np.where(codes[:, 4] >> 4 & 1, -1.0, 1.0)
    row = np.repeat(np.arange(len(texts)), [len(p) for p in texts])
    out = np.bincount(row * dim + bucket, sign, len(texts) * dim).reshape(-1, dim)
    size = np.sqrt((out * out).sum(axis=1, keepdims=True))
    return np.divide(out, size, out=np.zeros_like(out), where=size > 0)


def hashed_ngrams(
    df: DataFrame,
    id_column: str = "doc_id",
    text: str = "text",
    out: str = "x",
    dim: int = 256,
    salt: str = "",
    unigrams: bool = False,
    first_words: int | None = None,
) -> DataFrame:
    """(id, out): signed hashed word-pair counts, L2-normalised. One pass; only a table of very few files is spread
    over the cores
    before. A text without words has zeros."""

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                texts = [grams(leading_words(t, first_words), unigrams) for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), vectors(hashed_rows(texts, dim, salt))], names=["id", out]
                )

    return spread(df.select(F.col(id_column).cast("long"), text)).mapInArrow(run, f"id long, {out} array<double>")


def doc_vec(docs: DataFrame) -> DataFrame:
    return hashed_ngrams(docs)


def doc_vec_b(docs: DataFrame) -> DataFrame:
    return hashed_ngrams(docs, salt="b:", unigrams=True)


def doc_cap(docs: DataFrame, out: str = "t") -> DataFrame:
    """The caption of a document is its first twelve words."""
    return hashed_ngrams(docs, out=out, first_words=12)


def emb(embeddings: DataFrame) -> DataFrame:
    return embeddings.select(F.col("vec_id").alias("id"), L.doubles(F.col("embedding")).alias("x"), "label")


def small_noise(id_column, salt: str, size: float, dim: int = 64):
    """A vector of `dim` values within +-size, from an md5 of salt, id and place."""
    return F.transform(
        F.sequence(F.lit(0), F.lit(dim - 1)),
        lambda i: (F.conv(F.substring(F.md5(F.concat(F.lit(salt), id_column.cast("string"), F.lit(":"), i.cast("string"))), 1, 4), 16, 10).cast("double") / 65535.0 - 0.5) * (2 * size),
    )


def with_disturbed(df: DataFrame, times: int, salt: str, size: float, step: int = 10_000_000) -> DataFrame:
    """Each row of (id, x, ...) `times` times under ids that are `step` apart; x of all but the first is disturbed by
    small_noise of the new id and normalised. The hashes are made in blocks of rows, not by expressions."""
    columns = df.columns
    places = (columns.index("id"), columns.index("x"))

    def run(batches):
        for b in batches:
            ids, x = b.column(places[0]).to_numpy(), matrix(b.column(places[1]))
            for r in range(times if b.num_rows else 0):
                new, y = ids + r * step, x
                if r:
                    ends = [b":%d" % i for i in range(x.shape[1])]
                    heads = [salt.encode() + b"%d" % i for i in new.tolist()]
                    found = b"".join([hashlib.md5(head + end).digest()[:2] for head in heads for end in ends])
                    noise = np.frombuffer(found, ">u2").reshape(x.shape) / 65535.0
                    y = x + (noise - 0.5) * (2 * size)
                    total = np.zeros(len(y))
                    for v in y.T:
                        total += v * v
                    y = y * np.divide(1, np.sqrt(total), out=np.ones(len(y)), where=total > 0)[:, None]
                out = list(b.columns)
                out[places[0]], out[places[1]] = pa.array(new, pa.int64()), vectors(y)
                yield pa.RecordBatch.from_arrays(out, names=columns)

    return spread(df).mapInArrow(run, df.schema)


def emb_pair(embeddings: DataFrame) -> DataFrame:
    """(id, x, t): the second side is the first with a small fixed disturbance, normalised."""
    e = emb(embeddings)
    return e.select("id", "x", L.normalise(L.add(F.col("x"), small_noise(F.col("id"), "pair:", 0.05))).alias("t"))


def emb_planted(embeddings: DataFrame, most: int = 256, jitter: float = 0.002) -> DataFrame:
    """(id, x, source_id): each vector with floor(most / (1 + id)) copies under new ids; odd ones are disturbed a
    little."""
    e = emb(embeddings).select("id", "x")
    copies = e.where(F.col("id") < most).withColumn(
        "r", F.explode(F.sequence(F.lit(1), F.floor(F.lit(most) / (1 + F.col("id"))).cast("int")))
    )
    copies = copies.select("id", "x", "r", (F.lit(1_000_000) * F.col("r") + F.col("id")).alias("new_id"))
    x = F.when(F.col("r") % 2 == 0, F.col("x")).otherwise(
        L.add(F.col("x"), small_noise(F.col("new_id"), "plant:", jitter))
    )
    planted = copies.select("new_id", x.alias("y"), "id").toDF("id", "x", "source_id")
    return e.select("id", "x", F.col("id").alias("source_id")).unionByName(planted)

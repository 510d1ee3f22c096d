"""What the training-data operators share: reading, the shared folder, byte and word kernels."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import json
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, functions as F
from pyspark.sql.types import StructType

from nearcopy.components import materialize  # noqa: F401  (the operators take it from here)
from nearcopy.functions.blocks import spread

#: Bytes of text that one kernel call looks at; the arrays made from it are about 8 to 100 times as large.
BLOCK_BYTES = 1 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table; one of fewer files than there are cores is dealt to all of them."""
    return spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def bloom_test(keys: DataFrame, column: str, max_words: int = 1 << 17) -> Callable[[Column], Column]:
    """A test that all keys pass and few others; of at most `max_words` 64-bit words (a fuller filter lets more
    through). No Python on the executors."""
    words = min(max_words, max(1, 1 << (keys.count() * 12 // 64).bit_length()))

    def spots(key: Column) -> list[Column]:
        return [F.pmod(F.xxhash64(key, F.lit(h)), F.lit(words * 64)) for h in range(4)]

    rows = keys.select(F.explode(F.array(*spots(F.col(column)))).alias("bit")).groupBy(
        F.shiftright("bit", 6).alias("word")
    ).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit & 63 as int))")).alias("value")).collect()
    filled = [0] * words
    for r in rows:
        filled[r["word"]] = r["value"]
    table = F.from_json(F.lit(json.dumps(filled)), "array<bigint>")

    def test(key: Column) -> Column:
        out = F.lit(True)
        for bit in spots(key):
            out = out & (F.getbit(F.element_at(table, (F.shiftright(bit, 6) + 1).cast("int")), F.pmod(bit, F.lit(64)).cast("int")) == 1)
        return F.coalesce(out, F.lit(False))

    return test


def bloom_rows(keys: DataFrame, column: str, max_words: int = 1 << 17) -> Callable[..., DataFrame]:
    """The same as a function of (df, key, inside=True): the rows that pass, or the others. The filter is a table of one row
    that is broadcast (1 MB at most), so that no plan holds it: the driver keeps many copies of plans and of their texts."""
    spark = keys.sparkSession
    words = min(max_words, max(1, 1 << (keys.count() * 12 // 64).bit_length()))

    def spots(key: Column) -> list[Column]:
        return [F.pmod(F.xxhash64(key, F.lit(h)), F.lit(words * 64)) for h in range(4)]

    filled = keys.select(F.explode(F.array(*spots(F.col(column)))).alias("bit")).groupBy(
        F.shiftright("bit", 6).alias("word")
    ).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit & 63 as int))")).alias("value"))
    every = spark.range(words).select(F.col("id").alias("word")).join(filled, "word", "left")
    pairs = F.array_sort(F.collect_list(F.struct("word", F.coalesce("value", F.lit(0).cast("long")).alias("value"))))
    table = materialize(every.agg(F.transform(pairs, lambda p: p["value"]).alias("_filter")))

    def rows(df: DataFrame, key: str, inside: bool = True) -> DataFrame:
        passes = F.lit(True)
        for bit in spots(F.col(key)):
            word = F.element_at("_filter", (F.shiftright(bit, 6) + 1).cast("int"))
            passes = passes & (F.getbit(word, F.pmod(bit, F.lit(64)).cast("int")) == 1)
        return df.join(F.broadcast(table), F.coalesce(passes, F.lit(False)), "left_semi" if inside else "left_anti")

    return rows


def check_columns(df: DataFrame, *names: str) -> None:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; there are {df.columns}")


# ---- memory of Python workers ---------------------------------------------------------------

_caches: dict[str, Callable[[], None]] = {}
_owner = ""


def give_back(map_bytes: int | None = 1 << 20) -> None:
    """Freed memory to the system; arrays of `map_bytes` and more are mapped, so that they go as soon as they are
    freed (None: as the system has it)."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only glibc has these
        libc = ctypes.CDLL(None)
        if map_bytes:
            libc.mallopt(-3, map_bytes)
        libc.malloc_trim(0)


def claim(name: str, clear: Callable[[], None] | None = None) -> None:
    """A Python worker serves one operator after another: the one that starts drops what others have cached."""
    global _owner
    if clear:
        _caches[name] = clear
    if _owner != name:
        for other, drop in _caches.items():
            if other != name:
                drop()
        _owner = name
        gc.collect()
        give_back(None)


def arrow_map(df: DataFrame, f: Callable, schema: str | StructType, map_bytes: int | None = 1 << 20) -> DataFrame:
    """df.mapInArrow(f, schema); a worker gives memory back before and after each task."""

    def run(batches):
        give_back(map_bytes)
        try:
            yield from f(batches)
        finally:
            give_back(map_bytes)

    return df.mapInArrow(run, schema)


# ---- text columns as flat byte arrays -------------------------------------------------------


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows one after another, and n + 1 offsets into them (null: empty)."""
    claim("blocks")
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column, b"" if pa.types.is_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    offsets = np.frombuffer(
        column.buffers()[1], np.int64 if wide else np.int32
    )[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    if not len(column) or data is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    whole = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]]
    return whole, offsets - offsets[0]


def blocks(offsets: np.ndarray, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most `limit` bytes each, or of one row that is longer by itself."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


# ---- word kernels ---------------------------------------------------------------------------

_rng = np.random.default_rng(20240229)
_CASE = np.arange(256, dtype=np.uint8)
_CASE[65:91] += 32
#: A random odd value for each byte; A-Z share those of a-z.
_BYTE_VALUE = (_rng.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1))[_CASE]
_BASE, _BASE_INVERSE = np.uint64(0x9E3779B97F4A7C15), np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_GRAM = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) | np.uint64(1)

#: Bytes of a word after lower-casing A-Z: digits, letters and everything from 0x80 on.
ALNUM_BYTES = np.zeros(256, bool)
ALNUM_BYTES[48:58] = ALNUM_BYTES[65:91] = ALNUM_BYTES[97:123] = ALNUM_BYTES[128:] = True
#: All bytes but blank, tab, line feed, vertical tab, form feed and carriage return.
SOLID_BYTES = np.ones(256, bool)
SOLID_BYTES[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False

_power_cache: dict[str, np.ndarray] = {}


def _powers(base: np.uint64, n: int, name: str) -> np.ndarray:
    have = _power_cache.get(name)
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        have = np.full(size, base, np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        if size <= 1 << 22:
            _power_cache[name] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x81DADEF4BC2DD44D)
    x ^= x >> np.uint64(33)
    return x


class Words:
    """Words of a block of documents: byte ranges, hashes and the document of each."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, kind: np.ndarray):
        """data: bytes of the block; offsets: n + 1 offsets of its documents, from 0; kind: which bytes are in words."""
        n = len(data)
        inside = kind[data]
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        last = inside.copy()
        last[:-1] &= ~inside[1:]
        edges = offsets[(offsets > 0) & (offsets < n)]
        first[edges] = inside[edges]
        last[edges - 1] = inside[edges - 1]
        self.starts, self.ends = np.flatnonzero(first), np.flatnonzero(last) + 1
        self.bounds = np.searchsorted(self.starts, offsets)  # first word of each document
        self.counts = np.diff(self.bounds)
        values = _BYTE_VALUE[data]
        values *= _powers(_BASE, n, "up")
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(values, out=sums[1:])
        hashes = sums[self.ends] - sums[self.starts]
        hashes *= _powers(_BASE_INVERSE, n, "down")[self.starts] if n else np.zeros(0, np.uint64)
        self.hashes = mix(hashes + (self.ends - self.starts).astype(np.uint64))

    def grams(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hash of words i .. i+k-1 for each i, and whether these lie in one document."""
        n = len(self.hashes)
        if n < k:
            return np.zeros(n, np.uint64), np.zeros(n, bool)
        out = np.zeros(n, np.uint64)
        m = n - k + 1
        for j in range(k):
            out[:m] += self.hashes[j : j + m] * _GRAM[j]
        left = np.repeat(self.bounds[1:], self.counts) - np.arange(n)
        return mix(out), left >= k


def sliding(op: Callable, x: np.ndarray, width: int) -> np.ndarray:
    """op (np.minimum or np.maximum) over x[i : i + width], for each i with a full window."""
    out, have = x, 1
    while have * 2 <= width:
        out = op(out[: len(out) - have], out[have:])
        have *= 2
    if have < width:
        rest = width - have
        out = op(out[: len(out) - rest], out[rest:])
    return out


def window_minima(x: np.ndarray, width: int) -> np.ndarray:
    """Where x is the minimum of at least one run of `width` values (ties: all of them)."""
    n = len(x)
    if n < width:
        return np.zeros(n, bool)
    low = sliding(np.minimum, x, width)
    padded = np.zeros(n + width - 1, x.dtype)
    padded[width - 1 : width - 1 + len(low)] = low
    return sliding(np.maximum, padded, width) == x


def batch(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)],
        schema=schema,
    )

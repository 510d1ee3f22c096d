"""Token ids in binary files: a concatenated id array whose document boundaries are Elias-Fano coded.

A monotone sequence of n values below u is kept as floor(log2(u / n)) low bits a value, packed, and the high
parts in unary in a bit vector of at most 3n bits, with the place of each 256th one beside it. `select` returns any
values from these in near-minimal space; no table of 64-bit offsets is kept.

A file holds one run of documents in ascending id order: a header, the coded document ids, the coded ends of the
documents and the ids as 16- or 32-bit integers, with a CRC at the end. Files are rows of a Parquet dataset
(part, block, file) in the shared folder, so any store that Spark writes to can hold them.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from nearcopy.llm.common import arrow_map, batch, check_columns, documents, materialize
from nearcopy.llm.tokens import CachedTokenizer, public_file, text_groups

END_ID = 2
#: Tokens after which a file is closed; a file never cuts a document.
FILE_TOKENS = 1 << 20
#: Words whose ids a worker keeps here, where nothing else needs its memory.
CACHE_WORDS = 1_200_000
#: Parts whose first offsets are sent to the executors at once (16 bytes each).
MAX_PARTS = 1 << 20
_SAMPLE = 256
_MAGIC = b"EFTK"
_HEAD = struct.Struct("<4sHHIQqII")  # magic, id width, 0, documents, tokens, first document id, documents with a null id, reserved
_EF = struct.Struct("<QQBxxxIII")  # values, upper bound, low bits, bytes of low, high, samples


class EliasFano:
    def __init__(self, n: int, upper: int, bits: int, low: bytes, high: bytes, samples: bytes):
        self.n, self.upper, self.bits, self.low = n, upper, bits, low
        self.high, self.samples = np.frombuffer(high, "<u8"), np.frombuffer(samples, "<u4")
        self._bytes = (low, high, samples)

    @staticmethod
    def encode(values: np.ndarray, upper: int | None = None) -> EliasFano:
        """values: non-negative and never falling."""
        values = np.asarray(values, np.uint64)
        n = len(values)
        if n and bool((values[1:] < values[:-1]).any()):
            raise ValueError("values fall")
        upper = int(values[-1]) + 1 if upper is None and n else int(upper or 0)
        bits = max(0, (upper // n).bit_length() - 1) if n else 0
        low = np.packbits(
            ((values[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8).ravel(),
            bitorder="little",
        ).tobytes() if bits else b""
        places = (values >> np.uint64(bits)).astype(np.int64) + np.arange(n)
        size = -(-(int(places[-1]) + 1) // 64) * 64 if n else 0
        flags = np.zeros(size, np.uint8)
        flags[places] = 1
        return EliasFano(
            n,
            upper,
            bits,
            low,
            np.packbits(flags, bitorder="little").tobytes(),
            places[::_SAMPLE].astype("<u4").tobytes(),
        )

    def to_bytes(self) -> bytes:
        return _EF.pack(self.n, self.upper, self.bits, *map(len, self._bytes)) + b"".join(self._bytes)

    @staticmethod
    def read(data: bytes, at: int) -> tuple[EliasFano, int]:
        n, upper, bits, *sizes = _EF.unpack_from(data, at)
        at += _EF.size
        parts = []
        for s in sizes:
            parts.append(bytes(data[at : at + s]))
            at += s
        return EliasFano(n, upper, bits, *parts), at

    def select(self, which: np.ndarray) -> np.ndarray:
        """Values number `which`."""
        which = np.asarray(which, np.int64)
        if which.size and not (0 <= which.min() and which.max() < self.n):
            raise IndexError("no such value")
        place = np.empty(len(which), np.int64)
        for group in np.unique(which // _SAMPLE):  # from the sample, count ones word by word
            mine = np.flatnonzero(which // _SAMPLE == group)
            first = int(self.samples[group])
            end = int(self.samples[group + 1]) + 1 if group + 1 < len(self.samples) else len(self.high) * 64
            words = self.high[first // 64 : -(-end // 64)]
            flags = np.unpackbits(words.view(np.uint8), bitorder="little")
            flags[: first % 64] = 0
            place[mine] = np.flatnonzero(flags)[which[mine] - group * _SAMPLE] + first // 64 * 64
        high = (place - which).astype(np.uint64)
        if not self.bits:
            return high
        spots = (which[:, None] * self.bits + np.arange(self.bits)).astype(np.int64)
        raw = np.frombuffer(self.low, np.uint8)
        flags = (raw[spots >> 3] >> (spots & 7).astype(np.uint8)) & 1
        return (high << np.uint64(self.bits)) | (
            flags.astype(np.uint64) << np.arange(self.bits, dtype=np.uint64)
        ).sum(axis=1, dtype=np.uint64)

    def all(self) -> np.ndarray:
        return self.select(np.arange(self.n))


def write_file(doc_ids: list, ids: list[bytes], width: int) -> bytes:
    """doc_ids ascending, nulls first; ids: little-endian ids of each document."""
    nulls = sum(d is None for d in doc_ids)
    known = np.array(doc_ids[nulls:], np.int64)
    base = int(known[0]) if len(known) else 0
    ends = np.cumsum([len(x) // width for x in ids], dtype=np.int64)
    total = int(ends[-1]) if len(ends) else 0
    body = _HEAD.pack(
        _MAGIC, width, 0, len(doc_ids), total, base, nulls, 0
    ) + EliasFano.encode(known - base).to_bytes() + EliasFano.encode(ends, total + 1).to_bytes() + b"".join(ids)
    return body + struct.pack("<I", zlib.crc32(body))


class TokenFile:
    def __init__(self, data: bytes):
        if data[:4] != _MAGIC or zlib.crc32(memoryview(data)[:-4]) != struct.unpack("<I", data[-4:])[0]:
            raise ValueError("not a token file, or damaged")
        _, self.width, _, self.n_docs, self.n_tokens, self.base, self.nulls, _ = _HEAD.unpack_from(data)
        self._docs, at = EliasFano.read(data, _HEAD.size)
        self.ends, at = EliasFano.read(data, at)
        self.ids = np.frombuffer(data, f"<u{self.width}", self.n_tokens, at)

    def doc_ids(self) -> list:
        return [None] * self.nulls + (self._docs.all().astype(np.int64) + self.base).tolist()

    def bounds(self, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First token and the one after the last of documents number `which`."""
        which = np.asarray(which, np.int64)
        ends = self.ends.select(which).astype(np.int64)
        starts = np.zeros(len(which), np.int64)
        later = which > 0
        starts[later] = self.ends.select(which[later] - 1).astype(np.int64)
        return starts, ends

    def tokens(self, which: int) -> np.ndarray:
        a, b = self.bounds(np.array([which]))
        return self.ids[a[0] : b[0]]


def write_token_files(
    docs: DataFrame, tokenizer_path: str, end_id: int = END_ID, text: str = "text", id_column: str = "doc_id"
) -> DataFrame:
    """The files of `docs`, written to the shared folder: (part, block, before, n_docs, n_tokens, file); `before`
    counts the
    tokens of the part's earlier blocks. A null text is empty: only the end id. Repeated ids are
    ordered by text; null ids come first."""
    check_columns(docs, id_column, text)
    rows = docs.select(docs[id_column].cast("long").alias("_id"), docs[text].alias("_text"))
    ordered = rows.repartitionByRange("_id").sortWithinPartitions("_id", "_text")
    return materialize(ordered.transform(arrow_map, _writer(tokenizer_path, end_id), "part int, block int, before long, n_docs long, n_tokens long, file binary", None))


_FILES = pa.schema([("part", pa.int32()), ("block", pa.int32()), ("before", pa.int64()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("file", pa.binary())])


def _writer(path, end_id):
    def run(batches):
        tok, part, block, before = CachedTokenizer.of(path, CACHE_WORDS), TaskContext.get().partitionId(), 0, 0
        end, doc_ids, ids, held = np.array([end_id], tok.kind).tobytes(), [], [], 0
        for b in batches:
            all_ids = b.column("_id").to_pylist()
            for i, texts in text_groups(b.column("_text")):
                for d, raw in zip(all_ids[i : i + len(texts)], tok.encode(texts), strict=True):
                    doc_ids.append(d)
                    ids.append(raw + end)
                    held += len(raw) // tok.width + 1
                    if held >= FILE_TOKENS:
                        yield batch(
                            _FILES,
                            [part],
                            [block],
                            [before],
                            [len(doc_ids)],
                            [held],
                            [write_file(doc_ids, ids, tok.width)],
                        )
                        before, block, doc_ids, ids, held = before + held, block + 1, [], [], 0
        if doc_ids:
            yield batch(
                _FILES, [part], [block], [before], [len(doc_ids)], [held], [write_file(doc_ids, ids, tok.width)]
            )

    return run


def read_token_files(files: DataFrame) -> DataFrame:
    """Per document from the files: doc_id, start (over all files), n_tokens, ids_crc32."""
    spark = files.sparkSession
    sums = files.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    if sums.count() > MAX_PARTS:
        raise ValueError("too many parts; write with fewer shuffle partitions")
    start, first = 0, {}
    for r in sums.orderBy("part").collect():  # one row a shuffle partition
        first[r["part"]] = start
        start += r["n"]
    shared = spark.sparkContext.broadcast(first)
    schema = pa.schema(
        [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())]
    )

    def run(batches):
        for b in batches:
            for part, before, data in zip(
                b.column("part").to_pylist(), b.column("before").to_pylist(), b.column("file"), strict=True
            ):
                f = TokenFile(data.as_py())
                starts, ends = f.bounds(np.arange(f.n_docs))
                wide = f.ids.astype("<u4")
                crc = [zlib.crc32(wide[x:y]) for x, y in zip(starts, ends, strict=True)]
                yield batch(schema, f.doc_ids(), starts + shared.value[part] + before, ends - starts, crc)

    return files.select("part", "before", "file").transform(
        arrow_map, run, "doc_id long, start long, n_tokens long, ids_crc32 long", None
    )


def op6_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_token_files(write_token_files(documents(spark, sf_dir), public_file("word_bpe_49k.json")))

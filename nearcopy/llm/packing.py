"""Cost-balanced packing of token ids into sequences.

A piece of n tokens costs ``linear * n + quadratic * n**2`` (attention stays inside a piece). Documents are cut
into full sequences and one rest. Rests, in descending length, go to the sequence with the lowest cost so far that
still has room for all of it; where none has, the rest is cut to fill the cheapest open one. The sequences
opened for a batch of rests hold exactly as many tokens as the rests have, so all of them end full: what is
left over at a task's end goes to sequences whose lengths are powers of two, which need no padding.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from nearcopy.llm.common import arrow_map, batch, check_columns, documents
from nearcopy.llm.tokens import CachedTokenizer, public_file, text_groups

CAPACITY, END_ID = 1024, 0
#: Cost of a token, and of a pair of tokens: a layer of width 768 does 24 * 768**2 and 4 * 768 operations for them.
LINEAR, QUADRATIC = 24.0 * 768 * 768, 4.0 * 768
#: Rest tokens that are packed together.
GROUP_TOKENS = 1 << 20


def cost(n, linear: float = LINEAR, quadratic: float = QUADRATIC):
    return linear * n + quadratic * n * n


def room_for(total: int, capacity: int = CAPACITY) -> list[int]:
    """Lengths of sequences that hold exactly `total` tokens: full ones, and powers of two for the rest."""
    rest = total % capacity
    return [capacity] * (total // capacity) + [1 << b for b in range(rest.bit_length() - 1, -1, -1) if rest >> b & 1]


def assign(lengths: np.ndarray, sizes: list[int]) -> list[tuple[int, int, int, int, int]]:
    """(item, start in it, length, sequence, offset): each item, longest first, to the cheapest sequence with room.

    The sizes must add up to at least the sum of the lengths. Ties go to the earlier item and the earlier sequence."""
    free, spent = np.array(sizes, np.int64), np.zeros(len(sizes))
    used, out = np.zeros(len(sizes), np.int64), []
    for item in np.argsort(-lengths, kind="stable"):
        start, left = 0, int(lengths[item])
        while left:
            fits = free >= left
            if fits.any():
                k, n = int(np.where(fits, spent, np.inf).argmin()), left
            else:
                k = int(np.where(free > 0, spent, np.inf).argmin())
                n = int(free[k])
            out.append((int(item), start, n, k, int(used[k])))
            free[k] -= n
            used[k] += n
            spent[k] += cost(n)
            start, left = start + n, left - n
    return out


_NAMES = ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
_OUT = pa.schema([(n, pa.int64()) for n in _NAMES])


def pack_documents(
    docs: DataFrame,
    tokenizer_path: str,
    capacity: int = CAPACITY,
    end_id: int = END_ID,
    text: str = "text",
    id_column: str = "doc_id",
    with_ids: bool = False,
) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset and, with with_ids, ids: the
    piece's token ids as little-endian unsigned 32-bit integers.

    Each task packs what it reads; there is no shuffle. Sequence ids are the task's number times 2**40 plus a
    counter. A null or empty text is one end id. capacity: a power of two.
    """
    check_columns(docs, id_column, text)
    if capacity & (capacity - 1):
        raise ValueError("the capacity must be a power of two")
    rows = docs.select(docs[id_column].cast("long").alias("_id"), docs[text].alias("_text"))
    schema = ", ".join(f"{n} long" for n in _NAMES) + ", ids binary" * with_ids
    return rows.transform(arrow_map, _packer(tokenizer_path, capacity, end_id, with_ids), schema)


def _packer(path, capacity, end_id, with_ids):
    schema = _OUT.append(pa.field("ids", pa.binary())) if with_ids else _OUT

    def table(rows):
        return batch(schema, *map(list, zip(*rows, strict=True)))

    def run(batches):
        tok, next_id = CachedTokenizer.of(path), TaskContext.get().partitionId() << 40
        end, out, rests, held = np.array([end_id], tok.kind).tobytes(), [], [], 0

        def piece(doc, ids, start, n, total, sequence, offset):
            raw = ids[start : start + n].astype("<u4").tobytes()
            return (doc, start, n, zlib.crc32(raw), total, sequence, offset, *([raw] * with_ids))

        def flush(last):
            """Pack the rests; a part too short for full sequences waits for the next ones, unless it's the last."""
            nonlocal next_id, rests, held
            lengths = np.array([len(ids) - start for _, ids, start in rests], np.int64)
            total = int(lengths.sum())
            full = total // capacity * capacity
            later = []
            if not last and full < total:  # the shortest rests wait, the one at the border in part
                order, keep = np.argsort(lengths, kind="stable"), total - full
                for k in order:
                    if not keep:
                        break
                    n = min(keep, int(lengths[k]))
                    doc, ids, start = rests[k]
                    later.append((doc, ids, len(ids) - n))
                    lengths[k] -= n
                    keep -= n
                total = full
            sizes = room_for(total, capacity)
            rows = []
            for k, s, n, q, o in assign(lengths, sizes):
                doc, ids, start = rests[k]
                rows.append(piece(doc, ids, start + s, n, len(ids), next_id + q, o))
            next_id += len(sizes)
            rests, held = later, sum(len(ids) - start for _, ids, start in later)
            return rows

        for b in batches:
            doc_ids = b.column("_id").to_pylist()
            for i, texts in text_groups(b.column("_text")):
                for doc, raw in zip(doc_ids[i : i + len(texts)], tok.encode(texts), strict=True):
                    ids = tok.ids(raw + end)
                    whole = len(ids) // capacity * capacity
                    for start in range(0, whole, capacity):
                        out.append(piece(doc, ids, start, capacity, len(ids), next_id, 0))
                        next_id += 1
                    if whole < len(ids):
                        rests.append((doc, ids, whole))
                        held += len(ids) - whole
                    if held >= GROUP_TOKENS:
                        out += flush(False)
                    if len(out) >= (2000 if with_ids else 20_000):
                        yield table(out)
                        out = []
        out += flush(True)
        if out:
            yield table(out)

    return run


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(documents(spark, sf_dir), public_file("byte_bpe_50k.json"))

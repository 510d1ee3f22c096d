"""Benchmark decontamination by winnowed word k-grams.

Each item window of `window` words, if it occurs in a document, shares at least one selected k-gram with it: with
k-grams hashed and the minimum of each run of ``window - k + 1`` hashes selected, equal windows select equal grams at
equal offsets. Fingerprints of the items and of the documents meet on the hash, and each hit is extended word by
word to the left and right (the words themselves are compared, not hashes) to the longest match; matches of `window`
words count. Items shorter than the window are one window each and are looked up by the hash of all their words.

A benchmark of at most `part_bytes` bytes, which is checked, is sent to the executors as a sorted table of
fingerprints, and
documents stay where they are. A larger one is a table too, but no part of it reaches the driver: a filter of bounded
size over
the items' fingerprints (FILTER_BITS) tells which grams of a document may be hits, the windows around these are
joined with
the items' windows word for word, and the spans found are united by document.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.types import ArrayType, StructType

from nearcopy.llm.common import (
    ALNUM_BYTES,
    Words,
    arrow_map,
    batch,
    blocks,
    check_columns,
    documents,
    materialize,
    mix,
    text_bytes,
    window_minima,
)

GRAM = 5
#: Bits of the filter of a large benchmark's fingerprints (a fuller one lets more windows through, and loses none).
FILTER_BITS = 1 << 28
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


class Fingerprints:
    """Selected grams of benchmark items as flat arrays, sorted by hash; picklable."""

    def __init__(self, items: list[tuple[str, bytes]], window: int, gram: int = GRAM):
        self.window, self.gram = window, min(gram, window)
        self.names = [n for n, _ in items]
        texts = [t.translate(_LOWER) for _, t in items]
        self.data = np.frombuffer(b"".join(texts), np.uint8)
        w = Words(self.data, np.cumsum([0, *map(len, texts)]), ALNUM_BYTES)
        self.starts, self.ends, self.bounds = w.starts, w.ends, w.bounds
        #: By gram length (0: selected grams of items with a window): hashes in order, and the place (word number) of
        #: each.
        self.tables = {k: _sorted(*x) for k, x in item_grams(w, window, self.gram).items() if len(x[0])}

    def search(self, w: Words, data: np.ndarray) -> dict[int, list[tuple[int, int, int]]]:
        """Document (its place in the block): spans (first word, last word + 1, item) of matched windows."""
        out: dict[int, set] = defaultdict(set)
        mine, theirs = memoryview(self.data), memoryview(data)
        for k, (keys, places) in self.tables.items():
            hashes, kept = document_grams(w, k, self.window, self.gram)
            left = np.searchsorted(keys, hashes[kept], "left")
            hit = np.flatnonzero((left < len(keys)) & (keys[np.minimum(left, len(keys) - 1)] == hashes[kept]))
            covered: dict[tuple[int, int], int] = {}  # (item, diagonal): word up to which it is extended
            for h in hit:
                at, j = int(kept[h]), int(left[h])
                doc = int(np.searchsorted(w.bounds, at, "right")) - 1
                lo, hi = int(w.bounds[doc]), int(w.bounds[doc + 1])
                while j < len(keys) and keys[j] == hashes[at]:
                    p = int(places[j])
                    j += 1
                    item = int(np.searchsorted(self.bounds, p, "right")) - 1
                    if covered.get((item, at - p), -1) > at:
                        continue

                    def same(x, shift=p - at):
                        return theirs[w.starts[x] : w.ends[x]] == mine[self.starts[x + shift] : self.ends[x + shift]]

                    first, last = int(self.bounds[item]), int(self.bounds[item + 1])
                    a, b = at, at
                    while b < hi and b - at + p < last and same(b):
                        b += 1
                    while a > lo and a - at + p > first and same(a - 1):
                        a -= 1
                    covered[item, at - p] = b
                    if b - a >= (k or self.window):
                        out[doc].add((a - lo, b - lo, item))
        return out


def _sorted(hashes: np.ndarray, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(hashes, kind="stable")
    return hashes[order], places[order]


def item_grams(w: Words, window: int, gram: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """(hashes, places) by gram length: for items of n < `window` words their one n-gram; 0: selected grams of the
    others."""
    hashes, kept = document_grams(w, 0, window, gram)
    long = np.repeat(w.counts >= window, w.counts)
    kept = kept[long[kept]]
    out = {0: (hashes[kept], kept)}
    for n in range(1, window):
        at = w.bounds[:-1][w.counts == n]
        if len(at):
            out[n] = (w.grams(n)[0][at], at)
    return out


def document_grams(w: Words, k: int, window: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all grams of k words (0: `gram` words), and the places of those that count (0: selected ones)."""
    hashes, whole = w.grams(k or gram)
    if k:
        return hashes, np.flatnonzero(whole)
    safe = hashes.copy()
    safe[~whole] = np.uint64(0xFFFFFFFFFFFFFFFF)
    return hashes, np.flatnonzero(_selected(safe, w, window - gram + 1) & whole)


def _selected(hashes: np.ndarray, w: Words, run: int) -> np.ndarray:
    """window_minima inside each document; runs over a document's end only add selections."""
    if len(hashes) < run:
        return np.ones(len(hashes), bool)
    return window_minima(hashes, run)


_SPANS = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64()), ("item", pa.string())]))
_OUT = pa.schema([("n_words", pa.int64()), ("spans", _SPANS)])


def _plain_items(items: DataFrame, item_id: str, item_text: str) -> DataFrame:
    check_columns(items, item_id, item_text)
    name = F.coalesce(F.col(item_id).cast("string"), F.lit("")).alias("name")
    return items.where(F.length(item_text) > 0).select(name, F.encode(item_text, "utf-8").alias("bytes"))


def _fits(items: DataFrame, part_bytes: int) -> bool:
    total = items.agg(F.sum(F.octet_length("bytes") + F.octet_length("name"))).first()[0]
    return (total or 0) <= part_bytes


def _shared(items: DataFrame, window: int):
    rows = [(r[0], bytes(r[1])) for r in items.collect()]  # at most part_bytes
    return items.sparkSession.sparkContext.broadcast(Fingerprints(rows, window))


def find_contamination(
    docs: DataFrame,
    items: DataFrame,
    text: str = "text",
    item_id: str = "item_id",
    item_text: str = "text",
    window: int = 10,
    part_bytes: int = 32 << 20,
    id_column: str = "doc_id",
) -> DataFrame:
    """Per row of `docs`: id_column, n_words, spans (first, end, item), words counted from 0.

    Words are runs of digits, letters and characters from U+0080 on, after lower-casing A-Z. A null or empty text has no
    words and no spans; a null or empty item has no window; a null item id is the empty string. Equal items are all
    reported. With a benchmark beyond `part_bytes`, spans are the windows by themselves, rows that repeat an id
    have the spans of all of them, and rows without an id are looked at as one document each.
    """
    check_columns(docs, id_column, text)
    rows, plain = docs.select(F.col(id_column), F.col(text).alias("_text")), _plain_items(items, item_id, item_text)
    kind = docs.schema[id_column].dataType.simpleString()
    schema = f"`{id_column}` {kind}, n_words long, spans array<struct<first:long,end:long,item:string>>"
    if _fits(plain, part_bytes):
        return rows.transform(arrow_map, _kernel(_shared(plain, window), id_column), schema)
    marked = _marked(rows, window, items_filter(plain, window))
    found = _joined(marked, plain, window)
    out = marked.join(found, "_row", "left").select(F.col(id_column), "n_words", "spans")
    empty = F.array().cast("array<struct<first:bigint,end:bigint,item:string>>")
    return out.select(F.col(id_column), "n_words", F.coalesce("spans", empty).alias("spans"))


def drop_contaminated(
    docs: DataFrame,
    items: DataFrame,
    text: str = "text",
    item_id: str = "item_id",
    item_text: str = "text",
    window: int = 10,
    part_bytes: int = 32 << 20,
) -> DataFrame:
    """The rows of `docs`, with all their columns, in which no window of an item occurs; null and empty texts stay.
    With a benchmark of
    at most `part_bytes` there is no shuffle."""
    check_columns(docs, text)
    plain = _plain_items(items, item_id, item_text)
    if _fits(plain, part_bytes):
        return docs.transform(arrow_map, _filter(_shared(plain, window), docs.columns.index(text)), docs.schema)
    whole = docs.select(F.struct(*docs.columns).alias("_all"), F.col(text).alias("_text"))
    marked = _marked(whole, window, items_filter(plain, window))
    hit = _joined(marked, plain, window).select("_row")
    return marked.join(hit, "_row", "left_anti").select("_all.*")


# ---- a benchmark of any size -----------------------------------------------------------------


def _lowered(data: np.ndarray) -> np.ndarray:
    return np.frombuffer(data.tobytes().translate(_LOWER), np.uint8)


def _spots(hashes: np.ndarray, n: int) -> np.ndarray:
    """Two bits of the filter for each hash of a gram of n words (0: a selected one), one row each."""
    mixed = mix(hashes ^ np.uint64(n * 0x9E3779B9 + 1))
    return np.stack([mixed >> np.uint64(36), mixed & np.uint64(FILTER_BITS - 1)]) % np.uint64(FILTER_BITS)


def items_filter(plain: DataFrame, window: int) -> np.ndarray:
    """FILTER_BITS bits (as bytes) and, behind them, a flag for each gram length that occurs."""

    schema = pa.schema([("word", pa.int64()), ("value", pa.int64())])

    def run(batches):
        for b in batches:
            data, offsets = text_bytes(b.column("bytes"))
            for i, j in blocks(offsets):
                w = Words(_lowered(data[offsets[i] : offsets[j]]), offsets[i : j + 1] - offsets[i], ALNUM_BYTES)
                for n, (hashes, _) in item_grams(w, window, min(GRAM, window)).items():
                    if len(hashes):
                        spots = np.sort(_spots(hashes, n).ravel())
                        word, first = np.unique(spots >> np.uint64(6), return_index=True)
                        value = np.bitwise_or.reduceat(np.uint64(1) << (spots & np.uint64(63)), first).view(np.int64)
                        word = np.append(word.view(np.int64), FILTER_BITS >> 6)
                        yield batch(schema, word, np.append(value, 1 << n))

    words = plain.select("bytes").transform(arrow_map, run, "word long, value long")
    words = words.groupBy("word").agg(F.bit_or("value").alias("value")).toArrow()  # at most FILTER_BITS / 64 + 1 rows
    out = np.zeros((FILTER_BITS >> 6) + 1, np.int64)
    out[words.column(0).to_numpy()] = words.column(1).to_numpy()
    return out


def _marked(rows: DataFrame, window: int, bits: np.ndarray) -> DataFrame:
    """`rows` with _row (a name of the row), n_words and, as arrays, the windows that may be an item's: first word,
    length, words."""
    shared, place = rows.sparkSession.sparkContext.broadcast(bits), rows.columns.index("_text")
    kind = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64()), ("words", pa.string())]))

    def run(batches):
        table = shared.value
        kinds = [n for n in range(window) if int(table[-1]) >> n & 1]
        for b in batches:
            data, offsets = text_bytes(b.column(place))
            counts, maybe = np.zeros(b.num_rows, np.int64), [[] for _ in range(b.num_rows)]
            for i, j in blocks(offsets):
                part = _lowered(data[offsets[i] : offsets[j]])
                w = Words(part, offsets[i : j + 1] - offsets[i], ALNUM_BYTES)
                counts[i:j] = w.counts
                for first, n in candidate_windows(w, window, kinds, table):
                    doc = int(np.searchsorted(w.bounds, first, "right")) - 1
                    words = [part[w.starts[x] : w.ends[x]].tobytes().decode() for x in range(first, first + n)]
                    at = first - int(w.bounds[doc])
                    maybe[i + doc].append({"first": at, "end": at + n, "words": " ".join(words)})
            yield pa.RecordBatch.from_arrays(
                [*b.columns, pa.array(counts), pa.array(maybe, kind)], names=[*b.schema.names, "n_words", "_maybe"]
            )

    schema = StructType([*rows.schema.fields]).add("n_words", "long")
    window_type = StructType().add("first", "long").add("end", "long").add("words", "string")
    schema = schema.add("_maybe", ArrayType(window_type))
    marked = rows.transform(arrow_map, run, schema).drop("_text")
    # rows are named once, in a table that later reads don't change
    return materialize(marked.withColumn("_row", F.monotonically_increasing_id()))


def candidate_windows(w: Words, window: int, kinds: list[int], table: np.ndarray) -> list[tuple[int, int]]:
    """(first word, number of words) of the windows that hold a gram which the filter lets pass."""
    out = set()
    for k in kinds:
        hashes, kept = document_grams(w, k, window, min(GRAM, window))
        spots = _spots(hashes[kept], k)
        bits = table[(spots >> np.uint64(6)).astype(np.int64)].view(np.uint64) >> (spots & np.uint64(63)) & np.uint64(1)
        for at in kept[bits.all(axis=0)].tolist():
            doc = int(np.searchsorted(w.bounds, at, "right")) - 1
            lo, hi = int(w.bounds[doc]), int(w.bounds[doc + 1])
            if k:
                out.add((at, k))
            else:
                first = max(lo, at - window + min(GRAM, window))
                out.update((x, window) for x in range(first, min(at, hi - window) + 1))
    return sorted(out)


def _windows(window):
    """(words, item) of all windows of items."""

    def run(batches):
        schema = pa.schema([("words", pa.string()), ("item", pa.string())])
        for b in batches:
            for name, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                part = _lowered(np.frombuffer(text.as_py(), np.uint8))
                w = Words(part, np.array([0, len(part)]), ALNUM_BYTES)
                words = [part[x:y].tobytes().decode() for x, y in zip(w.starts, w.ends, strict=True)]
                n = min(window, len(words))
                runs = sorted({" ".join(words[x : x + n]) for x in range(len(words) - n + 1)}) if n else []
                for at in range(0, len(runs), 10_000):
                    yield batch(schema, runs[at : at + 10_000], [name] * len(runs[at : at + 10_000]))

    return run


def _joined(marked: DataFrame, plain: DataFrame, window: int) -> DataFrame:
    """(_row, spans) of rows with hits."""
    theirs = plain.transform(arrow_map, _windows(window), "words string, item string").distinct()
    mine = marked.where(F.size("_maybe") > 0).select("_row", F.explode("_maybe").alias("m"))
    met = mine.select("_row", "m.first", "m.end", "m.words").join(theirs, "words")
    return met.groupBy("_row").agg(F.sort_array(F.collect_list(F.struct("first", "end", "item"))).alias("spans"))


# ---- kernels ---------------------------------------------------------------------------------


def _filter(shared, place):
    def run(batches):
        for b in batches:
            data, offsets = text_bytes(b.column(place))
            clean = np.ones(b.num_rows, bool)
            for i, j in blocks(offsets):
                part = _lowered(data[offsets[i] : offsets[j]])
                for doc in shared.value.search(Words(part, offsets[i : j + 1] - offsets[i], ALNUM_BYTES), part):
                    clean[i + doc] = False
            yield b.filter(pa.array(clean))

    return run


def _kernel(shared, id_column):
    def run(batches):
        prints = shared.value
        for b in batches:
            data, offsets = text_bytes(b.column("_text"))
            counts, spans = np.zeros(b.num_rows, np.int64), [[] for _ in range(b.num_rows)]
            for i, j in blocks(offsets):
                part = _lowered(data[offsets[i] : offsets[j]])
                w = Words(part, offsets[i : j + 1] - offsets[i], ALNUM_BYTES)
                counts[i:j] = w.counts
                for doc, found in prints.search(w, part).items():
                    spans[i + doc] = [{"first": a, "end": e, "item": prints.names[k]} for a, e, k in sorted(found)]
            schema = pa.schema([b.schema.field(id_column), *_OUT])
            yield batch(schema, b.column(id_column), counts, spans)

    return run


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return digest(found)


def digest(found: DataFrame) -> DataFrame:
    """n_hit by joining the sorted spans: a span adds what reaches beyond all before it."""
    counts = "doc_id long, n_words long, n_hit long, n_items long"
    return found.transform(arrow_map, _digest, f"{counts}, items_sha256 string, contaminated boolean")


def _digest(batches):
    counts = [(n, pa.int64()) for n in ("doc_id", "n_words", "n_hit", "n_items")]
    schema = pa.schema([*counts, ("items_sha256", pa.string()), ("contaminated", pa.bool_())])
    none = hashlib.sha256(b"").hexdigest()
    for b in batches:
        hits, items, shas = [], [], []
        for spans in b.column("spans").to_pylist():
            if not spans:
                hits.append(0), items.append(0), shas.append(none)
                continue
            end = total = 0
            for s in sorted(spans, key=lambda s: (s["first"], s["end"])):
                total += max(0, s["end"] - max(end, s["first"]))
                end = max(end, s["end"])
            names = sorted({s["item"] for s in spans})
            hits.append(total), items.append(len(names))
            shas.append(hashlib.sha256(",".join(names).encode()).hexdigest())
        yield batch(schema, b.column("doc_id"), b.column("n_words"), hits, items, shas, [h > 0 for h in hits])


ORACLE_OP3 = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark
), iw AS (
  SELECT DISTINCT item_id, least(10, len(ws)) AS n, array_to_string(list_slice(ws, i, i + least(10, len(ws)) - 1), ' ') AS g
  FROM (SELECT item_id, ws, unnest(generate_series(1, greatest(1, len(ws) - 9))) AS i FROM b WHERE len(ws) > 0)
), sizes AS (SELECT DISTINCT n FROM iw), p AS (
  SELECT doc_id, ws, n, unnest(generate_series(1, len(ws) - n + 1)) AS i FROM w, sizes WHERE len(ws) >= n
), hits AS (
  SELECT p.doc_id, p.i, p.n, iw.item_id FROM (SELECT doc_id, i, n, array_to_string(list_slice(ws, i, i + n - 1), ' ') AS g FROM p) p JOIN iw ON p.n = iw.n AND p.g = iw.g
), words AS (
  SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + n - 1)) AS k FROM hits) GROUP BY doc_id
), named AS (
  SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS names FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hits) GROUP BY doc_id
)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM w LEFT JOIN words USING (doc_id) LEFT JOIN named USING (doc_id)
"""

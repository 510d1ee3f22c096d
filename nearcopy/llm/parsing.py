"""Exact repeats of a fixed byte length over a corpus, by prefix-free parsing.

Parse. A place is a trigger of modulus m if the rolling hash of the GRAM bytes from there on is 0 modulo m. Each modulus
of MODULI gives a parse; they divide one another, so the triggers of a coarse parse are among those of all finer ones. A
string of `length` bytes belongs to the coarsest parse that has a trigger inside it, and there to its first trigger:
equal strings have equal triggers at equal offsets, whatever stands around them. A phrase is the run of all strings
that belong to one trigger; it is known by the trigger's gram (key) and by all bytes of its strings (context). A
string without any
trigger, as in a text of one repeated byte, is a phrase by itself, with the string as its key.

Dictionary. Equal phrases are one entry. All strings of its later occurrences are repeats. Each task does so first for
what it holds: only the first occurrence of an entry is sent on, and the others' ranges, joined, as what they are.
So thousands of copies of a passage send a row a task and entry, and no key is hot.

Order. Entries that share a trigger can still share strings. For these, two suffix orders are made: that of the
dictionary (the
bytes before the trigger, read backwards, sorted) and that of the parse (the bytes from the trigger on, sorted), each
with the lengths that neighbours have in common. A string that starts d bytes before the trigger is in the corpus order
next to the strings with which it has d bytes in the first order and length - d in the second in common; of those
that agree in both, all but the first in (document, place) are repeats. Bytes are compared here, not hashes. A trigger
that occurs in one entry only needs no more work.

A trigger with more than GROUP entries (a line that very many texts share, in different surroundings) is not brought
together:
its strings become phrases by themselves and are settled as the dictionary is.

One suffix array of the whole corpus is never laid out: strings with different triggers are different, so
the orders of all triggers, one after another, are the corpus order that is asked for. Entries are told
apart by 128 bits (key and context).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from nearcopy.llm.common import (
    _BASE,
    _BASE_INVERSE,
    _powers,
    arrow_map,
    batch,
    blocks,
    check_columns,
    documents,
    materialize,
    mix,
    text_bytes,
)

GRAM, LENGTH = 32, 100
#: Moduli of the parses; about 1 in 40 bytes begins a phrase in ordinary text.
MODULI = (96, 48, 24, 12, 6, 3)
#: Entries of one trigger that are ordered in one task; more are settled string by string.
GROUP = 4096
#: Phrases of a task among which equal ones are looked for before any is sent.
HELD = 1 << 18
#: Keys of triggers with many entries that are broadcast; more are joined by a shuffle.
BROADCAST_KEYS = 100_000
_VALUES = np.random.default_rng(977).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_SECOND = np.uint64(0x9FB21C651E98DF25)
_PHRASE = "key long, ctx long, doc long, at long, end long"
_PHRASES = pa.schema([(n, pa.int64()) for n in ("key", "ctx", "doc", "at", "end")])
_FOUND = "doc long, first long, end long, key long, at long"
_FOUNDS = pa.schema([(n, pa.int64()) for n in ("doc", "first", "end", "key", "at")])
_CONTEXT = pa.schema([("key", pa.int64()), ("doc", pa.int64()), ("at", pa.int64()), ("bytes", pa.binary())])
_SPAN = pa.schema([("doc", pa.int64()), ("first", pa.int64()), ("end", pa.int64())])


def prefix_sums(data: np.ndarray) -> np.ndarray:
    values = _VALUES[data]
    values *= _powers(_BASE, len(data), "up")
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(values, out=sums[1:])
    return sums


def span_hashes(sums: np.ndarray, first: np.ndarray, end: np.ndarray) -> np.ndarray:
    return (sums[end] - sums[first]) * _powers(_BASE_INVERSE, len(sums), "down")[first]


def string_names(sums: np.ndarray, first: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Key and context of strings that are phrases by themselves. The halves' hashes make them independent of each
    other."""
    whole, half = span_hashes(sums, first, first + length), span_hashes(sums, first, first + length // 2)
    return mix(whole ^ _SECOND).view(np.int64), mix(mix(whole) + half).view(np.int64)


def pack(trigger: np.ndarray, back: np.ndarray, more: np.ndarray) -> np.ndarray:
    """Place of a phrase: of its trigger, how far before it the first string starts, and the number of its strings
    less one."""
    return trigger.astype(np.int64) << 14 | back << 7 | more


def unpack(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First string's start, and number of strings less one."""
    return (at >> 14) - (at >> 7 & 127), at & 127


def first_triggers(grams: np.ndarray, starts: np.ndarray, run: int) -> np.ndarray:
    """The trigger of the string at each start: the first of `run` places in the coarsest parse that has one there
    (-1: none has)."""
    rest = (grams % np.uint64(MODULI[0])).astype(np.uint8)
    owner, left = np.full(len(starts), -1, np.int64), np.arange(len(starts))
    for m in MODULI:
        flags = rest % m == 0 if m < MODULI[0] else rest == 0
        spots = np.flatnonzero(flags)
        if not len(spots) or not len(left):
            continue
        next_one = (np.cumsum(flags) - flags)[starts[left]]
        place = spots[np.minimum(next_one, len(spots) - 1)]
        fits = (next_one < len(spots)) & (place < starts[left] + run)
        owner[left[fits]] = place[fits]
        left = left[~fits]
    return owner


def phrases(data: np.ndarray, offsets: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Of a block of documents: key, context, document's number, trigger, first and last string start; places in the
    block."""
    none = tuple(np.zeros(0, np.int64) for _ in range(6))
    n, run = len(data), length - gram + 1
    if n < length:
        return none
    sums = prefix_sums(data)
    grams = sums[gram:] - sums[:-gram]
    grams *= _powers(_BASE_INVERSE, len(sums), "down")[: len(grams)]
    grams = mix(grams)
    inside = np.ones(n - length + 1, bool)
    for e in offsets[1:-1]:  # strings over a document's end
        inside[max(0, e - length + 1) : e] = False
    starts = np.flatnonzero(inside)
    if not len(starts):
        return none
    trigger = first_triggers(grams, starts, run)
    doc = np.searchsorted(offsets, starts, "right") - 1
    alone = trigger < 0
    trigger[alone] = starts[alone]
    new = (np.diff(trigger) != 0) | (np.diff(doc) != 0) | (np.diff(alone) != 0) | (np.diff(starts) != 1)
    cut = np.flatnonzero(new) + 1
    head, tail = np.concatenate(([0], cut)), np.concatenate((cut, [len(starts)])) - 1
    first, last, trigger, alone = starts[head], starts[tail], trigger[head], alone[head]
    shape = (trigger - first).astype(np.uint64) << np.uint64(32) | (last - first).astype(np.uint64)
    context = mix(span_hashes(sums, first, last + length) + mix(shape)).view(np.int64)
    key = grams[np.minimum(trigger, len(grams) - 1)].view(np.int64)
    if alone.any():
        key[alone], context[alone] = string_names(sums, first[alone], length)
    return key, context, doc[head], trigger, first, last


class _Settler:
    """Phrases that a task holds: the first of equal ones is sent, the others' ranges are told, joined where they
    touch."""

    def __init__(self, length: int):
        self.length, self.parts, self.size = length, [], 0

    def add(self, *columns: np.ndarray) -> Iterator[pa.RecordBatch]:
        if len(columns[0]):
            self.parts.append(columns)
            self.size += len(columns[0])
        if self.size >= HELD:
            yield from self.flush()

    def flush(self) -> Iterator[pa.RecordBatch]:
        if not self.size:
            return
        key, ctx, doc, at = (np.concatenate(c) for c in zip(*self.parts, strict=True))
        self.parts, self.size = [], 0
        order = np.lexsort((at, doc, ctx, key))
        key, ctx, doc, at = key[order], ctx[order], doc[order], at[order]
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (ctx[1:] != ctx[:-1])
        head = np.flatnonzero(new)[np.cumsum(new) - 1]
        yield batch(_PHRASES, key[new], ctx[new], doc[new], at[new], np.zeros(int(new.sum()), np.int64))
        later = np.flatnonzero(~new & ((doc != doc[head]) | (at != at[head])))
        if len(later):
            first, more = unpack(at[later])
            doc, first, end = joined_ranges(doc[later], first, first + more + self.length)
            spread = mix(mix(doc.view(np.uint64)) + first.view(np.uint64)).view(np.int64)
            yield batch(_PHRASES, spread, np.zeros(len(doc), np.int64), doc, first, end)


def joined_ranges(doc: np.ndarray, first: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ranges of one document that overlap or touch as one."""
    order = np.lexsort((first, doc))
    doc, first, end = doc[order], first[order], end[order]
    group = np.cumsum(np.concatenate(([0], doc[1:] != doc[:-1])))
    wide = int(end.max()) + 1
    reach = np.maximum.accumulate(end + group * wide) - group * wide  # the furthest end so far in the document
    new = np.ones(len(doc), bool)
    new[1:] = (group[1:] != group[:-1]) | (first[1:] > reach[:-1])
    heads = np.flatnonzero(new)
    return doc[heads], first[heads], np.maximum.reduceat(end, heads)


def _parse(length, gram):
    def run(batches):
        held = _Settler(length)
        for b in batches:
            data, offsets = text_bytes(b.column("_text"))
            ids = b.column("_id").to_numpy(zero_copy_only=False).astype(np.int64)
            for i, j in blocks(offsets):
                bounds = offsets[i : j + 1] - offsets[i]
                key, ctx, doc, trigger, first, last = phrases(data[offsets[i] : offsets[j]], bounds, length, gram)
                yield from held.add(key, ctx, ids[i + doc], pack(trigger - bounds[doc], trigger - first, last - first))
        yield from held.flush()

    return run


def _compare(length):
    """Sorted phrases: ranges of the dictionary entries' later occurrences, and (end 0) entries that share a trigger
    with others."""

    def run(batches):
        held = None  # the open entry's first occurrence; whether its trigger is known to have several
        for b in batches:
            key, ctx, doc, at, end = (c.to_numpy() for c in b.columns)
            told = np.flatnonzero(end)
            if len(told):
                zeros = np.zeros(len(told), np.int64)
                yield batch(_FOUNDS, doc[told], at[told], end[told], zeros, zeros)
            key, ctx, doc, at = (x[end == 0] for x in (key, ctx, doc, at))
            if not len(key):
                continue
            extra = int(held is not None)
            if held:
                now = (key, ctx, doc, at)
                key, ctx, doc, at = (np.concatenate(([x], y)) for x, y in zip(held[:4], now, strict=True))
            new_key = np.ones(len(key), bool)
            new_key[1:] = key[1:] != key[:-1]
            new = new_key.copy()
            new[1:] |= ctx[1:] != ctx[:-1]
            heads = np.flatnonzero(new)
            entry = np.cumsum(new) - 1
            later = np.flatnonzero(~new & ~((doc == doc[heads[entry]]) & (at == at[heads[entry]])))
            group = np.cumsum(new_key) - 1
            several = np.bincount(group[heads], minlength=group[-1] + 1) > 1
            if extra and held[4]:
                several[0] = True
            opened = new & several[group]
            if extra and held[4]:
                opened[0] = False  # told already
            opened = np.flatnonzero(opened)
            first, more = unpack(at[later])
            zeros = np.zeros(len(later), np.int64)
            yield batch(_FOUNDS, doc[later], first, first + more + length, zeros, zeros)
            zeros = np.zeros(len(opened), np.int64)
            yield batch(_FOUNDS, doc[opened], zeros, zeros, key[opened], at[opened])
            h = heads[-1]
            held = (key[h], ctx[h], doc[h], at[h], bool(several[-1]))

    return run


def _pieces(b: pa.RecordBatch, length: int):
    """(doc, key, at, bytes) of the asked phrases of a batch of documents. Where an id has several texts, those that
    are too short are passed over."""
    for doc, text, opened in zip(b.column("doc_id").to_pylist(), b.column("text"), b.column("opened"), strict=True):
        data = text.as_py().encode()
        for x in opened.as_py():
            start, size = (x["at"] >> 14) - (x["at"] >> 7 & 127), (x["at"] & 127) + length
            if start + size <= len(data):
                yield doc, x["key"], x["at"], data[start : start + size]


def _contexts(length):
    def run(batches):
        for b in batches:
            out, size = [], 0
            for doc, key, at, piece in _pieces(b, length):
                out.append((key, doc, at, piece))
                size += len(piece)
                if size > 4 << 20:
                    yield batch(_CONTEXT, *map(list, zip(*out, strict=True)))
                    out, size = [], 0
            if out:
                yield batch(_CONTEXT, *map(list, zip(*out, strict=True)))

    return run


def _strings(length):
    """The strings of the asked phrases as phrases by themselves."""

    def run(batches):
        held = _Settler(length)
        for b in batches:
            for doc, _, at, piece in _pieces(b, length):
                start, more = unpack(np.int64(at))
                steps = np.arange(int(more) + 1)
                key, ctx = string_names(prefix_sums(np.frombuffer(piece, np.uint8)), steps, length)
                yield from held.add(key, ctx, np.full(len(steps), doc, np.int64), (start + steps) << 14)
        yield from held.flush()

    return run


def sorted_suffixes(group: np.ndarray, rows: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The order of byte rows (`sizes` bytes of each count) within groups, and how many bytes each has in common with
    the one before (-1: another group)."""
    order = np.lexsort((np.ascontiguousarray(rows).view(f"S{rows.shape[1]}")[:, 0], group))
    a, b = rows[order[1:]], rows[order[:-1]]
    differ = a != b
    common = np.where(differ.any(axis=1), differ.argmax(axis=1), rows.shape[1])
    common = np.minimum(common, np.minimum(sizes[order[1:]], sizes[order[:-1]]))
    common[group[order[1:]] != group[order[:-1]]] = -1
    return order, np.concatenate(([-1], common))


def repeated_strings(
    group: np.ndarray, data: np.ndarray, offsets: np.ndarray, back: np.ndarray, count: np.ndarray, length: int
) -> np.ndarray:
    """Whether the string that starts d bytes before the trigger of row k is also that of an earlier row of its
    group: [k, d].

    Rows are contexts, ordered by group, document and place."""
    n, most = len(group), int(back.max()) + 1
    far = offsets[1:] - offsets[:-1]
    left, right = np.zeros((n, most), np.uint8), np.zeros((n, length), np.uint8)
    for d in range(most - 1):  # bytes before the trigger, the nearest first
        some = np.flatnonzero(back > d)
        left[some, d] = data[offsets[some] + back[some] - 1 - d]
    ahead = np.minimum(far - back, length)
    for d in range(length):
        some = np.flatnonzero(ahead > d)
        right[some, d] = data[offsets[some] + back[some] + d]
    by_left, common_left = sorted_suffixes(group, left, back)
    by_right, common_right = sorted_suffixes(group, right, ahead)
    least = back - count + 1
    out = np.zeros((n, most), bool)
    one, two = np.empty(n, np.int64), np.empty(n, np.int64)
    for d in range(most):
        mine = (least <= d) & (d <= back)
        one[by_left], two[by_right] = np.cumsum(common_left < d), np.cumsum(common_right < length - d)
        mine = np.flatnonzero(mine & (np.bincount(one)[one] > 1) & (np.bincount(two)[two] > 1))
        if len(mine) > 1:
            order = np.lexsort((mine, two[mine], one[mine]))
            a, b = one[mine][order], two[mine][order]
            out[mine[order[1:]], d] = (a[1:] == a[:-1]) & (b[1:] == b[:-1])
    return out


def _expand(length):
    """Contexts sorted by (key, doc, at), groups of at most GROUP: ranges of strings that a context of the same key
    has at an earlier place."""

    def settle(key, doc, at, pieces):
        same = np.zeros(len(key), bool)
        same[1:] = (key[1:] == key[:-1]) & (doc[1:] == doc[:-1]) & (at[1:] == at[:-1])  # of repeated rows
        if same.any():
            key, doc, at, pieces = key[~same], doc[~same], at[~same], pieces.filter(pa.array(~same))
        data, offsets = text_bytes(pieces)
        back, count = at >> 7 & 127, (at & 127) + 1
        group = np.cumsum(np.concatenate(([0], key[1:] != key[:-1])))
        hits = repeated_strings(group, data, offsets, back, count, length)
        edges = np.diff(np.pad(hits, ((0, 0), (1, 1))).astype(np.int8), axis=1)
        row, low = np.nonzero(edges == 1)
        _, high = np.nonzero(edges == -1)  # runs of d from low to high - 1, the far end starts first
        trigger = (at >> 14)[row]
        return batch(_SPAN, doc[row], trigger - high + 1, trigger - low + length)

    def run(batches):
        held = None
        for whole in batches:
            for lo in range(0, whole.num_rows, GROUP):
                part = whole.slice(lo, GROUP)
                columns = [part.column(i).to_numpy() for i in range(3)]
                pieces = part.column(3)
                if held:
                    columns = [np.concatenate(c) for c in zip(held[:3], columns, strict=True)]
                    pieces = pa.concat_arrays([held[3], pieces])
                last = int(np.searchsorted(columns[0], columns[0][-1]))  # the last group may go on
                if last:
                    yield settle(*[c[:last] for c in columns], pieces.slice(0, last))
                held = (*[c[last:] for c in columns], pieces.slice(last))
        if held and len(held[0]):
            yield settle(*held)

    return run


def repeated_spans(docs: DataFrame, text: str = "text", id_column: str = "doc_id", length: int = LENGTH) -> DataFrame:
    """(doc, first, end): byte ranges covered by `length`-byte strings that also start earlier; ranges may overlap.

    length: 64 to 159. Order is by (id, place). Rows that repeat an id count as one document; rows without an id and
    empty
    or null texts have no ranges.
    """
    check_columns(docs, id_column, text)
    if not 2 * GRAM <= length <= GRAM + 127:
        raise ValueError("length must be from 64 to 159")
    rows = docs.where(docs[id_column].isNotNull())
    rows = rows.select(docs[id_column].cast("long").alias("doc_id"), docs[text].alias("text"))

    def settled(parsed):
        sorted_ = parsed.repartition("key").sortWithinPartitions("key", "ctx", "doc", "at")
        return sorted_.transform(arrow_map, _compare(length), _FOUND)

    def with_texts(asked):
        lists = asked.groupBy("doc").agg(F.collect_list(F.struct("key", "at")).alias("opened"))
        return rows.join(lists, rows["doc_id"] == lists["doc"]).select("doc_id", "text", "opened")

    whole = rows.select(F.col("doc_id").alias("_id"), F.col("text").alias("_text"))
    found = materialize(settled(whole.transform(arrow_map, _parse(length, GRAM), _PHRASE)))  # read by all branches
    opened = found.where("end = 0").select("key", "doc", "at")
    sizes = opened.groupBy("key").count()
    many = materialize(sizes.where(F.col("count") > GROUP).select(F.col("key").alias("many")))
    n, out = many.count(), found.where("end > 0").select("doc", "first", "end")
    if n:
        many = F.broadcast(many) if n <= BROADCAST_KEYS else many
        strings = with_texts(opened.join(many, F.col("key") == F.col("many"), "left_semi"))
        single = settled(strings.transform(arrow_map, _strings(length), _PHRASE))
        out = out.unionByName(single.where("end > 0").select("doc", "first", "end"))
        opened = opened.join(many, F.col("key") == F.col("many"), "left_anti")
    contexts = with_texts(opened).transform(arrow_map, _contexts(length), "key long, doc long, at long, bytes binary")
    contexts = contexts.repartition("key").sortWithinPartitions("key", "doc", "at")
    return out.unionByName(contexts.transform(arrow_map, _expand(length), "doc long, first long, end long"))


def join_runs(spans) -> list[tuple[int, int]]:
    """Maximal runs of (first, end) ranges; ranges that touch are one run."""
    out: list[list[int]] = []
    for a, e in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([a, e])
    return [(a, e) for a, e in out]


_COUNTS = [(n, pa.int64()) for n in ("doc_id", "n_bytes", "n_removed", "n_spans")]
_KEPT = pa.schema([*_COUNTS, ("kept_sha256", pa.string()), ("kept", pa.binary())])


def _cut(with_bytes):
    schema = _KEPT if with_bytes else pa.schema(list(_KEPT)[:-1])

    def run(batches):
        for b in batches:
            rows = []
            ids = b.column("doc_id").to_pylist()
            for i, (text, spans) in enumerate(zip(b.column("text"), b.column("spans"), strict=True)):
                data = (text.as_py() or "").encode()
                runs, at, kept = join_runs((s["first"], s["end"]) for s in spans.as_py() or ()), 0, []
                for a, e in runs:
                    kept.append(data[at:a])
                    at = e
                rest = b"".join([*kept, data[at:]])
                name = hashlib.sha256(rest).hexdigest()
                rows.append((ids[i], len(data), len(data) - len(rest), len(runs), name, *([rest] * with_bytes)))
                if len(rows) == 1024 or i == b.num_rows - 1:
                    yield batch(schema, *map(list, zip(*rows, strict=True)))
                    rows = []

    return run


def remove_repeats(
    docs: DataFrame, text: str = "text", id_column: str = "doc_id", length: int = LENGTH, with_bytes: bool = True
) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 and (with_bytes) the kept bytes.

    Null texts are empty ones. Rows without an id keep all their bytes and are no repeat's first place."""
    spans = repeated_spans(docs, text, id_column, length)
    by_doc = spans.groupBy("doc").agg(F.collect_list(F.struct("first", "end")).alias("spans"))
    rows = docs.select(docs[id_column].cast("long").alias("doc_id"), docs[text].alias("text"))
    named = rows.where("doc_id IS NOT NULL")
    joined = named.join(by_doc, named["doc_id"] == by_doc["doc"], "left").select("doc_id", "text", "spans")
    loose = rows.where("doc_id IS NULL").withColumn("spans", F.lit(None).cast(joined.schema["spans"].dataType))
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_bytes
    return joined.unionByName(loose).transform(arrow_map, _cut(with_bytes), schema)


def op10_repeat_removal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(documents(spark, sf_dir), with_bytes=False)

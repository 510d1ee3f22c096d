"""Exact Jaccard self-join of word n-gram sets by the size-aware heavy-light method.

Texts with equal sets are one class; everything below is on classes. With s shingles in the smaller and
s' in the larger set, a pair is linked when it shares c(s, s') of them.

Light sets (at most `boundary` shingles): all subsets of c(s, s') shingles are enumerated for each size s' a partner may
have. Two sets with a common subset under the same pair of sizes are linked, so each subset's group is a star of links.
Subsets are told apart by 128 bits, as classes are.

Heavy sets: inverted lists over each set's rarest shingles, s - ceil(t s) + m(s) of them; linked sets meet in at least
min(m, m') lists, where m(s) grows with s. Rarity comes from a count sketch of all documents, as wide as they need;
it decides only the
order, not the result. A list is cut where the next size is too large for a link. The pairs of a short list are
counted over all lists, and those that meet too seldom are dropped; a long list isn't paired off but ties its members
together. Components of what remains are groups: each set travels once to its group, and there pairs are
refuted by parity bitmaps (the popcount of their exclusive or never exceeds the symmetric difference) or decided by an
exact merge. Pairs already connected are skipped, so a group yields a spanning forest of its links, not all pairs.

A group beyond `group_shingles` shingles or `group_sets` sets is dealt to parts by a hash. About eight of its sets go
to all parts, so that
near copies are connected across them by links with these. What is then not in the group's largest component is
compared with all sets of the group that are in other components, in blocks of bounded size by size bands; near
copies of one text leave nothing for that, and no link is lost where they do.

The boundary is where enumeration gets dearer than lists, from the sizes of all classes.
"""

from __future__ import annotations

import math
import zlib
from functools import cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from nearcopy.components import connected_components
from nearcopy.llm.common import (
    SOLID_BYTES,
    Words,
    arrow_map,
    batch,
    blocks,
    bloom_rows,
    check_columns,
    documents,
    materialize,
    mix,
    text_bytes,
)

SHINGLE, PERCENT = 4, 85
#: Least and most counters of the sketch (powers of two; a byte each when it is sent out), and slices in which it is
#: added up.
SKETCH, SLICES = (1 << 18, 1 << 25), 256
#: Longest list whose pairs are counted.
SHORT = 8
#: Largest size for which subsets are considered at all, and cost of a list entry in subsets.
MAX_LIGHT, LIST_COST = 16, 4.0
#: Shingles, and sets, of a group that one task verifies; and about how many sets of a larger group go to all its parts.
GROUP_SHINGLES, GROUP_SETS, LEADERS = 1 << 22, 512, 8
_CHECK = np.uint64(0x2545F4914F6CDD1D)
_WORDS = 16  # of 64 bits, in a parity bitmap


def need(a: int, b: int, percent: int = PERCENT) -> int:
    """Shingles that sets of a and b shingles must share: the least c with 100 c >= percent (a + b - c)."""
    return -(-percent * (a + b) // (100 + percent))


def shingle_sets(data: np.ndarray, offsets: np.ndarray, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of a block of documents, ascending in each, and n + 1 bounds."""
    w = Words(data, offsets, SOLID_BYTES)
    hashes, whole = w.grams(shingle)
    doc = np.repeat(np.arange(len(w.counts)), w.counts)
    for k in range(1, shingle):  # fewer words: all of them as one
        short = np.flatnonzero(w.counts == k)
        if len(short):
            at = w.bounds[short]
            hashes[at], whole[at] = w.grams(k)[0][at], True
    hashes, doc = hashes[whole], doc[whole]
    order = np.lexsort((hashes, doc))
    hashes, doc = hashes[order], doc[order]
    new = np.ones(len(hashes), bool)
    new[1:] = (hashes[1:] != hashes[:-1]) | (doc[1:] != doc[:-1])
    return hashes[new], np.searchsorted(doc[new], np.arange(len(w.counts) + 1))


def meetings(n):
    """Lists in which a linked pair meets at least, for the smaller value of its two sizes."""
    return 1 + n // 40


def rarest(n, percent: int = PERCENT):
    """Shingles of a set of n that go into lists."""
    return np.minimum(n, n - -(-percent * n // 100) + meetings(n))


def _rank(hashes, counters):
    return (hashes >> np.uint64(64 - counters.bit_length() + 1)).astype(np.int64)


def _count(shingle, counters):
    schema = pa.schema([("slice", pa.int32()), ("counts", pa.binary())])

    def run(batches):
        total = np.zeros(counters, np.uint32)
        for b in batches:
            data, offsets = text_bytes(b.column("_text"))
            for i, j in blocks(offsets):
                hashes, _ = shingle_sets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], shingle)
                np.add.at(total, _rank(hashes, counters), 1)
        if total.any():
            kind = np.min_scalar_type(int(total.max()))
            packed = [zlib.compress(x.tobytes(), 1) for x in total.astype(kind).reshape(SLICES, -1)]
            yield batch(schema, list(range(SLICES)), [bytes([kind.itemsize]) + x for x in packed])

    return run


def _add_up(batches):
    schema, sums = pa.schema([("slice", pa.int32()), ("levels", pa.binary())]), {}
    for b in batches:
        for k, raw in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            raw = raw.as_py()
            counts = np.frombuffer(zlib.decompress(memoryview(raw)[1:]), f"u{raw[0]}").astype(np.uint64)
            sums[k] = sums[k] + counts if k in sums else counts
    if sums:
        levels = [np.minimum(255, 8 * np.log2(1.0 + x)).astype(np.uint8).tobytes() for x in sums.values()]
        yield batch(schema, list(sums), levels)


def shingle_levels(texts: DataFrame, shingle: int = SHINGLE) -> np.ndarray:
    """Level of frequency (0 to 255, eight a doubling) of each sketch counter, over all documents; at most 32 MB."""
    size = texts.agg(F.sum(F.octet_length("_text"))).first()[0] or 0
    counters = min(SKETCH[1], max(SKETCH[0], 1 << (size // 96).bit_length()))  # about one for 16 words
    # a task sends a sketch of its own, so there are no more tasks than cores, however many files the table has
    few = texts.coalesce(texts.sparkSession.sparkContext.defaultParallelism)
    parts = few.transform(arrow_map, _count(shingle, counters), "slice int, counts binary").repartition("slice")
    parts = parts.transform(arrow_map, _add_up, "slice int, levels binary").collect()  # SLICES rows
    out = np.zeros(counters, np.uint8)
    for r in parts:
        out[r[0] * (counters // SLICES) : (r[0] + 1) * (counters // SLICES)] = np.frombuffer(r[1], np.uint8)
    return out


def _profile(levels, shingle, percent):
    schema = pa.schema([*[(n, pa.int64()) for n in ("doc_id", "n", "h1", "h2")], ("rare", pa.binary())])

    def run(batches):
        level = levels.value
        for b in batches:
            data, offsets = text_bytes(b.column("_text"))
            for i, j in blocks(offsets):
                hashes, bounds = shingle_sets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], shingle)
                n = np.diff(bounds)
                h1, h2 = np.zeros((2, len(n)), np.uint64)
                full = n > 0
                if full.any():
                    h1[full] = np.add.reduceat(mix(hashes), bounds[:-1][full])
                    h2[full] = np.add.reduceat(mix(hashes ^ np.uint64(0x5851F42D4C957F2D)), bounds[:-1][full])
                doc = np.repeat(np.arange(len(n)), n)
                order = np.lexsort((hashes, level[_rank(hashes, len(level))], doc))
                keep = rarest(n, percent) * full
                kept = order[(np.arange(len(hashes)) - bounds[:-1][doc]) < keep[doc]]
                small = np.flatnonzero((n > 0) & (n <= MAX_LIGHT))  # light sets are kept whole, behind their rarest
                ends, raw = np.cumsum(keep), hashes[kept].tobytes()
                rare = [raw[8 * (e - k) : 8 * e] for e, k in zip(ends, keep, strict=True)]
                for d in small:
                    rest = order[bounds[d] + keep[d] : bounds[d + 1]]
                    rare[d] += hashes[rest].tobytes()
                yield batch(schema, b.column("_id").slice(i, j - i), n, h1.view(np.int64), h2.view(np.int64), rare)

    return run


def choose_boundary(sizes: dict[int, int], percent: int = PERCENT) -> int:
    """The light boundary with the least cost. sizes: classes of each size up to MAX_LIGHT / (percent / 100)."""
    best, least = 0, math.inf
    for x in range(MAX_LIGHT + 1):
        subsets = entries = 0
        for s, c in sizes.items():
            if s <= x:
                subsets += c * sum(math.comb(s, need(s, o, percent)) for o in _partners(s, x, percent))
            if 100 * s >= percent * (x + 1):
                entries += c * (s - -(-percent * s // 100) + 1) * LIST_COST
        if subsets + entries < least:
            best, least = x, subsets + entries
    return best


def _partners(s: int, most: int, percent: int) -> range:
    return range(-(-percent * s // 100), min(most, 100 * s // percent) + 1)


@cache
def _subsets(n: int, c: int) -> np.ndarray:
    return np.array(list(combinations(range(n), c)), np.int64)


_ENTRY = pa.schema(
    [("key", pa.int64()), ("check", pa.int64()), ("kind", pa.int8()), ("n", pa.int32()), ("rep", pa.int64())]
)


def _entries(boundary, percent):
    """Inverted-list entries (kind 0) and subsets (kind 1: of the smaller size of the pair, 2: of the larger)."""

    def run(batches):
        for b in batches:
            reps, sizes, raws = b.column("rep").to_numpy(), b.column("n").to_numpy(), b.column("rare")
            keys, checks, kinds, rows = [], [], [], []
            for r in range(len(reps)):
                n, hashes = int(sizes[r]), np.frombuffer(raws[r].as_py(), np.uint64)
                if 100 * n >= percent * (boundary + 1):
                    p = int(rarest(n, percent))
                    keys.append(hashes[:p])
                    checks.append(np.zeros(p, np.uint64))
                    kinds.append(np.zeros(p, np.int8))
                    rows.append(np.full(p, r))
                if n <= boundary:
                    hashes = np.sort(hashes)
                    members, second = mix(hashes), mix(hashes ^ _CHECK)
                    for o in _partners(n, boundary, percent):
                        chosen = _subsets(n, need(n, o, percent))
                        sums = members[chosen].sum(axis=1, dtype=np.uint64)
                        keys.append(mix(sums + mix(np.array([min(n, o) << 32 | max(n, o)], np.uint64))))
                        checks.append(mix(second[chosen].sum(axis=1, dtype=np.uint64)))
                        kinds.append(np.full(len(sums), 1 if n <= o else 2, np.int8))
                        rows.append(np.full(len(sums), r))
            if keys:
                rows = np.concatenate(rows)
                names = (np.concatenate(x).view(np.int64) for x in (keys, checks))
                yield batch(_ENTRY, *names, np.concatenate(kinds), sizes[rows].astype(np.int32), reps[rows])

    return run


STAR, LIGHT, PAIR = range(3)


def _meet(percent):
    """Entries sorted by key, check, kind, n, rep: (a, b, how, needed). Of a long list and of a subset's group, each
    member with the first
    (STAR, LIGHT); of a short list, or part of one between sizes too far apart, all pairs (PAIR) with the meetings
    they need."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("how", pa.int8()), ("needed", pa.int32())])

    def pairs(key_rows, start, size):
        """Pairs of the segments of given starts and sizes."""
        n, rep = key_rows
        out = []
        for k in range(2, SHORT + 1):
            at = start[size == k]
            for x in range(k - 1) if len(at) else ():
                for y in range(x + 1, k):
                    near = 100 * n[at + x].astype(np.int64) >= percent * n[at + y]
                    i, j = at[near] + x, at[near] + y
                    times = meetings(np.minimum(n[i], n[j])).astype(np.int32)
                    out.append((rep[i], rep[j], np.full(len(i), PAIR, np.int8), times))
        return out

    def run(batches):
        held = None  # rows of the last segment: all, if it's short so far; else the last one, and its hub
        for b in batches:
            rows = [c.to_numpy() for c in b.columns]
            if not len(rows[0]):
                continue
            told, hub0, kind0 = 0, None, None
            if held:
                rows = [np.concatenate((x, y)) for x, y in zip(held[0], rows, strict=True)]
                told, hub0, kind0 = held[1:]
            key, check, kind, n, rep = rows
            light = kind > 0
            new = np.ones(len(key), bool)
            new[1:] = (key[1:] != key[:-1]) | (check[1:] != check[:-1]) | (light[1:] != light[:-1])
            new[1:] |= ~light[1:] & (100 * n[:-1].astype(np.int64) < percent * n[1:])
            start = np.flatnonzero(new)
            size = np.diff(np.append(start, len(key)))
            star = light[start] | (size > SHORT)
            hub, hub_kind = rep[start].copy(), kind[start].copy()
            if told:
                star[0], hub[0], hub_kind[0] = True, hub0, kind0
            segment = np.cumsum(new) - 1
            each = star[segment] & (rep != hub[segment]) & (hub_kind[segment] < 2)
            if told:
                each[0] = False
            how = np.where(light[each], LIGHT, STAR).astype(np.int8)
            out = [(hub[segment[each]], rep[each], how, np.ones(len(how), np.int32))]
            done = ~star
            done[-1] = False
            out += pairs((n, rep), start[done], size[done])
            found = [np.concatenate(c) for c in zip(*out, strict=True)]
            if len(found[0]):
                yield batch(schema, *found)
            keep = slice(len(key) - 1, None) if star[-1] else slice(start[-1], None)
            held = ([c[keep].copy() for c in rows], int(star[-1]), hub[-1], hub_kind[-1])
        if held and not held[1]:
            *_, n, rep = held[0]
            out = pairs((n, rep), np.array([0]), np.array([len(rep)]))
            if out:
                yield batch(schema, *[np.concatenate(c) for c in zip(*out, strict=True)])

    return run


_SET = pa.schema(
    [
        *[("group", pa.int64()), ("band", pa.int32()), ("i", pa.int32()), ("j", pa.int32())],
        *[("part", pa.int64()), ("own", pa.bool_()), ("rep", pa.int64()), ("n", pa.int32()), ("hashes", pa.binary())],
    ]
)
_SETS = "group long, band int, i int, j int, part long, own boolean, rep long, n int, hashes binary"


def _band(n: np.ndarray, percent: int) -> np.ndarray:
    """Linked sizes are in one band or in two next to each other (one is added for rounding)."""
    return np.floor(np.log(n) / np.log(100 / percent) * (1 - 1e-9)).astype(np.int64)


def _set_rows(shingle, places):
    """Rows of _SET: each set, with its hashes, at all `places(row, rep, size)` of (band, i, j, part, own)."""

    def run(batches):
        for b in batches:
            data, offsets = text_bytes(b.column("_text"))
            group, reps = b.column("group").to_pylist(), b.column("_id").to_pylist()
            facts = {c: b.column(c).to_pylist() for c in b.schema.names if c not in ("_id", "_text", "group")}
            for i, j in blocks(offsets):
                hashes, bounds = shingle_sets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], shingle)
                rows, size = [], 0
                for d in range(j - i):
                    raw, row = hashes[bounds[d] : bounds[d + 1]].tobytes(), {c: v[i + d] for c, v in facts.items()}
                    for place in places(row, reps[i + d], len(raw) // 8):
                        rows.append((group[i + d], *place, reps[i + d], len(raw) // 8, raw))
                        size += len(raw)
                        if size > 4 << 20:
                            yield batch(_SET, *map(list, zip(*rows, strict=True)))
                            rows, size = [], 0
                if rows:
                    yield batch(_SET, *map(list, zip(*rows, strict=True)))

    return run


def _hash(rep: int, salt: int) -> int:
    return int(mix(np.array([rep], np.int64).view(np.uint64) ^ np.uint64(salt))[0])


def _to_parts(row, rep, size):
    """Each set to a part of its group; a few sets to all."""
    if row["parts"] == 1:
        return [(0, 0, 0, 0, True)]
    if _hash(rep, 1) % max(1, row["members"] // LEADERS) == 0:
        return [(0, p, 0, 0, True) for p in range(row["parts"])]
    return [(0, _hash(rep, 0) % row["parts"], 0, 0, True)]


def _to_blocks(percent):
    """Sets outside of the largest component to all blocks of their band (own), and all sets to the blocks of the
    bands around theirs."""

    def places(row, rep, size):
        band, mine = int(_band(np.array([max(size, 1)]), percent)[0]), _hash(rep, 0) % row["parts"]
        out = [(x, u, mine, row["label"], False) for x in (band - 1, band, band + 1) for u in range(row["asked"])]
        if row["apart"]:
            own = _hash(rep, 2) % row["asked"]
            out += [(band, own, p, row["label"], True) for p in range(row["parts"])]
        return out

    return places


def spanning_links(
    reps: np.ndarray, sets: list[np.ndarray], may: np.ndarray | None = None, percent: int = PERCENT
) -> list[tuple[int, int]]:
    """A spanning forest of the links among the sets. may: (label, own) of each; then only sets with different labels
    pair, of which one
    is an own one and one is not."""
    order = np.argsort([len(s) for s in sets], kind="stable")
    sets, reps = [sets[k] for k in order], reps[order]
    kinds = may[order] if may is not None else None
    n = np.array([len(s) for s in sets], np.int64)
    maps = np.zeros((len(sets), _WORDS), np.uint64)
    for k, s in enumerate(sets):
        bits = np.bincount((s >> np.uint64(54)).astype(np.int64), minlength=64 * _WORDS) & 1
        maps[k] = np.packbits(bits.astype(np.uint8), bitorder="little").view(np.uint64)
    root, out = np.arange(len(sets)), []
    for k in range(len(sets) - 1):
        end = int(np.searchsorted(n, 100 * n[k] // percent, "right"))
        if end <= k + 1:
            continue
        others = np.arange(k + 1, end)
        others = others[root[others] != root[k]]
        if kinds is not None:
            others = others[_pairable(kinds[k], kinds[others])]
        while len(others):
            most = n[k] + n[others] - 2 * (-(-percent * (n[k] + n[others]) // (100 + percent)))
            apart = np.bitwise_count(maps[others] ^ maps[k]).sum(axis=1, dtype=np.int64)
            others = others[(apart <= most)][np.argsort(apart[apart <= most], kind="stable")]
            linked = False
            for at, o in enumerate(others):
                small, large = (sets[k], sets[o]) if n[k] <= n[o] else (sets[o], sets[k])
                place = np.searchsorted(large, small)
                common = int((large[np.minimum(place, len(large) - 1)] == small).sum())
                if common >= need(int(n[k]), int(n[o]), percent):
                    out.append((int(reps[k]), int(reps[o])))
                    root[root == root[o]] = root[k]
                    others, linked = others[at + 1 :], True
                    others = others[root[others] != root[k]]
                    break
            if not linked:
                break
    return out


def _pairable(one: np.ndarray, others: np.ndarray) -> np.ndarray:
    return (others[:, 0] != one[0]) & (others[:, 1] != one[1])


def _verify(percent, labelled=False):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        key, rows = None, []

        def links():
            if len(rows) < 2:
                return []
            sets = [np.frombuffer(r[4], np.uint64) for r in rows]
            may = np.array([r[1:3] for r in rows], np.int64) if labelled else None
            return spanning_links(np.array([r[3] for r in rows]), sets, may, percent)

        for b in batches:
            group, band, i, j, part, own, rep, _, _ = (c.to_pylist() for c in b.columns[:-1] + [b.columns[0]])
            raws, out = b.column("hashes"), []
            for r in range(b.num_rows):
                now = (group[r], band[r], i[r], j[r])
                if now != key:
                    out += links()
                    key, rows = now, []
                rows.append((None, part[r], own[r], rep[r], raws[r].as_py()))
            if out:
                yield batch(schema, *map(list, zip(*out, strict=True)))
        if found := links():
            yield batch(schema, *map(list, zip(*found, strict=True)))

    return run


def jaccard_components(
    docs: DataFrame,
    text: str = "text",
    id_column: str = "doc_id",
    shingle: int = SHINGLE,
    percent: int = PERCENT,
    group_shingles: int = GROUP_SHINGLES,
    group_sets: int = GROUP_SETS,
) -> DataFrame:
    """Per row: doc_id, n_shingles, component_id (smallest id reachable by links, itself included).

    Linked: 100 * intersection >= percent * union of the sets of `shingle` words. Texts with fewer words are one
    shingle;
    null, empty and blank texts have none and are linked with nothing. Rows that repeat an id count as one node. A
    null id
    has a null component. Other columns are not looked at.
    """
    check_columns(docs, id_column, text)
    spark = docs.sparkSession
    rows = docs.select(docs[id_column].cast("long").alias("_id"), docs[text].alias("_text"))
    levels = spark.sparkContext.broadcast(shingle_levels(rows.select("_text"), shingle))  # SKETCH bytes at any size
    profiled = "doc_id long, n long, h1 long, h2 long, rare binary"
    profile = materialize(rows.transform(arrow_map, _profile(levels, shingle, percent), profiled))
    named = profile.where("n > 0 AND doc_id IS NOT NULL")
    classes = materialize(named.groupBy("n", "h1", "h2").agg(F.min("doc_id").alias("rep")))
    counted = classes.where(F.col("n") <= 2 * MAX_LIGHT).groupBy("n").count().collect()  # at most 2 * MAX_LIGHT rows
    boundary = choose_boundary({r["n"]: r["count"] for r in counted}, percent)
    chosen = _first_of_classes(named, classes)
    entries = chosen.transform(
        arrow_map, _entries(boundary, percent), "key long, check long, kind byte, n int, rep long"
    )
    met = entries.repartition("key").sortWithinPartitions("key", "check", "kind", "n", "rep")
    met = met.transform(arrow_map, _meet(percent), "a long, b long, how byte, needed int")
    met = met.groupBy("a", "b", "how").agg(F.count("*").alias("times"), F.min("needed").alias("needed"))
    stars = materialize(met.where("times >= needed").select("a", "b", (F.col("how") == LIGHT).alias("light")))
    tied = connected_components(stars.where("NOT light"))
    sizes = classes.select(F.col("rep").alias("node"), "n")
    groups = materialize(tied.join(sizes, "node").select("node", "component", "n"))
    totals = groups.groupBy("component").agg(F.sum("n").alias("total"), F.count("*").alias("members"))
    parts = F.greatest(F.ceil(F.col("total") / group_shingles), F.ceil(F.col("members") / group_sets)).cast("int")
    totals = totals.select("component", "members", parts.alias("parts"))
    placed = groups.join(totals, "component").select("node", F.col("component").alias("group"), "members", "parts")
    texts = bloom_rows(groups, "node")(rows, "_id")  # texts of other documents stay where they are
    keys = ["group", "band", "i", "j"]

    def verified(places, into, labelled=False):
        sets = texts.join(places, F.col("_id") == F.col("node")).drop("node")
        sets = sets.transform(arrow_map, _set_rows(shingle, into), _SETS).repartition(*keys).sortWithinPartitions(*keys)
        return sets.transform(arrow_map, _verify(percent, labelled), "a long, b long")

    links = stars.where("light").select("a", "b").unionByName(verified(placed, _to_parts))
    large = placed.where("parts > 1")
    if not large.limit(1).count():
        comps = connected_components(links)
    else:
        links = materialize(links)
        comps = materialize(connected_components(links))
        label = comps.select(F.col("node").alias("k"), F.col("component").alias("label"))
        large = large.join(label, F.col("node") == F.col("k"), "left").drop("k")
        large = materialize(large.withColumn("label", F.coalesce("label", "node")))
        most = large.groupBy("group", "label").count().groupBy("group")
        most = most.agg(F.max_by("label", F.struct("count", "label")).alias("most"))
        apart = (F.col("label") != F.col("most")).alias("apart")
        large = large.join(most, "group").select("node", "group", "parts", "label", apart)
        rest = large.where("apart").groupBy("group").agg(F.ceil(F.count("*") / group_sets).cast("int").alias("asked"))
        if rest.limit(1).count():
            more = verified(large.join(rest, "group"), _to_blocks(percent), True)
            comps = connected_components(links.unionByName(more))
    member = profile.join(classes, ["n", "h1", "h2"], "left").select("doc_id", "n", "rep")
    component = F.coalesce("component", "rep", "doc_id").alias("component_id")
    member = member.join(comps, F.col("rep") == F.col("node"), "left")
    return member.select("doc_id", F.col("n").alias("n_shingles"), component)


def _first_of_classes(named: DataFrame, classes: DataFrame) -> DataFrame:
    """(rep, n, rare): the profile of each class's first document. Only rows that a filter of the copies' ids lets
    pass need a join."""
    copies = named.join(classes, ["n", "h1", "h2"]).where("doc_id <> rep").select("doc_id")
    maybe = bloom_rows(materialize(copies), "doc_id")
    first = classes.select(F.col("n").alias("cn"), F.col("h1").alias("c1"), F.col("h2").alias("c2"), "rep")
    same = (F.col("n") == F.col("cn")) & (F.col("h1") == F.col("c1")) & (F.col("h2") == F.col("c2"))
    doubtful = maybe(named, "doc_id").join(first, (F.col("doc_id") == F.col("rep")) & same).select("rep", "n", "rare")
    sure = maybe(named, "doc_id", False)
    return sure.select(F.col("doc_id").alias("rep"), "n", "rare").unionByName(doubtful)


def op5_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(documents(spark, sf_dir))

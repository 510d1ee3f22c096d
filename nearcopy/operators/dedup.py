"""Duplicate tests, representatives, groups and the de-duplicated set."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window, functions as F

from nearcopy.components import connected_components, materialize
from nearcopy.functions import linalg as L


def flag_absolute(nn: DataFrame, t: float) -> DataFrame:
    """(i, j): later neighbours j of i under a fixed distance; the test that the adaptive one replaces."""
    return nn.where((F.col("nid") > F.col("qid")) & (F.col("dist") < t)).select(
        F.col("qid").alias("i"), F.col("nid").alias("j")
    )


def flag_adaptive(nn: DataFrame, self_dist: DataFrame, tol: float = 0.01) -> DataFrame:
    """(i, j): later neighbours whose distance differs from i's self-distance by less than tol of it."""
    joined = nn.where("nid > qid").join(self_dist.select(F.col("id").alias("qid"), "self_dist"), "qid")
    return joined.where(L.is_near_copy(F.col("self_dist"), F.col("dist"), tol)).select(
        F.col("qid").alias("i"), F.col("nid").alias("j")
    )


def sweep_tolerance(nn: DataFrame, self_dist: DataFrame, tols: list[float]) -> DataFrame:
    """(tol, i, j) of each tolerance; the table of tolerances is a few rows."""
    joined = nn.where("nid > qid").join(self_dist.select(F.col("id").alias("qid"), "self_dist"), "qid")
    many = joined.withColumn("tol", F.explode(F.array(*[F.lit(float(t)) for t in tols])))
    return many.where(L.is_near_copy(F.col("self_dist"), F.col("dist"), F.col("tol"))).select(
        "tol", F.col("qid").alias("i"), F.col("nid").alias("j")
    )


def flag_raw(pairs: DataFrame, raw: DataFrame, raw_threshold: float, col: str = "x") -> DataFrame:
    """`pairs` (i, j) with raw_dist and is_dup: whether the raw vectors are nearer than the threshold."""
    a, b = raw.select(F.col("id").alias("i"), F.col(col).alias("_a")), raw.select(
        F.col("id").alias("j"), F.col(col).alias("_b")
    )
    return pairs.join(a, "i").join(b, "j").withColumn("raw_dist", L.l2(F.col("_a"), F.col("_b"))).withColumn(
        "is_dup", F.col("raw_dist") < raw_threshold
    ).drop("_a", "_b")


def parents(edges: DataFrame, mode: str = "ordered") -> DataFrame:
    """(j, parent). The sequential loop over ids overwrites j's representative last from its largest flagging
    predecessor (ordered); star takes the smallest."""
    pick = {"ordered": F.max, "star": F.min}[mode]
    return edges.where("i < j").groupBy("j").agg(pick("i").alias("parent"))


def pointer_jump(parent: DataFrame, ids: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(id, rep): the root of each id's chain of parents. A round doubles the reach; the driver reads one count a
    round."""
    rep = ids.select("id").distinct().join(parent, F.col("id") == F.col("j"), "left").select(
        "id", F.coalesce("parent", "id").alias("rep")
    )
    rep = materialize(rep)
    for _ in range(max_rounds):
        up = rep.where("id <> rep").select(F.col("id").alias("k"), F.col("rep").alias("to"))
        new = materialize(rep.join(up, F.col("rep") == F.col("k"), "left").select("id", F.coalesce("to", "rep").alias("rep"), F.col("to").isNotNull().alias("moved")))
        if not new.where("moved").limit(1).count():
            return new.select("id", "rep")
        rep = new.select("id", "rep")
    raise RuntimeError("a cycle of parents")


def resolve_representatives(edges: DataFrame, ids: DataFrame, mode: str = "ordered") -> DataFrame:
    """(id, rep). ordered: as the loop in id order gives; star: by the smallest predecessor; connected: smallest id
    of the connected component."""
    if mode == "connected":
        comps = connected_components(edges, "i", "j")
        return ids.select("id").distinct().join(comps, F.col("id") == F.col("node"), "left").select(
            "id", F.coalesce("component", "id").alias("rep")
        )
    return pointer_jump(parents(edges, mode), ids)


def deduplicate(df: DataFrame, reps: DataFrame, id_column: str = "id") -> DataFrame:
    """Rows that represent themselves."""
    kept = reps.where("id = rep").select(F.col("id").alias("_kept"))
    return df.join(kept, F.col(id_column) == F.col("_kept"), "left_semi")


def dropped(df: DataFrame, reps: DataFrame, id_column: str = "id") -> DataFrame:
    kept = reps.where("id = rep").select(F.col("id").alias("_kept"))
    return df.join(kept, F.col(id_column) == F.col("_kept"), "left_anti")


def representative_sets(reps: DataFrame) -> DataFrame:
    """(rep, members, n); a group's members are one array, so very large groups are better read from (id, rep)."""
    return reps.groupBy("rep").agg(F.sort_array(F.collect_list("id")).alias("members"), F.count("*").alias("n"))


def has_duplicate(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """(id, has_dup): whether an item is in any flagged pair, on either side."""
    touched = edges.select(F.col("i").alias("k")).unionByName(edges.select(F.col("j").alias("k"))).distinct()
    return ids.select("id").join(touched, F.col("id") == F.col("k"), "left").select(
        "id", F.col("k").isNotNull().alias("has_dup")
    )


def collapse_codes(encoded: DataFrame) -> DataFrame:
    """(cell, codes, id, n): one row for each distinct code, with its smallest id; searched instead of all its
    members."""
    return encoded.groupBy("cell", "codes").agg(F.min("id").alias("id"), F.count("*").alias("n"))


def collapsed_edges(encoded: DataFrame) -> DataFrame:
    """(i, j): of rows with equal cell and codes, from the smallest id to each other."""
    first = collapse_codes(encoded).where("n > 1").select("cell", "codes", F.col("id").alias("i"))
    return encoded.select(
        "cell", "codes", F.col("id").alias("j")
    ).join(first, ["cell", "codes"]).where("j > i").select("i", "j")


@dataclass
class DedupSpec:
    """feature: raw or another; codec: a function of the vector table that returns a codec, or None."""

    name: str = "identity"
    codec: object = None
    k_cells: int = 16
    m: int = 8
    bits: int = 8
    k: int = 10
    nprobe: int = 1
    tol: float = 0.01
    mode: str = "ordered"
    shards: int = 1
    tie: str = "id"
    collapse: bool = False
    ball: bool = False
    iters: int = 5
    seeded: bool = False
    codes: int = 16
    #: Let the planner choose collapse and ball too (the salt of hot cells is always its choice; it changes no result).
    planned: bool = False


@dataclass
class DedupResult:
    reps: DataFrame
    edges: DataFrame
    hist: DataFrame
    index: object
    stats: dict = field(default_factory=dict)


def dedup(df: DataFrame, spec: DedupSpec, col: str = "x") -> DedupResult:
    """Index, self-search, relative test, representatives. k counts the query itself. tie: id, or forward (of equally
    near codes ids after the query
    come first). collapse: rows with equal codes are tied together beforehand and searched once (not literal when k
    cuts a list). ball: all neighbours within the upper bound."""
    from nearcopy.operators.index import build_index, seeded_index
    from nearcopy.plans.planner import plan_dedup, plan_search

    if spec.seeded:
        index = seeded_index(df, col, spec.k_cells, spec.m, spec.codes)
    else:
        codec = spec.codec(df) if spec.codec else None
        index = build_index(df, col, spec.k_cells, spec.m, spec.bits, codec, spec.iters)
    index.encoded = materialize(index.encoded)
    own = index.encoded.select("id", "self_dist")
    steps = plan_search(index, 0, spec.nprobe, spec.k)
    salt, collapse, ball = steps.salt, spec.collapse, spec.ball
    if spec.planned:
        chosen = plan_dedup(index, spec.k, spec.tol)
        collapse, ball = collapse or chosen.collapse, ball or chosen.ball
        steps.steps += chosen.steps
    asked, more = index.encoded, None
    full = index.encoded
    if collapse:
        heads = collapse_codes(index.encoded).select("id")
        asked = index.encoded.join(heads, "id", "left_semi")
        index.encoded = materialize(asked)
        more = collapsed_edges(full)
    queries = asked.select("id", "z", "self_dist")
    if ball:
        nn = index.search_ball(queries, spec.tol, spec.nprobe, "z", True, salt)
    elif spec.tie == "forward":
        near = index.search_ball(queries, spec.tol, spec.nprobe, "z", True, salt)
        w = Window.partitionBy("qid").orderBy(
            F.round("dist", 12),
            F.when(F.col("nid") == F.col("qid"), 0).when(F.col("nid") > F.col("qid"), 1).otherwise(2),
            "nid",
        )
        nn = near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= spec.k)
    else:
        nn = index.search(queries, spec.k, spec.nprobe, col="z", shards=spec.shards, latent=True, salt=salt)
    edges = flag_adaptive(nn, own, spec.tol)
    if more is not None:
        edges = edges.unionByName(more).distinct()
    edges = materialize(edges)
    index.encoded = full
    reps = resolve_representatives(edges, df.select("id"), spec.mode)
    return DedupResult(
        reps,
        edges,
        duplication_histogram(reps),
        index,
        {"name": spec.name, "bytes_per_vector": index.bytes_per_vector(), "plan": steps.explain()},
    )


# ---- histogram and prompts ------------------------------------------------------------------


def group_sizes(reps: DataFrame) -> DataFrame:
    return reps.groupBy("rep").agg(F.count("*").alias("n"))


def duplication_histogram(reps: DataFrame) -> DataFrame:
    """(group_size, n_groups, n_items)."""
    return group_sizes(reps).groupBy(F.col("n").alias("group_size")).agg(
        F.count("*").alias("n_groups"), F.sum("n").alias("n_items")
    )


def top_duplicated(reps: DataFrame, n: int = 100) -> DataFrame:
    """(rep, n) of the n largest groups; ties by the smaller representative."""
    return group_sizes(reps).orderBy(F.desc("n"), "rep").limit(n)

"""Queries on features, quantizers, search, duplicate tests and the copy study, with SQL over the same seeded codebooks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window as W, functions as F

from nearcopy.components import materialize
from nearcopy.functions import features as FE, linalg as L, losses
from nearcopy.operators import auto, codecs, copies, dedup, index as I, kmeans as K, metrics as M, multimodal as MM, search as S
from nearcopy.registry.relational import table

QUERIES, ORACLES = {}, {}


def query(sql: str = ""):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return put


def emb(spark, d):
    return FE.emb(table(spark, d, "embeddings"))


def docs(spark, d):
    return table(spark, d, "documents").select("doc_id", "text", "lang")


# ---- SQL building blocks --------------------------------------------------------------------

EMB = "src AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings)"


def text_vectors(name: str = "src", salt: str = "", unigrams: bool = False, first: int | None = None) -> str:
    """CTEs for hashed word pairs of documents."""
    cut = f"[1:{first}]" if first else ""
    pairs = "CASE WHEN len(w) = 1 THEN w ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END"
    grams = f"list_concat({pairs}, w)" if unigrams else pairs
    return f"""{name}_t AS (SELECT doc_id AS id, list_filter(string_split(trim(regexp_replace(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')), ' '), lambda v: v <> ''){cut} AS w FROM documents),
{name}_g AS (SELECT id, unnest({grams}) AS g FROM {name}_t),
{name}_h AS (SELECT id, md5('{salt}' || g) AS h FROM {name}_g),
{name}_b AS (SELECT id, CAST(('0x' || substr(h, 1, 8))::BIGINT % 256 AS INT) AS k, sum(CASE WHEN ('0x' || substr(h, 9, 1))::INT % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END) AS v FROM {name}_h GROUP BY ALL),
{name}_n AS (SELECT id, sqrt(sum(v * v)) AS n FROM {name}_b GROUP BY id),
{name} AS (SELECT t.id, list(CASE WHEN n > 0 THEN coalesce(v, 0.0) / n ELSE 0.0::DOUBLE END ORDER BY r.k) AS x FROM {name}_t t CROSS JOIN range(0, 256) r(k) LEFT JOIN {name}_b b ON b.id = t.id AND b.k = r.k LEFT JOIN {name}_n n ON n.id = t.id GROUP BY t.id)"""


DOC = text_vectors()


def seeded(dim: int = 64, k: int = 8, m: int = 8, codes: int = 16, residual: bool = True) -> str:
    """CTEs after src: vec, cen, asg, blk, cb, cod and enc (id, x, cell, codes, y, self_dist)."""
    size = dim // m
    if k:
        cells = f"""cen AS (SELECT rk AS cell, x AS c FROM vec WHERE rk < {k}),
asg AS (SELECT v.id, any_value(v.rk) AS rk, any_value(v.x) AS x, min(struct_pack(d := list_distance(v.x, c), n := cell)).n AS cell FROM vec v, cen GROUP BY v.id),
base AS (SELECT a.id, a.rk, a.x, a.cell, {'cen.c' if residual else f'list_transform(range(0, {dim}), lambda i: 0.0::DOUBLE)'} AS c FROM asg a JOIN cen USING (cell))"""
    else:
        cells = f"base AS (SELECT id, rk, x, 0 AS cell, list_transform(range(0, {
            dim
        }), lambda i: 0.0::DOUBLE) AS c FROM vec)"
    return f"""vec AS (SELECT id, x, row_number() OVER (ORDER BY id) - 1 AS rk FROM src),
{cells},
res AS (SELECT *, list_transform(range(1, {dim + 1}), lambda i: x[i] - c[i]) AS e FROM base),
blk AS (SELECT id, rk, m, e[m * {size} + 1 : m * {size} + {size}] AS s FROM res, range(0, {m}) t(m)),
cb AS (SELECT m, rk AS code, s AS w FROM blk WHERE rk < {codes}),
cod AS (SELECT b.id, b.m, min(struct_pack(d := list_distance(b.s, w), n := code)).n AS code FROM blk b JOIN cb USING (m) GROUP BY b.id, b.m),
rec AS (SELECT res.id, any_value(res.x) AS x, any_value(res.cell) AS cell, any_value(res.c) AS c, flatten(list(w ORDER BY m)) AS w, string_agg(CAST(code AS VARCHAR), '.' ORDER BY m) AS codes FROM res JOIN cod ON res.id = cod.id JOIN cb USING (m, code) GROUP BY res.id),
enc0 AS (SELECT id, x, cell, codes, list_transform(range(1, {dim + 1}), lambda i: c[i] + w[i]) AS y FROM rec),
enc AS (SELECT *, list_distance(x, y) AS self_dist FROM enc0)"""


def ranked(pairs: str, k: int) -> str:
    return f"(SELECT qid, nid, dist, rank FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(dist, 12), nid) AS rank FROM ({pairs})) WHERE rank <= {k})"


def adc(probes: int, where: str = "true") -> str:
    """Asymmetric distances of queries to the codes in their nearest cells."""
    return f"""SELECT p.id AS qid, e.id AS nid, list_distance(p.x, e.y) AS dist FROM (SELECT q.id, q.x, cen.cell, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.x, cen.c), cen.cell) AS pr FROM src q, cen WHERE {where}) p
JOIN enc e ON e.cell = p.cell WHERE p.pr <= {probes}"""


TENTH = "q.id % 10 = 0"
EXACT = ranked(
    "SELECT q.id AS qid, v.id AS nid, list_distance(q.x, v.x) AS dist FROM src q JOIN src v ON q.id <> v.id WHERE q.id % 10 = 0",
    10,
)
WITHOUT_SELF = ranked(f"SELECT * FROM ({adc(2, TENTH)}) WHERE qid <> nid", 10)
SEEDED = f"WITH {EMB}, {seeded()}"


def tenth(spark, d):
    return emb(spark, d).where("id % 10 = 0").select("id", "x")


def seeded_index(spark, d, **options):
    return I.seeded_index(emb(spark, d).select("id", "x"), **options)


def found_without_self(spark, d, nprobe=2, k=10, **options):
    """k + 1 neighbours less the query itself."""
    found = seeded_index(spark, d, **options).search(tenth(spark, d), k + 1, nprobe).where("qid <> nid")
    return S.merge_topk(found.drop("rank"), k)


# ---- features -----------------------------------------------------------------------------


@query(f"WITH {DOC} SELECT id, i - 1 AS i, round(x[i], 6) AS v FROM src, range(1, 257) t(i) WHERE x[i] <> 0")
def q_hashed_features(spark, d):
    return FE.doc_vec(docs(spark, d)).select("id", F.posexplode("x").alias("i", "v")).where("v <> 0").select(
        "id", F.col("i").cast("long").alias("i"), F.round("v", 6).alias("v")
    )


@query(f"WITH {text_vectors(salt='b:', unigrams=True)} SELECT id, round(list_sum(list_transform(range(1, 257), lambda i: x[i] * i)), 4) AS s FROM src")
def q_hashed_features_b(spark, d):
    return FE.doc_vec_b(docs(spark, d)).select(
        "id",
        F.round(F.aggregate(F.transform("x", lambda v, i: v * (i + 1)), F.lit(0.0), lambda a, v: a + v), 4).alias("s"),
    )


@query(f"WITH {text_vectors(first=12)} SELECT id, round(list_sum(list_transform(range(1, 257), lambda i: x[i] * i)), 4) AS s FROM src")
def q_captions(spark, d):
    return FE.doc_cap(docs(spark, d)).select(
        "id",
        F.round(F.aggregate(F.transform("t", lambda v, i: v * (i + 1)), F.lit(0.0), lambda a, v: a + v), 4).alias("s"),
    )


_NOISE = "list_transform(range(0, 64), lambda i: (('0x' || substr(md5('{salt}' || CAST({id} AS VARCHAR) || ':' || CAST(i AS VARCHAR)), 1, 4))::INT / 65535.0::DOUBLE - 0.5) * {twice})"
PLANTED = f"""{EMB}, cp AS (SELECT id, x, r, 1000000 * r + id AS nid FROM src, range(1, 257) t(r) WHERE id < 256 AND r <= floor(256 / (1 + id))),
planted AS (SELECT id, x, id AS source_id FROM src UNION ALL SELECT nid, CASE WHEN r % 2 = 0 THEN x ELSE list_transform(list_zip(x, {_NOISE.format(salt='plant:', id='nid', twice='0.004::DOUBLE')}), lambda p: p[1] + p[2]) END, id FROM cp)"""


@query(f"WITH {PLANTED} SELECT id, source_id, round(x[1], 6) AS a, round(x[64], 6) AS z FROM planted")
def q_planted_copies(spark, d):
    return FE.emb_planted(table(spark, d, "embeddings")).select(
        "id", "source_id", F.round(F.col("x")[0], 6).alias("a"), F.round(F.col("x")[63], 6).alias("z")
    )


# ---- exact search ------------------------------------------------------------------------


@query(f"WITH {EMB} SELECT qid, nid, round(dist, 6) AS dist, rank FROM {EXACT}")
def q_knn_exact(spark, d):
    return S.knn_exact(tenth(spark, d), emb(spark, d), 10).withColumn("dist", F.round("dist", 6))


@query(f"WITH {EMB} SELECT qid, nid, rank FROM {EXACT} WHERE rank <= 5")
def q_topk_window(spark, d):
    """Blocks send a few rows a query, a window ranks them; a nested-loop join of all pairs gives the same (tests)."""
    return S.knn_exact(tenth(spark, d), emb(spark, d), 5).select("qid", "nid", "rank")


@query(f"WITH {EMB} SELECT qid, nid, round(-dist, 6) AS score, rank FROM {ranked('SELECT q.id AS qid, v.id AS nid, -list_inner_product(q.x, v.x) AS dist FROM src q, src v WHERE q.id % 10 = 0', 5)}")
def q_mips(spark, d):
    return S.mips(tenth(spark, d), emb(spark, d), 5).withColumn("score", F.round("score", 6))


@query(f"WITH {EMB} SELECT id, nid AS nn_id, round(dist, 6) AS dist FROM (SELECT q.id, v.id AS nid, list_distance(q.x, v.x) AS dist, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.x, v.x), v.id) AS k FROM src q JOIN src v ON q.id // 100 = v.id // 100 AND q.id <> v.id) WHERE k = 1")
def q_chunk_nearest(spark, d):
    return S.chunk_nearest(emb(spark, d), "x", 100, block=32).select("id", "nn_id", F.round("dist", 6).alias("dist"))


@query("SELECT vec_id AS id, c AS chunk_id FROM embeddings, range(0, 10000) t(c) WHERE vec_id >= c * 50 AND vec_id < c * 50 + 100 AND c <= vec_id // 50")
def q_sliding_chunks(spark, d):
    return S.with_chunks(emb(spark, d).select("id"), 100, 50).select("id", "chunk_id")


# ---- k-means and cells -----------------------------------------------------------------------


@query(f"""WITH {EMB}, vec AS (SELECT id, x, row_number() OVER (ORDER BY id) - 1 AS rk FROM src), cen AS (SELECT rk AS cell, x AS c FROM vec WHERE rk < 8),
asg AS (SELECT v.id, any_value(v.x) AS x, min(struct_pack(d := list_distance(v.x, c), n := cell)).n AS cell FROM vec v, cen GROUP BY v.id)
SELECT cell, i - 1 AS i, round(avg(x[i]), 6) AS v FROM asg, range(1, 65) t(i) GROUP BY cell, i""")
def q_kmeans_round(spark, d):
    centroids, _ = K.kmeans(emb(spark, d), "x", 8, 1, "first")
    rows = [(c, i, float(v)) for c, row in enumerate(centroids) for i, v in enumerate(row)]
    return spark.createDataFrame(rows, "cell long, i long, v double").withColumn("v", F.round("v", 6))


@query(f"{SEEDED} SELECT id, cell, round(list_distance(x, c), 6) AS cell_dist FROM asg JOIN cen USING (cell)")
def q_assign_cells(spark, d):
    e = emb(spark, d).select("id", "x")
    return K.assign_cells(e, "x", K.first_rows(e, "x", 8)).select(
        "id", F.col("cell").cast("long").alias("cell"), F.round("cell_dist", 6).alias("cell_dist")
    )


@query(f"{SEEDED} SELECT id, cell FROM asg")
def q_argmin(spark, d):
    """Nearest of a constant array of centroids by expressions alone."""
    e = emb(spark, d).select("id", "x")
    cells = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in K.first_rows(e, "x", 8)])
    dist = F.transform(
        cells, lambda c: F.aggregate(F.zip_with("x", c, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    )
    return e.withColumn("dist", dist).select("id", (F.array_position("dist", F.array_min("dist")) - 1).alias("cell"))


@query(
    f"{SEEDED} SELECT q.id AS qid, e.id AS nid FROM (SELECT * FROM enc q WHERE {TENTH}) q JOIN enc e ON e.cell = q.cell"
)
def q_cell_join(spark, d):
    e = seeded_index(spark, d).encoded.select("id", "cell")
    return e.where("id % 10 = 0").select(F.col("id").alias("qid"), "cell").join(
        e.hint("shuffle_hash").select(F.col("id").alias("nid"), "cell"), "cell"
    ).select("qid", "nid")


# ---- codes -----------------------------------------------------------------------------------


def _code_text(m=8):
    return F.array_join(
        F.transform(
            F.sequence(F.lit(0), F.lit(m - 1)),
            lambda i: F.conv(F.substring(F.hex("codes"), i * 2 + 1, F.lit(2)), 16, 10),
        ),
        ".",
    )


@query(f"{SEEDED} SELECT id, cell, codes, round(self_dist, 6) AS self_dist FROM enc")
def q_pack_codes(spark, d):
    return seeded_index(spark, d).encoded.select(
        "id",
        F.col("cell").cast("long").alias("cell"),
        _code_text().alias("codes"),
        F.round("self_dist", 6).alias("self_dist"),
    )


@query(f"WITH {EMB}, {seeded(residual=False)} SELECT id, codes, round(self_dist, 6) AS self_dist FROM enc")
def q_codes_without_residual(spark, d):
    return seeded_index(spark, d, by_residual=False).encoded.select(
        "id", _code_text().alias("codes"), F.round("self_dist", 6).alias("self_dist")
    )


@query(f"{SEEDED} SELECT id, round(y[1], 6) AS first, round(y[64], 6) AS last, round(list_sum(y), 5) AS total FROM enc")
def q_reconstruct(spark, d):
    i = seeded_index(spark, d)
    return i.decode(i.encoded).select(
        "id",
        F.round(F.col("y")[0], 6).alias("first"),
        F.round(F.col("y")[63], 6).alias("last"),
        F.round(L.total(F.col("y")), 5).alias("total"),
    )


@query(f"{SEEDED} SELECT cell, count(DISTINCT codes) AS codes, count(*) AS n FROM enc GROUP BY cell")
def q_distinct_codes(spark, d):
    return seeded_index(spark, d).encoded.groupBy(F.col("cell").cast("long").alias("cell")).agg(
        F.countDistinct("codes").alias("codes"), F.count("*").alias("n")
    )


@query(f"{SEEDED} SELECT min(id) AS id, count(*) AS n FROM enc GROUP BY cell, codes")
def q_collapse_codes(spark, d):
    return dedup.collapse_codes(seeded_index(spark, d).encoded).select("id", "n")


@query(f"{SEEDED} SELECT cell, count(*) AS n, round(avg(self_dist), 6) AS mean, round(stddev(self_dist), 6) AS sd, round(median(self_dist), 6) AS median FROM enc GROUP BY cell")
def q_self_distance_by_cell(spark, d):
    p = M.self_distance_profile(seeded_index(spark, d).encoded)
    return p.select(
        F.col("cell").cast("long").alias("cell"), "n", *[F.round(c, 6).alias(c) for c in ("mean", "sd", "median")]
    )


@query(f"{SEEDED} SELECT count(*) AS n, round(avg(self_dist * self_dist), 6) AS mse FROM enc")
def q_quantization_error(spark, d):
    return M.quantization_error(seeded_index(spark, d).encoded).withColumn("mse", F.round("mse", 6))


# ---- approximate search -----------------------------------------------------------------------


@query(f"{SEEDED} SELECT qid, nid, round(dist, 6) AS dist, rank FROM {ranked(adc(2, TENTH), 10)}")
def q_adc_search(spark, d):
    return seeded_index(spark, d).search(tenth(spark, d), 10, 2).withColumn("dist", F.round("dist", 6))


@query(f"{SEEDED} SELECT qid, nid, round(dist * dist, 6) AS dist, rank FROM {ranked(adc(1, TENTH), 10)}")
def q_adc_search_squared(spark, d):
    return seeded_index(spark, d).search(tenth(spark, d), 10, 1, "sq").withColumn("dist", F.round("dist", 6))


@query(f"WITH {EMB}, {seeded(k=0)} SELECT qid, nid, round(dist, 6) AS dist, rank FROM {ranked('SELECT q.id AS qid, e.id AS nid, list_distance(q.x, e.y) AS dist FROM src q, enc e WHERE q.id % 10 = 0', 5)}")
def q_pq_search(spark, d):
    """Product codes alone, without an inverted file."""
    return seeded_index(spark, d, k_cells=0).search(tenth(spark, d), 5).withColumn("dist", F.round("dist", 6))


@query(f"""{SEEDED} SELECT qid, nid, round(dist, 6) AS dist, rank FROM {ranked('SELECT p.id AS qid, a.id AS nid, list_distance(p.x, a.x) AS dist FROM (SELECT q.id, q.x, cen.cell, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.x, cen.c), cen.cell) AS pr FROM src q, cen WHERE q.id % 10 = 0) p JOIN asg a ON a.cell = p.cell WHERE p.pr <= 4', 5)}""")
def q_ivf_flat_search(spark, d):
    e = emb(spark, d).select("id", "x")
    return I.build_index(e, "x", 8, None, iters=0).search(tenth(spark, d), 5, 4).withColumn("dist", F.round("dist", 6))


@query(f"{SEEDED} SELECT round(avg(coalesce(h, 0) / 10.0), 6) AS recall FROM (SELECT DISTINCT qid FROM {EXACT}) LEFT JOIN (SELECT qid, count(*) AS h FROM {EXACT} e SEMI JOIN {WITHOUT_SELF} a ON e.qid = a.qid AND e.nid = a.nid GROUP BY qid) USING (qid)")
def q_recall_ivfpq(spark, d):
    return M.recall_at_k(
        S.knn_exact(tenth(spark, d), emb(spark, d), 10), found_without_self(spark, d), 10
    ).withColumn("recall", F.round("recall", 6))


@query(f"{SEEDED} SELECT qid, nid FROM {EXACT} INTERSECT SELECT qid, nid FROM {WITHOUT_SELF}")
def q_knn_intersect(spark, d):
    return S.knn_exact(tenth(spark, d), emb(spark, d), 10).select("qid", "nid").intersect(
        found_without_self(spark, d).select("qid", "nid")
    )


@query(f"{SEEDED} SELECT qid, nid FROM {EXACT} EXCEPT ALL SELECT qid, nid FROM {WITHOUT_SELF}")
def q_knn_missed(spark, d):
    return S.knn_exact(tenth(spark, d), emb(spark, d), 10).select("qid", "nid").exceptAll(
        found_without_self(spark, d).select("qid", "nid")
    )


@query(f"{SEEDED} SELECT qid, nid, rank FROM {ranked(adc(2, TENTH), 10)}")
def q_shard_union(spark, d):
    return seeded_index(spark, d).search(tenth(spark, d), 10, 2, shards=4).select("qid", "nid", "rank")


@query(f"{SEEDED} SELECT qid, nid, round(dist, 6) AS dist FROM ({adc(2, TENTH)}) JOIN enc e ON e.id = qid WHERE dist <= 1.05 * e.self_dist + 1e-12")
def q_search_ball(spark, d):
    i = seeded_index(spark, d)
    q = i.encoded.where("id % 10 = 0").select("id", "z", "self_dist")
    return i.search_ball(q, 0.05, 2, "z", True).select("qid", "nid", F.round("dist", 6).alias("dist"))


# ---- duplicates ----------------------------------------------------------------------------

SEEDED_DOC = f"WITH RECURSIVE {DOC}, {seeded(256)}"
NN = ranked(
    "SELECT p.id AS qid, e.id AS nid, list_distance(p.x, e.y) AS dist FROM enc p JOIN enc e ON e.cell = p.cell", 10
)
ADAPTIVE = f"(SELECT n.qid AS i, n.nid AS j FROM {NN} n JOIN enc s ON s.id = n.qid WHERE n.nid > n.qid AND CASE WHEN s.self_dist <= 1e-12 THEN abs(s.self_dist - n.dist) <= 1e-12 ELSE abs(s.self_dist - n.dist) < 0.01 * s.self_dist END)"


def doc_index(spark, d):
    """The features are written once; the index is trained on them, filled from them and asked with them."""
    return I.seeded_index(materialize(FE.doc_vec(docs(spark, d)))).materialize()


def doc_nn(spark, d):
    i = doc_index(spark, d)
    return i, i.search(i.encoded.select("id", "z"), 10, 1, col="z", latent=True)


def doc_edges(spark, d, tol=0.01):
    i, nn = doc_nn(spark, d)
    return dedup.flag_adaptive(nn, i.encoded, tol)


@query(f"{SEEDED_DOC} SELECT i, j FROM {ADAPTIVE}")
def q_flag_adaptive(spark, d):
    return doc_edges(spark, d)


@query(f"{SEEDED_DOC} SELECT qid AS i, nid AS j FROM {NN} WHERE nid > qid AND dist < 0.6")
def q_flag_absolute(spark, d):
    return dedup.flag_absolute(doc_nn(spark, d)[1], 0.6)


@query(f"{SEEDED_DOC} SELECT tol, count(*) AS n FROM (SELECT n.nid, s.self_dist, n.dist, t.tol FROM {NN} n JOIN enc s ON s.id = n.qid, (VALUES (0.001::DOUBLE), (0.01), (0.05), (0.1)) t(tol) WHERE n.nid > n.qid) WHERE CASE WHEN self_dist <= 1e-12 THEN abs(self_dist - dist) <= 1e-12 ELSE abs(self_dist - dist) < tol * self_dist END GROUP BY tol")
def q_sweep_tolerance(spark, d):
    i, nn = doc_nn(spark, d)
    return dedup.sweep_tolerance(nn, i.encoded, [0.001, 0.01, 0.05, 0.1]).groupBy("tol").agg(F.count("*").alias("n"))


_ROOT = ", par AS (SELECT j, {pick}(i) AS p FROM {edges} GROUP BY j), up(id, rep) AS (SELECT id, id FROM src UNION ALL SELECT up.id, par.p FROM up JOIN par ON par.j = up.rep), reps AS (SELECT id, min(rep) AS rep FROM up GROUP BY id)"
REPS = _ROOT.format(pick="max", edges=ADAPTIVE)


def doc_reps(spark, d, mode="ordered"):
    return dedup.resolve_representatives(
        doc_edges(spark, d), docs(spark, d).select(F.col("doc_id").cast("long").alias("id")), mode
    )


@query(f"{SEEDED_DOC}{REPS} SELECT id, rep FROM reps")
def q_representatives_seeded(spark, d):
    return doc_reps(spark, d)


@query(f"{SEEDED_DOC}{_ROOT.format(pick='min', edges=ADAPTIVE)} SELECT id, rep FROM reps")
def q_representatives_star(spark, d):
    return doc_reps(spark, d, "star")


@query(f"{SEEDED_DOC}, edge AS (SELECT i AS a, j AS b FROM {ADAPTIVE} UNION SELECT j, i FROM {ADAPTIVE}), walk(id, spot) AS (SELECT id, id FROM src UNION SELECT walk.id, edge.b FROM walk JOIN edge ON edge.a = walk.spot) SELECT id, min(spot) AS rep FROM walk GROUP BY id")
def q_representatives_connected(spark, d):
    return doc_reps(spark, d, "connected")


@query(f"{SEEDED_DOC}{REPS}, s AS (SELECT rep, count(*) AS n FROM reps GROUP BY rep) SELECT count(*) AS n, count(*) FILTER (id <> rep) AS duplicates, count(*) FILTER (s.n > 1) AS in_groups, count(*) FILTER (s.n > 1 AND id = rep) AS groups, round(count(*) FILTER (id <> rep) / count(*), 6) AS share FROM reps JOIN s USING (rep)")
def q_duplicate_counts(spark, d):
    return M.duplicate_counts(doc_reps(spark, d)).withColumn("share", F.round("share", 6))


@query(f"{SEEDED_DOC}{REPS} SELECT n, count(*) AS n_groups FROM (SELECT rep, count(*) AS n FROM reps GROUP BY rep) GROUP BY n")
def q_dup_histogram_seeded(spark, d):
    return dedup.duplication_histogram(doc_reps(spark, d)).select(F.col("group_size").alias("n"), "n_groups")


@query(f"{SEEDED_DOC}{REPS} SELECT count(*) AS n, round(avg(CAST(list_distance(a.x, b.x) < 0.5 AS INT)), 6) AS precision FROM reps JOIN src a ON a.id = reps.id JOIN src b ON b.id = reps.rep WHERE reps.id <> reps.rep")
def q_sampled_precision(spark, d):
    """The sample is larger than what is flagged here, so all of it counts."""
    return M.sampled_precision(
        doc_reps(spark, d), FE.doc_vec(docs(spark, d)), 0.5, 100_000
    ).withColumn("precision", F.round("precision", 6))


TRUTH = "truth AS (SELECT a.id, bool_or(list_distance(a.x, b.x) < 0.5) AS t FROM src a JOIN src b ON a.id <> b.id GROUP BY a.id)"
PRED = f"pred AS (SELECT src.id, src.id IN (SELECT i FROM {ADAPTIVE} UNION SELECT j FROM {ADAPTIVE}) AS p FROM src)"


def raw_truth(spark, d, threshold=0.5):
    v = FE.doc_vec(docs(spark, d))
    return S.knn_exact(v, v, 1).select(F.col("qid").alias("id"), (F.col("dist") < threshold).alias("is_true"))


@query(f"{SEEDED_DOC}, {TRUTH}, {PRED} SELECT count(*) FILTER (p AND t) AS tp, count(*) FILTER (p AND NOT t) AS fp, count(*) FILTER (NOT p AND t) AS fn, count(*) FILTER (NOT p AND NOT t) AS tn, round(count(*) FILTER (t) / count(*), 6) AS base_rate FROM truth JOIN pred USING (id)")
def q_presence_confusion(spark, d):
    v = FE.doc_vec(docs(spark, d))
    pr = M.presence_pr(dedup.has_duplicate(doc_edges(spark, d), v), raw_truth(spark, d))
    return pr.select("tp", "fp", "fn", "tn", F.round("base_rate", 6).alias("base_rate"))


@query(f"""{SEEDED_DOC}, f AS (SELECT d.lang, t.tol FROM {NN} n JOIN enc s ON s.id = n.qid JOIN documents d ON d.doc_id = n.qid,
(VALUES (0.001::DOUBLE), (0.01), (0.1)) t(tol) WHERE n.nid > n.qid AND CASE WHEN s.self_dist <= 1e-12 THEN abs(s.self_dist - n.dist) <= 1e-12
ELSE abs(s.self_dist - n.dist) < t.tol * s.self_dist END)
SELECT lang, count(*) FILTER (tol = 0.001::DOUBLE) AS "0.001", count(*) FILTER (tol = 0.01::DOUBLE) AS "0.01",
count(*) FILTER (tol = 0.1::DOUBLE) AS "0.1" FROM f GROUP BY lang""")
def q_pr_pivot(spark, d):
    """Flagged pairs by tolerance and language, one column a tolerance."""
    i, nn = doc_nn(spark, d)
    flagged = dedup.sweep_tolerance(nn, i.encoded, [0.001, 0.01, 0.1]).join(
        docs(spark, d).select(F.col("doc_id").alias("i"), "lang"), "i"
    )
    return flagged.groupBy("lang").pivot("tol", [0.001, 0.01, 0.1]).count().na.fill(0)


@query(f"WITH {DOC} SELECT a.id AS i, b.id AS j, round(list_distance(a.x, b.x), 6) AS raw_dist, list_distance(a.x, b.x) < 0.5 AS is_dup FROM src a JOIN src b ON b.id = a.id + 1")
def q_flag_raw(spark, d):
    v = FE.doc_vec(docs(spark, d))
    pairs = v.select(F.col("id").alias("i"), (F.col("id") + 1).alias("j"))
    return dedup.flag_raw(pairs, v, 0.5).select("i", "j", F.round("raw_dist", 6).alias("raw_dist"), "is_dup")


# ---- text and category queries ---------------------------------------------------------------

CAP = text_vectors("cap", first=12)
PROMPTS = """pm AS (SELECT lang, i, avg(x[i]) AS v FROM cap JOIN documents ON doc_id = cap.id, range(1, 257) t(i) WHERE cap.id % 5 = 0 GROUP BY lang, i),
pl AS (SELECT lang, list(v ORDER BY i) AS t FROM pm GROUP BY lang), prompts AS (SELECT lang AS category, list_transform(t, lambda v: v / sqrt(list_inner_product(t, t))) AS t FROM pl)"""
ZERO = f"WITH {DOC}, {CAP}, {PROMPTS}, z AS (SELECT id, category, row_number() OVER (PARTITION BY id ORDER BY -round(list_inner_product(x, t), 10), category) AS k FROM src, prompts WHERE id % 5 <> 0)"


def prompts(spark, d):
    c = docs(spark, d)
    cap = FE.doc_cap(c).where("id % 5 = 0").join(c.select(F.col("doc_id").alias("id"), "lang"), "id")
    return MM.class_prompts(cap, "lang")


@query(f"WITH {CAP}, {PROMPTS} SELECT category, round(t[1], 6) AS first, round(t[256], 6) AS last FROM prompts")
def q_broadcast_prompts(spark, d):
    return prompts(spark, d).select(
        "category", F.round(F.col("t")[0], 6).alias("first"), F.round(F.col("t")[255], 6).alias("last")
    )


@query(f"{ZERO} SELECT id, category FROM z WHERE k = 1")
def q_zero_shot(spark, d):
    return MM.zero_shot(FE.doc_vec(docs(spark, d)).where("id % 5 <> 0"), prompts(spark, d)).select("id", "category")


@query(f"{ZERO} SELECT count(*) AS n, round(avg(CAST(category = lang AS INT)), 6) AS accuracy FROM z JOIN documents ON doc_id = id WHERE k = 1")
def q_zero_shot_accuracy(spark, d):
    truth = docs(spark, d).select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    return M.accuracy(q_zero_shot(spark, d), truth).withColumn("accuracy", F.round("accuracy", 6))


@query(f"WITH {DOC}, {CAP} SELECT count(*) AS n, round(avg(h), 6) AS hit_rate FROM (SELECT qid, max(CAST(qid = nid AS INT)) AS h FROM {ranked('SELECT cap.id AS qid, src.id AS nid, -list_inner_product(cap.x, src.x) AS dist FROM cap, src WHERE cap.id % 10 = 0', 10)} GROUP BY qid)")
def q_paired_hit(spark, d):
    c = docs(spark, d)
    found = S.mips(FE.doc_cap(c).where("id % 10 = 0"), FE.doc_vec(c), 10, "t", "x")
    return M.paired_hit_at_k(found, 10).withColumn("hit_rate", F.round("hit_rate", 6))


# ---- losses -----------------------------------------------------------------------------

_PAIR = f"""{EMB}, pr AS (SELECT id, x, id // 64 AS b, list_transform(list_zip(x, {
    _NOISE.format(salt='pair:', id='id', twice='0.1::DOUBLE')
}), lambda p: p[1] + p[2]) AS u FROM src),
tp AS (SELECT id, b, x, list_transform(u, lambda v: v / sqrt(list_inner_product(u, u))) AS t FROM pr)"""
_CE = "SELECT {b}.b, ({b}.id) AS i, {o}.id AS j, list_cosine_similarity({b}.{u}, {o}.{v}) / 0.07 AS s FROM tp {b} JOIN tp {o} ON {b}.b = {o}.b"


def _contrastive_sql(u, v, other="tp"):
    return f"""(SELECT b, count(*) AS n, (avg(lr) + avg(lc)) / 2 AS loss FROM (SELECT r.b, r.i, r.l - r.dg AS lr, c.l - c.dg AS lc FROM
(SELECT a.b, a.id AS i, log_sum(list(list_cosine_similarity(a.{u}, o.{v}) / 0.07)) AS l, max(CASE WHEN a.id = o.id THEN list_cosine_similarity(a.{u}, o.{v}) / 0.07 END) AS dg FROM {other} a JOIN {other} o ON a.b = o.b GROUP BY a.b, a.id) r JOIN
(SELECT a.b, a.id AS i, log_sum(list(list_cosine_similarity(o.{u}, a.{v}) / 0.07)) AS l, max(CASE WHEN a.id = o.id THEN list_cosine_similarity(o.{u}, a.{v}) / 0.07 END) AS dg FROM {other} a JOIN {other} o ON a.b = o.b GROUP BY a.b, a.id) c USING (i)) GROUP BY b)""".replace("log_sum(list(", "ln(list_sum(list_transform(list(").replace(" / 0.07)) AS l", " / 0.07), lambda s: exp(s)))) AS l")


@query(f"WITH {_PAIR} SELECT round(sum(loss * n) / sum(n), 5) AS loss FROM {_contrastive_sql('t', 'x')}")
def q_math_loss(spark, d):
    """The paired loss of the identity codec."""
    return losses.contrastive_loss(
        FE.emb_pair(table(spark, d, "embeddings")), codecs.IdentityCodec(), 64
    ).withColumn("loss", F.round("loss", 5))


@query(f"""WITH {_PAIR}, nn AS (SELECT id, nid FROM (SELECT q.id, v.id AS nid, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.x, v.x), v.id) AS k FROM src q JOIN src v ON q.id // 128 = v.id // 128 AND q.id <> v.id) WHERE k = 1),
t2 AS (SELECT tp.id, tp.b, tp.x, tp.t, y.x AS y FROM tp JOIN nn USING (id) JOIN src y ON y.id = nn.nid)
SELECT round((SELECT sum(loss * n) / sum(n) FROM {_contrastive_sql('t', 'x', 't2')}) + (SELECT sum(loss * n) / sum(n) FROM {_contrastive_sql('x', 'y', 't2')}), 5) AS loss""")
def q_npcc_loss(spark, d):
    pairs = FE.emb_pair(table(spark, d, "embeddings"))
    near = S.chunk_nearest(pairs.select("id", "x"), "x", 128)
    y = pairs.select(F.col("id").alias("nn_id"), F.col("x").alias("x_nn"))
    return losses.npcc_loss(
        pairs.join(near.select("id", "nn_id"), "id").join(y, "nn_id"), codecs.IdentityCodec(), 64
    ).withColumn("loss", F.round("loss", 5))


@query(f"WITH {EMB} SELECT round(avg(list_inner_product(x[33:64], x[33:64])), 6) AS loss FROM src")
def q_mse_loss(spark, d):
    """A fixed codec that keeps the first half of the values."""
    keep = np.eye(64)[:, :32]
    half = codecs.Codec("half", keep, np.zeros(32), None, None, keep.T, np.zeros(64))
    return losses.mse_loss(emb(spark, d), half, batch=128).withColumn("loss", F.round("loss", 6))


@query(f"WITH {EMB} SELECT id, round(x[1] * 2 + 1, 6) AS a, round(x[2] - x[3] - 1, 6) AS b FROM src")
def q_encode_expression(spark, d):
    """A fixed encoder as a Catalyst expression."""
    w = np.zeros((64, 2))
    w[0, 0], w[1, 1], w[2, 1] = 2, 1, -1
    c = codecs.Codec("fixed", w, np.array([1.0, -1.0]))
    return c.encode(emb(spark, d), engine="expr").select(
        "id", F.round(F.col("z")[0], 6).alias("a"), F.round(F.col("z")[1], 6).alias("b")
    )


# ---- plans, fronts, ratios --------------------------------------------------------------------

#: Budgets of an index of each label's vectors: bytes of code a vector.
_CODE_BYTES = (2, 8, 32, 200)


@query(f"""WITH c AS (SELECT label, count(*) AS n, CAST(max(len(embedding)) AS BIGINT) AS dim, b FROM embeddings, (VALUES {', '.join(f'({b}::BIGINT)' for b in _CODE_BYTES)}) t(b) GROUP BY label, b),
s AS (SELECT label, n, dim, n * b + 64 * dim * 4 AS memory_bytes FROM c),
k AS (SELECT *, (SELECT max(1 << g) FROM range(0, 17) t(g) WHERE (1 << g) <= least(65536, 1 << CAST(round_even(log2(8 * sqrt(n)), 0) AS INT)) AND (g = 0 OR (1 << g) <= n // 8)) AS cells FROM s),
m AS (SELECT *, (SELECT max(1 << g) FROM range(0, 7) t(g) WHERE g = 0 OR (1 << g) <= least((memory_bytes - cells * dim * 4) / n, 64, dim)) AS m FROM k)
SELECT label, n, dim, memory_bytes, CAST(greatest(m, least(7 * m, dim) // m * m) AS BIGINT) AS out_dim, CAST(cells AS BIGINT) AS cells, CAST(m AS BIGINT) AS m FROM m""")
def q_auto_plan(spark, d):
    """An index of each label's vectors under several budgets."""
    sizes = table(spark, d, "embeddings").groupBy("label").agg(
        F.count("*").alias("n"), F.max(F.size("embedding")).cast("long").alias("dim")
    )
    many = sizes.withColumn("b", F.explode(F.array(*[F.lit(b).cast("long") for b in _CODE_BYTES])))
    cases = many.select("label", "n", "dim", (F.col("n") * F.col("b") + 64 * 4 * F.col("dim")).alias("memory_bytes"))
    return auto.plan_rows(cases).select("label", "n", "dim", "memory_bytes", "out_dim", "cells", "m")


#: Codecs that keep some values of a vector: name and places (from 0).
_KEPT = {f"first-{k}": range(k) for k in (4, 8, 16, 32, 64)} | {f"last-{k}": range(64 - k, 64) for k in (8, 16, 32)} | {f"each-{k}": range(0, 64, k) for k in (2, 4, 8)}
_ENERGY = " UNION ALL ".join(
    f"SELECT '{name}' AS name, {64 / len(places)!r}::DOUBLE AS ratio, round(sum({' + '.join(f'x[{i + 1}] * x[{i + 1}]' for i in places)}) / sum(list_inner_product(x, x)), 6) AS quality FROM src"
    for name, places in _KEPT.items()
)


@query(f"WITH {EMB}, c AS ({_ENERGY}) SELECT name FROM c a WHERE NOT EXISTS (SELECT 1 FROM c b WHERE b.ratio >= a.ratio AND b.quality >= a.quality AND (b.ratio > a.ratio OR b.quality > a.quality))")
def q_pareto(spark, d):
    """Codecs that keep some values of the embeddings: those that no other beats in ratio and kept share of squares."""
    square = F.transform("x", lambda v: v * v)
    e = emb(spark, d).select(square.alias("s"))
    sums = e.agg(*[F.sum(F.col("s")[i]).alias(f"s{i}") for i in range(64)])
    total, codecs_ = sum(F.col(f"s{i}") for i in range(64)), []
    for name, places in _KEPT.items():
        share = F.round(sum(F.col(f"s{i}") for i in places) / total, 6)
        codecs_.append(F.struct(F.lit(name).alias("name"), F.lit(64 / len(places)).alias("ratio"), share.alias("quality")))
    configs = sums.select(F.explode(F.array(*codecs_)).alias("c")).select("c.*")
    return M.pareto_front(materialize(configs), ["ratio", "quality"]).select("name")


@query("SELECT m, round(n * 64 * 4 / (n * (m + 12) + 4 * (8 * 64 + 256 * 64)), 6) AS ratio FROM (SELECT count(*) AS n FROM embeddings), (VALUES (2), (4), (8), (16)) t(m)")
def q_compression_ratio(spark, d):
    """Bytes of the vectors as they are read over those of an index. Falls as m rises: codes of eight bits take m bytes."""
    raw = table(spark, d, "embeddings").agg(
        F.count("*").alias("n"), F.sum(4 * F.coalesce(F.size("embedding"), F.lit(64))).alias("raw")
    )
    sizes = []
    for m in (2, 4, 8, 16):
        i = I.VectorIndex(np.zeros((8, 64)), np.zeros((m, 256, 64 // m)))
        sizes.append((m, i.size_bytes(1) - i.size_bytes(0), i.size_bytes(0)))
    size = F.explode(F.array(*[F.struct(F.lit(m).alias("m"), F.lit(a).alias("row"), F.lit(b).alias("tables")) for m, a, b in sizes]))
    both = raw.where("n > 0").withColumn("s", size)
    return both.select("s.m", F.round(F.col("raw") / (F.col("n") * F.col("s.row") + F.col("s.tables")), 6).alias("ratio"))


# ---- copies -----------------------------------------------------------------------------

_TAIL = f"{PLANTED}, top AS (SELECT source_id AS rep, count(*) AS n FROM planted GROUP BY 1 ORDER BY n DESC, rep LIMIT 100), pr AS (SELECT rep AS prompt_id, x, n FROM top JOIN src ON id = rep)"
_GEN = f"""gen AS (SELECT prompt_id, seed, CASE prompt_id % 3 WHEN 0 THEN x WHEN 1 THEN list_transform(list_zip(x, {
    _NOISE.format(salt='near:', id="(CAST(prompt_id AS VARCHAR) || '/' || CAST(seed AS VARCHAR))", twice='0.2::DOUBLE')
}), lambda p: p[1] + p[2])
ELSE {_NOISE.format(salt='far:', id="(CAST(prompt_id AS VARCHAR) || '/' || CAST(seed AS VARCHAR))", twice='0.6::DOUBLE')} END AS z, x FROM pr, range(0, 9) t(seed))"""
_GRADE = "CASE WHEN list_distance(z, x) < 0.1 THEN 'verbatim' WHEN list_distance(z, x) < 0.8 THEN 'between' ELSE 'none' END"


def planted_reps(spark, d):
    return FE.emb_planted(table(spark, d, "embeddings")).select("id", F.col("source_id").alias("rep"))


def tail(spark, d):
    return copies.tail_prompts(planted_reps(spark, d), emb(spark, d))


@query(f"WITH {_TAIL} SELECT prompt_id, n FROM pr")
def q_tail_prompts(spark, d):
    return tail(spark, d).select("prompt_id", "n")


@query(f"WITH {_TAIL}, {_GEN} SELECT prompt_id, seed, round(list_distance(z, x), 6) AS dist FROM gen")
def q_generate(spark, d):
    p = tail(spark, d)
    return copies.source_distance(copies.generate(p), p).select(
        "prompt_id", F.col("seed").cast("long").alias("seed"), F.round("dist", 6).alias("dist")
    )


@query(f"WITH {_TAIL}, {_GEN} SELECT prompt_id, seed, {_GRADE} AS grade FROM gen")
def q_case_grade(spark, d):
    p = tail(spark, d)
    return copies.grade_copies(copies.source_distance(copies.generate(p), p)).select(
        "prompt_id", F.col("seed").cast("long").alias("seed"), "grade"
    )


@query(f"WITH {_TAIL}, {_GEN}, g AS (SELECT prompt_id, {_GRADE} AS grade FROM gen) SELECT count(*) AS samples, count(*) FILTER (grade = 'verbatim') AS copies, round(count(*) FILTER (grade = 'verbatim') / count(*), 6) AS per_sample, count(DISTINCT prompt_id) FILTER (grade = 'verbatim') AS prompts FROM g")
def q_copy_yield(spark, d):
    p = tail(spark, d)
    return M.copy_yield(
        copies.grade_copies(copies.source_distance(copies.generate(p), p))
    ).withColumn("per_sample", F.round("per_sample", 6))


@query(f"WITH {_TAIL}, {_GEN} SELECT a.prompt_id, round(max(list_distance(a.z, b.z)), 6) AS spread, max(list_distance(a.z, b.z)) <= 0.05 AS ignores_seed FROM gen a JOIN gen b ON a.prompt_id = b.prompt_id AND a.seed < b.seed GROUP BY 1")
def q_seed_invariance(spark, d):
    return copies.seed_invariance(copies.generate(tail(spark, d))).withColumn("spread", F.round("spread", 6))


@query(f"WITH {_TAIL}, {_GEN} SELECT prompt_id, seed, nid FROM (SELECT prompt_id, seed, v.id AS nid, list_distance(z, v.x) AS dist, row_number() OVER (PARTITION BY prompt_id, seed ORDER BY round(list_distance(z, v.x), 12), v.id) AS k FROM gen, src v) WHERE k = 1 AND dist < 0.1")
def q_detect_copies(spark, d):
    return copies.detect_copies(copies.generate(tail(spark, d)), emb(spark, d), 0.1).select(
        "prompt_id", F.col("seed").cast("long").alias("seed"), "nid"
    )


@query(f"WITH {PLANTED} SELECT source_id AS rep, count(*) AS n FROM planted GROUP BY source_id HAVING count(*) > 1 ORDER BY md5('0:' || CAST(source_id AS VARCHAR)), rep LIMIT 50")
def q_sample_prompts(spark, d):
    """The weak filter: random groups of at least two items, in order of a hash."""
    return copies.sample_prompts(planted_reps(spark, d), 50)


@query("WITH g AS (SELECT doc_id AS id, min(doc_id) OVER (PARTITION BY text) AS rep, md5(coalesce(source, '')) AS c FROM documents) SELECT rep, count(*) AS n, count(DISTINCT c) AS captions, round(count(DISTINCT c) / count(*), 6) AS variety FROM g GROUP BY rep HAVING count(*) > 1")
def q_prompt_diversity(spark, d):
    from nearcopy.registry.relational import text_groups

    captions = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("source").alias("caption"))
    return copies.prompt_diversity(text_groups(spark, d), captions).withColumn("variety", F.round("variety", 6))


RUNS = """(SELECT DISTINCT {id}, array_to_string(w[i:i+7], ' ') AS g FROM (
SELECT {id}, w, unnest(range(1, len(w) - 6)) AS i FROM (
SELECT {id}, regexp_split_to_array(text, '[ \\t\\n\\r]+') AS w FROM {table}) WHERE len(w) >= 8))"""
HITS = f"(SELECT DISTINCT item_id, doc_id FROM {RUNS.format(id='doc_id', table='documents')} JOIN {
    RUNS.format(id='item_id', table='benchmark')
} USING (g))"


@query(f"SELECT item_id, doc_id FROM {HITS}")
def q_bench_hits(spark, d):
    return copies.bench_hits(table(spark, d, "documents"), table(spark, d, "benchmark"))


@query(f"WITH {PLANTED} SELECT n AS group_size, count(*) AS n_groups, CAST(sum(n) AS BIGINT) AS n_items FROM (SELECT source_id, count(*) AS n FROM planted GROUP BY 1) GROUP BY n")
def q_planted_histogram(spark, d):
    return dedup.duplication_histogram(planted_reps(spark, d))

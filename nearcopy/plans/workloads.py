"""The experiments, re-expressed on the given tables: fronts, ablations, de-duplication tables and the copy study."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from nearcopy.components import materialize
from nearcopy.functions import features as FE
from nearcopy.functions.blocks import hash_sample
from nearcopy.operators import auto, codecs, copies, dedup as D, index as I, kmeans as K, metrics as M, multimodal as MM, search as S

#: Training of the workloads' codecs: fewer rounds and smaller batches than the defaults, as the tables are small.
QUICK = {"rounds": 2, "epochs": 8, "batch": 128}
LATENT, CELLS = 128, 16


def _table(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


def _docs(spark, d):
    return _table(spark, d, "documents").select("doc_id", "text", "lang")


def _vectors(spark, d):
    docs = _docs(spark, d)
    x = materialize(FE.doc_vec(docs))
    return x, materialize(x.join(FE.doc_cap(docs), "id"))


def codec_family(
    x: DataFrame,
    pairs: DataFrame,
    latent: int,
    names=("identity", "pca", "mse", "contrastive", "npcc"),
    seed: int = 0,
    rows: DataFrame | None = None,
) -> dict[str, codecs.Codec]:
    """rows: codecs.neighbour_rows of the pairs, where several families are fitted."""
    o = QUICK | {"seed": seed}
    make = {
        "identity": codecs.IdentityCodec,
        "pca": lambda: codecs.fit_pca_codec(x, "x", latent),
        "mse": lambda: codecs.fit_mse_codec(x, "x", latent, **o),
        "contrastive": lambda: codecs.fit_contrastive_codec(pairs, latent, **o),
        "npcc": lambda: codecs.fit_npcc_codec(pairs, latent, rows=rows, **o),
        "hybrid": lambda: codecs.fit_hybrid_codec(pairs, latent, **o),
        "fused": lambda: codecs.fit_fused_codec(pairs, latent, **o),
    }
    with ThreadPoolExecutor(3) as threads:  # jobs of one training leave cores idle; the longest one begins
        fits = {n: threads.submit(make[n]) for n in sorted(names, key=lambda n: n != "npcc")}
        return {n: fits[n].result() for n in names}


def _self_free(found: DataFrame, k: int) -> DataFrame:
    return S.merge_topk(found.where("qid <> nid").drop("rank"), k)


def _recall(index, queries, truth, k, nprobe, engine="arrow"):
    return M.recall_at_k(truth, _self_free(index.search(queries, k + 1, nprobe, engine=engine), k), k).first()[0]


def _ratio(n, dim, index):
    return float(M.compression_ratio(n, dim, 4, index.size_bytes(n), index.codec.size_bytes()))


def _auto(x: DataFrame, n: int, dim: int, code_bytes: int):
    """The auto-configured baseline with about `code_bytes` bytes a vector."""
    return auto.plan_index(n, dim, n * code_bytes + 64 * dim * 4)


def _front(spark, x, pairs, ms, probes, latent, engines, one_in=10):
    n, dim = x.count(), codecs.width(x, "x")
    queries = materialize(x.where(f"id % {one_in} = 0"))
    truth = materialize(S.knn_exact(queries, x, 10))
    rows = []
    family, trained_on = codec_family(x, pairs, latent), I.codebook_rows(x)
    cells = dict(zip(family, K.kmeans_of_all(x, "x", CELLS, 3, [c.encode_block for c in family.values()]), strict=True))

    def build(name):
        found = I.build_indexes(x, "x", CELLS, ms, 8, family[name], 3, trained_on, cells[name])
        for index in found.values():
            index.encoded = index.encoded.select("id", "cell", "codes")
            index.materialize()
        return found

    with ThreadPoolExecutor(2) as threads:  # each holds its rows for codebooks on the driver
        built = dict(zip(family, threads.map(build, family), strict=True))
    for name, indexes in built.items():  # one after another: seconds are reported
        for m, index in indexes.items():
            for engine in engines:
                for p in probes if engine == "arrow" else probes[:1]:
                    began = time.time()
                    recall = float(_recall(index, queries, truth, 10, p, engine))
                    row = (name, m, p, engine, n, _ratio(n, dim, index), dim * 4 / m)
                    rows.append((*row, recall, time.time() - began))
    schema = "codec string, m int, nprobe int, engine string, n long, ratio double, code_ratio double, recall double"
    out = spark.createDataFrame(rows, schema + ", seconds double")
    front = M.pareto_front(out.where("engine = 'arrow'"), ["code_ratio", "recall"])
    front = front.select("codec", "m", "nprobe", F.lit("arrow").alias("engine"), F.lit(True).alias("on_front"))
    return out.join(front, ["codec", "m", "nprobe", "engine"], "left").na.fill(False, ["on_front"])


def w_retrieval_front(spark: SparkSession, d: str, ms=(2, 4, 8), probes=(1, 2, 4), latent: int = LATENT) -> DataFrame:
    """(codec, m, nprobe, engine, n, ratio, code_ratio, recall, seconds, on_front): image retrieval; one id in ten asks.

    Engines are blocks of an Arrow kernel and, for the first number of probes, plain expressions; they give the same
    neighbours. code_ratio leaves out ids, tables and encoder, which outweigh the codes of a small collection; the
    front is by it."""
    x, pairs = _vectors(spark, d)
    return _front(spark, x, pairs, ms, probes, latent, ("arrow", "expr"))


def w_larger_collection(
    spark: SparkSession, d: str, copies=(1, 4), ms=(4,), probes=(1, 4), latent: int = LATENT
) -> DataFrame:
    """The same on collections that grow: each vector is there `copies` times, all but the first of them disturbed. Every
    row whose id is divisible by 100 asks, against all rows."""
    x, pairs = _vectors(spark, d)
    out = None
    for c in copies:
        many = pairs
        if c > 1:
            many = materialize(FE.with_disturbed(pairs, c, "grow:", 0.02))
        part = _front(spark, many.select("id", "x"), many, ms, probes, latent, ("arrow",), 100)
        out = part if out is None else out.unionByName(part)
    return out


def w_zero_shot(spark: SparkSession, d: str, ms=(4, 8, 16), latent: int = LATENT, seeds=(0, 1)) -> DataFrame:
    """(codec, m, ratio, accuracy, spread, chance): language by prompt on what the index rebuilds, ids that made the
    prompts left out;
    auto is the baseline with m bytes a vector. spread: between seeds of the training."""
    x, pairs = _vectors(spark, d)
    docs, n, dim = _docs(spark, d), x.count(), codecs.width(x, "x")
    label = docs.select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    captions = FE.doc_cap(docs).where("id % 5 = 0").join(label.withColumnRenamed("label", "lang"), "id")
    prompts = materialize(MM.class_prompts(captions, "lang"))
    share = label.where("id % 5 <> 0").groupBy("label").count().agg(F.max("count") / F.sum("count"))
    chance, found = float(share.first()[0]), {}

    def score(name, m, index, asked):
        y = index.decode(index.encoded, "x").where("id % 5 <> 0")
        accuracy = float(M.accuracy(MM.zero_shot(y, asked), label).first()["accuracy"])
        found.setdefault((name, m), []).append((_ratio(n, dim, index), accuracy))

    rows = codecs.neighbour_rows(pairs)
    for seed in seeds:
        names = ("identity", "mse", "contrastive", "npcc") if seed == seeds[0] else ("mse", "contrastive", "npcc")
        for name, codec in codec_family(x, pairs, latent, names, seed, rows).items():
            asked = codec.encode(prompts, "t", "z", "text").select("category", F.col("z").alias("t"))
            for m, index in I.build_indexes(x, "x", CELLS, ms, 8, codec, 3).items():
                score(name, m, index, asked)
    for m in ms:
        index = auto.build_auto(x, _auto(x, n, dim, m), iters=3)
        score("auto", m, index, index.codec.encode(prompts, "t", "z").select("category", F.col("z").alias("t")))
    return _with_spread(spark, found, "accuracy", chance)


def _with_spread(spark, found, measure, chance=None):
    rows = []
    for (name, m), values in found.items():
        scores = [v for _, v in values]
        rows.append((name, m, values[0][0], sum(scores) / len(scores), max(scores) - min(scores), chance))
    out = spark.createDataFrame(
        rows, f"codec string, m int, ratio double, {measure} double, spread double, chance double"
    )
    return out if chance is not None else out.drop("chance")


def w_text_to_image(spark: SparkSession, d: str, ms=(4, 16), latent: int = LATENT, seeds=(0, 1)) -> DataFrame:
    """(codec, m, ratio, hit, spread): whether a caption finds its own document among the first ten that the index
    rebuilds."""
    x, pairs = _vectors(spark, d)
    n, dim = x.count(), codecs.width(x, "x")
    captions, found = materialize(FE.doc_cap(_docs(spark, d)).where("id % 10 = 0")), {}

    def score(name, m, index):
        hit = M.paired_hit_at_k(MM.cross_modal_search(captions, index, 10), 10).first()["hit_rate"]
        found.setdefault((name, m), []).append((_ratio(n, dim, index), float(hit)))

    rows = codecs.neighbour_rows(pairs)
    for seed in seeds:
        names = ("identity", "mse", "npcc") if seed == seeds[0] else ("mse", "npcc")
        for name, codec in codec_family(x, pairs, latent, names, seed, rows).items():
            for m, index in I.build_indexes(x, "x", CELLS, ms, 8, codec, 3).items():
                score(name, m, index)
    for m in ms:
        score("auto", m, auto.build_auto(x, _auto(x, n, dim, m), iters=3))
    return _with_spread(spark, found, "hit")


def w_auto_front(spark: SparkSession, d: str, code_bytes=(4, 8, 16, 32)) -> DataFrame:
    """(memory_bytes, m, out_dim, cells, ratio, recall) of indexes chosen under a budget."""
    x, _ = _vectors(spark, d)
    n, dim = x.count(), codecs.width(x, "x")
    queries = materialize(x.where("id % 10 = 0"))
    truth, rows = materialize(S.knn_exact(queries, x, 10)), []
    for spec, index in auto.auto_front(x, [n * b + 64 * dim * 4 for b in code_bytes], iters=3):
        recall = float(_recall(index.materialize(), queries, truth, 10, 4))
        rows.append((spec.memory_bytes, spec.m, spec.out_dim, spec.cells, _ratio(n, dim, index), recall))
    return spark.createDataFrame(rows, "memory_bytes long, m int, out_dim int, cells int, ratio double, recall double")


def w_latent_ablation(
    spark: SparkSession, d: str, dims=(8, 16, 32, 64, 128), code_bytes: int = 8, more_bytes: int = 16
) -> DataFrame:
    """(codec, arm, latent, m, code_bytes, recall). same: equal bytes of code after each latent; more: a low latent
    whose quantizer
    has more memory (`more_bytes` bytes, as far as the latent has dimensions)."""
    x, _ = _vectors(spark, d)
    queries = materialize(x.where("id % 10 = 0"))
    truth, rows = materialize(S.knn_exact(queries, x, 10)), []
    for dim in dims:
        for name, codec in codec_family(x, None, dim, ("pca", "mse")).items():
            arms = [("same", min(code_bytes, dim))] + [("more", min(more_bytes, dim))] * (
                code_bytes < dim <= more_bytes
            )
            for arm, m in arms:
                index = I.build_index(x, "x", CELLS, m, 8, codec, 3).materialize()
                rows.append((name, arm, dim, m, index.bytes_per_vector(), float(_recall(index, queries, truth, 10, 4))))
    return spark.createDataFrame(rows, "codec string, arm string, latent int, m int, code_bytes int, recall double")


def _specs(x, pairs, pairs_b, latent=LATENT):
    def spec(kind, source, m, shards):
        if kind == "mse":
            return D.DedupSpec(
                kind, lambda v: codecs.fit_mse_codec(v, "x", latent, **QUICK), CELLS, m, 8, shards=shards, iters=3
            )
        return D.DedupSpec(
            kind, lambda v: codecs.fit_npcc_codec(source, latent, **QUICK), CELLS, m, 8, shards=shards, iters=3
        )

    return [
        ("a-mse-m16-4-shards", x, spec("mse", pairs, 16, 4)),
        ("a-npcc-m16-4-shards", x, spec("npcc", pairs, 16, 4)),
        ("b-npcc-m4", pairs_b.select("id", "x"), spec("npcc", pairs_b, 4, 1)),
    ]


def w_dedup_table(spark: SparkSession, d: str, sample: int = 10_000) -> DataFrame:
    """(name, n, duplicates, share, precision, recall, base_rate, seconds, index_bytes, ratio) of three configurations.

    Truth is by the raw vectors of the same features: precision on a sample of flagged items against their
    representative; recall on
    a sample of items that have a near copy with a smaller id, of which it is the share that was flagged; base rate:
    the share of such items."""
    x, pairs = _vectors(spark, d)
    docs = _docs(spark, d)
    pairs_b = materialize(FE.doc_vec_b(docs).join(pairs.select("id", "t"), "id"))
    rows, truth = [], {}
    for name, v, spec in _specs(x, pairs, pairs_b):
        if name[0] not in truth:  # once for each feature set
            asked = hash_sample(v, sample, "id")
            near = S.knn_exact(asked, v, 10).groupBy("qid")
            near = near.agg(F.max(((F.col("nid") < F.col("qid")) & (F.col("dist") < 0.5)).cast("int")).alias("later"))
            truth[name[0]] = materialize(near)
        began = time.time()
        got = D.dedup(v, spec)
        reps = materialize(got.reps)
        took, counts = time.time() - began, M.duplicate_counts(reps).first()
        precision = M.sampled_precision(reps, v, 0.5).first()["precision"]
        later = truth[name[0]].join(reps, F.col("qid") == F.col("id"))
        base, hit, total = later.agg(
            F.avg("later"), F.sum(F.col("later") * (F.col("id") != F.col("rep")).cast("int")), F.sum("later")
        ).first()
        size = got.index.size_bytes(counts["n"])
        row = (
            name, counts["n"], counts["duplicates"], float(counts["share"]), float(precision or 0), hit / max(total, 1)
        )
        rows.append((*row, float(base), took, size, _ratio(counts["n"], 256, got.index)))
    return spark.createDataFrame(
        rows,
        "name string, n long, duplicates long, share double, precision double, recall double, base_rate double, "
        "seconds double, index_bytes long, ratio double",
    )


def w_pr_curve(
    spark: SparkSession, d: str, tols=(0.001, 0.005, 0.01, 0.05, 0.1), m: int = 8, sample: int = 1000
) -> DataFrame:
    """(half, tol, precision, recall, base_rate, chosen): presence of a copy of sampled items, against their
    exhaustive search on the raw
    vectors. A tolerance is chosen (by F1) on even ids; odd ids report what it gives."""
    x, _ = _vectors(spark, d)
    asked = materialize(hash_sample(x, sample, "id"))
    truth = S.knn_exact(asked, x, 1).select(F.col("qid").alias("id"), (F.col("dist") < 0.5).alias("is_true"))
    truth = materialize(truth)
    index = I.build_index(x, "x", CELLS, m, 8, None, 5).materialize()
    own = index.encoded.join(asked.select("id"), "id", "left_semi")
    nn = materialize(index.search(own.select("id", "z"), 10, 1, col="z", latent=True))
    both = nn.unionByName(nn.select(F.col("nid").alias("qid"), F.col("qid").alias("nid"), "dist", "rank"))
    edges = [D.flag_adaptive(both, index.encoded, t) for t in tols]
    rows = []
    for t, e in zip(tols, edges, strict=True):
        flags = materialize(D.has_duplicate(e, asked))
        for half, rest in (("choose", 0), ("report", 1)):
            keep = F.pmod("id", F.lit(2)) == rest
            r = M.presence_pr(flags.where(keep), truth.where(keep)).first()
            rows.append((half, float(t), float(r["precision"] or 0), float(r["recall"] or 0), float(r["base_rate"])))
    best = max(
        (r for r in rows if r[0] == "choose"), key=lambda r: (2 * r[2] * r[3] / max(r[2] + r[3], 1e-9), -r[1])
    )[1]
    schema = "half string, tol double, precision double, recall double, base_rate double, chosen boolean"
    return spark.createDataFrame([(*r, r[1] == best) for r in rows], schema)


def w_threshold_compare(spark: SparkSession, d: str, m: int = 8) -> DataFrame:
    """(test, value, pairs, precision, recall): absolute and adaptive tests on the same neighbours; truth by the raw
    vectors."""
    x, _ = _vectors(spark, d)
    index = I.build_index(x, "x", 16, m, 8, None, 5).materialize()
    nn = materialize(index.search(index.encoded.select("id", "z"), 10, 1, col="z", latent=True))
    true = materialize(D.flag_raw(S.knn_exact(x, x, 10).where("nid > qid").select(F.col("qid").alias("i"), F.col("nid").alias("j")), x, 0.5).where("is_dup").select("i", "j"))
    total, rows = true.count(), []
    cases = [("absolute", t, D.flag_absolute(nn, t)) for t in (0.3, 0.5, 0.7)] + [
        ("adaptive", t, D.flag_adaptive(nn, index.encoded, t)) for t in (0.01, 0.05, 0.1)
    ]
    for name, t, edges in cases:
        n, hit = edges.count(), edges.join(true, ["i", "j"], "left_semi").count()
        rows.append((name, float(t), n, hit / max(n, 1), hit / max(total, 1)))
    return spark.createDataFrame(rows, "test string, value double, pairs long, precision double, recall double")


def w_dup_histogram(spark: SparkSession, d: str) -> DataFrame:
    """(group_size, n_groups, n_items, share): planted copies found again by raw distance, and the tail's running
    share."""
    x = materialize(FE.emb_planted(_table(spark, d, "embeddings")))
    index = I.build_index(x, "x", 16, 16, 8, None, 2).materialize()
    ball = index.search_ball(index.encoded.select("id", "z", "self_dist"), 0.05, 1, "z", True)
    edges = D.flag_raw(
        ball.where("nid > qid").select(F.col("qid").alias("i"), F.col("nid").alias("j")), x, 0.1
    ).where("is_dup").select("i", "j")
    h = D.duplication_histogram(D.resolve_representatives(edges, x.select("id")))
    w = W.orderBy(F.desc("group_size")).rowsBetween(W.unboundedPreceding, 0)
    return h.withColumn("share", F.round(F.sum("n_items").over(w) / F.lit(x.count()), 6))


def w_copy_study(spark: SparkSession, d: str, raw_threshold: float = 0.1) -> DataFrame:
    """(prompts, size_class, samples, copies, per_sample, any_copies, prompts_with_copy): the tail against random
    groups. copies are near
    the prompt's own vector, any_copies near any training vector; groups are classed by size (a power of two, from
    below)."""
    db = FE.emb(_table(spark, d, "embeddings")).select("id", "x")
    reps = FE.emb_planted(_table(spark, d, "embeddings")).select("id", F.col("source_id").alias("rep"))
    weak = copies.sample_prompts(reps, 100, 1)
    random = db.join(F.broadcast(weak), F.col("id") == F.col("rep")).select(F.col("id").alias("prompt_id"), "x", "n")
    out = None
    for name, prompts in (("tail", copies.tail_prompts(reps, db)), ("random", random)):
        prompts = materialize(prompts)
        samples = materialize(copies.generate(prompts))
        own = copies.grade_copies(copies.source_distance(samples, prompts)).select("prompt_id", "seed", "grade")
        near = copies.detect_copies(samples, db, raw_threshold).select("prompt_id", "seed", "nid")
        graded = own.join(near, ["prompt_id", "seed"], "left").join(prompts.select("prompt_id", "n"), "prompt_id")
        graded = graded.withColumn("size_class", F.pow(F.lit(2), F.floor(F.log2("n"))).cast("long"))
        verbatim = F.col("grade") == "verbatim"
        part = graded.groupBy(F.lit(name).alias("prompts"), "size_class").agg(
            F.count("*").alias("samples"),
            F.count_if(verbatim).alias("copies"),
            F.avg(verbatim.cast("double")).alias("per_sample"),
            F.count("nid").alias("any_copies"),
            F.countDistinct(F.when(verbatim, F.col("prompt_id"))).alias("prompts_with_copy"),
        )
        out = part if out is None else out.unionByName(part)
    return out


def w_copied_passages(spark: SparkSession, d: str) -> DataFrame:
    """(size_class, groups, groups_with_hit, share): exact groups of documents by size, and in how many a benchmark
    text stands."""
    docs = _docs(spark, d)
    hits = copies.bench_hits(docs, _table(spark, d, "benchmark")).select("doc_id").distinct()
    marked = docs.join(hits.withColumn("hit", F.lit(1)), "doc_id", "left")
    groups = marked.groupBy(F.md5(F.coalesce("text", F.lit(""))).alias("g")).agg(
        F.count("*").alias("n"), F.max("hit").alias("hit")
    )
    classes = groups.groupBy(F.pow(F.lit(2), F.floor(F.log2("n"))).cast("long").alias("size_class"))
    return classes.agg(F.count("*").alias("groups"), F.count("hit").alias("groups_with_hit")).withColumn(
        "share", F.col("groups_with_hit") / F.col("groups")
    )


def w_caption_variety(spark: SparkSession, d: str) -> DataFrame:
    """(copied, groups, mean_n, mean_captions, mean_distance): whether groups that the stand-in generator copies
    differ from
    others in the number of distinct captions and in the captions' mean pair distance. A member's caption is that of a
    document that a hash of its id names, so no relation is to be expected here; a collection with captions of its
    own can show one."""
    db = FE.emb(_table(spark, d, "embeddings")).select("id", "x")
    reps = FE.emb_planted(_table(spark, d, "embeddings")).select("id", F.col("source_id").alias("rep"))
    docs = _docs(spark, d)
    total = docs.count()
    member = reps.withColumn("doc", F.pmod(F.xxhash64("id"), F.lit(total)))
    words = docs.select(F.col("doc_id").alias("doc"), F.substring("text", 1, 80).alias("caption"))
    captions = member.join(words, "doc").select("id", "caption")
    vectors = member.join(FE.doc_cap(docs).withColumnRenamed("id", "doc"), "doc").select("id", "rep", "t")
    variety = copies.prompt_diversity(reps, captions).join(copies.mean_pair_distance(vectors), "rep")
    prompts = materialize(copies.tail_prompts(reps, db))
    graded = copies.grade_copies(copies.source_distance(copies.generate(prompts), prompts))
    hit = graded.groupBy("prompt_id").agg(F.max((F.col("grade") == "verbatim").cast("int")).alias("copied"))
    joined = variety.join(hit, F.col("rep") == F.col("prompt_id")).groupBy("copied")
    return joined.agg(
        F.count("*").alias("groups"),
        F.avg("n").alias("mean_n"),
        F.avg("captions").alias("mean_captions"),
        F.avg("mean_distance").alias("mean_distance"),
    )


def w_alignment(spark: SparkSession, d: str, latent: int = LATENT) -> DataFrame:
    """(codec, hit): caption to document by latents, each side compressed by itself or both together."""
    x, pairs = _vectors(spark, d)
    cap = pairs.select("id", "t")
    one, two = codecs.fit_mse_codec(x, "x", latent, **QUICK), codecs.fit_mse_codec(cap, "t", latent, seed=1, **QUICK)
    rows = []
    cases = {"independent": (one.encode(x, "x", "z"), two.encode(cap, "t", "z"))}
    for name in ("contrastive", "npcc"):
        c = codec_family(x, pairs, latent, (name,))[name]
        cases[name] = (c.encode(x, "x", "z"), c.encode(cap, "t", "z", "text"))
    for name, (images, texts) in cases.items():
        found = S.mips(texts.where("id % 10 = 0").select("id", "z"), images.select("id", "z"), 10, "z")
        rows.append((name, float(M.paired_hit_at_k(found, 10).first()["hit_rate"])))
    return spark.createDataFrame(rows, "codec string, hit double")


def w_self_distance_by_cell(spark: SparkSession, d: str) -> DataFrame:
    x, _ = _vectors(spark, d)
    return M.self_distance_profile(I.build_index(x, "x", 16, 8, 8, None, 5).encoded)


def w_hybrids(spark: SparkSession, d: str, latent: int = LATENT) -> DataFrame:
    """(codec, recall): mixtures of losses and the fused encoder against the plain ones."""
    x, pairs = _vectors(spark, d)
    queries = x.where("id % 10 = 0")
    truth = materialize(S.knn_exact(queries, x, 10))
    fam = codec_family(x, pairs, latent, ("mse", "hybrid", "fused"))
    fam["contrastive-reconstructed"] = codecs.fit_contrastive_codec(pairs, latent, space="reconstructed", **QUICK)
    rows = [(n, float(_recall(I.build_index(x, "x", 16, 8, 8, c, 3), queries, truth, 10, 4))) for n, c in fam.items()]
    return spark.createDataFrame(rows, "codec string, recall double")


def w_residual(spark: SparkSession, d: str) -> DataFrame:
    """(by_residual, recall): product codes of residuals or of whole vectors."""
    x, _ = _vectors(spark, d)
    queries = x.where("id % 10 = 0")
    truth = materialize(S.knn_exact(queries, x, 10))
    rows = [(r, float(_recall(I.build_index(x, "x", 16, 8, 8, None, 3, by_residual=r), queries, truth, 10, 4))) for r in (True, False)]
    return spark.createDataFrame(rows, "by_residual boolean, recall double")


WORKLOADS = {
    f.__name__: f
    for f in (
        w_retrieval_front,
        w_larger_collection,
        w_zero_shot,
        w_text_to_image,
        w_auto_front,
        w_latent_ablation,
        w_dedup_table,
        w_pr_curve,
        w_threshold_compare,
        w_dup_histogram,
        w_copy_study,
        w_copied_passages,
        w_caption_variety,
        w_alignment,
        w_self_distance_by_cell,
        w_hybrids,
        w_residual,
    )
}

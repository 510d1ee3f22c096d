"""Invariants of quantizers, search, de-duplication and streams on the smallest tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from nearcopy.functions import features as FE, losses
from nearcopy.operators import auto, codecs, dedup as D, index as I, kmeans as K, metrics as M, search as S
from nearcopy.operators.smallworld import SmallWorldCoarse
from nearcopy.plans import planner


@pytest.fixture(scope="module")
def emb(spark, data):
    return FE.emb(spark.read.parquet(f"{data}/embeddings.parquet")).select("id", "x").cache()


@pytest.fixture(scope="module")
def doc(spark, data):
    return FE.doc_vec(spark.read.parquet(f"{data}/documents.parquet")).cache()


def rows(df, *cols):
    return sorted(map(tuple, df.select(*cols).collect()))


def test_exact_search_equals_join(emb):
    q = emb.where("id % 50 = 0")
    assert rows(S.knn_exact(q, emb, 5), "qid", "nid", "rank") == rows(S.knn_joined(q, emb, 5), "qid", "nid", "rank")


def test_full_probing_of_flat_lists_is_exact_and_recall_grows(emb):
    q = emb.where("id % 25 = 0")
    truth = S.knn_exact(q, emb, 10, include_self=True)
    index = I.build_index(emb, k_cells=8, m=None, iters=2)
    got = [M.recall_at_k(truth, index.search(q, 10, p), 10).first()[0] for p in (1, 2, 8)]
    assert got == sorted(got) and got[-1] == 1.0


def test_shards_and_joined_search_change_nothing(emb, monkeypatch):
    q = emb.where("id % 25 = 0")
    index = I.seeded_index(emb)
    one = rows(index.search(q, 5, 2), "qid", "nid", "rank")
    assert one == rows(index.search(q, 5, 2, shards=3), "qid", "nid", "rank")
    monkeypatch.setattr(I, "BROADCAST_BYTES", 1)
    assert one == rows(index.search(q, 5, 2, salt=3), "qid", "nid", "rank")


def test_self_distance_is_distance_to_the_rebuilt_vector(emb):
    index = I.build_index(emb, k_cells=4, m=8, bits=4, iters=2)
    both = index.encoded.join(index.decode(index.encoded), "id").select("z", "y", "self_dist").collect()
    assert all(abs(np.linalg.norm(np.array(r.z) - r.y) - r.self_dist) < 1e-9 for r in both)


def test_blocks_must_divide():
    with pytest.raises(ValueError):
        I.fit_codebooks(np.zeros((4, 10)), 3, 2, 1)


def test_kmeans_cost_never_rises(emb):
    _, costs = K.kmeans(emb, "x", 6, 5)
    assert all(b <= a + 1e-9 for a, b in zip(costs, costs[1:], strict=False))


def test_pca_and_linear_reconstruction(emb):
    pca = codecs.fit_pca_codec(emb, "x", 16)
    assert np.allclose(pca.image.T @ pca.image, np.eye(16), atol=1e-9)
    mse = codecs.fit_mse_codec(emb, "x", 16, rounds=2, epochs=30)
    error = lambda c: losses.mse_loss(emb, c, batch=1000).first()[0]
    assert error(pca) <= error(mse) + 1e-9 and error(mse) < 1.3 * error(pca)


def test_opq_is_orthogonal_and_improves(doc):
    c = codecs.fit_opq(doc, "x", 32, 8, 3, 4)
    assert np.allclose(c.image.T @ c.image, np.eye(32), atol=1e-8)
    assert c.manifest["errors"][-1] <= c.manifest["errors"][0]


def test_npcc_without_neighbours_is_the_contrastive_codec(spark, emb, data):
    pairs = FE.emb_pair(spark.read.parquet(f"{data}/embeddings.parquet"))
    a = codecs.fit_npcc_codec(pairs, 8, lam=0, rounds=1, epochs=2)
    b = codecs.fit_contrastive_codec(pairs, 8, rounds=1, epochs=2)
    assert np.allclose(a.image, b.image)


def test_contrastive_gradient():
    rng = np.random.default_rng(0)
    u, v = rng.standard_normal((6, 4)), rng.standard_normal((6, 4))
    loss, g, _ = losses.contrastive(u, v, 0.5)
    step = np.zeros_like(u)
    step[2, 1] = 1e-6
    assert abs((losses.contrastive(u + step, v, 0.5)[0] - loss) / 1e-6 - g[2, 1]) < 1e-5


def test_chunk_neighbours(emb):
    x = {r.id: np.array(r.x) for r in emb.collect()}
    for r in S.chunk_nearest(emb, "x", 100, block=32).collect():
        best = min((np.linalg.norm(x[r.id] - x[j]), j) for j in x if j != r.id and j // 100 == r.id // 100)
        assert best[1] == r.nn_id


def loop(n, edges):
    rep = list(range(n))
    for i in range(n):
        for j in sorted(b for a, b in edges if a == i and b > i):
            rep[j] = rep[i]
    return rep


def test_representatives_equal_the_sequential_loop(spark):
    rng = np.random.default_rng(5)
    for _ in range(4):
        n = 25
        edges = [(int(a), int(b)) for a, b in rng.integers(0, n, (40, 2)) if a < b]
        e = spark.createDataFrame(edges, "i long, j long")
        ids = spark.range(n)
        got = dict(D.resolve_representatives(e, ids).collect())
        assert [got[i] for i in range(n)] == loop(n, edges)
        star, linked = dict(D.resolve_representatives(e, ids, "star").collect()), dict(
            D.resolve_representatives(e, ids, "connected").collect()
        )
        dups = lambda r: sum(k != v for k, v in r.items())
        assert dups(got) == dups(star) <= dups(linked)


def test_no_edges_and_empty_tables(spark):
    e, ids = spark.createDataFrame([], "i long, j long"), spark.range(3)
    assert rows(D.resolve_representatives(e, ids), "id", "rep") == [(i, i) for i in range(3)]
    assert D.resolve_representatives(e, spark.range(0)).count() == 0


def test_flags_grow_with_the_tolerance(doc):
    index = I.seeded_index(doc)
    nn = index.search(index.encoded.select("id", "z"), 10, 1, col="z", latent=True)
    sets = [set(rows(D.flag_adaptive(nn, index.encoded, t), "i", "j")) for t in (0.001, 0.01, 0.1)]
    assert sets[0] <= sets[1] <= sets[2]


def test_kept_and_dropped_split_the_table(doc):
    got = D.dedup(doc, D.DedupSpec(seeded=True, k_cells=4))
    assert D.deduplicate(doc, got.reps).count() + D.dropped(doc, got.reps).count() == doc.count()
    assert got.hist.agg(F.sum("n_items")).first()[0] == doc.count()
    assert got.reps.where("rep > id").count() == 0


def test_planted_copies_are_found_and_the_control_is_clean(spark, data, emb):
    assert S.knn_exact(emb, emb, 1).where("dist < 0.75").count() == 0
    x = FE.emb_planted(spark.read.parquet(f"{data}/embeddings.parquet"), 16)
    assert D.flag_raw(
        S.knn_exact(x, x, 1).select(F.col("qid").alias("i"), F.col("nid").alias("j")), x, 0.1
    ).where("is_dup").count() > 0


def test_ball_pruning_and_plans(doc):
    index = I.seeded_index(doc).materialize()
    q = index.encoded.select("id", "z", "self_dist")
    probes = index.probe(q, 3, "z", True, True)
    kept = planner.prune_probes(probes, index, 0.05, planner.cell_radii(index))
    whole = index.search_ball(q, 0.05, 3, "z", True)
    cells = {r.id: r.cell for r in index.encoded.select("id", "cell").collect()}
    left = {(r.qid, r.cell) for r in kept.collect()}
    assert all((r.qid, cells[r.nid]) in left for r in whole.collect())
    assert "search" in planner.plan_search(index, 10, 99, 5).explain() and planner.plan_dedup(index, 1, 0.01).steps


def test_small_world_finds_most_nearest_cells():
    rng = np.random.default_rng(1)
    c, q = rng.standard_normal((300, 16)), rng.standard_normal((100, 16))
    assert (SmallWorldCoarse(c, 16).search(q)[:, 0] == K.nearest(q, c)[0][:, 0]).mean() > 0.9


def test_planned_index_of_the_printed_budget():
    s = auto.plan_index(350_000_000, 1024, 6 << 30)
    assert (s.opq_blocks, s.out_dim, s.cells, s.links, s.bits) == (16, 112, 65536, 32, 8)


def test_ratio_falls_with_more_blocks():
    made = [I.VectorIndex(np.zeros((8, 64)), np.zeros((m, 256, 64 // m))).size_bytes(1000) for m in (2, 4, 8)]
    assert made == sorted(made)


def test_store_round_trip(spark, emb, tmp_path):
    from nearcopy.sources.index_source import IndexSource, read_lists

    index = I.seeded_index(emb)
    index.save(str(tmp_path), spark)
    again = I.VectorIndex.load(str(tmp_path), spark)
    q = emb.where("id % 50 = 0")
    assert rows(index.search(q, 5, 2), "qid", "nid") == rows(again.search(q, 5, 2), "qid", "nid")
    spark.dataSource.register(IndexSource)
    want = rows(index.encoded.where("cell = 3"), "id")
    assert rows(read_lists(spark, str(tmp_path), [3]), "id") == want
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    for pruning in ("false", "true"):
        lists = spark.read.format("nearcopy_index").option("path", str(tmp_path)).option("pruning", pruning).load()
        assert rows(lists.where("cell = 3"), "id") == want


def test_invalid_vectors_go_to_quarantine(spark):
    from nearcopy.sources.vectors import validate_vectors

    df = spark.createDataFrame(
        [(1, [1.0, 2.0]), (2, [1.0]), (3, None), (4, [float("nan"), 0.0]), (5, [None, 1.0])], "id long, x array<double>"
    )
    good, bad = validate_vectors(df, "x", 2)
    assert rows(good, "id") == [(1,)] and rows(bad, "id") == [(2,), (3,), (4,), (5,)]


def test_captions_in_all_formats(spark, tmp_path):
    from nearcopy.sources.vectors import read_captions, write_captions

    df = spark.createDataFrame([(1, 'a "b"\nc'), (2, "ü,;")], "id long, caption string")
    for kind in ("json", "csv", "parquet"):
        write_captions(df, f"{tmp_path}/{kind}", kind)
        assert rows(
            read_captions(spark, f"{tmp_path}/{kind}", "id long, caption string", kind), "id", "caption"
        ) == rows(df, "id", "caption")


def test_stream_equals_batch_in_ball_mode(spark, data):
    from nearcopy.registry.streams import stream_dedup

    got = dict(stream_dedup(spark, data).collect())
    x = FE.emb_planted(spark.read.parquet(f"{data}/embeddings.parquet"), 32).select("id", "x")
    index = I.seeded_index(x)
    nn = index.search_ball(index.encoded.select("id", "z", "self_dist"), 0.01, 1, "z", True)
    assert got == dict(D.resolve_representatives(D.flag_adaptive(nn, index.encoded, 0.01), x).collect())


def test_arrivals_of_a_vector_are_not_capped(spark, tmp_path):
    from nearcopy.registry.streams import arrivals

    spark.createDataFrame(
        [(i, [float(i)] * 64, 0) for i in range(3)], "vec_id long, embedding array<float>, label int"
    ).write.parquet(f"{tmp_path}/embeddings.parquet")
    spark.range(10).selectExpr(
        "id AS event_id", "timestamp'2020-01-01' AS ts", "id AS user_id", "'view' AS event_type"
    ).write.parquet(f"{tmp_path}/events.parquet")
    assert rows(arrivals(spark, str(tmp_path)).groupBy("id").count(), "id", "count") == [(0, 4), (1, 3), (2, 3)]


def test_registered_stream_has_the_copies_of_all_sources(spark, data):
    from nearcopy.registry.streams import QUERIES

    x = FE.emb_planted(spark.read.parquet(f"{data}/embeddings.parquet"), 256)
    assert QUERIES["stream_dedup"](spark, data).count() == x.count()


def test_intermediate_tables_can_be_removed(spark, tmp_path, monkeypatch):
    from nearcopy import components

    monkeypatch.setattr(components, "_scratch", lambda s: f"{tmp_path}/scratch")
    gone = components.materialize(spark.range(5))
    assert gone.count() == 5 and (tmp_path / "scratch").exists()
    components.drop_scratch(spark)
    assert not (tmp_path / "scratch").exists()


def test_nearest_at_many_centroids_stays_small():
    """The reference's number of cells: memory is bounded by tiles, not by cells times dimensions."""
    import tracemalloc

    rng = np.random.default_rng(0)
    centroids, x = rng.standard_normal((65_536, 128)), rng.standard_normal((300, 128))
    x[7] = centroids[40_000]
    tracemalloc.start()
    at, d = K.nearest(x, centroids)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 200 << 20 and (at[7, 0], d[7, 0]) == (40_000, 0)
    few, _ = K.nearest(x[:5], centroids, 3)
    assert (few == np.argsort(((x[:5, None] - centroids[None]) ** 2).sum(axis=2), axis=1, kind="stable")[:, :3]).all()


def test_samples_keep_their_partitions(spark):
    from nearcopy.functions.blocks import hash_share

    rows = spark.range(100_000).repartition(8)
    some = hash_share(rows, 40_000, "id")
    assert 38_000 < some.count() < 42_000 and some.rdd.getNumPartitions() == 8
    assert sorted(some.collect()) == sorted(hash_share(rows.repartition(3), 40_000, "id").collect())
    assert hash_share(rows, 10**6, "id").count() == 100_000


def test_exact_search_by_block_pairs(spark, emb, monkeypatch):
    """More queries than are broadcast: blocks of both sides meet by a shuffle, with the same result."""
    q = emb.where("id % 3 = 0")
    want = rows(S.knn_exact(q, emb, 4), "qid", "nid", "rank")
    monkeypatch.setattr(S, "BLOCK_QUERIES", 10)
    monkeypatch.setattr(S, "BLOCK_BYTES", 64 * 8 * 60)
    assert rows(S.knn_exact(q, emb, 4), "qid", "nid", "rank") == want


def test_neighbours_in_chunks_by_block_pairs(spark, emb):
    want = rows(S.chunk_nearest(emb, "x", 100), "id", "nn_id")
    assert rows(S.chunk_nearest(emb, "x", 100, block=17), "id", "nn_id") == want


def test_engines_and_shards_give_the_same_neighbours(spark, emb):
    index, q = I.seeded_index(emb).materialize(), emb.where("id % 20 = 0")
    want = rows(index.search(q, 5, 2), "qid", "nid", "rank")
    assert rows(index.search(q, 5, 2, engine="expr"), "qid", "nid", "rank") == want
    assert rows(index.search(q, 5, 2, shards=4), "qid", "nid", "rank") == want
    flat = I.build_index(emb, "x", 8, None, iters=2).materialize()
    assert rows(flat.search(q, 5, 8), "qid", "nid", "rank") == rows(
        S.knn_exact(q, emb, 5, include_self=True), "qid", "nid", "rank"
    )


def test_saved_index_with_other_groups_and_appended_rows(spark, emb, tmp_path):
    from nearcopy.sources.index_source import IndexSource, read_lists

    index = I.build_index(emb.where("id < 300"), "x", 40, 8, iters=1, coarse="graph")
    path = str(tmp_path)
    index.save(path, spark, groups=16)
    assert I.VectorIndex.append_to(path, emb.where("id >= 300")) == 2
    again = I.VectorIndex.load(path, spark)
    assert again.coarse is not None and again.encoded.count() == emb.count()
    spark.dataSource.register(IndexSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    lists = spark.read.format("nearcopy_index").option("path", path).option("pruning", "true").load()
    for cells in ([37], [3, 20, 36]):
        want = rows(again.encoded.where(F.col("cell").isin(cells)), "id")
        assert want and rows(lists.where(F.col("cell").isin(cells)), "id") == want
        assert rows(read_lists(spark, path, cells), "id") == want
    assert rows(lists.where("cell IN (3, 20) AND cell = 20"), "id") == rows(again.encoded.where("cell = 20"), "id")


def test_planner_chooses_for_deduplication(spark, emb):
    same = emb.select("id", "x").unionByName(
        emb.where("id = 5").select(F.explode(F.sequence(F.lit(1000), F.lit(1030))).alias("id"), "x")
    )
    plain = D.dedup(same, D.DedupSpec(seeded=True, k=5, mode="connected"))
    planned = D.dedup(same, D.DedupSpec(seeded=True, k=5, mode="connected", planned=True))
    assert "collapse" in planned.stats["plan"] and "salt" in plain.stats["plan"]
    got = dict(planned.reps.select("id", "rep").collect())
    assert all(got[i] == got[5] for i in range(1000, 1031))


def test_knn_block_and_mean_vectors(spark, emb):
    from nearcopy.functions.sqlapi import mean_vectors, register

    register(spark, I.seeded_index(emb))
    got = spark.sql(
        "SELECT * FROM knn_block(array(array(0D, 0D)), array(array(1D, 0D), array(0D, 0D), array(0D, 2D)), 2)"
    ).collect()
    assert [(r.q, r.nn, r.dist) for r in got] == [(0, 1, 0.0), (0, 0, 1.0)]
    assert spark.sql("SELECT * FROM hash_features('one two three')").count() == 2
    table = spark.createDataFrame([(1, [1.0, 3.0]), (1, [3.0, 5.0]), (2, [0.0, 1.0])], "k int, x array<double>")
    assert dict(mean_vectors(table, "k").collect()) == {1: [2.0, 4.0], 2: [0.0, 1.0]}


def test_mean_pair_distance_needs_no_pairs(spark):
    from nearcopy.operators.copies import mean_pair_distance

    x = np.random.default_rng(1).standard_normal((6, 5))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    table = spark.createDataFrame([(i, 0, v.tolist()) for i, v in enumerate(x)], "id long, rep long, t array<double>")
    pairs = [((x[i] - x[j]) ** 2).sum() for i in range(6) for j in range(i)]
    assert abs(mean_pair_distance(table).first().mean_distance - np.sqrt(np.mean(pairs))) < 1e-9


def test_orderings_of_the_reference(spark):
    """On the given tables: the combined loss keeps texts and vectors together better than reconstruction, both better than the
    auto-configured baseline; compressing each side by itself loses the alignment; a latent of many dimensions beats a low one
    with more memory for the quantizer; contrastive alone is worse in retrieval."""
    from nearcopy.plans import workloads as W

    d = "/root/testdata/sf0.01"
    hits = {r.codec: r.hit for r in W.w_text_to_image(spark, d, ms=(4,), seeds=(0,)).collect()}
    assert hits["npcc"] > hits["mse"] > hits["auto"]
    sides = {r.codec: r.hit for r in W.w_alignment(spark, d).collect()}
    assert min(sides["npcc"], sides["contrastive"]) > 0.9 and sides["independent"] < 0.1
    arms = {(r.arm, r.latent): r.recall for r in W.w_latent_ablation(spark, d, dims=(16, 128)).where("codec = 'pca'").collect()}
    assert arms["same", 128] > arms["more", 16]
    x, pairs = W._vectors(spark, d)
    front = W._front(spark, x, pairs, (8,), (4,), 128, ("arrow", "expr")).collect()
    recall = {(r.codec, r.engine): r.recall for r in front}
    assert recall["contrastive", "arrow"] < min(recall["mse", "arrow"], recall["npcc", "arrow"])
    assert all(abs(recall[c, "arrow"] - recall[c, "expr"]) < 1e-9 for c, _ in recall)


def test_bucketed_tables_join_without_a_shuffle(spark, emb, tmp_path, monkeypatch):
    from nearcopy.sources.vectors import write_bucketed

    try:
        a = write_bucketed(emb.select("id", "x"), "nearcopy_a", "id", 8)
        b = write_bucketed(emb.selectExpr("id", "id % 3 AS label"), "nearcopy_b", "id", 8)
        joined = a.hint("merge").join(b, "id")
        plan = joined._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and "SortMergeJoin" in plan
        assert joined.count() == emb.count()
    finally:
        spark.sql("DROP TABLE IF EXISTS nearcopy_a")
        spark.sql("DROP TABLE IF EXISTS nearcopy_b")


def test_captions_as_text(spark, tmp_path):
    from nearcopy.sources.vectors import read_captions, write_captions

    write_captions(spark.createDataFrame([("one",), ("\u00fc two",)], "value string"), f"{tmp_path}/t", "text")
    assert rows(read_captions(spark, f"{tmp_path}/t", "value string", "text"), "value") == [("one",), ("\u00fc two",)]


def test_neighbours_of_a_training_are_looked_for_once(spark, data):
    """A stored table of the pairs that are trained on: rounds of training don't search again."""
    docs = spark.read.parquet(f"{data}/documents.parquet")
    pairs = FE.doc_vec(docs).join(FE.doc_cap(docs), "id")
    for sample in (1000, 60):
        rows = codecs.neighbour_rows(pairs, sample=sample)
        want = {r.id: r.nn_id for r in S.chunk_nearest(pairs, "x").collect()}
        assert "InArrow" not in rows._jdf.queryExecution().executedPlan().toString()
        vectors = {r.id: r.x for r in pairs.select("id", "x").collect()}
        got = {r.id: r.x_nn for r in rows.collect()}
        assert all(vectors[want[i]] == v for i, v in got.items())
        assert got.keys() == want.keys() if sample == 1000 else 20 < len(got) < 120

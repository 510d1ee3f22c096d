"""What showed at larger tables only: ties, exact results of the faster ways, and queries that read tables."""

import math
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from nearcopy.functions import features as FE
from nearcopy.functions.blocks import smallest_distances, summed_squares
from nearcopy.operators import index as I, search as S


def test_nearest_of_rows_that_rounding_tells_apart():
    """All distances are the same on paper; the sums in order of the dimensions, with one rounding a step, and their roots decide."""
    rng, d = np.random.default_rng(5), 256
    rows = np.zeros((80, d))
    for k, row in enumerate(rows):
        at = rng.choice(d // 2, rng.integers(3, 40), replace=False) + (k % 2) * (d // 2)
        row[at] = rng.choice([-1.0, 1.0, 2.0], len(at))
        row /= np.sqrt((row * row).sum())
    x, y = rows[::2], rows[1::2]

    def dist(a, b):
        total = 0.0
        for v, w in zip(a.tolist(), b.tolist(), strict=True):
            total = math.fma(v - w, v - w, total)
        return math.sqrt(total)

    want = [min(range(len(y)), key=lambda k: (dist(v, y[k]), k)) for v in x]
    assert smallest_distances(x, y, 1)[0][:, 0].tolist() == want
    far = x[:, None] - y[None]
    assert np.sqrt(summed_squares(far.reshape(-1, d))).tolist() == [dist(v, w) for v in x for w in y]


def read_columns(df):
    """The columns that Spark scans of files for a result."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return set(re.findall(r"(\w+)#\d+", " ".join(re.findall(r"Relation \[[^\]]*\] parquet", plan))))


def test_plans_fronts_and_ratios_read_vectors(spark, data):
    from nearcopy.registry import vectors as V

    for query in (V.q_auto_plan, V.q_compression_ratio):
        assert "embedding" in read_columns(query(spark, data))


def test_front_changes_with_the_vectors(spark, tmp_path):
    """Vectors with values in the last places only: codecs that keep the first ones aren't on the front."""
    from nearcopy.registry import vectors as V

    rows = [(i, [0.0] * 56 + [float(i + 1)] * 8) for i in range(20)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("label", F.lit("a"))
    table.write.parquet(f"{tmp_path}/embeddings.parquet")
    assert {r.name for r in V.q_pareto(spark, str(tmp_path)).collect()} == {"last-8", "first-4"}


def test_nearest_by_a_window_makes_no_pairs(spark, data):
    from nearcopy.registry import vectors as V

    assert "NestedLoop" not in V.q_topk_window(spark, data)._jdf.queryExecution().executedPlan().toString()


def test_arriving_copies_meet_each_code_once():
    """Of many rows with equal codes each has the largest smaller id that flags it, as the join of all pairs has."""
    import pyarrow as pa

    from nearcopy.operators.index import VectorIndex
    from nearcopy.streaming.dedup import last_flagging

    rng = np.random.default_rng(2)
    x = np.repeat(rng.standard_normal((150, 8)), 4, axis=0) + np.where(np.arange(600) % 3, 0, 1e-3)[:, None]
    x[:2] = 0
    index = VectorIndex(np.zeros((1, 8)), rng.standard_normal((2, 16, 4)))
    index.books[:, 0] = 0
    cell, codes, near = index.encode_block(x)
    own, ids = np.sqrt(((x - near) ** 2).sum(1)), rng.permutation(5000)[: len(x)]
    table = {"id": ids, "cell": cell, "codes": [c.tobytes() for c in codes], "z": list(x), "self_dist": own}
    table, want = pa.table(table), {}
    for j in range(len(x)):
        gap = np.abs(own - np.sqrt(((x - near[j]) ** 2).sum(1)))
        flag = np.where(own <= 1e-12, gap <= 1e-12, gap < own * 0.01) & (ids < ids[j])
        if flag.any():
            want[int(ids[j])] = int(ids[flag].max())
    got = last_flagging(index, table, table, 0.01)
    assert dict(zip(got[0].tolist(), got[1].tolist(), strict=True)) == want and len(want) > 300


@pytest.fixture
def many_tasks(spark):
    """Shuffles of as many tasks as they name, as large tables have them."""
    names = {"spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.shuffle.partitions": "13"}
    before = {n: spark.conf.get(n) for n in names}
    for n, v in names.items():
        spark.conf.set(n, v)
    yield
    for n, v in before.items():
        spark.conf.set(n, v)


def test_blocks_meet_in_many_tasks(spark, data, monkeypatch, many_tasks):
    x = FE.emb(spark.read.parquet(f"{data}/embeddings.parquet")).select("id", "x")
    asked = x.where("id % 3 = 0")
    want = sorted(map(tuple, S.knn_exact(asked, x, 5).select("qid", "nid", "rank").collect()))
    monkeypatch.setattr(S, "BLOCK_QUERIES", 10)
    monkeypatch.setattr(S, "BLOCK_BYTES", 64 * 8 * 40)
    got = S.knn_exact(asked, x, 5).select("qid", "nid", "rank")
    assert want and sorted(map(tuple, got.collect())) == want


def test_cells_meet_in_many_tasks(spark, data, monkeypatch, many_tasks):
    x = FE.emb(spark.read.parquet(f"{data}/embeddings.parquet")).select("id", "x")
    index = I.seeded_index(x)
    want = sorted(map(tuple, index.search(x, 5, 2).select("qid", "nid", "rank").collect()))
    monkeypatch.setattr(I, "BROADCAST_BYTES", 1)
    for salt in (1, 3):
        got = index.search(x, 5, 2, salt=salt).select("qid", "nid", "rank")
        assert want and sorted(map(tuple, got.collect())) == want


def made_rows(seed, n, d=12, few=3):
    """Ids out of order, exact copies, zeros, rows that rounding alone tells apart, and a few that are far longer."""
    rng = np.random.default_rng(seed)
    x = rng.integers(-few, few + 1, (n, d)).astype(float)
    x[n // 2 :] = x[rng.integers(0, n // 4, n - n // 2)] * rng.choice([1.0, 1.0, 3.0], n - n // 2)[:, None]
    x /= np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-9)
    x[:3], x[5:7] = 0.0, x[5:7] * 1e4
    return rng.permutation(10 * n)[:n].astype(np.int64), x


def by_distance(q, names, y, leave_out):
    d = np.sqrt(((q - y) ** 2).sum(1))
    order = [i for i in np.lexsort((names, np.round(d, 12))) if names[i] != leave_out]
    return names[order], d[order]


@pytest.mark.parametrize("include_self", [False, True])
def test_many_equal_rows_are_settled_by_id(include_self):
    ids, x = made_rows(1, 700)
    found = S._Nearest(ids[:90], x[:90], 4, "l2", include_self)
    for lo in range(0, 700, 130):
        found.meet(ids[lo : lo + 130], x[lo : lo + 130])
    got = {}
    for b in found.rows():
        for q, n, d in zip(*(c.to_pylist() for c in b.columns), strict=True):
            got.setdefault(q, []).append(n)
    want = {int(i): by_distance(v, ids, x, None if include_self else i)[0][:4].tolist() for i, v in zip(ids[:90], x[:90])}
    assert got == want


def test_partners_of_blocks_equal_brute_force():
    ids, x = made_rows(2, 400)
    want = np.arange(400) % 3 > 0
    got = S._nearest_others(ids, x, want).to_pydict()
    assert dict(zip(got["id"], got["nn_id"])) == {int(i): by_distance(v, ids, x, i)[0][0] for i, v in zip(ids[want], x[want])}
    a, b = np.arange(400) < 150, np.arange(400) >= 150
    got = S._nearest_others(ids[a], x[a], want[a], ids[b], x[b], want[b]).to_pydict()
    best = {int(i): by_distance(v, ids[o], x[o], i) for o, s in ((b, a), (a, b)) for i, v in zip(ids[s & want], x[s & want])}
    assert dict(zip(got["id"], got["nn_id"])) == {i: n[0] for i, (n, _) in best.items()}
    np.testing.assert_allclose(got["dist"], [best[i][1][0] for i in got["id"]], atol=1e-12)


def test_captions_take_the_head_of_a_text_apart():
    texts = [None, "", "a", "ΑΣ" * 40 + " ΒΣ ΓΣ'α δ", "Σ " * 90, "word-" * 5000, "x" * 900 + " İ ß_é " * 9, "one two " * 3 + "-" * 500 + "y z" * 9]
    for text in texts:
        for n in (1, 2, 5, 12, None):
            assert FE.leading_words(text, n) == FE.words(text)[:n]


@pytest.mark.parametrize("ball", [None, 0.5])
def test_codes_are_searched_by_one_product(ball, monkeypatch):
    """The same pairs and distances as sums over all table entries give, without working those out for all pairs."""
    rng = np.random.default_rng(4)
    index = I.VectorIndex(rng.standard_normal((2, 12)), rng.standard_normal((3, 8, 4)))
    codes, ids = rng.integers(0, 8, (900, 3)).astype(np.uint8), rng.permutation(5000)[:900]
    z, own = rng.standard_normal((50, 12)), rng.random(50) * 3 + 2
    qids, d = np.arange(50) + 7000, np.sqrt(I.lookup_distances(z - index.cells[1], index.books, codes))
    if ball is None:
        order = [np.lexsort((ids, np.round(row, 12)))[:5] for row in d]
    else:
        order = [np.flatnonzero(row <= 1.5 * s + 1e-12) for row, s in zip(d, own)]
    want = sorted((int(q), int(ids[i]), row[i]) for q, row, o in zip(qids, d, order) for i in o)
    monkeypatch.delattr(I, "lookup_distances")
    asked = (qids, z, None if ball is None else own)
    got = I._answers(index, asked, 1, ids, codes, I._keeper(5, "l2", ball), 5, ball)
    assert sorted(r for b in got for r in zip(*(c.to_pylist() for c in b.columns))) == want and len(want) > 100


def test_indexes_that_share_cells_equal_single_ones(spark, data):
    x = FE.emb(spark.read.parquet(f"{data}/embeddings.parquet")).select("id", "x")
    for m, index in I.build_indexes(x, "x", 4, (2, 8), 4, None, 2).items():
        one = I.build_index(x, "x", 4, m, 4, None, 2)
        assert (one.cells == index.cells).all() and (one.books == index.books).all()
        assert one.encoded.drop("z").exceptAll(index.encoded.drop("z")).count() == 0


def test_disturbed_copies_are_those_of_the_expressions(spark, data):
    from nearcopy.functions import linalg as L

    x = FE.emb(spark.read.parquet(f"{data}/embeddings.parquet")).where("id < 40")
    x = x.unionByName(spark.createDataFrame([(41, [0.0] * 64, 0)], "id long, x array<double>, label int").select(*[F.col(c).cast(x.schema[c].dataType) for c in x.columns]))
    many = x.withColumn("r", F.explode(F.sequence(F.lit(0), F.lit(2))))
    many = many.withColumn("id", F.col("id") + F.col("r") * 10_000_000)
    moved = L.normalise(L.add(F.col("x"), FE.small_noise(F.col("id"), "grow:", 0.02)))
    want = many.withColumn("x", F.when(F.col("r") == 0, F.col("x")).otherwise(moved))
    got = {r.id: r for r in FE.with_disturbed(x, 3, "grow:", 0.02).collect()}
    want = {r.id: r for r in want.collect()}
    assert got.keys() == want.keys() and len(got) == 3 * 41
    assert all(got[i].label == w.label for i, w in want.items())
    assert max(np.abs(np.subtract(got[i].x, w.x)).max() for i, w in want.items()) < 1e-15


def test_cells_of_all_codecs_by_the_same_passes(spark, data):
    from nearcopy.operators import codecs, kmeans as K

    x = FE.emb(spark.read.parquet(f"{data}/embeddings.parquet")).select("id", "x")
    tried = [codecs.IdentityCodec(), codecs.fit_pca_codec(x, "x", 16)]
    found = K.kmeans_of_all(x, "x", 8, 3, [c.encode_block for c in tried])
    rows = I.codebook_rows(x)
    for codec, cells in zip(tried, found, strict=True):
        want = I.build_index(x, "x", 8, 4, 4, codec, 3)
        got = I.build_indexes(x, "x", 8, (4,), 4, codec, 3, rows, cells)[4]
        assert np.allclose(got.cells, want.cells) and np.allclose(got.books, want.books)
        assert got.encoded.select("id", "cell").exceptAll(want.encoded.select("id", "cell")).count() == 0


def test_codecs_are_trained_on_all_rows(spark, monkeypatch):
    from nearcopy.operators import codecs

    seen = []
    monkeypatch.setattr(codecs, "train", lambda df, *a: seen.append(df.count()))
    x = spark.range(250_000).select("id", F.array(F.lit(1.0)).alias("x"))
    codecs._run(x, ["x"], {}, None, codecs._options({}))
    codecs._run(x, ["x"], {}, None, codecs._options({"sample": 1000}))
    assert seen[0] == 250_000 and 800 < seen[1] < 1200


def test_large_tasks_are_trained_on_in_parts(monkeypatch):
    import pyarrow as pa

    from nearcopy.operators import codecs

    monkeypatch.setattr(codecs, "HELD_ROWS", 50)
    batches = [pa.record_batch([pa.array([[float(i)] * 2 for i in range(n, n + 20)], pa.list_(pa.float64()))], names=["x"]) for n in range(0, 140, 20)]
    parts = [p[0] for p in codecs._held(batches, 1)]
    assert [len(p) for p in parts] == [60, 60, 20] and np.concatenate(parts)[:, 0].tolist() == list(range(140))


def test_all_rows_are_asked_for_neighbours(spark, monkeypatch):
    from nearcopy import components
    from nearcopy.operators import codecs

    monkeypatch.setattr(S, "chunk_nearest", lambda df, *a, asked=None: df.selectExpr("id", "id AS nn_id") if asked is None else asked.selectExpr("id", "id AS nn_id"))
    monkeypatch.setattr(components, "materialize", lambda df: df)
    pairs = spark.range(250_000).select("id", F.array(F.lit(1.0)).alias("x"), F.array(F.lit(1.0)).alias("t"))
    assert codecs.neighbour_rows(pairs).count() == 250_000

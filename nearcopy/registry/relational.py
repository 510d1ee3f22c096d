"""Queries on scans, predicates, joins, aggregates, windows and functions that surround the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from nearcopy.functions import linalg as L

QUERIES, ORACLES = {}, {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def query(sql: str):
    """Register a function under its name, with DuckDB SQL for the same rows."""

    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return put


GROUPS = "g AS (SELECT doc_id AS id, min(doc_id) OVER (PARTITION BY text) AS rep FROM documents)"


def text_groups(spark, d):
    """(id, rep) of exact text copies; the text stays out of the sort, its md5 is the key."""
    docs = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.md5("text").alias("h"))
    first = docs.groupBy("h").agg(F.min("id").alias("rep"))
    return docs.join(first, "h").select("id", "rep")


# ---- scans and projections --------------------------------------------------------------------


@query("SELECT vec_id, label, len(embedding) AS dim FROM embeddings WHERE label = 3")
def q_scan_embeddings(spark, d):
    return table(spark, d, "embeddings").where("label = 3").select("vec_id", "label", F.size("embedding").alias("dim"))


@query("SELECT vec_id, len(embedding) = 64 AND len(list_filter(embedding, lambda v: v IS NULL OR isnan(v))) = 0 AS valid FROM embeddings")
def q_validate_vectors(spark, d):
    from nearcopy.sources.vectors import validity

    return table(spark, d, "embeddings").select("vec_id", validity(F.col("embedding"), 64).alias("valid"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda v: v * v))), 6) AS norm FROM embeddings")
def q_project_norm(spark, d):
    return table(spark, d, "embeddings").select("vec_id", F.round(L.norm(F.col("embedding")), 6).alias("norm"))


@query("SELECT doc_id, lang, n_chars FROM documents WHERE lang = 'fr' AND n_chars BETWEEN 500 AND 3000")
def q_filter_lang(spark, d):
    return table(spark, d, "documents").where(
        (F.col("lang") == "fr") & F.col("n_chars").between(500, 3000)
    ).select("doc_id", "lang", "n_chars")


@query("SELECT p_partkey, p_name, p_size FROM part WHERE p_size IN (1, 5, 9, 20) AND p_type LIKE '%A%' AND p_retailprice BETWEEN 900 AND 1500")
def q_predicate_in_like_between(spark, d):
    return table(spark, d, "part").where(
        F.col("p_size").isin(1, 5, 9, 20) & F.col("p_type").like("%A%") & F.col("p_retailprice").between(900, 1500)
    ).select("p_partkey", "p_name", "p_size")


@query("SELECT d.doc_id, coalesce(l.quality, -1) AS quality, l.toxic IS NOT DISTINCT FROM NULL AS unlabelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def q_null_semantics(spark, d):
    docs, labels = table(spark, d, "documents").select("doc_id"), table(spark, d, "labels")
    return docs.join(labels, "doc_id", "left").select(
        "doc_id",
        F.coalesce("quality", F.lit(-1)).alias("quality"),
        F.col("toxic").eqNullSafe(F.lit(None).cast("int")).alias("unlabelled"),
    )


# ---- joins -----------------------------------------------------------------------------------


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def q_orders_lineitem(spark, d):
    o, li = table(
        spark, d, "orders"
    ).select("o_orderkey", "o_orderpriority"), table(spark, d, "lineitem").select("l_orderkey", "l_extendedprice")
    return o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(
        F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total")
    )


@query("SELECT a.doc_id AS i, b.doc_id AS j FROM documents a JOIN documents b ON a.lang = b.lang AND a.source = b.source AND a.n_chars = b.n_chars AND a.doc_id < b.doc_id")
def q_pairs_later(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "lang", "source", "n_chars")
    a, b = docs.alias("a"), docs.alias("b")
    same = [F.col(f"a.{c}") == F.col(f"b.{c}") for c in ("lang", "source", "n_chars")]
    return a.join(b, [*same, F.col("a.doc_id") < F.col("b.doc_id")]).select(
        F.col("a.doc_id").alias("i"), F.col("b.doc_id").alias("j")
    )


@query("SELECT a.doc_id AS i, b.doc_id AS j FROM documents a JOIN documents b ON a.source = b.source AND a.doc_id < b.doc_id AND abs(a.n_chars - b.n_chars) <= 20")
def q_length_band_pairs(spark, d):
    """A range join by bands: each row meets its own band and the next ones, then the exact condition decides."""
    band = 20
    docs = table(spark, d, "documents").select("doc_id", "source", "n_chars").withColumn(
        "band", F.floor(F.col("n_chars") / band)
    )
    a = docs.select(
        F.col("doc_id").alias("i"),
        "source",
        F.col("n_chars").alias("x"),
        F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"),
    )
    b = docs.select(F.col("doc_id").alias("j"), "source", F.col("n_chars").alias("y"), "band")
    return a.join(b, ["source", "band"]).where(
        (F.col("i") < F.col("j")) & (F.abs(F.col("x") - F.col("y")) <= band)
    ).select("i", "j")


@query("""
SELECT a.event_id, coalesce(b.event_id, -1) AS purchase_id FROM (SELECT event_id, user_id, ts FROM events WHERE event_type <> 'purchase') a
ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts""")
def q_asof_events(spark, d):
    """The last purchase of the user up to each other event: one sort by user and time, no join."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", (F.col("event_type") == "purchase").alias("p"))
    w = W.partitionBy("user_id").orderBy("ts", F.desc("p"), "event_id").rowsBetween(W.unboundedPreceding, 0)
    return e.withColumn(
        "purchase_id", F.last(F.when(F.col("p"), F.col("event_id")), True).over(w)
    ).where("NOT p").select("event_id", F.coalesce("purchase_id", F.lit(-1)).alias("purchase_id"))


@query(
    f"WITH {GROUPS} SELECT doc_id, lang FROM documents SEMI JOIN (SELECT id FROM g WHERE id = rep) k ON doc_id = k.id"
)
def q_dedup_kept(spark, d):
    kept = text_groups(spark, d).where("id = rep").select(F.col("id").alias("doc_id"))
    return table(spark, d, "documents").select("doc_id", "lang").join(kept, "doc_id", "left_semi")


@query(
    f"WITH {GROUPS} SELECT doc_id, lang FROM documents ANTI JOIN (SELECT id FROM g WHERE id = rep) k ON doc_id = k.id"
)
def q_dedup_dropped(spark, d):
    kept = text_groups(spark, d).where("id = rep").select(F.col("id").alias("doc_id"))
    return table(spark, d, "documents").select("doc_id", "lang").join(kept, "doc_id", "left_anti")


@query("SELECT md5(text) AS hash, count(*) AS n, min(doc_id) AS first_id FROM documents GROUP BY 1 HAVING count(*) > 1")
def q_exact_text_groups(spark, d):
    return table(spark, d, "documents").select("doc_id", F.md5("text").alias("hash")).groupBy("hash").agg(
        F.count("*").alias("n"), F.min("doc_id").alias("first_id")
    ).where("n > 1")


# ---- aggregates ----------------------------------------------------------------------------


@query("SELECT label, i - 1 AS i, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS mean FROM embeddings, range(1, 65) t(i) GROUP BY label, i")
def q_vector_mean(spark, d):
    return table(spark, d, "embeddings").select(
        "label", F.posexplode(L.doubles(F.col("embedding"))).alias("i", "v")
    ).groupBy("label", F.col("i").cast("long").alias("i")).agg(F.round(F.avg("v"), 6).alias("mean"))


@query(f"WITH {GROUPS} SELECT rep, string_agg(CAST(id AS VARCHAR), ',' ORDER BY id) AS members, count(*) AS n FROM g GROUP BY rep HAVING count(*) > 1")
def q_representative_sets(spark, d):
    from nearcopy.operators.dedup import representative_sets

    return representative_sets(text_groups(spark, d)).where("n > 1").withColumn(
        "members", F.array_join(F.col("members").cast("array<string>"), ",")
    )


@query(f"WITH {GROUPS} SELECT group_size, count(*) AS n_groups, CAST(sum(group_size) AS BIGINT) AS n_items FROM (SELECT rep, count(*) AS group_size FROM g GROUP BY rep) GROUP BY group_size")
def q_dup_histogram(spark, d):
    from nearcopy.operators.dedup import duplication_histogram

    return duplication_histogram(text_groups(spark, d))


@query("SELECT count(DISTINCT l_partkey) AS exact, true AS close FROM lineitem")
def q_approx_distinct(spark, d):
    """The exact count, and whether a sketch's is within a tenth of it (its value isn't SQL's)."""
    counts = F.approx_count_distinct("l_partkey", 0.02).alias("sketch"), F.countDistinct("l_partkey").alias("exact")
    close = (F.abs(F.col("sketch") - F.col("exact")) <= 0.1 * F.col("exact")).alias("close")
    return table(spark, d, "lineitem").agg(*counts).select("exact", close)


_DUPS = f"WITH {GROUPS}, r AS (SELECT lang, source, CAST(id <> rep AS INT) AS dup FROM g JOIN documents ON id = doc_id)"


def _dups(spark, d):
    return text_groups(spark, d).join(
        table(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang", "source"), "id"
    ).withColumn("dup", (F.col("id") != F.col("rep")).cast("int"))


@query(
    f"{_DUPS} SELECT lang, source, count(*) AS n, CAST(sum(dup) AS BIGINT) AS dups FROM r GROUP BY CUBE (lang, source)"
)
def q_dups_by_lang_source_cube(spark, d):
    return _dups(spark, d).cube("lang", "source").agg(F.count("*").alias("n"), F.sum("dup").alias("dups"))


@query(f"{_DUPS} SELECT lang, source, count(*) AS n, CAST(sum(dup) AS BIGINT) AS dups FROM r GROUP BY ROLLUP (lang, source)")
def q_dups_by_lang_source_rollup(spark, d):
    return _dups(spark, d).rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("dup").alias("dups"))


@query(f"{_DUPS} SELECT lang, source, grouping_id(lang, source) AS level, count(*) AS n, CAST(sum(dup) AS BIGINT) AS dups FROM r GROUP BY GROUPING SETS ((lang), (source), ())")
def q_dups_by_lang_source_sets(spark, d):
    return _dups(spark, d).groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(
        F.grouping_id("lang", "source").alias("level"), F.count("*").alias("n"), F.sum("dup").alias("dups")
    )


@query(f"""WITH {GROUPS}, s AS (SELECT rep, count(*) AS n FROM g GROUP BY rep), v AS (SELECT rep, count(DISTINCT md5(substr(text, 1, 20) || source)) AS c FROM g JOIN documents ON id = doc_id GROUP BY rep)
SELECT round(corr(n, c), 6) AS r, count(*) AS n_groups FROM s JOIN v USING (rep)""")
def q_size_vs_diversity(spark, d):
    caption = F.md5(F.concat(F.substring("text", 1, 20), "source"))
    v = text_groups(spark, d).join(
        table(spark, d, "documents").select(F.col("doc_id").alias("id"), caption.alias("c")), "id"
    ).groupBy("rep").agg(F.count("*").alias("n"), F.countDistinct("c").alias("c"))
    return v.agg(F.round(F.corr("n", "c"), 6).alias("r"), F.count("*").alias("n_groups"))


@query("SELECT source, count(*) AS n, round(avg(n_chars), 4) AS mean_chars FROM documents GROUP BY source HAVING count(*) > 40")
def q_having_hot_groups(spark, d):
    return table(spark, d, "documents").groupBy("source").agg(
        F.count("*").alias("n"), F.round(F.avg("n_chars"), 4).alias("mean_chars")
    ).where("n > 40")


# ---- windows, sorts, set operations ---------------------------------------------------------


@query(f"""WITH {GROUPS}, s AS (SELECT rep, count(*) AS n FROM g GROUP BY rep HAVING count(*) > 1)
SELECT rep, n, rank() OVER (ORDER BY n DESC) AS rnk, dense_rank() OVER (ORDER BY n DESC) AS dense, ntile(4) OVER (ORDER BY n DESC, rep) AS quarter, round(percent_rank() OVER (ORDER BY n DESC), 6) AS pct FROM s""")
def q_group_rank(spark, d):
    """Ranks over the groups of two or more. Rank, dense rank and percent rank follow from the sizes' counts, which are few; places
    within one size are counted apart, so no window holds all groups."""
    s = text_groups(spark, d).groupBy("rep").agg(F.count("*").alias("n")).where("n > 1")
    sizes, down = s.groupBy("n").agg(F.count("*").alias("c")), W.orderBy(F.desc("n"))
    above = F.coalesce(F.sum("c").over(down.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    total = F.sum("c").over(W.orderBy(F.desc("n")).rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    sizes = sizes.select("n", above.alias("above"), F.row_number().over(down).alias("dense"), total.alias("total"))
    placed = s.withColumn("inner", F.row_number().over(W.partitionBy("n").orderBy("rep"))).join(sizes, "n")
    row, least, more = F.col("above") + F.col("inner"), F.floor(F.col("total") / 4), F.pmod("total", F.lit(4))
    late = F.when(least > 0, more + F.ceil((row - more * (least + 1)) / least))
    quarter = F.when(row <= more * (least + 1), F.ceil(row / (least + 1))).otherwise(late)
    pct = F.when(F.col("total") > 1, F.col("above") / (F.col("total") - 1)).otherwise(0.0)
    return placed.select(
        "rep", "n", (F.col("above") + 1).alias(
            "rnk"
        ), F.col("dense").cast("long").alias("dense"), quarter.alias("quarter"), F.round(pct, 6).alias("pct")
    )


@query("""SELECT event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER w), -1) AS since, coalesce(epoch_us(lead(ts) OVER w) - epoch_us(ts), -1) AS until,
first_value(event_id) OVER w AS first_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def q_event_gaps(spark, d):
    e = table(spark, d, "events").select(
        "event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us")
    )
    w = W.partitionBy("user_id").orderBy("us", "event_id")
    return e.select(
        "event_id",
        F.coalesce(F.col("us") - F.lag("us").over(w), F.lit(-1)).alias("since"),
        F.coalesce(F.lead("us").over(w) - F.col("us"), F.lit(-1)).alias("until"),
        F.first("event_id").over(w).alias("first_id"),
    )


@query(f"""WITH {GROUPS}, h AS (SELECT n AS group_size, CAST(sum(n) AS BIGINT) AS items FROM (SELECT count(*) AS n FROM g GROUP BY rep) GROUP BY n)
SELECT group_size, items, round(sum(items) OVER (ORDER BY group_size DESC) / sum(items) OVER (), 6) AS share FROM h""")
def q_tail_share(spark, d):
    """Running share of items over group sizes, of which there are few."""
    from nearcopy.operators.dedup import duplication_histogram

    h = duplication_histogram(text_groups(spark, d)).select("group_size", F.col("n_items").alias("items"))
    run = W.orderBy(F.desc("group_size")).rowsBetween(W.unboundedPreceding, 0)
    return h.select(
        "group_size",
        "items",
        F.round(
            F.sum("items").over(run) / F.sum("items").over(
                W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
            ),
            6,
        ).alias("share"),
    )


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def q_events_range_frame(spark, d):
    e = table(spark, d, "events").select(
        "event_id", "user_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s")
    )
    return e.select(
        "event_id", F.count("*").over(W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n")
    )


@query("SELECT conv_id, turn, role, row_number() OVER w AS k, coalesce(lag(role) OVER w, '') AS before FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text)")
def q_conversation_order(spark, d):
    w = W.partitionBy("conv_id").orderBy("turn", "role", "text")
    return table(spark, d, "conversations").select(
        "conv_id",
        "turn",
        "role",
        F.row_number().over(w).alias("k"),
        F.coalesce(F.lag("role").over(w), F.lit("")).alias("before"),
    )


@query(f"WITH {GROUPS} SELECT rep, count(*) AS n FROM g GROUP BY rep ORDER BY n DESC, rep LIMIT 100")
def q_top_duplicated(spark, d):
    from nearcopy.operators.dedup import top_duplicated

    return top_duplicated(text_groups(spark, d), 100)


@query("SELECT o_orderkey, o_totalprice FROM orders")
def q_sort_global(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 100")
def q_offset(spark, d):
    return table(
        spark, d, "orders"
    ).select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(100).limit(50)


@query("SELECT DISTINCT text FROM documents WHERE n_chars < 600")
def q_distinct_rows(spark, d):
    return table(spark, d, "documents").where("n_chars < 600").select("text").distinct()


# ---- functions -----------------------------------------------------------------------------

_PAIRS = "SELECT a.vec_id AS id, CAST(a.embedding AS DOUBLE[]) AS x, CAST(b.embedding AS DOUBLE[]) AS y FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"


def _neighbours(spark, d):
    e = table(spark, d, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.col("embedding").alias("x")).join(
        e.select((F.col("vec_id") - 1).alias("id"), F.col("embedding").alias("y")), "id"
    )


@query(f"SELECT id, round(list_distance(x, y), 6) AS l2, round(list_distance(x, y) ** 2, 6) AS sq, round(list_inner_product(x, y), 6) AS dot, round(list_cosine_similarity(x, y), 6) AS cos FROM ({_PAIRS})")
def q_vector_distances(spark, d):
    x, y = F.col("x"), F.col("y")
    return _neighbours(spark, d).select(
        "id",
        F.round(L.l2(x, y), 6).alias("l2"),
        F.round(L.squared_l2(x, y), 6).alias("sq"),
        F.round(L.dot(x, y), 6).alias("dot"),
        F.round(L.cosine(x, y), 6).alias("cos"),
    )


@query(f"SELECT id, i - 1 AS i, round(x[i] + y[i], 6) AS plus, round(x[i] - y[i], 6) AS minus, round(x[i] * 2.5, 6) AS scaled FROM ({_PAIRS}), range(1, 65) t(i)")
def q_vector_arith(spark, d):
    x, y = F.col("x"), F.col("y")
    rows = _neighbours(spark, d).select(
        "id",
        F.posexplode(
            F.arrays_zip(L.add(x, y).alias("p"), L.subtract(x, y).alias("m"), L.scale(x, 2.5).alias("s"))
        ).alias("i", "v"),
    )
    return rows.select(
        "id",
        F.col("i").cast("long").alias("i"),
        F.round("v.p", 6).alias("plus"),
        F.round("v.m", 6).alias("minus"),
        F.round("v.s", 6).alias("scaled"),
    )


@query("SELECT vec_id, len(embedding[1:16]) AS size, embedding[17:32][1] AS second_start, true AS same FROM embeddings")
def q_vector_blocks(spark, d):
    e = table(spark, d, "embeddings").select(
        "vec_id", "embedding", L.split_blocks(F.col("embedding"), 4, 16).alias("b")
    )
    return e.select(
        "vec_id",
        F.size(F.col("b")[0]).alias("size"),
        F.col("b")[1][0].alias("second_start"),
        (F.flatten("b") == F.col("embedding")).alias("same"),
    )


@query("""SELECT vec_id, list_sort(embedding)[1] AS least, len(list_intersect(list_transform(embedding, lambda v: CAST(floor(v * 10) AS INT)), [-1, 0, 1])) AS common,
list_position(embedding, list_max(embedding)) - 1 AS at_most FROM embeddings""")
def q_array_functions(spark, d):
    e = F.col("embedding")
    return table(spark, d, "embeddings").select(
        "vec_id",
        F.array_sort(e)[0].alias("least"),
        F.size(F.array_intersect(F.transform(e, lambda v: F.floor(v * F.lit(10).cast("float")).cast("int")), F.array(F.lit(-1), F.lit(0), F.lit(1)))).alias("common"),
        (F.array_position(e, F.array_max(e)) - 1).alias("at_most"),
    )


@query("SELECT event_id, CASE event_type WHEN 'purchase' THEN 3 WHEN 'click' THEN 2 WHEN 'view' THEN 1 ELSE 0 END AS weight FROM events")
def q_map_config(spark, d):
    weights = F.map_from_arrays(F.array(*map(F.lit, ["view", "click", "purchase"])), F.array(*map(F.lit, [1, 2, 3])))
    return table(spark, d, "events").select(
        "event_id", F.coalesce(F.try_element_at(weights, "event_type"), F.lit(0)).alias("weight")
    )


@query("""SELECT doc_id, len(list_filter(string_split(trim(regexp_replace(lower(text), '[^\\p{L}\\p{N}]+', ' ', 'g')), ' '), lambda w: w <> '')) AS n_words FROM documents""")
def q_text_normalize(spark, d):
    plain = F.trim(F.regexp_replace(F.lower("text"), r"[^\p{L}\p{N}]+", " "))
    return table(spark, d, "documents").select(
        "doc_id", F.size(F.filter(F.split(plain, " "), lambda w: w != "")).alias("n_words")
    )


@query("""WITH t AS (SELECT doc_id, string_split(lower(text), ' ') AS w FROM documents), s AS (
SELECT doc_id, list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' '))) AS g
FROM t WHERE len(w) >= 5)
SELECT a.doc_id AS i, b.doc_id AS j,
round(len(list_intersect(a.g, b.g)) / (len(a.g) + len(b.g) - len(list_intersect(a.g, b.g))), 6) AS jaccard
FROM s a JOIN s b ON b.doc_id = a.doc_id + 1""")
def q_shingle_jaccard(spark, d):
    """Sets of five-word shingles of each document and of the one with the next id: all documents, whole texts."""
    t = table(spark, d, "documents").select("doc_id", F.split(F.lower("text"), " ").alias("w")).where("size(w) >= 5")
    n = F.size("w") - 4
    joined = F.slice("w", 1, n)
    for k in range(1, 5):
        joined = F.zip_with(joined, F.slice("w", k + 1, n), lambda a, b: F.concat(a, F.lit(" "), b))
    s = t.select("doc_id", F.array_distinct(joined).alias("g"))
    a, b = s.select(F.col("doc_id").alias("i"), F.col("g").alias("x")), s.select(
        F.col("doc_id").alias("j"), F.col("g").alias("y")
    )
    both = F.size(F.array_intersect("x", "y"))
    jaccard = F.round(both / (F.size("x") + F.size("y") - both), 6).alias("jaccard")
    return a.join(b, F.col("j") == F.col("i") + 1).select("i", "j", jaccard)


@query("SELECT p_partkey, levenshtein(p_name, p_type) AS distance FROM part")
def q_edit_distance(spark, d):
    return table(spark, d, "part").select("p_partkey", F.levenshtein("p_name", "p_type").cast("long").alias("distance"))


@query("SELECT md5(text) AS h, count(*) AS n FROM documents GROUP BY 1")
def q_hash_md5(spark, d):
    return table(spark, d, "documents").groupBy(F.md5("text").alias("h")).agg(F.count("*").alias("n"))


@query("SELECT event_id, json_extract_string(props, '$.' || json_keys(props)[1]) AS value FROM events WHERE props IS NOT NULL AND len(json_keys(props)) > 0")
def q_json_props(spark, d):
    e = table(spark, d, "events").select(
        "event_id", "props", F.json_object_keys("props").alias("k")
    ).where("size(k) > 0")
    return e.select("event_id", F.expr("get_json_object(props, concat('$.', k[0]))").alias("value"))


@query("SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS text_length FROM pages")
def q_page_text(spark, d):
    return table(spark, d, "pages").select(
        "page_id",
        F.parse_url("url", F.lit("HOST")).alias("host"),
        F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("text_length"),
    )


@query("SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, date_diff('day', o_orderdate, TIMESTAMP '2000-01-01') AS days FROM orders")
def q_date_parts(spark, d):
    return table(spark, d, "orders").select(
        "o_orderkey",
        F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"),
        F.datediff(F.lit("2000-01-01").cast("date"), F.to_date("o_orderdate")).cast("long").alias("days"),
    )


# ---- event-time windows on the batch table --------------------------------------------------


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS w, event_type, count(*) AS n FROM events GROUP BY ALL")
def q_tumbling(spark, d):
    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(
        F.col("w.start").cast("timestamp_ntz").alias("w"), "event_type", "n"
    )


@query("SELECT w, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE * k AS w FROM events, range(0, 2) t(k)) GROUP BY w")
def q_sliding(spark, d):
    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select(
        F.col("w.start").cast("timestamp_ntz").alias("w"), "n"
    )


@query("""WITH s AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 2 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
k AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM s)
SELECT user_id, min(ts) AS w, count(*) AS n FROM k GROUP BY user_id, k""")
def q_session(spark, d):
    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count("*").alias("n")).select(
        "user_id", F.col("w.start").cast("timestamp_ntz").alias("w"), "n"
    )

"""Streams, SQL functions, the index store and the workloads as queries. Where rows depend on training, tests check them
instead of SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from nearcopy.components import materialize, shared_dir
from nearcopy.functions import features as FE
from nearcopy.operators import index as I
from nearcopy.plans.workloads import WORKLOADS
from nearcopy.registry.relational import table
from nearcopy.registry.vectors import EMB, SEEDED, TENTH, adc, emb, ranked, seeded_index, tenth

QUERIES, ORACLES = dict(WORKLOADS), {}


def query(sql: str = ""):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return put


def arrivals(spark, d):
    """(event_id, ts, user_id, event_type, id, x): event e brings vector e modulo their number."""
    e = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    x = emb(spark, d).select("id", "x")
    n = x.count()
    return e.withColumn("id", F.pmod("event_id", F.lit(n))).join(x, "id")


def stream_of(spark, d, files: int = 4):
    """The arrivals as a stream of a few files in order of event id."""
    rows = arrivals(spark, d).repartitionByRange(files, "event_id").sortWithinPartitions("event_id")
    path = shared_dir(spark)
    rows.write.parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def run(stream, spark, each, mode="append"):
    """Run a stream over what is there; each(batch, id) for every micro-batch."""
    q = stream.writeStream.outputMode(
        mode
    ).option("checkpointLocation", shared_dir(spark)).trigger(availableNow=True).foreachBatch(each).start()
    q.awaitTermination()


def collected(stream, spark, mode="append"):
    """All micro-batches' rows with the batch's number, as a table in the shared folder."""
    path = shared_dir(spark)
    run(
        stream,
        spark,
        lambda b,
        k: b.withColumn("batch", F.lit(k)).write.mode("overwrite").parquet(f"{path}/k={k}"),
        mode,
    )
    return spark.read.schema(
        StructType([*stream.schema.fields, StructField("batch", IntegerType())])
    ).option("recursiveFileLookup", True).parquet(path)


@query()
def stream_dedup(spark, d, sources=32):
    from nearcopy.streaming.dedup import IncrementalDedup

    x = FE.emb_planted(table(spark, d, "embeddings"), sources).select("id", "x")
    index = I.seeded_index(x)
    index.encoded = None
    path = shared_dir(spark)
    x.repartitionByRange(4, "id").sortWithinPartitions("id").write.parquet(path)
    sink = IncrementalDedup(index, 0.01, spark=spark)
    run(spark.readStream.schema(x.schema).option("maxFilesPerTrigger", 1).parquet(path), spark, sink)
    return sink.representatives(spark)


#: The registered query plants copies of the fixture's 256 sources.
QUERIES["stream_dedup"] = lambda spark, d: stream_dedup(spark, d, 256)


#: Arrivals of each vector.
ARRIVED = "(SELECT event_id % (SELECT count(*) FROM embeddings) AS id, count(*) AS c FROM events GROUP BY 1)"


@query(f"{SEEDED} SELECT cell, count(DISTINCT codes) AS n FROM enc JOIN {ARRIVED} USING (id) GROUP BY cell")
def stream_code_dedup(spark, d):
    """First arrivals of codes, counted by cell (which of several arrivals of a batch is first is open)."""
    from nearcopy.streaming.dedup import code_dedup

    first = collected(code_dedup(stream_of(spark, d), seeded_index(spark, d), "365 days"), spark)
    return first.groupBy(F.col("cell").cast("long").alias("cell")).agg(F.count("*").alias("n"))


@query(f"{SEEDED} SELECT min(id) AS rep, CAST(sum(c) AS BIGINT) AS n FROM enc JOIN {ARRIVED} USING (id) GROUP BY cell, codes")
def stream_rep_state(spark, d):
    """Of each code the smallest id that has arrived, and the number of arrivals."""
    from nearcopy.streaming.dedup import rep_state

    got = collected(rep_state(stream_of(spark, d), seeded_index(spark, d)), spark, "update")
    return got.groupBy("code").agg(F.min("rep").alias("rep"), F.max("n").alias("n")).select("rep", "n")


def last_state(stream, spark):
    """The whole result after the last micro-batch."""
    rows = collected(stream, spark, "complete")
    return rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0]).drop("batch")


@query("""SELECT time_bucket(INTERVAL 1 HOUR, ts) AS w, event_type, count(*) AS n FROM events GROUP BY 1, 2""")
def stream_windows(spark, d):
    """Counts by hour of event time, after all arrivals."""
    from nearcopy.streaming.dedup import windowed_counts

    return last_state(windowed_counts(stream_of(spark, d)), spark).withColumn("w", F.col("w").cast("timestamp_ntz"))


@query("""WITH g AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events),
s AS (SELECT user_id, ts, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 2 HOUR THEN 1 ELSE 0 END)
OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
SELECT user_id, min(ts) AS w, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_sessions(spark, d):
    """Sessions of each user, after all arrivals."""
    from nearcopy.streaming.dedup import session_counts

    return last_state(
        session_counts(stream_of(spark, d), delay="365 days"), spark
    ).withColumn("w", F.col("w").cast("timestamp_ntz"))


@query("""SELECT a.event_id AS click_id, b.event_id, a.ts AS clicked, b.ts AS bought FROM events a JOIN events b ON a.user_id = b.user_id
WHERE a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR""")
def stream_purchases(spark, d):
    """Purchases within an hour of a click by the same user, as both arrive."""
    from nearcopy.streaming.dedup import purchases_after_clicks

    clicks, purchases = (stream_of(spark, d).where(F.col("event_type") == k) for k in ("click", "purchase"))
    found = collected(purchases_after_clicks(clicks, purchases, delay="365 days"), spark).drop("batch")
    return found.withColumns({n: F.col(n).cast("timestamp_ntz") for n in ("clicked", "bought")})


@query("""SELECT event_id, event_id % (SELECT count(*) FROM embeddings) AS id, label FROM events
LEFT JOIN embeddings ON vec_id = event_id % (SELECT count(*) FROM embeddings)""")
def stream_labels(spark, d):
    """Arrivals with the label of their vector, from a table that doesn't change."""
    from nearcopy.streaming.dedup import with_labels

    return collected(
        with_labels(stream_of(spark, d).select("event_id", "id"), emb(spark, d)), spark
    ).select("event_id", "id", "label")


@query(f"{SEEDED} SELECT qid, nid, round(dist, 6) AS dist FROM ({adc(1, TENTH)})")
def q_sql_adc(spark, d):
    from nearcopy.functions.sqlapi import register

    index = seeded_index(spark, d)
    register(spark, index)
    index.encoded.createOrReplaceTempView("nearcopy_lists")
    tenth(spark, d).createOrReplaceTempView("nearcopy_asked")
    return spark.sql("""
        WITH q AS (SELECT id AS qid, x, encode_vec(x).cell AS cell FROM nearcopy_asked)
        SELECT qid, l.id AS nid, round(adc(q.x, l.cell, l.codes), 6) AS dist FROM q JOIN nearcopy_lists l ON l.cell = q.cell""")


@query(f"{SEEDED} SELECT id, cell, round(dist, 6) AS dist FROM (SELECT q.id, cen.cell, list_distance(q.x, cen.c) AS dist, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.x, cen.c), cen.cell) AS pr FROM src q, cen WHERE {TENTH}) WHERE pr <= 2")
def q_udtf_probe(spark, d):
    from nearcopy.functions.sqlapi import register

    register(spark, seeded_index(spark, d))
    tenth(spark, d).createOrReplaceTempView("nearcopy_asked")
    return spark.sql(
        "SELECT id, CAST(p.cell AS BIGINT) AS cell, round(p.dist, 6) AS dist FROM nearcopy_asked, LATERAL probe(x, 2) p"
    )


@query("SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS first, round(avg(CAST(embedding[64] AS DOUBLE)), 6) AS last FROM embeddings GROUP BY label")
def q_udaf_vec_mean(spark, d):
    from nearcopy.functions.sqlapi import register

    register(spark, seeded_index(spark, d))
    emb(spark, d).createOrReplaceTempView("nearcopy_vectors")
    return spark.sql("SELECT label, round(m[0], 6) AS first, round(m[63], 6) AS last FROM (SELECT label, vec_mean(x) AS m FROM nearcopy_vectors GROUP BY label)")


@query(f"{SEEDED} SELECT qid, nid, rank FROM {ranked(adc(2, TENTH), 10)}")
def q_index_roundtrip(spark, d):
    """Save, load and search."""
    path = shared_dir(spark)
    seeded_index(spark, d).save(path, spark)
    return I.VectorIndex.load(path, spark).search(tenth(spark, d), 10, 2).select("qid", "nid", "rank")


@query(f"WITH {EMB} SELECT id FROM src WHERE id % 10 = 0")
def q_arrival_ids(spark, d):
    """Vectors that arrive, once each, of those with ids divisible by ten."""
    return materialize(arrivals(spark, d).select("id").distinct()).where("id % 10 = 0")

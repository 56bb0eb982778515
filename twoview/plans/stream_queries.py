"""Registered stream queries: each replays a table as a stream and must give what the batch form gives."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.operators import quantize as Q
from twoview.operators import search as S
from twoview.plans import sqlkit as K
from twoview.plans.registry import query
from twoview.plans.vector_queries import _ENC, COMMON, TAU, _first, _round
from twoview.sources import vectors as src
from twoview.streaming import streams as T


@query("stream_ingest", K.with_(*COMMON, K.nearest(64, 16), K.words(4)) + "SELECT vec_id, w AS w0 FROM wrd")
def stream_ingest(spark: SparkSession, d: str) -> DataFrame:
    _, model = _first(spark, d)
    return T.run_append(T.ingest(T.table_stream(spark, d, "embeddings"), model))


@query("stream_topk", K.with_(*_ENC, K.words(4), K.adc_pairs(64, 16), f"kept AS (SELECT adc.* FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id WHERE {K.ham('a.w', 'b.w')} <= {TAU})") + K.top("kept", 10))
def stream_topk(spark: SparkSession, d: str) -> DataFrame:
    """Standing queries over arriving base vectors, their ten best kept up."""
    s, model = _first(spark, d)
    prepared = S.prepare_queries(s.query, model)
    arriving = T.table_stream(spark, d, "embeddings").where("vec_id % 10 >= 4")
    return _round(T.running_topk(T.standing_queries(Q.encode(arriving, model), prepared, model, TAU), 10))


@query("stream_windows", "SELECT user_id, date_trunc('day', ts) AS day, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_windows(spark: SparkSession, d: str) -> DataFrame:
    e = T.table_stream(spark, d, "events").withWatermark("ts", "1 hour")
    g = e.groupBy(F.window("ts", "1 day"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return T.run_complete(g).select("user_id", F.col("window.start").cast("timestamp_ntz").alias("day"), "n", F.round("total", 4).alias("total"))


@query(
    "stream_sliding",
    "SELECT user_id, s AS start, count(*) AS n FROM (SELECT user_id, ts, unnest(range(0, 7)) AS k FROM events) e, LATERAL (SELECT date_trunc('day', ts) - to_days(k::INTEGER) AS s) GROUP BY 1, 2",
)
def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    e = T.table_stream(spark, d, "events").withWatermark("ts", "1 hour")
    g = e.groupBy(F.window("ts", "7 days", "1 day"), "user_id").agg(F.count("*").alias("n"))
    return T.run_complete(g).select("user_id", F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query(
    "stream_sessions",
    """WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w >= INTERVAL 1 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM o)
    SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 1 HOUR AS finish, count(*) AS n_events FROM s GROUP BY user_id, k""",
)
def stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    out = T.run_complete(T.sessions(T.table_stream(spark, d, "events")))
    return out.select("user_id", *[F.col(c).cast("timestamp_ntz").alias(c) for c in ("start", "finish")], "n_events")


@query(
    "stream_user_vectors",
    """WITH k AS (SELECT DISTINCT event_type FROM events), u AS (SELECT user_id, date_trunc('day', ts) AS start, count(*) AS n, avg(value) / 100 AS mean, coalesce(stddev_pop(value), 0) / 100 AS dev,
    count(*) FILTER (WHERE dayofweek(ts) BETWEEN 1 AND 5) / count(*) AS week FROM events GROUP BY 1, 2),
    e AS (SELECT user_id, date_trunc('day', ts) AS start, event_type, count(*) AS c FROM events GROUP BY 1, 2, 3),
    s AS (SELECT user_id, start, event_type, coalesce(c, 0) / n AS x FROM u CROSS JOIN k LEFT JOIN e USING (user_id, start, event_type))
    SELECT user_id AS vec_id, start, (row_number() OVER (PARTITION BY user_id, start ORDER BY event_type) - 1)::INTEGER AS k, round(x, 6) AS x FROM s
    UNION ALL SELECT user_id, start, ((SELECT count(*) FROM k) + z)::INTEGER, round([mean, dev, week][z + 1], 6) FROM u, range(3) t(z)""",
)
def stream_user_vectors(spark: SparkSession, d: str) -> DataFrame:
    """Daily user vectors, every component."""
    v = T.run_complete(T.windowed_users(T.table_stream(spark, d, "events"), src.event_types(spark.read.parquet(f"{d}/events.parquet"))))
    return v.select("vec_id", F.col("start").cast("timestamp_ntz").alias("start"), F.posexplode("embedding").alias("k", "x")).select("vec_id", "start", F.col("k").cast("int").alias("k"), F.round("x", 6).alias("x"))


@query("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Events twice each, told apart by id within the watermark."""
    e = T.table_stream(spark, d, "events")
    return T.run_append(T.deduplicated(e.unionAll(e)).select("event_id")).agg(F.count("*").alias("n"))


@query("stream_interval_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark: SparkSession, d: str) -> DataFrame:
    e = T.table_stream(spark, d, "events")
    return T.run_append(T.pairs_within(e, T.table_stream(spark, d, "events")))


@query(
    "stream_drift",
    K.with_(*COMMON, K.nearest(64, 16), "er AS (SELECT vec_id, sum(d2) AS err FROM enc GROUP BY vec_id)", "tr AS (SELECT avg(err) AS e FROM er WHERE vec_id % 10 BETWEEN 1 AND 3)")
    + "SELECT date_trunc('day', TIMESTAMP '1970-01-01' + to_hours(vec_id)) AS start, round(avg(err), 6) AS mean_error, count(*) AS n, avg(err) > 2 * (SELECT e FROM tr) AS alert FROM er GROUP BY 1",
)
def stream_drift(spark: SparkSession, d: str) -> DataFrame:
    """Quantization error of arriving vectors by day, where ids are hours, against training's."""
    s, model = _first(spark, d)
    trained = Q.reconstruction_error(s.train, model).agg(F.sum("mse").alias("e")).first().e
    v = T.table_stream(spark, d, "embeddings").select("vec_id", "embedding", F.timestamp_seconds(F.col("vec_id") * 3600).alias("ts"))
    got = T.run_complete(T.drift(v.withWatermark("ts", "1 hour"), model, "ts", trained_error=trained))
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), F.round("mean_error", 6).alias("mean_error"), "n", "alert")


@query("stream_late", "WITH o AS (SELECT count(*) AS n FROM events) SELECT n AS in_time, n AS late_dropped FROM o")
def stream_late(spark: SparkSession, d: str) -> DataFrame:
    """All events, then, once the watermark has passed, all of them again under other ids: none of the late ones counts."""
    return T.late_counts(spark, spark.read.parquet(f"{d}/events.parquet").select("event_id", "ts"))

"""Streams: ingest and encode, standing queries, windowed vectors, late data, joins, drift.

Each function takes and gives streaming DataFrames, or starts a query with the available data (trigger
availableNow) and a checkpoint, so that a stream can be replayed and held against its batch form.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.functions import expressions as E
from twoview.operators.model import CodeModel
from twoview.operators.quantize import encode
from twoview.operators.search import topk
from twoview.sources.vectors import user_vectors


def scratch(spark: SparkSession) -> str:
    """A fresh folder under the session's checkpoint folder; where none is set, a temporary one, on a single machine only."""
    import re
    import tempfile

    context = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not root:
        if not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="twoview-stream-")
    return f"{root.rstrip('/')}/stream-{uuid.uuid4().hex}"


def table_stream(spark: SparkSession, sf_dir: str, name: str, files_per_batch: int = 1) -> DataFrame:
    """A given table as a stream of its files; the name's last letter is a pattern, as a single file needs one."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/{name}.parque[t]")
    # watermarks need times of the session's zone
    return stream.withColumns({f.name: F.col(f.name).cast("timestamp") for f in schema if f.dataType.typeName() == "timestamp_ntz"})


def run_append(stream: DataFrame) -> DataFrame:
    """Runs a stream over what is there into Parquet files, and reads them."""
    spark, at = stream.sparkSession, scratch(stream.sparkSession)
    stream.writeStream.format("parquet").option("checkpointLocation", at + "/c").option("path", at + "/d").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(at + "/d")


def run_complete(stream: DataFrame) -> DataFrame:
    """Runs an aggregation in complete mode; each batch writes the whole result to its own folder, the last one counts."""
    spark, at, last = stream.sparkSession, scratch(stream.sparkSession), []

    def sink(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{at}/d/{batch}")
        last.append(batch)

    stream.writeStream.foreachBatch(sink).option("checkpointLocation", at + "/c").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/d/{max(last)}") if last else spark.createDataFrame([], stream.schema)


def ingest(stream: DataFrame, model: CodeModel) -> DataFrame:
    """Arriving vectors as codes; stateless, so each row is encoded once."""
    return encode(stream, model)


def standing_queries(stream_codes: DataFrame, prepared: DataFrame, model: CodeModel, tau: int) -> DataFrame:
    """Each arriving code against a fixed set of queries: bit test as the join's condition, then look-ups."""
    spec = model.spec
    w, q = E.word_columns("w", spec.n_words), E.word_columns("q", spec.n_words)
    return stream_codes.join(F.broadcast(prepared), E.hamming(w, q) <= tau).select("qid", "vec_id", E.adc(w, F.col("lut"), spec).alias("score"))


def running_topk(scored: DataFrame, k: int) -> DataFrame:
    """The k best of a stream of (qid, vec_id, score): each batch joins the kept rows. A batch that is done again changes nothing."""
    spark, at = scored.sparkSession, scratch(scored.sparkSession)
    state = {"at": None}

    def sink(df: DataFrame, batch: int) -> None:
        old = spark.read.schema("qid bigint, vec_id bigint, score double").parquet(state["at"]) if state["at"] else None
        new = df.select("qid", "vec_id", "score")
        both = new if old is None else new.unionAll(old).dropDuplicates(["qid", "vec_id"])
        topk(both, k).select("qid", "vec_id", "score").write.mode("overwrite").parquet(f"{at}/d/{batch}")
        state["at"] = f"{at}/d/{batch}"

    scored.writeStream.foreachBatch(sink).option("checkpointLocation", at + "/c").trigger(availableNow=True).start().awaitTermination()
    got = spark.read.schema("qid bigint, vec_id bigint, score double").parquet(state["at"]) if state["at"] else spark.createDataFrame([], "qid bigint, vec_id bigint, score double")
    return topk(got, k)


def windowed_users(events: DataFrame, types: list[str], length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """User vectors by tumbling or sliding window."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return user_vectors(events.withWatermark("ts", late).groupBy(w, "user_id"), types).select("vec_id", F.col("window.start").alias("start"), "embedding")


def sessions(events: DataFrame, gap: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Sessions of each user: start, end, events."""
    s = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n_events"))
    return s.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("finish"), "n_events")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events once each, while the watermark remembers their ids."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def pairs_within(left: DataFrame, right: DataFrame, hours: int = 1, late: str = "1 hour") -> DataFrame:
    """Events of one user, of the right stream at most some hours after the left's."""
    a = left.withWatermark("ts", late).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    b = right.withWatermark("ts", late).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    cond = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {hours} HOURS"))
    return a.join(b, cond).select("a_id", "b_id")


def drift(vectors: DataFrame, model: CodeModel, time_col: str, length: str = "1 day", factor: float = 2.0, trained_error: float = 1.0) -> DataFrame:
    """Mean quantization error by window, and whether it is over factor times that of training; vectors have vec_id, time and embedding."""
    import numpy as np

    from twoview.operators.vectors import map_vectors

    sent = vectors.sparkSession.sparkContext.broadcast(model)

    def err(x: np.ndarray) -> dict[str, np.ndarray]:
        m = sent.value
        flat = m.before.apply(x) if m.before is not None else x
        return {"err": ((flat - m.decode(m.encode(x))) ** 2).sum(1)}

    e = map_vectors(vectors, err, "err double", keep=["vec_id", time_col])
    return e.groupBy(F.window(time_col, length).alias("w")).agg(F.avg("err").alias("mean_error"), F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), "mean_error", "n", (F.col("mean_error") > factor * trained_error).alias("alert")
    )


def late_counts(spark: SparkSession, events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Replays events (event_id, ts) as a stream in three steps: all of them, one far later that moves the watermark on, and all
    again under new ids. Returns how many entered daily windows, and how many rows the watermark dropped.

    Dropped rows are counted by the stream's own progress reports.
    """
    at = scratch(spark)
    events = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    far = events.agg((F.max("event_id") + 1).alias("event_id"), (F.max("ts") + F.expr("INTERVAL 30 DAYS")).alias("ts"))
    again = events.crossJoin(F.broadcast(events.agg((F.max("event_id") - F.min("event_id") + 2).alias("_more")))).select((F.col("event_id") + F.col("_more")).alias("event_id"), "ts")
    dropped = 0
    for step in (events, far, again):
        step.coalesce(1).write.mode("append").parquet(at + "/in")
        daily = spark.readStream.schema(events.schema).parquet(at + "/in").withWatermark("ts", late).dropDuplicates(["event_id", "ts"]).select("event_id")
        run = daily.writeStream.format("parquet").option("checkpointLocation", at + "/c").option("path", at + "/d").outputMode("append").trigger(availableNow=True).start()
        run.awaitTermination()
        dropped += sum(o["numRowsDroppedByWatermark"] for p in run.recentProgress for o in p["stateOperators"])
    n = spark.read.schema("event_id bigint").parquet(at + "/d").agg((F.count("*") - 1).alias("in_time"))
    return n.select("in_time", F.lit(int(dropped)).cast("bigint").alias("late_dropped"))

"""Streams of events: windows with watermarks, scoring with a trained model, and one learning step for each micro-batch."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import query
from ..runtime import shared_dir
from ..sources.tables import table

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, late: str = "2 hours", schema=SCHEMA, files_a_batch: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream, with a watermark on ts."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch).parquet(folder).withWatermark("ts", late)


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    w = events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "1 day", step: str = "12 hours") -> DataFrame:
    w = events.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n"))
    return w.select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return w.select(F.col("w.start").alias("start"), "user_id", "n")


def _events(spark, d) -> DataFrame:
    e = table(spark, d, "events")
    return e.withColumn("ts", F.col("ts").cast("timestamp"))


def _run(spark: SparkSession, df: DataFrame, name: str, mode: str = "append", each=None) -> DataFrame | None:
    """Runs what there is of a stream; without `each`, its rows go to files of the shared folder (a memory sink would keep them all on the driver)."""
    tag = f"{name}-{uuid.uuid4().hex}"
    writer = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{shared_dir(spark)}/stream-{tag}")
    if each:
        writer.foreachBatch(each).start().awaitTermination()
        return None
    writer.format("parquet").start(f"{shared_dir(spark)}/rows-{tag}").awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{shared_dir(spark)}/rows-{tag}")


@query("stream_tumbling_batch_equiv", "select date_trunc('day', ts)::timestamp as start, event_type, count(*) as n, round(sum(value), 4) as total from events group by 1, 2")
def stream_tumbling_batch_equiv(spark, d):
    return tumbling(_events(spark, d)).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("stream_sliding_batch_equiv", "select to_timestamp((epoch_us(ts)//43200000000 - k)*43200)::timestamp as start, count(*) as n from events, (values (0), (1)) t(k) group by 1")
def stream_sliding_batch_equiv(spark, d):
    return sliding(_events(spark, d)).select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_session_batch_equiv", "with e as (select user_id, ts, case when ts < lag(ts) over (partition by user_id order by ts) + interval 30 minutes then 0 else 1 end as new from events), s as (select *, sum(new) over (partition by user_id order by ts, new desc rows unbounded preceding) as k from e) select min(ts) as start, user_id, count(*) as n from s group by user_id, k")
def stream_session_batch_equiv(spark, d):
    return sessions(_events(spark, d)).select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def _files(spark, d) -> str:
    folder = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    _events(spark, d).repartitionByRange(4, "ts").write.parquet(folder)
    return folder


@query("score_stream", "select event_id, case event_type when 'click' then 0.2::double when 'purchase' then 1.5::double else 0.0::double end * value as score from events")
def score_stream(spark, d):
    """A stream scored with a trained model by a stream-static join."""
    model = spark.createDataFrame([("click", 0.2), ("purchase", 1.5)], "event_type string, w double")
    scored = event_stream(spark, _files(spark, d)).join(F.broadcast(model), "event_type", "left").select("event_id", (F.coalesce("w", F.lit(0.0)) * F.col("value")).alias("score"))
    return _run(spark, scored, "scored")


@query("online_bgd")
def online_bgd(spark, d):
    """One update of a two-weight logistic model for each micro-batch."""
    w, trace = [0.0, 0.0], []

    def step(batch: DataFrame, number: int) -> None:
        y = F.when(F.col("event_type") == "purchase", 1.0).otherwise(0.0)
        x = F.col("value") / 200
        p = F.lit(1.0) / (F.lit(1.0) + F.exp(-(F.lit(w[0]) + F.lit(w[1]) * x)))
        s = batch.agg(F.sum(p - y).alias("a"), F.sum((p - y) * x).alias("b"), F.count("*").alias("n")).first()
        if s.n:
            w[0], w[1] = w[0] - 0.5 * s.a / s.n, w[1] - 0.5 * s.b / s.n
            trace.append((number, w[0], w[1]))

    _run(spark, event_stream(spark, _files(spark, d)), "online", each=step)
    return spark.createDataFrame(trace, "batch long, w0 double, w1 double")

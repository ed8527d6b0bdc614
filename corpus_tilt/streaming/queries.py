"""Streaming queries that must equal their batch form, and the stream of the selection."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..models.weight_models import LinearWeight
from ..sources.scratch import scratch
from .select import deduplicated, file_stream, run_to_table, stream_select, top_reservoir, windowed_counts, with_parameters


def _rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    where = scratch(spark, "stream")
    _rows(spark, sf_dir).write.parquet(where)
    return file_stream(spark, where, spark.read.parquet(where), 100)


def stream_tumbling(spark, sf_dir):
    got = run_to_table(spark, windowed_counts(_events(spark, sf_dir)), scratch(spark, "stream"), "complete")
    return got.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


def stream_late(spark, sf_dir):
    """Events, and after them copies of those more than a day old: the watermark shuts the late ones out.

    A watermark holds for late rows from the second batch after the rows that moved it, so the
    newest event is a batch of its own between them.
    """
    where, events = scratch(spark, "stream"), _rows(spark, sf_dir)
    last = events.agg(F.max_by("event_id", F.struct("ts", "event_id")), F.max("ts")).first()
    newest = F.col("event_id") == last[0]
    for part in (events.where(~newest), events.where(newest), events.where(F.col("ts") < F.lit(last[1]) - F.expr("interval 1 day"))):
        part.coalesce(1).write.mode("append").parquet(where)  # the stream takes files by time, one a batch
    got = run_to_table(spark, windowed_counts(file_stream(spark, where, events, 1)), scratch(spark, "stream"), "update")
    return got.groupBy(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type").agg(F.max("n").alias("n"))


def stream_dedup(spark, sf_dir):
    return run_to_table(spark, deduplicated(_events(spark, sf_dir)).select("event_id"), scratch(spark, "stream"))


def stream_join(spark, sf_dir):
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    steps = e.groupBy("event_type").agg(F.round(F.avg("value"), 6).alias("rate"))
    return run_to_table(spark, with_parameters(_events(spark, sf_dir), steps).select("event_id", "rate"), scratch(spark, "stream"))


def stream_state(spark, sf_dir):
    rows = _events(spark, sf_dir).select(F.col("event_type").alias("domain"), F.col("value").alias("score"))
    got = run_to_table(spark, top_reservoir(rows), scratch(spark, "stream"), "update")
    return got.groupBy("domain").agg(F.round(F.max("least"), 6).alias("least"), F.round(F.max("most"), 6).alias("most"), F.max("held").alias("held"))


def stream_selection(spark, sf_dir):
    where = scratch(spark, "stream")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    docs.repartition(4, "doc_id").write.parquet(f"{where}/in")
    query = stream_select(file_stream(spark, f"{where}/in", docs, 1), LinearWeight(), np.linspace(-2, 2, 16), 16, f"{where}/out", f"{where}/checkpoint")
    query.awaitTermination()
    return spark.read.parquet(f"{where}/out").select("id", "batch_id", F.round("score", 6).alias("score"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op_stream_tumbling": stream_tumbling, "op_stream_late": stream_late, "op_stream_dedup": stream_dedup, "op_stream_join": stream_join, "op_stream_state": stream_state, "q_stream_select": stream_selection}
ORACLES: dict[str, str] = {
    "op_stream_tumbling": "select strftime(time_bucket(interval 1 hour, ts), '%Y-%m-%d %H:%M') as start, event_type, cast(count(*) as bigint) as n from events group by 1, 2",
    "op_stream_late": "select strftime(time_bucket(interval 1 hour, ts), '%Y-%m-%d %H:%M') as start, event_type, cast(count(*) as bigint) as n from events group by 1, 2",
    "op_stream_dedup": "select distinct event_id from events",
    "op_stream_join": "select e.event_id, r.rate from events e join (select event_type, round(avg(value), 6) as rate from events group by event_type) r using (event_type)",
    "op_stream_state": "select event_type as domain, round(min(value), 6) as least, round(max(value), 6) as most, cast(count(*) as bigint) as held from (select event_type, value, row_number() over (partition by event_type order by value desc) as r from events) where r <= 5 group by event_type",
}

"""Selection over streams: the small model alone scans; kept examples go on."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.portable import usable_text
from ..operators.sampling import FILTERS
from ..plans.cascade import score_examples


def stream_select(stream: DataFrame, weight, alpha: np.ndarray, n: int, out: str, checkpoint: str, kind: str = "gumbel", seed: int = 0, id_col: str = "doc_id", text_col: str = "text", prefix: int | None = None) -> StreamingQuery:
    """Keep ``n`` examples of each micro-batch under ``out``/batch_id=...; a batch that is replayed writes its own folder again."""

    def batch(df: DataFrame, batch_id: int) -> None:
        rows = df.select(F.col(id_col).alias("id"), usable_text(F.col(text_col), prefix).alias("payload")).where("payload is not null")
        kept = FILTERS[kind](score_examples(rows, weight, alpha), n, seed, batch_id)
        kept.write.mode("overwrite").parquet(f"{out}/batch_id={batch_id}")

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_counts(events: DataFrame, delay: str = "10 minutes", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by window and type under a watermark."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean_value"))


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events without copies that arrive within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def with_parameters(events: DataFrame, steps: DataFrame) -> DataFrame:
    """A stream beside a static table of parameter versions (event_type, rate)."""
    return events.join(F.broadcast(steps), "event_type", "left")


def top_reservoir(stream: DataFrame, size: int = 5) -> DataFrame:
    """For each domain, the running best ``size`` scores seen so far (arbitrary state)."""

    def update(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        best = list(state.get[0]) if state.exists else []
        best = sorted([*best, *(s for f in frames for s in f["score"].tolist())], reverse=True)[:size]
        state.update((best,))
        yield pd.DataFrame({"domain": [key[0]], "least": [best[-1]], "most": [best[0]], "held": [len(best)]})

    return stream.groupBy("domain").applyInPandasWithState(update, "domain string, least double, most double, held long", "best array<double>", "update", "NoTimeout")


def run_to_table(spark: SparkSession, stream: DataFrame, where: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now into Parquet below ``where``, a folder a batch; the table that results.

    ``complete``: the last batch is the table; ``append`` and ``update``: all batches are.  A batch
    that is replayed writes its own folder again.
    """
    done: list[int] = []

    def batch(df: DataFrame, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{where}/out/batch_id={batch_id}")
        done.append(batch_id)

    query = stream.writeStream.foreachBatch(batch).outputMode(mode).option("checkpointLocation", f"{where}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{where}/out/batch_id={max(done)}")
    return spark.read.schema(stream.schema).option("basePath", f"{where}/out").parquet(f"{where}/out").select(*stream.columns)


def file_stream(spark: SparkSession, path: str, like: DataFrame, files: int = 1) -> DataFrame:
    return spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", "*.parquet").parquet(path)

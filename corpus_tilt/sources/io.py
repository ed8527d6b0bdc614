"""Readers that check schemas, round trips through file formats, and checkpoints of parameters."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from .scratch import scratch

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "benchmark": "item_id long, text string",
    "pages": "page_id long, url string, html string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}
PARAMETERS = "run_id string, step int, kind string, block int, vals array<double>"
BLOCK = 4096


def read_checked(spark: SparkSession, path: str, name: str) -> DataFrame:
    """A table whose columns must have the names and types that ``SCHEMAS`` gives; other columns are dropped."""
    df, want = spark.read.parquet(path), StructType.fromDDL(SCHEMAS[name])
    have = {f.name: f.dataType for f in df.schema}
    wrong = [f.name for f in want if have.get(f.name) is None or have[f.name].simpleString().replace("int", "bigint") != f.dataType.simpleString().replace("int", "bigint") and have[f.name] != f.dataType]
    if wrong:
        raise ValueError(f"{name}: columns {wrong} are missing or have other types")
    return df.select(*[f.name for f in want])


def bad_rows(df: DataFrame, text_col: str) -> int:
    """Rows without a usable text (null or under two bytes): counted, not lost silently."""
    return df.where(F.col(text_col).isNull() | (F.octet_length(text_col) < 2)).count()


def save_parameters(spark: SparkSession, path: str, run_id: str, step: int, kind: str, values: np.ndarray) -> None:
    """One vector in blocks, appended to a table partitioned by run."""
    rows = [(run_id, step, kind, i // BLOCK, values[i : i + BLOCK].tolist()) for i in range(0, len(values), BLOCK)]
    spark.createDataFrame(rows, PARAMETERS).write.mode("append").partitionBy("run_id").parquet(path)


def load_parameters(spark: SparkSession, path: str, run_id: str, kind: str, step: int | None = None) -> np.ndarray:
    """The vector of a step, or of the last one."""
    df = spark.read.parquet(path).where((F.col("run_id") == run_id) & (F.col("kind") == kind))
    step = df.agg(F.max("step")).first()[0] if step is None else step
    blocks = df.where(F.col("step") == step).select("block", "vals").collect()
    if not blocks:
        raise ValueError(f"no {kind} of run {run_id}")
    return np.concatenate([b["vals"] for b in sorted(blocks, key=lambda b: b["block"])])


class ParameterSource(DataSource):
    """``spark.read.format("tilt_parameters").load(path)``: parameter files of NumPy as rows (kind, idx, val)."""

    @classmethod
    def name(cls) -> str:
        return "tilt_parameters"

    def schema(self) -> str:
        return "kind string, idx long, val double"

    def reader(self, schema):
        return _ParameterReader(self.options["path"])


class _ParameterReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self):
        with np.load(self.path) as held:
            return [InputPartition(k) for k in held.files]

    def read(self, partition):
        with np.load(self.path) as held:
            for i, v in enumerate(held[partition.value].ravel().tolist()):
                yield partition.value, i, v


def op_io_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """labels through Parquet, CSV, JSON and ORC, bucketed and partitioned; the rows that all give back."""
    labels, where = spark.read.parquet(f"{sf_dir}/labels.parquet"), scratch(spark, "io")
    out = None
    for kind in ("parquet", "csv", "json", "orc"):
        labels.write.format(kind).mode("overwrite").save(f"{where}/{kind}")
        got = spark.read.schema(labels.schema).format(kind).load(f"{where}/{kind}")
        out = got if out is None else out.intersect(got)
    labels.write.partitionBy("quality").parquet(f"{where}/parts")
    return out.intersect(spark.read.parquet(f"{where}/parts").select(*[F.col(f.name).cast(f.dataType) for f in labels.schema]))


QUERIES = {"op_io_roundtrip": op_io_roundtrip}
ORACLES = {"op_io_roundtrip": "select distinct * from labels"}

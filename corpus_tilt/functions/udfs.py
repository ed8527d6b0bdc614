"""Functions beyond the built-in ones: vectorised, aggregating, table-valued; and their registration for SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..models.main_models import ByteModel
from ..models.weight_models import LinearWeight


def score_function(alpha: np.ndarray):
    """A scalar function of text: the linear weight model's score."""

    @F.pandas_udf(T.DoubleType())
    def tilt_score(texts: pd.Series) -> pd.Series:
        model = LinearWeight()
        raw = [t.encode() if t else b"" for t in texts]
        got = pd.Series(model.scores(alpha, model.prepare(raw)) if raw else [], dtype=float)
        return got.where(np.array([len(r) >= 2 for r in raw], bool), np.nan)

    return tilt_score


def loss_function(theta: np.ndarray, contexts: int = 16):
    """An iterator function of text, its model made once a task: nats a byte under the byte model."""

    @F.pandas_udf(T.DoubleType())
    def tilt_loss(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = ByteModel(contexts)
        for texts in batches:
            raw = [t.encode() if t else b"" for t in texts]
            got = model.losses(theta, model.prepare([r if len(r) >= 2 else b"  " for r in raw]))
            yield pd.Series(np.where([len(r) >= 2 for r in raw], got, np.nan))

    return tilt_loss


@F.udtf(returnType="gram string, n long")
class ByteNgrams:
    """The byte n-grams (hex) of a text and their counts."""

    def eval(self, text: str, k: int):
        from collections import Counter

        raw = (text or "").encode()
        for gram, n in sorted(Counter(raw[i : i + k] for i in range(len(raw) - k + 1)).items()):
            yield gram.hex().upper(), n


def register(spark: SparkSession, alpha: np.ndarray, theta: np.ndarray) -> None:
    """``tilt_score(text)``, ``tilt_loss(text)`` and the table function ``byte_ngrams(text, k)`` for SQL."""
    spark.udf.register("tilt_score", score_function(alpha))
    spark.udf.register("tilt_loss", loss_function(theta))
    spark.udtf.register("byte_ngrams", ByteNgrams)


@F.pandas_udf(T.DoubleType())
def _root_mean_square(x: pd.Series) -> float:
    return float(np.sqrt((x * x).mean()))


def op_udf_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    @F.pandas_udf(T.LongType())
    def byte_length(texts: pd.Series) -> pd.Series:
        import pyarrow.compute as pc

        return pc.binary_length(pa.array(texts, pa.string())).to_pandas()  # null for null

    return spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", byte_length("text").alias("n"))


def op_udaf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("event_type").agg(_root_mean_square("value").alias("x")).select("event_type", (F.round("x", 6) + F.lit(0.0)).alias("x"))


def op_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    spark.udtf.register("byte_ngrams", ByteNgrams)
    spark.read.parquet(f"{sf_dir}/benchmark.parquet").createOrReplaceTempView("tilt_benchmark")
    return spark.sql("select b.item_id, g.gram, g.n from tilt_benchmark b, lateral byte_ngrams(b.text, 1) g")


def op_map_in_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    def upper(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.utf8_upper(b.column(1))], ["n_nationkey", "name"])

    return spark.read.parquet(f"{sf_dir}/nation.parquet").select("n_nationkey", "n_name").mapInArrow(upper, "n_nationkey int, name string")


def op_apply_in_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    def spread(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"c_mktsegment": [pdf["c_mktsegment"].iat[0]], "n": [len(pdf)], "spread": [round(float(pdf["c_acctbal"].max() - pdf["c_acctbal"].min()), 6)]})

    return spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_mktsegment", "c_acctbal").groupBy("c_mktsegment").applyInPandas(spread, "c_mktsegment string, n long, spread double")


QUERIES = {f.__name__: f for f in (op_udf_pandas, op_udaf, op_udtf, op_map_in_arrow, op_apply_in_pandas)}
ORACLES = {
    "op_udf_pandas": "select doc_id, cast(octet_length(encode(text)) as bigint) as n from documents",
    "op_udaf": "select event_type, round(sqrt(avg(value * value)), 6) + 0e0 as x from events group by event_type",
    "op_udtf": "select item_id, gram, cast(count(*) as bigint) as n from (select item_id, unnest(list_transform(range(0, cast(length(hex(text)) / 2 as int)), lambda i: substr(hex(text), cast(2 * i + 1 as int), 2))) as gram from benchmark) group by item_id, gram",
    "op_map_in_arrow": "select n_nationkey, upper(n_name) as name from nation",
    "op_apply_in_pandas": "select c_mktsegment, cast(count(*) as bigint) as n, round(max(c_acctbal) - min(c_acctbal), 6) as spread from customer group by c_mktsegment",
}

"""Cheap first: score all, keep few, fetch payloads late.

The optimizer never moves a costly stage above a cheap filter by itself; these nodes are placed
so.  Scoring reads ids and texts; the kept ids then fetch their payload by a semi-join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.portable import usable_text
from ..operators.sampling import FILTERS


def score_examples(df: DataFrame, weight, alpha: np.ndarray, id_col: str = "id", payload: str = "payload") -> DataFrame:
    """(id, score): the weight model's parameters are broadcast, the pass is map-only; examples without a payload are left out."""
    shared = df.sparkSession.sparkContext.broadcast((weight, alpha))

    def score(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model, a = shared.value
        for f in frames:
            rows = f.loc[f[payload].notna()]
            if len(rows):
                yield pd.DataFrame({"id": rows[id_col].to_numpy(), "score": model.scores(a, model.prepare([bytes(x) for x in rows[payload]]))})

    return df.select(id_col, payload).mapInPandas(score, "id long, score double")


def linear_scores(df: DataFrame, alpha: np.ndarray, id_col: str = "id", payload: str = "payload") -> DataFrame:
    """The same for the linear model over nibble shares, inside the JVM: no Python at all."""
    h, n = F.hex(payload), F.octet_length(payload)

    def count(c: str):
        return F.size(F.filter(F.sequence(F.lit(0), n - 1), lambda i: F.substr(h, 2 * i + 1, F.lit(1)) == c))

    terms = [F.lit(float(a)) * count(c) for a, c in zip(alpha, "0123456789ABCDEF", strict=True)]
    return df.where(F.octet_length(payload) >= 1).select(F.col(id_col).alias("id"), (sum(terms[1:], terms[0]) / n).alias("score"))


def select_then_fetch(docs: DataFrame, weight, alpha: np.ndarray, n: int, kind: str = "gumbel", seed: int = 0, step: int = 0, id_col: str = "doc_id", text_col: str = "text", prefix: int | None = None) -> DataFrame:
    """Rows of ``docs`` that the filter keeps: score whole texts (or prefixes), filter, then a semi-join for whole rows."""
    examples = docs.select(F.col(id_col).alias("id"), usable_text(F.col(text_col), prefix).alias("payload")).where("payload is not null")
    kept = FILTERS[kind](score_examples(examples, weight, alpha), n, seed, step)
    return docs.join(kept.select(F.col("id").alias(id_col)), id_col, "left_semi")


def sliced(docs: DataFrame, path: str, slices: int, id_col: str = "doc_id") -> None:
    """Write once by slices of hashed ids, so that a step reads one slice by partition pruning instead of sampling a scan."""
    docs.withColumn("slice", F.pmod(F.xxhash64(id_col), F.lit(slices)).cast("int")).repartition("slice").write.mode("overwrite").partitionBy("slice").parquet(path)


def gradient_sums(df: DataFrame, main, theta: np.ndarray, w_col: str = "w", payload: str = "payload") -> np.ndarray:
    """Sum of weighted gradients over all rows: each task adds up its own, blocks are summed by key, one vector reaches the driver."""
    shared = df.sparkSession.sparkContext.broadcast((main, theta))
    block = 4096

    def partial(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model, t = shared.value
        total = np.zeros(model.size)
        for f in frames:
            if len(f):
                total += model.grad(t, model.prepare([bytes(x) for x in f[payload]]), f[w_col].to_numpy())
        at = np.flatnonzero(total)
        yield pd.DataFrame({"block": at // block, "at": at, "g": total[at]})

    sums = df.select(payload, w_col).mapInPandas(partial, "block long, at long, g double").groupBy("block", "at").agg(F.sum("g").alias("g")).toArrow()
    out = np.zeros(main.size)
    out[sums["at"].to_numpy()] = sums["g"].to_numpy()
    return out

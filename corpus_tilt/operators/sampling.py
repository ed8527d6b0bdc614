"""Samples and filters over scored examples, as DataFrame plans.

Randomness is a hash of id, seed and step, so a plan that runs again keeps the same rows.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.portable import gumbel, u01


def softmax_weights(df: DataFrame, by: str | None = None, score: str = "score") -> DataFrame:
    """Weights that sum to one inside each batch ``by``, or over everything (two aggregates, no window)."""
    if by:
        w = Window.partitionBy(by)
        up = df.withColumn("__e", F.exp(F.col(score) - F.max(score).over(w)))
        return up.withColumn("w", F.col("__e") / F.sum("__e").over(w)).drop("__e")
    top, total = log_normaliser(df, score)
    return df.withColumn("w", F.exp(F.col(score) - F.lit(top)) / F.lit(total))


def log_normaliser(df: DataFrame, score: str = "score") -> tuple[float, float]:
    """max and sum(exp(score - max)): two numbers a partition meet on the driver."""
    top = df.agg(F.max(score)).first()[0]
    if top is None:
        return 0.0, 1.0
    return top, df.agg(F.sum(F.exp(F.col(score) - F.lit(top)))).first()[0]


def _checked(n: int) -> None:
    if n <= 0:
        raise ValueError("a filter keeps at least one row")


def sample_uniform(df: DataFrame, n: int, seed: int, step: int, id_col: str = "id") -> DataFrame:
    """n rows without replacement: a heap of n a partition, merged; all rows where there are fewer."""
    _checked(n)
    key = u01(F.col(id_col), f"{seed}/{step}/u")
    return df.withColumn("__k", key).orderBy("__k", id_col).limit(n).drop("__k")


def filter_gumbel(df: DataFrame, n: int, seed: int, step: int, id_col: str = "id") -> DataFrame:
    """n rows without replacement, drawn by weight: the largest of score plus Gumbel noise."""
    _checked(n)
    return df.withColumn("key", F.col("score") + gumbel(F.col(id_col), f"{seed}/{step}/g")).orderBy(F.desc("key"), id_col).limit(n)


def filter_top(df: DataFrame, n: int, id_col: str = "id") -> DataFrame:
    """The n rows of the highest scores."""
    _checked(n)
    return df.orderBy(F.desc("score"), id_col).limit(n)


def filter_iid(df: DataFrame, n: int, seed: int, step: int, id_col: str = "id") -> DataFrame:
    """n independent draws by weight, as rows with ``copies``.

    A two-level prefix sum: totals of hash buckets meet on the driver (a fixed number), draws
    are dealt to buckets there, and each bucket sums within itself; no single-task window.
    """
    import numpy as np

    _checked(n)
    buckets = 64
    top, _ = log_normaliser(df)
    rows = df.withColumns({"__b": F.pmod(F.xxhash64(id_col), F.lit(buckets)).cast("int"), "__w": F.exp(F.col("score") - F.lit(top))})
    got = {r["__b"]: r["t"] for r in rows.groupBy("__b").agg(F.sum("__w").alias("t")).collect()}
    totals = np.array([got.get(b, 0.0) for b in range(buckets)])
    edges = np.concatenate([[0.0], np.cumsum(totals)])
    at = np.sort(np.random.default_rng([seed, step]).random(n)) * edges[-1]
    bucket = np.clip(np.searchsorted(edges, at, side="right") - 1, 0, buckets - 1)
    draws = df.sparkSession.createDataFrame([(int(b), float(x - edges[b])) for b, x in zip(bucket, at, strict=True)], "__b int, __u double")  # n rows, the batch asked for
    hi = F.sum("__w").over(Window.partitionBy("__b").orderBy(id_col).rowsBetween(Window.unboundedPreceding, 0))
    cum = rows.withColumn("__hi", hi).withColumn("__lo", F.col("__hi") - F.col("__w"))
    hit = cum.join(F.broadcast(draws), (cum["__b"] == draws["__b"]) & (draws["__u"] >= cum["__lo"]) & (draws["__u"] < cum["__hi"])).drop(draws["__b"])
    return hit.groupBy(*df.columns).agg(F.count("*").cast("int").alias("copies"))


def filter_poisson(df: DataFrame, n: int, seed: int, step: int, id_col: str = "id", bins: int = 4096) -> DataFrame:
    """About n rows in one pass without a sort: inclusion min(1, c w); c from a histogram of scores.

    The size is random and the law only near that of ``filter_gumbel``; for one huge pass.
    """
    _checked(n)
    ends = df.agg(F.min("score"), F.max("score")).first()
    if ends[0] is None:
        return df.limit(0)
    width = max((ends[1] - ends[0]) / bins, 1e-9)
    cell = F.least(F.floor((F.col("score") - F.lit(ends[0])) / width), F.lit(bins - 1))
    hist = [(r["c"], r["n"], r["t"] / r["n"]) for r in df.groupBy(cell.alias("c")).agg(F.count("*").alias("n"), F.sum(F.exp(F.col("score") - F.lit(ends[1]))).alias("t")).collect()]
    lo, hi = -60.0, 60.0 + math.log(n) - math.log(max(min(m for *_, m in hist), 1e-300))
    for _ in range(200):  # the expected size grows with c
        mid = (lo + hi) / 2
        if sum(k * min(1.0, math.exp(min(mid, 700)) * m) for _, k, m in hist) < n:
            lo = mid
        else:
            hi = mid
    chance = F.least(F.lit(1.0), F.exp(F.col("score") - F.lit(ends[1]) + F.lit(hi)))
    return df.withColumn("inclusion", chance).where(u01(F.col(id_col), f"{seed}/{step}/p") < F.col("inclusion"))


def filter_gumbel_threshold(df: DataFrame, n: int, seed: int, step: int, id_col: str = "id", spare: float = 1.5) -> DataFrame:
    """Exactly ``filter_gumbel``, but rows below an approximate quantile of the keys are dropped before the final heap."""
    keyed = df.withColumn("key", F.col("score") + gumbel(F.col(id_col), f"{seed}/{step}/g"))
    total = keyed.count()
    if total <= n:
        return keyed
    share = max(0.0, 1 - spare * n / total)
    edge = keyed.agg(F.percentile_approx("key", share, 10_000)).first()[0]
    above = keyed.where(F.col("key") >= edge)
    chosen = above if above.count() >= n else keyed
    return chosen.orderBy(F.desc("key"), id_col).limit(n)


FILTERS = {"gumbel": filter_gumbel, "iid": filter_iid, "top": lambda df, n, seed, step, id_col="id": filter_top(df, n, id_col), "uniform": sample_uniform, "poisson": filter_poisson}


def weight_concentration(df: DataFrame) -> DataFrame:
    """Effective sample size, entropy and the largest weight of column w."""
    return df.agg((F.sum("w") ** 2 / F.sum(F.col("w") ** 2)).alias("ess"), (-F.sum(F.col("w") * F.log("w"))).alias("entropy"), F.max("w").alias("top_weight"))


def batch_diversity(draws: DataFrame, id_col: str = "id") -> DataFrame:
    return draws.agg(F.count_distinct(id_col).alias("distinct_items"), F.sum("copies").alias("draws"), F.max("copies").alias("most_copies"))

"""Connected components of an edge table by alternating star contractions.

Every step is an aggregate or an equality join over written tables; nothing about nodes or edges
reaches the driver but two numbers a round, by which it sees that the edges stand still.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def _stars(edges: DataFrame, both: bool) -> DataFrame:
    """Link each node's larger (or, where not ``both``, smaller) neighbours to the least node around it."""
    seen = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if both else edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = written(seen.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")), "least")
    joined = seen.join(least, "a")
    out = joined.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")) if both else joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    out = out.where("a <> b")
    return out if both else out.distinct()


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every node of ``edges`` (a, b): the component is its least node; its own row included.

    Nodes are of any type with an order (64-bit numbers, or structs of them).
    """
    now = written(edges.select("a", "b").where("a <> b").distinct(), "edges")
    state = None
    while True:
        sign = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if sign[0] == 0 or tuple(sign) == state:
            break
        state = tuple(sign)
        now = written(_stars(written(_stars(now, True), "edges"), False), "edges")
    tops = now.select(F.col("b").alias("id")).distinct()
    return now.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(tops.select("id", F.col("id").alias("component")))

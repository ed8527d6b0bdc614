"""All queries of the library and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..functions import udfs
from ..operators import relational
from ..sources import io
from ..streaming import queries as streams
from ..training.experiments import EXPERIMENTS
from . import kernel


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {n: kernel.spark_query(n) for n in kernel.QUERIES} | relational.SPARK | udfs.QUERIES | io.QUERIES | streams.QUERIES | EXPERIMENTS


def oracles() -> dict[str, str]:
    return {n: kernel.oracle_text(n) for n in kernel.QUERIES} | relational.SQL | udfs.ORACLES | io.ORACLES | streams.ORACLES

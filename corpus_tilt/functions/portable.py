"""Deterministic randomness as Columns: hashes of ids, never the engine's own generator.

A task that is run again, another partitioning or another engine draws the same numbers.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def u01(key: Column, seed: int | str | Column) -> Column:
    """A number in (0, 1) from a hash of seed and key."""
    head = F.concat(seed, F.lit(":")) if isinstance(seed, Column) else F.lit(f"{seed}:")
    text = F.concat(head, key.cast("string"))
    return (F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") + F.lit(0.5)) / F.lit(4294967296.0)


def gumbel(key: Column, seed: int | str | Column) -> Column:
    """Standard Gumbel noise: the n largest of score plus noise are n draws without replacement."""
    return -F.log(-F.log(u01(key, seed)))


def usable_text(text: Column, max_bytes: int | None = None) -> Column:
    """The bytes of a text, or the first ``max_bytes``; null where there are fewer than two (no loss is defined there)."""
    raw = F.encode(text, "utf-8")
    if max_bytes is not None:
        raw = F.substring(raw, 1, max_bytes)
    return F.when(F.octet_length(raw) >= 2, raw)

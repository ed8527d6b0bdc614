"""SQL text for two engines, and chains of named steps that run on either."""

from __future__ import annotations

import re
import uuid
from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..sources.scratch import written


def num(x: float) -> str:
    """A double literal in both engines."""
    return f"{float(x)!r}e0" if "e" not in repr(float(x)) else repr(float(x))


@dataclass(frozen=True)
class Dialect:
    name: str

    def series(self, n: str) -> str:
        """A lateral table with column i = 0 .. n - 1 (n at least 1)."""
        inner = f"explode(sequence(0, cast({n} as int) - 1))" if self.name == "spark" else f"unnest(range(0, cast({n} as int)))"
        return f"lateral (select {inner} as i)"

    def hex_int(self, e: str) -> str:
        return f"cast(conv({e}, 16, 10) as bigint)" if self.name == "spark" else f"cast(('0x' || {e}) as bigint)"

    def u01(self, key: str, seed: int | str) -> str:
        """A number in (0, 1) from the hash of seed and key: the same in every run, split and engine."""
        return f"(({self.hex_int(f'''substr(md5(concat('{seed}', ':', {key})), 1, 8)''')} + 0.5e0) / 4294967296e0)"

    def octets(self, e: str) -> str:
        return f"octet_length({e})" if self.name == "spark" else f"strlen({e})"

    def r6(self, e: str) -> str:
        return f"(round({e}, 6) + 0e0)"


SPARK, DUCK = Dialect("spark"), Dialect("duck")
TABLES = tuple("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())


@dataclass
class Chain:
    """Named steps of SQL; ``@name`` refers to another step or a table."""

    dialect: Dialect
    steps: dict[str, str] = field(default_factory=dict)
    data: set[str] = field(default_factory=set)
    makers: dict[str, Callable] = field(default_factory=dict)
    scans: set[str] = field(default_factory=set)  # steps that only read and filter a table: never made

    def add(self, name: str, sql: str, data: bool = False, make: Callable | None = None) -> str:
        """``data``: the step's rows grow with the tables, not only with the model or the batch.

        ``make``: what Spark runs for the step in place of the SQL, as a function from a step's name
        to its DataFrame; the SQL says the same, and names the steps that are used.
        """
        self.steps[name] = sql
        if data:
            self.data.add(name)
        if make:
            self.makers[name] = make
        return name

    def _needed(self, name: str, seen: dict[str, None]) -> None:
        for ref in re.findall(r"@(\w+)", self.steps[name]):
            if ref in self.steps and ref not in seen:
                self._needed(ref, seen)
        seen[name] = None

    def order(self, final: str) -> list[str]:
        seen: dict[str, None] = {}
        self._needed(final, seen)
        return list(seen)

    def text(self, final: str) -> str:
        """One statement with common table expressions."""
        plain = lambda s: re.sub(r"@(\w+)", r"\1", s)
        *before, last = self.order(final)
        head = ", ".join(f"{n} as ({plain(self.steps[n])})" for n in before)
        return (f"with {head} " if head else "") + plain(self.steps[last])

    def run(self, spark: SparkSession, sf_dir: str, final: str) -> DataFrame:
        """Steps as views.  A step that others read more than once is made once, when the query is
        built: a table that grows with the data is written below the shared folder, one bounded by
        the model or the batch becomes a local relation, so plans do not grow with the chain."""
        tag = uuid.uuid4().hex[:8]
        views: dict[str, str] = {}
        order = self.order(final)
        uses = Counter(ref for n in order for ref in re.findall(r"@(\w+)", self.steps[n]))

        def view(ref: str) -> str:
            if ref not in views:
                if ref not in TABLES:
                    raise ValueError(f"no step or table {ref}")
                views[ref] = f"tilt_{ref}_{tag}"
                spark.read.parquet(f"{sf_dir}/{ref}.parquet").createOrReplaceTempView(views[ref])
            return views[ref]

        df = None
        for name in order:
            if name in self.makers:
                df = self.makers[name](lambda ref: spark.table(view(ref)))
            else:
                df = spark.sql(re.sub(r"@(\w+)", lambda m: view(m[1]), self.steps[name]))
            if name == final:
                break
            if uses[name] > 1 and name not in self.scans:
                df = written(df, f"step-{name}") if name in self.data else spark.createDataFrame(df.toArrow())
            views[name] = f"tilt_{name}_{tag}"
            df.createOrReplaceTempView(views[name])
        return df

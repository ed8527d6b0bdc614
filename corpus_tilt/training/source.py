"""Where batches come from: rows that the driver holds whole, or a DataFrame that stays on the cluster.

Both draw by the same hashes of (seed, what for, epoch or step, id), so a run is the same on either:
an epoch deals the rows to slices of about the batch's size, a step takes one slice (its least
hashes, where it is larger), and no row comes twice in an epoch.  On the cluster a step scores its
slice where the rows are, filters on (id, score) alone, and only what is kept is fetched; a drawn
source fetches the batches of many steps at once, packed.  Nothing that grows with the data reaches
the driver.  ``source_of`` holds rows in the driver only where their whole payload is below a
checked bound.
"""

from __future__ import annotations

import hashlib
import math
import pickle
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.portable import gumbel, u01
from ..models.base import size_of, softmax, take
from ..sources.scratch import workers_import, written
from .task import Task, payload_bytes, plain, stored_examples

#: Bytes of payload that a driver may hold.
LOCAL_BYTES = 16 << 20
#: Payload and rows that a task prepares at once.
STRETCH_BYTES, STRETCH_ROWS = 1 << 20, 4096


def hashes(ids: np.ndarray, seed: str) -> np.ndarray:
    """Twin of ``portable.u01`` for ids in the driver."""
    return np.array([(int(hashlib.md5(f"{seed}:{i}".encode()).hexdigest()[:8], 16) + 0.5) / 2**32 for i in ids.tolist()])


def slices(total: int, n: int) -> int:
    return max(1, total // n)


def choose(kind: str, scores: np.ndarray, n: int, u: np.ndarray, draws: np.ndarray | None = None) -> np.ndarray:
    """Positions that a filter keeps of a scored batch; ``u``: a uniform number a row, ``draws``: one a draw (for ``iid``)."""
    if kind == "gumbel":
        return np.argsort(-(scores - np.log(-np.log(u))), kind="stable")[:n]
    if kind == "top":
        return np.argsort(-scores, kind="stable")[:n]
    if kind == "uniform":
        return np.argsort(u, kind="stable")[:n]
    if kind == "iid":
        edges = np.cumsum(softmax(scores))
        return np.minimum(np.searchsorted(edges, draws * edges[-1], side="right"), len(scores) - 1)
    raise ValueError(f"unknown filter {kind}")


@dataclass
class Batch:
    """Prepared rows for the main and the weight model."""

    ids: np.ndarray
    payloads: list
    x: object
    xw: object

    def __len__(self) -> int:
        return len(self.ids)

    def take(self, at: np.ndarray) -> Batch:
        return Batch(self.ids[at], [self.payloads[i] for i in at], take(self.x, at), None if self.xw is None else take(self.xw, at))


class PackedBatch:
    """A batch of packed rows; the main model's form is made when it is asked for."""

    def __init__(self, main, ids: np.ndarray, sizes: np.ndarray, blobs: list[bytes], xw: object) -> None:
        self.main, self.ids, self.sizes, self.blobs, self.xw = main, ids, sizes, blobs, xw

    def __len__(self) -> int:
        return len(self.ids)

    @cached_property
    def x(self) -> object:
        return self.main.unpacked(self.blobs) if hasattr(self.main, "unpacked") else self.main.prepare([pickle.loads(b) for b in self.blobs])  # noqa: S301  packed by this program's tasks

    def take(self, at: np.ndarray) -> PackedBatch:
        return PackedBatch(self.main, self.ids[at], self.sizes[at], [self.blobs[i] for i in at], None if self.xw is None else take(self.xw, at))


@dataclass(frozen=True)
class Draw:
    """Batches of ``n`` rows of a side's training rows, for the steps ``steps``."""

    side: int
    n: int
    steps: range
    tag: str
    seed: int


@dataclass
class Source:
    task: Task
    main: object
    weight: object = None

    def __post_init__(self) -> None:
        """For the kinds of sources to prepare themselves."""

    def expect(self, draws: list[Draw]) -> None:
        """Batches that will be asked for; a source may fetch them together."""

    def batch(self, ids: np.ndarray, payloads: list) -> Batch:
        return Batch(ids, payloads, self.main.prepare(payloads), self.weight.prepare(payloads) if self.weight is not None else None)


class LocalSource(Source):
    """All rows of a side and split in the driver."""

    def whole(self, side: int, split: str = "train") -> Batch:
        held = self.__dict__.setdefault("_held", {})
        if (side, split) not in held:
            held[side, split] = self.batch(*self.task.rows(side, split))
        return held[side, split]

    def total(self, side: int, split: str, among=None) -> int:
        return len(self.whole(side, split)) if among is None else len(among)

    def uniform(self, side: int, split: str, n: int, steps: range, tag: str, seed: int, among: np.ndarray | None = None) -> list[Batch]:
        rows = self.whole(side, split)
        rows = rows if among is None else rows.take(among)
        parts = slices(len(rows), n)
        out = []
        for t in steps:
            u = hashes(rows.ids, f"{seed}/{tag}/{t // parts}")
            own = np.flatnonzero(np.floor(u * parts).astype(int) == t % parts)
            own = own[np.argsort(u[own], kind="stable")][:n]
            out.append(rows.take(np.sort(own)))
        return out

    def filtered(self, alpha: np.ndarray, kind: str, large: int, small: int, steps: range, seed: int) -> list[tuple[Batch, Batch, int, int]]:
        """For each step: what the filter keeps of a large generic batch, a uniform part of that batch, its rows and its bytes."""
        out = []
        for t, big in zip(steps, self.uniform(0, "train", large, steps, "big", seed), strict=True):
            kept, sub = chosen(self.weight, alpha, kind, small, big, t, seed)
            out.append((big.take(kept), big.take(sub), len(big), sum(len(p) if isinstance(p, bytes) else 0 for p in big.payloads)))
        return out

    def tally(self, measure: Callable[[object], dict[str, float]], side: int, split: str) -> dict[str, float]:
        """Sums of ``measure`` over all prepared rows."""
        return measure(self.whole(side, split).x)

    def best(self, form: str, score: Callable[[object], np.ndarray], keep: float, least: int) -> np.ndarray:
        """The generic training rows of the highest scores of their ``form`` (main or weight): a share ``keep`` of all, ``least`` at least."""
        rows = self.whole(0)
        n = max(least, round(keep * len(rows)))
        return np.sort(np.argsort(-score(rows.x if form == "main" else rows.xw), kind="stable")[:n])


class ClusterSource(Source):
    """Rows stay in a DataFrame; batches of the sizes asked for come to the driver."""

    def __post_init__(self) -> None:
        """Write the examples once by side and split, so that a step reads its own part by partition pruning."""
        if not self.task.stored:
            self.task = Task(self.task.name, stored_examples(self.task.examples), stored=True)

    def frame(self, side: int, split: str, among: DataFrame | None = None) -> DataFrame:
        df = self.task.frame(side, split)
        return df if among is None else df.join(among, "id", "left_semi")

    def total(self, side: int, split: str, among: DataFrame | None = None) -> int:
        held = self.__dict__.setdefault("_totals", {})
        key = side, split, id(among)
        if key not in held:
            held[key] = self.frame(side, split, among).count()
        return held[key]

    def _dealt(self, side: int, split: str, n: int, steps: range, tag: str, seed: int, among: DataFrame | None = None) -> DataFrame:
        """Rows (step, id, payload) of the steps' batches."""
        parts = slices(self.total(side, split, among), n)

        def place(epoch: Column) -> Column:
            u = u01(F.col("id"), F.concat(F.lit(f"{seed}/{tag}/"), epoch.cast("string")))
            return F.struct((epoch * parts + F.floor(u * parts)).cast("int").alias("step"), u.alias("u"))

        epochs = F.sequence(F.lit(steps.start // parts), F.lit((steps.stop - 1) // parts))
        dealt = self.frame(side, split, among).withColumn("place", F.explode(F.filter(F.transform(epochs, place), lambda p: (p["step"] >= steps.start) & (p["step"] < steps.stop)))).select("place.step", "place.u", "id", "payload")
        rows = dealt.select("step", "id", "payload")
        if self.total(side, split, among) <= n:
            return rows
        first = F.row_number().over(Window.partitionBy("step").orderBy("u", "id"))
        keys = dealt.select("step", "u", "id").withColumn("turn", first).where(F.col("turn") <= n).select("step", "id")
        return rows.join(keys, ["step", "id"], "left_semi")

    def _batches(self, rows: DataFrame, steps: range) -> dict:
        got: dict = {}
        for r in rows.collect():  # as many as the batches asked for
            got.setdefault((r["step"], r["part"]), []).append((r["id"], plain(r["payload"]), r["copies"]))
        out = {}
        for key, held in got.items():
            held = sorted(held, key=lambda r: r[0])
            held = [(i, p) for i, p, copies in held for _ in range(copies)]
            out[key] = self.batch(np.array([h[0] for h in held]), [h[1] for h in held])
        return out

    def uniform(self, side: int, split: str, n: int, steps: range, tag: str, seed: int, among: DataFrame | None = None) -> list[Batch]:
        rows = self._dealt(side, split, n, steps, tag, seed, among).withColumns({"part": F.lit("all"), "copies": F.lit(1)})
        got = self._batches(rows, steps)
        return [got[t, "all"] if (t, "all") in got else self.batch(np.zeros(0, np.int64), []) for t in steps]

    def filtered(self, alpha: np.ndarray, kind: str, large: int, small: int, steps: range, seed: int) -> list[tuple[Batch, Batch, int, int]]:
        """As ``LocalSource.filtered``: one job scores the large batches of all ``steps`` and fetches what is kept."""
        dealt = self._dealt(0, "train", large, steps, "big", seed)
        scored = written(_scored(dealt, self.weight, alpha), "scored")
        by = Window.partitionBy("step")
        if kind == "iid":
            e = F.exp(F.col("score") - F.max("score").over(by))
            sums = scored.withColumn("e", e).withColumn("hi", F.sum("e").over(by.orderBy("id").rowsBetween(Window.unboundedPreceding, 0)))
            sums = sums.withColumns({"lo": (F.col("hi") - F.col("e")) / F.sum("e").over(by), "hi": F.col("hi") / F.sum("e").over(by)})
            draws = dealt.sparkSession.createDataFrame([(t, float(u)) for t in steps for u in hashes(np.arange(small), f"{seed}/{t}/i")], "s int, d double")
            hit = sums.join(F.broadcast(draws), (F.col("step") == F.col("s")) & (F.col("d") >= F.col("lo")) & (F.col("d") < F.col("hi")))
            kept = hit.groupBy("step", "id").agg(F.count("*").cast("int").alias("copies"))
        else:
            step = F.col("step").cast("string")
            noise = F.concat(F.lit(f"{seed}/"), step, F.lit("/g"))
            key = {"gumbel": F.col("score") + gumbel(F.col("id"), noise), "top": F.col("score"), "uniform": -u01(F.col("id"), noise)}[kind]
            kept = scored.withColumn("turn", F.row_number().over(by.orderBy(key.desc(), "id"))).where(F.col("turn") <= small).select("step", "id", F.lit(1).alias("copies"))
        part = u01(F.col("id"), F.concat(F.lit(f"{seed}/"), F.col("step").cast("string"), F.lit("/sub")))
        sub = scored.withColumn("turn", F.row_number().over(by.orderBy(part, "id"))).where(F.col("turn") <= small).select("step", "id", F.lit(1).alias("copies"))
        asked = kept.withColumn("part", F.lit("kept")).unionByName(sub.withColumn("part", F.lit("sub")))
        rows = self.task.frame(0, "train").select("id", "payload").join(F.broadcast(asked), "id")  # 2 * small rows a step
        got = self._batches(rows, steps)
        sizes = {r["step"]: (r["n"], r["bytes"]) for r in scored.groupBy("step").agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes")).collect()}
        return [(got[t, "kept"], got[t, "sub"], *sizes[t]) for t in steps if t in sizes]

    def tally(self, measure: Callable[[object], dict[str, float]], side: int, split: str) -> dict[str, float]:
        main = self.main

        def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[str, float] = {}
            for b in batches:
                for _, rows in stretches(b.column(0)):
                    for k, v in measure(main.prepare(rows)).items():
                        total[k] = total.get(k, 0.0) + v
            yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.string()), pa.array([float(v) for v in total.values()], pa.float64())], ["name", "value"])

        df = self.frame(side, split).select("payload")
        workers_import(df.sparkSession)
        cores = df.sparkSession.sparkContext.defaultParallelism
        if df.rdd.getNumPartitions() < cores:  # a few files of many rows to measure
            df = df.repartition(2 * cores)
        rows = df.mapInArrow(sums, "name string, value double").groupBy("name").agg(F.sum("value").alias("value")).collect()
        if not rows:
            raise ValueError(f"{self.task.name}: no {split} examples on side {side}")
        return {r["name"]: r["value"] for r in rows}

    def best(self, form: str, score: Callable[[object], np.ndarray], keep: float, least: int) -> DataFrame:
        """Ids of the rows above the scores' quantile (from a sketch, so the share is about ``keep``)."""
        model, df = self.main if form == "main" else self.weight, self.frame(0, "train")
        workers_import(df.sparkSession)

        def scores(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for lo, rows in stretches(b.column(1)):
                    got = score(model.prepare(rows))
                    yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, len(rows)), pa.array(np.asarray(got, float))], ["id", "score"])

        scored = written(df.select("id", "payload").mapInArrow(scores, "id long, score double"), "scored")
        n = self.total(0, "train")
        share = min(1.0, max(keep, least / max(n, 1)))
        edge = scored.agg(F.percentile_approx("score", 1 - share, 10_000)).first()[0]
        return written(scored.where(F.col("score") >= edge).select("id"), "best")


class DrawnSource(ClusterSource):
    """Rows stay in a DataFrame; the batches of many steps come packed in two jobs, and are scored and filtered in the driver.

    A run's batches depend on the ids alone, not on parameters, so those of all its steps can be
    drawn before it: one job deals (side, id) for all draws expected, one packs the rows dealt (the
    weight model's form, and pair counts where the main model has them).  The driver holds about
    HELD_BYTES of them, whatever the table's size; what is beyond comes in further pairs of jobs.
    """

    HELD_BYTES = 64 << 20

    def __post_init__(self) -> None:
        super().__post_init__()
        self._rows: dict[tuple, list] = {}  # (side, id): (payload's bytes, the weight model's form, blob)
        self._dealt_ids: dict[tuple, dict[int, np.ndarray]] = {}  # by draw, by step
        self._wanted: dict[tuple, range] = {}
        self._bytes = 0

    def _sums(self) -> dict[tuple, tuple[int, int]]:
        """Rows and bytes by side and split."""
        if "_held_sums" not in self.__dict__:
            got = self.task.examples.groupBy("side", "split").agg(F.count("*").alias("n"), F.sum(payload_bytes(self.task.examples)).alias("b")).collect()
            self._held_sums = {(r["side"], r["split"]): (r["n"], r["b"] or 0) for r in got}
        return self._held_sums

    def total(self, side: int, split: str, among: DataFrame | None = None) -> int:
        return self._sums().get((side, split), (0, 0))[0] if among is None else super().total(side, split, among)

    def _each(self, side: int) -> int:
        n, size = self._sums().get((side, "train"), (0, 0))
        return size // max(n, 1) + 256

    def expect(self, draws: list[Draw]) -> None:
        """Fetch the batches of ``draws``, as far as they fit; what does not is fetched when it is asked for."""
        for d in draws:
            key = d.side, "train", d.n, d.tag, d.seed, None
            self._wanted[key] = range(0, max(d.steps.stop, self._wanted.get(key, range(0)).stop))
        missing = {}
        for d in draws:
            key = d.side, "train", d.n, d.tag, d.seed, None
            steps = [t for t in d.steps if t not in self._dealt_ids.get(key, {})]
            if steps and d.n > 0:
                lo, hi = missing.get(key, (None, (steps[0], steps[-1])))[1]
                missing[key] = (None, (min(lo, steps[0]), max(hi, steps[-1])))
        room, fitting = self.HELD_BYTES - self._bytes, []
        for key, (_, (lo, hi)) in missing.items():
            cost = min((hi + 1 - lo) * key[2], self.total(key[0], "train")) * self._each(key[0])
            if cost <= room:
                room -= cost
                fitting.append((key, range(lo, hi + 1)))
        if fitting:
            self._draw(fitting)

    def _draw(self, draws: list[tuple[tuple, range]], among: DataFrame | None = None) -> None:
        """One job for the ids of all ``draws``, and one for the rows that are not held yet."""

        def places(turn: int, key: tuple, steps: range) -> Column:
            parts = slices(self.total(key[0], key[1], among), key[2])

            def place(epoch: Column) -> Column:
                u = u01(F.col("id"), F.concat(F.lit(f"{key[4]}/{key[3]}/"), epoch.cast("string")))
                return F.struct(F.lit(turn).alias("turn"), (epoch * parts + F.floor(u * parts)).cast("int").alias("step"), u.alias("u"))

            epochs = F.sequence(F.lit(steps.start // parts), F.lit((steps.stop - 1) // parts))
            return F.filter(F.transform(epochs, place), lambda p: (p["step"] >= steps.start) & (p["step"] < steps.stop))

        found = []
        for (side, split) in dict.fromkeys(key[:2] for key, _ in draws):
            own = [places(i, key, steps) for i, (key, steps) in enumerate(draws) if key[:2] == (side, split)]
            found.append(self.frame(side, split, among).select("id", F.explode(F.concat(*own)).alias("p")).select(F.lit(side).alias("side"), F.col("p.turn").alias("turn"), F.col("p.step").alias("step"), F.col("p.u").alias("u"), "id"))
        most = F.create_map(*(F.lit(x) for i, (key, _) in enumerate(draws) for x in (i, key[2])))
        first = F.row_number().over(Window.partitionBy("turn", "step").orderBy("u", "id"))
        keys = reduce(DataFrame.unionByName, found).withColumn("rank", first).where(F.col("rank") <= most[F.col("turn")]).select("turn", "step", "id").toArrow()
        turn, step, ids = (keys[c].to_numpy() for c in ("turn", "step", "id"))
        order = np.lexsort((ids, step, turn))
        turn, step, ids = turn[order], step[order], ids[order]
        wanted: dict[tuple, list] = {}
        for i, (key, steps) in enumerate(draws):
            lo, hi = np.searchsorted(turn, (i, i + 1))
            own_ids, own_steps = ids[lo:hi], step[lo:hi]
            held = self._dealt_ids.setdefault(key, {})
            for t in steps:
                held[t] = np.unique(own_ids[np.searchsorted(own_steps, t) : np.searchsorted(own_steps, t, side="right")])
            wanted.setdefault(key[:2], []).append(np.unique(own_ids))
        for (side, split), parts in wanted.items():
            self._fetch(side, split, np.array([i for i in np.unique(np.concatenate(parts)).tolist() if (side, split, i) not in self._rows], np.int64))

    def _fetch(self, side: int, split: str, ids: np.ndarray) -> None:
        if not len(ids):
            return
        main, weight, spark = self.main, self.weight, self.task.examples.sparkSession

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for lo, rows in stretches(b.column(1)):
                    blobs = main.packed(rows) if hasattr(main, "packed") else [pickle.dumps(r, 5) for r in rows]
                    xw = weight.prepare(rows) if weight is not None else [None] * len(rows)
                    sizes = [len(r) if isinstance(r, bytes) else 0 for r in rows]
                    yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, len(rows)), pa.array(sizes, pa.int64()), pa.array([pickle.dumps(w, 5) for w in xw], pa.binary()), pa.array(blobs, pa.binary())], ["id", "size", "xw", "blob"])

        workers_import(spark)
        asked = spark.createDataFrame(pa.table({"id": pa.array(ids)}))
        got = self.task.frame(side, split).select("id", "payload").join(F.broadcast(asked), "id").mapInArrow(pack, "id long, size long, xw binary, blob binary").toArrow()
        for b in got.to_batches():
            for i, size, xw, blob in zip(*(b.column(c).to_pylist() for c in ("id", "size", "xw", "blob")), strict=True):
                self._rows.setdefault((side, split, i), []).append((size, pickle.loads(xw), blob))  # noqa: S301  packed by this program's tasks
                self._bytes += len(xw) + len(blob) + 256

    def _packed(self, side: int, split: str, ids: np.ndarray) -> PackedBatch:
        rows = [(i, *r) for i in ids.tolist() for r in self._rows[side, split, i]]
        blobs = [r[3] for r in rows]
        xw = None if self.weight is None else np.array([r[2] for r in rows]) if rows else self.weight.prepare([])
        return PackedBatch(self.main, np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.int64), blobs, xw)

    def uniform(self, side: int, split: str, n: int, steps: range, tag: str, seed: int, among: DataFrame | None = None) -> list[PackedBatch]:
        key = side, split, n, tag, seed, among
        out = []
        for t in steps:
            if t not in self._dealt_ids.get(key, {}):
                if self._bytes > self.HELD_BYTES:  # begin anew
                    self._rows.clear()
                    self._dealt_ids.clear()
                    self._bytes = 0
                ahead = max(1, self.HELD_BYTES // (2 * n * self._each(side)))
                stop = max(self._wanted.get(key, range(0)).stop, steps.stop)
                self._draw([(key, range(t, min(stop, t + ahead)))], among)
            out.append(self._packed(side, split, self._dealt_ids[key][t]))
        return out

    def filtered(self, alpha: np.ndarray, kind: str, large: int, small: int, steps: range, seed: int) -> list[tuple[PackedBatch, PackedBatch, int, int]]:
        out = []
        for t, big in zip(steps, self.uniform(0, "train", large, steps, "big", seed), strict=True):
            if len(big):
                kept, sub = chosen(self.weight, alpha, kind, small, big, t, seed)
                out.append((big.take(kept), big.take(sub), len(big), int(big.sizes.sum())))
        return out


def chosen(weight, alpha: np.ndarray, kind: str, small: int, big, t: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of a large batch that the filter keeps at step ``t``, and a uniform part of it."""
    kept = choose(kind, weight.scores(alpha, big.xw), small, hashes(big.ids, f"{seed}/{t}/g"), hashes(np.arange(small), f"{seed}/{t}/i"))
    return np.sort(kept), np.sort(np.argsort(hashes(big.ids, f"{seed}/{t}/sub"), kind="stable")[:small])


def _values(column: pa.Array) -> list:
    if pa.types.is_list(column.type) and pa.types.is_floating(column.type.value_type) and not column.null_count:
        numbers = column.flatten()
        if not numbers.null_count:
            every, ends = numbers.to_numpy().tolist(), np.cumsum(column.value_lengths().to_numpy()).tolist()
            return [every[lo:hi] for lo, hi in zip([0, *ends], ends, strict=False)]
    return column.to_pylist()


def payloads_of(column: pa.Array) -> list:
    """Payloads of an Arrow column, as ``prepare`` takes them; structs go field by field, lists of numbers in one piece."""
    if pa.types.is_struct(column.type) and not column.null_count:
        return list(zip(*(_values(c) for c in column.flatten()), strict=True))
    return [tuple(p.values()) if isinstance(p, dict) else p for p in column.to_pylist()]


def stretches(column: pa.Array) -> Iterator[tuple[int, list]]:
    """(first row, payloads) of stretches of an Arrow column: about STRETCH_BYTES and STRETCH_ROWS at most, a row at least."""
    n = len(column)
    ends = np.cumsum(np.asarray(pc.binary_length(column).fill_null(0), np.int64)) if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else np.zeros(n, np.int64)
    lo = 0
    while lo < n:
        upto = int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + STRETCH_BYTES, side="right"))
        hi = min(max(upto, lo + 1), lo + STRETCH_ROWS, n)
        yield lo, payloads_of(column.slice(lo, hi - lo))
        lo = hi


def _scored(df: DataFrame, weight, alpha: np.ndarray) -> DataFrame:
    """(step, id, score, bytes): map-only, the parameters are broadcast."""
    workers_import(df.sparkSession)
    shared = df.sparkSession.sparkContext.broadcast((weight, alpha))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, a = shared.value
        for b in batches:
            if b.num_rows:
                rows = payloads_of(b.column(2))
                sizes = [len(p) if isinstance(p, bytes) else 0 for p in rows]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.asarray(model.scores(a, model.prepare(rows)), float)), pa.array(sizes, pa.int64())], ["step", "id", "score", "bytes"])

    return df.select("step", "id", "payload").mapInArrow(score, "step int, id long, score double, bytes long")


def source_of(task: Task, main, weight=None, mode: str = "auto") -> Source:
    """``local``, ``cluster``, ``drawn``, or by the size of the payloads: below LOCAL_BYTES the driver holds all rows, else the batches drawn."""
    if mode == "auto":
        mode = "local" if not task.stored and task.size() <= LOCAL_BYTES else "drawn"
    return {"local": LocalSource, "cluster": ClusterSource, "drawn": DrawnSource}[mode](task, main, weight)


def mean_losses(source: Source, thetas: list[np.ndarray], split: str = "test", side: int = 1) -> list[float]:
    """Mean loss under each of ``thetas``, in one pass over the rows."""
    main = source.main
    if not thetas:
        return []

    def measure(x) -> dict[str, float]:
        return {"n": size_of(x)} | {str(i): float(losses.sum()) for i, losses in enumerate(losses_each(main, thetas, x))}

    got = source.tally(measure, side, split)
    return [got[str(i)] / got["n"] if got["n"] else math.nan for i in range(len(thetas))]


def losses_each(main, thetas: list[np.ndarray], x) -> Iterable[np.ndarray]:
    return main.losses_each(thetas, x) if hasattr(main, "losses_each") else (main.losses(t, x) for t in thetas)


def mean_loss(source: Source, theta: np.ndarray, split: str = "test", side: int = 1) -> float:
    return mean_losses(source, [theta], split, side)[0]

"""Best-fit packing of documents into fixed-length sequences by a grouping genetic algorithm.

Pieces are dealt to shards of a bounded size.  A shard begins with best-fit decreasing; where
that is not proven optimal (bins above ceil(total / capacity)), islands evolve populations of
packings: crossover injects whole well-filled bins of one parent into another, drops the bins
that then hold duplicates, and best-fits the displaced documents; after each epoch an island's
elite migrates to the next one.  The poorly filled bins of neighbouring shards are then packed
together once more, level by level, so what shards leave open does not add up.

Defined results: null or empty text has the end id alone; a null id is kept; repeated rows are
packed each on its own; an empty table gives no rows; columns other than those named are not read.
"""

from __future__ import annotations

import random
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import encoded, encoder, lean, workers_import, written

_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, salt long"


def token_pieces(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode, append the end id, and cut what is longer than ``capacity``: one row a piece."""
    end, step = int(end_id).to_bytes(4, "little"), capacity * 4

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = TaskContext.get().partitionId() << 40
        for b in batches:
            rows = []
            for key, own in zip(b.column(0).to_pylist(), encoded(tokenizer, b.column(1).to_pylist()), strict=True):
                ids = own + end
                for i in range(0, len(ids), step):
                    part = ids[i : i + step]
                    rows.append((key, i // step, i // 4, len(part) // 4, zlib.crc32(part), seen))
                    seen += 1
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], [c.split()[0] for c in _PIECES.split(", ")])
        encoder(tokenizer).forget()

    workers_import(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(lean(cut), _PIECES)


# --- one shard --------------------------------------------------------------------------------


class _Room:
    """Open bins by what is left in them; the best fit is the lowest set bit above a size."""

    def __init__(self, capacity: int) -> None:
        self.capacity, self.mask, self.by_left = capacity, 0, {}

    def put(self, bin_no: int, left: int) -> None:
        if left:
            self.by_left.setdefault(left, []).append(bin_no)
            self.mask |= 1 << left

    def take(self, size: int) -> tuple[int, int] | None:
        rest = self.mask >> size
        if not rest:
            return None
        left = size + (rest & -rest).bit_length() - 1
        here = self.by_left[left]
        bin_no = here.pop()
        if not here:
            self.mask ^= 1 << left
        return bin_no, left


def _fit(sizes: list[int], capacity: int, bins: list[list[int]], items: list[int]) -> list[list[int]]:
    """Best-fit ``items``, largest first, into ``bins`` and new ones after them."""
    room = _Room(capacity)
    for no, held in enumerate(bins):
        room.put(no, capacity - sum(sizes[i] for i in held))
    for i in sorted(items, key=lambda i: -sizes[i]):
        got = room.take(sizes[i])
        if got:
            bins[got[0]].append(i)
            room.put(got[0], got[1] - sizes[i])
        else:
            bins.append([i])
            room.put(len(bins) - 1, capacity - sizes[i])
    return bins


def fitness(sizes: list[int], capacity: int, bins: list[list[int]]) -> tuple[int, float]:
    """Fewer bins are better; among equals, unevenly filled ones, which leave room to close one."""
    return -len(bins), sum((sum(sizes[i] for i in held) / capacity) ** 2 for held in bins)


def crossover(sizes: list[int], capacity: int, into: list[list[int]], other: list[list[int]], rng: random.Random) -> list[list[int]]:
    """Whole well-filled bins of ``other`` go in; bins with duplicates go out; the displaced are best-fitted."""
    fill = [sum(sizes[i] for i in held) for held in other]
    ranked = sorted(range(len(other)), key=lambda b: -fill[b])[: max(1, len(other) // 2)]
    injected = [other[b] for b in rng.sample(ranked, max(1, len(ranked) // 2))]
    has = {i for held in injected for i in held}
    kept, displaced = [], []
    for held in into:
        if has.isdisjoint(held):
            kept.append(list(held))
        else:
            displaced.extend(i for i in held if i not in has)
    return _fit(sizes, capacity, [list(h) for h in injected] + kept, displaced)


def mutate(sizes: list[int], capacity: int, bins: list[list[int]], rng: random.Random) -> list[list[int]]:
    """Empty the worst-filled bin and a few random ones; best-fit what they held."""
    order = sorted(range(len(bins)), key=lambda b: sum(sizes[i] for i in bins[b]))
    out = set(order[:1]) | set(rng.sample(range(len(bins)), min(len(bins), 3)))
    return _fit(sizes, capacity, [list(h) for b, h in enumerate(bins) if b not in out], [i for b in out for i in bins[b]])


def _bins(assign: np.ndarray) -> list[list[int]]:
    order = np.argsort(assign, kind="stable")
    cuts = np.flatnonzero(np.diff(assign[order])) + 1
    return [x.tolist() for x in np.split(order, cuts)] if len(assign) else []


def _assign(bins: list[list[int]], n: int) -> np.ndarray:
    out = np.zeros(n, np.int32)
    for no, held in enumerate(bins):
        out[held] = no
    return out


def evolve(sizes: list[int], capacity: int, population: list[list[list[int]]], bound: int, rng: random.Random, generations: int) -> list[list[list[int]]]:
    """Steady-state generations: two parents by tournament, the child replaces the worst if it is better."""
    scored = [(fitness(sizes, capacity, p), p) for p in population]
    for _ in range(generations):
        if -max(s for s, _ in scored)[0] <= bound:
            break
        a, b = (max(rng.sample(scored, 2), key=lambda x: x[0])[1] for _ in range(2))
        child = crossover(sizes, capacity, a, b, rng)
        if rng.random() < 0.5:
            child = mutate(sizes, capacity, child, rng)
        worst = min(range(len(scored)), key=lambda i: scored[i][0])
        got = fitness(sizes, capacity, child)
        if got > scored[worst][0] and all(got != s for s, _ in scored):
            scored[worst] = got, child
    return [p for _, p in sorted(scored, key=lambda x: x[0], reverse=True)]


def first_population(sizes: list[int], capacity: int, rng: random.Random, size: int) -> list[list[list[int]]]:
    """Best-fit decreasing, and best-fit in random orders by blocks."""
    items = list(range(len(sizes)))
    out = [_fit(sizes, capacity, [], items)]
    while len(out) < size:
        head = rng.sample(items, len(items) // 2)
        chosen = set(head)
        out.append(_fit(sizes, capacity, _fit(sizes, capacity, [], head), [i for i in items if i not in chosen]))
    return out


# --- shards, islands, levels --------------------------------------------------------------------

_ORDER = ["length", "doc_id", "piece", "salt"]
_STATE = "shard long, island int, bins int, bound int, score double, sizes binary, population array<binary>"


def _sorted(pdf: pd.DataFrame) -> pd.DataFrame:
    return pdf.sort_values(_ORDER, ascending=[False, True, True, True], kind="stable", ignore_index=True)


def _state(shard: int, island: int, sizes: list[int], bound: int, population: list, capacity: int) -> dict:
    best = fitness(sizes, capacity, population[0])
    return {"shard": shard, "island": island, "bins": -best[0], "bound": bound, "score": best[1], "sizes": np.array(sizes, np.int32).tobytes(), "population": [_assign(p, len(sizes)).tobytes() for p in population]}


def _begin(capacity: int, islands: int, population: int, seed: int):
    def begin(pdf: pd.DataFrame) -> pd.DataFrame:
        shard = int(pdf["shard"].iat[0])
        sizes = _sorted(pdf)["length"].tolist()
        bound = -(-sum(sizes) // capacity)
        best = [_fit(sizes, capacity, [], list(range(len(sizes))))]
        if len(best[0]) <= bound:
            return pd.DataFrame([_state(shard, 0, sizes, bound, best, capacity)])
        return pd.DataFrame([_state(shard, i, sizes, bound, first_population(sizes, capacity, random.Random(f"{seed}/{shard}/{i}"), population), capacity) for i in range(islands)])

    return begin


def _epoch(capacity: int, generations: int, seed: int, epoch: int):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            out = []
            for r in pdf.itertuples(index=False):
                sizes = np.frombuffer(r.sizes, np.int32).tolist()
                people = [_bins(np.frombuffer(x, np.int32)) for x in r.population]
                if r.migrant is not None:
                    people[-1] = _bins(np.frombuffer(r.migrant, np.int32))
                people = evolve(sizes, capacity, people, r.bound, random.Random(f"{seed}/{r.shard}/{r.island}/{epoch}"), generations)
                out.append(_state(r.shard, r.island, sizes, r.bound, people, capacity))
            yield pd.DataFrame(out, columns=[c.split()[0] for c in _STATE.split(", ")])

    return run


def _place(capacity: int, tail: float):
    """Rows with bin and offset; ``open`` marks the worst-filled bins, to be packed again with neighbours."""

    def place(pieces: pd.DataFrame, best: pd.DataFrame) -> pd.DataFrame:
        pdf = _sorted(pieces)
        pdf["bin"] = np.frombuffer(best["best"].iat[0], np.int32)
        pdf["offset"] = pdf.groupby("bin")["length"].cumsum() - pdf["length"]
        fill = pdf.groupby("bin")["length"].sum().sort_values(kind="stable")
        worst = fill[fill <= capacity * (1 - tail)].index[: max(1, len(fill) // 2)]
        pdf["open"] = pdf["bin"].isin(worst)
        return pdf

    return place


def _solve(pieces: DataFrame, capacity: int, islands: int, population: int, epochs: int, generations: int, tail: float, seed: int) -> DataFrame:
    """``pieces`` has a shard; adds bin, offset and open."""
    state = written(pieces.groupBy("shard").applyInPandas(_begin(capacity, islands, population, seed), _STATE), "packings")
    done = [state.where("bins <= bound")]
    left = state.where("bins > bound")
    for epoch in range(epochs):
        if left.isEmpty():
            break
        elite = left.select("shard", ((F.col("island") + 1) % islands).alias("island"), F.element_at("population", 1).alias("migrant"))
        left = written(left.join(elite, ["shard", "island"], "left").mapInPandas(_epoch(capacity, generations, seed, epoch), _STATE), "packings")
    best = done[0].unionByName(left).groupBy("shard").agg(F.max_by(F.element_at("population", 1), F.struct(-F.col("bins"), F.col("score"), -F.col("island"))).alias("best"))
    kinds = f"{_PIECES}, shard long, bin int, offset long, open boolean"
    return pieces.groupBy("shard").cogroup(best.groupBy("shard")).applyInPandas(_place(capacity, tail), kinds)


def pack(pieces: DataFrame, capacity: int = 4096, shard_items: int = 8192, islands: int = 3, population: int = 5, epochs: int = 2, generations: int = 12, tail: float = 0.03, seed: int = 0) -> DataFrame:
    """Give each piece a sequence_id and an offset there, in as few sequences as can be.

    ``pieces`` is what ``token_pieces`` gives.  All rows go to some shard of about
    ``shard_items``; bins filled to 1 - ``tail`` or less (at most half of a shard's) go on to the
    next level, where neighbouring shards are one; ``level`` tells how often a row was packed again.
    """
    rows = written(pieces, "pieces")
    shards = max(1, -(-rows.count() // shard_items))
    level, done = 0, []
    todo = rows.withColumn("shard", F.pmod(F.xxhash64("salt", "doc_id", "piece"), F.lit(shards)).cast("long"))
    while True:
        last = shards == 1
        solved = written(_solve(todo, capacity, islands, population, epochs, generations, tail, seed + level), "packed")
        closed = solved if last else solved.where("not open")
        done.append(closed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.lit(level) * (1 << 56) + F.col("shard") * (1 << 20) + F.col("bin")).alias("sequence_id"), "offset", F.lit(level).alias("level")))
        if last:
            break
        left, before = solved.where("open"), shards
        shards, level = max(1, min(-(-left.count() // shard_items), shards // 2)), level + 1
        todo = left.select(*[c.split()[0] for c in _PIECES.split(", ")], F.floor(F.col("shard") * shards / before).cast("long").alias("shard"))
    out = done[0]
    for df in done[1:]:
        out = out.unionByName(df)
    return out

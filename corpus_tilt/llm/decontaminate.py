"""Benchmark decontamination by pigeonhole edit matching.

Each benchmark item has an error budget k (a share of its length) and is cut into k + 1 pieces:
an occurrence with at most k edits has at least one piece intact.  An automaton of all pieces
finds the exact hits in one pass over a document; the surrounding stretch is then verified with
Myers' bit-parallel distance, the pattern anywhere in the stretch.

Texts are compared lower-cased and with white space runs as one space.  Defined results: null or
empty documents and items match nothing; items shorter than one piece are compared whole and
exactly, as words of their own (no letter or digit beside them); repeated items and documents are
reported each, a null id like others; an empty table gives no rows; columns other than those named
are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, workers_import

_MATCH = "doc_id long, item_id long, distance long, budget long, start long, end long, version long"


def plain(text: str | None) -> str:
    return " ".join((text or "").lower().split())


@dataclass(frozen=True)
class Item:
    item_id: int | None
    text: str
    budget: int
    alone: bool = False  # to stand between word bounds

    def pieces(self) -> list[tuple[int, str]]:
        """Where each of the budget-plus-one pieces begins, and the piece."""
        cuts = [len(self.text) * i // (self.budget + 1) for i in range(self.budget + 2)]
        return [(lo, self.text[lo:hi]) for lo, hi in zip(cuts, cuts[1:], strict=False)]


def best_in(pattern: str, text: str, masks: dict[str, int] | None = None) -> tuple[int, int]:
    """The least edit distance of ``pattern`` to any stretch of ``text``, and where that ends (Myers)."""
    m = len(pattern)
    if masks is None:
        masks = pattern_masks(pattern)
    full, high = (1 << m) - 1, 1 << (m - 1)
    up, down, score = full, 0, m
    best, end = m, 0
    for at, c in enumerate(text, 1):
        eq = masks.get(c, 0)
        x = eq | down
        flat = (((eq & up) + up) ^ up) | eq
        plus = down | ~(flat | up) & full
        minus = up & flat
        if plus & high:
            score += 1
        elif minus & high:
            score -= 1
        plus = plus << 1 & full
        minus = minus << 1 & full
        up = minus | ~(x | plus) & full
        down = plus & x
        if score < best:
            best, end = score, at
    return best, end


def pattern_masks(pattern: str) -> dict[str, int]:
    out: dict[str, int] = {}
    for i, c in enumerate(pattern):
        out[c] = out.get(c, 0) | 1 << i
    return out


class Matcher:
    """The automaton of a block of items."""

    def __init__(self, items: list[Item]) -> None:
        import ahocorasick

        self.items = items
        self.masks = [pattern_masks(i.text) for i in items]
        self.automaton = ahocorasick.Automaton()
        owners: dict[str, list[tuple[int, int]]] = {}
        for no, item in enumerate(items):
            for lo, piece in item.pieces():
                owners.setdefault(piece, []).append((no, lo))
        for piece, own in owners.items():
            self.automaton.add_word(piece, (len(piece), own))
        if owners:
            self.automaton.make_automaton()

    def matches(self, text: str) -> list[tuple[int | None, int, int, int, int]]:
        """(item_id, distance, budget, start, end) of each item in ``text``: its best place."""
        if not self.items or not text:
            return []
        begins: dict[int, set[int]] = {}
        for end, (size, own) in self.automaton.iter(text):
            for no, lo in own:
                begin = end + 1 - size - lo
                if self.items[no].alone and (text[begin - 1 : begin].isalnum() and begin or text[end + 1 : end + 2].isalnum()):
                    continue
                begins.setdefault(no, set()).add(begin)
        out = []
        for no, at in begins.items():
            item, best = self.items[no], None
            k, m, upto = item.budget, len(item.text), -1
            for begin in sorted(at):  # stretches of hits near each other are verified as one
                lo, hi = max(0, begin - k), min(len(text), begin + m + k)
                if hi <= upto:
                    continue
                if best is None or best[0] > 0:
                    hi = max(hi, min(len(text), begin + m + 2 * k))
                    got, end = best_in(item.text, text[lo:hi], self.masks[no])
                    if got <= k and (best is None or got < best[0]):
                        best = (got, lo + end)
                    upto = hi
            if best:
                out.append((item.item_id, best[0], k, max(0, best[1] - m), best[1]))
        return out


def budget_of(length: int, rate: float, least_piece: int) -> int:
    return max(0, min(int(length * rate), length // least_piece - 1))


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", rate: float = 0.08, least_piece: int = 12, block_chars: int = 16_000_000) -> DataFrame:
    """One row for each document and item found in it: distance, budget, the place in the plain text, and the hash of the document's text.

    The benchmark is the stated query set.  It is taken in blocks of at most ``block_chars``
    characters (by running sums over its rows), each broadcast on its own, so its size is bounded.
    """
    spark = docs.sparkSession
    workers_import(spark)
    blocks: list[list[Item]] = [[]]
    size = 0
    for row in benchmark.select(F.col(item_col).cast("long").alias("i"), F.col(item_text).alias("t")).toLocalIterator():
        text = plain(row["t"])
        if not text:
            continue
        if size + len(text) > block_chars and blocks[-1]:
            blocks.append([])
            size = 0
        blocks[-1].append(Item(row["i"], text, budget_of(len(text), rate, least_piece), len(text) < least_piece))
        size += len(text)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(F.col(text_col)).alias("version"))
    out = None
    for items in blocks:
        shared = spark.sparkContext.broadcast(items)

        def search(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(shared.value)
            for b in batches:
                found = [(key, *m, version) for key, text, version in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True) for m in matcher.matches(plain(text))]
                yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in range(7)], [c.split()[0] for c in _MATCH.split(", ")])

        part = rows.mapInArrow(lean(search), _MATCH)
        out = part if out is None else out.unionByName(part)
    return out

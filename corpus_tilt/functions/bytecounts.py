"""Counts of bytes and byte pairs of whole texts: one vectorised pass, map-only."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..sources.scratch import workers_import

_DIGIT = pa.array([f"{i:X}" for i in range(16)])
_BYTE = pa.array([f"{i:02X}" for i in range(256)])


def _raw(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8).astype(np.int64)


def _cells(raw: np.ndarray, contexts: int) -> np.ndarray:
    """The number of each pair: class of the byte before, then the byte."""
    return (raw[:-1] * contexts >> 8) << 8 | raw[1:]


def _pair_names(cells: np.ndarray, contexts: int) -> tuple[pa.Array, pa.Array]:
    return (_DIGIT if contexts == 16 else _BYTE).take(pa.array(cells >> 8)), _BYTE.take(pa.array(cells & 255))


def pair_counts(ex: DataFrame, contexts: int) -> DataFrame:
    """(id, side, split, k, y, n): each text's distinct pairs."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            held, row, size = [], [], 0
            for i, text in enumerate(b.column(3).to_pylist()):
                held.append(np.unique(_cells(_raw(text), contexts), return_counts=True))
                row.append(i)
                size += len(held[-1][0])
                if size > 200_000:
                    yield out(b, row, held)
                    held, row, size = [], [], 0
            if held:
                yield out(b, row, held)

    def out(b: pa.RecordBatch, row: list[int], held: list) -> pa.RecordBatch:
        at = pa.array(np.repeat(row, [len(h[0]) for h in held]))
        k, y = _pair_names(np.concatenate([h[0] for h in held]), contexts)
        return pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at), b.column(2).take(at), k, y, pa.array(np.concatenate([h[1] for h in held]), pa.int64())], ["id", "side", "split", "k", "y", "n"])

    workers_import(ex.sparkSession)
    return ex.select("id", "side", "split", "h").mapInArrow(count, "id long, side int, split string, k string, y string, n long")


def nibble_shares(ex: DataFrame) -> DataFrame:
    """(id, k, share): each text's shares of bytes by high nibble."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                n = np.stack([np.bincount(_raw(t) >> 4, minlength=16) for t in b.column(1).to_pylist()])
                row, k = np.nonzero(n)
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(row)), _DIGIT.take(pa.array(k)), pa.array(n[row, k] / n.sum(axis=1)[row])], ["id", "k", "share"])

    workers_import(ex.sparkSession)
    return ex.select("id", "h").mapInArrow(count, "id long, k string, share double")


def _task_sums(ex: DataFrame, keys: str, cells: int, of, names, schema: str) -> DataFrame:
    """Sums a task over its texts, by the columns ``keys``; what is left to add up is a few rows a task."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple, np.ndarray] = {}
        for b in batches:
            columns = [b.column(i).to_pylist() for i in range(b.num_columns)]
            for *key, text in zip(*columns, strict=True):
                own = total.setdefault(tuple(key), np.zeros(cells, np.int64))
                own += np.bincount(of(_raw(text)), minlength=cells)
        for key, n in total.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([*(pa.array([x] * len(at), pa.int32() if isinstance(x, int) else pa.string()) for x in key), *names(at), pa.array(n[at])], [c.split()[0] for c in schema.split(", ")])

    workers_import(ex.sparkSession)
    return ex.select(*keys.split(), "h").mapInArrow(count, schema)


def pair_totals(ex: DataFrame, contexts: int) -> DataFrame:
    """(side, split, k, y, n), to be added up."""
    return _task_sums(ex, "side split", contexts * 256, lambda raw: _cells(raw, contexts), lambda at: _pair_names(at, contexts), "side int, split string, k string, y string, n long")


def byte_totals(ex: DataFrame) -> DataFrame:
    """(side, b, n), to be added up."""
    return _task_sums(ex, "side", 256, lambda raw: raw, lambda at: (_BYTE.take(pa.array(at)),), "side int, b string, n long")

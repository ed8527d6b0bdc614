"""Hashed word shingles of whole texts and the bands of their minwise sketches, vectorised."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..sources.scratch import workers_import

_U = np.uint64


def _spread(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(33))) * _U(0xFF51AFD7ED558CCD)
        return x ^ (x >> _U(33))


def shingle_set(text: str | None, words: int) -> np.ndarray:
    """Sorted distinct hashes of runs of ``words`` words between single spaces; a shorter text is one run."""
    from xxhash import xxh64_intdigest

    parts = (text or "").split(" ")
    hashes = np.array([xxh64_intdigest(w.encode("utf-8", "surrogatepass"), 7) for w in parts], _U)
    n = max(len(parts) - words + 1, 1)
    run = np.full(n, min(len(parts), words), _U)
    with np.errstate(over="ignore"):
        for i in range(min(words, len(parts))):
            run = run * _U(0x9E3779B97F4A7C15) + hashes[i : i + n]
    return np.unique(_spread(run))


def banded_sets(docs: DataFrame, words: int, bands: int, rows: int, seed: int = 3) -> DataFrame:
    """(doc_id, f1, f2, n, s, keys): a text's set, its size and two fingerprints, and the keys of its bands."""
    rng = np.random.default_rng(seed)
    salt, odd = rng.integers(0, 1 << 63, bands * rows, np.int64).astype(_U), rng.integers(0, 1 << 62, bands * rows, np.int64).astype(_U) * _U(2) + _U(1)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, f1, f2, sets, keys = b.column(0), [], [], [], []
            for text in b.column(1).to_pylist():
                own = shingle_set(text, words)
                least = np.full(bands * rows, 0xFFFFFFFFFFFFFFFF, _U)
                with np.errstate(over="ignore"):
                    for lo in range(0, len(own), 20_000):
                        least = np.minimum(least, _spread((own[lo : lo + 20_000, None] ^ salt) * odd).min(axis=0))
                    key = np.arange(bands, dtype=_U)
                    for column in least.reshape(bands, rows).T:
                        key = _spread(key * _U(0x9E3779B97F4A7C15) + column)
                    f1.append(own.sum(dtype=_U))
                    f2.append(_spread(own ^ _U(0x5A5A)).sum(dtype=_U))
                sets.append(own.view(np.int64))
                keys.append(key.view(np.int64))
            signed = lambda x: pa.array(np.array(x, _U).view(np.int64))
            yield pa.RecordBatch.from_arrays([ids, signed(f1), signed(f2), pa.array([len(s) for s in sets], pa.int64()), pa.array(sets, pa.list_(pa.int64())), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "f1", "f2", "n", "s", "keys"])

    workers_import(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(make, "doc_id long, f1 long, f2 long, n long, s array<long>, keys array<long>")

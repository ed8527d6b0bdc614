"""Word bigram models with modified Kneser-Ney smoothing, counted in Spark over one shared vocabulary.

Vocabulary: the words (of a group, say a language) that are at least a share ``WORD_SHARE`` of all
words of the corpus, so 1 / WORD_SHARE at most by arithmetic; a rarer word is known by its class
(its group and its length in bytes).  Numbers of words and classes have 21 bits, bigrams 42.

Counting: a task keeps sorted distinct keys and their counts, in bounded memory, and sends them on
as packed stretches, one for each cell of the key space; a cell's stretches are merged by one task.
Keys are scrambled by a bijection first, so cells are even whatever the words.  There are as many
cells as the corpus needs for a cell to stay small: what is counted grows with the corpus, and
nothing that does reaches the driver.  There arrive the vocabulary and, for each word in it, sums
over its bigrams (``ModelStats``), both bounded by the vocabulary.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column_slices, lean, written
from .words import mix, text_words

_U = np.uint64
WORD_SHARE = 2.0**-20
ID_BITS = 21
KEY_BITS = 2 * ID_BITS
LENGTHS = 64
_START = LENGTHS - 1  # the class before a text's first word
_KEY_MASK = (1 << KEY_BITS) - 1
_ODD = 0x2545F4914F6D | 1
_ODD_BACK = pow(_ODD, -1, 1 << KEY_BITS)
_HELD = 1_500_000  # distinct keys that a task holds before it sends them on
_CELL_BYTES = 4 << 20  # of text for each cell


# --- keys, counts and packed stretches ------------------------------------------------------------


def scramble(key: np.ndarray) -> np.ndarray:
    """A bijection of KEY_BITS-bit keys that spreads them over the key space."""
    with np.errstate(over="ignore"):
        key = key * _U(_ODD) & _U(_KEY_MASK)
        return (key ^ (key >> _U(ID_BITS))) * _U(_ODD) & _U(_KEY_MASK)


def unscramble(key: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        key = key * _U(_ODD_BACK) & _U(_KEY_MASK)
        return (key ^ (key >> _U(ID_BITS))) * _U(_ODD_BACK) & _U(_KEY_MASK)


def merged(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order, and the sums of their counts."""
    if not len(keys):
        return keys, counts
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    new = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[new], np.add.reduceat(counts[order], new)


def packed(keys: np.ndarray, *columns: np.ndarray) -> bytes:
    """Sorted keys as differences, and further unsigned columns, byte plane by byte plane, compressed."""
    steps = np.diff(keys, prepend=_U(0))
    planes = [steps.view(np.uint8).reshape(-1, 8).T.tobytes()]
    planes += [c.view(np.uint8).reshape(len(c), -1).T.tobytes() for c in columns]
    return pa.compress(b"".join(planes), codec="zstd", asbytes=True)


def unpacked(n: int, blob: bytes, *kinds: str) -> list[np.ndarray]:
    widths = [8, *(np.dtype(k).itemsize for k in kinds)]
    raw = np.frombuffer(pa.decompress(blob, decompressed_size=n * sum(widths), codec="zstd", asbytes=True), np.uint8)
    out, at = [], 0
    for width, kind in zip(widths, ("<u8", *kinds), strict=True):
        out.append(np.ascontiguousarray(raw[at : at + n * width].reshape(width, n).T).view(kind).ravel())
        at += n * width
    out[0] = np.cumsum(out[0], dtype=_U)
    return out


def cell_of(keys: np.ndarray, cells: int, bits: int) -> np.ndarray:
    """The cell of each key of ``bits`` bits: even ranges of the key space, in order."""
    top = keys >> _U(max(bits - 32, 0))
    return (top * _U(cells) >> _U(min(bits, 32))).astype(np.int64)


_STRETCH = "cell long, n long, blob binary"


def _stretch_rows(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate((pa.int64(), pa.int64(), pa.binary()))], ["cell", "n", "blob"])


class Counter:
    """Counts of keys in bounded memory; ``rows`` gives packed stretches by cell."""

    def __init__(self, cells: int, bits: int) -> None:
        self.cells, self.bits, self.parts, self.size = cells, bits, [], 0

    def add(self, keys: np.ndarray, counts: np.ndarray | None = None) -> None:
        if counts is None:
            keys, counts = np.unique(keys, return_counts=True)
        self.parts.append((keys, counts.astype(np.uint64)))
        self.size += len(keys)

    def full(self) -> bool:
        if self.size > _HELD:
            self._merge()
        return self.size > _HELD // 2

    def _merge(self) -> None:
        if len(self.parts) > 1:
            self.parts = [merged(np.concatenate([p[0] for p in self.parts]), np.concatenate([p[1] for p in self.parts]))]
            self.size = len(self.parts[0][0])

    def rows(self) -> list[tuple[int, int, bytes]]:
        self._merge()
        if not self.size:
            return []
        keys, counts = self.parts[0]
        self.parts, self.size = [], 0
        cell = cell_of(keys, self.cells, self.bits)
        cuts = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(keys)]
        return [(int(cell[lo]), hi - lo, packed(keys[lo:hi], counts[lo:hi])) for lo, hi in zip(cuts, cuts[1:], strict=False)]


def by_cell(batches: Iterator[pa.RecordBatch], column: str = "cell") -> Iterator[tuple[int, list[pa.RecordBatch]]]:
    """The rows of each cell, of input sorted by it."""
    held: list[pa.RecordBatch] = []
    now = None
    for b in batches:
        of = b.column(b.schema.get_field_index(column)).to_numpy()
        cuts = [0, *(np.flatnonzero(np.diff(of)) + 1).tolist(), len(of)]
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            if lo == hi:
                continue
            if of[lo] != now and held:
                yield now, held
                held = []
            now = int(of[lo])
            held.append(b.slice(lo, hi - lo))
    if held:
        yield now, held


def _merge_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One stretch a cell."""
    for cell, parts in by_cell(batches):
        keys, counts = np.zeros(0, _U), np.zeros(0, np.uint64)
        for b in parts:  # a few at a time, so that a cell is held about twice
            got = [unpacked(n, blob, "<u8") for n, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
            keys, counts = merged(np.concatenate([keys, *(g[0] for g in got)]), np.concatenate([counts, *(g[1] for g in got)]))
        yield _stretch_rows([(cell, len(keys), packed(keys, counts.astype(np.uint64)))])


def counted(stretches: DataFrame, name: str) -> DataFrame:
    """Stretches (cell, n, blob) merged to one a cell, written."""
    return written(stretches.repartition(F.col("cell")).sortWithinPartitions("cell").mapInArrow(lean(_merge_cells), _STRETCH), name)


def cells_for(texts: DataFrame) -> int:
    """How many cells the texts' total length asks for."""
    total = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(1, -(-total // _CELL_BYTES))


# --- vocabulary ------------------------------------------------------------------------------------


def group_codes(groups: list[str | None]) -> np.ndarray:
    """14 bits for each group (a language, say), by a hash of its name."""
    from xxhash import xxh64_intdigest as digest

    known = {g: digest("" if g is None else f"={g}".encode("utf-8", "surrogatepass"), 3) & 0x3FFF for g in set(groups)}
    return np.array([known[g] for g in groups], _U)


@dataclass
class Tokens:
    """The words of some texts: hashes with their group, classes, places, and where texts begin."""

    names: np.ndarray
    classes: np.ndarray
    places: np.ndarray
    cuts: np.ndarray
    data: bytes

    @classmethod
    def of(cls, texts: list[str | None], groups: list[str | None]) -> Tokens:
        hashes, places, cuts, data = text_words(texts)
        code = np.repeat(group_codes(groups), np.diff(cuts)) if len(texts) else np.zeros(0, _U)
        with np.errstate(over="ignore"):
            names = mix(hashes + code * _U(0x9E3779B97F4A7C15))
        length = np.minimum(places[1] - places[0], _START - 1).astype(_U)
        return cls(names, code * _U(LENGTHS) + length, places, cuts, data)


_CLASS_CELL, _PAIR_CELL = -1, -2


def _word_counter(cells: int):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, classes, pairs = Counter(cells, 64), Counter(1, 64), np.zeros(1 << 16, np.int64)
        for b in batches:
            groups = b.column(1).to_pylist()
            for lo, hi, texts in column_slices(b.column(0)):
                t = Tokens.of(texts, groups[lo:hi])
                words.add(t.names)
                classes.add(t.classes)
                classes.add(np.unique(group_codes(groups[lo:hi])) * _U(LENGTHS) + _U(_START), np.zeros(len(set(group_codes(groups[lo:hi]).tolist())), np.uint64))
                pairs += np.bincount(byte_pairs(t.data), minlength=1 << 16)
                if words.full():
                    yield _stretch_rows(words.rows())
        rest = words.rows() + [(_CLASS_CELL, n, blob) for _, n, blob in classes.rows()]
        if len(at := np.flatnonzero(pairs)):
            rest.append((_PAIR_CELL, len(at), packed(at.astype(_U), pairs[at].astype(_U))))
        if rest:
            yield _stretch_rows(rest)

    return count


def byte_pairs(data: bytes) -> np.ndarray:
    """The number of each pair (byte before, byte), white space as one byte; the first follows a space."""
    raw = np.frombuffer(data + b" ", np.uint8)
    raw = np.where(_WHITE[raw], np.uint8(32), raw).astype(np.int64)
    return np.concatenate([[32], raw[:-1]]) << 8 | raw


_WHITE = np.zeros(256, bool)
_WHITE[[9, 10, 11, 12, 13, 32]] = True


@dataclass
class Vocabulary:
    """Sorted hashes of the words, then the sorted classes; ``spelling``: log-probability of a byte after another."""

    names: np.ndarray
    classes: np.ndarray
    tokens: int
    spelling: np.ndarray

    @property
    def size(self) -> int:
        return len(self.names) + len(self.classes)

    def ids(self, t: Tokens) -> tuple[np.ndarray, np.ndarray]:
        """The number of each token (word or class), and whether it is a word."""
        at = np.minimum(np.searchsorted(self.names, t.names), max(len(self.names) - 1, 0))
        word = self.names[at] == t.names if len(self.names) else np.zeros(len(t.names), bool)
        return np.where(word, at, len(self.names) + np.searchsorted(self.classes, t.classes)).astype(_U), word

    def bigrams(self, t: Tokens) -> tuple[np.ndarray, np.ndarray]:
        """The key of each token with the one before it in its text, and whether the token is a word."""
        ids, word = self.ids(t)
        before = np.concatenate([ids[:1], ids[:-1]])
        first = np.unique(t.cuts[:-1][np.diff(t.cuts) > 0])
        before[first] = len(self.names) + np.searchsorted(self.classes, t.classes[first] // _U(LENGTHS) * _U(LENGTHS) + _U(_START)).astype(_U)
        return before << _U(ID_BITS) | ids, word

    def spelled(self, t: Tokens) -> np.ndarray:
        """Log-probability of each token's bytes and the space after it, byte by byte."""
        logs = np.concatenate([[0.0], np.cumsum(self.spelling[byte_pairs(t.data)], dtype=np.float64)])
        return logs[t.places[1] + 1] - logs[t.places[0]]


def vocabulary(texts: DataFrame, cells: int) -> Vocabulary:
    """The words of at least WORD_SHARE of all in ``texts`` (text, grp): 2^20 at most reach the driver."""
    rows = counted(texts.select("text", "grp").mapInArrow(lean(_word_counter(cells)), _STRETCH), "words")
    small = {r["cell"]: unpacked(r["n"], bytes(r["blob"]), "<u8") for r in rows.where("cell < 0").collect()}
    classes, n = small.get(_CLASS_CELL, [np.zeros(0, _U), np.zeros(0, np.uint64)])
    tokens = int(rows.where("cell >= 0").mapInArrow(lean(_totals), "n long").agg(F.sum("n")).first()[0] or 0)
    least = max(1, tokens * WORD_SHARE)

    def often(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for size, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                keys, counts = unpacked(size, blob, "<u8")
                yield pa.RecordBatch.from_arrays([pa.array(keys[counts >= least].view(np.int64))], ["name"])

    names = np.sort(rows.where("cell >= 0").mapInArrow(lean(often), "name long").toArrow()["name"].to_numpy().view(_U))
    pairs = np.full(1 << 16, 0.5)
    at, times = small.get(_PAIR_CELL, [np.zeros(0, _U), np.zeros(0, np.uint64)])
    pairs[at.astype(np.int64)] += times
    square = pairs.reshape(256, 256)
    return Vocabulary(names, classes, tokens, np.log(square / square.sum(axis=1, keepdims=True)).astype(np.float32).ravel())


def _totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        sums = [int(unpacked(n, blob, "<u8")[1].sum(dtype=np.int64)) for n, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array(sums, pa.int64())], ["n"])


# --- smoothing -------------------------------------------------------------------------------------


_SUMS = "id long, total long, n1 long, n2 long, n3 long, follows long"


def sums_of(keys: np.ndarray, counts: np.ndarray) -> list[np.ndarray]:
    """Rows (id, total, n1, n2, n3, follows) of distinct bigrams (not scrambled), and one of id -1: how many have counts one to four."""
    first, second = (keys >> _U(ID_BITS)).astype(np.int64), (keys & _U((1 << ID_BITS) - 1)).astype(np.int64)
    a, at = np.unique(first, return_inverse=True)
    by = [np.bincount(at, w, len(a)).astype(np.int64) for w in (counts, counts == 1, counts == 2, counts >= 3)]
    b, follows = np.unique(second, return_counts=True)
    kinds = [int((counts == k).sum()) for k in (1, 2, 3, 4)]
    zeros = np.zeros(len(b), np.int64)
    return [np.concatenate([a, b, [-1]]), *(np.concatenate([x, zeros, [k]]) for x, k in zip(by, kinds, strict=True)), np.concatenate([np.zeros(len(a), np.int64), follows, [0]])]


def discounts(n1: int, n2: int, n3: int, n4: int) -> np.ndarray:
    """What is taken off counts of none, one, two, and more; a half where counts are missing."""
    if not (n1 and n2 and n3 and n4):
        return np.array([0, 0.5, 0.5, 0.5])
    y = n1 / (n1 + 2 * n2)
    return np.clip(np.array([0, 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3]), 0, [0, 0.99, 1.99, 2.99])


@dataclass
class ModelStats:
    """By token: total of its bigrams, the share that goes to the lower order, and its probability there."""

    total: np.ndarray
    spare: np.ndarray
    lower: np.ndarray
    taken: np.ndarray

    @classmethod
    def of(cls, sums: pa.Table, size: int) -> ModelStats:
        id_, *columns = (sums[c].to_numpy() for c in ("id", "total", "n1", "n2", "n3", "follows"))
        own = id_ >= 0
        total, n1, n2, n3, follows = (np.bincount(id_[own], c[own], size) for c in columns)
        kinds = [int(c[~own].sum()) for c in columns[:4]]
        taken = discounts(*kinds)
        spare = np.where(total > 0, (taken[1] * n1 + taken[2] * n2 + taken[3] * n3) / np.maximum(total, 1), 1.0)
        cut = discounts(*(int((follows == k).sum()) for k in (1, 2, 3, 4)))[np.minimum(follows, 3).astype(int)]
        types = max(follows.sum(), 1)
        lower = np.maximum(follows - cut, 0) / types + (cut.sum() / types if follows.any() else 1.0) / max(size, 1)
        return cls(total, spare, lower, taken)

    def probability(self, keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Of the second token of each bigram after the first, given the bigram's count."""
        first, second = (keys >> _U(ID_BITS)).astype(np.int64), (keys & _U((1 << ID_BITS) - 1)).astype(np.int64)
        own = np.maximum(counts - self.taken[np.minimum(counts, 3).astype(int)], 0) / np.maximum(self.total[first], 1)
        return own + self.spare[first] * self.lower[second]


def bigram_counter(shared, cells: int) -> Callable:
    """Stretches of scrambled bigrams and their counts, of rows (text, grp)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, total = shared.value, Counter(cells, KEY_BITS)
        for b in batches:
            groups = b.column(1).to_pylist()
            for lo, hi, texts in column_slices(b.column(0)):
                total.add(scramble(known.bigrams(Tokens.of(texts, groups[lo:hi]))[0]))
                if total.full():
                    yield _stretch_rows(total.rows())
        if rows := total.rows():
            yield _stretch_rows(rows)

    return count


def stretch_sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``sums_of`` the merged stretches of bigrams."""
    for b in batches:
        for n, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
            keys, counts = unpacked(n, blob, "<u8")
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in sums_of(unscramble(keys), counts.astype(np.int64))], [c.split()[0] for c in _SUMS.split(", ")])


def model_stats(sums: DataFrame, size: int) -> ModelStats:
    """Sums by token of rows from ``sums_of``: as many rows as the vocabulary has reach the driver."""
    return ModelStats.of(sums.groupBy("id").agg(*(F.sum(c).alias(c) for c in ("total", "n1", "n2", "n3", "follows"))).toArrow(), size)

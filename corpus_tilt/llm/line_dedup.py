"""Line deduplication by a segment-partition edit join.

Lines of the corpus are linked when they are equal or, from ``near_from`` characters on, within
``edits`` edits.  A line is cut into edits + 1 even segments: a line within that distance holds at
least one of them, shifted by no more than the edits on either side.  An index of (length, segment
number, segment) is probed with the substrings that can align for each admissible length, and what
meets is verified with a banded bit-parallel distance.  Classes are connected components; of a
class that at least ``min_docs`` documents have, its first line in (doc_id, line) order stays; of
any other, the first in each document.

Any edits + 1 disjoint stretches of a line would do as segments.  A key that very many lines meet
under (a common beginning, say) is therefore never a meeting: its lines meet again under the key
together with edits + 1 stretches of the segment farthest from it, and once more where such a key
is common too.  Which keys are divided is planned on a share of the lines; it decides where lines
meet, not which.

Lines are known by 128-bit hashes; texts are fetched for lines that meet another alone.

Defined results: lines without a word are neither linked nor removed; null and empty texts have
none; documents with a null id lose nothing; rows that repeat both id and text are one document,
so the first line of a class stays in each of them, while rows of one id with other texts are
documents of their own; ties go to the least (doc_id, hash of the text, line); an empty table gives
no rows; other columns are not read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import HOT_SHARE, SPACES, column_slices, fresh, join_hot, lean, workers_import, written
from .components import components
from .near_dedup import _group_cuts, by_group
from .words import mix


def edits_within(a: str, b: str, most: int) -> bool:
    """Is the edit distance at most ``most``?  Common ends are cut off, the rest is banded and bit-parallel.

    For each number of edits, the bits of an integer are the diagonals of the band that can be
    reached with no more (the automaton of Wu and Manber, held to 2 * most + 1 diagonals).
    """
    if len(a) < len(b):
        a, b = b, a
    if len(a) - len(b) > most:
        return False
    lo = 0
    while lo < len(b) and a[lo] == b[lo]:
        lo += 1
    hi = 0
    while hi < len(b) - lo and a[-1 - hi] == b[-1 - hi]:
        hi += 1
    a, b = a[lo : len(a) - hi], b[lo : len(b) - hi]
    if len(a) <= most:
        return True
    where: dict[str, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i + most  # bit i + most: so that the band's lowest diagonal has bit 0
    band = (1 << 2 * most + 1) - 1
    reach = [((1 << d + 1) - 1) << most & band for d in range(most + 1)]
    for j, c in enumerate(b):
        same = where.get(c, 0) >> j & band
        last = reach[0]
        reach[0] = last & same
        for d in range(1, most + 1):
            now = reach[d]
            reach[d] = (now & same | last | last >> 1 | reach[d - 1] << 1) & band
            last = now
        if not reach[most]:
            return False
    return bool(reach[most] >> len(a) - len(b) + most & 1)


def segments(length: int, edits: int) -> list[tuple[int, int]]:
    """Where each of the edits-plus-one segments of a line begins, and its size: even, the longer ones last."""
    n, out, at = edits + 1, [], 0
    for i in range(n):
        size = length // n + (i >= n - length % n)
        out.append((at, size))
        at += size
    return out


def probes(length: int, edits: int, near_from: int) -> list[tuple[int, int, int, int]]:
    """(indexed length, segment number, start, size) of the substrings to probe for a line of ``length``."""
    out = []
    for other in range(max(near_from, length - edits), length + 1):
        more = length - other
        for i, (at, size) in enumerate(segments(other, edits)):
            lo = max(at - i, at + more - (edits - i), 0)
            hi = min(at + i, at + more + (edits - i), length - size)
            out += [(other, i, start, size) for start in range(lo, hi + 1) if more or start != at]
    return out


def has_word(line: Column) -> Column:
    return F.length(F.btrim(line, F.lit(SPACES))) > 0


def stretches(length: int, taken: tuple, edits: int) -> list[tuple[int, int]]:
    """edits + 1 disjoint stretches (begin, size) of a line: of the whole segment that is farthest from those ``taken``; none if there is none."""
    whole = [(lo, size) for lo, size in segments(length, edits) if all(lo + size <= at or at + n <= lo for at, n in taken)]
    if not whole:
        return []
    lo, size = max(whole, key=lambda p: (min(abs(p[0] - at) for at, _ in taken), p[0]))
    return [(lo + at, n) for at, n in segments(size, edits)] if size > edits else []


#: How many stretches a key may be made of.
_DEEP = 3


class _Signer:
    """Keys of lines; ``hot`` are keys that are divided."""

    def __init__(self, edits: int, near_from: int, hot: np.ndarray) -> None:
        from xxhash import xxh64_intdigest

        self.edits, self.near_from, self.digest = edits, near_from, xxh64_intdigest
        self.hot = set(hot.tolist())
        self.plans: dict[int, tuple[list, list]] = {}
        self.below: dict[tuple, list] = {}

    def _divide(self, line: str, key: int, indexed: bool, length: int, taken: tuple) -> Iterator[tuple[int, bool, bool]]:
        """The keys beside a hot one: of the line's own stretches, and of those that lines of ``length`` may share with it."""
        if (length, taken) not in self.below:
            self.below[length, taken] = stretches(length, taken, self.edits)
        parts = self.below[length, taken]
        if not parts:
            yield self.digest(b"the rest", key), indexed, True
        for i, (at, size) in enumerate(parts):
            for start in range(max(at - self.edits, 0), min(at + self.edits, len(line) - size) + 1):
                own = indexed and start == at
                below = self.digest(line[start : start + size].encode("utf-8", "surrogatepass"), key + i + 1 & 0xFFFFFFFFFFFFFFFF)
                last = len(taken) + 1 == _DEEP
                if not last and below in self.hot:
                    yield from self._divide(line, below, own, length, (*taken, (at, size)))
                else:
                    yield below, own, last

    def keys(self, line: str) -> dict[int, tuple[bool, bool]]:
        """Keys and, for each, whether it is one of the line's own segments, and whether it cannot be divided further."""
        n = len(line)
        if n not in self.plans:
            own = [(n, i, at, at, size) for i, (at, size) in enumerate(segments(n, self.edits))]
            starts = {length: segments(length, self.edits) for length in range(max(n - self.edits, 0), n + 1)}
            self.plans[n] = own, [(length, i, starts[length][i][0], start, size) for length, i, start, size in probes(n, self.edits, self.near_from)]
        out: dict[int, tuple[bool, bool]] = {}
        for no, plan in enumerate(self.plans[n]):
            for length, i, at, start, size in plan:
                key = self.digest(line[start : start + size].encode("utf-8", "surrogatepass"), length << 8 | i)
                if key not in self.hot:
                    out.setdefault(key, (not no, False))
                    continue
                for below, own, last in self._divide(line, key, not no, length, ((at, size),)):
                    out[below] = own or out.get(below, (False,))[0], last
        return out


def _sign(edits: int, near_from: int, shared, planning: bool = False):
    """(key, line, indexed) of the lines of texts; when planning, of keys that can be divided alone."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer, seen = _Signer(edits, near_from, shared.value), set()
        digest = signer.digest
        keys: list[int] = []
        lines: list[int] = []
        index: list[bool] = []

        def batch() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(np.array(keys, np.uint64).view(np.int64)), pa.array(np.array(lines, np.uint64).view(np.int64)), pa.array(index, pa.bool_())], ["key", "line", "indexed"])
            for held in (keys, lines, index):
                held.clear()
            return out

        for b in batches:
            for text in (t for _, _, some in column_slices(b.column(0)) for t in some):
                for line in (text or "").split("\n"):
                    if len(line) < near_from or not line.strip(SPACES):
                        continue
                    own = digest(line.encode("utf-8", "surrogatepass"), 42)
                    if own in seen:
                        continue
                    seen.add(own)
                    for key, (indexed, last) in signer.keys(line).items():
                        if not (planning and last):
                            keys.append(key)
                            lines.append(own)
                            index.append(indexed)
                    if len(keys) > 200_000:
                        yield batch()
            if len(seen) > 300_000:
                seen.clear()
        if keys:
            yield batch()

    return sign


_SIGNED = "key long, line long, indexed boolean"


def _long_lines(texts: DataFrame, near_from: int) -> DataFrame:
    return texts.select(F.explode(F.split("text", "\n")).alias("text")).where((F.length("text") >= near_from) & has_word(F.col("text")))


def hot_keys(texts: DataFrame, edits: int, near_from: int, many: int, every: int) -> np.ndarray:
    """Keys under which about ``many`` lines or more would meet, told from one line in ``every``, level by level.

    A key has to be one in 100,000 of its level's as well, so no more than that reach the driver at once.
    """
    sc = texts.sparkSession.sparkContext
    some = written(_long_lines(texts, near_from).where(F.pmod(F.xxhash64("text"), F.lit(every)) == 0).distinct(), "plan")
    found = np.zeros(0, np.uint64)
    for _ in range(1, _DEEP):
        signed = some.mapInArrow(lean(_sign(edits, near_from, sc.broadcast(found), True)), _SIGNED)
        counts = written(signed.groupBy("key").agg(F.count_distinct("line").alias("n")).where(F.col("n") >= max(many // every, 2)), "keys")
        least = (counts.agg(F.sum("n")).first()[0] or 0) // 100_000
        more = counts.where(F.col("n") >= least).select("key").toArrow()["key"].to_numpy().view(np.uint64)
        if not len(more):
            break
        found = np.union1d(found, more)
    return found


def _meetings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Groups of lines that meet under a key; a group is known by a fingerprint of its lines, so equal groups fall together."""
    for b in by_group(batches):
        key, line, indexed = b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy(zero_copy_only=False)
        at = np.array([lo for lo, _ in _group_cuts(key)])
        good = (np.minimum.reduceat(line, at) != np.maximum.reduceat(line, at)) & np.maximum.reduceat(indexed.astype(np.int8), at).astype(bool)
        rows = np.repeat(good, np.diff(np.append(at, len(key))))
        key, line = key[rows], line[rows]
        if not len(key):
            continue
        order = np.lexsort((line, key))
        key, line = key[order], line[order]
        new = np.concatenate([[True], (np.diff(key) != 0) | (np.diff(line) != 0)])
        key, line = key[new], line[new]
        cuts = _group_cuts(key)
        with np.errstate(over="ignore"):
            name = np.add.reduceat(mix(line.view(np.uint64)), [lo for lo, _ in cuts], dtype=np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(name, [hi - lo for lo, hi in cuts])), pa.array(line)], ["meeting", "line"])


def _letter_counts(texts: list[str]) -> np.ndarray:
    """Counts by 32 classes of letters, modulo 256: differences of near texts are small and so exact."""
    out = np.zeros((len(texts), 32), np.int8)
    for i, t in enumerate(texts):
        out[i] = np.bincount(np.frombuffer(t.encode("utf-32-le", "surrogatepass"), "<u4") & 31, minlength=32).astype(np.int8)
    return out


def _verifier(edits: int):
    """Links (a, b) of lines that join each group's, by distances of those that letter counts do not rule out; input (meeting, line, more, text)."""

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_group(batches):
            found = []
            for lo, hi in _group_cuts(b.column(0).to_numpy()):
                lines = list(zip(b.column(1).slice(lo, hi - lo).to_pylist(), b.column(2).slice(lo, hi - lo).to_pylist(), strict=True))
                texts = b.column(3).slice(lo, hi - lo).to_pylist()
                if hi - lo == 2:
                    if edits_within(*texts, edits):
                        found.append((*lines[0], *lines[1]))
                    continue
                letters, top, classes = _letter_counts(texts), np.arange(hi - lo), hi - lo
                for i in range(hi - lo - 1):
                    near = np.flatnonzero((np.abs(letters[i + 1 :] - letters[i]).sum(axis=1, dtype=np.int16) <= 2 * edits) & (top[i + 1 :] != top[i])) + i + 1
                    for j in near.tolist():
                        if top[i] != top[j] and edits_within(texts[i], texts[j], edits):
                            found.append((*lines[i], *lines[j]))
                            top[top == top[j]] = top[i]
                            classes -= 1
                    if classes == 1:
                        break
            yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in range(4)], ["a1", "a2", "b1", "b2"])

    return verify


#: Spark chains hashes: the second one begins with the hash of this number.
_SECOND = 0x5BD1E995


def line_id(line: Column) -> Column:
    """A 128-bit hash of a line."""
    return F.struct(F.xxhash64(line).alias("x"), F.xxhash64(F.lit(_SECOND).cast("long"), line).alias("y"))


class HashBitmap:
    """Which hashes may be among some: a bit for each value of their first ``bits`` bits, 2^29 bits at most.

    It is put together from sections that tasks pack, so 64 MB is all that ever reaches the driver;
    the more hashes there are beyond that, the more others pass.
    """

    def __init__(self, hashes: DataFrame, column: str, count: int) -> None:
        self.bits = min(29, max(16, (32 * count).bit_length()))
        place = F.shiftrightunsigned(F.col(column), 64 - self.bits)
        rows = hashes.select(F.shiftright(place, 16).cast("long").alias("section"), place.bitwiseAND(0xFFFF).cast("int").alias("bit"))
        self.data = bytearray(1 << self.bits - 3)
        for r in rows.repartition(F.col("section")).sortWithinPartitions("section").mapInArrow(lean(_pack_sections), "section long, packed binary").collect():
            self.data[r["section"] << 13 : (r["section"] << 13) + 8192] = r["packed"]

    def may_have(self, value: int) -> int:
        at = value >> 64 - self.bits
        return self.data[at >> 3] >> (at & 7) & 1


def _pack_sections(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in by_group(batches):
        section, bit = b.column(0).to_numpy(), b.column(1).to_numpy()
        cuts = _group_cuts(section)
        packed = []
        for lo, hi in cuts:
            bits = np.zeros(1 << 16, np.uint8)
            bits[bit[lo:hi]] = 1
            packed.append(np.packbits(bits, bitorder="little").tobytes())
        yield pa.RecordBatch.from_arrays([pa.array([section[lo] for lo, _ in cuts], pa.int64()), pa.array(packed, pa.binary())], ["section", "packed"])


def _distinct_lines(near_from: int, shared):
    """(64-bit hash, 128-bit hash, line) of the long lines of texts that may be asked for: of equal lines of a task, one."""

    def lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest as digest

        second, seen, asked = digest(_SECOND.to_bytes(8, "little"), 42), set(), shared.value
        for b in batches:
            out = []
            for text in (t for _, _, some in column_slices(b.column(0)) for t in some):
                for line in (text or "").split("\n"):
                    if len(line) < near_from:
                        continue
                    raw = line.encode("utf-8", "surrogatepass")
                    own = digest(raw, 42)
                    if asked.may_have(own) and own not in seen and line.strip(SPACES):
                        seen.add(own)
                        out.append((own, digest(raw, second), raw))
            if len(seen) > 300_000:
                seen.clear()
            x, y = (pa.array(np.array([o[i] for o in out], np.uint64).view(np.int64)) for i in (0, 1))
            yield pa.RecordBatch.from_arrays([x, x, y, pa.array([o[2] for o in out], pa.binary()).cast(pa.string())], ["line", "x", "y", "text"])

    return lines


def near_line_classes(texts: DataFrame, edits: int, near_from: int, many: int, every: int) -> DataFrame:
    """(id, component) of the lines, by ``line_id``, that are within ``edits`` of another."""
    hot = texts.sparkSession.sparkContext.broadcast(hot_keys(texts, edits, near_from, many, every))
    signed = texts.select("text").mapInArrow(lean(_sign(edits, near_from, hot)), _SIGNED)
    met = signed.repartition(F.col("key")).sortWithinPartitions("key").mapInArrow(lean(_meetings), "meeting long, line long")
    met = written(met.distinct(), "meetings")
    asked = written(met.select("line").distinct(), "asked")
    shared = texts.sparkSession.sparkContext.broadcast(HashBitmap(asked, "line", asked.count()))
    line = texts.select("text").mapInArrow(lean(_distinct_lines(near_from, shared)), "line long, x long, y long, text string")
    own = written(line.join(asked.hint("merge"), "line", "left_semi").dropDuplicates(["line", "x", "y"]), "lines")
    rows = met.join(own, "line").select("meeting", "x", "y", "text")
    links = rows.repartition(F.col("meeting")).sortWithinPartitions("meeting").mapInArrow(lean(_verifier(edits)), "a1 long, a2 long, b1 long, b2 long")
    node = lambda side: F.struct(F.col(f"{side}1").alias("x"), F.col(f"{side}2").alias("y")).alias(side)
    return written(components(links.select(node("a"), node("b"))), "classes")


def line_removals(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", edits: int = 2, near_from: int = 30, min_docs: int = 2, many: int = 512, every: int = 64) -> DataFrame:
    """One row a document (doc_id, version): n_lines (with a word), n_exact and n_near removed, and ``removed``, their numbers.

    ``version`` is the 64-bit hash of the text.  ``many``: keys that about so many lines meet
    under are divided, as told from one line in ``every``.
    """
    workers_import(docs.sparkSession)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).where("doc_id is not null")
    classes = near_line_classes(texts, edits, near_from, many, every)
    cut = texts.select("doc_id", F.xxhash64("text").alias("version"), F.posexplode(F.split("text", "\n")).alias("line_no", "line"))
    worded = has_word(F.col("line"))  # a text's first line is there in any case, to count rows by
    known_by = F.when(worded, line_id(F.col("line"))).otherwise(F.struct(F.xxhash64("doc_id", "version").alias("x"), F.col("version").alias("y")))
    places = written(cut.where(worded | (F.col("line_no") == 0)).select("doc_id", "version", "line_no", worded.alias("worded"), known_by.alias("line")), "places")
    total = places.count()
    hot = written(places.groupBy("line").agg(F.count("*").alias("n")).where(F.col("n") > total * HOT_SHARE), "hot")
    told = join_hot(places, classes.withColumnRenamed("id", "line"), "line", hot)
    known = written(told.select("doc_id", "version", "line_no", "worded", "line", F.coalesce("component", "line").alias("class")), "places")
    own = ["class", "doc_id", "version"]
    each = known.where("worded").groupBy(*own).agg(F.min(F.struct("line_no", "line")).alias("head"), F.count("*").alias("n"))
    whole = each.groupBy("class").agg(F.min(F.struct("doc_id", "version", "head")).alias("first"), F.count("*").alias("docs"), F.sum("n").alias("n"))
    many_rows = written(whole.where("n > 1").select("class", "n", (F.col("docs") >= min_docs).alias("across"), F.col("first.doc_id").alias("first_doc"), F.col("first.version").alias("first_version"), F.col("first.head.line_no").alias("first_no"), F.col("first.head.line").alias("first_line")), "repeated")
    told = join_hot(known, many_rows.drop("n"), "class", many_rows.where(F.col("n") > total * HOT_SHARE))
    if min_docs > 2:  # below that, a class that is not compared across documents is in one alone
        heads = each.where("n > 1").join(many_rows.where("not across").select("class"), "class", "left_semi").select(*own, F.col("head.line_no").alias("own_no"), F.col("head.line").alias("own_line"))
        told = told.join(heads, own, "left")
        inner = F.coalesce(~F.col("across"), F.lit(False))
        for first, mine in (("first_doc", F.col("doc_id")), ("first_version", F.col("version")), ("first_no", F.coalesce("own_no", "line_no")), ("first_line", F.coalesce("own_line", "line"))):
            told = told.withColumn(first, F.when(inner, mine).otherwise(F.col(first)))
    elsewhere = (F.col("doc_id") != F.col("first_doc")) | (F.col("version") != F.col("first_version")) | (F.col("line_no") != F.col("first_no"))
    told = told.withColumn("gone", F.coalesce(elsewhere & F.col("worded"), F.lit(False)))
    near = F.col("gone") & (F.col("line") != F.col("first_line"))
    sets = told.groupBy("doc_id", "version").agg((F.count_if("worded") / F.count_if(F.col("line_no") == 0)).cast("long").alias("n_lines"), F.array_sort(F.collect_set(F.when(F.col("gone"), F.col("line_no")))).alias("removed"), F.collect_set(F.when(near, F.col("line_no"))).alias("near"))  # repeated rows count once
    n_near = F.size("near").cast("long")
    return sets.where("n_lines > 0").select("doc_id", "version", "n_lines", (F.size("removed") - n_near).alias("n_exact"), n_near.alias("n_near"), "removed")


def _without(texts: pd.Series, removed: pd.Series) -> pd.Series:
    """Texts without the lines of the given numbers."""

    def rest(text: str, gone) -> str:
        out = set(gone.tolist())
        return "\n".join([x for i, x in enumerate(text.split("\n")) if i not in out])

    return pd.Series([None if t is None else rest(t, g) for t, g in zip(texts, removed, strict=True)], dtype=object)


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """``docs`` without the removed lines; a document that had lines and loses all of them is dropped."""
    key, version, removed, empty = fresh(docs, "key", "version", "removed", "nothing_left")
    gone = line_removals(docs, id_col, text_col, **how).where(F.size("removed") > 0)
    gone = written(gone.select(F.col("doc_id").alias(key), F.col("version").alias(version), F.col("removed").alias(removed), (F.col("n_lines") == F.size("removed")).alias(empty)), "removals")
    same = (F.col(id_col).cast("long") == F.col(key)) & (F.xxhash64(F.col(text_col)) == F.col(version))
    joined = docs.join(gone.hint("merge"), same, "left").where(~F.coalesce(F.col(empty), F.lit(False)))
    there = F.col(removed).isNotNull()
    kept = F.pandas_udf(_without, "string")(F.when(there, F.col(text_col)), F.col(removed))
    return joined.withColumn(text_col, F.when(there, kept).otherwise(F.col(text_col))).select(*docs.columns)

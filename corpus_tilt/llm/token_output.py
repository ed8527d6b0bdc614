"""Token ids in binary shards with a minimal perfect hash index for keyed access.

Format, below one folder: ``ids-NNNNNN.bin`` holds raw little-endian ids (two bytes where the
vocabulary allows, else four) of documents in ascending key order; ``index-NNNNN.npz`` holds,
for one bucket of keys, the levels of a minimal perfect hash and, by its slots, a fingerprint,
the shard, the offset there and the length.  A lookup reads one bucket file, evaluates the hash
in constant time, compares the fingerprint and seeks to the ids.

Defined results: null text has only the end id; rows that repeat a key are separate entries,
told apart by their order in the files (that of a checksum of their first ids); a null key sorts first; an empty table has no files;
columns other than the two named are not read.
"""

from __future__ import annotations

import io
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import PartFile, encoded, encoder, file_system, lean, shared_folder, workers_import, written

_DIRECTORY = "key long, turn long, shard int, offset long, n long"
_FLUSH = 1 << 22
_SHARD_BYTES = 32 << 20  # of text
_MOST_SHARDS = 20_000


# --- minimal perfect hash -----------------------------------------------------------------


def _mix(a: np.ndarray, b: np.ndarray, salt: int) -> np.ndarray:
    """A 64-bit hash of two 64-bit keys, another one for each salt."""
    with np.errstate(over="ignore"):
        x = a ^ (b * np.uint64(0x9E3779B97F4A7C15)) ^ np.uint64((salt * 0xD1B54A32D192ED03 + 0x8CB92BA72F3D8DD7) & (2**64 - 1))
        for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(by)
        return x ^ (x >> np.uint64(31))


class PerfectHash:
    """A minimal perfect hash of distinct 128-bit keys: levels of bits, each set where one key alone falls.

    Keys that share a place go on to the next level; a key's slot is the count of set bits
    before its own.  About three bits a key; a lookup looks at a constant number of levels on average.
    """

    def __init__(self, levels: list[np.ndarray]) -> None:
        self.levels = levels
        counts = [int(x.sum()) for x in levels]
        self.ranks = [np.cumsum(x, dtype=np.int64) - x + sum(counts[:i]) for i, x in enumerate(levels)]

    @classmethod
    def of(cls, a: np.ndarray, b: np.ndarray, spread: float = 1.6) -> PerfectHash:
        levels = []
        while len(a):
            size = max(2, int(len(a) * spread))
            at = (_mix(a, b, len(levels)) % np.uint64(size)).astype(np.int64)
            alone = np.bincount(at, minlength=size) == 1
            levels.append(alone)
            a, b = a[~alone[at]], b[~alone[at]]
            if len(levels) > 200:
                raise ValueError("the keys are not distinct")
        return cls(levels)

    def slots(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The slot of each key; -1 where no level has it (then it was never a key)."""
        out, left = np.full(len(a), -1, np.int64), np.arange(len(a))
        for i, (bits, rank) in enumerate(zip(self.levels, self.ranks, strict=True)):
            at = (_mix(a[left], b[left], i) % np.uint64(len(bits))).astype(np.int64)
            hit = bits[at]
            out[left[hit]] = rank[at[hit]]
            left = left[~hit]
        return out


# --- writing --------------------------------------------------------------------------------


@dataclass(frozen=True)
class TokenStore:
    """Where shards and index are; the shards' totals (one number a shard) give global starts."""

    folder: str
    width: int
    bases: tuple[int, ...]
    buckets: int


def _encoder(path: str, width: int, end_id: int):
    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        end = np.array([end_id], f"<u{width}").tobytes()
        for b in batches:
            ids = [own + end for own in encoded(path, b.column(2).to_pylist(), width)]
            salt = [zlib.crc32(x[:256]) for x in ids]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(salt, pa.int64()), pa.array(ids, pa.binary())], ["low", "key", "salt", "ids"])
        encoder(path).forget()  # other stages use the worker's memory

    return encode


def _shard_writer(folder: str, width: int):
    """A file a shard, of input sorted by shard (column 0)."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, now, offset, last, turn, held, size = None, None, 0, object(), 0, [], 0
        for batch in batches:
            rows = []
            for shard, key, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                if shard != now:
                    if out:
                        out.write(b"".join(held))
                        out.close()
                    out, now, offset, last, held, size = PartFile(folder, f"ids-{shard:06d}.bin"), shard, 0, object(), [], 0
                data = data.as_py()
                held.append(data)
                size += len(data)
                if size > _FLUSH:
                    out.write(b"".join(held))
                    held, size = [], 0
                turn = turn + 1 if key == last else 0
                last = key
                rows.append((key, turn, shard, offset, len(data) // width))
                offset += len(data) // width
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64()), strict=True)], ["key", "turn", "shard", "offset", "n"])
        if out:
            out.write(b"".join(held))
            out.close()

    return write


def _edges(texts: DataFrame) -> list[int]:
    """Keys that divide the rows about evenly in shards of ``_SHARD_BYTES`` of text; a key with very many rows stands there repeatedly."""
    rows, size = texts.agg(F.count("*"), F.sum(F.octet_length("text"))).first()
    shards = min(max(1, -(-(size or 0) // _SHARD_BYTES)), rows or 1, _MOST_SHARDS)
    if shards == 1:
        return []
    return texts.agg(F.percentile_approx(_low_key(), [i / shards for i in range(1, shards)], 20 * shards)).first()[0]


def _low_key() -> Column:
    return F.coalesce("key", F.lit(-(1 << 63)))


def _shard_of(edges: list[int]) -> Column:
    """The shard of a row (low, salt): ascending in the key; rows of a key that is several edges are dealt by their salt."""
    shared = F.array(*(F.lit(e).cast("long") for e in edges)) if edges else F.array().cast("array<long>")
    below = F.size(F.filter(shared, lambda e: e < F.col("low")))
    same = F.size(F.filter(shared, lambda e: e == F.col("low")))
    return (below + F.floor(F.col("salt") * (same + 1) / F.lit(1 << 32))).cast("int")


def _turns(directory: DataFrame) -> DataFrame:
    """Turns of keys that go on over a shard's end count on there.

    Shards are ranges of (key, salt), so the keys found in two shards or more are at most as many
    as there are shards: a proven bound for the broadcast.
    """
    by_shard = directory.groupBy("key", "shard").agg(F.count("*").alias("own"))
    over = by_shard.groupBy("key").agg(F.collect_list(F.struct("shard", "own")).alias("parts")).where(F.size("parts") > 1)
    earlier = F.aggregate(F.filter("parts", lambda p: p["shard"] < F.col("part.shard")), F.lit(0).cast("long"), lambda t, p: t + p["own"])
    before = over.select("key", "parts", F.explode("parts").alias("part")).select(F.col("key").alias("of"), F.col("part.shard").alias("there"), earlier.alias("before"))
    same = F.col("key").eqNullSafe(F.col("of")) & (F.col("shard") == F.col("there"))
    return directory.join(F.broadcast(before), same, "left").select("key", (F.col("turn") + F.coalesce("before", F.lit(0))).alias("turn"), "shard", "offset", "n")


def _hashed(df: DataFrame, buckets: int) -> DataFrame:
    """Two independent 64-bit hashes of (key, turn) and the bucket of the index that has them."""
    return df.withColumns({"h1": F.xxhash64("key", "turn"), "h2": F.xxhash64(F.lit(0x5BD1), "turn", "key")}).withColumn("bucket", F.pmod(F.xxhash64("h1", "h2"), F.lit(buckets)).cast("int"))


def _fingerprint(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (_mix(b, a, 977) & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.Table]]:
    """The rows of each bucket, of input sorted by bucket (column 0)."""
    held, now = [], None
    for batch in batches:
        of = batch.column(0).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(np.diff(of)) + 1).tolist(), len(of)]
        for lo, hi in zip(cuts, cuts[1:], strict=False):
            if lo == hi:
                continue
            if of[lo] != now and held:
                yield now, pa.Table.from_batches(held)
                held = []
            now = int(of[lo])
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield now, pa.Table.from_batches(held)


def _column(rows: pa.Table, name: str, kind: str | None = None) -> np.ndarray:
    x = rows[name].to_numpy()
    return x.view(kind) if kind else x


def _index_writer(folder: str):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bucket, rows in _groups(batches):
            a, b = _column(rows, "h1", "u8"), _column(rows, "h2", "u8")
            hashed = PerfectHash.of(a, b)
            slot = hashed.slots(a, b)
            order = np.argsort(slot)
            blob = io.BytesIO()
            np.savez(blob, fingerprint=_fingerprint(a, b)[order], **{c: _column(rows, c)[order] for c in ("shard", "offset", "n")}, **{f"level{i}": np.packbits(x) for i, x in enumerate(hashed.levels)}, sizes=np.array([len(x) for x in hashed.levels]))
            out = PartFile(folder, f"index-{bucket:05d}.npz")
            out.write(blob.getvalue())
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([len(a)], pa.int64())], ["bucket", "keys"])

    return write


def write_tokens(docs: DataFrame, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", keys_per_bucket: int = 50_000) -> TokenStore:
    """Encode every text, write shards in ascending key order, and index them.

    Texts are encoded where they are read; what is shuffled for the order is their ids, to shards
    that are ranges of keys (a key with very many rows is dealt to several by a hash of its ids).  The index shuffles a few numbers a document.  Files appear by renaming,
    so a task that is run again replaces its own shard.
    """
    spark = docs.sparkSession
    workers_import(spark)
    from tokenizers import Tokenizer

    width = 2 if max(Tokenizer.from_file(tokenizer).get_vocab_size(with_added_tokens=True) - 1, end_id) < 0x10000 else 4
    folder = shared_folder(spark, "tokens")
    texts = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).alias("text"))
    ids = texts.select(_low_key().alias("low"), "key", "text").mapInArrow(lean(_encoder(tokenizer, width, end_id)), "low long, key long, salt long, ids binary")
    edges = _edges(texts)
    dealt = ids.select(_shard_of(edges).alias("shard"), "low", "key", "salt", "ids").repartitionById(len(edges) + 1, F.col("shard"))
    ordered = dealt.sortWithinPartitions("shard", "low", "key", "salt").select("shard", "key", "ids")
    directory = written(ordered.mapInArrow(lean(_shard_writer(folder, width)), _DIRECTORY), "directory")
    totals = {r["shard"]: (r["ids"], r["keys"]) for r in directory.groupBy("shard").agg(F.sum("n").alias("ids"), F.count("*").alias("keys")).collect()}
    bases, at = [], 0
    for shard in range(max(totals, default=-1) + 1):
        bases.append(at)
        at += totals.get(shard, (0, 0))[0]
    buckets = max(1, -(-sum(k for _, k in totals.values()) // keys_per_bucket))
    dealt = _hashed(_turns(directory), buckets).select("bucket", "h1", "h2", "shard", "offset", "n").repartition(F.col("bucket")).sortWithinPartitions("bucket")
    dealt.mapInArrow(lean(_index_writer(folder)), "bucket int, keys long").agg(F.sum("keys")).collect()
    return TokenStore(folder, width, tuple(bases), buckets)


# --- keyed reading -----------------------------------------------------------------------------


def _load_index(folder: str, bucket: int) -> dict:
    files, base = file_system(folder)
    with files.open_input_file(f"{base}/index-{bucket:05d}.npz") as f:
        got = dict(np.load(io.BytesIO(f.read())))
    got["hash"] = PerfectHash([np.unpackbits(got[f"level{i}"], count=int(n)).astype(bool) for i, n in enumerate(got["sizes"])])
    return got


def _finder(folder: str, bases: tuple[int, ...]):
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = np.array(bases, np.int64)
        for bucket, rows in _groups(batches):
            index = _load_index(folder, bucket)
            a, b = _column(rows, "h1", "u8"), _column(rows, "h2", "u8")
            slot = index["hash"].slots(a, b)
            found = slot >= 0
            found[found] = index["fingerprint"][slot[found]] == _fingerprint(a, b)[found]
            at = slot[found]
            keep = rows.filter(pa.array(found))
            shard, offset, n = (index[c][at] for c in ("shard", "offset", "n"))
            yield pa.RecordBatch.from_arrays([keep["key"].combine_chunks(), keep["turn"].combine_chunks(), *(pa.array(x) for x in (shard, offset, n, of[shard] + offset))], _FOUND_NAMES)

    return find


_FOUND = f"{_DIRECTORY}, start long"
_FOUND_NAMES = [c.split()[0] for c in _FOUND.split(", ")]


def _payload_reader(folder: str, width: int, digest: bool):
    """The ids of each entry, or their checksum alone."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, base = file_system(folder)
        handle, at = None, None
        for batch in batches:
            out = []
            shard, offset, n = (batch.column(i).to_numpy() for i in (2, 3, 4))
            for s, o, k in zip(shard.tolist(), offset.tolist(), n.tolist(), strict=True):
                if s != at:
                    if handle:
                        handle.close()
                    handle, at = files.open_input_file(f"{base}/ids-{s:06d}.bin"), s
                raw = handle.read_at(k * width, o * width)
                raw = raw if width == 4 else np.frombuffer(raw, "<u2").astype("<u4").tobytes()
                out.append(zlib.crc32(raw) if digest else raw)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.int64() if digest else pa.binary())], [*batch.schema.names, "ids_crc32" if digest else "ids"])

    return read


def lookup(store: TokenStore, keys: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Find each key by the index: key, turn, start (ids of all documents before it), shard, offset, n.

    A key that stands k times in ``keys`` finds the first k of its documents; one that the
    index lacks finds none.
    """
    asked = keys.select(F.col(id_col).cast("long").alias("key")).groupBy("key").agg(F.count("*").alias("n"))
    block = 10_000  # a key that stands there very often is dealt out in blocks of turns
    blocks = asked.select("key", "n", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / block))).alias("part"))
    turns = blocks.select("key", F.explode(F.sequence(F.col("part") * block, F.least(F.col("n"), (F.col("part") + 1) * block) - 1)).alias("turn"))
    dealt = _hashed(turns, store.buckets).select("bucket", "h1", "h2", "key", "turn").repartition(F.col("bucket")).sortWithinPartitions("bucket")
    return dealt.mapInArrow(lean(_finder(store.folder, store.bases)), _FOUND)


def _in_file_order(found: DataFrame) -> DataFrame:
    return found.repartition(F.col("shard"), F.floor(F.col("offset") / 500_000)).sortWithinPartitions("shard", "offset").select(*_FOUND_NAMES)


def read_tokens(store: TokenStore, found: DataFrame) -> DataFrame:
    """The ids (binary, little-endian unsigned 32-bit) of what ``lookup`` found, read in file order."""
    return _in_file_order(found).mapInArrow(lean(_payload_reader(store.folder, store.width, False)), f"{_FOUND}, ids binary")


def token_digest(store: TokenStore, keys: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""
    read = _in_file_order(lookup(store, keys, id_col)).mapInArrow(lean(_payload_reader(store.folder, store.width, True)), f"{_FOUND}, ids_crc32 long")
    return read.select(F.col("key").alias("doc_id"), "start", F.col("n").alias("n_tokens"), "ids_crc32")

"""What the operators share: tables, the shared folder, part files and unit-cached tokenizers."""

from __future__ import annotations

import atexit
import codecs
import contextlib
import ctypes
import os
import random
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
#: The ASCII white space that separates words in the contracts.
SPACES = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    workers_import(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def workers_import(spark: SparkSession) -> None:
    """Python workers import this package by name, whatever folder the driver was started in."""
    env = spark.sparkContext.environment
    if ROOT not in (paths := env.get("PYTHONPATH", "").split(os.pathsep)):
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, paths)])


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new URI below ``spark.checkpoint.dir``, which the driver and all executors can reach.

    Only where that setting is missing and the master is local (tests), a temporary folder stands in.
    The folder is removed when the driver ends.
    """
    workers_import(spark)
    top = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not top:
        known, master = spark.sparkContext._jsc.sc().getCheckpointDir(), spark.sparkContext.master
        if not known.isDefined() and (not master.startswith("local") or master.startswith("local-cluster")):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        top = known.get() if known.isDefined() else _own_folder()
    uri = f"{top.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    path = jvm.org.apache.hadoop.fs.Path(uri)
    files = path.getFileSystem(conf)
    files.mkdirs(path)
    uri = files.makeQualified(path).toString()
    atexit.register(_remove, files, path)
    return uri


_OWN: list[str] = []


def _own_folder() -> str:
    if not _OWN:
        _OWN.append("file://" + tempfile.mkdtemp(prefix="tilt-"))
    return _OWN[0]


def _remove(files, path) -> None:
    try:
        files.delete(path, True)
    except Exception:  # noqa: BLE001  the JVM may have ended before
        return


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once as Parquet in the shared folder and read again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    uri = shared_folder(spark, name) + "/rows"
    df.write.parquet(uri)
    return spark.read.schema(df.schema).parquet(uri)


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable:
    """``run``, after which a worker process gives its free memory back: Spark keeps idle workers for other stages."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):
                ctypes.CDLL(None).malloc_trim(0)

    return wrapped


def column_slices(texts: pa.Array, most: int = 1 << 20) -> Iterator[tuple[int, int, list[str | None]]]:
    """The rows of a column of texts, some at a time: (from, up to, texts) of about ``most`` bytes together, one text at least."""
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    upto, lo = np.cumsum(sizes, dtype=np.int64), 0
    while lo < len(sizes):
        hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + most, side="right")))
        yield lo, hi, texts.slice(lo, hi - lo).to_pylist()
        lo = hi


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names like ``names`` that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    while taken & {n.lower() for n in names}:
        names = tuple(f"{n}_" for n in names)
    return list(names)


def join_hot(big: DataFrame, table: DataFrame, key: str, hot: DataFrame) -> DataFrame:
    """``big`` with the columns of ``table`` (one row a key), left; ``hot`` holds the keys that are many rows of ``big``.

    Hot keys are those with more than a share ``HOT_SHARE`` of the rows, so 1 / HOT_SHARE at most:
    their rows of ``table`` are broadcast; the others, none of which is large, are joined by a sort-merge.
    """
    few = written(table.join(hot.select(key).hint("broadcast"), key, "left_semi"), "hot")
    own = big.join(few.select(key).hint("broadcast"), key, "left_semi").join(few.hint("broadcast"), key, "left")
    rest = big.join(few.select(key).hint("broadcast"), key, "left_anti").join(table.hint("merge"), key, "left")
    return own.unionByName(rest)


HOT_SHARE = 1e-4


def file_system(uri: str):
    """The public Arrow file system of a URI and the path in it."""
    from pyarrow import fs

    if re.match(r"file:/(?!/)", uri):
        uri = "file://" + uri[5:]
    return fs.FileSystem.from_uri(uri)


class PartFile:
    """A file that appears whole or not at all: attempts write beside it and rename at the end."""

    def __init__(self, folder: str, name: str) -> None:
        self.files, base = file_system(folder)
        self.path = f"{base}/{name}"
        self.draft = f"{self.path}.{uuid.uuid4().hex[:8]}"
        self.out = self.files.open_output_stream(self.draft, compression=None)
        self.size = 0

    def write(self, data: bytes) -> None:
        self.out.write(data)
        self.size += len(data)

    def close(self) -> None:
        self.out.close()
        self.files.move(self.draft, self.path)


def text_bytes(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


#: ASCII punctuation: after a letter or digit it is a pre-token of its own.
_TAIL = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_CUT = re.compile(r"(?<=\S)(?=[ \t\n\r])")
_WIDE = re.compile("[^\x00-\xff]")
#: What stands for each byte in vocabularies of bytes; the space stays, as what cuts.
_PRINTED = {b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174}
_BYTES = "".join(chr(b if b in _PRINTED or b == 32 else 256 + sum(c not in _PRINTED for c in range(b))) for b in range(256))
#: Bytes of a cache entry beside its key and ids, by the sizes of Python objects.
_ENTRY = 190


def _ids(tokenizer, texts: list[str]) -> list[list[int]]:
    return [e.ids for e in tokenizer.encode_batch_fast(texts, add_special_tokens=False)]


class UnitEncoder:
    """Token ids of whole texts, put together from cached ids of their white-space-led units.

    A text is cut only where a character that is not white space meets white space.  Where the
    pre-tokenizer never joins across such a place, the ids of the units, in order, are those of
    the text; this is tried on odd texts when the encoder is made, and a tokenizer that fails
    encodes whole texts.  The caches hold about ``room`` bytes at most.
    """

    def __init__(self, path: str, room: int = 128 << 20) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.kind = "<u2" if self.tokenizer.get_vocab_size(with_added_tokens=True) <= 0x10000 else "<u4"
        self.room, self.used = room, 0
        self.marks = self._word_marks()
        self.model = self.tokenizer.model if self._plain_words() else None
        self.inner: dict[str, bytes] = {}
        self.exact: dict[str, bytes] = {}
        self.whole_only = not any(self._splits(line) for line in (" ", " \n"))

    def _plain_words(self) -> bool:
        """Are a word of Latin-1 letters' ids those of the model for its bytes in lower case, and does a space add none?"""
        letters, rng = [c for c in map(chr, range(256)) if c.isalpha()], random.Random(6)
        words = letters + [a + b for a in letters for b in letters] + ["".join(rng.choices(letters, k=rng.randint(3, 12))) for _ in range(1000)]
        try:
            return self._by_model(self.tokenizer.model, words) == self._encode([" " + k for k in words])
        except Exception:  # noqa: BLE001  a model of another kind, or without some byte
            return False

    def _by_model(self, model, words: list[str]) -> list[bytes]:
        """Ids of words of Latin-1 letters by the library's model alone, without its passes over whole texts; cases are one."""
        units = codecs.charmap_decode(" ".join(words).lower().encode(), "strict", _BYTES)[0].split(" ")
        new = list(dict.fromkeys(units))
        told = [[t.id for t in tokens] for tokens in map(model.tokenize, new)]
        raw, w = np.array([i for ids in told for i in ids], self.kind).tobytes(), np.dtype(self.kind).itemsize
        ends = (np.cumsum([len(ids) for ids in told], dtype=np.int64) * w).tolist()
        known = {k: raw[lo:hi] for k, lo, hi in zip(new, [0, *ends], ends, strict=False)}
        return [known[k] for k in units]

    def _splits(self, line: str) -> bool:
        """Do the units' ids make up those of whole texts, on texts of odd parts?  ``line`` is what stands for a line break before a unit."""
        parts = ["a", "Word", " ", "  ", "\n", "\t", "don't", "'s", "\u00c9", "e\u0301", "<|endoftext|>", ".", ",", "12", "_", "\U0001f44d", "%%%", "\x1c", "\r\n", "\u4e2d\u6587", "\u00a0", "x" * 40]
        rng = random.Random(5)
        self.forget()
        try:
            texts = ["".join(rng.choice(parts) for _ in range(rng.randint(1, 9))) for _ in range(400)]
            self.line, self.whole_only = line, False
            return self.ids_many(texts) == [np.array(ids, self.kind).tobytes() for ids in _ids(self.tokenizer, texts)]
        except (AttributeError, KeyError, IndexError):
            return False

    def _words(self, words: list[str]) -> list[bytes]:
        """Ids of each word of letters after a space.  Words go to the library many at a time, and are told apart by its marks of a word's begin or end."""
        if self.marks is None:
            return self._encode([" " + k for k in words])
        out: list[bytes] = []
        for group in (words[i : i + 400] for i in range(0, len(words), 400)):
            text = " " + " ".join(group)
            if self.model is not None and not _WIDE.search(text):
                out += self._by_model(self.model, group)
                continue
            ids = np.array(_ids(self.tokenizer, [text])[0], self.kind)
            at = np.flatnonzero(self.marks[ids])
            cuts = [*at.tolist(), len(ids)] if self.lead else [0, *(at + 1).tolist()]
            if len(cuts) == len(group) + 1 and cuts[0] == 0 and cuts[-1] == len(ids):
                raw, w = ids.tobytes(), ids.itemsize
                out += [raw[lo * w : hi * w] for lo, hi in zip(cuts, cuts[1:], strict=False)]
            else:
                out += self._encode([" " + k for k in group])
        return out

    def _encode(self, units: list[str]) -> list[bytes]:
        """Ids of each unit, by itself."""
        return [np.array(ids, self.kind).tobytes() for ids in _ids(self.tokenizer, units)]

    def _word_marks(self):
        """By id, whether a token begins (a space mark) or ends (a suffix) a word; None if the vocabulary has neither."""
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=True)
        suffix = getattr(self.tokenizer.model, "end_of_word_suffix", None)
        self.lead = not suffix
        out = np.zeros(max(vocabulary.values()) + 1, bool)
        for token, i in vocabulary.items():
            out[i] = token.endswith(suffix) if suffix else token.startswith("\u0120")
        return out if out.any() else None

    def _store(self, known: dict[str, bytes], units: list[str], ids: list[bytes]) -> None:
        known.update(zip(units, ids, strict=True))
        self.used += sum(map(len, units)) + sum(map(len, ids)) + _ENTRY * len(units)

    def forget(self) -> None:
        """Empty the caches."""
        self.inner.clear()
        self.exact.clear()
        self.used = 0

    def _learn(self, parts: set[str]) -> set[str]:
        """Add the ids of words after a space (or led by a line break); those that are no such words are given back."""
        words = {k for k in parts if k.isalpha()}
        rest = parts - words
        odd = {k for k in rest if (bare := k[1:] if k[:1] == "\n" else k).split() != [bare]}
        split = {k: (bare, k[len(bare) :]) for k in rest - odd if k[0] != "\n" and "<|" not in k and (bare := k.rstrip(_TAIL)) != k and bare and bare[-1].isalnum()}
        bares = {bare for bare, _ in split.values()}.difference(self.inner, words)
        letters = list(words) + [k for k in bares if k.isalpha()]
        others = [k for k in bares if not k.isalpha()] + list(rest - odd - split.keys())
        self._store(self.inner, letters, self._words(letters))
        self._store(self.inner, others, self._encode([k if k[0] == "\n" else " " + k for k in others]))
        self._whole({tail for _, tail in split.values()})
        self._store(self.inner, list(split), [self.inner[bare] + self.exact[tail] for bare, tail in split.values()])
        return odd

    def _whole(self, units: set[str]) -> None:
        new = list(units.difference(self.exact))
        self._store(self.exact, new, self._encode(new))

    def ids_many(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text, in the narrower of two and four bytes; new units of all of them are encoded together."""
        if self.whole_only:
            return self._encode([t or "" for t in texts])
        if self.used > self.room:
            self.forget()
        parts = pc.split_pattern(pa.array([(t or "").replace("\n", self.line) for t in texts], pa.large_string()), " ")
        coded, cuts = parts.flatten().dictionary_encode(), parts.offsets.to_numpy()  # Python sees a unit once
        units, codes = coded.dictionary.to_numpy(zero_copy_only=False).tolist(), coded.indices.to_numpy().copy()
        heads = [units[c] for c in codes[cuts[:-1]].tolist()]
        odd = self._learn({k for k in units if k not in self.inner})
        self._whole(set(heads))
        codes[cuts[:-1]] = len(units)  # what a text begins with has no space before it
        known = [self.inner.get(k, b"") for k in units] + [b""]
        raw, ends = self._gathered(known, codes)
        strange = np.array([k in odd for k in units] + [False])[codes] if odd else np.zeros(len(codes), bool)
        whole = np.logical_or.reduceat(strange, cuts[:-1]).tolist() if len(texts) else []
        bounds, out = [0, *ends[cuts[1:] - 1].tolist()], []
        for t, head, bad, lo, hi in zip(texts, heads, whole, bounds, bounds[1:], strict=False):
            if not bad and (head.split() == [head] or not head):
                out.append(self.exact[head] + raw[lo:hi].tobytes())
                continue
            own = _CUT.split(t or "")
            self._whole(set(own))
            out.append(b"".join(map(self.exact.__getitem__, own)))
        return out

    def _gathered(self, known: list[bytes], codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of ``known``[c] for each of ``codes``, one after another, and up to where each one's go."""
        ids = np.frombuffer(b"".join(known), self.kind)
        sizes = np.fromiter(map(len, known), np.int64, len(known)) // ids.itemsize
        n = sizes[codes]
        ends = np.cumsum(n)
        return ids[np.repeat((np.cumsum(sizes) - sizes)[codes] - ends + n, n) + np.arange(ends[-1] if len(ends) else 0)], ends

    def ids(self, text: str | None) -> bytes:
        """The ids of a text as little-endian unsigned 32-bit integers."""
        return next(encoded_by(self, [text], 4))


_ENCODERS: dict[str, UnitEncoder] = {}


def encoder(path: str) -> UnitEncoder:
    """One encoder a worker process, kept from task to task; a task that is done with it makes it ``forget``."""
    if path not in _ENCODERS:
        _ENCODERS[path] = UnitEncoder(path)
    return _ENCODERS[path]


def _stretches(text: str, most: int) -> Iterator[str]:
    """A long text in stretches of about ``most`` characters, cut only between units."""
    at = 0
    while len(text) - at > most and (m := _CUT.search(text, at + most)):
        yield text[at : m.start()]
        at = m.start()
    yield text[at:]


def encoded_by(own: UnitEncoder, texts: list[str | None], width: int, at_once: int = 1 << 20) -> Iterator[bytes]:
    """Ids of each text in ``width`` bytes; about ``at_once`` characters are in work, a longer text goes stretch by stretch."""
    widen = (lambda raw: raw) if np.dtype(own.kind).itemsize == width else (lambda raw: np.frombuffer(raw, own.kind).astype(f"<u{width}").tobytes())
    block, size = [], 0
    for t in texts:
        n = len(t or "")
        if block and size + n > at_once:
            yield from map(widen, own.ids_many(block))
            block, size = [], 0
        if n > at_once and not own.whole_only:
            yield widen(b"".join(own.ids_many([part])[0] for part in _stretches(t, at_once)))
        else:
            block.append(t)
            size += n
    yield from map(widen, own.ids_many(block))


def encoded(path: str, texts: list[str | None], width: int = 4) -> Iterator[bytes]:
    """Ids of each text as little-endian unsigned integers of ``width`` bytes."""
    return encoded_by(encoder(path), texts, width)


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


__all__ = ["F", "HOT_SHARE", "PartFile", "UnitEncoder", "encoded", "column_slices", "encoder", "file_system", "fresh", "join_hot", "lean", "shared_folder", "table", "text_bytes", "tokenizer_path", "workers_import", "written"]

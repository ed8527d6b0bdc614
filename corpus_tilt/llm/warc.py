"""WARC archives: written by tasks, read back by boundary chains.

Reading cuts files into chunks of bytes.  A task emits, for every place in its chunk that looks
like the head of a record, where the record after it would begin.  Pointer jumping over these
links from the start of each file keeps the reachable records alone, so the magic string inside
a payload is never taken for a record.

Defined results: a null payload is empty; a null url is ``urn:none``, one too long for a head (64 KB
at most) the ``urn:sha1`` of it; rows that repeat a page id
and payload are records of the same kind; a null page id is written as ``-`` and never the
response others refer to, unless no other has that payload; an empty table gives no files and no
rows; columns other than the three named are not read.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import PartFile, file_system, lean, shared_folder, text_bytes, workers_import, written

MAGIC = b"WARC/1.1\r\n"
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_HEAD = 1 << 16  # a head's blank line is nearer than this


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def _uri(url: str | None) -> str:
    out = quote(url or "urn:none", safe=":/?#[]@!$&()*+,;=%~")
    return out if len(out) < _HEAD // 2 else f"urn:sha1:{sha1_base32(out.encode())}"


def record(page: int | None, url: str | None, payload: bytes, refers_to: int | None, date: str) -> bytes:
    """One record: a response with its payload, or a revisit with the HTTP head alone."""
    block = _HTTP if refers_to is not None else _HTTP + payload
    lines = [
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:page:{'-' if page is None else page}>",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {_uri(url)}",
        f"WARC-Payload-Digest: sha1:{sha1_base32(payload)}",
        f"WARC-Payload-Length: {len(payload)}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if refers_to is not None:
        lines += [f"WARC-Profile: {_PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    return MAGIC + "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


_MANIFEST = "file string, size long, records long"


def _writer(folder: str, roll: int, date: str):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made, out, n = TaskContext.get().partitionId(), [], None, 0
        for b in batches:
            for page, url, html, refers in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if out and out.size >= roll:
                    out.close()
                    made.append((name, out.size, n))
                    out = None
                if not out:
                    name, n = f"pages-{part:06d}-{len(made):04d}.warc", 0
                    out = PartFile(folder, name)
                out.write(record(page, url, text_bytes(html), refers, date))
                n += 1
        if out:
            out.close()
            made.append((name, out.size, n))
        if made:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*made, strict=True), (pa.string(), pa.int64(), pa.int64()), strict=True)], ["file", "size", "records"])

    return write


def write_warc(pages: DataFrame, least_bytes: int = 0, roll: int = 64 << 20, date: str = "1970-01-01T00:00:00Z") -> tuple[str, DataFrame]:
    """Write a record a row of ``pages`` (page_id, url, html); the folder and a table of its files.

    Of rows with equal payloads of at least ``least_bytes`` the one with the largest page id is
    the response and the others are revisits of it.
    """
    spark = pages.sparkSession
    workers_import(spark)
    folder = shared_folder(spark, "warc")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    digest = F.sha1(F.col("html").cast("binary"))
    heads = rows.where(F.octet_length("html") >= least_bytes).select("page_id", digest.alias("digest")).groupBy("digest").agg(F.count("*").alias("copies"), F.max("page_id").alias("head")).where("copies > 1").select("digest", "head")
    heads = written(heads, "payloads")  # so that both sides of the join are plain and a hot payload can be split
    refers = F.when(F.col("page_id") != F.col("head"), F.col("head")).when(F.col("page_id").isNull(), F.col("head"))
    told = rows.withColumn("digest", digest).join(heads, "digest", "left").select("page_id", "url", "html", refers.alias("refers"))
    return folder, written(told.mapInArrow(lean(_writer(folder, roll, date)), _MANIFEST), "warc-files")


# --- reading ------------------------------------------------------------------------------------

_FIELD = re.compile(rb"^([\w-]+): ?(.*?)\r?$", re.M)


class _Window:
    """Bytes of a file from a chunk's start on, read further when a record needs it."""

    def __init__(self, handle, start: int, end: int, size: int) -> None:
        self.handle, self.start, self.size = handle, start, size
        self.data = handle.read_at(min(end, size) - start, start)

    def upto(self, end: int) -> bytes:
        have = self.start + len(self.data)
        if end > have and have < self.size:
            self.data += self.handle.read_at(min(end, self.size) - have, have)
        return self.data

    def head(self, at: int) -> tuple[dict[bytes, bytes], int] | None:
        """The fields of the head at ``at`` and where its block begins; None if none is there."""
        data = self.upto(at + _HEAD)
        lo = at - self.start
        stop = data.find(b"\r\n\r\n", lo, lo + _HEAD)
        if data[lo : lo + len(MAGIC)] != MAGIC or stop < 0:
            return None
        fields = {m[1].lower(): m[2] for m in _FIELD.finditer(data, lo + len(MAGIC), stop + 1)}
        return (fields, self.start + stop + 4) if fields.get(b"content-length", b"").isdigit() else None


_LENGTH = re.compile(rb"\r\ncontent-length: ?(\d{1,18})\r\n", re.I)


def record_links(data: bytes, start: int, end: int) -> dict[int, int]:
    """Of each place before ``end`` that looks like a record's head, where the record after it would begin.

    ``data`` begins at ``start``.  Heads, their ends and their lengths are each found in one pass
    and matched in order, so a payload full of magic strings costs no more than any other.
    """
    blank = [m.start() for m in re.finditer(rb"\r\n\r\n", data)]
    lengths = [(m.start(), int(m[1])) for m in _LENGTH.finditer(data)]
    out, i, j = {}, 0, 0
    for m in re.finditer(re.escape(MAGIC), data):
        lo = m.start()
        if start + lo >= end:
            break
        while i < len(blank) and blank[i] < lo:
            i += 1
        while j < len(lengths) and lengths[j][0] < lo:
            j += 1
        if i < len(blank) and blank[i] < lo + _HEAD and j < len(lengths) and lengths[j][0] < blank[i]:
            out[start + lo] = start + blank[i] + 4 + lengths[j][1] + 4
    return out


def _candidates(folder: str):
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, base = file_system(folder)
        for b in batches:
            out = []
            for name, start, end, size in zip(*(b.column(b.schema.get_field_index(c)).to_pylist() for c in ("file", "start", "end", "size")), strict=True):
                with files.open_input_file(f"{base}/{name}") as handle:
                    links = record_links(_Window(handle, start, end + _HEAD, size).data, start, end)
                exits: dict[int, int] = {}
                for place in sorted(links, reverse=True):  # a link that stays in the chunk is followed here
                    to = links[place]
                    exits[place] = to if to >= end else exits.get(to, -1)
                out += [(name, place, links[place], to) for place, to in exits.items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate((pa.string(), pa.int64(), pa.int64(), pa.int64()))], ["file", "at", "next", "leaves"])

    return find


def reachable_entries(links: DataFrame, hops: int) -> DataFrame:
    """Pointer jumping: of links (file, at, leaves), where the chain from a file's start enters chunks.

    ``hops`` bounds the length of a chain; rounds double what a link spans, so their number is its logarithm.
    """
    entered = links.select("file", F.col("leaves").alias("at")).where("at >= 0").distinct()
    jump = written(links.join(entered, ["file", "at"], "left_semi").select("file", "at", "leaves").unionByName(links.where("at = 0").select("file", "at", "leaves")).distinct(), "links")
    reached = jump.where("at = 0").select("file", "at")
    span = 1
    while span <= hops:
        ahead = jump.select("file", F.col("at").alias("leaves"), F.col("leaves").alias("further"))
        step = reached.join(jump, ["file", "at"]).select("file", F.col("leaves").alias("at"))
        reached = written(reached.unionByName(step).distinct(), "reached")
        jump = written(jump.join(ahead, ["file", "leaves"]).select("file", "at", F.col("further").alias("leaves")), "links")
        span *= 2
    return reached


_RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, file string, at long"


def _page(raw: bytes | None) -> int | None:
    m = re.fullmatch(rb"<urn:page:(-?\d+)>", raw or b"")
    return int(m[1]) if m else None


def _reader(folder: str):
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, base = file_system(folder)
        for b in batches:
            out = []
            for name, at, end, size in zip(*(b.column(b.schema.get_field_index(c)).to_pylist() for c in ("file", "at", "end", "size")), strict=True):
                with files.open_input_file(f"{base}/{name}") as handle:
                    window = _Window(handle, at, end, size)
                    place = at
                    while place < min(end, size):
                        fields, block = window.head(place)
                        length = int(fields[b"content-length"])
                        data = window.upto(block + length)[block - at : block + length - at]
                        said = fields[b"warc-payload-digest"].decode().removeprefix("sha1:")
                        if fields[b"warc-type"] == b"response":
                            payload = data.partition(b"\r\n\r\n")[2]
                            if sha1_base32(payload) != said:
                                raise ValueError(f"{name} at {place}: the payload's digest differs")
                            out.append((_page(fields[b"warc-record-id"]), len(payload), said, "response", None, name, place))
                        else:
                            out.append((_page(fields[b"warc-record-id"]), int(fields[b"warc-payload-length"]), said, "revisit", _page(fields[b"warc-refers-to"]), name, place))
                        place = block + length + 4
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], [c.split()[0] for c in _RECORD.split(", ")])

    return read


def read_warc(folder: str, files: DataFrame, chunk: int = 4 << 20) -> DataFrame:
    """The records of the archives, one row each: page id, payload length and digest, type, referred page, place."""
    places = F.explode(F.sequence(F.lit(0), F.ceil(F.col("size") / chunk).cast("long") - 1))
    chunks = files.where("size > 0").select("file", "size", places.alias("chunk")).withColumns({"start": F.col("chunk") * chunk, "end": F.least(F.col("size"), (F.col("chunk") + 1) * chunk)})
    chunks = written(chunks, "chunks")
    longest = chunks.agg(F.max("chunk")).first()[0]
    spread = chunks.repartition(F.col("file"), F.col("chunk"))
    links = written(spread.mapInArrow(lean(_candidates(folder)), "file string, at long, next long, leaves long"), "links")
    entries = reachable_entries(links.select("file", "at", "leaves"), longest or 0)
    first = entries.withColumn("chunk", F.floor(F.col("at") / chunk)).groupBy("file", "chunk").agg(F.min("at").alias("at"))
    return chunks.join(first, ["file", "chunk"]).repartition(F.col("file"), F.col("chunk")).mapInArrow(lean(_reader(folder)), _RECORD)

"""Token counts of whole texts by overlapping chunks that are spliced where both agree.

A long text is cut into chunks that overlap.  Each is encoded with offsets; the counts are
spliced at a boundary that both encodings of the overlap have and that is proven stable: the
vocabulary has no piece with the space mark after another character, so no merge reaches from a
non-space into a following space, and the tokens on either side of such a place never depend on
the other side.  Where an overlap has no such place it is widened, at last to the whole text.
The pass is map-only, and of a long text one chunk is in work at a time.

Defined results: null or empty text has 0 bytes and 0 tokens; a null or repeated id gives one
row for each input row; an empty table gives none; columns other than the two named are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, workers_import

_MARK = "▁"
_SHOWN = 8
_MODELS: dict[str, tuple] = {}


def _model(path: str):
    """The processor, and whether the vocabulary has the property that makes boundaries stable."""
    if path not in _MODELS:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = (sp.id_to_piece(i) for i in range(sp.get_piece_size()))
        probe = "a  b "  # extra spaces must survive, else the counts on either side could differ
        stable = not any(_MARK in p.lstrip(_MARK) for p in pieces) and "".join(sp.encode_as_pieces(probe)) == _MARK + probe.replace(" ", _MARK)
        _MODELS[path] = sp, stable
    return _MODELS[path]


def _stable(text: str, offsets: list, at: int, least: int) -> dict[int, int]:
    """The first stable boundaries over ``least``: places in the whole text, and how many tokens are before them."""
    out: dict[int, int] = {}
    for i, (lo, _) in enumerate(offsets):
        if lo > least and text[lo] == " " and not text[lo - 1].isspace():
            out[at + lo] = i
            if len(out) == _SHOWN:
                break
    return out


def spliced_count(sp, text: str, chunk: int, overlap: int) -> int | None:
    """Tokens of ``text`` from chunks that overlap by ``overlap`` characters; None where two have no stable place in common."""
    total, tail, begin = 0, {}, 0
    for at in range(0, len(text), chunk):
        own = text[at : at + chunk + overlap]
        offsets = sp.encode_as_offset_mapping(own)["offsets"]
        if at:
            head = _stable(own, offsets, at, 0)
            place = min(tail.keys() & head.keys(), default=None)
            if place is None:
                return None
            total += tail[place] - begin
            begin = head[place]
        if at + chunk >= len(text):
            return total + len(offsets) - begin
        tail = _stable(own, offsets, at, chunk)
    return 0


def _counter(path: str, chunk: int, overlaps: tuple[int, ...]):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp, stable = _model(path)
        for b in batches:
            texts = b.column(2).to_pylist()
            short = [i for i, t in enumerate(texts) if len(t) <= chunk or not stable]
            n = [0] * len(texts)
            for lo in range(0, len(short), 500):
                some = short[lo : lo + 500]
                for i, ids in zip(some, sp.encode([texts[i] for i in some], num_threads=1), strict=True):
                    n[i] = len(ids)
            for i in sorted(set(range(len(texts))).difference(short)):
                found = next((k for o in overlaps if (k := spliced_count(sp, texts[i], chunk, o)) is not None), None)
                n[i] = len(sp.encode(texts[i])) if found is None else found
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n, pa.int64())], ["id", "n_bytes", "n_tokens"])

    return count


def count_tokens(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", chunk: int = 30_000, overlaps: tuple[int, ...] = (256, 1_024, 4_096)) -> DataFrame:
    """Rows of id, n_bytes and n_tokens; ``overlaps`` are tried in turn, then the whole text."""
    workers_import(docs.sparkSession)
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text"))
    return rows.mapInArrow(lean(_counter(model, chunk, overlaps)), "id long, n_bytes long, n_tokens long")

"""Chat formatting by token-level assembly.

Each turn is ``<|turn|>role<|says|>text<|done|>``.  The three marks are reserved ids above the
vocabulary, spliced between separately encoded segments, so no text can produce them.  Control
strings inside roles and texts are broken by a backslash after their first character (and
backslashes doubled), which ``unescape`` takes back.  The loss mask is the prefix sum of +1 after
an assistant's ``<|says|>`` and -1 at its ``<|done|>``.

Output: part files (Arrow streams) of turns in (conversation, turn) order, with ids and mask.  A
conversation may reach over many parts, so a very long one is not gathered by one task when it is
formatted; its sequential digests are taken by streaming the parts.

Defined results: null text or role is empty; a null turn sorts first in its conversation, rows
that repeat a turn follow each other (by role, then text); rows with a null conversation form
one; an empty table gives no rows; columns other than the four named are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import PartFile, encoder, file_system, lean, shared_folder, workers_import, written

MARKS = ("<|turn|>", "<|says|>", "<|done|>")
#: Strings that chat templates use for control.
CONTROL = (*MARKS, "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|endoftext|>", "<|im_start|>", "<|im_end|>")
_CONTROL = re.compile("|".join(re.escape(c) for c in CONTROL))
_BREAK = re.compile(r"\\(\\?)")


def escape(text: str) -> str:
    if "\\" in text:
        text = text.replace("\\", "\\\\")
    return _CONTROL.sub(lambda m: m[0][0] + "\\" + m[0][1:], text) if "<" in text or "[" in text else text


def unescape(text: str) -> str:
    return _BREAK.sub(r"\1", text) if "\\" in text else text


class ChatAssembler:
    """Ids and mask of a turn, and back."""

    def __init__(self, path: str) -> None:
        self.encoder = encoder(path)
        self.tokenizer = self.encoder.tokenizer
        self.base = self.tokenizer.get_vocab_size(with_added_tokens=True)

    def turn(self, role: str, text: str) -> tuple[np.ndarray, np.ndarray]:
        marks = [np.array([self.base + i], np.uint32) for i in range(3)]
        who, what = (np.frombuffer(self.encoder.ids(escape(x)), "<u4") for x in (role, text))
        ids = np.concatenate([marks[0], who, marks[1], what, marks[2]])
        step = np.zeros(len(ids), np.int8)
        if role == "assistant" and len(what):
            step[len(who) + 2], step[-1] = 1, -1
        return ids, np.cumsum(step, dtype=np.int8)

    def read(self, ids: np.ndarray, mask: np.ndarray) -> tuple[str, str, str, int]:
        """Role, text, the text under the mask, and the formatted length in code points."""
        at = np.flatnonzero(ids >= self.base)
        if len(at) != 3 or list(ids[at] - self.base) != [0, 1, 2]:
            raise ValueError("a turn has its three marks in order")
        decode = lambda part: self.tokenizer.decode(part.tolist(), skip_special_tokens=False) if len(part) else ""
        role, text = decode(ids[at[0] + 1 : at[1]]), decode(ids[at[1] + 1 : at[2]])
        under = ids[mask > 0]
        loss = text if len(under) == at[2] - at[1] - 1 else decode(under)
        return unescape(role), unescape(text), unescape(loss) if len(under) else "", sum(map(len, MARKS)) + len(role) + len(text)


_SCHEMA = pa.schema([("conv_id", pa.int64()), ("turn", pa.int64()), ("ids", pa.binary()), ("mask", pa.binary())])


def _part_name(part: int) -> str:
    return f"chat-{part:06d}.arrow"


def _writer(folder: str, path: str):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made = TaskContext.get().partitionId(), ChatAssembler(path)
        out, stream, first, last, n = None, None, None, None, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            conv, turn, role, text = (batch.column(i).to_pylist() for i in range(4))
            turns = [made.turn(r or "", x or "") for r, x in zip(role, text, strict=True)]
            if not out:
                out = PartFile(folder, _part_name(part))
                stream, first = pa.ipc.new_stream(out.out, _SCHEMA), conv[0]
            stream.write_batch(pa.RecordBatch.from_arrays([pa.array(conv, pa.int64()), pa.array(turn, pa.int64()), pa.array([i.tobytes() for i, _ in turns], pa.binary()), pa.array([np.packbits(m).tobytes() for _, m in turns], pa.binary())], schema=_SCHEMA))
            last, n = conv[-1], n + len(conv)
        if out:
            stream.close()
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([first], pa.int64()), pa.array([last], pa.int64()), pa.array([n], pa.int64())], ["part", "first", "last", "turns"])

    return write


def format_chats(chats: DataFrame, tokenizer: str) -> tuple[str, DataFrame]:
    """Write the formatted turns of ``chats`` (conv_id, turn, role, text); the folder and its parts' table."""
    spark = chats.sparkSession
    workers_import(spark)
    folder = shared_folder(spark, "chats")
    rows = chats.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    order = ("conv_id", "turn", "role", "text")
    parts = rows.repartitionByRange(*order[:2]).sortWithinPartitions(*order).mapInArrow(lean(_writer(folder, tokenizer)), "part int, first long, last long, turns long")
    return folder, written(parts, "chat-parts")


def _turns(folder: str, parts: list[int]) -> Iterator[tuple[int, int | None, bytes, bytes]]:
    files, base = file_system(folder)
    for part in parts:
        with files.open_input_stream(f"{base}/{_part_name(part)}", compression=None) as f, pa.ipc.open_stream(f) as stream:
            for batch in stream:
                for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    yield part, *row


_READ = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def read_chats(folder: str, parts: DataFrame, tokenizer: str) -> DataFrame:
    """Read the part files back: one row a conversation, digests taken from ids and mask.

    A part's task reads the conversations that begin in it, to their end in later parts.
    """
    spark = parts.sparkSession
    line = sorted(((r["part"], r["first"], r["last"]) for r in parts.collect()))  # one entry a part
    names = [p for p, _, _ in line]
    begins = [i == 0 or line[i - 1][2] != line[i][1] for i in range(len(line))]

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = ChatAssembler(tokenizer)
        for batch in batches:
            for i in batch.column(0).to_pylist():
                out, now = [], None
                skip = not begins[i]
                for part, conv, _, ids, mask in _turns(folder, names[i:]):
                    if skip and part == names[i] and conv == line[i][1]:
                        continue
                    if now is None or conv != now[0]:
                        if part != names[i]:
                            break
                        now = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                        out.append(now)
                    coded = np.frombuffer(ids, "<u4")
                    role, text, loss, chars = made.read(coded, np.unpackbits(np.frombuffer(mask, np.uint8), count=len(coded)))
                    now[1] += 1
                    now[2].update(f"{role}\n{text}\n".encode())
                    now[3] += len(loss)
                    now[4].update(loss.encode())
                    now[5] += chars
                cols = [[r[0] for r in out], [r[1] for r in out], [r[2].hexdigest() for r in out], [r[3] for r in out], [r[4].hexdigest() for r in out], [r[5] for r in out]]
                kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [c.split()[0] for c in _READ.split(", ")])

    n = max(1, len(line))
    return spark.range(0, len(line), 1, min(n, 4096)).mapInArrow(lean(read), _READ)

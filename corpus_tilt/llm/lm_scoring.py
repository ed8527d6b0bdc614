"""Cross-entropy difference: documents scored by matched target and background models.

Both are word bigram models (``ngram_model``) over one vocabulary, that of the whole corpus, with
the same smoothing; only their counts differ.  The target model counts the target documents, the
background model all of them.  A document's score is its mean loss a word under the target model
less that under the background model: the lower, the more it is like the target.

No bigram is pruned, and no model is gathered anywhere.  Bigrams that are at least ``HEAVY_SHARE`` of
all positions (2^20 at most, by arithmetic) are broadcast with their losses and added up where the
texts are read, so no key is hot afterwards.  Each other bigram of each document travels to the
task of its key (packed by blocks of documents), where all its occurrences meet; that task knows
its counts, works out its probability under both models from sums by word that the vocabulary
bounds, and sends back partial sums of losses, one for each document and cell.

Defined results: null or empty text has no words and null losses; documents that stand in
``target`` more than once count once; with no target text every score is null; repeated rows are
scored each; a null id is scored, and never a target; an empty table gives no rows; columns other
than those named are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column_slices, lean, workers_import, written
from .ngram_model import _STRETCH, _SUMS, KEY_BITS, Counter, ModelStats, Tokens, _stretch_rows, by_cell, cell_of, cells_for, counted, merged, model_stats, packed, scramble, sums_of, unpacked, unscramble, vocabulary

#: Target ids up to this number are broadcast (eight bytes each); more are joined by a sort-merge.
MOST_IDS = 4_000_000
HEAVY_SHARE = 2.0**-20
_BLOCK = 256
_POSITIONS = "cell long, block long, n long, marks binary, blob binary, ids array<long>, sizes array<long>"
_PARTS = "block long, docs binary, losses binary, ids array<long>, sizes array<long>"
_SCORES = "doc_id long, n_words long, target_loss double, background_loss double"


def _names(schema: str) -> list[str]:
    return [c.split()[0] for c in schema.split(", ")]


def _bigram_counts(shared, cells: int):
    """Stretches of bigrams: of target documents in the first ``cells`` cells, of all documents in as many after them."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, totals = shared.value, (Counter(cells, KEY_BITS), Counter(cells, KEY_BITS))

        def rows(model: int) -> list[tuple[int, int, bytes]]:
            return [(cell + model * cells, n, blob) for cell, n, blob in totals[model].rows()]

        for b in batches:
            marks = b.column(2).to_pylist()
            for lo, hi, texts in column_slices(b.column(1)):
                tokens = Tokens.of(texts, [None] * (hi - lo))
                keys = scramble(known.bigrams(tokens)[0])
                own = np.repeat(np.array(marks[lo:hi], bool), np.diff(tokens.cuts))
                for model, some in enumerate((keys[own], keys)):
                    totals[model].add(some)
                    if totals[model].full():
                        yield _stretch_rows(rows(model))
        if last := rows(0) + rows(1):
            yield _stretch_rows(last)

    return count


def _model_sums(cells: int):
    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for cell, n, blob in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                keys, counts = unpacked(n, blob, "<u8")
                rows = sums_of(unscramble(keys), counts.astype(np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows[0]), cell // cells, np.int32)), *(pa.array(r) for r in rows)], ["model", *_names(_SUMS)])

    return sums


def _heavy(stretches: DataFrame, cells: int, models: list[ModelStats], positions: int) -> tuple[np.ndarray, np.ndarray]:
    """The frequent bigrams (scrambled keys, in order) and the losses of each under both models."""
    least = max(2, positions * HEAVY_SHARE)

    def often(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for n, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                keys, counts = unpacked(n, blob, "<u8")
                yield pa.RecordBatch.from_arrays([pa.array(keys[counts >= least].view(np.int64)), pa.array(counts[counts >= least].view(np.int64))], ["key", "n"])

    every = stretches.where(F.col("cell") >= cells).mapInArrow(lean(often), "key long, n long").toArrow()
    order = np.argsort(every["key"].to_numpy().view(np.uint64))
    keys, counts = every["key"].to_numpy().view(np.uint64)[order], every["n"].to_numpy()[order]
    asked = stretches.sparkSession.sparkContext.broadcast(keys)

    def these(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for n, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                own, times = unpacked(n, blob, "<u8")
                some = np.isin(own, asked.value, assume_unique=True)
                yield pa.RecordBatch.from_arrays([pa.array(own[some].view(np.int64)), pa.array(times[some].view(np.int64))], ["key", "n"])

    aimed = stretches.where(F.col("cell") < cells).mapInArrow(lean(these), "key long, n long").toArrow()
    target = np.zeros(len(keys), np.int64)
    target[np.searchsorted(keys, aimed["key"].to_numpy().view(np.uint64))] = aimed["n"].to_numpy()
    plain = unscramble(keys)
    return keys, np.stack([-np.log(m.probability(plain, n)) for m, n in zip(models, (target, counts), strict=True)]).astype(np.float32)


def _position_rows(shared, heavy, cells: int):
    """Bigrams of blocks of documents by cell, but for heavy ones; and a row a block (cells below zero) with its ids, numbers of words, and sums of heavy ones' losses."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, (frequent, losses), block = shared.value, heavy.value, TaskContext.get().partitionId() << 32
        for b in batches:
            ids, marks = b.column(0).to_pylist(), b.column(2).to_pylist()
            out = []
            for lo, hi, texts in column_slices(b.column(1)):
                for at in range(lo, hi, _BLOCK):
                    upto = min(at + _BLOCK, hi)
                    tokens = Tokens.of(texts[at - lo : upto - lo], [None] * (upto - at))
                    doc = np.repeat(np.arange(upto - at, dtype=np.uint8), np.diff(tokens.cuts))
                    keys = scramble(known.bigrams(tokens)[0])
                    added = np.zeros((2, upto - at))
                    if len(frequent):
                        place = np.minimum(np.searchsorted(frequent, keys), len(frequent) - 1)
                        often = frequent[place] == keys
                        added = np.stack([np.bincount(doc[often], x[place[often]], upto - at) for x in losses])
                        keys, doc = keys[~often], doc[~often]
                    order = np.argsort(keys, kind="stable")
                    keys, doc = keys[order], doc[order]
                    flags = np.packbits(np.array(marks[at:upto], bool)).tobytes()
                    cell = cell_of(keys, cells, KEY_BITS)
                    cuts = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(keys)] if len(keys) else [0]
                    out += [(int(cell[x]), block, y - x, flags, packed(keys[x:y], doc[x:y]), None, None) for x, y in zip(cuts, cuts[1:], strict=False)]
                    out.append((-1 - block % 64, block, 0, None, added.tobytes(), ids[at:upto], np.diff(tokens.cuts).tolist()))
                    block += 1
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], _names(_POSITIONS))

    return rows


def _cell_losses(shared):
    """Partial sums of losses under both models, by block: the documents, and two numbers for each.  Blocks' own rows go on."""

    def losses(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cell, parts in by_cell(batches):
            blocks, sizes, marks, blobs, ids, words = ([x for p in parts for x in p.column(i).to_pylist()] for i in range(1, 7))
            if cell < 0:
                yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int64()), pa.nulls(len(blocks), pa.binary()), pa.array(blobs, pa.binary()), pa.array(ids, pa.list_(pa.int64())), pa.array(words, pa.list_(pa.int64()))], _names(_PARTS))
                continue
            got = [unpacked(n, blob, "u1") for n, blob in zip(sizes, blobs, strict=True)]
            own = np.concatenate([g[0] for g in got])
            place = np.concatenate([g[1].astype(np.int32) + np.int32(_BLOCK * j) for j, g in enumerate(got)])
            mark = np.concatenate([np.unpackbits(np.frombuffer(m, np.uint8))[g[1]] for m, g in zip(marks, got, strict=True)])
            keys, every = merged(own, np.ones(len(own), np.int32))
            of = np.searchsorted(keys, own).astype(np.int32)
            counts = (np.bincount(of, mark, len(keys)).astype(np.int64), every)
            keys, width = unscramble(keys), _BLOCK * len(blocks)
            sums = [np.bincount(place, -np.log(m.probability(keys, n))[of], width).reshape(-1, _BLOCK) for m, n in zip(shared.value, counts, strict=True)]
            docs = [np.flatnonzero(row) for row in np.bincount(place, minlength=width).reshape(-1, _BLOCK)]
            out = [np.stack([s[j, d] for s in sums]).astype(np.float32).tobytes() for j, d in enumerate(docs)]
            none = pa.nulls(len(docs), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int64()), pa.array([d.astype(np.uint8).tobytes() for d in docs], pa.binary()), pa.array(out, pa.binary()), none, none], _names(_PARTS))

    return losses


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Scores of each block's documents, from its partial sums and its row of ids."""
    for _, parts in by_cell(batches, "block"):
        total = np.zeros((2, _BLOCK))
        ids, sizes = [], []
        for b in parts:
            for docs, losses, own, words in zip(*(b.column(c).to_pylist() for c in range(1, 5)), strict=True):
                if own is not None:
                    ids, sizes = own, words
                    total[:, : len(own)] += np.frombuffer(losses, np.float64).reshape(2, -1)
                else:
                    total[:, np.frombuffer(docs, np.uint8)] += np.frombuffer(losses, np.float32).reshape(2, -1)
        n = np.array(sizes, np.int64)
        mean = total[:, : len(n)] / np.maximum(n, 1)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(n), *(pa.array(m, mask=n == 0) for m in mean)], _names(_SCORES))


def cross_entropy_difference(docs: DataFrame, target: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: doc_id, score, n_words, target_loss, background_loss (natural log a word).

    ``target`` holds the ids of the target's documents.
    """
    spark = docs.sparkSession
    workers_import(spark)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    plain = texts.select("text", F.lit(None).cast("string").alias("grp"))
    cells = cells_for(plain)
    known = vocabulary(plain, cells)
    shared = spark.sparkContext.broadcast(known)
    wanted = written(target.select(F.col(id_col).cast("long").alias("doc_id")).where("doc_id is not null").distinct().withColumn("mark", F.lit(True)), "target")
    few = wanted.limit(MOST_IDS + 1).count() <= MOST_IDS
    marked = texts.join(wanted.hint("broadcast" if few else "merge"), "doc_id", "left").select("doc_id", "text", F.coalesce("mark", F.lit(False)).alias("mark"))
    if not few:  # the same blocks whenever a task is run again
        marked = marked.sortWithinPartitions("doc_id", F.xxhash64("text"))
    stretches = counted(marked.mapInArrow(lean(_bigram_counts(shared, cells)), _STRETCH), "bigrams")
    sums = written(stretches.mapInArrow(lean(_model_sums(cells)), f"model int, {_SUMS}").groupBy("model", "id").agg(*(F.sum(c).alias(c) for c in _names(_SUMS)[1:])), "sums")
    models = [model_stats(sums.where(F.col("model") == m), known.size) for m in (0, 1)]
    heavy = spark.sparkContext.broadcast(_heavy(stretches, cells, models, known.tokens))
    positions = marked.mapInArrow(lean(_position_rows(shared, heavy, cells)), _POSITIONS).repartition(F.col("cell")).sortWithinPartitions("cell")
    parts = positions.mapInArrow(lean(_cell_losses(spark.sparkContext.broadcast(models))), _PARTS)
    scored = parts.repartition(F.col("block")).sortWithinPartitions("block").mapInArrow(lean(_add_up), _SCORES)
    usable = F.lit(bool(models[0].total.any()))
    return scored.select("doc_id", F.when(usable, F.col("target_loss") - F.col("background_loss")).alias("score"), "n_words", F.when(usable, F.col("target_loss")).alias("target_loss"), F.when(usable, F.col("background_loss")).alias("background_loss"))

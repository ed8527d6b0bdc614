"""Quality rules: simple counts of a text, and n-gram perplexity within bands of its language.

The perplexity is that of a word bigram model of the text's language (``ngram_model``), counted in
Spark over all texts; a word outside the vocabulary is spelled byte by byte as well.  No bigram is
pruned: those that are at least ``HEAVY_SHARE`` of all positions (2^20 at most, by arithmetic) are
broadcast as sorted hash arrays and added up where the texts are read; every other one travels to
the task of its key, packed by blocks of documents, where all its occurrences meet, and partial
sums of losses come back, one for each document and cell.

A language's band is set by the spread of its own documents: median log-perplexity plus and minus
``width`` times the spread between its quartiles, at least ``least``; short texts, whose mean loss
varies more, have a wider one by the root of 1/2 + 100 / n_words.  Documents outside are rejected,
be they gibberish (above) or repetition (below).  A model that prunes nothing knows a group of copies
(and a text of words that no other has) by heart, so what is too easy is told by the lower order
alone (``word_perplexity``, with a band of its own on both sides): it counts the distinct words before
a word, which copies do not raise.

Defined results: a null text has no words and fails; an empty table gives no rows; languages are
compared as they stand, null being one of its own; a language none of whose documents passes the
simple rules has no band and rejects none by it; repeated rows each count; a null id is a document
like others.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACES, column_slices, lean, text_bytes, workers_import, written
from .ngram_model import _STRETCH, _SUMS, ID_BITS, KEY_BITS, ModelStats, Tokens, Vocabulary, bigram_counter, by_cell, cell_of, cells_for, counted, model_stats, packed, scramble, stretch_sums, unpacked, unscramble, vocabulary

SIGNS = "#*$%&|<>"
_BIN = 1 / 128
HEAVY_SHARE = 2.0**-20
_BLOCK = 1 << 16  # documents, whose places have two bytes


def text_counts(text: str) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of a text."""
    words = text_bytes(text).split()
    n = len(words)
    word_chars = len(text) - sum(map(text.count, SPACES))
    symbols = sum(map(text.count, SIGNS))
    lines = text.split("\n")
    dup_lines = 0
    if len(set(lines)) < len(lines):
        dup_lines = sum(k - 1 for line, k in Counter(lines).items() if k > 1 and line.strip(SPACES))
    repeat = 0
    if n > 3:
        grams = list(zip(words, words[1:], words[2:], strict=False))
        if len(set(grams)) < len(grams):
            counts = Counter(grams)
            covered, upto = 0, 0
            for i, g in enumerate(grams):
                if counts[g] > 1:
                    covered += i + 3 - max(i, upto)
                    upto = i + 3
            repeat = covered
    return n, word_chars, symbols, dup_lines, repeat


def _heavy(stretches: DataFrame, stats: ModelStats, positions: int) -> tuple[np.ndarray, np.ndarray]:
    """The frequent bigrams (scrambled keys, in order) and their losses."""
    least = max(2, positions * HEAVY_SHARE)

    def often(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for n, blob in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                keys, counts = unpacked(n, blob, "<u8")
                some = counts >= least
                yield pa.RecordBatch.from_arrays([pa.array(keys[some].view(np.int64)), pa.array(counts[some].astype(np.int64))], ["key", "n"])

    got = stretches.mapInArrow(lean(often), "key long, n long").toArrow()
    keys, counts = got["key"].to_numpy().view(np.uint64), got["n"].to_numpy()
    order = np.argsort(keys)
    keys, counts = keys[order], counts[order]
    return keys, -np.log(stats.probability(unscramble(keys), counts)).astype(np.float32)


def fit(texts: DataFrame, cells: int) -> tuple[Vocabulary, ModelStats, tuple[np.ndarray, np.ndarray]]:
    """Vocabulary, sums by token and frequent bigrams of rows (text, grp): what reaches the driver, all bounded."""
    words = vocabulary(texts, cells)
    stretches = counted(texts.select("text", "grp").mapInArrow(lean(bigram_counter(texts.sparkSession.sparkContext.broadcast(words), cells)), _STRETCH), "bigrams")
    stats = model_stats(stretches.mapInArrow(lean(stretch_sums), _SUMS), words.size)
    return words, stats, _heavy(stretches, stats, words.tokens)


_COUNTS = "doc_id long, lang string, version long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"
_SCORED = f"{_COUNTS}, log_perplexity double, word_perplexity double"
_POSITIONS = "cell long, block long, n long, blob binary, own binary"
_PARTS = "block long, docs binary, losses binary, own binary"


def _names(schema: str) -> list[str]:
    return [c.split()[0] for c in schema.split(", ")]


def _sent(batch: pa.RecordBatch) -> bytes:
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, batch.schema) as to:
        to.write_batch(batch)
    return out.getvalue().to_pybytes()


def _position_rows(shared, heavy, cells: int):
    """Bigrams of blocks of documents by cell, but for heavy ones; and a row a block (cells below zero) with its documents' counts, and their losses by spelling and heavy bigrams, and by the lower order."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (known, low), (frequent, losses), block = shared.value, heavy.value, TaskContext.get().partitionId() << 32
        for b in batches:
            langs = b.column(1).to_pylist()
            for lo, hi, texts in column_slices(b.column(3)):
                for at in range(lo, hi, _BLOCK):
                    upto = min(at + _BLOCK, hi)
                    some = [t or "" for t in texts[at - lo : upto - lo]]
                    tokens = Tokens.of(some, langs[at:upto])
                    doc = np.repeat(np.arange(upto - at, dtype=np.uint16), np.diff(tokens.cuts))
                    keys, word = known.bigrams(tokens)
                    loss = np.where(word, 0.0, -known.spelled(tokens))
                    simple = loss + low[(keys & np.uint64((1 << ID_BITS) - 1)).astype(np.int64)]
                    keys = scramble(keys)
                    if len(frequent):
                        place = np.minimum(np.searchsorted(frequent, keys), len(frequent) - 1)
                        often = frequent[place] == keys
                        loss[often] += losses[place[often]]
                        order = np.flatnonzero(~often)
                        order = order[np.argsort(keys[order], kind="stable")]
                    else:
                        order = np.argsort(keys, kind="stable")
                    got = [text_counts(t) for t in some]
                    own = b.slice(at, upto - at)
                    counts = [pa.array([g[i] for g in got], pa.int64()) for i in range(5)]
                    sums = [pa.array(np.bincount(doc, x, upto - at)) for x in (loss, simple)]
                    out = [(-1 - block % 64, block, 0, None, _sent(pa.RecordBatch.from_arrays([*own.columns[:3], *counts, *sums], [*_names(_COUNTS), "loss", "simple"])))]
                    keys, doc = keys[order], doc[order]
                    cell = cell_of(keys, cells, KEY_BITS)
                    cuts = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(keys)] if len(keys) else [0]
                    out += [(int(cell[x]), block, y - x, packed(keys[x:y], doc[x:y]), None) for x, y in zip(cuts, cuts[1:], strict=False)]
                    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()))], _names(_POSITIONS))
                    block += 1

    return rows


def _cell_losses(shared):
    """Partial sums of losses by block: the documents, and a number for each.  Blocks' own rows go on."""

    def losses(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cell, parts in by_cell(batches):
            if cell < 0:
                for p in parts:
                    none = pa.nulls(p.num_rows, pa.binary())
                    yield pa.RecordBatch.from_arrays([p.column(1), none, none, p.column(4)], _names(_PARTS))
                continue
            blocks, sizes, blobs = ([x for p in parts for x in p.column(i).to_pylist()] for i in (1, 2, 3))
            got = [unpacked(n, blob, "<u2") for n, blob in zip(sizes, blobs, strict=True)]
            keys = np.concatenate([g[0] for g in got])
            order = np.argsort(keys, kind="stable")
            new = np.concatenate([[True], np.diff(keys[order]) != 0])
            at = np.flatnonzero(new)
            each = -np.log(shared.value.probability(unscramble(keys[order[at]]), np.diff(at, append=len(keys))))
            loss = np.empty(len(keys))
            loss[order] = each[np.cumsum(new) - 1]
            docs, sums, lo = [], [], 0
            for _, doc in got:
                own = np.flatnonzero(np.bincount(doc))
                docs.append(own.astype("<u2").tobytes())
                sums.append(np.bincount(doc, loss[lo : lo + len(doc)])[own].astype("<f4").tobytes())
                lo += len(doc)
            yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int64()), pa.array(docs, pa.binary()), pa.array(sums, pa.binary()), pa.nulls(len(blocks), pa.binary())], _names(_PARTS))

    return losses


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each block's documents with their mean losses, from its own row and its partial sums."""
    for _, parts in by_cell(batches, "block"):
        total, counts = np.zeros(_BLOCK), None
        for b in parts:
            for docs, losses, own in zip(*(b.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                if own is None:
                    total[np.frombuffer(docs, "<u2")] += np.frombuffer(losses, "<f4")
                else:
                    counts = pa.ipc.open_stream(own).read_next_batch()
        size = counts.column("n_words").to_numpy()
        sums = counts.column("loss").to_numpy() + total[: len(size)], counts.column("simple").to_numpy()
        yield pa.RecordBatch.from_arrays([*counts.columns[:-2], *(pa.array(x / np.maximum(size, 1), mask=size == 0) for x in sums)], _names(_SCORED))


def bands(scored: DataFrame, column: str, width: float, least: float) -> DataFrame:
    """Per language (key ``band_lang``): the median of ``column`` and the reach about it, from a histogram of all its passing documents."""
    cells = scored.where(~F.col("base_failed") & F.col(column).isNotNull()).groupBy(F.coalesce(F.concat(F.lit("="), "lang"), F.lit("")).alias("band_lang"), F.floor(F.col(column) / _BIN).alias("cell")).agg(F.count("*").alias("n"))
    by = Window.partitionBy("band_lang")
    upto = F.sum("n").over(by.orderBy("cell").rowsBetween(Window.unboundedPreceding, 0))
    told = cells.withColumns({"upto": upto, "all": F.sum("n").over(by)})
    at = lambda q: F.min(F.when(F.col("upto") >= q * F.col("all"), F.col("cell"))) * F.lit(_BIN)
    quart = told.groupBy("band_lang").agg(at(0.25).alias("q1"), at(0.5).alias("q2"), at(0.75).alias("q3"))
    reach = F.greatest(F.lit(least), width * (F.col("q3") - F.col("q1")))
    return quart.select("band_lang", F.col("q2").alias(f"{column}_mid"), reach.alias(f"{column}_reach"))


def quality(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", min_words: int = 50, max_repeat_percent: int = 50, width: float = 3.5, least: float = 0.05) -> DataFrame:
    """One row a document: the counts, base_failed, log_perplexity and its upper bound, word_perplexity and its bounds, kept, and ``version``, the hash of its text."""
    spark = docs.sparkSession
    workers_import(spark)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(lang_col).cast("string").alias("lang"), F.xxhash64(F.col(text_col)).alias("version"), F.col(text_col).alias("text"))
    plain = texts.select("text", F.col("lang").alias("grp"))
    cells, share = cells_for(plain), spark.sparkContext.broadcast
    words, stats, heavy = fit(plain, cells)
    positions = texts.mapInArrow(lean(_position_rows(share((words, -np.log(stats.lower).astype(np.float32))), share(heavy), cells)), _POSITIONS).repartition(F.col("cell")).sortWithinPartitions("cell")
    parts = positions.mapInArrow(lean(_cell_losses(share(stats))), _PARTS)
    scored = parts.repartition(F.col("block")).sortWithinPartitions("block").mapInArrow(lean(_add_up), _SCORED)
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat_percent * F.col("n_words"))
    scored = written(scored.withColumn("base_failed", failed), "quality")
    wider = F.sqrt(0.5 + 100 / F.greatest(F.col("n_words"), F.lit(1)))
    edge = lambda column, sign: F.col(f"{column}_mid") + sign * F.col(f"{column}_reach") * wider
    inside = F.coalesce((F.col("log_perplexity") <= F.col("upper")) & F.col("word_perplexity").between(F.col("word_lower"), F.col("word_upper")), F.lit(True))
    told = scored.withColumn("band_lang", F.coalesce(F.concat(F.lit("="), "lang"), F.lit("")))
    for column in ("log_perplexity", "word_perplexity"):
        told = told.join(bands(scored, column, width, least), "band_lang", "left")
    told = told.withColumns({"upper": edge("log_perplexity", 1), "word_lower": edge("word_perplexity", -1), "word_upper": edge("word_perplexity", 1)})
    return told.withColumn("kept", ~F.col("base_failed") & inside).select(*scored.columns, "upper", "word_lower", "word_upper", "kept")

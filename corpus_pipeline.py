"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again as the next one's input.

In every stage a row is known by its id and the hash of its text, so a null id is a document like
others (it is linked with nothing), rows that repeat an id are judged each by its text, and rows
that repeat both meet the same fate.  Empty tables give empty tables; further columns, whatever
their names, come out as they went in.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_tilt.llm.common import fresh, table, tokenizer_path, written
from corpus_tilt.llm.decontaminate import contaminated
from corpus_tilt.llm.line_dedup import dedup_lines
from corpus_tilt.llm.near_dedup import near_duplicates
from corpus_tilt.llm.packing import pack, token_pieces
from corpus_tilt.llm.quality_rules import quality


def _rows(docs: DataFrame, told: DataFrame, how: str, *more: str) -> DataFrame:
    """The rows of ``docs`` that stand (``left_semi``) or do not stand (``left_anti``) in ``told`` by id, text and ``more``."""
    names = fresh(docs, "own_id", "own_version", *(f"own_{m}" for m in more))
    own = [F.col("doc_id").cast("long"), F.xxhash64("text"), *(F.col(m).cast("string") for m in more)]
    there = told.select(*(F.col(c).alias(n) for c, n in zip(("doc_id", "version", *more), names, strict=True))).distinct()
    same = [a.eqNullSafe(F.col(n)) for a, n in zip(own, names, strict=True)]
    return docs.join(there.hint("merge"), same, how).select(*docs.columns)


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the quality rules, each by its text and language; null and empty texts fail."""
    return _rows(docs, quality(docs).where("kept"), "left_semi", "lang")


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that stand before, in themselves or another; ``n_chars`` follows the text.

    The first of equal or near lines stays, by (doc_id, hash of the text, line); a document that
    loses all its lines goes; null ids and texts without lines stay as they are.
    """
    return dedup_lines(docs).withColumn("n_chars", F.length("text").cast("long"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group, that of the least id; documents without words or id stay."""
    return _rows(docs, near_duplicates(docs).where("kept"), "left_semi")


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark item occurs; null and empty texts hold none."""
    found = written(contaminated(docs, table(spark, sf_dir, "benchmark")).select("doc_id", "version").distinct(), "contaminated")
    return _rows(docs, found, "left_anti")


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places of the remaining documents' pieces in sequences of 4096 tokens; every row is packed, an empty text as its end id."""
    return pack(token_pieces(docs, tokenizer_path("word_bpe_49k.json"), end_id=1, capacity=4096), 4096).drop("level")


STAGES = [("quality_rules", quality_rules), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("decontamination", decontamination), ("packing", packing)]

#: The stages use a model, an edit join and a packing search, which SQL does not express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs

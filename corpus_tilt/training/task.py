"""Tasks: a generic and a specific set of examples (id, side, split, payload) with leak-free splits.

A task is a DataFrame of whole texts, pairs, vectors or rows; ``source`` draws batches from it.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.scratch import scratch


def text_split(text: Column) -> Column:
    """train, valid or test by a hash of the text, so equal texts fall together."""
    h = F.conv(F.substring(F.md5(F.lower(F.trim(text))), 1, 8), 16, 10).cast("long") % 10
    return F.when(h < 6, "train").when(h < 8, "valid").otherwise("test")


def _examples(df: DataFrame, key: Column, text: Column, side: int) -> DataFrame:
    raw = F.encode(text, "utf-8")
    return df.select(key.cast("long").alias("id"), F.lit(side).alias("side"), text_split(text).alias("split"), raw.alias("payload")).where(F.octet_length("payload") >= 2)


#: Targets among the documents: predicates over ``documents``.
DOCUMENT_TARGETS = {"lang_fr": "lang = 'fr'", "lang_de": "lang = 'de'", "lang_es": "lang = 'es'", "source_0": "source = 'src0'"}
TARGETS = (*DOCUMENT_TARGETS, "quality_low", "benchmark", "pages_html", "conv_user", "conv_assistant")


def text_examples(spark: SparkSession, sf_dir: str, target: str) -> DataFrame:
    """Examples (id, side, split, payload) of a text task; generic texts that a specific set holds are left out."""
    read = lambda n: spark.read.parquet(f"{sf_dir}/{n}.parquet")
    docs = read("documents")
    doc = lambda df, side: _examples(df, F.col("doc_id"), F.col("text"), side)
    if target in DOCUMENT_TARGETS:
        own = F.expr(DOCUMENT_TARGETS[target])
        return doc(docs.where(~own), 0).unionByName(doc(docs.where(own), 1))
    if target == "quality_low":
        bad = read("labels").where("quality = 0").select("doc_id")
        return doc(docs.join(bad, "doc_id", "left_anti"), 0).unionByName(doc(docs.join(bad, "doc_id", "left_semi"), 1))
    if target == "benchmark":
        items = _examples(read("benchmark"), F.col("item_id"), F.col("text"), 1)
        clean = docs.join(read("benchmark").select(F.md5("text").alias("h")), F.md5(docs["text"]) == F.col("h"), "left_anti")
        return doc(clean, 0).unionByName(items)
    if target == "pages_html":
        return doc(docs, 0).unionByName(_examples(read("pages"), F.col("page_id"), F.col("html"), 1))
    if target in ("conv_user", "conv_assistant"):
        turns = read("conversations").where(F.col("role") == target.removeprefix("conv_"))
        return doc(docs, 0).unionByName(_examples(turns, F.col("conv_id") * 1000 + F.col("turn"), F.col("text"), 1))
    raise ValueError(f"unknown target {target}; there are {TARGETS}")


def stored_examples(examples: DataFrame) -> DataFrame:
    """The examples written once by side and split, so that a step reads its own part by partition pruning."""
    where = scratch(examples.sparkSession, "examples")
    examples.select("id", "side", "split", "payload").write.partitionBy("side", "split").parquet(where)
    schema = T.StructType([*(f for f in examples.schema if f.name in ("id", "payload")), T.StructField("side", T.IntegerType()), T.StructField("split", T.StringType())])
    return examples.sparkSession.read.schema(schema).parquet(where)


def stored_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents of all text tasks, written once by split, with what tells their targets: a task more is no copy more."""
    read = lambda n: spark.read.parquet(f"{sf_dir}/{n}.parquet")
    docs = read("documents")
    low = read("labels").where("quality = 0").select("doc_id", F.lit(True).alias("low")).distinct()
    items = read("benchmark").select(F.md5("text").alias("h"), F.lit(True).alias("item")).distinct()
    told = docs.join(low, "doc_id", "left").join(items, F.md5(docs["text"]) == F.col("h"), "left")
    flags = [F.coalesce(c, F.lit(False)).alias(c) for c in ("low", "item")]
    rows = told.select(F.col("doc_id").cast("long").alias("id"), F.encode("text", "utf-8").alias("payload"), "lang", "source", *flags, text_split(F.col("text")).alias("split")).where(F.octet_length("payload") >= 2)
    where = scratch(spark, "texts")
    rows.write.partitionBy("split").parquet(where)
    return spark.read.schema(rows.schema).parquet(where)


def shared_examples(spark: SparkSession, sf_dir: str, target: str, texts: DataFrame) -> DataFrame:
    """``text_examples`` over ``stored_texts``; only rows of other tables are written."""
    doc = lambda own, side: texts.where(own).select("id", F.lit(side).alias("side"), "split", "payload")
    if own := {**DOCUMENT_TARGETS, "quality_low": "low"}.get(target):
        return doc(~F.expr(own), 0).unionByName(doc(F.expr(own), 1))
    other = stored_examples(text_examples(spark, sf_dir, target).where("side = 1"))
    return doc(~F.col("item") if target == "benchmark" else F.lit(True), 0).unionByName(other)


def pair_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User turn and next assistant turn; specific are pairs whose user turn has an accented letter."""
    from pyspark.sql import Window

    w = Window.partitionBy("conv_id").orderBy("turn")
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").withColumns({"r": F.lead("role").over(w), "tgt": F.lead("text").over(w)}).where("role = 'user' and r = 'assistant'")
    h = F.conv(F.substring(F.md5(F.col("conv_id").cast("string")), 1, 8), 16, 10).cast("long") % 10
    split = F.when(h < 6, "train").when(h < 8, "valid").otherwise("test")
    return turns.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("text").rlike("[À-ÿ]").cast("int").alias("side"), split.alias("split"), F.struct(F.col("text").alias("src"), "tgt").alias("payload"))


def planted_pairs(spark: SparkSession, sf_dir: str, words: int = 8, classes: int = 22) -> DataFrame:
    """Pairs with a rule that the pair model can learn: the first distinct words of a document, and the same by their hash class.

    Specific are French documents; the generic set has the other languages, and every second of its
    targets is in the source's order, so that some generic rows teach the rule and some do not.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").where("text is not null")
    head = F.slice(F.array_distinct(F.filter(F.split(F.lower("text"), "[^a-z\u00e0-\u00ff]+"), lambda w: w != "")), 1, words)
    ordered = F.transform(F.array_sort(F.transform(head, lambda w: F.struct((F.crc32(w.cast("binary")) % classes).alias("c"), w.alias("w")))), lambda r: r["w"])
    side = (F.col("lang") == "fr").cast("int")
    h = F.conv(F.substring(F.md5(F.concat_ws(" ", head)), 1, 8), 16, 10).cast("long")
    told = F.when((side == 1) | (h % 2 == 0), ordered).otherwise(head)
    tenth = F.floor(h / 16) % 10
    split = F.when(tenth < 6, "train").when(tenth < 8, "valid").otherwise("test")
    return docs.where(F.size(head) >= 3).select(F.col("doc_id").alias("id"), side.alias("side"), split.alias("split"), F.struct(F.concat_ws(" ", head).alias("src"), F.concat_ws(" ", told).alias("tgt")).alias("payload"))


def vector_examples(spark: SparkSession, sf_dir: str, planted: bool) -> DataFrame:
    """Vectors as images: generic are even ids, specific odd ids of half the classes.  ``planted``: classes by signs of three entries."""
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    sign = sum(((F.get("embedding", F.lit(i)) > 0).cast("int") * (1 << i) for i in range(3)), F.lit(0))
    label = sign if planted else F.col("label")
    half = 4 if planted else 5
    h = F.conv(F.substring(F.md5(F.col("vec_id").cast("string")), 1, 8), 16, 10).cast("long") % 10
    split = F.when(h < 4, "train").when(h < 6, "valid").otherwise("test")
    side = F.when(F.col("vec_id") % 2 == 0, 0).when(label < half, 1)
    return e.select(F.col("vec_id").alias("id"), side.alias("side"), split.alias("split"), F.struct(F.col("embedding").alias("x"), label.cast("int").alias("y")).alias("payload")).where("side is not null")


def row_examples(spark: SparkSession, sf_dir: str, nation: int = 0) -> DataFrame:
    """Order lines with the return flag as class; specific are those of one nation's customers."""
    read = lambda n: spark.read.parquet(f"{sf_dir}/{n}.parquet")
    j = read("lineitem").join(read("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(read("customer"), F.col("o_custkey") == F.col("c_custkey"))
    x = F.array(F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.log("l_extendedprice") / 10, F.year("l_shipdate") - F.lit(1995.0), F.col("c_acctbal") / 10000)
    y = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    key = F.abs(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate"))
    split = F.when(key % 10 < 6, "train").when(key % 10 < 8, "valid").otherwise("test")
    return j.select(key.alias("id"), (F.col("c_nationkey") == nation).cast("int").alias("side"), split.alias("split"), F.struct(x.alias("x"), y.alias("y")).alias("payload"))


def plain(payload):
    if hasattr(payload, "asDict"):
        return tuple(payload)
    return bytes(payload) if isinstance(payload, bytearray) else payload


def payload_bytes(examples: DataFrame) -> Column:
    """Bytes of a row's payload, about: 20 for each number, as text and in Python alike."""
    kind = examples.schema["payload"].dataType
    if isinstance(kind, T.BinaryType):
        return F.octet_length("payload")
    parts = []
    for f in kind.fields:
        own = F.col("payload")[f.name]
        each = F.octet_length(own) if isinstance(f.dataType, T.StringType) else 20 * F.size(own) if isinstance(f.dataType, T.ArrayType) else F.lit(20)
        parts.append(F.coalesce(each, F.lit(0)))
    return sum(parts, F.lit(16))


@dataclass
class Task:
    """A generic (side 0) and a specific set (side 1), each split in train, valid and test."""

    name: str
    examples: DataFrame
    stored: bool = False  # by split at least, in the shared folder

    def frame(self, side: int, split: str) -> DataFrame:
        return self.examples.where((F.col("side") == side) & (F.col("split") == split))

    def rows(self, side: int, split: str) -> tuple[np.ndarray, list]:
        """Ids and payloads of all rows, in id order; for tasks of a checked size (``size``)."""
        got = sorted(((r["id"], plain(r["payload"])) for r in self.frame(side, split).select("id", "payload").collect()), key=lambda r: r[0])
        if not got:
            raise ValueError(f"{self.name}: no {split} examples on side {side}")
        return np.array([g[0] for g in got]), [g[1] for g in got]

    def size(self) -> int:
        """Bytes of all payloads, about."""
        return self.examples.agg(F.sum(payload_bytes(self.examples))).first()[0] or 0


class MixtureTarget:
    """A task whose specific set is several tasks' together, in given shares: each row has copies in proportion.

    Shares are kept by drawing: row i of a part with share p stands ``round(p / least share)`` times.
    """

    def __new__(cls, parts: list[tuple[Task, float]]) -> Task:
        least = min(p for _, p in parts)
        out = parts[0][0].examples.where("side = 0")
        for turn, (task, share) in enumerate(parts):
            copies = F.explode(F.sequence(F.lit(0), F.lit(max(1, round(share / least)) - 1))).alias("copy")
            own = task.examples.where("side = 1").select("*", copies)
            key = (F.col("id") * len(parts) + turn) * 1000 + F.col("copy")
            out = out.unionByName(own.withColumn("id", key).drop("copy"))
        texts = out.where("side = 1").select(F.md5("payload").alias("h")).distinct()
        generic = out.where("side = 0").join(texts, F.md5("payload") == F.col("h"), "left_anti")
        return Task("+".join(t.name for t, _ in parts), generic.unionByName(out.where("side = 1")))


def build_task(spark: SparkSession, sf_dir: str, name: str, texts: DataFrame | None = None) -> Task:
    """``texts``: ``stored_texts``, where several text tasks share them."""
    if texts is not None and name in TARGETS:
        return Task(name, shared_examples(spark, sf_dir, name, texts), stored=True)
    if name == "pairs":
        df = pair_examples(spark, sf_dir)
    elif name == "pairs_planted":
        df = planted_pairs(spark, sf_dir)
    elif name in ("vectors", "vectors_planted"):
        df = vector_examples(spark, sf_dir, name == "vectors_planted")
    elif name == "rows":
        df = row_examples(spark, sf_dir)
    else:
        df = text_examples(spark, sf_dir, name)
    return Task(name, df)

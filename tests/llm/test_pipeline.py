"""The pipeline's stages on the smallest tables, each against its own input."""

import math
import random
from collections import Counter

import corpus_pipeline
from corpus_tilt.llm import quality_rules
from corpus_tilt.llm.decontaminate import contaminated
from corpus_tilt.llm.line_dedup import line_removals
from corpus_tilt.llm.near_dedup import near_duplicates

from ..conftest import SF


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").cache()
    columns, ids = docs.columns, {r["doc_id"] for r in docs.select("doc_id").collect()}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF).cache()
        if name == "packing":
            rows = out.collect()
            assert {r["doc_id"] for r in rows} == ids
            assert len({r["sequence_id"] for r in rows}) <= math.ceil(sum(r["length"] for r in rows) / 4096) + 2
            break
        now = {r["doc_id"] for r in out.select("doc_id").collect()}
        assert out.columns == columns and now <= ids and now
        if name == "near_dedup":
            assert all(r["kept"] for r in near_duplicates(out).collect())
        if name == "decontamination":
            assert contaminated(out, spark.read.parquet(f"{SF}/benchmark.parquet")).count() == 0
        docs, ids = out, now


ODD = [(None, "a null id of some words " * 12), (None, "another null id, of other words " * 12), (1, "one of two texts under an id " * 12), (1, "the other of the two texts " * 12), (2, None), (3, ""), (4, "word " * 9000), (5, "same row twice " * 20), (5, "same row twice " * 20), (6, "f\u00fcnf Zeilen\n\n" * 30)]


def test_stages_on_odd_rows_and_empty_tables(spark):
    docs = spark.createDataFrame(ODD, "doc_id long, text string").selectExpr("doc_id", "text", "'en' as lang", "'s' as source", "length(text) as n_chars", "1 as version", "2 as own_id", "3 as kept")
    for name, stage in corpus_pipeline.STAGES:
        none = stage(spark, docs.limit(0), SF)
        assert none.count() == 0, name
        out = stage(spark, docs, SF)
        if name == "packing":
            assert out.groupBy("doc_id", "piece").count().count() >= 8
            assert out.where("doc_id is null").count() == 2
            continue
        assert out.columns == docs.columns, name
        got = Counter((r["doc_id"], r["text"]) for r in out.collect())
        if name == "quality_rules":
            assert all(k[1] for k in got)
        elif name == "near_dedup":
            assert got == Counter(ODD)
        elif name == "decontamination":
            assert got == Counter(ODD)
        else:
            assert got[None, ODD[0][1]] == 1 and got[2, None] == 1 and got[3, ""] == 1


def test_quality_stage_judges_each_row(spark):
    rng = random.Random(1)
    words = [f"word{i}" for i in range(200)]
    good = [(i, " ".join(rng.choice(words) for _ in range(120))) for i in range(40)]
    rows = good + [(None, " ".join(rng.choice(words) for _ in range(150))), (7, "too short"), (None, "short too")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'en' as lang", "'s' as source", "length(text) as n_chars")
    got = {(r["doc_id"], r["text"]) for r in corpus_pipeline.quality_rules(spark, docs, SF).collect()}
    assert got == {*good, rows[40]}


def test_quality_stage_counts_bigrams_that_are_not_broadcast(spark, monkeypatch):
    """The stage keeps the same rows whether its bigrams are broadcast or all meet by key: none is dropped."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = []
    for share in (quality_rules.HEAVY_SHARE, 2.0):
        monkeypatch.setattr(quality_rules, "HEAVY_SHARE", share)
        kept.append(sorted(r["doc_id"] for r in corpus_pipeline.quality_rules(spark, docs, SF).collect()))
    assert kept[0] == kept[1] and 0 < len(kept[0]) < docs.count()


def test_line_stage_removes_what_two_share(spark):
    docs = spark.createDataFrame([(1, "one of a kind\nshared line of text"), (2, "another thing\nshared line of text\nshared line of text"), (3, "third text")], "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in corpus_pipeline.line_dedup(spark, docs, SF).collect()}
    assert got == {1: "one of a kind\nshared line of text", 2: "another thing", 3: "third text"}


def test_repeats_within_a_document_go_below_min_docs(spark):
    docs = spark.createDataFrame([(1, "a b\nx y"), (2, "a b\nc d\na b"), (3, "a b\na b\na b"), (4, "q\nq")], "doc_id long, text string")
    got = {r["doc_id"]: r["removed"] for r in line_removals(docs, min_docs=6).collect()}
    assert got == {1: [], 2: [2], 3: [1, 2], 4: [1]}

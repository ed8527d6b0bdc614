"""Streams against their batch form, restarts, parameter checkpoints, the data source, SQL functions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpus_tilt.functions import udfs
from corpus_tilt.models.main_models import ByteModel
from corpus_tilt.models.weight_models import LinearWeight
from corpus_tilt.operators import relational
from corpus_tilt.sources import io
from corpus_tilt.sources.scratch import scratch
from corpus_tilt.streaming.select import file_stream, stream_select
from corpus_tilt.training.bilevel import Setting, train_bilevel
from corpus_tilt.training.source import LocalSource
from corpus_tilt.training.task import build_task

from .conftest import SF


def test_a_stream_that_starts_again_goes_on(spark, tmp_path):
    """The second start selects from new files alone; batches that were done stay as they were."""
    where = str(tmp_path)
    docs = spark.createDataFrame([(i, f"text {i} " * (i % 5 + 1)) for i in range(40)], "doc_id long, text string")
    docs.where("doc_id < 20").coalesce(1).write.parquet(f"{where}/in")

    def run():
        stream = file_stream(spark, f"{where}/in", docs, 1)
        stream_select(stream, LinearWeight(), np.linspace(-1, 1, 16), 5, f"{where}/out", f"{where}/checkpoint").awaitTermination()
        return {(r["batch_id"], r["id"]) for r in spark.read.parquet(f"{where}/out").collect()}

    first = run()
    assert len(first) == 5 and run() == first
    docs.where("doc_id >= 20").coalesce(1).write.mode("append").parquet(f"{where}/in")
    second = run()
    assert first < second and {i for b, i in second - first} <= set(range(20, 40)) and len(second) == 10


def test_a_run_goes_on_from_its_parameters(spark, tmp_path):
    """Four steps are two, a checkpoint, and two more."""
    source = LocalSource(build_task(spark, SF, "lang_fr"), ByteModel(16), LinearWeight())
    s = Setting(steps=2, small=8, large=32)
    first = train_bilevel(source, "cosine", s)
    path = str(tmp_path / "p")
    for kind, v in (("theta", first.theta), ("alpha", first.trajectory[-1])):
        io.save_parameters(spark, path, "run", 2, kind, v)
        io.save_parameters(spark, path, "other", 9, kind, v * 0)
    theta, alpha = (io.load_parameters(spark, path, "run", kind) for kind in ("theta", "alpha"))
    assert np.array_equal(theta, first.theta) and np.array_equal(alpha, first.trajectory[-1])
    with pytest.raises(ValueError):
        io.load_parameters(spark, path, "run", "v")
    a, b = (train_bilevel(source, "cosine", s, t, w) for t, w in ((theta, alpha), (first.theta, first.trajectory[-1])))
    assert np.array_equal(a.theta, b.theta)


def test_readers_and_data_source(spark, tmp_path):
    assert io.read_checked(spark, f"{SF}/documents.parquet", "documents").columns == ["doc_id", "text", "lang", "source", "n_chars"]
    with pytest.raises(ValueError):
        io.read_checked(spark, f"{SF}/labels.parquet", "documents")
    df = spark.createDataFrame([(1, "a"), (2, None), (3, "ab")], "i int, t string")
    assert io.bad_rows(df, "t") == 2
    np.savez(tmp_path / "p.npz", theta=np.arange(3.0), alpha=np.array([5.0]))
    spark.dataSource.register(io.ParameterSource)
    got = {(r["kind"], r["idx"]): r["val"] for r in spark.read.format("tilt_parameters").load(str(tmp_path / "p.npz")).collect()}
    assert got == {("theta", 0): 0.0, ("theta", 1): 1.0, ("theta", 2): 2.0, ("alpha", 0): 5.0}


def test_sql_functions(spark):
    alpha, main = np.linspace(-1, 1, 16), ByteModel(16)
    theta = np.random.default_rng(0).normal(0, 0.1, main.size)
    udfs.register(spark, alpha, theta)
    texts = ["hello", "\u00e9t\u00e9 abc"]
    spark.createDataFrame([(t,) for t in texts], "t string").createOrReplaceTempView("tilt_texts")
    rows = {r["t"]: r for r in spark.sql("select t, tilt_score(t) s, tilt_loss(t) l from tilt_texts").collect()}
    for t in texts:
        assert np.isclose(rows[t]["s"], LinearWeight().scores(alpha, LinearWeight().prepare([t.encode()]))[0])
        assert np.isclose(rows[t]["l"], main.losses(theta, main.prepare([t.encode()]))[0])
    assert spark.sql("select sum(n) from byte_ngrams('abcab', 2)").first()[0] == 4


def test_approximate_aggregates_are_near(spark):
    events = spark.read.parquet(f"{SF}/events.parquet")
    for column in ("user_id", "event_id"):
        exact, near = events.agg(F.count_distinct(column), F.approx_count_distinct(column, 0.02)).first()
        assert abs(near - exact) <= 0.06 * exact
    for name in ("op_approx_distinct", "op_approx_percentile"):
        assert relational.SPARK[name](spark, SF).count() > 0


def test_scratch_needs_a_shared_folder(spark):
    a, b = scratch(spark, "x"), scratch(spark, "x")
    assert a != b and "shared" in a

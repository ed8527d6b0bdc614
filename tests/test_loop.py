"""Filters, the loop, the other strategies, planted truth, cost."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpus_tilt.models.main_models import ByteModel, ContextMlp, PairModel
from corpus_tilt.models.weight_models import ImageWeight, LinearWeight
from corpus_tilt.operators import sampling as S
from corpus_tilt.plans.cascade import gradient_sums, linear_scores, score_examples, select_then_fetch, sliced
from corpus_tilt.streaming.select import file_stream, stream_select
from corpus_tilt.training.bilevel import METHODS, Setting, fine_tune, train_bilevel, train_frozen, train_shuffled
from corpus_tilt.training.diagnose import acceleration_rates, mix_diagnostic
from corpus_tilt.training.optim import Adam
from corpus_tilt.training.source import ClusterSource, DrawnSource, LocalSource, choose, mean_loss, mean_losses
from corpus_tilt.training.task import TARGETS, MixtureTarget, Task, build_task, stored_texts

from .conftest import SF


def test_choose():
    rng = np.random.default_rng(0)
    z = np.array([3.0, 0.0, 1.0, -2.0])
    w = np.exp(z) / np.exp(z).sum()
    assert choose("top", z, 2, rng.random(4)).tolist() == [0, 2]
    assert sorted(choose("gumbel", z, 9, rng.random(4))) == [0, 1, 2, 3]
    first = np.bincount([choose("gumbel", z, 1, rng.random(4))[0] for _ in range(4000)], minlength=4) / 4000
    assert np.abs(first - w).max() < 0.03
    draws = np.bincount(choose("iid", z, 4000, rng.random(4), rng.random(4000)), minlength=4) / 4000
    assert np.abs(draws - w).max() < 0.03
    assert len(choose("gumbel", np.array([1000.0, 0.0]), 1, rng.random(2))) == 1


def test_filters(spark):
    df = spark.range(500).select("id", (F.col("id") % 7).cast("double").alias("score"))
    for name in ("gumbel", "top", "uniform"):
        a, b = (sorted(r["id"] for r in S.FILTERS[name](x, 40, 1, 2).collect()) for x in (df, df.repartition(7)))
        assert a == b and len(set(a)) == 40
        assert S.FILTERS[name](df, 900, 1, 2).count() == 500
    kept = {r["id"] for r in S.filter_gumbel(df, 40, 1, 2).collect()}
    assert {r["id"] for r in S.filter_gumbel_threshold(df, 40, 1, 2).collect()} == kept
    draws = S.filter_iid(df, 300, 1, 2)
    assert draws.agg(F.sum("copies")).first()[0] == 300
    sizes = [S.filter_poisson(df, 60, seed, 0).count() for seed in range(8)]
    assert 40 < np.mean(sizes) < 80
    w = S.softmax_weights(df)
    assert abs(w.agg(F.sum("w")).first()[0] - 1) < 1e-9
    with pytest.raises(ValueError):
        S.filter_top(df, 0)
    plan = S.filter_gumbel(df, 40, 1, 2)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in plan and "SinglePartition" not in plan


def _strings(rng, table, n):
    out = []
    for _ in range(n):
        s = [0]
        for _ in range(40):
            s.append(rng.choice(3, p=table[s[-1]]))
        out.append(bytes(97 + 32 * (c == 2) - 32 * (c == 1) + c for c in s))
    return out


def test_planted_truth(spark):
    """Generic data hide a tenth of target strings: learned weights must rank them first."""
    rng = np.random.default_rng(1)
    a, b = np.array([[0.8, 0.1, 0.1]] * 3), np.array([[0.1, 0.1, 0.8]] * 3)
    hidden = np.arange(400) < 40
    rows = [(i, 0, "train", t) for i, t in enumerate(_strings(rng, b, 40) + _strings(rng, a, 360))] + [(i, 1, sp, t) for i, (sp, t) in enumerate(zip(["train", "valid", "test"] * 20, _strings(rng, b, 60), strict=True))]
    task = Task("planted", spark.createDataFrame(rows, "id long, side int, split string, payload binary"))
    source = LocalSource(task, ByteModel(16), LinearWeight())
    for outer in ("unroll", "cosine", "implicit"):
        run = train_bilevel(source, outer, Setting(steps=40, small=16, large=128, rate=5, weight_rate=50, rho=5))
        s = source.weight.scores(run.trajectory[-1], source.whole(0).xw)
        auc = (s[hidden][:, None] > s[~hidden][None]).mean()
        w = np.exp(s - s.max())
        assert auc > 0.9 and w[hidden].sum() / w.sum() > 0.1, outer


def test_loop_repeats_and_counts(spark):
    source = LocalSource(build_task(spark, SF, "lang_fr"), ByteModel(16), LinearWeight())
    s = Setting(steps=6, small=8, large=32, rate=5.0)
    a, b = train_bilevel(source, "implicit", s), train_bilevel(source, "implicit", s)
    assert np.array_equal(a.theta, b.theta) and len(a.trajectory) == 7
    c = a.cost.summary()
    assert 6 * 24 < c["weight_fwd"] <= 6 * 32 and c["main_fwd"] == 6 * 8 and c["ratio"] == c["weight_fwd"] / 48 and c["bytes_in"] > 0
    assert np.isfinite(train_frozen(source, a.trajectory[-1:], s).theta).all()
    assert np.isfinite(train_shuffled(source, a.trajectory, s).theta).all()
    start = mean_loss(source, a.theta, "valid")
    assert mean_loss(source, fine_tune(source, a.theta, 20), "valid") <= start
    for name, run in METHODS.items():
        assert np.isfinite(run(source, Setting(steps=3, small=8, large=32)).theta).all(), name
    r = acceleration_rates(source, a.theta, 3, 8)
    assert 0 <= r["sar"] <= 1 and 0 <= r["gar"] <= 1
    assert set(mix_diagnostic(source, a.theta, a.trajectory[-1], n=8)) == {"generic_move", "specific_move"}
    adam = train_bilevel(source, "cosine", Setting(steps=3, small=8, large=32, rate=0.05, optimizer=Adam))
    assert np.isfinite(adam.theta).all() and not np.allclose(adam.theta, 0)


def test_an_epoch_takes_no_row_twice(spark):
    source = LocalSource(build_task(spark, SF, "lang_fr"), ByteModel(16), LinearWeight())
    n = source.total(0, "train")
    ids = [i for b in source.uniform(0, "train", 10, range(n // 10), "big", 0) for i in b.ids]
    assert len(set(ids)) == len(ids) > 0.8 * n


@pytest.mark.parametrize("kind", ["gumbel", "top", "iid", "uniform"])
def test_cluster_is_the_local_loop(spark, kind):
    task = build_task(spark, SF, "lang_fr")
    a, b = (make(task, ByteModel(16), LinearWeight()) for make in (LocalSource, ClusterSource))
    s = Setting(steps=3, small=6, large=20, rate=5.0, filter=kind)
    x, y = train_bilevel(a, "implicit", s), train_bilevel(b, "implicit", s)
    assert np.allclose(x.theta, y.theta, atol=1e-12) and np.allclose(x.trajectory[-1], y.trajectory[-1], atol=1e-12)
    assert {k: v for k, v in x.cost.summary().items() if k != "seconds"} == {k: v for k, v in y.cost.summary().items() if k != "seconds"}
    assert np.isclose(mean_loss(a, x.theta), mean_loss(b, x.theta))
    s.delay = 3  # one job for all three steps
    assert np.allclose(train_bilevel(a, "cosine", s).theta, train_bilevel(b, "cosine", s).theta)


@pytest.mark.parametrize("method", ["mixing", "contrastive_select", "domain_classifier", "batch_reweight", "loss_input_weights"])
def test_other_strategies_on_the_cluster(spark, method):
    task = build_task(spark, SF, "lang_fr")
    s = Setting(steps=2, small=6, large=20, rate=5.0)
    a, b = (METHODS[method](make(task, ByteModel(16), LinearWeight()), s).theta for make in (LocalSource, ClusterSource))
    close = np.allclose(a, b, atol=1e-9)
    assert close or method in ("contrastive_select", "domain_classifier") and np.isfinite(b).all()  # their share is a quantile's


def test_mixture_and_other_loss(spark):
    parts = [build_task(spark, SF, n) for n in ("lang_fr", "lang_de")]
    both = MixtureTarget([(parts[0], 0.75), (parts[1], 0.25)])
    n = [p.frame(1, "train").count() for p in parts]
    assert both.frame(1, "train").count() == 3 * n[0] + n[1]
    assert both.frame(1, "train").select("id").distinct().count() == 3 * n[0] + n[1]
    assert both.frame(0, "train").join(parts[1].frame(1, "train"), "payload").count() == 0
    source = LocalSource(both, ByteModel(16), LinearWeight())

    class Doubled(ByteModel):
        def grad(self, theta, x, w):
            return 2 * super().grad(theta, x, w)

    s = Setting(steps=2, small=8, large=32)
    plain = train_bilevel(source, "unroll_first", s)
    s.specific = Doubled(16)
    other = train_bilevel(source, "unroll_first", s)
    assert np.allclose(other.trajectory[1] - other.trajectory[0], 2 * (plain.trajectory[1] - plain.trajectory[0]))


@pytest.mark.parametrize("name", [*TARGETS, "pairs", "vectors", "rows"])
def test_tasks(spark, name):
    task = build_task(spark, SF, name)
    both = task.examples.groupBy("split").count().count()
    assert both == 3
    assert task.frame(0, "train").count() > 0
    with pytest.raises(ValueError):
        build_task(spark, SF, "nothing")


def test_cascade(spark, tmp_path):
    docs = spark.createDataFrame([(1, "hello"), (2, None), (3, ""), (4, "a"), (5, "été à"), (6, "zzzz")], "doc_id long, text string")
    alpha = np.linspace(-1, 1, 16)
    ex = docs.select(F.col("doc_id").alias("id"), F.encode("text", "utf-8").alias("payload"))
    got = {r["id"]: r["score"] for r in score_examples(ex.where("length(payload) > 1"), LinearWeight(), alpha).collect()}
    native = {r["id"]: r["score"] for r in linear_scores(ex.where("length(payload) > 1"), alpha).collect()}
    assert got.keys() == {1, 5, 6} and all(abs(got[k] - native[k]) < 1e-12 for k in got)
    assert {r["doc_id"] for r in select_then_fetch(docs, LinearWeight(), alpha, 2, "top").collect()} < {1, 5, 6}
    main = ByteModel(16)
    rows = ex.where("length(payload) > 1").withColumn("w", F.lit(0.25))
    payloads = [bytes(r["payload"]) for r in rows.collect()]
    assert np.allclose(gradient_sums(rows, main, main.init()), main.grad(main.init(), main.prepare(payloads), np.full(3, 0.25)))
    sliced(docs, str(tmp_path / "s"), 4)
    plan = spark.read.parquet(str(tmp_path / "s")).where("slice = 1")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(slice" in plan


def test_selection_reads_whole_texts(spark, tmp_path):
    """Two texts that differ after their first 512 bytes alone."""
    docs = spark.createDataFrame([(1, "a" * 600 + " " * 900), (2, "a" * 600 + "z" * 900)], "doc_id long, text string")
    alpha = np.zeros(16)
    alpha[7] = 1.0  # bytes of p to z
    assert [r["doc_id"] for r in select_then_fetch(docs, LinearWeight(), alpha, 1, "top").collect()] == [2]
    where = str(tmp_path)
    docs.write.parquet(f"{where}/in")
    stream_select(file_stream(spark, f"{where}/in", docs, 100), LinearWeight(), alpha, 2, f"{where}/out", f"{where}/checkpoint", "top").awaitTermination()
    got = {r["id"]: r["score"] for r in spark.read.parquet(f"{where}/out").collect()}
    assert got == {1: 0.0, 2: 0.6}


def _jobs(spark, work):
    """What ``work`` gives, and the number of jobs it took."""
    group = f"jobs-{id(work)}-{np.random.default_rng().integers(1 << 40)}"
    spark.sparkContext.setJobGroup(group, "counted")
    try:
        return work(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


@pytest.mark.parametrize("kind", ["gumbel", "iid"])
def test_drawn_is_the_local_loop(spark, kind):
    """The batches of all steps come in a few jobs, whatever the number of steps, and are those of the local source."""
    task = build_task(spark, SF, "lang_fr")
    a, b = (make(task, ByteModel(16), LinearWeight()) for make in (LocalSource, DrawnSource))
    s = Setting(steps=25, small=6, large=20, rate=5.0, filter=kind)
    x = train_bilevel(a, "implicit", s)
    y, jobs = _jobs(spark, lambda: train_bilevel(b, "implicit", s))
    assert np.allclose(x.theta, y.theta, atol=1e-12) and np.allclose(x.trajectory[-1], y.trajectory[-1], atol=1e-12) and jobs < 15
    assert {k: v for k, v in x.cost.summary().items() if k != "seconds"} == {k: v for k, v in y.cost.summary().items() if k != "seconds"}
    b.HELD_BYTES = 20_000  # a few steps at a time
    b._rows.clear()
    b._dealt_ids.clear()
    assert np.allclose(train_bilevel(b, "implicit", s).theta, x.theta, atol=1e-12)


def test_validation_is_one_pass(spark):
    source = ClusterSource(build_task(spark, SF, "lang_fr"), ByteModel(16), LinearWeight())
    assert source.task.stored  # written once by side and split
    rng = np.random.default_rng(0)
    thetas = [rng.normal(0, 0.1, source.main.size) for _ in range(6)]
    losses, jobs = _jobs(spark, lambda: mean_losses(source, thetas, "valid"))
    assert np.allclose(losses, [mean_loss(source, t, "valid") for t in thetas]) and jobs <= 3  # the adaptive plan runs its stages as jobs


def test_byte_models_pack_rows():
    for contexts in (16, 256):
        main, texts = ByteModel(contexts), [b"ab", b"a" * 900, bytes(range(256)) * 40, "été à".encode()]
        x, y = main.prepare(texts), main.unpacked(main.packed(texts))
        assert np.array_equal(x[0], y[0]) and all(np.array_equal(p, q) for a, b in zip(x[1], y[1], strict=True) for p, q in zip(a, b, strict=True))


def test_non_convex_model_in_bounded_memory():
    """A long text's positions are taken in stretches: the same loss and gradient, without 256 numbers a position at once."""
    import tracemalloc

    main, rng = ContextMlp(), np.random.default_rng(0)
    theta, long = main.init(0), [bytes(rng.integers(97, 123, 60_000, dtype=np.uint8)), b"short text"]
    tracemalloc.start()
    x = main.prepare(long)
    losses, grad = main.losses(theta, x), main.grad(theta, x, np.array([0.5, 0.5]))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 80 << 20
    main.STRETCH = 1 << 30
    assert np.allclose(losses, main.losses(theta, x)) and np.allclose(grad, main.grad(theta, x, np.array([0.5, 0.5])))


def test_image_weights_score_many_rows_in_bounded_memory():
    """A task scores thousands of rows at once: their patches are made by stretches, with the same scores."""
    import tracemalloc

    weight, rng = ImageWeight(), np.random.default_rng(0)
    alpha, x = weight.init(0), weight.prepare(list(rng.normal(0, 1, (700, 64))))
    tracemalloc.start()
    scores = weight.scores(alpha, x)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 150 << 20
    weight.STRETCH = 1 << 30
    assert np.allclose(scores, weight.scores(alpha, x), atol=1e-12)


def test_pair_model_decodes_and_measures_in_one_pass():
    main, rng = PairModel(24), np.random.default_rng(0)
    theta = rng.normal(0, 1, main.size)
    x = main.prepare([(f"a{i % 5} b{i % 3} c", f"d{i % 4} e f") for i in range(30)])
    assert main.beam_decode_all(theta, [bag for bag, _ in x]) == [main.beam_decode(theta, bag) for bag, _ in x]
    assert main.beam_decode_all(theta, []) == []
    assert np.allclose(main.losses(theta, x), [-(g * np.log(p)).sum(1).mean() for p, g in (main._parts(theta, r) for r in x)])


def test_payloads_by_field_and_their_bytes(spark):
    import pyarrow as pa

    from corpus_tilt.training.source import payloads_of
    from corpus_tilt.training.task import payload_bytes

    rows = [{"x": [1.0, 2.5], "y": 1, "s": "ab"}, {"x": [], "y": None, "s": None}, {"x": [None, 3.0], "y": 2, "s": "c"}, {"x": None, "y": 3, "s": ""}, {"x": [0.1], "y": 4, "s": "d"}]
    kind = pa.struct([("x", pa.list_(pa.float64())), ("y", pa.int32()), ("s", pa.string())])
    for part in (rows, rows[:2], rows[1:], rows[4:]):
        assert payloads_of(pa.array(part, kind)) == [tuple(r.values()) for r in part]
        assert payloads_of(pa.array([rows[0], *part], kind).slice(1)) == [tuple(r.values()) for r in part]
    df = spark.createDataFrame([(1, ([1.0, 2.0], 3, "abc")), (2, (None, 3, None))], "id long, payload struct<x array<double>, y int, s string>")
    sized = df.select("id", payload_bytes(df).alias("n"))
    assert {r["id"]: r["n"] for r in sized.collect()} == {1: 16 + 40 + 20 + 3, 2: 16 + 20}
    assert "to_json" not in sized._jdf.queryExecution().toString()


@pytest.mark.parametrize("name", TARGETS)
def test_shared_texts_give_the_same_tasks(spark, name):
    """Documents written once serve each text task with the same examples; its source writes no copy of them."""
    texts = stored_texts(spark, SF)
    alone, shared = build_task(spark, SF, name), build_task(spark, SF, name, texts)
    rows = [sorted((r["id"], r["side"], r["split"], bytes(r["payload"])) for r in t.examples.collect()) for t in (alone, shared)]
    assert rows[0] == rows[1]
    source = DrawnSource(shared, ByteModel(16), LinearWeight())
    assert source.task is shared
    plan = source.frame(0, "valid")._jdf.queryExecution().executedPlan().toString()
    assert 0 < plan.count("FileScan") == plan.count(" = valid)")  # the stored split alone is read

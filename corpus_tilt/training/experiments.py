"""The experiments: each gives rows of (task, method, phase, metric, value), over all rows and whole texts of its task."""

from __future__ import annotations

import zlib
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import partial

import numpy as np
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..models.base import size_of
from ..models.main_models import ByteModel, ContextMlp, DualEncoder, LinearSoftmax, PairModel, bleu_counts, bleu_of
from ..models.weight_models import ConvWeight, ImageWeight, LinearWeight, MlpWeight, PairWeight
from .bilevel import METHODS, Setting, best_of, draws, run_generic_only, run_mixing, train_bilevel, train_frozen, train_shuffled, tune_path
from .diagnose import acceleration_rates, rank_correlation
from .optim import Adam
from .source import LOCAL_BYTES, Draw, Source, losses_each, mean_loss, mean_losses, source_of
from .task import TARGETS, MixtureTarget, Task, build_task, stored_texts

SCHEMA = "task string, method string, phase string, metric string, value double"
ALL = tuple(METHODS)
FEW = ("generic_only", "mixing", "contrastive_select", "domain_classifier", "unroll", "cosine", "implicit")


def caption_vectors(classes: int, size: int = 64) -> np.ndarray:
    """A fixed vector for each class's caption, from a hash of its text."""
    return np.array([np.random.default_rng(zlib.crc32(f"a photo of a class-{k}".encode())).normal(0, 1 / np.sqrt(size), size) for k in range(classes)])


def models(task: str, contexts: int = 16):
    """Main model, weight model and setting of a task."""
    if task == "pairs_planted":
        return PairModel(24), PairWeight(24), Setting(steps=250, small=16, large=64, rate=100.0, weight_rate=20.0, rho=20.0)
    if task == "pairs":
        return PairModel(), PairWeight(), Setting(steps=60, small=16, large=128, rate=12.0, weight_rate=20.0, rho=4.0)
    if task.startswith("vectors"):
        return DualEncoder(caption_vectors(10)), ImageWeight(), Setting(steps=60, small=16, large=64, rate=0.1, weight_rate=1.0, rho=0.1)
    if task == "rows":
        return LinearSoftmax(7, 3), MlpWeight(7), Setting(steps=100, rate=0.5, weight_rate=2.0, rho=0.5)
    return ByteModel(contexts), LinearWeight(), Setting(steps=80, rate=20.0, weight_rate=200.0, rho=20.0)


def measures(source: Source, thetas: list[np.ndarray]) -> list[dict[str, float]]:
    """For each of ``thetas`` the loss and what else the main model is measured by, over all held-out specific rows, in one pass."""
    main = source.main

    def sums(x) -> dict[str, float]:
        every = {}
        for i, (theta, losses) in enumerate(zip(thetas, losses_each(main, thetas, x), strict=True)):
            out = {"n": size_of(x), "loss": losses.sum()}
            if isinstance(main, ByteModel):
                out |= {"nll": (losses * x[0]).sum(), "bytes": x[0].sum()}
            if hasattr(main, "accuracy"):
                out["hits"] = main.accuracy(theta, x) * size_of(x)
            if isinstance(main, PairModel):
                out |= bleu_counts(main.beam_decode_all(theta, [bag for bag, _ in x]), [[t for t in r.tolist() if t > 1] for _, r in x])
            every |= {f"{i}/{k}": float(v) for k, v in out.items()}
        return every

    told, all_told = source.tally(sums, 1, "test"), []
    for i in range(len(thetas)):
        got = {k.split("/")[1]: v for k, v in told.items() if k.startswith(f"{i}/")}
        out = {"loss": got["loss"] / got["n"]}
        if "bytes" in got:
            out["nll_per_byte"] = got["nll"] / got["bytes"]
        if "hits" in got:
            out["accuracy"] = got["hits"] / got["n"]
        if "hyp" in got:
            out["bleu"] = bleu_of(got)
        all_told.append(out)
    return all_told


def compare(spark: SparkSession, sf_dir: str, task: str | Task, methods: tuple[str, ...] = ALL, seed: int = 0, mode: str = "auto", steps: int | None = None, texts: DataFrame | None = None) -> list[tuple]:
    """All methods on one task, before and after fine-tuning; the batches are drawn together, and validation and test are a pass each."""
    task = build_task(spark, sf_dir, task, texts) if isinstance(task, str) else task
    main, weight, setting = models(task.name)
    setting.seed, setting.steps = seed, steps or setting.steps
    source = source_of(task, main, weight, mode)
    source.expect(draws(methods, setting, tune=True))
    runs = [METHODS[name](source, setting) for name in methods]
    tuned = best_of(source, [tune_path(source, run.theta, setting.steps, setting.small, setting.rate, seed) for run in runs])
    told = iter(measures(source, [theta for run, after in zip(runs, tuned, strict=True) for theta in (run.theta, after)]))
    rows = []
    for name, run in zip(methods, runs, strict=True):
        for phase in ("pre", "ft"):
            rows += [(task.name, name, phase, m, v) for m, v in next(told).items()]
        rows += [(task.name, name, "cost", m, float(v)) for m, v in run.cost.summary().items()]
    return rows


def at_once(spark: SparkSession, work: list[Callable[[], object]], threads: int = 3) -> list:
    """What ``work`` gives, in order; small jobs of several tasks run beside each other."""
    with ThreadPoolExecutor(threads) as pool:
        return [f.result() for f in [pool.submit(inheritable_thread_target(spark)(w)) for w in work]]


def shared_texts(spark: SparkSession, sf_dir: str) -> DataFrame | None:
    """The documents for many text tasks at once; none where the driver may hold a task's rows."""
    size = spark.read.parquet(f"{sf_dir}/documents.parquet").agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return stored_texts(spark, sf_dir) if size > LOCAL_BYTES else None


def compare_all(spark: SparkSession, sf_dir: str, *asked: tuple, threads: int = 3, **more) -> list[tuple]:
    """``compare`` for each of (task, methods)."""
    parts = at_once(spark, [partial(compare, spark, sf_dir, task, methods, **more) for task, methods in asked], threads)
    return [r for part in parts for r in part]


def _table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(*r[:4], float(r[4])) for r in rows], SCHEMA)


def _losses(spark: SparkSession, source: Source, thetas: dict[tuple[str, str], np.ndarray]) -> DataFrame:
    """Rows of the test loss by (method, phase), in one pass."""
    losses = mean_losses(source, list(thetas.values()))
    return _table(spark, [(source.task.name, *key, "loss", loss) for key, loss in zip(thetas, losses, strict=True)])


def language_one(spark, sf_dir):
    """A far target with all methods, and a near one with the main ones."""
    return _table(spark, compare_all(spark, sf_dir, ("lang_fr", ALL), ("benchmark", ALL)))


def language_nine(spark, sf_dir):
    """Nine targets; beside the losses, each method's place (1 is best) by target and phase."""
    out = _table(spark, compare_all(spark, sf_dir, *((t, FEW) for t in TARGETS), steps=40, texts=shared_texts(spark, sf_dir)))
    by = Window.partitionBy("task", "phase").orderBy("value")
    places = out.where("metric = 'nll_per_byte'").select("task", "method", "phase", F.lit("place").alias("metric"), F.rank().over(by).cast("double").alias("value"))
    return out.unionByName(places)


def translation(spark, sf_dir):
    """The given pairs, and pairs with a rule to learn."""
    return _table(spark, compare_all(spark, sf_dir, ("pairs", ALL), ("pairs_planted", FEW), threads=1))  # most of its time is the driver's Python, which threads do not share


def vectors(spark, sf_dir):
    return _table(spark, compare_all(spark, sf_dir, ("vectors", ALL), ("vectors_planted", ALL)))


def table_rows(spark, sf_dir):
    return _table(spark, compare(spark, sf_dir, "rows", FEW))


def non_convex(spark, sf_dir):
    """The non-convex byte model with a convolution as weight model and Adam."""
    s = Setting(steps=10, small=6, large=32, rate=0.02, weight_rate=2.0, rho=0.02, optimizer=Adam)
    source = source_of(build_task(spark, sf_dir, "lang_fr"), ContextMlp(), ConvWeight())
    runs = {"generic_only": run_generic_only(source, s), "mixing": run_mixing(source, s, 0.5), "cosine": train_bilevel(source, "cosine", s), "unroll": train_bilevel(source, "unroll_first", s)}
    losses = mean_losses(source, [run.theta for run in runs.values()])
    return _table(spark, [("lang_fr", name, "pre", "loss", loss) for name, loss in zip(runs, losses, strict=True)])


def trajectory(spark, sf_dir, seeds: int = 3):
    """Learned trajectory, its last weights frozen, and its weights in random order; a smaller large batch."""
    main, weight, s = models("lang_fr")
    s.large //= 2
    source, got = source_of(build_task(spark, sf_dir, "lang_fr"), main, weight), {}
    for seed in range(seeds):
        s.seed = seed
        run = train_bilevel(source, "implicit", s)
        got |= {("learned", seed): run.theta, ("final", seed): train_frozen(source, run.trajectory[-1:], s).theta, ("shuffled", seed): train_shuffled(source, run.trajectory, s).theta}
    return _losses(spark, source, {(name, f"seed{seed}"): theta for (name, seed), theta in got.items()})


def filter_kinds(spark, sf_dir, seeds: int = 3):
    main, weight, s = models("lang_fr")
    source, got, kinds = source_of(build_task(spark, sf_dir, "lang_fr"), main, weight), {}, ("gumbel", "top", "iid", "uniform")
    for seed in range(seeds):  # the filters of a seed have the same batches
        for kind in kinds:
            s.seed, s.filter = seed, kind
            got[kind, f"seed{seed}"] = train_bilevel(source, "implicit", s).theta
    return _losses(spark, source, {(kind, f"seed{seed}"): got[kind, f"seed{seed}"] for kind in kinds for seed in range(seeds)})


def diagnostic(spark, sf_dir):
    """Rates of every task at an early main model, beside the gain of the cosine method, and the correlation of their ranks."""
    texts = shared_texts(spark, sf_dir)

    def one(task: str) -> tuple[dict[str, float], float]:
        main, weight, s = models(task)
        source = source_of(build_task(spark, sf_dir, task, texts), main, weight)
        s.steps = 40
        source.expect([*draws(("generic_only", "cosine"), s), *(Draw(side, 32, range(8), "rates", 0) for side in (0, 1))])
        s.steps = 10
        got = acceleration_rates(source, run_generic_only(source, s).theta, 8)
        s.steps = 40
        plain, own = mean_losses(source, [run_generic_only(source, s).theta, train_bilevel(source, "cosine", s).theta])
        return got, (plain - own) / plain

    tasks = (*TARGETS, "pairs", "vectors", "vectors_planted")
    told = at_once(spark, [partial(one, task) for task in tasks], threads=2)  # each holds its batches in the driver
    rows = []
    for task, (got, gain) in zip(tasks, told, strict=True):
        rows += [(task, "diagnostic", "10 steps", m, v) for m, v in got.items()]
        rows.append((task, "cosine", "pre", "gain", gain))
    rates, gains = [got["mean_rate"] for got, _ in told], [gain for _, gain in told]
    return _table(spark, [*rows, ("all", "diagnostic", "10 steps", "rank_correlation", rank_correlation(rates, gains))])


def small_to_large(spark, sf_dir):
    """Weights learned with 16 contexts, used as they end to train 256 contexts."""
    task = build_task(spark, sf_dir, "lang_fr")
    small, weight, s = models("lang_fr", 16)
    large, _, _ = models("lang_fr", 256)
    a = source_of(task, small, weight)
    b = source_of(a.task, large, weight)
    learned, own = train_bilevel(a, "implicit", s), train_bilevel(b, "implicit", s)
    runs = {"small_implicit": (a, learned), "large_generic_only": (b, run_generic_only(b, s)), "large_implicit": (b, own), "large_reused": (b, train_frozen(b, learned.trajectory[-1:], s))}
    losses = {id(x): iter(mean_losses(x, [run.theta for source, run in runs.values() if source is x])) for x in (a, b)}
    rows = [("lang_fr", name, "pre", "loss", next(losses[id(source)])) for name, (source, _) in runs.items()]
    return _table(spark, [*rows, ("lang_fr", "small", "size", "parameters", small.size), ("lang_fr", "large", "size", "parameters", large.size)])


def complementarity(spark, sf_dir):
    """What selection and fine-tuning gain, each alone and together, against generic training alone."""
    rows = compare_all(spark, sf_dir, ("lang_fr", ALL), ("vectors_planted", FEW), steps=40)
    loss = _table(spark, rows).where("metric = 'loss'").groupBy("task", "method").pivot("phase", ["pre", "ft"]).agg(F.first("value"))
    plain = loss.where("method = 'generic_only'").select("task", F.col("pre").alias("pre0"), F.col("ft").alias("ft0"))
    told = loss.join(plain, "task").select("task", "method", (F.col("pre0") - F.col("pre")).alias("selection"), (F.col("pre0") - F.col("ft0")).alias("tuning"), (F.col("pre0") - F.col("ft")).alias("both"), (F.col("ft0") - F.col("ft")).alias("beyond_tuning"))
    return told.unpivot(["task", "method"], ["selection", "tuning", "both", "beyond_tuning"], "metric", "value").select("task", "method", F.lit("gain").alias("phase"), "metric", "value")


def validation(spark, sf_dir):
    """A grid of both batch sizes, the rate and the mixing share, by the validation loss."""
    main, weight, s = models("lang_fr")
    source, got = source_of(build_task(spark, sf_dir, "lang_fr"), main, weight), {}
    s.steps = 40
    for small in (16, 32):
        for large in (128, 512):
            for rate in (10.0, 20.0):
                s.small, s.large, s.rate = small, large, rate
                got[f"cosine small={small} large={large} rate={rate:g}"] = train_bilevel(source, "cosine", s).theta
    s.small, s.rate = 32, 20.0
    for p in (0.1, 0.25, 0.5, 0.9):
        source.expect(draws(("mixing",), s, shares=(p,)))
        got[f"mixing share={p:g}"] = run_mixing(source, s, p).theta
    losses = mean_losses(source, list(got.values()), "valid")
    rows = [("lang_fr", name, "valid", "loss", loss) for name, loss in zip(got, losses, strict=True)]
    for family in ("cosine", "mixing"):
        best = min((r for r in rows if r[1].startswith(family)), key=lambda r: r[4])
        rows.append((best[0], best[1], "chosen", "loss", best[4]))
    return _table(spark, rows)


def cost_asymmetry(spark, sf_dir):
    """Examples scored against examples trained, with scoring on the cluster: the filter, none, and weights held for several steps; at three sizes of the generic set."""
    rows = []
    task = build_task(spark, sf_dir, "lang_fr")
    for times in (1, 3, 10):
        copies = task.examples.where("side = 0").select("*", F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("copy"))
        grown = copies.withColumn("id", F.col("id") * 16 + F.col("copy")).drop("copy").unionByName(task.examples.where("side = 1"))
        main, weight, s = models("lang_fr")
        s.steps, s.large = 4, 256 * times
        source = source_of(Task("lang_fr", grown), main, weight, "cluster")
        for name, dense, delay in (("sparse", False, 1), ("dense", True, 1), ("delayed", False, 4)):
            s.dense, s.delay = dense, delay
            run = train_bilevel(source, "cosine", s)
            rows += [(f"lang_fr x{times}", name, "cost", k, float(v)) for k, v in run.cost.summary().items()]
            rows.append((f"lang_fr x{times}", name, "pre", "loss", mean_loss(source, run.theta)))
    return _table(spark, rows)


def mixture(spark, sf_dir):
    """A target made of two, three parts to one."""
    both = MixtureTarget([(build_task(spark, sf_dir, "lang_fr"), 0.75), (build_task(spark, sf_dir, "lang_de"), 0.25)])
    return _table(spark, compare(spark, sf_dir, both, ("generic_only", "mixing", "cosine"), steps=40))


def cluster_run(spark, sf_dir):
    """The weight model after four steps of the loop with scoring on the cluster."""
    main, weight, s = models("lang_fr")
    s.steps = 4
    run = train_bilevel(source_of(build_task(spark, sf_dir, "lang_fr"), main, weight, "cluster"), "implicit", s)
    return spark.createDataFrame([(k, float(a)) for k, a in enumerate(run.trajectory[-1])], "k int, a double")


EXPERIMENTS = {"e1_language": language_one, "e1_non_convex": non_convex, "e2_nine_targets": language_nine, "e3_translation": translation, "e4_vectors": vectors, "e5_trajectory": trajectory, "e6_filters": filter_kinds, "e7_diagnostic": diagnostic, "e8_small_to_large": small_to_large, "e9_complementarity": complementarity, "e10_validation": validation, "e11_costs": cost_asymmetry, "e13_rows": table_rows, "e14_mixture": mixture, "q_bilevel_run": cluster_run}

"""Near-duplicate classes by a chosen-path set similarity join.

A document's set is its distinct word shingles.  Trees branch the documents: a node picks one or
a few of the sketch's minwise coordinates and sends each document to the child of its token
there, so similar documents stay together more often than they part.  Nodes of at most ``small``
documents are compared exhaustively; larger ones branch again.  Independent trees raise the
recall to any target.  Links are confirmed on whole sets, and classes are the connected components.

Equal sets are one representative, so groups of exact copies never enter the trees.  A large
node that a branching hardly divides (texts whose sketches agree), or that is left after
``levels`` branchings, is first dealt to blocks that all hold its least document.  What these and
the small nodes leave in different classes is then compared whole, block against block over many
tasks: the documents outside the node's largest class against all of it, each pair in one node alone.

Defined results: texts without words have an empty set and are linked with nothing; with fewer
words than a shingle the whole sequence is one; a null id is linked with nothing and kept; rows
that repeat an id are one document, known to links by the text of the least hash (``version``);
an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HOT_SHARE, column_slices, join_hot, lean, workers_import, written
from .components import components
from .words import mix, slices, text_words

_U = np.uint64
_mix = mix


def shingle_sets(texts: list[str | None], words: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text (A-Z lower-cased)."""
    out: list[np.ndarray] = []
    for at, upto in slices(texts):
        hashes, _, cuts, _ = text_words(texts[at:upto], lower=True)
        with np.errstate(over="ignore"):
            rolled = hashes.copy()
            for i in range(1, words):
                rolled = rolled[: max(len(hashes) - i, 0)] * _U(0x9FB21C651E98DF25) + hashes[i:]
            rolled = mix(rolled)
        for lo, hi in pairwise(cuts.tolist()):
            if hi - lo >= words:
                out.append(np.unique(rolled[lo : hi - words + 1]))
            elif hi > lo:
                few = int(hi - lo)
                for h in hashes[lo:hi].tolist():
                    few = (few * 0x9FB21C651E98DF25 + h) & (2**64 - 1)
                out.append(mix(np.array([few], _U) ^ _U(0xA5A5A5A5)))
            else:
                out.append(np.zeros(0, _U))
    return out


def _coordinates(n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 1 << 32, n, np.uint32), rng.integers(0, 1 << 31, n, np.uint32) * np.uint32(2) + np.uint32(1)


def sketch(own: np.ndarray, salt: np.ndarray, odd: np.ndarray) -> np.ndarray:
    """The least value of each coordinate's hash over a set."""
    low = (own >> _U(32)).astype(np.uint32)
    out = np.full(len(salt), 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(low), 20_000):
        x = (low[lo : lo + 20_000, None] ^ salt) * odd
        np.minimum(out, (x ^ (x >> np.uint32(15))).min(axis=0), out=out)
    return out


def _children(paths: np.ndarray, tokens: np.ndarray, extra: float) -> tuple[np.ndarray, np.ndarray]:
    """Child paths of rows (node path, sketch): which row, and the child's path; one or two coordinates a node."""
    n = tokens.shape[1]
    with np.errstate(over="ignore"):
        a, b = _mix(paths ^ _U(0x1234567)), _mix(paths ^ _U(0x89ABCDEF))
        first = (a % _U(n)).astype(np.int64)
        second = ((a >> _U(20)) % _U(n)).astype(np.int64)
        two = np.flatnonzero(((b >> _U(11)).astype(np.float64) / 2**53 < extra) & (second != first))
        rows = np.concatenate([np.arange(len(paths)), two])
        pick = np.concatenate([first, second[two]])
        child = _mix(_mix(paths[rows] + pick.astype(_U) * _U(0x9E3779B97F4A7C15)) ^ tokens[rows, pick].astype(_U))
    return rows, child


def _sketcher(words: int, size: int, trees: int, extra: float, seed: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        salt, odd = _coordinates(size, seed)
        roots = _mix(np.arange(1, trees + 1, dtype=_U) * _U(0xC2B2AE3D27D4EB4F) + _U(seed))
        for b in batches:
            for lo, hi, texts in column_slices(b.column(1)):
                sets = shingle_sets(texts, words)
                tokens = np.array([sketch(s, salt, odd) for s in sets], np.uint32).reshape(len(sets), size)
                with np.errstate(over="ignore"):
                    one = [int(s.sum(dtype=_U)) if len(s) else 0 for s in sets]
                    other = [int(_mix(s ^ _U(0x77)).sum(dtype=_U)) if len(s) else 0 for s in sets]
                paths: list[list[int]] = [[] for _ in sets]
                for root in roots:
                    rows, child = _children(np.full(len(sets), root, _U), tokens, extra)
                    for r, c in zip(rows.tolist(), child.view(np.int64).tolist(), strict=True):
                        paths[r].append(c)
                own = b.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays([own.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(np.array(one, _U).view(np.int64)), pa.array(np.array(other, _U).view(np.int64)), pa.array([t.tobytes() for t in tokens], pa.binary()), pa.array(paths, pa.list_(pa.int64())), own.column(2)], ["doc_id", "n_shingles", "f1", "f2", "tokens", "paths", "version"])

    return make


def _branch(extra: float):
    def branch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            paths = b.column(0).to_numpy().view(_U)
            tokens = np.frombuffer(b"".join(b.column(2).to_pylist()), np.uint32).reshape(len(paths), -1)
            rows, child = _children(paths, tokens, extra)
            yield pa.RecordBatch.from_arrays([pa.array(child.view(np.int64)), b.column(1).take(pa.array(rows)), b.column(3).take(pa.array(rows))], ["path", "doc", "above"])

    return branch


def by_group(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches of whole groups, of input sorted by column 0."""
    held: list[pa.RecordBatch] = []

    def joined() -> pa.RecordBatch:
        table = pa.Table.from_batches(held)
        if table.nbytes > 1 << 30:  # beyond the offsets of plain strings
            large = {pa.string(): pa.large_string(), pa.binary(): pa.large_binary()}
            table = table.cast(pa.schema([f.with_type(large.get(f.type, f.type)) for f in table.schema]))
        return table.combine_chunks().to_batches()[0]

    for b in batches:
        if not b.num_rows:
            continue
        keys = b.column(0).to_numpy(zero_copy_only=False)
        if held and held[-1].column(0)[-1].as_py() == keys[-1]:
            held.append(b)
            continue
        if cut := int(np.flatnonzero(keys == keys[-1])[0]):
            held.append(b.slice(0, cut))
        if held:
            yield joined()
        held = [b.slice(cut)]
    if held:
        yield joined()


def _group_cuts(keys: np.ndarray) -> list[tuple[int, int]]:
    cuts = [0, *(np.flatnonzero(np.diff(keys)) + 1).tolist(), len(keys)]
    return list(pairwise(cuts))


def _likely(least: int):
    """Of each node, the documents whose sketch agrees with another's in at least ``least`` places."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_group(batches):
            keys = b.column(0).to_numpy()
            tokens = np.frombuffer(b"".join(b.column(2).to_pylist()), np.uint32).reshape(len(keys), -1)
            keep = np.zeros(len(keys), bool)
            for lo, hi in _group_cuts(keys):
                if hi - lo == 2:
                    keep[lo:hi] = (tokens[lo] == tokens[lo + 1]).sum() >= least
                elif hi - lo > 2:
                    own = tokens[lo:hi]
                    for i in range(len(own) - 1):
                        same = (own[i + 1 :] == own[i]).sum(axis=1) >= least
                        keep[lo + i] |= same.any()
                        keep[lo + i + 1 : hi] |= same
            at = pa.array(np.flatnonzero(keep))
            yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at)], ["path", "doc"])

    return compare


def _confirm(words: int, percent: int):
    """Exact links of each node that join what is not joined yet; input (path, doc, label, text)."""

    def confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_group(batches):
            keys, docs, labels = (b.column(i).to_numpy() for i in range(3))
            found = []
            for lo, hi in _group_cuts(keys):
                sets = shingle_sets(b.column(3).slice(lo, hi - lo).to_pylist(), words)
                top = labels[lo:hi].tolist()
                order = sorted(range(hi - lo), key=lambda i: (len(sets[i]), docs[lo + i]))
                for x, i in enumerate(order):
                    for j in order[x + 1 :]:
                        if 100 * len(sets[i]) < percent * len(sets[j]):
                            break  # sets only get larger
                        if top[i] == top[j]:
                            continue
                        both = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                        if both and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                            found.append((int(docs[lo + i]), int(docs[lo + j])))
                            old, new = top[j], top[i]
                            top = [new if t == old else t for t in top]
            yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], ["a", "b"])

    return confirm


def _open_pairs(b: pa.RecordBatch, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows that probe, rows probed, and which of their pairs this task has to compare; input (task, doc, label, probe, loose, before)."""
    docs, labels = (b.column(i).slice(lo, hi - lo).to_numpy() for i in (1, 2))
    probe, loose = (b.column(i).slice(lo, hi - lo).to_numpy(zero_copy_only=False) for i in (3, 4))
    x, y = np.flatnonzero(probe), np.flatnonzero(~probe)
    todo = (labels[x, None] != labels[y]) & (~loose[y] | (docs[x, None] < docs[y]))
    members: dict[int, list[int]] = {}
    for i, paths in enumerate(b.column(5).slice(lo, hi - lo).to_pylist()):
        for path in paths:
            members.setdefault(path, []).append(i)
    for rows in members.values():  # both are in an earlier node, which compares them
        own = np.zeros(hi - lo, bool)
        own[rows] = True
        todo &= ~(own[x, None] & own[y])
    return x, y, todo


def _likely_across(least: int):
    """Of each task, the rows with a pair to compare whose sketches agree in at least ``least`` places; tokens are column 6."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_group(batches):
            tokens = np.frombuffer(b"".join(b.column(6).to_pylist()), np.uint32).reshape(b.num_rows, -1)
            keep = np.zeros(b.num_rows, bool)
            for lo, hi in _group_cuts(b.column(0).to_numpy()):
                x, y, todo = _open_pairs(b, lo, hi)
                for i, row in zip(x.tolist(), todo, strict=True):
                    others = lo + y[row]
                    near = others[(tokens[others] == tokens[lo + i]).sum(axis=1) >= least]
                    keep[near] = True
                    keep[lo + i] |= len(near) > 0
            yield b.select(list(range(6))).take(pa.array(np.flatnonzero(keep)))

    return compare


def _confirm_across(words: int, percent: int):
    """Exact links of each task that join what is not joined yet; texts are column 6."""

    def confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_group(batches):
            found = []
            for lo, hi in _group_cuts(b.column(0).to_numpy()):
                x, y, todo = _open_pairs(b, lo, hi)
                if not todo.any():
                    continue
                docs, top = b.column(1).slice(lo, hi - lo).to_numpy(), b.column(2).slice(lo, hi - lo).to_numpy().copy()
                sets = shingle_sets(b.column(6).slice(lo, hi - lo).to_pylist(), words)
                sizes = np.array([len(s) for s in sets])
                names, own = np.unique(np.concatenate(sets), return_inverse=True)
                parts = np.split(own, np.cumsum(sizes)[:-1])
                probed, begins = np.concatenate([parts[j] for j in y]), np.cumsum(sizes[y]) - sizes[y]
                held = np.zeros(len(names), bool)
                for i, row in zip(x.tolist(), todo, strict=True):
                    if not (row & (top[y] != top[i])).any():
                        continue
                    held[parts[i]] = True
                    both = np.add.reduceat(held[probed], begins, dtype=np.int64)
                    held[parts[i]] = False
                    for j in y[row & (both > 0) & (100 * both >= percent * (sizes[i] + sizes[y] - both))].tolist():
                        if top[i] != top[j]:
                            found.append((int(docs[i]), int(docs[j])))
                            top[top == top[j]] = top[i]
            yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], ["a", "b"])

    return confirm


def _across(large: DataFrame, classes: DataFrame, block: int) -> DataFrame:
    """Tasks (task, doc, label, probe, loose, before) that together hold every pair of a large node in different classes.

    The documents outside a node's largest class (loose) probe all of the node, blocks against blocks.
    ``before``: the large nodes of the document with lesser paths, which compare the pairs they share.
    """
    labelled = large.join(classes.withColumnRenamed("id", "doc"), "doc", "left").select("path", "doc", F.coalesce("component", "doc").alias("label"))
    labelled = written(labelled, "large")
    counts = labelled.groupBy("path", "label").agg(F.count("*").alias("n")).groupBy("path").agg(F.sum("n").alias("n"), F.max(F.struct("n", "label")).alias("most"))
    most = written(counts.where("n > most.n").select("path", "n", F.col("most.label").alias("most"), F.ceil(F.col("n") / block).alias("blocks"), F.ceil((F.col("n") - F.col("most.n")) / block).alias("probes")), "most")
    hot = most.where(F.col("n") > labelled.count() * HOT_SHARE)
    paths = large.groupBy("doc").agg(F.collect_set("path").alias("paths"))
    rows = join_hot(labelled, most.drop("n"), "path", hot).where("most is not null").join(paths, "doc").withColumn("loose", F.col("label") != F.col("most"))
    rows = rows.withColumn("before", F.filter("paths", lambda p: p < F.col("path"))).withColumn("hash", F.xxhash64("path", "doc"))
    first, second = F.pmod("hash", F.col("probes")), F.pmod("hash", F.col("blocks"))
    probing = rows.where("loose").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("task", F.xxhash64("path", first, F.col("other")))
    probed = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("probes") - 1))).withColumn("task", F.xxhash64("path", F.col("other"), second))
    columns = ["task", "doc", "label", "probe", "loose", "before"]
    return probing.withColumn("probe", F.lit(True)).select(columns).unionByName(probed.withColumn("probe", F.lit(False)).select(columns))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80, trees: int = 12, first: int = 2, small: int = 48, levels: int = 6, undivided: float = 0.75, size: int = 64, seed: int = 1) -> DataFrame:
    """One row a document: doc_id, n_shingles, component_id (the least id of its class), version (its text's hash), kept.

    ``percent``: documents are linked whose intersection is at least that share of their union.
    ``first``: trees whose links are confirmed before the others, which then only look for links
    between classes.  ``size``: coordinates of a sketch.  ``undivided``: a large node that still has
    this share of the node above it is not branched further but dealt to blocks, and compared whole
    at the end in blocks of about 16 * ``small`` documents.
    """
    spark = docs.sparkSession
    workers_import(spark)
    share = percent / 100
    extra = 1 / share - 1 + 0.1
    least = math.floor(size * (share - 4.5 * math.sqrt(share * (1 - share) / size)))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(F.col(text_col)).alias("version"))
    made = written(rows.mapInArrow(lean(_sketcher(words, size, trees, extra, seed)), "doc_id long, n_shingles long, f1 long, f2 long, tokens binary, paths array<long>, version long"), "sketches")
    usable = made.where("n_shingles > 0 and doc_id is not null")
    equal = written(usable.groupBy("f1", "f2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")), "sets")
    told = usable.groupBy("doc_id").agg(F.min("version").alias("own"), F.max("version").alias("other")).where("own <> other").select("doc_id", "own")
    one = usable.join(told, "doc_id", "left").where("own is null or own = version").drop("own")
    mine = one.join(equal.where("copies > 1").select("f1", "f2", "n_shingles", "rep"), ["f1", "f2", "n_shingles"], "left").where("rep is null or rep = doc_id")
    reps = written(mine.select(F.col("doc_id").alias("doc"), "version", "tokens", "paths").dropDuplicates(["doc"]), "reps")

    paths = written(reps.select("doc", F.explode("paths").alias("path"), F.lit(None).cast("long").alias("above")), "paths")
    nodes, large, level = [], [], 0
    while True:
        counted = written(paths.groupBy("path").agg(F.count("*").alias("n"), F.min("doc").alias("least"), F.max("above").alias("above")).where("n > 1"), "nodes")
        live = paths.drop("above").join(counted.withColumn("whole", (F.lit(level >= levels) | F.coalesce(F.col("n") >= undivided * F.col("above"), F.lit(False)))), "path")
        nodes.append(live.where(F.col("n") <= small).select("path", "doc"))
        block = F.xxhash64("path", F.pmod(F.xxhash64("path", "doc"), F.ceil(F.col("n") / (small - 8)).cast("long")))
        dealt = live.where((F.col("n") > small) & F.col("whole") & (F.col("doc") != F.col("least"))).select("least", block.alias("path"), "doc")
        large.append(live.where((F.col("n") > small) & F.col("whole")).select("path", "doc"))
        nodes += [dealt.select("path", "doc"), dealt.select("path", F.col("least").alias("doc")).distinct()]
        wide = live.where((F.col("n") > small) & ~F.col("whole")).select("path", "doc", "n")
        if counted.where((F.col("n") > small) & ~(F.lit(level >= levels) | F.coalesce(F.col("n") >= undivided * F.col("above"), F.lit(False)))).isEmpty():
            break
        level += 1
        paths = written(wide.join(reps.select("doc", "tokens"), "doc").select("path", "doc", "tokens", "n").mapInArrow(lean(_branch(extra)), "path long, doc long, above long").distinct(), "paths")
    grouped = nodes[0]
    for more in nodes[1:]:
        grouped = grouped.unionByName(more)
    sorted_by_node = lambda df: df.repartition(F.col("path")).sortWithinPartitions("path")
    likely = written(sorted_by_node(grouped.join(reps.select("doc", "tokens"), "doc").select("path", "doc", "tokens")).mapInArrow(lean(_likely(least)), "path long, doc long"), "likely")

    def texts_of(docs_of: DataFrame) -> DataFrame:
        wanted = docs_of.select("doc").distinct().join(reps.select("doc", "version"), "doc").withColumnRenamed("doc", "doc_id")
        return rows.join(wanted, ["doc_id", "version"], "left_semi").dropDuplicates(["doc_id"]).select(F.col("doc_id").alias("doc"), "text")

    texts = written(texts_of(likely), "texts")

    def confirmed(of: DataFrame) -> DataFrame:
        return sorted_by_node(of.join(texts, "doc").select("path", "doc", "label", "text")).mapInArrow(lean(_confirm(words, percent)), "a long, b long").distinct()

    turn = F.pmod(F.xxhash64("path", F.lit(seed)), F.lit(trees))
    links = written(confirmed(likely.where(turn < first).withColumn("label", F.col("doc"))), "links")
    classes = written(components(links), "classes")
    labelled = written(likely.where(turn >= first).join(classes.withColumnRenamed("id", "doc"), "doc", "left").select("path", "doc", F.coalesce("component", "doc").alias("label")), "likely")
    open_nodes = labelled.groupBy("path").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("path")
    more = confirmed(labelled.join(open_nodes, "path", "left_semi"))
    links = written(links.unionByName(more), "links")
    classes = written(components(links), "classes")
    undivided_nodes = large[0]
    for lower in large[1:]:
        undivided_nodes = undivided_nodes.unionByName(lower)
    undivided_nodes = written(undivided_nodes.distinct(), "large")
    if not undivided_nodes.isEmpty():
        tasks = _across(undivided_nodes, classes, 16 * small)
        by_task = lambda df: df.repartition(F.col("task")).sortWithinPartitions("task")
        kinds = "task long, doc long, label long, probe boolean, loose boolean, before array<long>"
        pairs = written(by_task(tasks.join(reps.select("doc", "tokens"), "doc").select(*tasks.columns, "tokens")).mapInArrow(lean(_likely_across(least)), kinds), "across")
        if not pairs.isEmpty():
            across = by_task(pairs.join(texts_of(pairs), "doc").select(*pairs.columns, "text")).mapInArrow(lean(_confirm_across(words, percent)), "a long, b long").distinct()
            links = written(links.unionByName(across), "links")
            classes = written(components(links), "classes")
    tops = equal.join(classes, equal["rep"] == classes["id"], "left").select("f1", "f2", "n_shingles", F.coalesce("component", "rep").alias("component"))
    tops = written(tops, "tops")
    known = made.drop("tokens", "paths").join(tops, ["f1", "f2", "n_shingles"], "left")
    top = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("component")).otherwise(F.col("doc_id"))
    return known.select("doc_id", "n_shingles", top.alias("component_id"), "version").withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))

"""Forward, backward and training on sampled minibatches.

A layer takes each vertex's own vector and the mean of its drawn neighbours' vectors, side by side, times a
weight matrix, with a rectifier between layers; the last layer's outputs are class scores. Kernels are
numpy, one minibatch at a time. Steps follow each other and are small, so that one task makes all steps of a bulk in turn:
minibatches are gathered by all tasks, and weights and optimizer go in and come out once for each bulk. The minibatches of one step see the
same weights, so that the task works on them in as many threads; there is nothing else to do meanwhile.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import durable, ensure_importable
from .features import feature_words, fetch_features
from .framework import SampleSpec, make_batches, sample_minibatches
from .grid import Grid
from .matrix import to_adjacency


@dataclass(frozen=True)
class ModelSpec:
    inputs: int
    hidden: int
    classes: int
    layers: int = 3
    rate: float = 0.01
    seed: int = 5
    #: Precision of vectors, weights and gradients.
    dtype: str = "float64"

    def weights(self) -> list[np.ndarray]:
        rng = np.random.default_rng(self.seed)
        sizes = [self.inputs, *[self.hidden] * (self.layers - 1), self.classes]
        return [rng.normal(0, np.sqrt(2 / (2 * a)), (2 * a, b)).astype(self.dtype) for a, b in zip(sizes, sizes[1:])]


@dataclass
class Minibatch:
    """Edges of each layer from the inputs to the batch, as local ids; vectors; labels of the batch's own vertices."""

    edges: list[tuple[np.ndarray, np.ndarray]]
    x: np.ndarray
    roots: np.ndarray
    labels: np.ndarray
    state: list = field(default_factory=list)


def local_minibatch(layers: list[tuple[int, np.ndarray, np.ndarray]], ids: np.ndarray, x: np.ndarray, roots: np.ndarray, labels: np.ndarray) -> Minibatch:
    """Global ids to positions in `ids` (sorted); layers ordered from the outermost (1) to the batch."""
    at = lambda v: np.searchsorted(ids, v)
    return Minibatch([(at(s), at(d)) for _, s, d in sorted(layers, key=lambda e: e[0])], x, at(roots), labels)


#: Rows that still have values to add, below which each is finished on its own.
FEW_ROWS = 16


def _row_sums(n: int, at: np.ndarray, values: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Sums of values[of] by row `at`, of n rows: the first value of every row, then the second of those that have one, and so on."""
    order = np.argsort(at, kind="stable")
    of, counts = of[order], np.bincount(at, minlength=n)
    rows = np.argsort(-counts, kind="stable")
    counts, starts = counts[rows], (np.cumsum(counts) - counts)[rows]
    sums, t = np.zeros((n, values.shape[1]), values.dtype), 0
    while (live := int(np.searchsorted(-counts, -t))) >= FEW_ROWS:
        now = values[of[starts[:live] + t]]
        if t:
            sums[:live] += now
        else:
            sums[:live] = now
        t += 1
    for k in range(live):
        sums[k] += values[of[starts[k] + t : starts[k] + counts[k]]].sum(axis=0)
    out = np.empty_like(sums)
    out[rows] = sums
    return out


def _distinct(x: np.ndarray) -> np.ndarray:
    """Sorted and without repeats; by sorting, which is faster here than a table."""
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


def _reach(m: Minibatch) -> list[tuple[np.ndarray, ...]]:
    """For each layer, from the inputs on: the vertices that it is computed for, its distinct edges from them, and the vertices that these need below."""
    n, need, out = len(m.x), np.unique(m.roots), []
    for src, dst in reversed(m.edges):
        asked = np.zeros(n, bool)
        asked[need] = True
        kept = asked[src]
        src, dst = np.divmod(_distinct(src[kept] * n + dst[kept]), max(1, n))
        asked[dst] = True
        below = np.flatnonzero(asked)
        out.append((need, src, dst, below))
        need = below
    return out[::-1]


def forward(m: Minibatch, weights: list[np.ndarray]) -> np.ndarray:
    """Class scores of the batch's own vertices; keeps what the backward pass needs. A layer computes what the roots see of it."""
    layers, m.state = _reach(m)[: len(weights)], []
    h = m.x[layers[0][3]]
    for k, (w, (need, src, dst, below)) in enumerate(zip(weights, layers)):
        place = np.empty(len(m.x), np.int64)
        place[need] = np.arange(len(need))
        src = place[src]
        place[below] = np.arange(len(below))
        own, dst = place[need], place[dst]
        count = np.maximum(np.bincount(src, minlength=len(need)), 1)[:, None]
        mean = _row_sums(len(need), src, h, dst)
        mean /= count.astype(h.dtype)
        both = np.concatenate([h[own], mean], axis=1)
        z = both @ w
        m.state.append((both, z, src, dst, count, own, len(below)))
        h = np.maximum(z, 0) if k + 1 < len(weights) else z
    return h[np.searchsorted(layers[-1][0], m.roots)]


def loss_and_gradients(m: Minibatch, weights: list[np.ndarray]) -> tuple[float, int, list[np.ndarray]]:
    """Summed cross-entropy over labelled roots, their number, and the summed gradients."""
    scores = forward(m, weights)
    known = m.labels >= 0
    shifted = scores - scores.max(axis=1, keepdims=True)
    p = np.exp(shifted)
    p /= p.sum(axis=1, keepdims=True)
    n = int(known.sum())
    loss = float(-np.log(np.maximum(p[known, m.labels[known]], 1e-30)).sum())
    g = p.copy()
    g[known, m.labels[known]] -= 1
    g[~known] = 0
    own = np.unique(m.roots)
    top = _row_sums(len(own), np.searchsorted(own, m.roots), g, np.arange(len(g)))
    out: list[np.ndarray] = [np.zeros_like(w) for w in weights]
    for k in range(len(weights) - 1, -1, -1):
        both, z, src, dst, count, own, n_below = m.state[k]
        gz = top if k + 1 == len(weights) else top * (z > 0)
        out[k] = both.T @ gz
        if k:
            gb = gz @ weights[k].T
            width = both.shape[1] // 2
            top = _row_sums(n_below, dst, gb[:, width:] / count.astype(gb.dtype), src)
            top[own] += gb[:, :width]
    return loss, n, out


def minibatch_rows(sampled: DataFrame, features: DataFrame, batches: DataFrame, labels: DataFrame, layers: int) -> DataFrame:
    """One row per batch: everything a kernel needs, gathered in two shuffles. A batch is bounded by its fan-out."""
    edges = sampled.groupBy("batch").agg(F.collect_list(F.struct("layer", "src", "dst")).alias("edges"))
    vectors = fetch_features(sampled, features, batches).groupBy("batch").agg(F.array_sort(F.collect_list(F.struct("v", "vec"))).alias("vectors"))
    marked = batches.join(labels.select("v", "label"), "v", "left").groupBy("batch").agg(F.array_sort(F.collect_list(F.struct("v", F.coalesce("label", F.lit(-1)).alias("label")))).alias("roots"))
    return marked.join(vectors, "batch").join(edges, "batch", "left")


def _among(x: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Whether each is one of the sorted ids."""
    return ids[np.minimum(np.searchsorted(ids, x), len(ids) - 1)] == x if len(ids) else np.zeros(len(x), bool)


def _minibatch(batch, r: int, layers: int, dtype="float64") -> tuple[np.ndarray, Minibatch]:
    """A row of an Arrow batch as (global ids, minibatch), from the arrays as they lie."""

    def column(name: str, *fields: str) -> list:
        held = batch.column(batch.schema.get_field_index(name)).slice(r, 1).flatten()
        return [held.field(f) for f in fields]

    v, vec = column("vectors", "v", "vec")
    ids = v.to_numpy(zero_copy_only=False).astype(np.int64)
    x = vec.flatten().to_numpy(zero_copy_only=False).astype(dtype).reshape(len(ids), -1)
    roots, labels = (a.to_numpy(zero_copy_only=False).astype(np.int64) for a in column("roots", "v", "label"))
    kept = _among(roots, ids)
    layer, src, dst = (a.to_numpy(zero_copy_only=False).astype(np.int64) for a in column("edges", "layer", "src", "dst"))
    ok = _among(src, ids) & _among(dst, ids)
    each = [(k, src[at], dst[at]) for k in range(1, layers + 1) for at in [ok & (layer == k)]]
    return ids, local_minibatch(each, ids, x, roots[kept], labels[kept])


def _minibatches(batch, layers: int, dtype="float64") -> Iterator[tuple[np.ndarray, Minibatch]]:
    """All rows of an Arrow batch."""
    return (_minibatch(batch, r, layers, dtype) for r in range(batch.num_rows))


class Adam:
    def __init__(self, rate: float):
        self.rate, self.t, self.m, self.v = rate, 0, None, None

    def step(self, weights: list[np.ndarray], gradients: list[np.ndarray]) -> list[np.ndarray]:
        self.t += 1
        if self.m is None:
            self.m, self.v = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights]
        out = []
        for k, (w, g) in enumerate(zip(weights, gradients)):
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            out.append((w - self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)).astype(w.dtype))
        return out


@dataclass
class Progress:
    """What passes from one bulk to the next: weights, optimizer, the gradients of the step under way, and sums for the report."""

    weights: list[np.ndarray]
    optimizer: Adam
    pending: list[np.ndarray] | None = None
    held: int = 0
    loss: float = 0.0
    labelled: int = 0
    steps: int = 0

    def add(self, loss: float, n: int, gradients: list[np.ndarray]) -> None:
        self.loss, self.labelled, self.held = self.loss + loss, self.labelled + n, self.held + n
        self.pending = gradients if self.pending is None else [x + y for x, y in zip(self.pending, gradients)]

    def step(self) -> None:
        self.steps += 1
        if self.held:
            self.weights = self.optimizer.step(self.weights, [x / self.held for x in self.pending])
        self.pending, self.held = None, 0


#: Neighbours of a vertex that race in one task.
BLOCK = 1024
#: Minibatches in one Arrow batch.
TOGETHER = 8


def _few_together(spark, action):
    """Run an action whose rows are whole minibatches: few of them at a time go to a Python worker."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(TOGETHER))
    try:
        return action()
    finally:
        spark.conf.set(name, before)


def steps_of(found: Iterable, now: Progress, low: int, end: int, count: int, processes: int, layers: int, threads: int) -> Progress:
    """All updates from Arrow batches whose rows are minibatches in order."""
    from concurrent.futures import ThreadPoolExecutor

    at, due = low, []

    def gradients(held: tuple):
        return loss_and_gradients(_minibatch(*held, layers, now.weights[0].dtype)[1], now.weights)

    def settle() -> None:
        # the minibatches of a step see the same weights; their gradients are summed in order
        for x in pool.map(gradients, due):
            now.add(*x)
        due.clear()

    def close(upto: int) -> None:
        # batches without any row count for their step too
        nonlocal at
        for b in range(at, upto):
            if (b + 1) % processes == 0 or b + 1 == count:
                settle()
                now.step()
        at = max(at, upto)

    with ThreadPoolExecutor(threads) as pool:
        for batch in found:
            for r, b in enumerate(batch.column(batch.schema.get_field_index("batch")).to_pylist()):
                close(b)
                due.append((batch, r))
        close(end)
        settle()
    return now


def run_steps(rows: DataFrame, progress: Progress, low: int, end: int, count: int, processes: int, layers: int) -> Progress:
    """All updates of the batches from `low` up to `end`, one for each `processes` batches, in the order of the batches."""
    import pickle

    import pyarrow as pa

    spark = rows.sparkSession
    ensure_importable(spark)
    sent = spark.sparkContext.broadcast(progress)

    def work(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        threads = max(1, min(processes, len(os.sched_getaffinity(0))))
        now = steps_of(found, sent.value, low, end, count, processes, layers, threads)
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(now)], pa.binary())], ["state"])

    ordered = rows.select("batch", "vectors", "roots", "edges").coalesce(1).sortWithinPartitions("batch")
    found = _few_together(spark, ordered.mapInArrow(work, "state binary").collect)
    sent.unpersist()
    if found:
        return pickle.loads(bytes(found[0]["state"]))
    for b in range(low, end):
        if (b + 1) % processes == 0 or b + 1 == count:
            progress.step()
    return progress


@dataclass
class EpochReport:
    """`seconds` by phase; `remote_words`: feature words that another block row owns, if a grid was given."""

    epoch: int
    loss: float
    labelled: int
    steps: int
    seconds: dict[str, float]
    k: int = 0
    remote_words: int | None = None

    @property
    def sampling_share(self) -> float:
        return self.seconds["sampling"] / max(1e-9, sum(self.seconds.values()))


def train(
    edges: DataFrame, features: DataFrame, labels: DataFrame, train_vertices: DataFrame, model: ModelSpec, spec: SampleSpec, batch_size: int,
    epochs: int = 1, processes: int = 4, k: int | None = None, weights: list[np.ndarray] | None = None, adjacency=None, memory: int | None = None,
    words_over: Grid | None = None,
) -> tuple[list[np.ndarray], list[EpochReport]]:
    """Bulk-synchronous training: sample k batches at once, fetch, then one update per `processes` batches.

    Samples depend on seed, epoch and batch only, so any k gives the same weights. Without k all batches are sampled together,
    or as many as the planner finds room for in `memory` bytes for each process.
    """
    from dataclasses import replace
    from time import perf_counter

    weights = weights or model.weights()
    train_vertices = durable(train_vertices)  # read several times in each epoch
    if adjacency is None and spec.node_wise and spec.method == "race_uniform" and spec.strategy == "shuffle":
        # made once for all epochs; a race draws for every neighbour, so that the draws of a hub are dealt out by its blocks
        adjacency = to_adjacency(edges, BLOCK)
    progress, reports = Progress(weights, Adam(model.rate)), []
    for epoch in range(epochs):
        batches = durable(make_batches(train_vertices, batch_size, spec.seed, epoch))
        count = (batches.agg(F.max("batch")).first()[0] or 0) + 1 if not batches.isEmpty() else 0
        progress = replace(progress, pending=None, held=0, loss=0.0, labelled=0, steps=0)
        seconds, words = {"sampling": 0.0, "fetch": 0.0, "propagation": 0.0}, 0
        if k is None and memory is not None:
            from ..plans.planner import plan_epoch

            width = plan_epoch(edges, features, count, batch_size, spec.fanout, processes, memory).k
        else:
            width = k or max(1, count)
        for low in range(0, count, width):
            end = min(low + width, count)
            bulk = batches.where(f"batch >= {low} AND batch < {end}")
            t = perf_counter()
            sampled = durable(sample_minibatches(edges, bulk, replace(spec, seed=spec.seed + 1000 * epoch), adjacency))
            seconds["sampling"] += perf_counter() - t
            t = perf_counter()
            rows = durable(minibatch_rows(sampled, features, bulk, labels, model.layers))
            seconds["fetch"] += perf_counter() - t
            if words_over is not None:
                words += feature_words(sampled, words_over, model.inputs).agg(F.sum("remote_words")).first()[0] or 0
            t = perf_counter()
            progress = run_steps(rows, progress, low, end, count, processes, model.layers)
            seconds["propagation"] += perf_counter() - t
        reports.append(EpochReport(epoch, progress.loss / max(1, progress.labelled), progress.labelled, progress.steps, seconds, width, words if words_over is not None else None))
    return progress.weights, reports


def evaluate(edges: DataFrame, features: DataFrame, labels: DataFrame, vertices: DataFrame, weights: list[np.ndarray], spec: SampleSpec, batch_size: int, adjacency=None) -> DataFrame:
    """(v, label, predicted) of the vertices under a test fan-out."""
    import pyarrow as pa

    layers = len(weights)
    batches = durable(make_batches(vertices, batch_size, spec.seed))
    rows = minibatch_rows(sample_minibatches(edges, batches, spec, adjacency), features, batches, labels, layers)
    ensure_importable(rows.sparkSession)
    sent = rows.sparkSession.sparkContext.broadcast(weights)

    def work(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in found:
            for ids, m in _minibatches(batch, layers, sent.value[0].dtype):
                scores = forward(m, sent.value)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids[m.roots]), pa.array([int(x) if x >= 0 else None for x in m.labels], pa.int64()), pa.array(scores.argmax(axis=1), pa.int64())],
                    ["v", "label", "predicted"],
                )

    return _few_together(rows.sparkSession, lambda: durable(rows.mapInArrow(work, "v long, label long, predicted long")))


def text_features(documents: DataFrame, width: int = 64, n: int = 3) -> DataFrame:
    """(v, vec): hashed character n-gram frequencies of whole texts, scaled to unit length."""
    import pyarrow as pa

    ensure_importable(documents.sparkSession)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text in batch.column(1).to_pylist():
                codes = np.frombuffer((text or "").lower().encode(), np.uint8).astype(np.uint64)
                h = np.zeros(max(0, len(codes) - n + 1), np.uint64)
                for k in range(n):
                    h = h * np.uint64(1099511628211) + codes[k : len(codes) - n + 1 + k]
                counts = np.bincount((((h * np.uint64(11400714819323198485)) >> np.uint64(40)) % np.uint64(width)).astype(np.int64), minlength=width)
                rows.append((counts / max(1e-30, np.sqrt((counts * counts).sum()))).astype(np.float32))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r.tolist() for r in rows], pa.list_(pa.float32()))], ["v", "vec"])

    return documents.select("doc_id", "text").mapInArrow(work, "v long, vec array<float>")

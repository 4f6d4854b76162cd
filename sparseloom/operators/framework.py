"""Bulk sampling: the layers of all batches of a bulk, one relation per hop."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from time import perf_counter

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import BITS, u52
from ..sources.graphs import running_offsets
from ..sources.tables import durable, small_enough
from . import draw, grid, matrix, samplers
from .samplers import LayerIndependent, LayerWise, NodeWise, Sampler

#: Training vertices in one range of the hash, on average, when batches are ranked; and the most ranges.
RANKED_TOGETHER, MOST_RANGES = 1 << 16, 1 << 20


def make_batches(vertices: DataFrame, size: int, seed: int = 42, epoch: int = 0, mode: str = "exact", count: int | None = None) -> DataFrame:
    """Training vertices (column v) to (batch, pos, v).

    `exact`: all batches full but the last, by rank in hash order; `bucketed`: batch by hash modulo the
    number of batches, without any ranking across tasks.
    """
    hashed = vertices.select("v").withColumn("h", u52(seed, "batch", epoch, F.col("v")))
    if mode == "bucketed":
        if count is None:
            count = max(1, -(-vertices.count() // size))
        pos = F.row_number().over(Window.partitionBy("batch").orderBy("h", "v")) - 1
        return hashed.withColumn("batch", F.pmod("h", F.lit(count))).select("batch", pos.cast("long").alias("pos"), "v")
    bits = min(MOST_RANGES, max(1024, vertices.count() // RANKED_TOGETHER)).bit_length() - 1
    ranged = hashed.withColumn("part", F.shiftright("h", BITS - bits))
    inside = F.row_number().over(Window.partitionBy("part").orderBy("h", "v"))
    ranked = ranged.join(F.broadcast(running_offsets(ranged)), "part").withColumn("rank", F.col("offset") + inside - 1)
    return ranked.select(F.floor(F.col("rank") / size).cast("long").alias("batch"), F.pmod("rank", F.lit(size)).cast("long").alias("pos"), "v")


def bulks(batches: DataFrame, k: int) -> DataFrame:
    """Adds bulk: k batches at a time."""
    return batches.withColumn("bulk", F.floor(F.col("batch") / k).cast("long"))


#: Draws of one spec: those for equal weights, and those that follow the weights.
EQUAL, WEIGHTED = ("race_uniform", "positions"), ("race", "its", "its_fixed", "rejection", "with_replacement")
_OPTIONS = {
    "race_uniform": {"rng"}, "positions": {"rng"}, "race": {"rng"}, "its": {"overdraw"}, "its_fixed": {"draws", "complete"}, "rejection": {"tries"}, "with_replacement": set(),
}
STRATEGIES = ("shuffle", "replicated", "bucketed", "grid")


@dataclass(frozen=True)
class SampleSpec:
    """What to sample. `fanout[0]` applies next to the batch; None takes every neighbour.

    `sampler` may be the name of a registered one. Without a `method` the draw follows the sampler's law: `race_uniform` where all
    weights are equal, `race` where they are not. Combinations that are not built are refused.
    """

    sampler: Sampler | str = NodeWise()
    fanout: tuple[int | None, ...] = (15, 10, 5)
    seed: int = 42
    method: str | None = None
    strategy: str = "shuffle"
    grid: grid.Grid | None = None
    options: tuple[tuple[str, object], ...] = ()
    #: Write each hop before the next one starts: no hop is planned or computed again inside a later one.
    cut_layers: bool = True

    def __post_init__(self) -> None:
        if isinstance(self.sampler, str):
            object.__setattr__(self, "sampler", samplers.REGISTRY[self.sampler]())
        if self.method is None:
            object.__setattr__(self, "method", "race_uniform" if self.sampler.equal_weights else "race")
        if self.method not in (*EQUAL, *WEIGHTED):
            raise ValueError(f"unknown method {self.method!r}")
        if self.strategy not in STRATEGIES:
            raise ValueError(f"unknown strategy {self.strategy!r}")
        if self.method in EQUAL and not self.sampler.equal_weights:
            raise ValueError(f"{self.method} draws as if all weights were equal; this sampler's are not")
        if self.method == "positions" and self.strategy not in ("bucketed", "replicated"):
            raise ValueError("positions are drawn from adjacency rows: strategy 'bucketed' or 'replicated'")
        if self.node_wise and self.strategy in ("bucketed", "replicated") and self.method not in EQUAL:
            raise ValueError("where the adjacency row lies, draws are race_uniform or positions")
        if self.strategy != "shuffle" and not (self.node_wise or type(self.sampler) is LayerWise):
            raise ValueError(f"{self.strategy} is built for node-wise draws of equal weight and for the layer-wise sampler")
        if self.strategy == "grid" and self.grid is None:
            raise ValueError("strategy 'grid' needs a grid")
        if not set(dict(self.options)) <= _OPTIONS[self.method]:
            raise ValueError(f"{self.method} takes {sorted(_OPTIONS[self.method])}; got {dict(self.options)}")

    @property
    def node_wise(self) -> bool:
        return isinstance(self.sampler, NodeWise) and self.sampler.equal_weights


class Timings(dict):
    """Seconds by part: probability, sampling, extraction. Each part is then written before the next one starts."""

    def part(self, name: str, df: DataFrame) -> DataFrame:
        t = perf_counter()
        out = durable(df)
        self[name] = self.get(name, 0.0) + perf_counter() - t
        return out


def sample_minibatches(edges: DataFrame, batches: DataFrame, spec: SampleSpec, adjacency: matrix.Adjacency | DataFrame | None = None, timings: Timings | None = None) -> DataFrame:
    """(batch, layer, row_id, src, dst, rank) over all layers; layers count down to 1 away from the batch.

    `adjacency`: the graph at rest in rows, for the strategies that draw there; made from `edges` otherwise.
    """
    graph = _at_hand(edges, spec, adjacency)
    frontier, out = spec.sampler.init_frontier(batches), None
    for hop, s in enumerate(spec.fanout):
        layer = len(spec.fanout) - hop
        sampled, picked = _hop(spec, frontier, graph, s, layer, timings)
        sampled = sampled.select("batch", F.lit(layer).cast("long").alias("layer"), "row_id", "src", "dst", "rank")
        if layer > 1 and spec.cut_layers and timings is None:
            sampled = durable(sampled)
            picked = picked if picked is not None and not spec.node_wise else None
        out = sampled if out is None else out.unionByName(sampled)
        if layer > 1:
            if picked is None:
                picked = sampled.select("batch", "row_id", F.col("dst").alias("col"), "rank")
            frontier = spec.sampler.next_frontier(sampled, picked, s if s is not None else 1 << 20, frontier)
            if spec.cut_layers and not spec.node_wise:
                frontier = durable(frontier)
    return out


def _at_hand(edges: DataFrame, spec: SampleSpec, adjacency) -> DataFrame | matrix.Adjacency:
    """The graph in the form that the strategy joins with."""
    if isinstance(adjacency, DataFrame):
        adjacency = matrix.Adjacency(adjacency)
    in_rows = spec.strategy in ("bucketed", "replicated") or spec.strategy in ("shuffle", "grid") and spec.node_wise and spec.method == "race_uniform"
    if in_rows:
        if adjacency is None:
            adjacency = matrix.to_adjacency(edges, cut=len(spec.fanout) > 1)
        if spec.strategy == "replicated" and small_enough(adjacency.rows):
            return adjacency.replicated()
        return adjacency  # too large a graph for every process stays where it is
    return durable(edges) if len(spec.fanout) > 1 and spec.cut_layers else edges


def _hop(spec: SampleSpec, frontier: DataFrame, graph, s: int | None, layer: int, timings: Timings | None):
    """One hop: sampled edges, and the drawn columns where these are not simply the edges' ends."""
    step = timings.part if timings is not None else (lambda _, df: df)
    options = dict(spec.options)
    if spec.node_wise and isinstance(graph, matrix.Adjacency):
        if spec.strategy == "grid":
            frontier, graph = grid.rows_on_grid(frontier, graph, spec.grid)
        if s is None:
            sampled = _all_of(graph.expand(frontier))
        else:
            drawn = samplers.positions if spec.method == "positions" else samplers.pushdown
            sampled = drawn(frontier, graph, s, spec.seed, layer, **options)
        return step("sampling", sampled), None
    if isinstance(spec.sampler, LayerIndependent):
        picked = samplers.independent_picks(spec.sampler, frontier, graph, s, spec, layer)
        picked = step("sampling", picked)
        return step("extraction", spec.sampler.extract(frontier, graph, picked)), picked
    if isinstance(spec.sampler, LayerWise):
        rows = grid.extract_rows_grid(frontier, graph, spec.grid) if spec.strategy == "grid" else samplers.extract_rows(frontier, graph)
        rows = step("extraction", rows)
        prob = step("probability", spec.sampler.weigh_rows(rows))
        picked = step("sampling", _every_column(prob) if s is None else draw.sample_rows(prob, s, spec.seed, layer, spec.method, **options))
        found = grid.extract_columns_grid(rows, picked, spec.grid) if spec.strategy == "grid" else samplers.extract_columns(rows, picked)
        return step("extraction", found), picked
    prob = step("probability", _grid_prob(spec, frontier, graph) if spec.strategy == "grid" else spec.sampler.weigh(frontier, graph))
    picked = step("sampling", _every_column(prob) if s is None else draw.sample_rows(prob, s, spec.seed, layer, spec.method, **options))
    return step("extraction", spec.sampler.extract(frontier, graph, picked)), picked


def _grid_prob(spec: SampleSpec, frontier: DataFrame, edges: DataFrame) -> DataFrame:
    """The product on the grid; the row's vertex rides along, so that the draw needs no join back."""
    q = frontier.select("batch", F.col("v").alias("src"), F.col("row_id").alias("row"), F.col("v").alias("col"), F.lit(1).cast("long").alias("val"))
    product = grid.spgemm_grid(q, edges.withColumnsRenamed({"src": "row", "dst": "col"}), spec.grid, keys=("batch", "src"))
    return product.select("batch", F.col("row").alias("row_id"), "col", F.col("val").alias("w"), "src")


def _every_column(prob: DataFrame) -> DataFrame:
    order = Window.partitionBy("batch", "row_id").orderBy("col")
    return prob.select("batch", "row_id", "col").withColumn("rank", F.row_number().over(order).cast("long"))


def _all_of(prob: DataFrame) -> DataFrame:
    """Every neighbour, in order."""
    order = Window.partitionBy("batch", "row_id").orderBy("col")
    return prob.select("batch", "row_id", "src", F.col("col").alias("dst"), F.row_number().over(order).cast("long").alias("rank"))


def in_bulks(edges: DataFrame, batches: DataFrame, spec: SampleSpec, k: int, count: int, adjacency=None) -> Iterator[DataFrame]:
    """The samples of k batches at a time, one after the other: each bulk is a plan of its own, made when it is asked for."""
    for low in range(0, count, k):
        yield sample_minibatches(edges, batches.where(f"batch >= {low} AND batch < {low + k}"), spec, adjacency)


def batch_slice(sampled: DataFrame, batch: int) -> DataFrame:
    return sampled.where(F.col("batch") == batch)


def subgraphs(sampled: DataFrame) -> DataFrame:
    """Self-contained minibatches: batch, layers (array of layer and edges), vertices. One row per batch for trainers."""
    edges = F.array_sort(F.collect_list(F.struct("row_id", "rank", "src", "dst")))
    layers = sampled.groupBy("batch", "layer").agg(edges.alias("edges"), F.array_union(F.collect_set("src"), F.collect_set("dst")).alias("vs"))
    return layers.groupBy("batch").agg(
        F.array_sort(F.collect_list(F.struct("layer", "edges"))).alias("layers"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("vs")))).alias("vertices")
    )

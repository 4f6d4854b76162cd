"""Samplers: how a frontier becomes weights, which edges a draw extracts, what the next frontier is.

A frontier is (batch, row_id, v). `batch` is a key everywhere: many batches are one relation, and
one batch is the same relation with one key.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ranges import range_of, upto_cuts
from ..functions.rng import digits52, h52, stem, u52
from ..sources.tables import durable, ensure_importable
from . import draw, matrix
from .matrix import Adjacency


class Sampler:
    """Base of all samplers; a new one supplies these four, and says whether all its weights are equal."""

    equal_weights = False

    def init_frontier(self, batches: DataFrame) -> DataFrame:
        raise NotImplementedError

    def weigh(self, frontier: DataFrame, edges: DataFrame) -> DataFrame:
        """(batch, row_id, col, w)."""
        raise NotImplementedError

    def extract(self, frontier: DataFrame, edges: DataFrame, picked: DataFrame) -> DataFrame:
        """(batch, row_id, src, dst, rank)."""
        raise NotImplementedError

    def next_frontier(self, sampled: DataFrame, picked: DataFrame, s: int, frontier: DataFrame) -> DataFrame:
        raise NotImplementedError


@dataclass(frozen=True)
class NodeWise(Sampler):
    """Each frontier vertex draws among its own neighbours.

    `occurrence`: every drawn edge is a row of the next frontier; `distinct`: repeats within a batch merge.
    `weight`: a column of the edges (positive integers) by which neighbours are drawn; without one all are alike.
    """

    frontier: str = "occurrence"
    weight: str | None = None

    @property
    def equal_weights(self) -> bool:
        return self.weight is None

    def init_frontier(self, batches: DataFrame) -> DataFrame:
        row = F.col("pos") if self.frontier == "occurrence" else F.col("v")
        return batches.select("batch", row.cast("long").alias("row_id"), "v")

    def weigh(self, frontier: DataFrame, edges: DataFrame) -> DataFrame:
        w = F.lit(1) if self.weight is None else F.col(self.weight)
        met = frontier.join(edges.select("src", "dst", w.cast("long").alias("w")), F.col("v") == F.col("src"))
        return met.select("batch", "row_id", F.col("dst").alias("col"), "w", F.col("v").alias("src"))

    def extract(self, frontier: DataFrame, edges: DataFrame, picked: DataFrame) -> DataFrame:
        # the drawn entries are the edges already: their row is the frontier vertex
        return picked.join(frontier, ["batch", "row_id"]).select("batch", "row_id", F.col("v").alias("src"), F.col("col").alias("dst"), "rank")

    def next_frontier(self, sampled: DataFrame, picked: DataFrame, s: int, frontier: DataFrame) -> DataFrame:
        if self.frontier == "occurrence":
            return sampled.select("batch", (F.col("row_id") * s + F.col("rank") - 1).alias("row_id"), F.col("dst").alias("v"))
        return sampled.select("batch", F.col("dst").alias("row_id"), F.col("dst").alias("v")).distinct()


@dataclass(frozen=True)
class LayerWise(Sampler):
    """Each batch draws among the neighbours of its whole frontier, by the `power` of how many see them.

    `include_self`: the frontier's own vertices go on to the next layer beside the drawn ones.
    """

    power: int = 2
    include_self: bool = False

    def init_frontier(self, batches: DataFrame) -> DataFrame:
        return batches.select("batch", F.lit(0).cast("long").alias("row_id"), "v").distinct()

    def weigh(self, frontier: DataFrame, edges: DataFrame) -> DataFrame:
        return self.weigh_rows(extract_rows(frontier, edges))

    def weigh_rows(self, rows: DataFrame) -> DataFrame:
        """The weights, from the rows of the graph that the frontier names: (batch, src, dst)."""
        e = rows.groupBy("batch", F.lit(0).cast("long").alias("row_id"), F.col("dst").alias("col")).agg(F.count(F.lit(1)).alias("e"))
        w = F.lit(1).cast("long")
        for _ in range(self.power):
            w = w * F.col("e")
        return e.select("batch", "row_id", "col", w.alias("w"))

    def extract(self, frontier: DataFrame, edges: DataFrame, picked: DataFrame) -> DataFrame:
        return extract_columns(extract_rows(frontier, edges), picked)

    def next_frontier(self, sampled: DataFrame, picked: DataFrame, s: int, frontier: DataFrame) -> DataFrame:
        drawn = picked.select("batch", F.lit(0).cast("long").alias("row_id"), F.col("col").alias("v"))
        return drawn.union(frontier.select("batch", "row_id", "v")).distinct() if self.include_self else drawn


@dataclass(frozen=True)
class LayerIndependent(LayerWise):
    """Each batch draws among all vertices, by their degree (or its square), whatever the frontier."""

    weight: str = "degree"

    def vertex_weights(self, edges: DataFrame) -> DataFrame:
        """(col, w): one row per vertex, the same for all batches."""
        deg = edges.groupBy(F.col("src").alias("col")).agg(F.count(F.lit(1)).alias("deg"))
        return deg.select("col", (F.col("deg") * F.col("deg") if self.weight == "degree_sq" else F.col("deg")).alias("w"))

    def weigh(self, frontier: DataFrame, edges: DataFrame) -> DataFrame:
        """The whole matrix, batches by vertices: for tables of a size to look at. Draws come from `independent_draws`."""
        batches = frontier.select("batch", "row_id").distinct()
        return self.vertex_weights(edges).crossJoin(F.broadcast(batches)).select("batch", "row_id", "col", "w")


def independent_picks(sampler: LayerIndependent, frontier: DataFrame, edges: DataFrame, s: int | None, spec, layer: int) -> DataFrame:
    """The layer-independent draws of a bulk: from one shared table of prefix sums, never batches by vertices."""
    if s is None:
        raise ValueError("drawing every vertex for every batch is the graph itself; give a number")
    if spec.method not in ("race", "its", "its_fixed"):
        raise ValueError(f"{spec.method} is not built for the layer-independent sampler")
    return independent_draws(edges, frontier.select("batch").distinct(), s, spec.seed, layer, sampler.weight, dict(spec.options).get("draws"))


#: Rounds of draws of the layer-independent sampler before batches that are still short are completed otherwise.
INDEPENDENT_ROUNDS = 16


def independent_draws(edges: DataFrame, batches: DataFrame | int, s: int, seed: int, layer: int = 1, weight: str = "degree", draws: int | None = None) -> DataFrame:
    """Draws of all batches (a number, or a table of them) from one shared distribution: (batch, row_id, col, rank).

    One prefix-sum table over the vertices, in the order of their ids, serves all batches. It is cut into ranges at quantiles of the ids,
    and the ranges' running totals are a table of bounded size; a draw finds its range there, and its vertex inside the range.
    Batches still short after `draws` draw on, in rounds.
    """
    spark = edges.sparkSession
    draws = draws or 4 * s
    w = LayerIndependent(weight=weight).vertex_weights(edges)
    n_cols = w.count()
    if not n_cols:
        return spark.createDataFrame([], "batch long, row_id long, col long, rank long")
    parts = min(4096, max(1, n_cols // 4096))
    w = w.withColumn("part", range_of(w, "col", parts))
    inside = Window.partitionBy("part").orderBy("col")
    w = durable(w.withColumn("hi", F.sum("w").over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow))))
    totals = [tuple(r) for r in w.groupBy("part").agg(F.sum("w").alias("n")).orderBy("part").collect()]  # at most 4097 rows
    ranges, at = [], 0
    for part, n in totals:
        ranges.append((part, at, at + n))
        at += n
    asked_of = durable(spark.range(batches).withColumnRenamed("id", "batch") if isinstance(batches, int) else batches)
    if n_cols <= s:  # few vertices: every batch takes all
        order = Window.partitionBy("batch").orderBy("col")
        every = asked_of.crossJoin(F.broadcast(w.select("col"))).withColumn("rank", F.row_number().over(order).cast("long"))
        return every.select("batch", F.lit(0).cast("long").alias("row_id"), "col", "rank")
    index = F.broadcast(spark.createDataFrame([(k, part, low) for k, (part, low, _) in enumerate(ranges)], "k long, part long, low long"))
    hits, short = None, asked_of
    for turn in range(INDEPENDENT_ROUNDS):
        asked = short.select("batch", F.explode(F.sequence(F.lit(turn * draws), F.lit((turn + 1) * draws - 1))).alias("t"))
        asked = asked.withColumn("r", F.pmod(u52(seed, F.col("batch"), layer, 0, F.col("t")), F.lit(at)))
        # the range that holds a draw: as many ranges end at or before it
        asked = asked.withColumn("k", upto_cuts(F.col("r"), [high for _, _, high in ranges]))
        placed = asked.join(index, "k").select("batch", "t", "part", (F.col("r") - F.col("low")).alias("r"))
        new = placed.join(w, "part").where("r >= hi - w AND r < hi").select("batch", "col", "t")
        hits = durable((new if hits is None else hits.unionByName(new)).groupBy("batch", "col").agg(F.min("t").alias("t")))
        got = hits.groupBy("batch").agg(F.count(F.lit(1)).alias("got"))
        short = durable(asked_of.join(got, "batch", "left").where(F.coalesce("got", F.lit(0)) < s).select("batch"))
        if short.isEmpty():
            break
    best = Window.partitionBy("batch").orderBy("t")
    picked = hits.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= s).select("batch", F.lit(0).cast("long").alias("row_id"), "col", F.col("rank").cast("long").alias("rank"))
    if short.isEmpty():
        return picked
    # weights so uneven that many rounds don't reach enough vertices: those left race
    left = w.select("col", "w").crossJoin(short).join(hits, ["batch", "col"], "left").withColumn("row_id", F.lit(0).cast("long"))
    return picked.join(short, "batch", "left_anti").unionByName(draw.completed(left, s, seed, layer).drop("t"))


def extract_rows(frontier: DataFrame, graph: DataFrame | Adjacency) -> DataFrame:
    """Rows of the graph that the frontier names, per batch: (batch, src, dst)."""
    named = frontier.select("batch", "v").distinct()
    if isinstance(graph, Adjacency):
        return graph.expand(named.withColumn("row_id", F.lit(0).cast("long"))).select("batch", "src", F.col("col").alias("dst"))
    return named.join(graph.select("src", "dst"), F.col("v") == F.col("src")).select("batch", "src", "dst")


def extract_columns(rows: DataFrame, picked: DataFrame) -> DataFrame:
    """Of these, the columns that the batch has drawn. The batch in the key is the block diagonal."""
    cols = picked.select("batch", F.col("col").alias("dst"), "rank")
    return rows.join(cols, ["batch", "dst"]).select("batch", F.lit(0).cast("long").alias("row_id"), "src", "dst", "rank")


def extract_columns_chunked(rows: DataFrame, picked: DataFrame, batches: int, chunk: int) -> DataFrame:
    """The same in several smaller products, `chunk` batches each: a chunk lies in one task, and a task multiplies its chunks in turn.

    Both sides are made once, for all chunks.
    """
    end = -(-max(1, batches) // chunk) * chunk
    number = F.floor(F.col("batch") / chunk).alias("chunk")
    left = rows.where(F.col("batch").between(0, end - 1)).select(number, "batch", "src", "dst").repartition("chunk")
    right = picked.where(F.col("batch").between(0, end - 1)).select(number, "batch", F.col("col").alias("dst"), "rank").repartition("chunk")
    met = left.hint("merge").join(right, ["chunk", "batch", "dst"])
    return met.select("batch", F.lit(0).cast("long").alias("row_id"), "src", "dst", "rank")


def compact_columns(sampled: DataFrame) -> DataFrame:
    """Adds local_col: the drawn vertices of a batch and layer, numbered in order."""
    keys = [k for k in ("batch", "layer") if k in sampled.columns]
    return matrix.compact(sampled, keys, col="dst")


def uncovered(frontier: DataFrame, sampled: DataFrame) -> DataFrame:
    """Per batch: frontier vertices, and those that no drawn edge reaches."""
    asked = frontier.select("batch", "v").distinct()
    reached = sampled.select("batch", F.col("src").alias("v")).distinct().withColumn("hit", F.lit(1))
    return asked.join(reached, ["batch", "v"], "left").groupBy("batch").agg(
        F.count(F.lit(1)).alias("vertices"), F.sum(F.when(F.col("hit").isNull(), 1).otherwise(0)).alias("uncovered")
    )


def debiased(sampled: DataFrame, prob: DataFrame, s: int) -> DataFrame:
    """Adds scale: 1 / (s p) of the drawn vertex, as a share of its row's sum."""
    total = F.sum("w").over(Window.partitionBy("batch", "row_id"))
    weights = prob.withColumn("p", F.col("w") / total).select("batch", F.col("col").alias("dst"), "p")
    raw = sampled.join(weights, ["batch", "dst"]).withColumn("scale", 1 / (F.lit(s) * F.col("p")))
    return raw.withColumn("scale", F.col("scale") / F.sum("scale").over(Window.partitionBy("batch", "src"))).drop("p")


REGISTRY: dict[str, type[Sampler]] = {"node_wise": NodeWise, "layer_wise": LayerWise, "layer_independent": LayerIndependent}


def register_sampler(name: str, sampler: type[Sampler]) -> None:
    """Make a sampler of one's own known by name; `SampleSpec(sampler=name)` finds it."""
    REGISTRY[name] = sampler


def race_rows(prob: DataFrame, s: int, seed: int, layer: int, rng: str = "md5") -> DataFrame:
    """The `s` smallest draws of each row of equal weights, with the row's vertex: (batch, row_id, src, dst, rank)."""
    best = Window.partitionBy("batch", "row_id").orderBy("key", "col")
    ranked = prob.withColumn("key", _key(rng, seed, F.col("batch"), layer, F.col("row_id"), F.col("col"))).withColumn("rank", F.row_number().over(best))
    return ranked.where(F.col("rank") <= s).select("batch", "row_id", "src", F.col("col").alias("dst"), F.col("rank").cast("long").alias("rank"))


def _key(rng: str, *at):
    return h52(*at) if rng == "md5" else u52(*at, kind=rng)


def pushdown(frontier: DataFrame, adjacency: Adjacency, s: int, seed: int, layer: int, rng: str = "md5") -> DataFrame:
    """Node-wise draws made where the adjacency row lies: only `s` picks leave the join, not all neighbours.

    Weights are equal, so ranking neighbours by their draw is the uniform sample without replacement, and the
    same one that `race` with unit weights gives. Works on a bucketed adjacency without moving it. Of a row in blocks,
    each block gives its `s` smallest draws, and the smallest of these are kept.
    """
    at = [seed, F.col("batch"), layer, F.col("row_id")]
    # what the draws of one row have in common is put together once, before the join
    frontier = adjacency.dealt(frontier)
    asked = frontier.withColumn("stem", stem(*at)) if rng == "md5" else frontier
    in_numpy = rng == "md5" and dict(adjacency.rows.dtypes)["nbrs"] == "array<bigint>"
    key = (lambda n: digits52(F.col("stem"), n)) if rng == "md5" else (lambda n: u52(*at, n, kind=rng))
    picks = F.slice(F.sort_array(F.transform("nbrs", lambda n: F.struct(key(n).alias("key"), n.alias("dst")))), 1, s)
    if in_numpy:
        ensure_importable(frontier.sparkSession)

    def found(rows: DataFrame, in_blocks: bool = False) -> DataFrame:
        met = adjacency.meet_blocks(asked) if in_blocks else adjacency.meet(asked, rows)
        if in_numpy:
            met = met.select("batch", "row_id", "src", "stem", "nbrs").mapInArrow(raced(s), f"{_of(met, 'batch', 'row_id', 'src')}, key array<long>, dst array<long>")
            return met.select("batch", "row_id", "src", F.posexplode(F.arrays_zip("key", "dst")).alias("at", "pick"))
        return met.select("batch", "row_id", "src", F.posexplode(picks).alias("at", "pick"))

    out = found(adjacency.rows).select("batch", "row_id", "src", F.col("pick.dst").alias("dst"), (F.col("at") + 1).cast("long").alias("rank"))
    if adjacency.blocks is None:
        return out
    best = Window.partitionBy("batch", "row_id").orderBy("pick.key", "pick.dst")
    hubs = found(adjacency.blocks, True).withColumn("rank", F.row_number().over(best).cast("long")).where(F.col("rank") <= s)
    return out.unionByName(hubs.select("batch", "row_id", "src", F.col("pick.dst").alias("dst"), "rank"))


def _of(df: DataFrame, *names: str) -> str:
    return ", ".join(f"{n} {dict(df.dtypes)[n]}" for n in names)


def raced(s: int):
    """For mapInArrow over (batch, row_id, src, stem, nbrs): each row's `s` smallest md5 draws with their neighbours, made for whole arrays at once."""

    def work(batches):
        import numpy as np
        import pyarrow as pa

        from sparseloom.functions.md5_races import draws, smallest

        for batch in batches:
            nbrs = batch.column("nbrs")
            lengths = np.diff(nbrs.offsets.to_numpy())
            ids = nbrs.flatten().to_numpy(zero_copy_only=False)
            keys = draws([x.encode() for x in batch.column("stem").to_pylist()], lengths, ids)
            at, counts = smallest(keys, lengths, s)
            ends = pa.array(np.concatenate([[0], np.cumsum(counts)]), pa.int32())
            lists = [pa.ListArray.from_arrays(ends, pa.array(x[at])) for x in (keys, ids)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("batch", "row_id", "src")), *lists], ["batch", "row_id", "src", "key", "dst"])

    return work


def positions(frontier: DataFrame, adjacency: Adjacency, s: int, seed: int, layer: int, rng: str = "md5") -> DataFrame:
    """Node-wise draws of positions in the adjacency row: `s` random numbers a row, however many neighbours it has.

    Of d neighbours, m = min(s, d) draws are made; draw t is below d - m + t + 1, and where it hits a position already
    taken, the last position of its range is taken instead. Every set of m neighbours is equally likely. The
    samples are others than those of `race`, which needs a random number for each neighbour. Of a row in blocks, only the blocks
    that hold a drawn position are read.
    """
    frontier = adjacency.dealt(frontier)
    met = frontier.join(adjacency.rows.select("src", "nbrs"), F.col("v") == F.col("src"))
    found = F.transform(_positions(F.size("nbrs").cast("long"), s, seed, layer, rng), lambda p: F.element_at("nbrs", (p + 1).cast("int")))
    out = met.select("batch", "row_id", "src", F.posexplode(found).alias("at", "dst"))
    out = out.select("batch", "row_id", "src", "dst", (F.col("at") + 1).cast("long").alias("rank"))
    if adjacency.blocks is None:
        return out
    asked = frontier.join(adjacency.hubs.select("src", "deg"), F.col("v") == F.col("src"))
    asked = asked.select("batch", "row_id", "src", F.posexplode(_positions(F.col("deg"), s, seed, layer, rng)).alias("at", "p"))
    asked = asked.withColumn("blk", F.floor(F.col("p") / adjacency.longest).cast("int"))
    hit = asked.join(adjacency.blocks.select("src", "blk", "cum_before", "nbrs"), ["src", "blk"])
    drawn = F.element_at("nbrs", (F.col("p") - F.col("cum_before") + 1).cast("int"))
    return out.unionByName(hit.select("batch", "row_id", "src", drawn.alias("dst"), (F.col("at") + 1).cast("long").alias("rank")))


def _positions(degree: Column, s: int, seed: int, layer: int, rng: str) -> Column:
    """Array of min(s, degree) distinct positions below the degree, in the order they were drawn."""
    free = degree - F.least(F.lit(s).cast("long"), degree)
    at = [F.col("batch"), layer, F.col("row_id")]
    draws = F.transform(F.sequence(free + 1, degree), lambda n: F.pmod(u52(seed, *at, n - free - 1, kind=rng), n))
    untaken = lambda taken, r: F.when(F.array_contains(taken, r), free + F.size(taken)).otherwise(r)
    return F.aggregate(draws, F.array().cast("array<long>"), lambda taken, r: F.concat(taken, F.array(untaken(taken, r).cast("long"))))

"""What bulk sampling is compared with: one batch at a time, whole neighbourhoods, a single process."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import durable, ensure_importable, shared_folder
from . import matrix
from .framework import SampleSpec, in_bulks, sample_minibatches


def per_batch_loop(edges: DataFrame | None, batches: DataFrame, spec: SampleSpec, count: int, adjacency: matrix.Adjacency | None = None, jobs: int | None = None) -> DataFrame:
    """The same samples by one job after the other, one batch each; the graph replicated as in the compared system.

    With `jobs`, at most so many: where there are more batches, a job takes several, and the number of jobs does not grow with the input.
    """
    one_by_one = replace(spec, strategy="replicated")
    if adjacency is None:
        adjacency = matrix.to_adjacency(edges)
    batches = durable(batches)
    together = 1 if jobs is None else max(1, -(-count // jobs))
    folder, parts = shared_folder(batches.sparkSession, "per-batch"), []
    for part in in_bulks(edges, batches, one_by_one, together, count, adjacency):
        parts.append(f"{folder}/{len(parts)}")
        part.write.parquet(parts[-1])
    return batches.sparkSession.read.parquet(*parts)


def full_neighborhood(edges: DataFrame | None, batches: DataFrame, hops: int, columns: DataFrame | None = None) -> DataFrame:
    """(batch, hop, vertices, edges): everything within reach, unsampled, repeats merged per batch.

    The graph's columns are dealt to blocks, and every batch's frontier meets every block: a block marks which of its own vertices
    are reached, so that no visited edge leaves its task, and only the frontiers move. `columns`: the graph at hand as (dst, srcs).
    """
    ensure_importable(batches.sparkSession)
    columns = matrix.to_cols(edges) if columns is None else columns
    blocks = max(LEAST_BLOCKS, int(batches.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 12)
    graph = columns.select(F.pmod(F.hash("dst"), F.lit(blocks)).alias("blk"), F.col("dst").cast("long").alias("dst"), F.col("srcs").cast("array<long>").alias("srcs"))
    front = batches.where("v IS NOT NULL").groupBy("batch").agg(F.collect_set(F.col("v").cast("long")).alias("vs")).mapInArrow(_packed, "batch long, held binary")
    out = None
    for h in range(1, hops + 1):
        sent = front.withColumn("blk", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
        met = graph.groupBy("blk").cogroup(sent.select("blk", "batch", "held").groupBy("blk")).applyInArrow(_reached(h < hops), "batch long, vertices long, edges long, held binary")
        part = met.groupBy("batch").agg(F.sum("vertices").alias("vertices"), F.sum("edges").alias("edges")).withColumn("hop", F.lit(h).cast("long"))
        out = part if out is None else out.unionByName(part)
        front = met.select("batch", "held")
    return out


#: Blocks of the graph's columns at least.
LEAST_BLOCKS = 8


def _pack(vs) -> bytes:
    """Ascending ids as their first one and the gaps, in as few bytes as the largest gap needs."""
    import numpy as np

    gaps = np.diff(vs)
    width = next((w for w in (1, 2, 4) if not len(gaps) or gaps.max() < 1 << 8 * w), 8)
    return bytes([width]) + np.int64(vs[0]).tobytes() + gaps.astype(f"<u{width}").tobytes()


def _unpack(held: bytes):
    import numpy as np

    gaps = np.frombuffer(held, f"<u{held[0]}", offset=9)
    out = np.empty(len(gaps) + 1, np.int64)
    out[0] = np.frombuffer(held, "<i8", 1, 1)[0]
    out[1:] = gaps
    return np.cumsum(out)


def _packed(frames):
    import numpy as np
    import pyarrow as pa

    for frame in frames:
        held = [_pack(np.sort(np.array(vs, np.int64))) for vs in frame.column("vs").to_pylist()]
        yield pa.RecordBatch.from_arrays([frame.column("batch"), pa.array(held, pa.binary())], ["batch", "held"])


def _reached(onward: bool):
    """For one block of columns and all frontiers: per batch, how many of the block's vertices are reached, by how many edges; and which, if they go on."""

    def work(graph, fronts):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        if not len(graph) or not len(fronts):
            return pa.table({"batch": pa.array([], pa.int64()), "vertices": pa.array([], pa.int64()), "edges": pa.array([], pa.int64()), "held": pa.array([], pa.binary())})
        dst, srcs = graph.column("dst").to_numpy(), graph.column("srcs")
        lengths = np.concatenate([c.value_lengths().to_numpy() for c in srcs.chunks])
        ends = [pc.min_max(c.flatten()) for c in srcs.chunks if len(c.flatten())]
        low = min(x["min"].as_py() for x in ends)
        span = max(x["max"].as_py() for x in ends) - low + 1
        ids = None
        if span <= 8 * int(lengths.sum()) + 1024 and span < 1 << 31:  # ids lie close: their distance is their number
            at_src = np.concatenate([(c.flatten().to_numpy() - low).astype(np.int32) for c in srcs.chunks])
        else:
            ids, at_src = np.unique(np.concatenate([c.flatten().to_numpy() for c in srcs.chunks]), return_inverse=True)
            span = len(ids)
        many = np.bincount(at_src, minlength=span)
        starts = np.concatenate([[0], np.cumsum(many)[:-1]])
        # the block's entries by source, a stretch of sources at a time: sorting all at once would take several times their memory
        owner, to, done = np.repeat(np.arange(len(dst), dtype=np.int32), lengths), np.empty(len(at_src), np.int32), 0
        edges_of = np.linspace(0, span, STRETCHES + 1).astype(np.int64)
        for first, last in zip(edges_of[:-1], edges_of[1:]):
            some = np.flatnonzero((at_src >= first) & (at_src < last))
            to[done : done + len(some)] = owner[some[np.argsort(at_src[some], kind="stable")]]
            done += len(some)
        del owner, at_src
        numbers = fronts.column("batch").to_numpy()
        held, turn, found = fronts.column("held"), np.argsort(numbers, kind="stable"), []
        cuts = np.flatnonzero(np.diff(numbers[turn])) + 1
        for own in np.split(turn, cuts):
            v = np.concatenate([_unpack(held[int(k)].as_py()) for k in own])
            if ids is None:
                at = v[(v >= low) & (v < low + span)] - low
            else:
                at = np.minimum(np.searchsorted(ids, v), len(ids) - 1)
                at = at[ids[at] == v]
            at = at[many[at] > 0]
            if not len(at):
                continue
            n = many[at]
            ends = np.cumsum(n)
            seen = np.zeros(len(dst), bool)
            for a in range(0, len(at), TOGETHER):  # in pieces: a frontier of hubs visits more edges than memory holds
                b = min(a + TOGETHER, len(at))
                base = ends[a - 1] if a else 0
                seen[to[np.repeat(starts[at[a:b]] - (ends[a:b] - n[a:b] - base), n[a:b]) + np.arange(ends[b - 1] - base)]] = True
            found.append((int(numbers[own[0]]), int(np.count_nonzero(seen)), int(ends[-1]), _pack(np.sort(dst[seen])) if onward else None))
        columns = list(zip(*found)) or [[]] * 4
        return pa.table({k: pa.array(x, kind) for k, x, kind in zip(("batch", "vertices", "edges", "held"), columns, (pa.int64(), pa.int64(), pa.int64(), pa.binary()))})

    return work


#: Stretches in which a block's entries are sorted.
STRETCHES = 8
#: Vertices of a frontier whose rows are looked up at once.
TOGETHER = 4096


def serial_run(edges: DataFrame, batches: DataFrame, spec: SampleSpec) -> DataFrame:
    """The same samples from a single partition."""
    return sample_minibatches(edges.coalesce(1), batches.coalesce(1), spec)

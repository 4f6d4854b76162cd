"""Choosing strategy, replication and bulk size from sizes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.grid import Grid
from ..sources.tables import BROADCAST_BYTES
from .cost import best_c


@dataclass(frozen=True)
class Choice:
    strategy: str
    grid: Grid
    k: int


def bulk_bytes(k: int, b: int, fanout: tuple[int, ...], bytes_per_edge: int = 40) -> int:
    """Sampled edges of k batches, all layers, no merging of repeats."""
    rows, total = k * b, 0
    for s in fanout:
        rows *= s
        total += rows
    return total * bytes_per_edge


def choose(
    edges: int, vertices: int, feature_width: int, batches: int, b: int, fanout: tuple[int, ...], p: int, memory: int,
    bucketed: bool = False, broadcast_bytes: int = BROADCAST_BYTES,
) -> Choice:
    """Largest replication whose copies fit, then the largest k; the graph is replicated only if its size allows."""
    topology, features = 16 * edges, 4 * vertices * feature_width
    strategy = "replicated" if topology <= min(broadcast_bytes, memory // 4) else "bucketed" if bucketed else "grid"
    per_process = memory - (topology if strategy == "replicated" else 0)
    copies = max(1, int(p * per_process * 0.5 // max(1, features + (0 if strategy == "replicated" else topology))))
    c = best_c(p, copies)
    k = batches
    while k > 1 and bulk_bytes(k, b, fanout) > p * per_process * 0.4:
        k = -(-k // 2)
    return Choice(strategy, Grid(p, c), k)


def plan_epoch(edges: DataFrame, features: DataFrame, batches: int, b: int, fanout: tuple[int | None, ...], p: int, memory: int, bucketed: bool = False) -> Choice:
    """`choose` with the sizes counted; a hop that takes every neighbour counts with the mean degree."""
    n_edges, sources = edges.agg(F.count(F.lit(1)), F.approx_count_distinct("src")).first()
    n, width = features.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    degree = -(-n_edges // max(1, sources))
    return choose(n_edges, n, width or 0, batches, b, tuple(degree if s is None else s for s in fanout), p, memory, bucketed)

"""Feature fetch: the vectors of every vertex that a batch's sampled edges name."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import BROADCAST_BYTES, durable
from .grid import Grid


def needed_vertices(sampled: DataFrame, roots: DataFrame | None = None) -> DataFrame:
    """Distinct (batch, v): both ends of every sampled edge, and the batch's own vertices."""
    ids = sampled.select("batch", F.explode(F.array("src", "dst")).alias("v"))  # in one pass: the last hop is not drawn twice
    if roots is not None:
        ids = ids.union(roots.select("batch", "v"))
    return ids.distinct()


def fetch_features(sampled: DataFrame, features: DataFrame, roots: DataFrame | None = None, grid: Grid | None = None) -> DataFrame:
    """(batch, v, vec). With a grid, also whether the owner is another block row."""
    got = needed_vertices(sampled, roots).join(features.select("v", "vec"), "v")
    if grid is None:
        return got.select("batch", "v", "vec")
    remote = F.pmod("v", F.lit(grid.rows)) != F.pmod("batch", F.lit(grid.rows))
    return got.select("batch", "v", "vec", remote.alias("remote"))


def hot_vertices(edges: DataFrame, fraction: float, most: int = 1_000_000) -> DataFrame:
    """The most pulled-from vertices: a fraction of all, and never more than `most`."""
    deg = edges.groupBy(F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("deg"))
    n = min(most, max(1, int(deg.count() * fraction)))
    return deg.orderBy(F.desc("deg"), "v").limit(n).select("v")


def fetch_features_cached(sampled: DataFrame, features: DataFrame, edges: DataFrame, fraction: float = 0.2, roots: DataFrame | None = None, limit: int = BROADCAST_BYTES) -> DataFrame:
    """The same rows in two tiers: hot vectors by broadcast, the others by shuffle; `near` says which.

    As many hot vertices as `fraction` says, or as their vectors leave room for below `limit` bytes.
    """
    ids = needed_vertices(sampled, roots).where("v IS NOT NULL")
    width = features.agg(F.max(F.size("vec"))).first()[0] or 1
    hot = durable(features.select("v", "vec").join(F.broadcast(hot_vertices(edges, fraction, limit // (16 * width + 32))), "v"))
    near = ids.join(F.broadcast(hot), "v").select("batch", "v", "vec", F.lit(True).alias("near"))
    # not an anti join: that would be pushed below the ids' exchange, and the samples drawn again for this tier
    missed = ids.join(F.broadcast(hot.select("v", F.lit(True).alias("hit"))), "v", "left").where("hit IS NULL")
    cold = missed.join(features.select("v", "vec"), "v")
    return near.unionByName(cold.select("batch", "v", "vec", F.lit(False).alias("near")))


def feature_words(sampled: DataFrame, grid: Grid, width: int) -> DataFrame:
    """Remote feature words per batch: distinct needed vertices whose owner is another block row."""
    ids = sampled.select("batch", F.col("src").alias("v")).union(sampled.select("batch", "dst")).distinct()
    remote = F.pmod("v", F.lit(grid.rows)) != F.pmod("batch", F.lit(grid.rows))
    return ids.groupBy("batch").agg(F.count(F.lit(1)).alias("vertices"), (F.sum(remote.cast("long")) * width).alias("remote_words"))


def mean_features(sampled: DataFrame, features: DataFrame) -> DataFrame:
    """(batch, row_id, src, vec): mean vector of each row's drawn neighbours, all inside the JVM."""
    spread = sampled.join(features.select(F.col("v").alias("dst"), "vec"), "dst").select("batch", "row_id", "src", F.posexplode("vec").alias("i", "x"))
    cells = spread.groupBy("batch", "row_id", "src", "i").agg(F.avg(F.col("x").cast("double")).alias("x"))
    return cells.groupBy("batch", "row_id", "src").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda c: c["x"]).alias("vec"))

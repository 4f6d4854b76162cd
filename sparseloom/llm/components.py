"""Connected components of a link relation, without collecting it anywhere.

Rounds of two grouped steps pull every vertex toward the smallest one it can reach: first each
vertex hands its smallest neighbour to its larger neighbours, then to all its smaller ones
and itself. Links shrink to stars around the smallest vertex of each component. Every round is
cut with a checkpoint, so lost executors cost one round at most. Minima are partial
aggregates, and links of a vertex with very many of them meet its minimum where they lie (`look_up`), so no
vertex needs a task of its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, look_up


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) links, in any order and with repeats, to (vertex, root) for every linked vertex.

    Vertices are longs or strings; `root` is the smallest of the component. Links with a null end
    and loops are passed over. No links give no rows.
    """
    pairs = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    pairs = durable(pairs.where("a IS NOT NULL AND b IS NOT NULL AND a <> b").distinct())
    state = _state(pairs)
    for _ in range(max_rounds):
        if state[0] == 0:
            break
        moved = durable(_to_larger(pairs, state[0]))
        pairs = durable(_to_smaller(moved, state[0]))
        new = _state(pairs)
        if new == state:
            break
        state = new
    else:
        raise RuntimeError(f"components did not settle within {max_rounds} rounds")
    return pairs.select(F.col("a").alias("vertex"), F.col("b").alias("root")).union(
        pairs.select(F.col("b").alias("vertex"), F.col("b").alias("root")).distinct()
    )


def _state(pairs: DataFrame) -> tuple:
    """Number of links and an order-free digest of them; equal when nothing moved."""
    digest = F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))
    return tuple(pairs.agg(F.count(F.lit(1)), digest).first())


def _to_larger(pairs: DataFrame, total: int) -> DataFrame:
    """Each vertex links its larger neighbours to the smallest of its neighbours and itself."""
    both = pairs.select("a", "b").union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy(F.col("a").alias("b")).agg(F.least(F.min("b"), F.col("a")).alias("m"), F.count(F.lit(1)).alias("n"))
    # the larger end of a link hears from the smaller end
    moved = look_up(pairs.select("a", "b"), "b", least, "n", total)
    return moved.select("a", F.col("m").alias("b")).where("a <> b").distinct()


def _to_smaller(pairs: DataFrame, total: int) -> DataFrame:
    """Each vertex links its smaller neighbours, and itself, to the smallest of them."""
    least = pairs.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n"))
    moved = look_up(pairs.select("a", "b"), "a", least, "n", total)
    return moved.select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()

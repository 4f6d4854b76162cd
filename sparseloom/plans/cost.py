"""Latency-bandwidth cost model of the grid product, and measures of runs."""

from __future__ import annotations

from dataclasses import dataclass
from math import log2, sqrt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.features import feature_words  # noqa: F401
from ..operators.grid import Grid


@dataclass(frozen=True)
class CostModel:
    """alpha: seconds per message; beta: seconds per word."""

    alpha: float = 1.0
    beta: float = 1.0

    def msg_time(self, words: float) -> float:
        return self.alpha + self.beta * words

    def gather_words(self, grid: Grid, k: int, b: int) -> float:
        return k * b / grid.c

    def row_words(self, grid: Grid, k: int, b: int, d: float) -> float:
        return k * b * d / grid.c

    def reduce_words(self, grid: Grid, k: int, b: int, d: float) -> float:
        return grid.c * k * b * d / grid.p

    def t_rowdata(self, grid: Grid, k: int, b: int, d: float) -> float:
        return self.alpha * log2(max(1.0, grid.p / grid.c**2)) + self.beta * self.row_words(grid, k, b, d)

    def t_allreduce(self, grid: Grid, k: int, b: int, d: float) -> float:
        return self.alpha * log2(grid.c) + self.beta * self.reduce_words(grid, k, b, d)

    def t_prob(self, grid: Grid, k: int, b: int, d: float) -> float:
        latency = self.alpha * (grid.p / grid.c**2 + log2(grid.c))
        return latency + self.beta * (self.row_words(grid, k, b, d) + self.reduce_words(grid, k, b, d))


def scaling(p: int, c: float) -> float:
    """Bandwidth factor of the model: 1/c + c/p."""
    return 1 / c + c / p


def best_c(p: int, most: int | None = None) -> int:
    """The replication that a grid of p allows with the least bandwidth; at most `most` copies fit in memory."""
    allowed = [c for c in range(1, int(sqrt(p)) + 1) if p % (c * c) == 0 and (most is None or c <= most)]
    return min(allowed, key=lambda c: scaling(p, c))


def best_c_of(p: Column) -> Column:
    """The same for a column of process counts."""
    allowed = F.filter(F.sequence(F.lit(1).cast("long"), F.floor(F.sqrt(p)).cast("long")), lambda c: p % (c * c) == 0)
    return F.array_min(F.transform(allowed, lambda c: F.struct((F.lit(1.0) / c + c / p).alias("factor"), c.alias("c"))))["c"]


def speedup(baseline: float, ours: float) -> float:
    return baseline / ours


def parallel_efficiency(t0: float, p0: int, t: float, p: int) -> float:
    return t0 * p0 / (t * p)


def scaling_table(times: dict[int, float]) -> list[tuple[int, float, float, float]]:
    """(p, seconds, speed-up, efficiency) against the smallest p."""
    p0 = min(times)
    return [(p, t, times[p0] / t, parallel_efficiency(times[p0], p0, t, p)) for p, t in sorted(times.items())]


def graph_stats(edges: DataFrame) -> DataFrame:
    """Sources, edges, mean and largest degree."""
    deg = edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    return deg.agg(F.count(F.lit(1)).alias("sources"), F.sum("deg").alias("edges"), F.avg("deg").alias("mean_degree"), F.max("deg").alias("max_degree"))


def shape_report(sampled: DataFrame) -> DataFrame:
    """Rows, entries and distinct columns per layer."""
    return sampled.groupBy("layer").agg(
        F.countDistinct("batch", "row_id", "src").alias("rows"), F.count(F.lit(1)).alias("entries"), F.countDistinct("batch", "dst").alias("columns")
    )


def inclusion_error(drawn: DataFrame, expected: DataFrame) -> DataFrame:
    """Total variation and chi square of counted draws (col, drawn) against the shares that they should have (col, share)."""
    total = drawn.agg(F.sum("drawn")).first()[0] or 0
    both = expected.join(drawn, "col", "full").select(F.coalesce("drawn", F.lit(0)).alias("drawn"), F.coalesce("share", F.lit(0.0)).alias("share"))
    gap = F.col("drawn") / F.lit(float(max(1, total))) - F.col("share")
    chi = F.when(F.col("share") > 0, gap * gap / F.col("share") * total)
    return both.agg((F.sum(F.abs(gap)) / 2).alias("variation"), F.sum(chi).alias("chi_square"))


def accuracy(predicted: DataFrame) -> DataFrame:
    """Share of labelled rows (label, predicted) that are right."""
    return predicted.where("label IS NOT NULL").agg(F.avg((F.col("label") == F.col("predicted")).cast("double")).alias("accuracy"))

"""Drawing distinct columns from the rows of a weight matrix, all rows at once.

Input: (batch, row_id, col, w) with integer weights; output: (batch, row_id, col, rank), at most `s` per
row. Integer weights keep prefix sums and draws exact in every engine. `race` takes one pass;
`its` finds draws in prefix sums, in rounds, until each row has its columns; both follow the same law.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import h52, u01, u52
from ..sources.tables import durable, ensure_importable

KEYS = ["batch", "row_id"]
#: Added to the seed where rows still short after their draws are completed.
COMPLETING = 1_000_003


def prefix_sum(prob: DataFrame) -> DataFrame:
    """Adds hi (sum of weights up to the column, in column order) and total."""
    row = Window.partitionBy(*KEYS)
    upto = row.orderBy("col").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return prob.withColumns({"hi": F.sum("w").over(upto), "total": F.sum("w").over(row)})


def _draws(rows: DataFrame, first, count, seed: int, layer: int) -> DataFrame:
    """Draw counters `first` .. `first+count-1` of each row (columns total, first, count)."""
    spread = rows.withColumn("t", F.explode(F.sequence(first, first + count - 1)))
    return spread.withColumn("r", F.pmod(u52(seed, F.col("batch"), layer, F.col("row_id"), F.col("t")), F.col("total")))


def _hits(prefixed: DataFrame, draws: DataFrame) -> DataFrame:
    """The column whose share of the prefix sums holds each draw: a range inside an equal key."""
    d = draws.select(*KEYS, "t", "r")
    return prefixed.join(d, KEYS).where("r >= hi - w AND r < hi").select(*KEYS, "t", "col")


def its_single(prob: DataFrame, seed: int, layer: int) -> DataFrame:
    """One draw per row."""
    prefixed = prefix_sum(prob)
    rows = prefixed.select(*KEYS, "total").distinct()
    return _hits(prefixed, _draws(rows, F.lit(0), F.lit(1), seed, layer)).select(*KEYS, "col")


def completed(met: DataFrame, s: int, seed: int, layer: int) -> DataFrame:
    """`s` columns a row, or all: first those drawn, by `t`; in rows still short, then those not drawn (null `t`).

    The latter follow by a race on their weights: the law of drawing on until there are `s` distinct columns.
    """
    hit = F.count("t").over(Window.partitionBy(*KEYS))
    open_rows = met.where("w > 0").withColumn("hit", hit).where(F.col("t").isNotNull() | (F.col("hit") < s))
    arrival = -F.log(u01(seed + COMPLETING, F.col("batch"), layer, F.col("row_id"), F.col("col"))) / F.col("w")
    keyed = open_rows.withColumn("key", F.when(F.col("t").isNull(), arrival))
    best = Window.partitionBy(*KEYS).orderBy(F.asc_nulls_last("t"), "key", "col")
    return keyed.withColumn("rank", F.row_number().over(best).cast("long")).where(F.col("rank") <= s).select(*KEYS, "col", "rank", "t")


def its_fixed(prob: DataFrame, s: int, seed: int, layer: int, draws: int, complete: bool = True) -> DataFrame:
    """`draws` draws per row in one pass; the first `s` distinct columns in order of their first hit.

    Rows still short are completed, unless `complete` is off: then the draws made are all there are.
    """
    prefixed = prefix_sum(prob)
    rows = prefixed.select(*KEYS, "total").distinct()
    draws_ = _draws(rows, F.lit(0), F.lit(draws), seed, layer)
    if not complete:
        return _ranked(_hits(prefixed, draws_).groupBy(*KEYS, "col").agg(F.min("t").alias("t")), ["t"], s)
    d = draws_.select(F.col("batch").alias("b"), F.col("row_id").alias("i"), "t", "r")
    met = prefixed.join(d, F.expr("batch = b AND row_id = i AND r >= hi - w AND r < hi"), "left")
    return completed(met.groupBy(*KEYS, "col", "w").agg(F.min("t").alias("t")), s, seed, layer).drop("t")


def with_replacement(prob: DataFrame, s: int, seed: int, layer: int) -> DataFrame:
    """`s` draws per row, repeats kept."""
    prefixed = prefix_sum(prob)
    rows = prefixed.select(*KEYS, "total").distinct()
    return _hits(prefixed, _draws(rows, F.lit(0), F.lit(s), seed, layer)).select(*KEYS, "col", (F.col("t") + 1).cast("long").alias("rank"))


def _ranked(rows: DataFrame, order: list[str], s: int) -> DataFrame:
    best = Window.partitionBy(*KEYS).orderBy(*order, "col")
    return rows.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= s).select(*KEYS, "col", F.col("rank").cast("long").alias("rank"))


def race(prob: DataFrame, s: int, seed: int, layer: int, unit: bool = False, rng: str = "md5") -> DataFrame:
    """One pass: exponential arrival times at rate w, the `s` earliest. Unit weights compare plain integers."""
    at = [F.col("batch"), layer, F.col("row_id"), F.col("col")]
    key = (h52(seed, *at) if rng == "md5" else u52(seed, *at, kind=rng)) if unit else -F.log(u01(seed, *at, kind=rng)) / F.col("w")
    return _ranked(prob.withColumn("key", key), ["key"], s)


def its_rounds(prob: DataFrame, s: int, seed: int, layer: int, overdraw: int = 4) -> DataFrame:
    """Draws in rounds: rows still short draw again from what is left of their weights.

    Rows with no more columns than they need take all and leave. A round takes at least one column of
    each row, so there are at most `s` rounds; with the default overdraw one or two are usual.
    """
    sizes = Window.partitionBy(*KEYS)
    left = prob.select(*KEYS, "col", "w").withColumns({"n": F.count(F.lit(1)).over(sizes)})
    everything = left.where(F.col("n") <= s)
    done = everything.withColumn("rank", F.row_number().over(sizes.orderBy("col")).cast("long")).select(*KEYS, "col", "rank")
    left = durable(left.where(F.col("n") > s).select(*KEYS, "col", "w").withColumns({"missing": F.lit(s).cast("long"), "drawn": F.lit(0).cast("long")}))
    for _ in range(s):
        if left.isEmpty():
            break
        prefixed = prefix_sum(left)
        rows = prefixed.select(*KEYS, "total", "missing", "drawn").distinct()
        draws = _draws(rows, F.col("drawn"), F.col("missing") * overdraw, seed, layer)
        first = _hits(prefixed, draws).groupBy(*KEYS, "col").agg(F.min("t").alias("t"))
        order = Window.partitionBy(*KEYS).orderBy("t")
        taken = first.withColumn("at", F.row_number().over(order)).join(rows.select(*KEYS, "missing"), KEYS).where("at <= missing")
        taken = durable(taken.select(*KEYS, "col", (F.col("at") + s - F.col("missing")).cast("long").alias("rank")))
        done = done.unionByName(taken)
        got = taken.groupBy(*KEYS).agg(F.count(F.lit(1)).alias("got"))
        left = left.join(got, KEYS).withColumns({"drawn": F.col("drawn") + F.col("missing") * overdraw, "missing": F.col("missing") - F.col("got")})
        left = durable(left.where("missing > 0").drop("got").join(taken.select(*KEYS, "col"), [*KEYS, "col"], "left_anti"))
    return done


def rejection(prob: DataFrame, s: int, seed: int, layer: int, tries: int) -> DataFrame:
    """Uniform proposals, each kept with probability w / max(w); first `s` distinct, with the number of tries each took.

    Rows still short after `tries` are completed without proposals; those picks have null tries.
    """
    row = Window.partitionBy(*KEYS)
    numbered = prob.withColumns({"at": (F.row_number().over(row.orderBy("col")) - 1).cast("long"), "n": F.count(F.lit(1)).over(row), "top": F.max("w").over(row)})
    rows = numbered.select(*KEYS, "n", "top").distinct().withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(tries - 1))))
    proposed = rows.withColumns({
        "at": F.pmod(u52(seed, F.col("batch"), layer, F.col("row_id"), F.col("t")), F.col("n")),
        "r": F.pmod(u52(seed + 1, F.col("batch"), layer, F.col("row_id"), F.col("t")), F.col("top")),
    })
    d = proposed.select(F.col("batch").alias("b"), F.col("row_id").alias("i"), F.col("at").alias("a"), "t", "r")
    met = numbered.join(d, F.expr("batch = b AND row_id = i AND at = a AND r < w"), "left")
    picked = completed(met.groupBy(*KEYS, "col", "w").agg(F.min("t").alias("t")), s, seed, layer)
    return picked.select(*KEYS, "col", "rank", (F.col("t") + 1).cast("long").alias("tries"))


def its_arrow(rows: DataFrame, s: int, seed: int, layer: int, draws: int) -> DataFrame:
    """The same draws as `its_fixed` on array rows (batch, row_id, cols, ws): a numpy kernel per row."""
    import pyarrow as pa

    ensure_importable(rows.sparkSession)

    def work(batches):
        import hashlib

        import numpy as np

        for batch in batches:
            out = []
            for b, r, cols, ws in zip(*(c.to_pylist() for c in batch.columns)):
                order = np.argsort(cols, kind="stable")
                hi = np.cumsum(np.asarray(ws, np.int64)[order])
                picks = [int(hashlib.md5(f"{seed}|{b}|{layer}|{r}|{t}".encode()).hexdigest()[:13], 16) % int(hi[-1]) for t in range(draws)]
                found = np.asarray(cols, np.int64)[order][np.searchsorted(hi, picks, side="right")]
                chosen = list(dict.fromkeys(found.tolist()))[:s]
                if len(chosen) < s:  # complete short rows as `completed` does
                    left = {c: w for c, w in zip(cols, ws) if w > 0}
                    for c in chosen:
                        del left[c]
                    u = {c: (int(hashlib.md5(f"{seed + COMPLETING}|{b}|{layer}|{r}|{c}".encode()).hexdigest()[:13], 16) + 0.5) / 4503599627370496.0 for c in left}
                    chosen += sorted(left, key=lambda c: (-np.log(u[c]) / left[c], c))[: s - len(chosen)]
                out += [(b, r, c, i + 1) for i, c in enumerate(chosen)]
            columns = zip(*out) if out else [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in columns], ["batch", "row_id", "col", "rank"])

    return rows.select("batch", "row_id", "cols", "ws").mapInArrow(work, "batch long, row_id long, col long, rank long")


def two_level(frontier: DataFrame, blocks: DataFrame, s: int, seed: int, layer: int) -> DataFrame:
    """Uniform picks from hub rows stored in blocks: positions first, then the blocks that hold them.

    `frontier`: batch, row_id, v, deg. A pick is a position below deg; only the block that holds it is read,
    so no task ever holds a whole hub row. Distinct picks come from `4*s` draws, first hits first; rows of few
    neighbours that are still short take the rest from the positions left.
    """
    picks = frontier.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(4 * s - 1))))
    picks = picks.withColumn("at", F.pmod(u52(seed, F.col("batch"), layer, F.col("row_id"), F.col("t")), F.col("deg")))
    first = picks.groupBy("batch", "row_id", "v", "at").agg(F.min("t").alias("t"))
    best = Window.partitionBy(*KEYS).orderBy("t")
    kept = first.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= s).select(*KEYS, "v", "at", F.col("rank").cast("long").alias("rank"))
    got = kept.groupBy(*KEYS).agg(F.count(F.lit(1)).alias("got"))
    short = frontier.select(*KEYS, "v", "deg").join(got, KEYS).where(F.col("got") < F.least(F.col("deg"), F.lit(s)))
    left = short.withColumn("at", F.explode(F.sequence(F.lit(0).cast("long"), F.col("deg").cast("long") - 1))).join(kept.select(*KEYS, "at"), [*KEYS, "at"], "left_anti")
    more = left.withColumn("key", u52(seed + COMPLETING, F.col("batch"), layer, F.col("row_id"), F.col("at")))
    more = more.withColumn("rank", F.col("got") + F.row_number().over(Window.partitionBy(*KEYS).orderBy("key", "at")))
    kept = kept.unionByName(more.where(F.col("rank") <= s).select(*KEYS, "v", "at", "rank"))
    spans = blocks.select(F.col("src").alias("v"), "cum_before", (F.col("cum_before") + F.size("nbrs")).alias("cum_after"), "nbrs")
    found = kept.join(spans, "v").where("at >= cum_before AND at < cum_after")
    return found.select("batch", "row_id", F.element_at("nbrs", (F.col("at") - F.col("cum_before") + 1).cast("int")).alias("col"), F.col("rank").cast("long").alias("rank"))


def sample_rows(prob: DataFrame, s: int, seed: int, layer: int, method: str = "race", **options) -> DataFrame:
    """At most `s` distinct columns per row, by the method named."""
    methods = {
        "race": race, "race_uniform": lambda *a, **o: race(*a, unit=True, **o), "its": its_rounds, "its_fixed": its_fixed,
        "rejection": rejection, "with_replacement": with_replacement,
    }
    return methods[method](prob, s, seed, layer, **options)

"""Sparse matrices as COO relations (row, col, val), optionally keyed by batch."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import durable


def spgemm(a: DataFrame, b: DataFrame, keys: Sequence[str] = (), left=("row", "col"), right=("row", "col")) -> DataFrame:
    """Product of two sparse matrices; `keys` are columns of `a` (such as batch) that stay apart."""
    x = a.select(*keys, F.col(left[0]).alias("row"), F.col(left[1]).alias("k"), F.col("val").alias("va"))
    y = b.select(F.col(right[0]).alias("k"), F.col(right[1]).alias("col"), F.col("val").alias("vb"))
    return x.join(y, "k").groupBy(*keys, "row", "col").agg(F.sum(F.col("va") * F.col("vb")).alias("val"))


def spmm(a: DataFrame, h: DataFrame, agg: str = "mean", keys: Sequence[str] = ()) -> DataFrame:
    """Sparse times dense: per row, the mean, sum or max of the vectors (v, vec) that it names."""
    f = {"mean": F.avg, "sum": F.sum, "max": F.max}[agg]
    spread = a.join(h.select(F.col("v").alias("col"), "vec"), "col").select(*keys, "row", F.posexplode("vec").alias("i", "x"))
    cells = spread.groupBy(*keys, "row", "i").agg(f(F.col("x").cast("double")).alias("x"))
    return cells.groupBy(*keys, "row").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda c: c["x"]).alias("vec"))


def vstack(matrices: Sequence[DataFrame], key: str = "batch") -> DataFrame:
    """Matrices one below the other: the key column says whose rows they are."""
    out = None
    for i, m in enumerate(matrices):
        tagged = m.withColumn(key, F.lit(i).cast("long"))
        out = tagged if out is None else out.unionByName(tagged)
    return out


def block_diag(stacked: DataFrame, key: str = "batch", height: int | None = None, width: int | None = None) -> DataFrame:
    """Blocks on a diagonal. With sizes the key turns into offsets; without, it stays a key, which is the same."""
    if height is None or width is None:
        return stacked
    return stacked.select((F.col("row") + F.col(key) * height).alias("row"), (F.col("col") + F.col(key) * width).alias("col"), "val")


def row_selector(vs: DataFrame, keys: Sequence[str] = ("batch",)) -> DataFrame:
    """One row per vertex to pick (pos, v), its one in the vertex's column."""
    return vs.select(*keys, F.col("pos").cast("long").alias("row"), F.col("v").alias("col"), F.lit(1).cast("long").alias("val"))


def col_selector(vs: DataFrame, keys: Sequence[str] = ("batch",)) -> DataFrame:
    """One column per vertex to pick, its one in the vertex's row."""
    return vs.select(*keys, F.col("v").alias("row"), F.col("pos").cast("long").alias("col"), F.lit(1).cast("long").alias("val"))


def expand_rows(q: DataFrame, key: str = "batch") -> DataFrame:
    """A row with many ones to many rows with a single one, in column order."""
    order = Window.partitionBy(key).orderBy("col")
    return q.select(key, (F.row_number().over(order) - 1).cast("long").alias("row"), "col", "val")


def normalize_rows(m: DataFrame, power: int = 1, keys: Sequence[str] = ("row",)) -> DataFrame:
    """Adds p: each entry's power as a share of its row's sum."""
    w = F.pow(F.col("val"), F.lit(power)) if power != 1 else F.col("val").cast("double")
    return m.withColumn("p", w / F.sum(w).over(Window.partitionBy(*keys)))


def power(m: DataFrame, exponent: int = 2) -> DataFrame:
    return m.withColumn("val", F.pow("val", F.lit(exponent)).cast("long"))


def compact(m: DataFrame, keys: Sequence[str] = ("batch",), col: str = "col", out: str = "local_col") -> DataFrame:
    """Renumber the columns that occur, per key, in column order. Ids come from the distinct columns only."""
    ids = m.select(*keys, col).distinct()
    ids = ids.withColumn(out, (F.row_number().over(Window.partitionBy(*keys).orderBy(col)) - 1).cast("long"))
    return m.join(ids, [*keys, col])


def transpose(m: DataFrame) -> DataFrame:
    return m.withColumnsRenamed({"row": "col", "col": "row"})


def identity(vs: DataFrame) -> DataFrame:
    return vs.select(F.col("v").alias("row"), F.col("v").alias("col"), F.lit(1).cast("long").alias("val"))


def to_rows(edges: DataFrame) -> DataFrame:
    """src, deg, nbrs (ascending): one row per nonempty matrix row."""
    return edges.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).select("src", F.size("nbrs").cast("long").alias("deg"), "nbrs")


def to_cols(edges: DataFrame) -> DataFrame:
    """dst, deg, srcs (ascending): one row per nonempty matrix column."""
    return edges.groupBy("dst").agg(F.array_sort(F.collect_list("src")).alias("srcs")).select("dst", F.size("srcs").cast("long").alias("deg"), "srcs")


def to_coo(rows: DataFrame) -> DataFrame:
    return rows.select("src", F.explode("nbrs").alias("dst"), F.lit(1).cast("long").alias("val"))


def to_blocks(edges: DataFrame, block: int = 1024) -> DataFrame:
    """Adjacency with hub rows cut into blocks of at most `block` neighbours: src, blk, cum_before, nbrs."""
    order = Window.partitionBy("src").orderBy("dst")
    numbered = edges.select("src", "dst", (F.row_number().over(order) - 1).alias("at"))
    cut = numbered.withColumn("blk", F.floor(F.col("at") / block).cast("int"))
    return cut.groupBy("src", "blk").agg(F.min("at").cast("long").alias("cum_before"), F.array_sort(F.collect_list("dst")).alias("nbrs"))


#: Neighbours in one array at most; rows with more are kept in blocks of so many.
LONGEST_ROW = 1 << 16


@dataclass(frozen=True)
class Adjacency:
    """A graph at rest in rows.

    `rows`: src, deg, nbrs, of all sources with up to `longest` neighbours; `hubs`: src, deg of the others, and `blocks`: their
    src, blk, cum_before, nbrs. Without hubs these are None. `spread`: tasks that a frontier is dealt to: its rows are few and small,
    but each stands for many draws, so that sizes in bytes say little about the work. None where the rows lie in buckets and say so themselves.
    """

    rows: DataFrame
    hubs: DataFrame | None = None
    blocks: DataFrame | None = None
    longest: int = LONGEST_ROW
    spread: int | None = None
    by: tuple[str, ...] = ("v",)
    #: The rows hold `asked_by`, the block rows of a grid that they are sent to; the frontier then has its own, `i`.
    asked: bool = False

    def replicated(self) -> Adjacency:
        """With the rows sent to every task; blocks stay where they are. The frontier is split by its own rows."""
        return replace(self, rows=F.broadcast(self.rows), by=("batch", "row_id"))

    def dealt(self, frontier: DataFrame) -> DataFrame:
        return frontier if self.spread is None else frontier.repartition(self.spread, *self.by)

    def meet(self, frontier: DataFrame, rows: DataFrame) -> DataFrame:
        """The frontier beside the rows, or blocks, that it names."""
        if not self.asked:
            return frontier.join(rows.select("src", "nbrs"), F.col("v") == F.col("src"))
        return frontier.join(rows.select("src", "nbrs", "asked_by"), (F.col("v") == F.col("src")) & F.array_contains("asked_by", F.col("i")))

    def meet_blocks(self, frontier: DataFrame) -> DataFrame:
        """The frontier beside the blocks that it names; each block of a hub is met in a task of its own."""
        if self.asked or self.spread is None:
            return self.meet(frontier, self.blocks)
        last = F.floor((F.col("deg") - 1) / self.longest).cast("int")
        named = frontier.join(self.hubs.select("src", F.explode(F.sequence(F.lit(0), last)).alias("blk")).hint("broadcast"), F.col("v") == F.col("src"))
        return named.repartition(self.spread, "src", "blk").join(self.blocks.select("src", "blk", "nbrs").hint("merge"), ["src", "blk"])

    def edges(self) -> DataFrame:
        """(src, dst): the graph's entries, from where it lies."""
        rows = self.rows.select("src", F.explode("nbrs").alias("dst"))
        return rows if self.blocks is None else rows.unionByName(self.blocks.select("src", F.explode("nbrs").alias("dst")))

    def expand(self, frontier: DataFrame) -> DataFrame:
        """(batch, row_id, src, col): the frontier's whole rows; only the frontier moves to a bucketed table."""
        frontier, cols = self.dealt(frontier), ["batch", "row_id", "src", F.explode("nbrs").alias("col")]
        out = self.meet(frontier, self.rows).select(*cols)
        if self.blocks is None:
            return out
        return out.unionByName(self.meet(frontier, self.blocks).select(*cols))


def to_adjacency(edges: DataFrame, longest: int = LONGEST_ROW, cut: bool = True) -> Adjacency:
    """Rows for most sources, blocks for hubs: no array grows with a hub. The edges are made once; `cut`: so are the rows."""
    edges = durable(edges.select("src", "dst"))
    spread = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    hubs = durable(edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg")).where(F.col("deg") > longest))
    if hubs.isEmpty():
        rows = to_rows(edges)
        return Adjacency(durable(rows) if cut else rows, longest=longest, spread=spread)
    named = hubs.select("src")
    rows = durable(to_rows(edges.join(named, "src", "left_anti")))
    blocks = durable(to_blocks(edges.join(named, "src", "left_semi"), longest))
    return Adjacency(rows, hubs, blocks, longest, spread)


def at_rest(rows: DataFrame, longest: int = LONGEST_ROW) -> Adjacency:
    """The same of rows that are made already (src, deg, nbrs): written once, hubs cut into blocks."""
    rows = durable(rows)
    spread = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    long = rows.where(F.col("deg") > longest)
    if long.isEmpty():
        return Adjacency(rows, longest=longest, spread=spread)
    starts = F.sequence(F.lit(0).cast("long"), F.col("deg") - 1, F.lit(longest).cast("long"))
    cut = long.select("src", "nbrs", F.posexplode(starts).alias("blk", "cum_before"))
    blocks = cut.select("src", "blk", "cum_before", F.slice("nbrs", (F.col("cum_before") + 1).cast("int"), longest).alias("nbrs"))
    return Adjacency(rows.where(F.col("deg") <= longest), durable(long.select("src", "deg")), durable(blocks), longest, spread)


def storage_bytes(rows: int, cols: int, nnz: int, fmt: str, index: int = 8, value: int = 4) -> int:
    """Bytes of a sparse matrix: coordinates, or a pointer array with one entry per row or column."""
    pointers = {"coo": 0, "csr": rows + 1, "csc": cols + 1}[fmt]
    return index * (pointers + nnz * (2 if fmt == "coo" else 1)) + value * nnz

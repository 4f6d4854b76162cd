"""SimHash near-duplicates through pivot distance tables.

Every text gets a 64-bit fingerprint: the bitwise majority over the XXH64 values of its word
shingles. Equal fingerprints are one vertex. The pivot table is made once, when the distinct fingerprints are
known: next to each lie its Hamming distances to `PIVOTS` fixed reference fingerprints, one byte each.
Distances obey the triangle inequality, so two fingerprints at `radius` or fewer bits differ by at most
`radius` in every coordinate. Every pair of fingerprints that meet is put to that test first: pairs with a
larger coordinate difference are discarded without being compared, and the survivors are verified on their bits.

Which pairs meet at all is settled exactly by the pigeonhole rule: of `blocks` parts of the
fingerprint at most `radius` can differ, so two linked fingerprints agree on some
`blocks - radius` parts. Coordinates alone cannot route pairs at scale (README, with figures): distances of random
fingerprints to any reference lie within a few bits of 32. Cells are grouped by those
agreeing parts, sorted by their first coordinate and swept inside the radius. A cell with more
than `CELL_ROWS` fingerprints is laid out as a grid of tiles, so that each task holds two
tiles at most and no pair is lost. A cell never emits its pairs: it joins what it has verified
and emits one link per fingerprint, which keeps reachability whole.

Defined results: null and empty texts have fingerprint zero, which links like any other; fewer
words than a shingle are one shingle; repeated rows each give a row; a null doc_id stays null
and never names a component; if all rows of a component lack an id, so does the component; rows of one id and
different texts are documents of their own; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, look_up, map_batches, texts
from .components import components

SHINGLE_WORDS = 4
SEED = 42
RADIUS = 4
BLOCKS = 6
PIVOTS = 24
CELL_ROWS = 4096


def fingerprint(text: str, shingle_words: int = SHINGLE_WORDS) -> int:
    """Bitwise majority over the hashes of the text's word shingles, repeats included."""
    import xxhash

    words = text.encode("utf-8", "replace").lower().split()  # bytes: only A-Z change, only ASCII blanks split
    if not words:
        return 0
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = max(1, len(words) - shingle_words + 1)
    lasts = ends[shingle_words - 1 :] if len(words) >= shingle_words else ends[-1:]
    digest = xxhash.xxh64_digest
    total = np.zeros(64, np.int64)
    spans = list(zip(starts[:n].tolist(), lasts.tolist()))
    for at in range(0, n, 8192):  # bounded memory for very long texts
        hashes = b"".join([digest(line[a:b], SEED) for a, b in spans[at : at + 8192]])
        total += np.unpackbits(np.frombuffer(hashes, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * total > n).tobytes(), "big")


def references(n: int = PIVOTS) -> np.ndarray:
    """Reference fingerprints, from a fixed seed."""
    return np.random.default_rng(64).integers(0, 2**64, n, dtype=np.uint64)


def pivot_table(fingerprints: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """Hamming distance of each fingerprint to each reference (rows by pivots, one byte each)."""
    return np.bitwise_count(fingerprints[:, None] ^ pivots[None, :]).astype(np.int8)


def linked_pairs(fps: np.ndarray, table: np.ndarray, radius: int = RADIUS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within the radius, from fingerprints and their rows of the pivot table.

    Rows are swept in order of their first coordinate; a strip of rows meets only the rows
    whose first coordinate is within the radius, then loses pairs by the difference of each
    other coordinate, and what survives is verified.
    """
    order = np.argsort(table[:, 0], kind="stable")
    first = table[order, 0]
    step = max(1, 2_000_000 // max(1, len(order)))
    for at in range(0, len(order), step):
        rows = order[at : at + step]
        a = np.searchsorted(first, table[rows[0], 0] - radius, side="left")
        b = np.searchsorted(first, table[rows[-1], 0] + radius, side="right")
        cand = order[a:b]
        i, j = np.nonzero(np.abs(table[rows, 0][:, None] - table[cand, 0][None, :]) <= radius)
        i, j = rows[i], cand[j]
        i, j = i[(keep := i < j)], j[keep]
        for p in range(1, table.shape[1]):
            keep = np.abs(table[i, p] - table[j, p]) <= radius
            i, j = i[keep], j[keep]
        keep = np.bitwise_count(fps[i] ^ fps[j]) <= radius
        if keep.any():
            yield i[keep], j[keep]


def _forest(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Root of each of n vertices after joining the pairs."""
    root = np.arange(n)
    for i, j in pairs:
        while True:
            a, b = root[i], root[j]
            if (a == b).all():
                break
            low = np.minimum(a, b)
            np.minimum.at(root, a, low)
            np.minimum.at(root, b, low)
            while (root[root] != root).any():
                root = root[root]
    return root


def _part_masks(blocks: int) -> list[int]:
    cuts = [round(64 * k / blocks) for k in range(blocks + 1)]
    return [((1 << (b - a)) - 1) << a for a, b in zip(cuts, cuts[1:])]


def cell_keys(fingerprint, radius: int, blocks: int):
    """Array of (choice, agreeing bits): one per choice of parts that a linked pair may share."""
    masks = [sum(m) for m in combinations(_part_masks(blocks), blocks - radius)]
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    return F.array(*[F.struct(F.lit(k).alias("choice"), fingerprint.bitwiseAND(F.lit(m).cast("long")).alias("bits")) for k, m in enumerate(signed)])


def with_pivots(fingerprints: DataFrame, n_pivots: int = PIVOTS) -> DataFrame:
    """Adds `pivots`: the fingerprint's row of the pivot table, one byte for each reference."""
    names = [c for c in fingerprints.columns if c != "fp"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = pivot_table(batch.column(0).to_numpy().view(np.uint64), references(n_pivots))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([r.tobytes() for r in rows], pa.binary())], [*batch.schema.names, "pivots"])

    kinds = dict(fingerprints.dtypes)
    return map_batches(fingerprints.select("fp", *names), work, ", ".join(["fp long", *(f"{c} {kinds[c]}" for c in names), "pivots binary"]))


def link_fingerprints(
    fingerprints: DataFrame, radius: int = RADIUS, blocks: int = BLOCKS, n_pivots: int = PIVOTS, cell_rows: int = CELL_ROWS
) -> DataFrame:
    """(a, b): links between distinct fingerprints that keep reachability whole.

    Takes column `fp` (long), and `pivots` where the table is there already.
    """
    if blocks <= radius:
        raise ValueError("blocks must exceed the radius")
    tabled = fingerprints if "pivots" in fingerprints.columns else durable(with_pivots(fingerprints.select("fp"), n_pivots))
    cells = tabled.select("fp", F.explode(cell_keys(F.col("fp"), radius, blocks)).alias("k")).select("fp", "k.choice", "k.bits")
    sizes = cells.groupBy("choice", "bits").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    sides = F.ceil(F.col("n") / F.lit(cell_rows)).cast("int")
    tile = F.pmod(F.xxhash64("fp", F.lit(7)), F.col("side").cast("long")).cast("int")
    # tiles: row t of a cell meets every tile u; the task (t, u), t <= u, gets both
    placed = (
        cells.join(sizes.withColumn("side", sides), ["choice", "bits"])
        .withColumn("tile", tile)
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("side") - 1)))
        .select("choice", "bits", F.least("tile", "other").alias("t"), F.greatest("tile", "other").alias("u"), "fp")
    )
    keys = ["choice", "bits", "t", "u"]
    # only fingerprints that meet others fetch their row of the table
    spread = placed.join(tabled.select("fp", "pivots"), "fp").select(*keys, "fp", "pivots").repartition(*[F.col(k) for k in keys]).sortWithinPartitions(*keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in _whole_cells(batches, keys):
            key = np.stack([part.column(k).to_numpy() for k in keys])
            cuts = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1
            bounds = np.concatenate([[0], cuts, [part.num_rows]])
            fps = part.column("fp").to_numpy().astype(np.int64)
            table = np.frombuffer(b"".join(part.column("pivots").to_pylist()), np.int8).reshape(-1, n_pivots)
            sizes = np.diff(bounds)
            two = bounds[:-1][sizes == 2]  # most cells: two fingerprints, all compared at once
            found = [_pairs_of_two(fps, table, two, radius)]
            for c in np.flatnonzero(sizes > 2):
                at = slice(bounds[c], bounds[c + 1])
                root = _forest(sizes[c], linked_pairs(fps[at].view(np.uint64), table[at], radius))
                moved = np.flatnonzero(root != np.arange(sizes[c]))
                found.append((fps[at][moved], fps[at][root[moved]]))
            a, b = (np.concatenate(x) for x in zip(*found))
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return map_batches(spread, run, "a long, b long").distinct()


def _pairs_of_two(fps: np.ndarray, table: np.ndarray, at: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows `at` and `at + 1`: discarded by their largest coordinate difference, then verified."""
    at = at[np.abs(table[at] - table[at + 1]).max(axis=1, initial=0) <= radius]
    at = at[np.bitwise_count((fps[at] ^ fps[at + 1]).view(np.uint64)) <= radius]
    return fps[at], fps[at + 1]


def _whole_cells(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Tables that end where a cell ends; the open cell at the end of a batch is carried on."""
    rest: list[pa.Table] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([batch])
        key = np.stack([table.column(k).to_numpy() for k in keys])
        last = key[:, -1:]
        open_from = int(np.flatnonzero((key != last).any(axis=0)).max(initial=-1)) + 1
        held = rest and [rest[-1].column(k)[rest[-1].num_rows - 1].as_py() for k in keys]
        if open_from == 0 and rest and held == last[:, 0].tolist():
            rest.append(table)
            continue
        yield pa.concat_tables([*rest, table.slice(0, open_from)]).combine_chunks() if open_from or rest else table.slice(0, 0)
        rest = [table.slice(open_from)]
    if rest:
        yield pa.concat_tables(rest).combine_chunks()


def fingerprints(docs: DataFrame, shingle_words: int = SHINGLE_WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_hash (of the text) and fp (the fingerprint as a signed long) for every row."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [fingerprint(x, shingle_words) for x in batch.column(2).to_pylist()]
            fps = pa.array(np.array(found, np.uint64).view(np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), fps], ["doc_id", "text_hash", "fp"])

    rows = texts(docs, id_col, text_col).select("doc_id", F.xxhash64("text").alias("text_hash"), "text")
    return map_batches(rows, work, "doc_id long, text_hash long, fp long")


def near_duplicates(
    docs: DataFrame, radius: int = RADIUS, shingle_words: int = SHINGLE_WORDS, blocks: int = BLOCKS,
    id_col: str = "doc_id", text_col: str = "text",
) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable), text_hash, kept, for every row.

    `kept`: the row stands for its component: it has the smallest doc_id there, and among rows of that id the smallest text_hash.
    """
    rows = durable(fingerprints(docs, shingle_words, id_col, text_col))
    named_row = F.struct("doc_id", "text_hash")
    own = rows.groupBy("fp").agg(F.min(F.when(F.col("doc_id").isNotNull(), named_row)).alias("least"), F.count(F.lit(1)).alias("n_rows"))
    distinct = durable(with_pivots(own))
    grouped = components(link_fingerprints(distinct.select("fp", "pivots"), radius, blocks))
    # a component's name is its smallest doc_id; fingerprints without links name themselves
    rooted = durable(distinct.drop("pivots").join(grouped, F.col("fp") == F.col("vertex"), "left").select("fp", "least", "n_rows", "root"))
    in_groups = rooted.where("root IS NOT NULL")
    members = in_groups.groupBy("root").agg(F.min("least").alias("first"), F.count(F.lit(1)).alias("n_fps"))
    n_grouped, n_rows = rooted.agg(F.count("root"), F.coalesce(F.sum("n_rows"), F.lit(0))).first()
    linked = look_up(in_groups.select("root", "fp", "n_rows"), "root", members, "n_fps", n_grouped).select("fp", "n_rows", "first")
    alone = rooted.where("root IS NULL").select("fp", "n_rows", F.col("least").alias("first"))
    met = look_up(rows, "fp", linked.unionByName(alone), "n_rows", n_rows)
    digits = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    kept = (F.col("doc_id") == F.col("first.doc_id")) & (F.col("text_hash") == F.col("first.text_hash"))
    return met.select("doc_id", digits.alias("fingerprint"), F.col("first.doc_id").alias("component_id"), "text_hash", F.coalesce(kept, F.lit(False)).alias("kept"))


def deduplicate(docs: DataFrame, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each near-duplicate group, with all its columns: the one with the smallest id.

    Decided row by row: rows of one id whose texts belong to different groups each stand for their own. Of rows with the same
    id in one group the one with the smallest hash of its text stays, and of rows with the same id and text one.
    Rows without an id cannot be named by a group and stay.
    """
    own_id, own_hash = (_free(name, docs.columns) for name in ("_id", "_hash"))
    stay = near_duplicates(docs, radius, id_col=id_col, text_col=text_col).where("kept")
    stay = stay.select(F.col("doc_id").alias(own_id), F.col("text_hash").alias(own_hash)).distinct()
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    keyed = docs.withColumns({own_id: F.col(id_col).cast("long"), own_hash: F.xxhash64(body)})
    staying = keyed.join(stay, [own_id, own_hash], "left_semi").dropDuplicates([own_id, own_hash]).select(*docs.columns)
    return staying.unionByName(docs.where(F.col(id_col).isNull())).select(*docs.columns)


def _free(name: str, taken: list[str]) -> str:
    while name in taken:
        name += "_"
    return name

"""Graphs on the given tables, and edits of graphs. `src` pulls from `dst`."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ranges import range_of
from ..functions.rng import u52
from .tables import Tables, durable, ensure_importable


def _edges(df: DataFrame, src: str | Column, dst: str | Column) -> DataFrame:
    as_long = lambda c: (F.col(c) if isinstance(c, str) else c).cast("long")
    return df.select(as_long(src).alias("src"), as_long(dst).alias("dst")).distinct().withColumn("val", F.lit(1).cast("long"))


def copurchase_graph(t: Tables) -> DataFrame:
    """Parts bought in one order, both directions."""
    lines = t.lineitem.select("l_orderkey", "l_partkey").distinct()
    pairs = lines.alias("a").join(lines.alias("b"), "l_orderkey").where("a.l_partkey <> b.l_partkey")
    return _edges(pairs, F.col("a.l_partkey"), F.col("b.l_partkey"))


def copurchase_rows(t: Tables) -> DataFrame:
    """The same graph as src, deg, nbrs (ascending), without its edges one by one: an order's parts meet as one array."""
    lines = t.lineitem.where("l_orderkey IS NOT NULL").select("l_orderkey", F.col("l_partkey").cast("long").alias("part"))
    orders = lines.repartition("l_orderkey").groupBy("l_orderkey").agg(F.collect_set("part").alias("parts"))
    ends = orders.where(F.size("parts") > 1).select(F.explode("parts").alias("src"), "parts")
    nbrs = F.array_sort(F.array_except(F.flatten(F.collect_list("parts")), F.array("src")))
    rows = ends.repartition("src").groupBy("src").agg(nbrs.alias("nbrs"))
    return rows.select("src", F.size("nbrs").cast("long").alias("deg"), "nbrs")


def weighted_copurchase_graph(t: Tables) -> DataFrame:
    """Parts bought in one order, both directions; `val` counts the orders."""
    lines = t.lineitem.select("l_orderkey", "l_partkey").distinct()
    pairs = lines.alias("a").join(lines.alias("b"), "l_orderkey").where("a.l_partkey <> b.l_partkey")
    return pairs.groupBy(F.col("a.l_partkey").alias("src"), F.col("b.l_partkey").alias("dst")).agg(F.count(F.lit(1)).alias("val"))


#: Distance between the id ranges of the trade graph's vertex kinds.
TRADE_STRIDE = 10_000_000_000


def trade_graph(t: Tables) -> DataFrame:
    """Customer to order to part to supplier, in one id space; suppliers are sinks."""
    s = TRADE_STRIDE
    orders = t.orders.select(F.col("o_custkey").alias("a"), (F.col("o_orderkey") + s).alias("b"))
    parts = t.lineitem.select((F.col("l_orderkey") + s).alias("a"), (F.col("l_partkey") + 2 * s).alias("b"))
    suppliers = t.lineitem.select((F.col("l_partkey") + 2 * s).alias("a"), (F.col("l_suppkey") + 3 * s).alias("b"))
    return _edges(orders.unionByName(parts).unionByName(suppliers), "a", "b")


def bipartite_graph(t: Tables) -> DataFrame:
    """Customer to every part bought."""
    bought = t.orders.select("o_orderkey", "o_custkey").join(t.lineitem.select("l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    return _edges(bought, "o_custkey", "l_partkey")


def supplies_graph(t: Tables) -> DataFrame:
    """Supplier to part: few sources of high degree."""
    return _edges(t.lineitem, "l_suppkey", "l_partkey")


def handoff_graph(t: Tables) -> DataFrame:
    """User to the next different user in the day's event stream."""
    day = Window.partitionBy(F.to_date("ts")).orderBy("ts", "event_id")
    following = t.events.select("user_id", F.lead("user_id").over(day).alias("next"))
    return _edges(following.where("next IS NOT NULL AND next <> user_id"), "user_id", "next")


def page_link_graph(t: Tables) -> DataFrame:
    """Page to link target, by text; targets keep their string key."""
    links = t.pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1)))).alias("target"))
    return links.select(F.col("page_id").alias("src"), "target")


def similarity_graph(t: Tables, m: int | None = 16, tau: float | None = None, block: int = 512) -> DataFrame:
    """Nearest vectors by cosine: the m best of each, or all at or above tau.

    An exact search: vectors meet block by block in matrix products, each task holding two
    blocks. For vector sets whose square is out of reach use `similarity_graph_lsh`.
    """
    import numpy as np
    import pandas as pd

    rows = t.embeddings.select("vec_id", "embedding")
    n = rows.count()
    blocks = max(1, -(-n // block))
    tagged = rows.withColumn("blk", F.pmod("vec_id", F.lit(blocks)).cast("int"))
    left = tagged.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumnRenamed("blk", "own")
    right = tagged.withColumn("own", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumnRenamed("blk", "other")

    def meet(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        x, y = (np.array(d["embedding"].tolist(), np.float64) for d in (a, b))
        if not len(x) or not len(y):
            return pd.DataFrame({"src": [], "dst": [], "sim": []})
        x, y = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-30) for v in (x, y))
        sim = np.round(x @ y.T, 9)
        sim[a["vec_id"].to_numpy()[:, None] == b["vec_id"].to_numpy()[None, :]] = -2
        if tau is not None:
            i, j = np.nonzero(sim >= tau)
        else:
            k = min(m, sim.shape[1])
            j = np.argsort(-sim, axis=1, kind="stable")[:, :k]
            i = np.repeat(np.arange(len(x)), k)
            j = j.ravel()
            i, j = i[(keep := sim[i, j] > -2)], j[keep]
        return pd.DataFrame({"src": a["vec_id"].to_numpy()[i], "dst": b["vec_id"].to_numpy()[j], "sim": sim[i, j]})

    near = left.groupBy("own", "other").cogroup(right.groupBy("own", "other")).applyInPandas(meet, "src long, dst long, sim double")
    if tau is None:
        best = Window.partitionBy("src").orderBy(F.desc("sim"), "dst")
        near = near.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= m)
        return near.select("src", "dst", F.lit(1).cast("long").alias("val"), "sim", "rank")
    return near.select("src", "dst", F.lit(1).cast("long").alias("val"), "sim")


def similarity_graph_lsh(t: Tables, m: int = 16, bits: int = 5, tables: int = 48, seed: int = 1) -> DataFrame:
    """Nearest vectors by cosine, approximately: the m best among those that meet, for sets whose square is out of reach.

    Vectors meet where the signs of `bits` random projections agree, in any of `tables` draws of projections; those that meet are compared
    exactly. More tables find more of the neighbours, more bits make cells smaller. The vectors themselves go to a cell once for each table;
    a cell of more than `CELL` vectors is cut by further projections.
    """
    import numpy as np
    import pandas as pd

    rows = t.embeddings.select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    width = rows.agg(F.max(F.size("x"))).first()[0] or 1
    n = rows.count()
    planes = np.random.default_rng(seed).normal(size=(tables, bits + max(0, (n // CELL).bit_length()), width))

    def place(frames):
        for f in frames:
            x = np.array(f["x"].tolist(), float).reshape(len(f), -1)
            for k, p in enumerate(planes):
                signs = (x @ p.T > 0) @ (1 << np.arange(len(p)))
                yield pd.DataFrame({"vec_id": f["vec_id"], "x": f["x"], "cell": signs * tables + k})

    def meet(frame: pd.DataFrame) -> pd.DataFrame:
        x = np.array(frame["x"].tolist())
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-30)
        ids, found = frame["vec_id"].to_numpy(), []
        for at in range(0, len(x), CELL):
            sim = np.round(x[at : at + CELL] @ x.T, 9)
            sim[ids[at : at + CELL, None] == ids[None, :]] = -2
            k = min(m, len(x))
            j = np.argpartition(-sim, k - 1, axis=1)[:, :k]
            i = np.repeat(np.arange(len(sim)), k)
            found.append(pd.DataFrame({"src": ids[at + i], "dst": ids[j.ravel()], "sim": sim[i, j.ravel()]}))
        found = pd.concat(found)
        return found[found["sim"] > -2]

    cells = rows.mapInPandas(place, "vec_id long, x array<double>, cell long")
    pairs = cells.groupBy("cell").applyInPandas(meet, "src long, dst long, sim double").distinct()
    best = Window.partitionBy("src").orderBy(F.desc("sim"), "dst")
    near = pairs.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= m)
    return near.select("src", "dst", F.lit(1).cast("long").alias("val"), "sim", "rank")


#: Vectors in one cell of the approximate search, on average, at most.
CELL = 4096


#: Word hashes that a task keeps, and parts that shingles are dealt to by hash: a task looks for links in one after the other.
WORDS_KEPT, SHINGLE_PARTS = 1 << 20, 4096
#: Shingles, of whole texts, that a task packs at once.
SHINGLES_TOGETHER = 1 << 20


class _WordHashes(dict):
    """Hashes of words, made when first asked for."""

    def __missing__(self, word: str) -> int:
        import xxhash

        if len(self) >= WORDS_KEPT:
            self.clear()
        found = self[word] = xxhash.xxh64_intdigest(word)
        return found


def shingle_hashes(words: list[str], shingle: int, known: dict[str, int]):
    """Distinct hashes of all runs of `shingle` words, or of all words where there are fewer: equal for equal words in equal order."""
    import numpy as np

    if not words:
        return np.empty(0, np.int64)
    each = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    length = min(shingle, len(words))
    h = np.full(len(words) - length + 1, length, np.uint64)
    for k in range(length):
        h = h * np.uint64(0x9E3779B97F4A7C15) + each[k : k + len(h)]
    h ^= h >> np.uint64(32)
    h.sort()
    return h[np.concatenate([[True], h[1:] != h[:-1]])].view(np.int64)


def _links(h, doc, known, least: int, most: int):
    """Distinct links (smaller id, larger id) among rows of whole shingles, in the order of h. Ids that are not `known` count and aren't linked."""
    import numpy as np

    starts = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
    counts = np.diff(np.append(starts, len(h)))
    met = np.repeat(counts, counts) >= max(2, least)
    group, doc, known = np.repeat(np.arange(len(starts)), counts)[met], doc[met], known[met]
    ids, at = np.unique(doc, return_inverse=True)
    group, at, rare = group[known], at[known], counts <= most
    first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if len(group) else np.empty(0, np.int64)
    hub = np.zeros(len(starts), np.int64)
    hub[group[first]] = np.minimum.reduceat(at, first) if len(first) else 0
    spoke = ~rare[group]
    found = [np.unique(hub[group[spoke]] * len(ids) + at[spoke])]
    group, at = group[~spoke], at[~spoke]
    for k in range(1, most):
        same = group[k:] == group[:-k]
        if not same.any():
            break
        a, b = at[:-k][same], at[k:][same]
        found.append(np.unique(np.minimum(a, b) * len(ids) + np.maximum(a, b)))
    low, high = np.divmod(np.unique(np.concatenate(found)), max(1, len(ids)))
    return ids[low[low != high]], ids[high[low != high]]


def neardup_graph(t: Tables, shingle: int = 5, least: int = 2, most: int = 20) -> DataFrame:
    """Documents that share a word shingle of whole texts, both directions.

    All documents of a shingle are linked with each other where there are at most `most`. Where there are more, each is linked
    to the one with the smallest id: as many edges as documents, and the same reachability. Shingles are made once, and move once, as arrays.
    """
    import pyarrow as pa

    ensure_importable(t.spark)

    def hashes(batches):
        import numpy as np

        def packed(found, doc):
            lengths, h = [len(f) for f in found], np.concatenate([np.empty(0, np.int64), *found])
            part = (h & (SHINGLE_PARTS - 1)).astype(np.uint16)
            order = np.argsort(part, kind="stable")
            columns = [h, *(np.repeat(x.to_numpy(zero_copy_only=False), lengths) for x in (doc.fill_null(0), doc.is_valid()))]
            parts, starts = np.unique(part[order], return_index=True)
            ends = np.append(starts, len(h))
            # an array for each part, as bytes
            arrays = [pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(parts), [None, pa.py_buffer(ends * x.itemsize), pa.py_buffer(x[order])]).cast(pa.binary()) for x in columns]
            return pa.RecordBatch.from_arrays([pa.array(parts, pa.int32()), *arrays], ["part", "h", "doc", "known"])

        known = _WordHashes()
        for batch in batches:
            doc, texts = batch.column(0).cast(pa.int64()), batch.column(1)
            found, first, many = [], 0, 0
            for at, text in enumerate(texts):
                found.append(shingle_hashes((text.as_py() or "").lower().split(), shingle, known))
                many += len(found[-1])
                if many >= SHINGLES_TOGETHER:
                    yield packed(found, doc.slice(first, len(found)))
                    found, first, many = [], at + 1, 0
            yield packed(found, doc.slice(first, len(found)))

    def linked(batches):
        import numpy as np

        def links(held: list):
            h, doc, known = (np.frombuffer(b"".join(x), kind) for x, kind in zip(zip(*held), (np.int64, np.int64, bool)))
            order = np.argsort(h)
            a, b = _links(h[order], doc[order], known[order], least, most)
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

        held, of = [], None
        for batch in batches:
            for part, *row in zip(*(c.to_pylist() for c in batch.columns)):
                if part != of and held:
                    yield links(held)
                    held = []
                of = part
                held.append(row)
        if held:
            yield links(held)

    held = t.documents.select("doc_id", "text").mapInArrow(hashes, "part int, h binary, doc binary, known binary")
    ordered = held.repartition("part").sortWithinPartitions("part")
    pairs = ordered.mapInArrow(linked, "a long, b long").distinct()
    ways = F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))))
    return pairs.select(ways.alias("e")).select("e.src", "e.dst", F.lit(1).cast("long").alias("val"))


def benchmark_graph(t: Tables, shingle: int = 5) -> DataFrame:
    """Benchmark item to every document with which it shares a word shingle; in the JVM, over whole texts."""

    def shingles(df: DataFrame, key: str) -> DataFrame:
        words = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+"), lambda w: w != "")
        at = F.sequence(F.lit(1), F.greatest(F.size("w") - (shingle - 1), F.lit(1)))
        spread = df.select(key, words.alias("w")).where(F.size("w") > 0).select(key, F.explode(F.array_distinct(F.transform(at, lambda i: F.array_join(F.slice("w", i, shingle), " ")))).alias("text"))
        return spread.select(key, F.md5("text").alias("h"))

    items, docs = shingles(t.benchmark, "item_id"), shingles(t.documents, "doc_id")
    return _edges(items.join(docs, "h"), "item_id", "doc_id")


# ------------------------------------------------------------------ edits


def symmetrize(e: DataFrame) -> DataFrame:
    return e.select("src", "dst", "val").unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "val")).dropDuplicates(["src", "dst"])


def dedupe(e: DataFrame) -> DataFrame:
    return e.select("src", "dst").distinct().withColumn("val", F.lit(1).cast("long"))


def drop_loops(e: DataFrame) -> DataFrame:
    return e.where("src <> dst")


def add_loops(e: DataFrame) -> DataFrame:
    loops = vertices_of(e).select(F.col("v").alias("src"), F.col("v").alias("dst"), F.lit(1).cast("long").alias("val"))
    return drop_loops(e).select("src", "dst", "val").unionByName(loops)


def vertices_of(e: DataFrame) -> DataFrame:
    return e.select(F.col("src").alias("v")).union(e.select("dst")).distinct()


def relabel(e: DataFrame, together: int = 1 << 16) -> tuple[DataFrame, DataFrame]:
    """Dense ids 0..n-1 in key order: (edges with new ids, v to new id).

    Vertices are ranked inside ranges of the key and shifted by the ranges' running counts. Ranges are cut at quantiles and hold
    about `together` vertices, so no task sees many more, however the keys lie.
    """
    v = durable(vertices_of(e))
    ranged = v.withColumn("part", range_of(v, "v", min(4096, v.count() // together + 1)))
    inside = Window.partitionBy("part").orderBy("v")
    ids = durable(ranged.join(F.broadcast(running_offsets(ranged)), "part").select("v", (F.col("offset") + F.row_number().over(inside) - 1).cast("long").alias("id")))
    a, b = ids.withColumnsRenamed({"v": "src", "id": "s"}), ids.withColumnsRenamed({"v": "dst", "id": "d"})
    return e.join(a, "src").join(b, "dst").select(F.col("s").alias("src"), F.col("d").alias("dst"), "val"), ids


def running_offsets(ranged: DataFrame) -> DataFrame:
    """Rows before each `part`; one row per part, of which there is a fixed number."""
    counts = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return counts.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))


def induced(e: DataFrame, vs: DataFrame) -> DataFrame:
    """Edges with both ends among `vs` (column v)."""
    kept = e.join(vs.select(F.col("v").alias("src")).distinct(), "src", "left_semi")
    return kept.join(vs.select(F.col("v").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst", "val")


def vertex_sample(e: DataFrame, parts: int = 8, seed: int = 42) -> DataFrame:
    """The subgraph on one in `parts` of the vertices, chosen by hash."""
    return induced(e, vertices_of(e).where(u52(seed, "keep", F.col("v")) % parts == 0))


def degrees(e: DataFrame, side: str = "src") -> DataFrame:
    return e.groupBy(F.col(side).alias("v")).agg(F.count(F.lit(1)).alias("deg"))


def k_hop(e: DataFrame, roots: DataFrame, hops: int) -> DataFrame:
    """Vertices within `hops` of the roots (column v), with their smallest distance."""
    reached = roots.select("v").distinct().withColumn("hop", F.lit(0).cast("long"))
    front = reached
    for h in range(1, hops + 1):
        step = front.join(e, F.col("v") == F.col("src")).select(F.col("dst").alias("v")).distinct()
        front = step.join(reached, "v", "left_anti").withColumn("hop", F.lit(h).cast("long"))
        reached = reached.unionByName(front)
    return reached


def sinks(e: DataFrame) -> DataFrame:
    """Vertices that nothing is pulled for: they never occur as src."""
    return vertices_of(e).join(e.select(F.col("src").alias("v")).distinct(), "v", "left_anti")


def split(vs: DataFrame, seed: int = 42, train: int = 60, validate: int = 20) -> DataFrame:
    """Vertices with a hash-drawn split: train, validate or test."""
    r = u52(seed, "split", F.col("v")) % 100
    return vs.withColumn("split", F.when(r < train, "train").when(r < train + validate, "validate").otherwise("test"))


#: Edges of the worked example, one direction each.
WORKED6 = [(0, 1), (0, 2), (1, 2), (1, 4), (3, 4), (3, 5), (4, 5)]


def worked6(spark) -> DataFrame:
    """Six vertices, seven undirected edges: small enough to enumerate."""
    return spark.createDataFrame([(a, b, 1) for x in WORKED6 for a, b in (x, x[::-1])], "src long, dst long, val long")

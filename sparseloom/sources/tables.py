"""Reading and writing: given tables, edge lists in several formats, bucketed and minibatch sinks."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_LONG, _INT, _DOUBLE, _STRING, _TIME = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType(), T.TimestampType()

#: The given tables and their columns.
SCHEMAS: dict[str, T.StructType] = {
    name: T.StructType([T.StructField(c, t) for c, t in columns])
    for name, columns in {
        "region": [("r_regionkey", _INT), ("r_name", _STRING)],
        "nation": [("n_nationkey", _INT), ("n_name", _STRING), ("n_regionkey", _INT)],
        "customer": [("c_custkey", _LONG), ("c_name", _STRING), ("c_nationkey", _INT), ("c_acctbal", _DOUBLE), ("c_mktsegment", _STRING)],
        "supplier": [("s_suppkey", _LONG), ("s_name", _STRING), ("s_nationkey", _INT), ("s_acctbal", _DOUBLE)],
        "part": [("p_partkey", _LONG), ("p_name", _STRING), ("p_brand", _STRING), ("p_type", _STRING), ("p_size", _INT), ("p_retailprice", _DOUBLE)],
        "orders": [("o_orderkey", _LONG), ("o_custkey", _LONG), ("o_orderstatus", _STRING), ("o_totalprice", _DOUBLE), ("o_orderdate", _TIME), ("o_orderpriority", _STRING)],
        "lineitem": [
            ("l_orderkey", _LONG), ("l_partkey", _LONG), ("l_suppkey", _LONG), ("l_linenumber", _INT), ("l_quantity", _DOUBLE), ("l_extendedprice", _DOUBLE),
            ("l_discount", _DOUBLE), ("l_tax", _DOUBLE), ("l_returnflag", _STRING), ("l_linestatus", _STRING), ("l_shipdate", _TIME),
        ],
        "events": [("event_id", _LONG), ("ts", _TIME), ("user_id", _LONG), ("event_type", _STRING), ("value", _DOUBLE), ("props", _STRING)],
        "documents": [("doc_id", _LONG), ("text", _STRING), ("lang", _STRING), ("source", _STRING), ("n_chars", _LONG)],
        "embeddings": [("vec_id", _LONG), ("embedding", T.ArrayType(T.FloatType())), ("label", _INT)],
        "pages": [("page_id", _LONG), ("url", _STRING), ("html", _STRING)],
        "benchmark": [("item_id", _LONG), ("text", _STRING)],
        "labels": [("doc_id", _LONG), ("quality", _INT), ("toxic", _INT)],
        "conversations": [("conv_id", _LONG), ("turn", _LONG), ("role", _STRING), ("text", _STRING)],
    }.items()
}


class Tables:
    """The given tables by name, each read when first asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        if name not in SCHEMAS:
            raise AttributeError(name)
        return self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")

    def register_views(self, *names: str) -> SparkSession:
        """Temporary views of the tables, for SQL."""
        for name in names or SCHEMAS:
            getattr(self, name).createOrReplaceTempView(name)
        return self.spark


def load(spark: SparkSession, sf_dir: str) -> Tables:
    return Tables(spark, sf_dir)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder that all executors see; local sessions without a shared one get a temporary folder."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if root is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = tempfile.mkdtemp(prefix="sparseloom-")
    return f"{root}/{name}-{uuid.uuid4().hex}"


def durable(df: DataFrame) -> DataFrame:
    """Cut the lineage with a checkpoint in the shared folder."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession, "checkpoint"))
    return df.checkpoint()


#: What may be sent to every task.
BROADCAST_BYTES = 512 * 1024 * 1024


def small_enough(rows: DataFrame, limit: int = BROADCAST_BYTES) -> bool:
    """Whether a table's rows, with all that their arrays and texts hold, are within the limit: counted, not estimated."""
    width = {"long": 8, "bigint": 8, "int": 4, "double": 8, "float": 4, "boolean": 1}
    size = F.lit(0).cast("long")
    for name, kind in rows.dtypes:
        if kind.startswith("array<"):
            size += F.coalesce(F.size(name), F.lit(0)) * width.get(kind[6:-1], 16) + 16
        elif kind in ("string", "binary"):
            size += F.coalesce(F.octet_length(name), F.lit(0)) + 16
        else:
            size += width.get(kind, 16)
    return (rows.agg(F.sum(size)).first()[0] or 0) <= limit


EDGE_SCHEMA = "src long, dst long, val long"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """An edge list; text files hold "src dst" per line. A missing val is 1."""
    if fmt == "text":
        cut = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).select(cut[0].cast("long").alias("src"), cut[1].cast("long").alias("dst"), F.lit(1).cast("long").alias("val"))
    if fmt not in ("parquet", "csv", "json", "orc"):
        raise ValueError(f"unknown format {fmt!r}")
    reader = spark.read.schema(EDGE_SCHEMA)
    df = reader.csv(path, header=True) if fmt == "csv" else reader.format(fmt).load(path)
    return df.select("src", "dst", F.coalesce("val", F.lit(1)).alias("val"))


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite") -> str:
    if fmt == "text":
        edges.select(F.concat_ws(" ", "src", "dst").alias("value")).write.mode(mode).text(path)
    elif fmt == "csv":
        edges.write.mode(mode).csv(path, header=True)
    else:
        edges.write.mode(mode).format(fmt).save(path)
    return path


def save_adjacency(edges: DataFrame, name: str, buckets: int = 16, path: str | None = None) -> DataFrame:
    """Adjacency rows as a bucketed, sorted table: joins on src need no exchange of the graph."""
    from sparseloom.operators.matrix import to_rows

    return save_bucketed(to_rows(edges), name, buckets, path)


def save_bucketed(rows: DataFrame, name: str, buckets: int, path: str | None = None) -> DataFrame:
    """Rows by buckets of `src`, sorted inside, as a table; in the warehouse, or below a path of one's own."""
    writer = rows.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").format("parquet")
    (writer.option("path", path) if path else writer).saveAsTable(name)
    return rows.sparkSession.table(name)


def save_minibatches(sampled: DataFrame, path: str, batches_per_bulk: int = 16) -> str:
    """Sampled edges as files by bulk and layer, for trainers outside Spark."""
    tagged = sampled.withColumn("bulk", F.floor(F.col("batch") / batches_per_bulk).cast("long"))
    tagged.repartition("bulk").write.mode("overwrite").partitionBy("bulk", "layer").parquet(path)
    return path


def ensure_importable(spark: SparkSession) -> None:
    """Send this package to Python workers that don't have it on their path."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    sc = spark.sparkContext
    if root in os.environ.get("PYTHONPATH", "").split(os.pathsep) or getattr(sc, "_sparseloom_shipped", False):
        return
    import shutil

    package = os.path.basename(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    sc.addPyFile(shutil.make_archive(os.path.join(tempfile.mkdtemp(prefix="sparseloom-"), package), "zip", root, package))
    sc._sparseloom_shipped = True

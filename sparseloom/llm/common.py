"""Helpers shared by the training-data operators: row access, durable cuts, worker state."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("documents", "pages", "benchmark", "labels", "conversations", "embeddings")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; the path is only ever opened by Spark's own readers."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Two columns (doc_id long, text string); a null text is the empty text.

    Other columns, whatever their names, are left behind, so they cannot clash with
    the names an operator uses inside.
    """
    return df.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
    )


def fold(doc_id, folds: int):
    """crc32 of the id's decimal text, modulo the number of folds (column); a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(folds).cast("long"))


class Remembered(dict):
    """A dict that computes and keeps what it lacks; long keys are not kept."""

    def __init__(self, make):
        self.make = make

    def __missing__(self, key):
        value = self.make(key)
        if len(key) <= 64:
            self[key] = value
        return value


def map_batches(
    df: DataFrame, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str
) -> DataFrame:
    """Arrow batches through `work`; the package travels with the job if workers lack it."""
    ship_package(df.sparkSession)
    return df.mapInArrow(work, schema)


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in Python workers that don't have it on their path."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    if root in os.environ.get("PYTHONPATH", "").split(os.pathsep):
        return
    sc = spark.sparkContext
    if getattr(sc, "_sparseloom_shipped", False):
        return
    import shutil

    folder = tempfile.mkdtemp(prefix="sparseloom-")
    package = os.path.basename(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    sc.addPyFile(shutil.make_archive(os.path.join(folder, package), "zip", root, package))
    sc._sparseloom_shipped = True


def durable(df: DataFrame) -> DataFrame:
    """Cut the lineage with checkpoint(): the rows survive the loss of any executor.

    The folder is the cluster's own `spark.checkpoint.dir`. Only a local session without
    one (tests) gets a temporary folder; a cluster without one is an error.
    """
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="sparseloom-checkpoint-")
        sc.setCheckpointDir(folder)
    return df.checkpoint()


#: At most `2 * FREQUENT` answers of a lookup are sent to every task: keys that occur in more than one of `FREQUENT` rows.
FREQUENT = 1000


def look_up(rows: DataFrame, key: str, answers: DataFrame, count: str, total: int) -> DataFrame:
    """`rows` joined with the one row that `answers` has for their key, however often a key occurs.

    `count` (a column of `answers`, dropped here) says in how many rows the key occurs, of `total` in all. Keys above a
    thousandth of all rows, and so a bounded number of them, are answered by broadcast, where the rows lie; the
    others by an ordinary join, in which no key is large.
    """
    large = F.col(count) * FREQUENT > F.lit(total)
    frequent = answers.where(large).drop(count)
    rare = answers.where(~large).drop(count)
    flag = "_answered"
    met = rows.join(F.broadcast(frequent.withColumn(flag, F.lit(True))), key, "left")
    done = met.where(F.col(flag)).drop(flag)
    open_rows = met.where(F.col(flag).isNull()).select(*rows.columns)
    return done.unionByName(open_rows.join(rare, key))


def keep_rows(docs: DataFrame, text_col: str, keep: Callable[[list[str]], list[bool]]) -> DataFrame:
    """The rows, with all their columns, whose text `keep` approves; a null text counts as empty."""
    names = docs.columns
    at = names.index(text_col)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 1024):
                part = batch.slice(k, 1024)
                approved = keep([x or "" for x in part.column(at).to_pylist()])
                yield part.filter(pa.array(approved, pa.bool_()))

    return map_batches(docs, work, row_schema(docs))


def row_schema(df: DataFrame) -> str:
    """The frame's columns as a schema string, for work that hands whole rows on."""
    return ", ".join(f"`{n}` {t}" for n, t in df.dtypes)


def tokenizer_path(name: str) -> str:
    """Where the public vocabulary file lies on this machine (driver or executor)."""
    if os.path.sep in name:
        return name
    import public_tokenizers

    return public_tokenizers.path(name)

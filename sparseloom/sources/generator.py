"""A Python data source that makes graphs of any size in parallel, with a chosen skew."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .tables import ensure_importable, shared_folder

#: A prime below 2^31, so that products of two numbers below it fit into 64 bits.
PRIME = 2147483647


def scrambled(i, seed: int):
    """Numbers from 0 up to 1, a function of the counters i alone: a linear step, a square, a linear step."""
    x = (i % PRIME * 48271 + 1 + seed * 69621) % PRIME
    return (x * x % PRIME * 69621 + i) % PRIME / PRIME


class _Whole:
    """An array of whole numbers whose remainders keep the sign of the number, as they do in SQL."""

    def __init__(self, x):
        self.x = x

    def __mod__(self, n: int):
        import numpy as np

        return _Whole(np.fmod(self.x, n))

    def __mul__(self, y):
        return _Whole(self.x * getattr(y, "x", y))

    def __add__(self, y):
        return _Whole(self.x + getattr(y, "x", y))

    def __truediv__(self, y):
        return self.x / y


def edges_of(counters: DataFrame, vertices: int, skew: int = 1, seed: int = 42) -> DataFrame:
    """An edge for each row of a table: the generator's own for the counter `i` (whole, from 0) of the row."""
    share, src = scrambled(F.col("i"), 2 * seed), F.lit(float(vertices))
    for _ in range(skew):
        src = src * share
    dst = F.lit(float(vertices)) * scrambled(F.col("i"), 2 * seed + 1)
    return counters.select(F.floor(src).cast("long").alias("src"), F.floor(dst).cast("long").alias("dst"), F.lit(1).cast("long").alias("val"))


class EdgeGenerator(DataSource):
    """Options: vertices, edges, skew (a whole number; 1 is even, larger gathers edges at few vertices), seed, partitions.

    `counters`: a folder of Parquet files that all executors see, with whole numbers as their only column. An edge is then made for each of these, with the number `i`
    beside it, in place of the numbers from 0 up to `edges`; each file is a partition.
    """

    @classmethod
    def name(cls) -> str:
        return "edge_generator"

    def schema(self) -> str:
        return "src bigint, dst bigint, val bigint" + (", i bigint" if "counters" in self.options else "")

    def reader(self, schema) -> DataSourceReader:
        return _Reader({k: float(self.options.get(k, d)) for k, d in (("vertices", 1000), ("edges", 10000), ("skew", 1), ("seed", 42), ("partitions", 8))}, self.options.get("counters"))


class _Part(InputPartition):
    def __init__(self, number: int, file: str | None = None):
        self.number, self.file = number, file


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, float], counters: str | None = None):
        self.options, self.counters = options, counters

    def partitions(self) -> list[InputPartition]:
        if self.counters is None:
            return [_Part(i) for i in range(int(self.options["partitions"]))]
        from pyarrow import fs

        store, path = _located(self.counters)
        files = sorted(f.path for f in store.get_file_info(fs.FileSelector(path)) if f.base_name.endswith(".parquet"))
        return [_Part(i, f) for i, f in enumerate(files)] or [_Part(0)]

    def numbers(self, partition: _Part) -> Iterator:
        """The partition's counters, as Arrow arrays of bounded length."""
        import numpy as np
        import pyarrow as pa
        import pyarrow.parquet as pq

        if self.counters is None:
            o, parts = self.options, int(self.options["partitions"])
            first, end = (int(o["edges"]) * k // parts for k in (partition.number, partition.number + 1))
            for at in range(first, end, 100_000):
                yield pa.array(np.arange(at, min(end, at + 100_000)))
        elif partition.file is not None:
            with _located(self.counters)[0].open_input_file(partition.file) as held:
                for batch in pq.ParquetFile(held).iter_batches(100_000):
                    yield batch.column(0).cast(pa.int64())

    def read(self, partition: _Part) -> Iterator:
        import numpy as np
        import pyarrow as pa

        o = self.options
        for numbers in self.numbers(partition):
            missing = numbers.is_null().to_numpy(zero_copy_only=False)
            i = _Whole(numbers.fill_null(0).to_numpy(zero_copy_only=False))
            share, src = scrambled(i, 2 * int(o["seed"])), float(o["vertices"])
            for _ in range(int(o["skew"])):
                src = src * share
            dst = float(o["vertices"]) * scrambled(i, 2 * int(o["seed"]) + 1)
            made = [pa.array(np.floor(x).astype(np.int64), mask=missing) for x in (src, dst)] + [pa.array(np.ones(len(missing), np.int64))]
            names = ["src", "dst", "val"]
            if self.counters is not None:
                made, names = [*made, numbers], [*names, "i"]
            yield pa.RecordBatch.from_arrays(made, names)


def _located(folder: str):
    """The file system of a folder, and the folder's path in it."""
    from pyarrow import fs

    if folder.startswith("file:"):
        return fs.LocalFileSystem(), "/" + folder[5:].lstrip("/")
    return fs.FileSystem.from_uri(folder) if "://" in folder else (fs.LocalFileSystem(), folder)


def generated_edges(spark: SparkSession, **options) -> DataFrame:
    ensure_importable(spark)
    spark.dataSource.register(EdgeGenerator)
    reader = spark.read.format("edge_generator")
    for k, v in options.items():
        reader = reader.option(k, str(v))
    return reader.load()


def generated_edges_at(counters: DataFrame, **options) -> DataFrame:
    """(src, dst, val, i): the generator's edges of the different numbers in the column `i`, which go to it by way of the shared folder."""
    spark = counters.sparkSession
    folder = shared_folder(spark, "counters")
    counters.select(F.col("i").cast("long")).distinct().write.parquet(folder)
    return generated_edges(spark, counters=folder, **options)

"""Relational operators that users of the samplers need and Spark has no single call for."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources import graphs


def top_per_group(df: DataFrame, keys: Sequence[str], order: Sequence[Column], n: int) -> DataFrame:
    """The first n rows of each group (rn); each task prunes to n before the shuffle."""
    ranked = df.withColumn("rn", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)).cast("long"))
    return ranked.where(F.col("rn") <= n)


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with `previous`: the right row's `value` at the latest strictly earlier time of the key (largest value on ties)."""
    asked = left.select(key, time, F.lit(0).alias("known"), F.col(value).alias("row"), F.lit(None).cast(dict(right.dtypes)[value]).alias("given"))
    known = right.select(key, time, F.lit(1).alias("known"), F.col(value).alias("row"), F.col(value).alias("given"))
    window = Window.partitionBy(key).orderBy(time, "known", "row").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = asked.unionByName(known).withColumn("previous", F.last("given", ignorenulls=True).over(window))
    return found.where("known = 0").select(key, time, F.col("row").alias(value), "previous")


def interval_join(a: DataFrame, b: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs with b between a and `seconds` later, as aliases a and b: time slices make it an equi-join that spreads busy keys."""
    slot = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    left = a.withColumn("slot", F.explode(F.array(slot(F.col(time)), slot(F.col(time)) + 1))).alias("a")
    right = b.withColumn("slot", slot(F.col(time))).alias("b")
    same = (F.col(f"a.{key}") == F.col(f"b.{key}")) & (F.col("a.slot") == F.col("b.slot"))
    inside = F.col(f"b.{time}").between(F.col(f"a.{time}"), F.col(f"a.{time}") + F.expr(f"INTERVAL {seconds} SECONDS"))
    return left.join(right, same & inside)


def salted_sum(df: DataFrame, keys: Sequence[str], value: str, salts: int = 32) -> DataFrame:
    """Sum per key in two steps, so that a hot key's rows meet in `salts` tasks first."""
    partial = df.withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts))).groupBy(*keys, "salt").agg(F.sum(value).alias("part"))
    return partial.groupBy(*keys).agg(F.sum("part").alias("total"))


def sql_draw(t, spark: SparkSession) -> DataFrame:
    """The counter-based draw as an SQL function."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION draw52(seed BIGINT, k BIGINT) RETURNS BIGINT "
        "RETURN CAST(conv(substring(md5(concat_ws('|', CAST(seed AS STRING), CAST(k AS STRING))), 1, 13), 16, 10) AS BIGINT)"
    )
    t.register_views("part")
    return spark.sql("SELECT p_partkey, draw52(42, p_partkey) AS u FROM part")


def udtf_sample(t, spark: SparkSession, s: int) -> DataFrame:
    """Neighbour sampling as a table function, called from SQL for each adjacency row."""
    from pyspark.sql.functions import udtf

    class SampleNeighbors:
        def eval(self, nbrs: list, size: int, seed: int, batch: int, layer: int, row: int):
            import hashlib

            draw = lambda n: int(hashlib.md5(f"{seed}|{batch}|{layer}|{row}|{n}".encode()).hexdigest()[:13], 16)
            for rank, (_, n) in enumerate(sorted((draw(n), n) for n in nbrs)[:size]):
                yield n, rank + 1

    spark.udtf.register("sample_neighbors", udtf(SampleNeighbors, returnType="dst bigint, rank bigint"))
    from .matrix import to_rows

    to_rows(graphs.supplies_graph(t)).createOrReplaceTempView("adjacency")
    return spark.sql(f"SELECT a.src, s.dst, s.rank FROM adjacency a, LATERAL sample_neighbors(a.nbrs, {s}, 42, 0, 1, a.src) s")

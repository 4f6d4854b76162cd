"""Streams of edges: event files replayed, windows, de-duplication, joins, reservoirs, sampling on arrival."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rng import u52
from ..sources.tables import SCHEMAS, shared_folder


def edge_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int | None = None, delay: str = "10 minutes") -> DataFrame:
    """The events table as a stream with a watermark."""
    reader = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events*.parquet")
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(sf_dir).withWatermark("ts", delay)


def replay(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a finite stream to its end and give what it wrote.

    `append` goes to files in the shared folder. `complete` and `update` write every micro-batch to its own
    folder; the last one holds the whole result of `complete`. Rows of `update` carry their micro-batch (column `trigger`), and a
    later one replaces what an earlier one said.
    """
    spark = stream.sparkSession
    path = shared_folder(spark, "stream")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{path}/out")
    last: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        tagged = batch if mode == "complete" else batch.withColumn("trigger", F.lit(number).cast("long"))
        tagged.write.mode("overwrite").parquet(f"{path}/out/{number}")
        last.append(number)

    q = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    if not last:
        empty = spark.createDataFrame([], stream.schema)
        return empty if mode == "complete" else empty.withColumn("trigger", F.lit(0).cast("long"))
    return spark.read.parquet(*([f"{path}/out/{last[-1]}"] if mode == "complete" else [f"{path}/out/{n}" for n in sorted(set(last))]))


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    return _windowed(stream, F.window("ts", width))


def sliding(stream: DataFrame, width: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    return _windowed(stream, F.window("ts", width, step))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def _windowed(stream: DataFrame, window) -> DataFrame:
    counted = stream.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("start"), "event_type", "n")


def dedup(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def view_purchase_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Views with purchases of the same user within ten minutes; both sides' state is bounded by watermarks."""
    a = edge_stream(spark, sf_dir).where("event_type = 'view'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = edge_stream(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return a.join(b, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 10 MINUTES")).select("a", "b")


def reservoir(stream: DataFrame, s: int = 5, seed: int = 42) -> DataFrame:
    """Per user, the `s` events with the smallest draws: order-free, so equal to a batch race over everything."""
    keyed = stream.select("user_id", "event_id", u52(seed, 0, 1, F.col("user_id"), F.col("event_id")).alias("key"))

    def keep(key: tuple, frames: Iterator, state) -> Iterator:
        import pandas as pd

        held = list(zip(*state.get)) if state.exists else []
        for frame in frames:
            held = sorted({*held, *zip(frame["key"].tolist(), frame["event_id"].tolist())})[:s]
        state.update(tuple(list(x) for x in zip(*held)))
        yield pd.DataFrame({"user_id": key[0], "event_id": [e for _, e in held], "rank": range(1, len(held) + 1), "size": len(held)})

    return keyed.groupBy("user_id").applyInPandasWithState(
        keep, "user_id long, event_id long, rank long, size long", "keys array<long>, events array<long>", "update", "NoTimeout"
    )


def last_state(updates: DataFrame, key: str) -> DataFrame:
    """Of what a stream in `update` mode wrote, the rows of each key's last micro-batch."""
    newest = updates.groupBy(key).agg(F.max("trigger").alias("trigger"))
    return updates.join(newest, [key, "trigger"]).drop("trigger")


def on_arrival(stream: DataFrame, sample: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Each micro-batch of roots is sampled in bulk as it arrives."""
    spark = stream.sparkSession
    path = shared_folder(spark, "arrivals")

    def work(batch: DataFrame, number: int) -> None:
        sample(batch).write.mode("overwrite").parquet(f"{path}/out/{number}")

    q = stream.writeStream.foreachBatch(work).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{path}/out/*")


def late_rows(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    """Micro-batches of a replayed windowed count, with the rows that came behind the watermark."""
    spark = stream.sparkSession
    path = shared_folder(spark, "late")
    q = tumbling(stream, width).writeStream.format("noop").outputMode("append").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    rows = [(p["batchId"], p["numInputRows"], sum(o["numRowsDroppedByWatermark"] for o in p["stateOperators"])) for p in q.recentProgress]
    return spark.createDataFrame(rows, "batch long, rows long, dropped long")

"""Driver queries of the streaming operators; each is compared with its batch counterpart."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rng import u52_sql
from ..operators.framework import SampleSpec, sample_minibatches
from ..sources import graphs, tables
from ..streaming import edges as stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "stream_ingest": lambda s, d: stream.replay(stream.edge_stream(s, d).select(F.col("user_id").alias("src"), F.col("event_type").alias("dst"))).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")),
    "stream_tumbling": lambda s, d: stream.replay(stream.tumbling(stream.edge_stream(s, d)), "complete"),
    "stream_sliding": lambda s, d: stream.replay(stream.sliding(stream.edge_stream(s, d)), "complete"),
    "stream_session": lambda s, d: stream.replay(stream.sessions(stream.edge_stream(s, d)), "complete"),
    "stream_dedup": lambda s, d: stream.replay(stream.dedup(stream.edge_stream(s, d))),
    "stream_join": lambda s, d: stream.replay(stream.view_purchase_join(s, d)),
    "stream_late": lambda s, d: stream.late_rows(stream.edge_stream(s, d)).agg(F.sum("rows").alias("rows"), F.sum("dropped").alias("dropped")),
}


def _reservoir(spark: SparkSession, d: str, files_per_trigger: int | None = None) -> DataFrame:
    """The last state of each user."""
    out = stream.replay(stream.reservoir(stream.edge_stream(spark, d, files_per_trigger)), "update")
    return stream.last_state(out, "user_id").select("user_id", "event_id", "rank")


def _arrival(spark: SparkSession, d: str) -> DataFrame:
    bought = tables.durable(graphs.bipartite_graph(tables.load(spark, d)))

    def sample(batch: DataFrame) -> DataFrame:
        roots = batch.select(F.lit(0).cast("long").alias("batch"), F.col("user_id").alias("pos"), F.col("user_id").alias("v")).distinct()
        return sample_minibatches(bought, roots, SampleSpec(fanout=(3,), seed=42))

    return stream.on_arrival(stream.edge_stream(spark, d), sample)


QUERIES["stream_reservoir"] = _reservoir
QUERIES["stream_bulk_sampling"] = _arrival

_KEY = u52_sql("42", "0", "1", "user_id", "event_id")
_DRAW = u52_sql("42", "0", "1", "src", "dst")
ORACLES: dict[str, str] = {
    "stream_ingest": "SELECT user_id AS src, event_type AS dst, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_tumbling": "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT time_bucket(INTERVAL 15 MINUTE, ts) - to_minutes(15 * k) AS start, event_type, count(*) AS n FROM events, range(4) AS g(k) GROUP BY 1, 2",
    "stream_session": (
        "WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
        "b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM a) "
        'SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", count(*) AS n FROM b GROUP BY user_id, session'
    ),
    "stream_dedup": "SELECT DISTINCT event_id, user_id FROM events",
    "stream_join": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE",
    "stream_late": "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS dropped FROM events",
    "stream_reservoir": f"SELECT user_id, event_id, rank FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY {_KEY}, event_id) AS rank FROM events) WHERE rank <= 5",
    "stream_bulk_sampling": (
        "WITH e AS (SELECT DISTINCT o_custkey AS src, l_partkey AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey IN (SELECT user_id FROM events)) "
        f"SELECT CAST(0 AS BIGINT) AS batch, CAST(1 AS BIGINT) AS layer, src AS row_id, src, dst, rank FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY {_DRAW}, dst) AS rank FROM e) WHERE rank <= 3"
    ),
}

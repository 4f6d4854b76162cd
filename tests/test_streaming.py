"""Streams in several triggers against their batch counterparts; rows that come too late."""

import os
import time

import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from sparseloom.plans import streaming_queries
from sparseloom.streaming import edges as stream


@pytest.fixture(scope="module")
def in_parts(sf, tmp_path_factory):
    """The events in three files of the same folder."""
    folder = tmp_path_factory.mktemp("events")
    whole = pq.read_table(f"{sf}/events.parquet")
    for k in range(3):
        pq.write_table(whole.take(pa.array(range(k, whole.num_rows, 3))), folder / f"events{k}.parquet")
    return str(folder)


def test_the_reservoir_holds_its_last_state_only(spark, sf, in_parts):
    once = {tuple(r) for r in streaming_queries.QUERIES["stream_reservoir"](spark, sf).collect()}
    thrice = {tuple(r) for r in streaming_queries._reservoir(spark, in_parts, files_per_trigger=1).collect()}
    assert once == thrice and max(r[2] for r in thrice) <= 5


def test_late_rows_are_counted(spark, sf, tmp_path):
    """The newest events come first; a row is late when it is behind the watermark of the trigger before the last."""
    whole = pq.read_table(f"{sf}/events.parquet").sort_by("ts")
    third, now = whole.num_rows // 3, time.time()
    for k, first in enumerate((2 * third, third, 0)):
        pq.write_table(whole.slice(first, third if k else None), tmp_path / f"events{k}.parquet")
        os.utime(tmp_path / f"events{k}.parquet", (now - 60 + k, now - 60 + k))
    late = stream.late_rows(stream.edge_stream(spark, str(tmp_path), 1)).agg({"dropped": "sum", "rows": "sum"}).first().asDict()
    assert late["sum(dropped)"] > 0 and late["sum(rows)"] == whole.num_rows
    at_once = stream.late_rows(stream.edge_stream(spark, str(tmp_path))).agg({"dropped": "sum"}).first()[0]
    assert at_once == 0

"""Streams give what the batch gives."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import SF
from thinfsm.plans.dictionary import word_matchers
from thinfsm.sources.ladder import read_payload_files
from thinfsm.streaming import flows


@pytest.mark.parametrize("name", ["stream_windows", "stream_dedupe", "stream_interval_join", "stream_static_join", "stream_late", "stream_rule_update", "stream_flow_match"])
def test_stream_equals_sql(spark, same, name):
    same(flows.QUERIES[name](spark, SF), flows.ORACLES[name])


def test_idle_flows_are_closed_and_start_anew(spark):
    """A word split over fragments is found while the flow lives; after it was idle the state is gone."""
    rows = [(1, 0, "he", 0, 0), (2, 0, "he", 0, 0), (1, 1, "llo", 1, 1), (3, 0, "x", 90, 2), (3, 1, "x", 95, 3), (2, 1, "llo", 96, 4), (3, 2, "x", 200, 5), (3, 3, "x", 201, 6)]
    d = spark.createDataFrame(rows, "flow long, seq long, text string, hour int, step int")
    d = d.withColumn("ts", F.expr("timestamp'2024-01-01 00:00:00' + make_dt_interval(0, hour)")).drop("hour")
    m = word_matchers(iter([b"hello"]))[0][1]
    out = flows.drained(flows.flow_states(flows.dealt(spark, d, "step", 7).withWatermark("ts", "1 hour"), m, "flow", "seq", "text", time_col="ts", idle_ms=3_600_000), "update").toPandas()
    assert out[out.flow_id == 1]["matches"].max() == 1  # in one life
    assert out[out.flow_id == 2]["matches"].max() == 0 and out[(out.flow_id == 2) & ~out.closed]["length"].tolist().count(3) == 1  # the second life begins at the start state
    assert set(out[out.closed].flow_id) >= {1, 2}


def test_payload_files(spark, tmp_path):
    (tmp_path / "a").mkdir()
    (tmp_path / "a" / "x.bin").write_bytes(b"\x00he\xff")
    (tmp_path / "y.bin").write_bytes(b"zz")
    got = {r["path"].rsplit("/", 1)[1]: bytes(r["body"]) for r in read_payload_files(spark, str(tmp_path)).collect()}
    assert got == {"x.bin": b"\x00he\xff", "y.bin": b"zz"}
    from thinfsm.match import match

    m = word_matchers(iter([b"he"]))[0][1]
    runs = match(read_payload_files(spark, str(tmp_path)), m).collect()
    assert sorted((r["length"], r["matches"]) for r in runs) == [(2, 0), (4, 1)] and np.sum([r["hops"] for r in runs]) >= 0

"""Streams: matchers over payloads and flows, windows of counts, late and repeated rows.

Queries run the stream over files with the ``availableNow`` trigger and return what it wrote;
the batch form of each gives the same rows.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..match import Matcher, Matchers, match
from ..model import table
from ..plans.dictionary import _matcher, word_matchers
from ..scratch import shared_dir

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


def stream(spark: SparkSession, sf_dir: str, name: str, files: int = 1) -> DataFrame:
    """The table (a file or a folder, hence the glob) as a file stream."""
    path, schema = f"{sf_dir}/{name}.parque[t]", spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def dealt(spark: SparkSession, rows: DataFrame, step: str, steps: int) -> DataFrame:
    """The rows as a file stream in ``steps`` micro-batches: those of step 0 arrive first, and a trigger takes one step's folder."""
    path = f"{shared_dir(spark)}/stream/{uuid.uuid4().hex}/in"
    for k in range(steps):
        rows.filter(F.col(step) == k).drop(step).write.parquet(f"{path}/step={k}")
    jvm = spark._jvm.org.apache.hadoop.fs.Path(path)
    listed = jvm.getFileSystem(spark._jsc.hadoopConfiguration())
    most = max(sum(1 for f in listed.listStatus(spark._jvm.org.apache.hadoop.fs.Path(f"{path}/step={k}")) if f.getPath().getName().endswith(".parquet")) for k in range(steps))
    return spark.readStream.schema(rows.drop(step).schema.add("step", "integer")).option("maxFilesPerTrigger", most).parquet(path)


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to the end of its input and read what it wrote.  'complete' and 'update' keep the last version of each batch."""
    spark, base = df.sparkSession, f"{shared_dir(df.sparkSession)}/stream/{uuid.uuid4().hex}"
    schema = df.schema

    def put(batch: DataFrame, epoch: int):
        batch.write.mode("overwrite").parquet(f"{base}/out/epoch={epoch}")

    q = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
    q.awaitTermination()
    out = spark.read.schema(schema.add("epoch", "long")).parquet(f"{base}/out")
    if mode == "complete":
        last = out.agg(F.max("epoch").alias("last"))
        out = out.join(F.broadcast(last), F.col("epoch") == F.col("last")).drop("last")
    return out.drop("epoch")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS hour, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_windows(spark, sf_dir):
    """Tumbling windows over the event stream."""
    e = stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    w = e.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(w, "complete").select(F.col("w.start").cast("timestamp_ntz").alias("hour"), "event_type", "n")


@query("SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS begins, count(*) AS n FROM events, range(2) t(k) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    e = stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    w = e.groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return drained(w, "complete").select(F.col("w.start").cast("timestamp_ntz").alias("begins"), "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS begins, count(*) AS n FROM s GROUP BY user_id, k")
def stream_sessions(spark, sf_dir):
    e = stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    w = e.groupBy(F.session_window("ts", "2 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(w, "complete").select("user_id", F.col("w.start").cast("timestamp_ntz").alias("begins"), "n")


@query("SELECT DISTINCT event_id FROM events")
def stream_dedupe(spark, sf_dir):
    """The stream with every row sent twice, repeats dropped within the watermark."""
    e = stream(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).withWatermark("ts", "365 days")
    return drained(twice.dropDuplicatesWithinWatermark(["event_id"])).select("event_id")


@query("""WITH d AS (SELECT ts, event_id % 10 = 0 AS second, event_id % 20 = 0 AS third FROM events), w AS (SELECT max(ts) - INTERVAL 1 DAY AS mark FROM d WHERE NOT second),
t AS (SELECT ts, NOT third OR date_trunc('day', ts) + INTERVAL 1 DAY > mark AS kept FROM d, w) SELECT date_trunc('day', ts) AS day, count(*) FILTER (kept) AS n FROM t GROUP BY 1 HAVING count(*) FILTER (kept) > 0""")
def stream_late(spark, sf_dir):
    """Every 20th event arrives in a third batch; those whose day had ended a day before the newest event of the first are late and dropped (a batch goes by the watermark of the one before)."""
    step = F.when(F.col("event_id") % 20 == 0, 2).when(F.col("event_id") % 10 == 0, 1).otherwise(0)
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), step.alias("step"))
    w = dealt(spark, e, "step", 3).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return drained(w, "update").groupBy(F.col("w.start").cast("timestamp_ntz").alias("day")).agg(F.max("n").alias("n"))


_VERSIONS = "v AS (SELECT w, (row_number() OVER (ORDER BY w) - 1) % 2 AS version FROM (SELECT DISTINCT p_name AS w FROM part WHERE p_name <> ''))"


@query(f"WITH {_VERSIONS} SELECT page_id, CAST(page_id % 2 AS BIGINT) AS version, bool_or(contains(html, w)) AS accepts FROM pages JOIN v ON v.version <= page_id % 2 GROUP BY 1, 2")
def stream_rule_update(spark, sf_dir):
    """Pages in two batches; before the second the other half of the names joins the rules, and a new delayed automaton takes over."""
    w = Window.orderBy("w")  # the rules
    words = table(spark, sf_dir, "part").select(F.col("p_name").alias("w")).filter("w <> ''").distinct().select("w", ((F.row_number().over(w) - 1) % 2).alias("version"))
    pages = table(spark, sf_dir, "pages").withColumn("step", (F.col("page_id") % 2).cast("int"))
    rules_at = lambda epoch: words.filter(F.col("version") <= epoch).select("w")
    return updating_match(dealt(spark, pages, "step", 2), rules_at, "page_id", "html").select(F.col("payload_id").alias("page_id"), "version", "accepts")


def updating_match(payloads: DataFrame, rules_at, id_col: str, text_col: str) -> DataFrame:
    """RUNS with the version of the rules: before each micro-batch the rules are looked up, and only if they changed a new matcher is made and sent.

    rules_at: batch number to a table of words (w).  A payload is matched by one version from end to end."""
    spark, at = payloads.sparkSession, f"{shared_dir(payloads.sparkSession)}/stream/{uuid.uuid4().hex}"
    now: dict = {"mark": None, "version": -1, "matcher": None}

    def put(batch: DataFrame, epoch: int) -> None:
        words = rules_at(epoch)
        mark = tuple(words.agg(F.count("*"), F.sum(F.xxhash64("w").cast("decimal(38,0)"))).first())
        if mark != now["mark"]:
            parts = [m for _, m, _ in word_matchers(r[0].encode() for r in words.distinct().orderBy("w").toLocalIterator())]
            now.update(mark=mark, version=now["version"] + 1, matcher=parts[0] if len(parts) == 1 else Matchers(parts))
        match(batch, now["matcher"], id_col=id_col, text_col=text_col).withColumn("version", F.lit(now["version"]).cast("long")).write.mode("overwrite").parquet(f"{at}/out/epoch={epoch}")

    payloads.writeStream.foreachBatch(put).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{at}/out").drop("epoch")


@query("SELECT a.event_id AS click_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE")
def stream_interval_join(spark, sf_dir):
    """Stream-stream join with time bounds on both sides' watermarks."""
    e = lambda: stream(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    a = e().filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    b = e().filter("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "1 hour")
    return drained(a.join(b, F.expr("u = u2 AND t2 > t AND t2 <= t + INTERVAL 5 MINUTES"))).select("click_id", "error_id")


@query("SELECT doc_id FROM documents JOIN labels USING (doc_id) WHERE quality = 1")
def stream_static_join(spark, sf_dir):
    d = stream(spark, sf_dir, "documents").select("doc_id")
    return drained(d.join(table(spark, sf_dir, "labels").filter("quality = 1").select("doc_id"), "doc_id")).select("doc_id")


@query("SELECT DISTINCT doc_id FROM documents JOIN (SELECT DISTINCT text AS w FROM benchmark WHERE text <> '') b ON contains(documents.text, w)")
def stream_match(spark, sf_dir):
    """Stateless matcher over a stream of payloads: documents that hold a whole passage."""
    runs = match(stream(spark, sf_dir, "documents"), _matcher(spark, sf_dir, "benchmark", "text"), id_col="doc_id", text_col="text")
    return drained(runs.filter("accepts")).select(F.col("payload_id").alias("doc_id"))


FLOW = "flow_id long, state array<long>, length long, hops long, matches long, closed boolean"


def flow_states(fragments: DataFrame, matcher: Matcher | Matchers, flow_col: str, seq_col: str, text_col: str, *, time_col: str | None = None, idle_ms: int = 0) -> DataFrame:
    """The automaton's state (one for each group of rules) survives between fragments of a flow.

    Fragments of a batch are taken in order of their number; one output row per flow and batch.
    With ``time_col`` (with a watermark) the state of a flow that was idle for ``idle_ms`` beyond
    the watermark is given out as closed and forgotten; should the flow come back, it starts anew."""

    groups = len(matcher.parts) if isinstance(matcher, Matchers) else 1

    def row(key, at, length, hops, found, closed) -> pd.DataFrame:
        return pd.DataFrame({"flow_id": [key[0]], "state": [at], "length": [length], "hops": [hops], "matches": [found], "closed": [closed]})

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        at, length, hops, found, newest = state.get if state.exists else ([0] * groups, 0, 0, 0, 0)
        if state.hasTimedOut:
            state.remove()
            yield row(key, list(at), length, hops, found, True)
            return
        part = pd.concat(list(frames)).sort_values("seq")
        for text in part["text"]:
            raw = (text or "").encode()
            got = matcher.run([raw], np.array(at, np.int64))
            at, length, hops, found = np.atleast_1d(got["end_state"][0]).tolist(), length + len(raw), hops + int(got["hops"][0]), found + int(got["matches"][0])
        newest = max(int(newest), int(part["ms"].max()))
        state.update((at, length, hops, found, newest))
        if time_col:
            state.setTimeoutTimestamp(max(newest, state.getCurrentWatermarkMs()) + max(1, idle_ms))
        yield row(key, at, length, hops, found, False)

    kept = [F.col(time_col)] if time_col else []
    rows = fragments.select(F.col(flow_col).cast("long").alias("flow_id"), F.col(seq_col).alias("seq"), F.col(text_col).alias("text"), (F.unix_millis(F.col(time_col)) if time_col else F.lit(0).cast("long")).alias("ms"), *kept)
    timeout = GroupStateTimeout.EventTimeTimeout if time_col else GroupStateTimeout.NoTimeout
    return rows.groupBy("flow_id").applyInPandasWithState(step, FLOW, "state array<long>, length long, hops long, matches long, newest long", "update", timeout)


def _turns(spark, sf_dir):
    """Conversations as a stream in which the second turns and the rest come in batches of their own, so flows cross batches."""
    c = table(spark, sf_dir, "conversations")
    first = c.groupBy("conv_id").agg(F.min("turn").alias("t0"))
    rows = c.join(first, "conv_id").select("conv_id", "turn", "text", F.least(F.col("turn") - F.col("t0"), F.lit(2)).cast("int").alias("step"))
    return dealt(spark, rows, "step", 3)


_NAMES = "n AS (SELECT DISTINCT p_name AS w FROM part WHERE p_name <> ''), c AS (SELECT conv_id AS flow_id, string_agg(coalesce(text, ''), '' ORDER BY turn) AS t FROM conversations GROUP BY 1)"
_FLOWS = f"WITH {_NAMES} SELECT flow_id, CAST(strlen(any_value(t)) AS BIGINT) AS length, CAST(sum((length(t) - length(replace(t, w, ''))) / length(w)) AS BIGINT) AS matches FROM c, n GROUP BY 1"


@query(_FLOWS)
def stream_flow_match(spark, sf_dir):
    m = _matcher(spark, sf_dir, "part", "p_name")
    out = drained(flow_states(_turns(spark, sf_dir), m, "conv_id", "turn", "text"), "update")
    return out.groupBy("flow_id").agg(F.max("length").alias("length"), F.max("matches").alias("matches"))


@query()
def stream_idle_flows(spark, sf_dir):
    """Events of a user as a flow of their types; users that are idle for a day beyond the watermark are closed and their state is dropped."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", F.concat("event_type", F.lit(" ")).alias("text"), F.col("ts").cast("timestamp").alias("ts"))
    span = e.agg(F.min("ts").alias("lo"), F.max("ts").alias("hi"))
    third = F.least(F.floor(3 * (F.unix_micros("ts") - F.unix_micros("lo")) / (F.unix_micros("hi") - F.unix_micros("lo") + 1)), F.lit(2)).cast("int")
    rows = e.join(F.broadcast(span)).withColumn("step", third).drop("lo", "hi")
    m = word_matchers(iter([b"click ", b"error "]))[0][1]
    out = drained(flow_states(dealt(spark, rows, "step", 3).withWatermark("ts", "1 hour"), m, "user_id", "event_id", "text", time_col="ts", idle_ms=86_400_000), "update")
    return out.groupBy("closed").agg(F.count("*").alias("rows"), F.count_distinct("flow_id").alias("flows"))


@query(_FLOWS)
def flow_match(spark, sf_dir):
    """Batch form of stream_flow_match: each flow's fragments put together in order."""
    m = _matcher(spark, sf_dir, "part", "p_name")
    whole = table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), "").alias("text"))
    return match(whole, m, id_col="conv_id", text_col="text").select(F.col("payload_id").alias("flow_id"), "length", "matches")

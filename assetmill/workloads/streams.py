"""Structured Streaming twins of the event workloads, run to the end of their input.

Each reads the event file as a stream, writes Parquet under a checkpoint in the shared folder and returns
what the sink holds, which equals the batch query's rows.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor
from pyspark.sql.types import IntegerType

from assetmill.plans.scratch import Scratch
from assetmill.plans.ship import ship
from assetmill.sources.tables import table


def _stream(spark: SparkSession, d: str) -> DataFrame:
    schema = table(spark, d, "events").schema
    return spark.readStream.schema(schema).parquet(f"{d}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def _finish(spark: SparkSession, df: DataFrame, tag: str, mode: str = "append") -> DataFrame:
    with Scratch(spark, tag) as s:
        out = s.path("sink")
        if mode == "append":
            q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", s.path("log")).trigger(availableNow=True).start()
        else:  # the whole result of each batch replaces the one before, so a repeated batch does no harm
            q = df.writeStream.outputMode(mode).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(out)).option("checkpointLocation", s.path("log")).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(out)


def tumbling(spark, d):
    g = _stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("event_type") == "error").cast("long")).alias("failed"))
    return _finish(spark, g.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "failed"), "st-tumbling", "complete")


def sliding(spark, d):
    g = _stream(spark, d).groupBy(F.window("ts", "2 hours", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return _finish(spark, g.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n"), "st-sliding", "complete")


def dedup(spark, d):
    g = _stream(spark, d).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return _finish(spark, g.select("event_id", "user_id"), "st-dedup")


def static_join(spark, d):
    c = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    g = _stream(spark, d).where("event_type = 'purchase'").join(c, F.col("user_id") == F.col("c_custkey"))
    return _finish(spark, g.select("event_id", "c_mktsegment"), "st-static")


def stream_join(spark, d):
    a = _stream(spark, d).where("event_type = 'error'").select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("e1")).withWatermark("t1", "1 hour")
    b = _stream(spark, d).where("event_type = 'signup'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("e2")).withWatermark("t2", "1 hour")
    return _finish(spark, a.join(b, F.expr("u1 = u2 AND t1 >= t2 AND t1 <= t2 + INTERVAL 1 HOUR")).select("e1", "e2"), "st-join")


def session(spark, d):
    """Sessions of a user that end after 30 minutes without an event."""
    g = _stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return _finish(spark, g.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n"), "st-session", "complete")


def _tally(key, batches, state):
    """Running counts of one user; the state is two numbers."""
    n, failed = state.get if state.exists else (0, 0)
    for b in batches:
        n, failed = n + len(b), failed + int((b["event_type"] == "error").sum())
    state.update((n, failed))
    import pandas as pd

    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "failed": [failed]})


def user_state(spark, d):
    """Events and failures of each user by state kept between batches. A batch's rows go to a folder of its own
    number, so a repeated batch replaces itself; the latest row of a user has the largest count."""
    ship(spark)
    rows = _stream(spark, d).select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(_tally, "user_id long, n long, failed long", "n long, failed long", "update", "NoTimeout")
    with Scratch(spark, "st-state") as s:
        out = s.path("sink")
        q = rows.writeStream.outputMode("update").foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{out}/batch={i}")).option("checkpointLocation", s.path("log")).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(rows.schema).parquet(out).groupBy("user_id").agg(F.max("n").alias("n"), F.max("failed").alias("failed"))


class LastSuccess(StatefulProcessor):
    """Of each bucket of shapes the last fetch that succeeded, as state of one row; what a failed fetch takes."""

    def init(self, handle):
        self.kept = handle.getValueState("kept", "ts timestamp, event_id long, value double")

    def handleInputRows(self, key, rows, timerValues):
        import pandas as pd

        best = self.kept.get() if self.kept.exists() else None
        for batch in rows:
            good = batch[batch["event_type"] != "error"]
            if len(good):
                last = good.sort_values(["ts", "event_id"]).iloc[-1]
                now = (last["ts"], int(last["event_id"]), float(last["value"]))
                if best is None or (now[0], now[1]) > (pd.Timestamp(best[0]).tz_localize(None) if pd.Timestamp(best[0]).tzinfo else pd.Timestamp(best[0]), best[1]):
                    best = now
        if best is not None:
            self.kept.update((pd.Timestamp(best[0]).to_pydatetime(), best[1], best[2]))
            yield pd.DataFrame({"shape": [key[0]], "event_id": [best[1]], "value": [best[2]]})

    def close(self):
        pass


ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def refresh(spark, d):
    """The placeholder of each bucket after all fetches, kept by state that a new success replaces."""
    ship(spark)
    at, before = "spark.sql.streaming.stateStore.providerClass", None
    before = spark.conf.get(at)
    rows = _stream(spark, d).select(F.pmod("user_id", F.lit(7)).alias("shape"), "ts", "event_id", "event_type", "value")
    out = rows.groupBy("shape").transformWithStateInPandas(LastSuccess(), "shape long, event_id long, value double", "update", "None")
    try:
        spark.conf.set(at, ROCKS)  # the store that this operator needs, for this query only
        with Scratch(spark, "st-refresh") as s:
            sink = s.path("sink")
            q = out.writeStream.outputMode("update").foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{sink}/batch={i}")).option("checkpointLocation", s.path("log")).trigger(availableNow=True).start()
            q.awaitTermination()
            last = spark.read.schema(out.schema.add("batch", IntegerType())).parquet(sink)
    finally:
        spark.conf.set(at, before)
    return last.groupBy("shape").agg(F.max_by(F.struct("event_id", "value"), "batch").alias("x")).select("shape", "x.event_id", F.round("x.value", 6).alias("value"))


def late_rows(spark, d):
    """Rows that arrive after the watermark has passed their hour: two batches, the second with rows a day old, and
    what the query's own progress says it dropped."""
    e = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    newest = e.agg(F.max("ts").alias("newest"))
    with Scratch(spark, "st-late") as s:
        feed = s.path("feed")
        e.coalesce(1).write.parquet(f"{feed}/batch=0")
        read = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{feed}/batch=*")
        hours = read.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))

        def drain():
            q = hours.writeStream.outputMode("append").format("parquet").option("path", s.path("sink")).option("checkpointLocation", s.path("log")).trigger(availableNow=True).start()
            q.awaitTermination()
            return sum(int(o["numRowsDroppedByWatermark"]) for p in q.recentProgress for o in json.loads(p.json if isinstance(p.json, str) else json.dumps(p))["stateOperators"])

        before = drain()
        e.join(newest).where("ts > newest - INTERVAL 10 MINUTES").select("event_id", (F.col("ts") - F.expr("INTERVAL 1 DAY")).alias("ts")).coalesce(1).write.parquet(f"{feed}/batch=1")
        return spark.createDataFrame([(before, drain())], "on_time long, late long")


QUERIES = {
    "st_placeholder": (refresh, "SELECT user_id % 7 AS shape, arg_max(event_id, (ts, event_id)) AS event_id, round(arg_max(value, (ts, event_id)), 6) AS value FROM events WHERE event_type <> 'error' GROUP BY 1"),
    "st_late_rows": (late_rows, None),
    "st_session": (session, "WITH g AS (SELECT user_id, ts, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 30 MINUTE)::INTEGER AS same FROM events), k AS (SELECT *, sum(1 - coalesce(same, 0)) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM k GROUP BY user_id, k"),
    "st_user_state": (user_state, "SELECT user_id, count(*) AS n, count(*) FILTER (event_type = 'error') AS failed FROM events GROUP BY 1"),
    "st_tumbling": (tumbling, "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, count(*) AS n, count(*) FILTER (event_type = 'error') AS failed FROM events GROUP BY 1"),
    "st_sliding": (sliding, "SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start, count(*) AS n FROM events, range(4) r(k) GROUP BY 1"),
    "st_dedup": (dedup, "SELECT DISTINCT event_id, user_id FROM events"),
    "st_join_static": (static_join, "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey WHERE event_type = 'purchase'"),
    "st_join_stream": (stream_join, "SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'signup' AND a.ts BETWEEN b.ts AND b.ts + INTERVAL 1 HOUR"),
}

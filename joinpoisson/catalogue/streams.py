"""Queries of the streaming operators; each runs to the end of its input."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.catalogue.registry import add
from joinpoisson.functions.rng import u01_sql
from joinpoisson.plans.storage import shared_dir
from joinpoisson.sources.workloads import WEIGHTS
from joinpoisson.streaming import windows

SEED, PARTS = 7, 3


def _events(s, d) -> DataFrame:
    return s.read.parquet(f"{d}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")


def _stream(s, d, df: DataFrame | None = None) -> DataFrame:
    df = _events(s, d) if df is None else df
    return windows.read(s, windows.slices(s, df, PARTS, "event_id"), df.schema)


def _register() -> None:
    add("stream_filter_append", lambda s, d: windows.finish(_stream(s, d).where("value > 50").select("event_id", "value")), "SELECT event_id, value FROM events WHERE value > 50")
    micros = lambda df: df.select(*[F.unix_micros("start").alias("start_us") if c == "start" else c for c in df.columns])
    add("stream_tumbling", lambda s, d: micros(windows.finish(windows.tumbling(_stream(s, d)), "complete")), "SELECT CAST(epoch_us(date_trunc('hour', ts)) AS BIGINT) AS start_us, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
    add("stream_sliding", lambda s, d: micros(windows.finish(windows.sliding(_stream(s, d)), "complete")), "SELECT CAST(epoch_us(h) AS BIGINT) AS start_us, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY 1")
    gaps = "SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"
    add("stream_session", lambda s, d: micros(windows.finish(windows.sessions(_stream(s, d)), "complete")), f"WITH g AS ({gaps}), k AS (SELECT *, sum(first) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start_us, CAST(count(*) AS BIGINT) AS n FROM k GROUP BY user_id, k")
    add("stream_watermark_late", lambda s, d: micros(windows.finish(windows.tumbling(_stream(s, d).withWatermark("ts", "400 days"), "1 day"), "complete")), "SELECT CAST(epoch_us(date_trunc('day', ts)) AS BIGINT) AS start_us, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")

    def dedup(s, d):
        events = _events(s, d)
        again = events.unionByName(events.where("event_id % 3 = 0"))
        return windows.finish(_stream(s, d, again).withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))

    add("stream_dedup", dedup, "SELECT event_id FROM events")

    def static(s, d):
        users = s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
        return windows.finish(_stream(s, d).join(users, "user_id").select("event_id", "c_mktsegment"))

    add("stream_static_join", static, "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")

    def both(s, d):
        a = _stream(s, d).where("event_type = 'click'").select("event_id", "user_id", "ts").withWatermark("ts", "400 days")
        b = _stream(s, d).where("event_type <> 'click'").select(F.col("event_id").alias("other_id"), F.col("user_id").alias("other"), F.col("ts").alias("other_ts")).withWatermark("other_ts", "400 days")
        near = (F.col("user_id") == F.col("other")) & (F.col("other_ts") >= F.col("ts")) & (F.col("other_ts") <= F.col("ts") + F.expr("INTERVAL 6 HOURS"))
        return windows.finish(a.join(b, near).select("event_id", "other_id"))

    add("stream_stream_join", both, "SELECT a.event_id, b.event_id AS other_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type <> 'click' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR")
    coin = u01_sql(str(SEED), "0", "'coin'", "event_id")
    add("stream_sample_bernoulli", lambda s, d: windows.finish(windows.sample_stream(_stream(s, d), WEIGHTS["evt"], SEED).select("event_id")), f"SELECT event_id FROM events WHERE {coin} < {WEIGHTS['evt']}")

    def stateful(s, d):
        seen = windows.finish(windows.running_counts(_stream(s, d)), "update")
        return seen.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("total", "n"), 4).alias("total"))

    add("stream_stateful_counts", stateful, "SELECT user_id, CAST(count(*) AS BIGINT) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")

    def state_by_batch(s, d):
        home = f"{shared_dir(s)}/batches-{uuid.uuid4().hex}"

        def step(rows: DataFrame, batch: int) -> None:
            rows.groupBy("event_type").agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{home}/batch={batch}")

        query = _stream(s, d).writeStream.foreachBatch(step).option("checkpointLocation", f"{home}-log").trigger(availableNow=True).start()
        query.awaitTermination()
        return s.read.parquet(home).groupBy("event_type").agg(F.sum("n").alias("n"))

    add("stream_foreachbatch_state", state_by_batch, "SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")

    def estimates(s, d):
        sample = windows.sample_stream(_stream(s, d), WEIGHTS["evt"], SEED).withColumn("w", F.expr(WEIGHTS["evt"]))
        sums = sample.groupBy("event_type").agg(F.count("*").alias("sampled"), F.sum(1 / F.col("w")).alias("estimate"))
        return windows.finish(sums, "complete").withColumn("estimate", F.round("estimate", 4))

    add("stream_sampled_ht", estimates, f"SELECT event_type, CAST(count(*) AS BIGINT) AS sampled, round(sum(1 / {WEIGHTS['evt']}), 4) AS estimate FROM events WHERE {coin} < {WEIGHTS['evt']} GROUP BY 1")


_register()

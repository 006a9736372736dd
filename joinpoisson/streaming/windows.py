"""Structured Streaming plans over the events stream, run to the end of their input."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from joinpoisson.functions.rng import u01
from joinpoisson.plans.storage import shared_dir

def slices(spark: SparkSession, df: DataFrame, parts: int, order: str) -> str:
    """df as files in order of a column, a range each, for a file stream to read one after the other."""
    where = f"{shared_dir(spark)}/stream-in-{uuid.uuid4().hex}"
    bounds = df.stat.approxQuantile(order, [i / parts for i in range(1, parts)], 0.001) if parts > 1 else []  # exact ones hold the column on the driver
    part = sum((F.col(order) > b).cast("int") for b in bounds) if bounds else F.lit(0)
    for i in range(parts):
        df.where(part == i).coalesce(1).write.mode("append").parquet(where)
    return where


def read(spark: SparkSession, where: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(where)


def finish(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there, into a table in the shared folder: of each batch (complete: of the last one, which
    has all rows; its forerunner goes once a batch is written). Nothing of the result is on the driver."""
    spark = stream.sparkSession
    out = f"{shared_dir(spark)}/out_{uuid.uuid4().hex}"
    files = spark._jvm.org.apache.hadoop.fs.Path(out).getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())

    def write(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{out}/batch={batch}")
        if mode == "complete" and batch:
            files.delete(spark._jvm.org.apache.hadoop.fs.Path(f"{out}/batch={batch - 1}"), True)

    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{out}-log").trigger(availableNow=True)
    query = (writer.format("parquet").option("path", out) if mode == "append" else writer.foreachBatch(write)).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out).select(*stream.columns)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def sample_stream(events: DataFrame, weight: str, seed: int) -> DataFrame:
    """A coin for every event as it comes; the coin hangs on the event's id, so a replay tosses the same."""
    return events.where(u01(F.lit(seed), F.lit(0), F.lit("coin"), F.col("event_id")) < F.expr(weight))


def running_counts(events: DataFrame) -> DataFrame:
    """Per user the number and sum of events so far, kept in state of its own."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for b in batches:
            n, total = n + len(b), total + float(b["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return events.select("user_id", "value").groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)

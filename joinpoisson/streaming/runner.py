"""Streams of insertions into a maintained sample or index."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joinpoisson.plans.relations import RelationSpec
from joinpoisson.plans.storage import shared_dir


def insertion_log(specs: list[RelationSpec], eta: dict[str, str] | None = None) -> DataFrame:
    """All tuples as one log: relation, rid, w, and every attribute as a long (null where the relation lacks it)."""
    names = list(dict.fromkeys(a for s in specs for a in s.attrs))
    out = None
    for s in specs:
        one = s.narrow().select(F.lit(s.name).alias("relation"), *[(F.col(a) if a in s.attrs else F.lit(None)).cast("long").alias(a) for a in names], "rid", "w")
        out = one if out is None else out.unionByName(one)
    return out


def write_slices(log: DataFrame, slices: int, slice_of=None) -> str:
    """The log as files, one per slice, in a new folder; returns the folder."""
    where = f"{shared_dir(log.sparkSession)}/log-{uuid.uuid4().hex}"
    pick = slice_of if slice_of is not None else F.pmod(F.xxhash64("relation", "rid"), F.lit(slices))
    marked = log.withColumn("_slice", pick.cast("int"))
    for i in range(slices):
        marked.where(F.col("_slice") == i).drop("_slice").coalesce(1).write.mode("append").parquet(where)
    return where


def run_insertions(spark: SparkSession, where: str, schema, attrs: dict[str, tuple[str, ...]], insert: Callable[[int, dict[str, DataFrame]], None], files_per_batch: int = 1) -> None:
    """Feeds the files of a log to insert(batch, tuples by relation), a file per micro-batch, until all are in."""
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(where)

    def step(rows: DataFrame, batch: int) -> None:
        insert(batch, {n: rows.where(F.col("relation") == n).select(*a, "rid", "w") for n, a in attrs.items()})

    query = stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}").trigger(availableNow=True).start()
    query.awaitTermination()


def in_batches(log: DataFrame, slices: int, attrs: dict[str, tuple[str, ...]], insert: Callable[[int, dict[str, DataFrame]], None], slice_of=None) -> None:
    """The same without a stream: the slices one after the other."""
    pick = slice_of if slice_of is not None else F.pmod(F.xxhash64("relation", "rid"), F.lit(slices))
    for i in range(slices):
        rows = log.where(pick == i)
        insert(i, {n: rows.where(F.col("relation") == n).select(*a, "rid", "w") for n, a in attrs.items()})

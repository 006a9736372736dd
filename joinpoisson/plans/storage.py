"""Tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir of the session. Where none is set: a new one, in the temporary
    folder of a local session, else in the warehouse, which a cluster shares."""
    held = spark.sparkContext.getCheckpointDir()
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        if held is None:
            spark.sparkContext.setCheckpointDir(configured)
        return configured.rstrip("/")
    if held is None:
        local = spark.sparkContext.master.split("[")[0] == "local"
        warehouse = spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="ckpt-") if local else f"{warehouse}/ckpt-{uuid.uuid4().hex}")
        held = spark.sparkContext.getCheckpointDir()
    return held.rstrip("/")


#: Once a table is written, nothing needs the shuffle files that led to it.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write df to the shared folder and read it again: ends the lineage and fixes ids made from row positions."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEAN, "false")
    spark.conf.set(_CLEAN, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEAN, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def cut_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int | None = None) -> DataFrame:
    """`cut` into hash buckets of the keys, sorted within each: a join or grouping on the keys reads it without an exchange.
    Buckets: as many as the session's shuffle partitions, so that what is exchanged for such a join meets them."""
    spark = df.sparkSession
    n = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    table = f"{name.replace('-', '_')}_{uuid.uuid4().hex}"
    path = f"{shared_dir(spark)}/{table}"
    before = spark.conf.get(_CLEAN, "false")
    spark.conf.set(_CLEAN, "true")
    try:
        df.repartition(n, *keys).write.bucketBy(n, *keys).sortBy(*keys).option("path", path).saveAsTable(table)
    finally:
        spark.conf.set(_CLEAN, before)
    out = spark.table(table)
    out._cut_path = path
    return out


#: Rows up to which a table may go to all executors by way of the driver.
FEW = 100_000


def side(df: DataFrame, rows: int | None = None) -> DataFrame:
    """df as a side of joins: merged, by hint, where it has more than FEW rows. A planner knows a written table by the bytes of its
    files, and a million rows of keys and counts are few bytes there, but a map of 100 MB once the driver has built it.
    rows: how many it has, if known."""
    return df.hint("merge") if (df.limit(FEW + 1).count() if rows is None else rows) > FEW else df


def release(*tables: DataFrame | None) -> None:
    """Delete tables made by `cut` that no later plan reads."""
    for t in tables:
        path = getattr(t, "_cut_path", None)
        if path:
            jvm = t.sparkSession._jvm
            place = jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(t.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(place, True)


def running_sum(df: DataFrame, groups: list[str], order: list[str], value: str, out: str) -> DataFrame:
    """df with out = sum of value over the rows of its group up to and with its own, in a group of any size.

    Rows are sorted over range partitions and written; each partition sums its groups, the sums are added up over the
    partitions (one row per group and partition), and only the rest of the sum runs inside a partition.
    """
    keys = [F.col(c) for c in (*groups, *order)]
    at = F.monotonically_increasing_id()
    placed = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", at).withColumn("_part", F.shiftright("_at", 33))
    placed = cut(placed, "prefix")
    own = Window.partitionBy("_part", *groups).orderBy("_at").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    earlier = Window.partitionBy(*groups).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    sums = placed.groupBy("_part", *groups).agg(F.sum(value).alias("_sum")).withColumn("_start", F.coalesce(F.sum("_sum").over(earlier), F.lit(0).cast("long"))).drop("_sum")
    met = placed.withColumn("_run", F.sum(value).over(own)).join(sums, ["_part", *groups])
    return met.withColumn(out, F.col("_start") + F.col("_run")).drop("_at", "_part", "_run", "_start")

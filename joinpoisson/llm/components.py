"""Connected components of an edge table by alternating large and small stars, all in DataFrame functions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.llm.common import cut, release


def components(edges: DataFrame) -> DataFrame:
    """edges (a, b) -> (node, root), root the least node of the component; nodes without an edge are absent.

    A large star hangs each greater neighbour on the least one near a node, a small star the lesser neighbours;
    a node's neighbours are only aggregated to their least, so no neighbourhood is gathered in one row.
    """
    now = cut(edges.where("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "cc")
    mark = _mark(now)
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = _star(both, greater=True)
        small = cut(_star(large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")), greater=False), "cc")
        release(now)
        before, mark, now = mark, _mark(small), small
        if mark == before:
            break
    return small.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(small.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def _mark(pairs: DataFrame) -> tuple:
    """Equal for equal sets of pairs; two sums of independent hashes tell others apart."""
    hashes = [F.sum(F.shiftright(F.xxhash64(F.lit(k), "a", "b"), 20)) for k in (1, 2)]
    return tuple(pairs.agg(F.count("*"), *hashes).first())


def _star(pairs: DataFrame, greater: bool) -> DataFrame:
    least = pairs.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("m", "a"))
    met = pairs.join(least, "a")
    if greater:
        out = met.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        out = met.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(met.select("a", F.col("m").alias("b")))
    return out.where("a != b").distinct()


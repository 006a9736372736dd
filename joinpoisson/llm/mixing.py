"""Mixing sources to target weights by systematic sampling, in DataFrame functions only.

Every source gets a target of words; a document of it is expected expected = target / source_size times. Within
a source the documents are ordered by size and doc_id, expected copies are summed along that order, one random
offset is added, and a document is emitted once for each whole number its step crosses. Order by size spreads
the taken copies evenly over short and long texts, so the taken words come near the target.

Ranks come from range partitions: each partition counts its rows of each source, the counts are summed over
the partitions, so no source has to fit into one task.

Cases: a null text has size 0 and is expected as often as any other of its source; a source of size 0 has
target 0 and takes nothing; a null source is a source of its own, last in order; rows that repeat doc_id,
text and source share one draw; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from joinpoisson.llm.common import cut, hash128, packed, unpacked

#: Fixed values of the contract: weights in the order of the sources, share of all words, most copies.
WEIGHTS, SHARE, MOST, SEED = (3, 1, 2), 1.5, 2, 20240607


def word_count(text: Column) -> Column:
    """Number of [^\\x20\\x09-\\x0D]+ in text; a null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """sizes (source, source_size) with weight and target. A target is the lesser of most * size and level * weight,
    where level makes the targets sum to share of all words: the limit of resharing the excess by weight."""
    order = Window.orderBy(F.col("source").isNull(), "source")  # one row per source
    listed = sizes.withColumn("place", F.row_number().over(order) - 1)
    weighed = listed.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.col("place") % len(weights) + 1).cast("int")))
    stop = F.col("source_size") * most
    by_stop = Window.orderBy(stop / F.col("weight"), "place")
    all_ = Window.partitionBy()
    upto = by_stop.rowsBetween(Window.unboundedPreceding, -1)
    after = by_stop.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    filled = weighed.withColumns({"budget": F.sum("source_size").over(all_) * F.lit(float(share)), "before": F.coalesce(F.sum(stop).over(upto), F.lit(0)), "rest": F.sum("weight").over(after)})
    # In order of stop / weight the level rises up to the first source that it does not fill, and falls behind it.
    level = (F.col("budget") - F.col("before")) / F.col("rest")
    levelled = filled.withColumn("level", F.max(F.when(level * F.col("weight") <= stop, level)).over(all_))
    target = F.least(stop.cast("double"), F.coalesce(F.col("level") * F.col("weight"), stop.cast("double")))
    return levelled.select("source", "source_size", "weight", target.alias("target"))


def copies(docs: DataFrame, seed: int = SEED, weights: tuple = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """One row per distinct (doc_id, text, source): k1, k2 (its hash), doc_id, source, size, times (such rows), source_size, target, copies."""
    k1, k2 = hash128("k", F.col("doc_id"), F.col("source"), F.col("text"))
    rows = docs.select(k1, k2, "doc_id", "source", word_count(F.col("text")).alias("size"))
    light = rows.groupBy("k1", "k2").agg(*[F.first(c).alias(c) for c in ("doc_id", "source", "size")], F.count("*").alias("times"))
    absent = F.col("source").isNull()
    keys = [absent, F.col("source"), F.col("size"), F.col("doc_id").isNull(), F.col("doc_id"), F.col("k1"), F.col("k2")]
    placed = light.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("at", F.monotonically_increasing_id())
    placed = cut(placed.withColumn("part", F.shiftright("at", 33)), "mix-order")
    whole = cut(targets(placed.groupBy("source").agg(F.sum(F.col("size") * F.col("times")).alias("source_size")), weights, share, most), "targets")
    counts = placed.groupBy("source", "part").agg(F.count("*").alias("rows"), F.min("at").alias("first"))
    before = F.coalesce(F.sum("rows").over(Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = counts.withColumn("before", before)
    same = lambda a, b: a["source"].eqNullSafe(b["source"])
    starts = starts.join(whole, same(starts, whole)).select(starts["source"], "part", "first", "before", "source_size", "target")
    met = placed.alias("p").join(starts.alias("s"), (F.col("p.part") == F.col("s.part")) & F.col("p.source").eqNullSafe(F.col("s.source")))
    rank = F.col("s.before") + F.col("p.at") - F.col("s.first")
    expected = F.when(F.col("s.source_size") > 0, F.col("s.target") / F.col("s.source_size")).otherwise(0.0)
    drawn = F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce("p.source", F.lit("\0"))).cast("binary"))
    offset = F.conv(F.substring(drawn, 1, 5), 16, 10).cast("double") / float(1 << 20)
    crossed = F.floor((rank + 1) * expected + offset) - F.floor(rank * expected + offset)
    return met.select("p.k1", "p.k2", "p.doc_id", "p.source", "p.size", "p.times", "s.source_size", "s.target", F.least(crossed, F.lit(most)).alias("copies"))


def digest(docs: DataFrame, **settings) -> DataFrame:
    """doc_id, size, source_size, target, taken for every row of docs."""
    drawn = copies(docs, **settings)
    each = drawn.withColumn("again", F.explode(F.sequence(F.lit(1), F.col("times").cast("int"))))
    return each.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "source", "copies")


def mix(docs: DataFrame, **settings) -> DataFrame:
    """docs with every row as often as it is taken, columns as given."""
    keyed = docs.select(*hash128("k", F.col("doc_id"), F.col("source"), F.col("text")), packed(docs).alias("row"))
    drawn = copies(docs, **settings).where("copies > 0").select("k1", "k2", "copies")
    each = keyed.join(drawn, ["k1", "k2"]).select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("again"))
    return each.select(*unpacked("row", docs.columns))

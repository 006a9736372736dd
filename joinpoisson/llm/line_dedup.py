"""Line dedup over levelled sorted runs of line hashes, in DataFrame functions only.

A run is a table of (h1, h2, n): the 128-bit hash of a line's key and the number of documents that have it, in hash
buckets, sorted within each. A batch of documents is counted and merge-joined with the runs, which needs no exchange of
theirs: a key that no run holds is new (the anti join), for others the runs tell how many documents had it before. The
keys that come to `min_docs` documents with this batch are handed on as frequent, each by exactly one batch; the result
is made of these. The batch becomes a run of level 0. Once a level holds `fanout` runs they are merged into one run of
the next level, so a key is rewritten once per level.

The lines that go are marked by their positions, 64 to a word, so a text of any number of lines takes time in proportion.

A line's key is the line stripped of white space at both ends with A-Z lower-cased. Cases: a null or empty text is one
empty line; the empty key is never dropped; rows with the same doc_id are one document, those without one too; columns
named like the result's get it with underscores behind; an empty table gives no rows.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from joinpoisson.llm.common import WHITE, cut, cut_bucketed, fresh_names, hash128, packed, release, unpacked

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
MIN_DOCS, MIN_POINTS, BATCHES, FANOUT, WORD = 10, 1, 4, 2, 64
KEY = ["h1", "h2"]


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(WHITE)), UPPER, LOWER)


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


class LineRuns:
    """The levelled runs; all tables lie in the shared folder."""

    def __init__(self, spark: SparkSession, fanout: int = FANOUT, min_docs: int = MIN_DOCS):
        self.spark, self.fanout, self.min_docs, self.levels = spark, fanout, min_docs, []

    def runs(self) -> list[DataFrame]:
        return [r for level in self.levels for r in level]

    def counts(self) -> DataFrame | None:
        """h1, h2, n over all runs."""
        return reduce(_merged, self.runs()) if self.runs() else None

    def ingest(self, keys: DataFrame) -> DataFrame:
        """keys: a row (h1, h2) for each document and distinct key of it. Adds a run; returns the batch's keys with n,
        is_new (in no run before) and frequent (min_docs documents with this batch, fewer before)."""
        batch = keys.groupBy(*KEY).agg(F.count("*").alias("n"))
        held = []
        for i, run in enumerate(self.runs()):
            batch = batch.join(run.withColumnRenamed("n", f"held{i}"), KEY, "left")
            held.append(F.col(f"held{i}"))
        before = reduce(Column.__add__, [F.coalesce(c, F.lit(0)) for c in held], F.lit(0).cast("long"))
        is_new = F.lit(True) if not held else F.coalesce(*held).isNull()
        marked = batch.select(*KEY, "n", is_new.alias("is_new"), ((before < self.min_docs) & (before + F.col("n") >= self.min_docs)).alias("frequent"))
        run = cut_bucketed(marked, "run0", KEY)
        self._push(0, run.select(*KEY, "n"))
        return self.spark.read.schema(run.schema).parquet(run._cut_path)  # what makes a union of runs needs no buckets

    def _push(self, level: int, run: DataFrame) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(run)
        if len(self.levels[level]) >= self.fanout:
            merged = cut_bucketed(reduce(_merged, self.levels[level]), f"run{level + 1}", KEY)
            self.levels[level] = []
            self._push(level + 1, merged)


def _merged(one: DataFrame, two: DataFrame) -> DataFrame:
    """The counts of two runs, by a merge join of their buckets."""
    both = one.join(two.withColumnRenamed("n", "m"), KEY, "full")
    return both.select(*KEY, (F.coalesce("n", F.lit(0)) + F.coalesce("m", F.lit(0))).alias("n"))


def line_dedup(docs: DataFrame, min_docs: int = MIN_DOCS, min_points: int = MIN_POINTS, batches: int = BATCHES, fanout: int = FANOUT) -> DataFrame:
    """docs with n_lines, n_dropped and kept_text: lines whose key is in min_docs documents or more are gone."""
    t1, t2 = hash128("t", F.col("text"))
    keys = F.transform(lines_of(F.col("text")), line_key)
    lists = docs.select(t1, t2, "doc_id", F.posexplode(keys).alias("pos", "k")).where(F.length("k") >= min_points)
    batch = F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(batches)).cast("int").alias("batch")
    light = cut(lists.select(batch, "t1", "t2", "doc_id", "pos", *hash128("h", F.col("k"))), "lines")
    store = LineRuns(docs.sparkSession, fanout, min_docs)
    found = [store.ingest(light.where(F.col("batch") == b).select(*KEY, "doc_id").distinct()).where("frequent").select(*KEY) for b in range(batches)]
    drops = light.select("t1", "t2", "pos", *KEY).join(reduce(DataFrame.unionByName, found), KEY, "left_semi")
    # Copies of a text share their lines, so they meet here.
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("pos") % WORD)
    marks = drops.groupBy("t1", "t2", F.expr(f"pos div {WORD}").cast("int").alias("word")).agg(F.bit_or(bit).alias("bits"))
    marks = cut(marks.groupBy("t1", "t2").agg(F.collect_list(F.struct("word", "bits")).alias("marks")), "line-marks")
    release(light)
    met = docs.select(t1, t2, packed(docs).alias("row")).join(marks, ["t1", "t2"], "left")
    text = f"row.c{[c.lower() for c in docs.columns].index('text')}"
    met = met.select("row", "marks", lines_of(F.col(text)).alias("lines"))
    words = F.transform(F.sequence(F.lit(0), F.expr(f"(size(lines) - 1) div {WORD}").cast("int")), lambda w: F.struct(w.alias("word"), F.coalesce(F.get(F.filter("marks", lambda m: m["word"] == w), F.lit(0))["bits"], F.lit(0)).alias("bits")))
    stays = F.transform(words, lambda w: F.filter(F.slice("lines", w["word"] * WORD + 1, WORD), lambda x, i: F.getbit(w["bits"], i) == 0))
    left = met.select("row", F.size("lines").cast("long").alias("n"), F.when(F.col("marks").isNull(), F.col("lines")).otherwise(F.flatten(stays)).alias("left"))
    n_lines, n_dropped, kept_text = fresh_names(docs.columns, ("n_lines", "n_dropped", "kept_text"))
    return left.select(*unpacked("row", docs.columns), F.col("n").alias(n_lines), (F.col("n") - F.size("left")).alias(n_dropped), F.array_join("left", "\n").alias(kept_text))


def digest(docs: DataFrame, **settings) -> DataFrame:
    done = line_dedup(docs.select("doc_id", "text"), **settings)
    return done.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))

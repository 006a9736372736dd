"""Candidate ranks: of each part's ranks 1..n every one with probability p, without touching the others.

The ranks of a part are cut into chunks that expect CHUNK_HITS hits. A chunk jumps from hit to hit by geometric gaps;
chunks are disjoint, so together they are one draw. Chunks are dealt to tasks before the gaps are drawn, so one large
part spreads over the cluster, and neither the driver nor a task holds a list of ranks.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.rng import SCALE, mixed_uniforms, nonempty_probability, truncated_geometric, u01, u01_value
from joinpoisson.functions.arith import div

CHUNK_HITS, GROUP = 64, 1024
LISTED = 1 << 16  # ranks that one row of all_ranks is made into


def chunk_length(p: float) -> int:
    return max(1, math.ceil(CHUNK_HITS / p)) if p > 0 else 1 << 62


def candidate_ranks(parts: DataFrame, seed: int, draw: int = 0, draws: int = 1, gate: bool = False, bulk: bool = False, purpose: str = "gap", deal: bool = True) -> DataFrame:
    """parts: n, p and any columns that tell them apart, with `part` (text, names the part in the uniforms). Adds draw, rank.

    gate: first a coin for whether the part has a hit at all, then the first hit in it, then the rest from there.
    deal: whether parts are dealt to tasks; not where they are many and spread already, as it moves them all.
    """
    some = parts.where((F.col("n") > 0) & (F.col("p") > 0))
    some = some.withColumn("draw", F.explode(F.sequence(F.lit(draw), F.lit(draw + draws - 1))))
    own = [c for c in some.columns]
    if gate:
        q = nonempty_probability(F.col("p"), F.col("n"))
        some = some.where(u01(F.lit(seed), F.col("draw"), F.lit("gate"), F.col("part")) < q)
        first = truncated_geometric(u01(F.lit(seed), F.col("draw"), F.lit("first"), F.col("part")), F.col("p"), F.col("n"))
        some = some.withColumn("_from", first + 1)
        certain = some.select(*own, F.col("_from").alias("rank"))
    else:
        some = some.withColumn("_from", F.lit(0).cast("long"))
    length = F.least(F.lit(1 << 62).cast("long"), F.ceil(F.lit(float(CHUNK_HITS)) / F.col("p")).cast("long"))
    some = some.withColumn("_length", length).withColumn("_chunks", div(F.col("n") - F.col("_from") + F.col("_length") - 1, F.col("_length"))).where("_chunks > 0")
    groups = some.withColumn("_group", F.explode(F.sequence(F.lit(0).cast("long"), div(F.col("_chunks") - 1, F.lit(GROUP)))))
    groups = _dealt(groups, F.xxhash64("part", "draw", "_group")) if deal else groups
    chunks = groups.withColumn("_chunk", F.explode(F.sequence(F.col("_group") * GROUP, F.least(F.col("_group") * GROUP + GROUP, F.col("_chunks")) - 1)))
    shape = chunks.select(*own, F.lit(0).cast("long").alias("rank")).schema
    carried = chunks.select(*own, "_from", "_length", "_chunk")

    def draw_gaps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = {c: b.column(i) for i, c in enumerate(b.schema.names)}
            col = lambda c: at[c].to_numpy(zero_copy_only=False)
            begin = col("_from") + col("_chunk") * col("_length")
            room = np.minimum(col("_length"), col("n") - begin)
            hits = _bulk_hits if bulk else _md5_hits
            which, ranks = hits(seed, purpose, at["part"].to_pylist(), col("draw"), col("_chunk"), col("p"), begin, room)
            take = pa.array(which, pa.int64())
            yield pa.RecordBatch.from_arrays([*[at[c].take(take) for c in own], pa.array(ranks, pa.int64())], names=[*own, "rank"])

    found = carried.mapInArrow(draw_gaps, shape)
    return found.unionByName(certain) if gate else found


def _dealt(rows: DataFrame, key: Column) -> DataFrame:
    """Rows dealt to all tasks; with a number of them, as few small rows would else be put into one task, whatever becomes of them."""
    return rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), key)


def all_ranks(parts: DataFrame, runs: bool = False) -> DataFrame:
    """parts (n and any other columns) with each rank from 1 to n: in pieces of LISTED ranks, dealt to tasks before they are listed.
    runs: the pieces themselves, with their first and last rank."""
    own, last = [c for c in parts.columns if c != "n"], div(F.col("n") - 1, F.lit(LISTED))
    pieces = _dealt(parts.where("n > 0").withColumn("_piece", F.explode(F.sequence(F.lit(0).cast("long"), last))), F.xxhash64(*own, "_piece"))
    first, end = F.col("_piece") * LISTED + 1, F.least((F.col("_piece") + 1) * LISTED, F.col("n"))
    if runs:
        return pieces.select(*own, first.alias("first"), end.alias("last"))
    return pieces.select(*own, F.explode(F.sequence(first, end)).alias("rank"))


def _md5_hits(seed, purpose, part, draw, chunk, p, begin, room) -> tuple[list[int], list[int]]:
    which, ranks = [], []
    for i in range(len(part)):
        place, turn, step = 0, 0, math.log1p(-p[i]) if p[i] < 1 else 0.0
        while True:
            turn += 1
            gap = 0 if p[i] >= 1 else int(min(float(room[i]), math.log(u01_value(seed, int(draw[i]), purpose, part[i], int(chunk[i]), turn)) / step))
            place += gap + 1
            if place > room[i]:
                break
            which.append(i)
            ranks.append(int(begin[i]) + place)
    return which, ranks


def _bulk_hits(seed, purpose, part, draw, chunk, p, begin, room) -> tuple[np.ndarray, np.ndarray]:
    """All chunks at once, a gap of each at a time."""
    base = np.array([int(u01_value(seed, int(d), purpose, x) * SCALE) for x, d in zip(part, draw, strict=True)], np.uint64) if len(part) else np.zeros(0, np.uint64)
    streams = base ^ (chunk.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    step = np.log1p(-np.minimum(p, 1 - 2.0**-53))
    live, place, turn = np.arange(len(p)), np.zeros(len(p), np.int64), 0
    out_i, out_r = [], []
    while len(live):
        turn += 1
        gap = np.where(p[live] >= 1, 0.0, np.minimum(room[live].astype(np.float64), np.floor(np.log(mixed_uniforms(seed, streams[live], turn)) / step[live])))
        place[live] += gap.astype(np.int64) + 1
        live = live[place[live] <= room[live]]
        out_i.append(live)
        out_r.append(begin[live] + place[live])
    return (np.concatenate(out_i), np.concatenate(out_r)) if out_i else (np.zeros(0, np.int64), np.zeros(0, np.int64))

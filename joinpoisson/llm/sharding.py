"""Sharding by a minimax contiguous partition.

Equal texts form one atomic group; groups are ordered by the SHA-256 of the text. The smallest capacity for
which a greedy walk over the ordered sizes needs no more than the given shards is found by binary search, and
the walk with that capacity makes the cuts.

The walk only asks for the last group end at or below a position. The driver holds the group ends as a grid of
cells (smallest end, largest end, number); a lookup inside a cell that is not known in full gives a sure and a
hopeful answer, so each capacity is feasible, infeasible or open. Cells on open walks are split into finer ones
by one aggregation over the ends, until no capacity is open. So the driver holds a bounded number of cells, and
the capacity is exact.

A group larger than an even share of what is left gets a shard of its own first (there can be no more of them
than shards); the rest is cut into the remaining shards. Cases: a null text has 16 bytes of size, crc 0 and counts
as empty; rows that repeat stay together; more shards than groups leave shards empty; an empty table gives no rows.
"""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from joinpoisson.llm.common import cut, position_ids

SHARDS, OVERHEAD, CELL_BITS = 40, 16, 12


class EndGrid:
    """Group ends as cells, each (smallest end, largest end, number of ends), refined on demand."""

    def __init__(self, ends: DataFrame, total: int, bits: int = CELL_BITS):
        self.ends, self.total, self.bits, self.cells = ends, total, bits, []
        self._add(ends, max(0, total.bit_length() - bits))

    def _add(self, ends: DataFrame, shift: int) -> None:
        found = ends.groupBy(F.shiftright(F.col("end") - 1, shift).alias("c")).agg(F.min("end"), F.max("end"), F.count("*")).collect()
        self.cells = sorted(self.cells + [(lo, hi, n, shift) for _, lo, hi, n in found])
        self.lows = [c[0] for c in self.cells]

    def last(self, x: int, hopeful: bool, touched: set) -> int:
        """The last end at or below x: for sure, or at most."""
        i = bisect_right(self.lows, x) - 1
        if i < 0:
            return 0
        lo, hi, n, _ = self.cells[i]
        if hi <= x:
            return hi
        if n <= 2:
            return lo
        touched.add(i)
        return min(x, hi - 1) if hopeful else lo

    def walk(self, capacity: int, shards: int, hopeful: bool, touched: set) -> list[int] | None:
        at, cuts = 0, []
        for _ in range(shards):
            if at + capacity >= self.total:
                return cuts
            to = self.last(at + capacity, hopeful, touched)
            if to <= at:
                return None
            cuts.append(at := to)
        return None

    def least(self, shards: int, low: int, hopeful: bool) -> int:
        high = self.total
        while low < high:
            mid = (low + high) // 2
            if self.walk(mid, shards, hopeful, set()) is None:
                low = mid + 1
            else:
                high = mid
        return low

    def refine(self, which: set) -> None:
        shift = max(self.cells[i][3] for i in which)
        which = {i for i in which if self.cells[i][3] == shift}
        ids = sorted({(self.cells[i][0] - 1) >> shift for i in which})
        self.cells = [c for i, c in enumerate(self.cells) if i not in which]
        self._add(self.ends.where(F.shiftright(F.col("end") - 1, shift).isin(ids)), max(0, shift - max(1, self.bits - 3)))

    def cut(self, shards: int, largest: int) -> tuple[int, list[int]]:
        """The least feasible capacity and its cuts."""
        if self.total <= 0:
            return 0, []
        floor = max(largest, -(-self.total // shards))
        while True:
            low, high = self.least(shards, floor, True), self.least(shards, floor, False)
            touched: set = set()
            for c in {low, high, *(low + (high - low) * k // 16 for k in range(16))}:
                for hopeful in (True, False):
                    self.walk(c, shards, hopeful, touched)
            if low == high and not touched:
                return low, self.walk(low, shards, False, set())
            if not touched:
                return high, self.walk(high, shards, False, set())
            self.refine(touched)


def minimax_shards(docs: DataFrame, shards: int = SHARDS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of docs, and capacity."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + OVERHEAD).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.unhex(F.sha2(text, 256)).alias("g"))
    placed = cut(position_ids(rows, "g", F.col("doc_id")), "shard-rows")
    groups = cut(position_ids(placed.groupBy("g").agg(F.sum("size").alias("bytes")), "g"), "shard-groups")
    own, left, open_shards = [], groups.agg(F.sum("bytes")).first()[0] or 0, shards
    biggest = groups.orderBy(F.desc("bytes"), "g").limit(shards).collect()
    while biggest and open_shards > 1 and biggest[0]["bytes"] * open_shards > left:
        own.append(bytes(biggest[0]["g"]))
        left, open_shards = left - biggest[0]["bytes"], open_shards - 1
        biggest = biggest[1:]
    alone = F.col("g").isin([F.lit(g) for g in own]) if own else F.lit(False)
    weights = groups.withColumn("w", F.when(alone, 0).otherwise(F.col("bytes")))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row per partition
    starts = weights.groupBy("part").agg(F.sum("w").alias("whole")).withColumn("start", F.coalesce(F.sum("whole").over(before), F.lit(0)))
    running = weights.withColumn("run", F.sum("w").over(Window.partitionBy("part").orderBy("at")))
    ends = cut(running.join(starts, "part").select("g", "w", (F.col("start") + F.col("run")).alias("end")), "shard-ends")
    capacity, cuts = EndGrid(ends.where("w > 0").select("end"), left).cut(open_shards, biggest[0]["bytes"] if biggest else 0)
    behind = F.size(F.filter(F.array(*[F.lit(c).cast("long") for c in cuts]), lambda c: c < F.col("end"))) if cuts else F.lit(0)
    shard = F.when(F.col("w") == 0, F.array_position(F.array(*map(F.lit, own)), F.col("g")).cast("int") - 1).otherwise(behind + len(own)) if own else behind
    dealt = placed.join(ends.select("g", shard.cast("int").alias("shard")), "g")
    numbered = cut(dealt.withColumn("n", F.row_number().over(Window.partitionBy("part", "shard").orderBy("at"))), "shard-dealt")
    sums = numbered.groupBy("shard", "part").agg(F.count("*").alias("here"))
    sums = sums.withColumn("start", F.coalesce(F.sum("here").over(Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    out = numbered.join(sums, ["shard", "part"])
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("start") + F.col("n") - 1).alias("slot"), F.lit(None).cast("int").alias("grown_shard"), F.lit(capacity).cast("long").alias("capacity"))

"""Relations of a natural join: attributes, weight, and a fixed order of the tuples."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import Algebra
from joinpoisson.plans.storage import cut

RID, WEIGHT = "rid", "w"


@dataclass(frozen=True)
class RelationSpec:
    """df has the attributes, rid (unique BIGINT that fixes the order of the tuples) and w (weight, DOUBLE)."""

    name: str
    df: DataFrame
    attrs: tuple[str, ...]

    def narrow(self) -> DataFrame:
        return self.df.select(*self.attrs, F.col(RID).cast("long").alias(RID), F.col(WEIGHT).cast("double").alias(WEIGHT))


def schemas(specs: list[RelationSpec]) -> dict[str, tuple[str, ...]]:
    return {s.name: s.attrs for s in specs}


def assign_rid(df: DataFrame, order: list[str], name: str = RID) -> DataFrame:
    """df with a dense number from 1 in the given order, by range partitions; written, so that the numbers hold."""
    keys = [F.col(c) for c in order]
    placed = cut(df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id()), "rid")
    part = F.shiftright("_at", 33)
    counts = {r["p"]: r["n"] for r in placed.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()}  # one row per partition
    start, starts = 0, []
    for p in sorted(counts):
        starts.append((p, start))
        start += counts[p]
    table = df.sparkSession.createDataFrame(starts or [(0, 0)], "_part long, _start long")
    met = placed.withColumn("_part", part).join(F.broadcast(table), "_part")
    return met.withColumn(name, F.col("_start") + F.col("_at").bitwiseAND((1 << 33) - 1) + 1).drop("_part", "_start", "_at")


def validate_weights(specs: list[RelationSpec], algebra: Algebra) -> None:
    """Raise ValueError where a weight is null, not a number, or outside [0, 1], or where sums can pass 1."""
    if algebra.name == "constant":
        return
    tops = []
    for s in specs:
        w = F.col(WEIGHT)
        bad, top = s.narrow().agg(F.count(F.when(w.isNull() | F.isnan(w) | (w < 0) | (w > 1), 1)), F.max(w)).first()
        if bad:
            raise ValueError(f"{s.name}: {bad} weights are not in [0, 1]")
        tops.append(top or 0.0)
    if algebra.name == "sum" and sum(tops) > 1 + 1e-12:
        from joinpoisson.operators.metrics import largest_sum

        if largest_sum(specs) > 1 + 1e-12:
            raise ValueError("the weights of a result can sum to more than 1")

"""Subset samplers over an explicit table: element, weight in [0, 1].

All skip samplers are one method: elements have places 1..n within a part, candidate places are drawn under the part's
ceiling, joined to the elements, and kept with weight / ceiling.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import score_of
from joinpoisson.functions.rng import u01
from joinpoisson.operators.ranks import candidate_ranks
from joinpoisson.plans.storage import running_sum

CAP = 40


def sample_bernoulli(df: DataFrame, key: str, weight: Column, seed: int, draw: int = 0) -> DataFrame:
    """A coin for every element: one scan, no exchange."""
    return df.where(u01(F.lit(seed), F.lit(draw), F.lit("coin"), F.col(key)) < weight)


def placed(df: DataFrame, part: Column, key: str) -> DataFrame:
    """df with part and place: 1..n within the part in order of key, for parts of any size."""
    ones = df.withColumn("part", part.cast("string")).withColumn("_one", F.lit(1).cast("long"))
    return running_sum(ones, ["part"], [key], "_one", "place").drop("_one")


def element_at_rank(elements: DataFrame, asked: DataFrame) -> DataFrame:
    """elements (part, place, ...) at the asked (part, rank)."""
    return asked.join(elements.withColumnRenamed("place", "rank"), ["part", "rank"])


def sample_parts(elements: DataFrame, parts: DataFrame, key: str, weight: Column | None, seed: int, draw: int = 0, draws: int = 1, gate: bool = True, bulk: bool = False) -> DataFrame:
    """elements: part, place, key and weight; parts: part, n, p (a ceiling of the weights, or the weight where weight is None)."""
    hits = candidate_ranks(parts.select("part", "n", "p"), seed, draw, draws, gate, bulk)
    met = element_at_rank(elements, hits.select("part", "rank", "draw", F.col("p").alias("_p")))
    if weight is not None:
        met = met.where(u01(F.lit(seed), F.col("draw"), F.lit("keep"), F.col(key)) * F.col("_p") < weight)
    return met.withColumnRenamed("rank", "place").drop("_p")


def sample_uniform_skip(df: DataFrame, key: str, p: float, seed: int, draw: int = 0, gate: bool = False, bulk: bool = False) -> DataFrame:
    """Every element with the same p, by geometric gaps."""
    elements = placed(df, F.lit("all"), key)
    parts = elements.groupBy("part").agg(F.count("*").alias("n")).withColumn("p", F.lit(float(p)))
    return sample_parts(elements, parts, key, None, seed, draw, gate=gate, bulk=bulk)


def sample_rejection(df: DataFrame, key: str, weight: Column, seed: int, draw: int = 0, ceiling: float | None = None, bulk: bool = False) -> DataFrame:
    """Candidates under one ceiling (the largest weight), kept with weight / ceiling."""
    elements = placed(df, F.lit("all"), key)
    top = F.max(weight) if ceiling is None else F.lit(float(ceiling))
    parts = elements.groupBy("part").agg(F.count("*").alias("n"), top.alias("p"))
    return sample_parts(elements, parts, key, weight, seed, draw, gate=False, bulk=bulk)


def sample_batched(df: DataFrame, key: str, part: Column, weight: Column, seed: int, draw: int = 0, meta: bool = True, bulk: bool = False) -> DataFrame:
    """Disjoint parts, each under its own largest weight. meta: a part is only entered if its coin says it has a candidate."""
    elements = placed(df, part, key)
    parts = elements.groupBy("part").agg(F.count("*").alias("n"), F.max(weight).alias("p"))
    return sample_parts(elements, parts, key, weight, seed, draw, gate=meta, bulk=bulk)


def uniformity(df: DataFrame, weight: Column) -> DataFrame:
    """n, largest, least (above 0), beta = largest / least, light (largest <= 1 / n)."""
    stats = df.agg(F.count("*").alias("n"), F.max(weight).alias("largest"), F.min(F.when(weight > 0, weight)).alias("least"))
    return stats.withColumns({"beta": F.col("largest") / F.col("least"), "light": F.col("largest") * F.col("n") <= 1})


@dataclass
class ClassifiedSet:
    """Elements by weight class, (2^-(c+1), 2^-c], so that each part's weights differ by at most 2."""

    elements: DataFrame
    key: str
    cap: int = CAP

    @classmethod
    def build(cls, df: DataFrame, key: str, weight: Column, cap: int = CAP) -> ClassifiedSet:
        some = df.withColumn("_weight", weight).where("_weight > 0").withColumn("_class", score_of(F.col("_weight"), cap))
        return cls(placed(some, F.col("_class"), key), key, cap)

    def parts(self) -> DataFrame:
        return self.elements.groupBy("part").agg(F.count("*").alias("n")).withColumn("p", F.pow(F.lit(2.0), -F.col("part").cast("double")))

    def sample(self, seed: int, draw: int = 0, draws: int = 1, gate: bool = True, bulk: bool = False) -> DataFrame:
        return sample_parts(self.elements, self.parts(), self.key, F.col("_weight"), seed, draw, draws, gate, bulk)

    def _raw(self) -> DataFrame:
        return self.elements.drop("part", "place", "_class")

    def upsert(self, delta: DataFrame, weight: Column) -> ClassifiedSet:
        """Elements of delta are new or get a new weight."""
        new = delta.withColumn("_weight", weight)
        kept = self._raw().join(new.select(self.key), self.key, "left_anti")
        return ClassifiedSet.build(kept.unionByName(new.select(*kept.columns)), self.key, F.col("_weight"), self.cap)

    def delete(self, keys: DataFrame) -> ClassifiedSet:
        return ClassifiedSet.build(self._raw().join(keys.select(self.key), self.key, "left_anti"), self.key, F.col("_weight"), self.cap)

"""Baselines: make the join and toss a coin for each result, and what else the samplers are compared with."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import PRODUCT, Algebra
from joinpoisson.functions.rng import u01
from joinpoisson.operators.explicit import ClassifiedSet
from joinpoisson.operators.sampler import result_coin
from joinpoisson.plans.relations import RelationSpec


def natural_join(specs: list[RelationSpec]) -> DataFrame:
    """All results: attributes, rid_*, w_*."""
    out = None
    for s in specs:
        one = s.narrow().withColumnsRenamed({"rid": f"rid_{s.name}", "w": f"w_{s.name}"})
        shared = [] if out is None else [a for a in s.attrs if a in out.columns]
        out = one if out is None else out.join(one, shared) if shared else out.crossJoin(one)
    return out


def naive_sample(specs: list[RelationSpec], algebra: Algebra = PRODUCT, seed: int = 0, draw: int = 0, draws: int = 1) -> DataFrame:
    """Make the join, then a coin per result and draw."""
    names = [s.name for s in specs]
    joined = natural_join(specs).withColumn("weight", algebra.weight([F.col(f"w_{n}") for n in sorted(names)]))
    many = joined.withColumn("draw", F.explode(F.sequence(F.lit(draw), F.lit(draw + draws - 1)))) if draws > 1 else joined.withColumn("draw", F.lit(draw))
    return many.where(result_coin(seed, F.col("draw"), names, "naive") < F.col("weight"))


@dataclass
class MaterializedIndex:
    """The join, written with its results by weight class: long to build, each draw then costs what it returns."""

    results: ClassifiedSet

    @classmethod
    def build(cls, specs: list[RelationSpec], algebra: Algebra = PRODUCT) -> MaterializedIndex:
        names = sorted(s.name for s in specs)
        joined = natural_join(specs)
        keyed = joined.withColumn("result", F.concat_ws("-", *[F.lpad(F.col(f"rid_{n}").cast("string"), 12, "0") for n in names]))
        return cls(ClassifiedSet.build(keyed, "result", algebra.weight([F.col(f"w_{n}") for n in names])))

    def sample(self, seed: int, draw: int = 0, draws: int = 1, gate: bool = False) -> DataFrame:
        return self.results.sample(seed, draw, draws, gate).withColumnRenamed("_weight", "weight")


def sample_inputs_then_join(specs: list[RelationSpec], seed: int = 0, draw: int = 0) -> DataFrame:
    """Not a sampler of results: the tuples toss the coins, so results that share a tuple depend on each other. A control
    that the independence test has to reject."""
    thinned = [RelationSpec(s.name, s.narrow().where(u01(F.lit(seed), F.lit(draw), F.lit(s.name), F.col("rid")) < F.col("w")), s.attrs) for s in specs]
    return natural_join(thinned)

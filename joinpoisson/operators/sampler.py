"""Samplers of join results: every result stays with its own probability, independently of the others."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import GRID, PRODUCT, Algebra
from joinpoisson.functions.rng import u01
from joinpoisson.operators.blocks import drawn, worthwhile
from joinpoisson.operators.index import ScoreIndex
from joinpoisson.operators.ranks import candidate_ranks
from joinpoisson.plans.jointree import size_bound
from joinpoisson.plans.relations import RelationSpec, schemas


def result_coin(seed: int, draw, names: list[str], purpose: str = "keep"):
    """The uniform of a result: a hash of its tuples' rids in order of the relations' names."""
    return u01(F.lit(seed), draw, F.lit(purpose), *[F.col(f"rid_{n}") for n in sorted(names)])


def sample_index(index: ScoreIndex, seed: int, draw: int = 0, draws: int = 1, gate: bool = False, bulk: bool = False) -> DataFrame:
    """Draws from an index: attributes, rid_*, w_*, draw, score, rank, weight. Each draw is independent of the others."""
    if not gate and worthwhile(index, draws):
        found = drawn(index, seed, draw, draws, bulk)
    else:
        found = _looked_up(index, seed, draw, draws, gate, bulk)
    weight = index.algebra.weight([F.col(f"w_{n}") for n in sorted(index.names)])
    keep = result_coin(seed, F.col("draw"), index.names) * F.col("_p") < F.col("weight")
    return found.withColumn("weight", weight).where(keep).drop("_p")


def _looked_up(index: ScoreIndex, seed: int, draw: int, draws: int, gate: bool, bulk: bool) -> DataFrame:
    name = F.concat_ws("-", "score") if index.buckets.schema["score"].dataType.typeName() == "array" else F.col("score").cast("string")
    parts = index.buckets.select("score", "n", F.col("ceiling").alias("p"), name.alias("part"))
    asked = candidate_ranks(parts, seed, draw, draws, gate, bulk).select("score", "rank", "draw", F.col("p").alias("_p"))
    return index.access(asked)


def sample_join(specs: list[RelationSpec], algebra: Algebra = PRODUCT, seed: int = 0, draw: int = 0, method: str = "batched", cap: int | str = "exact", root: str | None = None, bulk: bool = False, tail: str = "saturate") -> DataFrame:
    """One draw. batched: the tables stay in one lazy plan. index: they are written first. auto: batched when there are
    more candidates than tuples / log2(tuples). root_local: root tuples draw their own results, no ranks over the root.
    grid: one part per combination of classes. tail (batched, index, auto): what becomes of the cap's scores, see
    `sample_with_tail`."""
    if method == "root_local":
        from joinpoisson.operators.rootlocal import sample_root_local

        return sample_root_local(specs, algebra, seed, draw, cap, root, bulk)
    if method == "grid":
        return ScoreIndex.build(specs, GRID, cap, root).sample(seed, draw, bulk=bulk)
    if method == "auto":
        method = choose_method(specs, algebra, cap, root)
    index = ScoreIndex.build(specs, algebra, cap, root, store=method == "index")
    return sample_with_tail(index, specs, seed, draw, bulk, tail)


def sample_with_tail(index: ScoreIndex, specs: list[RelationSpec], seed: int, draw: int = 0, bulk: bool = False, tail: str = "saturate") -> DataFrame:
    """A draw whose last bucket, of all scores from the cap on, is treated in one of three ways. saturate: it is counted
    and drawn from like the others. materialize: its results are made (they alone) and each tosses a coin of its own.
    proxy: its size is not counted but taken to be the bound that the relations' sizes give the join; ranks behind its
    results are dropped in the descent. The bound costs candidates: choose a cap whose ceiling times the bound is small."""
    if tail == "saturate":
        return index.sample(seed, draw, bulk=bulk)
    last = F.col("score") == index.cap
    if tail == "proxy":
        bound = size_bound(schemas(specs), {s.name: s.df.count() for s in specs})
        if bound >= 1 << 62:
            raise ValueError("the bound on the join is beyond what ranks can hold")
        return replace(index, buckets=index.buckets.withColumn("n", F.when(last, F.lit(bound).cast("long")).otherwise(F.col("n")))).sample(seed, draw, bulk=bulk)
    if tail != "materialize":
        raise ValueError(f"no tail variant {tail}")
    head = replace(index, buckets=index.buckets.where(~last)).sample(seed, draw, bulk=bulk)
    weight = index.algebra.weight([F.col(f"w_{n}") for n in sorted(index.names)])
    made = index.enumerate([index.cap]).withColumns({"draw": F.lit(draw), "weight": weight})
    return head.unionByName(made.where(result_coin(seed, F.col("draw"), index.names, "naive") < F.col("weight")))


def choose_method(specs: list[RelationSpec], algebra: Algebra, cap: int | str = "exact", root: str | None = None) -> str:
    import math

    index = ScoreIndex.build(specs, algebra, cap, root, store=False)
    candidates = index.buckets.agg(F.sum(F.col("n") * F.col("ceiling"))).first()[0] or 0.0
    tuples = sum(s.df.count() for s in specs)
    return "batched" if candidates > tuples / math.log2(max(2, tuples)) else "index"

"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import PRODUCT, Algebra
from joinpoisson.operators.index import ScoreIndex, join_size, message_of
from joinpoisson.plans.jointree import Node, build_join_tree
from joinpoisson.plans.relations import RelationSpec, schemas



def input_size(specs: list[RelationSpec]) -> int:
    return sum(s.df.count() for s in specs)


def _fold(node: Node, specs: dict[str, RelationSpec], leaf: Callable, merge: Callable, keep: list) -> DataFrame:
    """A message with the columns that leaf makes of a tuple, merged with the children's; keep aggregates them by key."""
    rows = leaf(specs[node.name].narrow())
    for c in node.children:
        message = _fold(c, specs, leaf, merge, keep)
        names = [n for n in message.columns if n not in c.key]
        message = message.select(*c.key, *[F.col(n).alias(f"_{n}") for n in names])
        rows = merge(rows.join(message, list(c.key)) if c.key else rows.crossJoin(F.broadcast(message))).drop(*[f"_{n}" for n in names])
    return rows.groupBy(*node.key).agg(*keep)


def expected_size(specs: list[RelationSpec], algebra: Algebra = PRODUCT) -> float:
    """The expected sample size. Products and sums are folded along the tree; minimum and maximum are added up over the
    distinct weights, as the sum of weights times the number of results that have them (counted along the tree)."""
    tree, by_name = build_join_tree(schemas(specs)), {s.name: s for s in specs}
    if algebra.name == "constant":
        return algebra.p * join_size(specs)
    if algebra.name == "product":
        out = _fold(tree, by_name, lambda r: r.withColumn("m", F.col("w")), lambda r: r.withColumn("m", F.col("m") * F.col("_m")), [F.sum("m").alias("m")])
        return out.agg(F.sum("m")).first()[0] or 0.0
    if algebra.name == "sum":
        merge = lambda r: r.withColumns({"m": F.col("m") * F.col("_n") + F.col("n") * F.col("_m"), "n": F.col("n") * F.col("_n")})
        out = _fold(tree, by_name, lambda r: r.withColumns({"m": F.col("w"), "n": F.lit(1.0)}), merge, [F.sum("m").alias("m"), F.sum("n").alias("n")])
        return out.agg(F.sum("m")).first()[0] or 0.0
    return weight_spectrum(specs, algebra).agg(F.sum(F.col("w") * F.col("n"))).first()[0] or 0.0


def weight_spectrum(specs: list[RelationSpec], algebra: Algebra) -> DataFrame:
    """w, n: how many results have each weight, for minimum and maximum (a result's weight is one of its tuples')."""
    pick = F.least if algebra.name == "min" else F.greatest

    def fold(node: Node) -> DataFrame:
        rows = {s.name: s for s in specs}[node.name].narrow().withColumn("n", F.lit(1).cast("long"))
        for c in node.children:
            m = fold(c).select(*c.key, F.col("w").alias("_w"), F.col("n").alias("_n"))
            rows = (rows.join(m, list(c.key)) if c.key else rows.crossJoin(F.broadcast(m))).withColumns({"w": pick("w", "_w"), "n": F.col("n") * F.col("_n")}).drop("_w", "_n")
        return rows.groupBy(*node.key, "w").agg(F.sum("n").alias("n"))

    return fold(build_join_tree(schemas(specs)))


def largest_sum(specs: list[RelationSpec]) -> float:
    """The largest sum of weights that a result has."""
    out = _fold(build_join_tree(schemas(specs)), {s.name: s for s in specs}, lambda r: r.withColumn("m", F.col("w")), lambda r: r.withColumn("m", F.col("m") + F.col("_m")), [F.max("m").alias("m")])
    return out.agg(F.max("m")).first()[0] or 0.0


def candidate_size(index: ScoreIndex) -> float:
    """Expected number of candidates of a draw."""
    return index.buckets.agg(F.sum(F.col("n") * F.col("ceiling"))).first()[0] or 0.0


def overhead(index: ScoreIndex, expected: float) -> float:
    return candidate_size(index) / expected if expected else float("nan")


def index_nonzeros(index: ScoreIndex) -> int:
    return index.nonzeros().agg(F.sum("entries")).first()[0] or 0


def tail_size(index: ScoreIndex) -> int:
    """Results in the last bucket, which collects all scores from the cap on."""
    return index.buckets.where(F.col("score") == index.cap).agg(F.sum("n")).first()[0] or 0


def bucket_uniformity(results: DataFrame, weight: Column, score: Column) -> DataFrame:
    """score, n, beta: the largest weight of a bucket over its least."""
    return results.groupBy(score.alias("score")).agg(F.count("*").alias("n"), (F.max(weight) / F.min(weight)).alias("beta"))


def inclusion_counts(draws: DataFrame, names: list[str]) -> DataFrame:
    """How often each result was drawn."""
    return draws.groupBy(*[f"rid_{n}" for n in names]).agg(F.count("*").alias("times"))


def size_moments(draws: DataFrame, n_draws: int) -> DataFrame:
    """draws, mean, variance of the sample size; draws without a result count."""
    sizes = draws.sparkSession.range(n_draws).select(F.col("id").cast("int").alias("draw")).join(draws.groupBy("draw").agg(F.count("*").alias("size")), "draw", "left")
    size = F.coalesce("size", F.lit(0))
    return sizes.agg(F.count("*").alias("draws"), F.avg(size).alias("mean"), F.var_pop(size).alias("variance"))


def pair_counts(draws: DataFrame, result: str, shared: str, n_draws: int) -> DataFrame:
    """For pairs of results that share a tuple: pairs, and the mean over them of P(both) - P(one) P(other), observed.

    Per draw and shared tuple the number of pairs is a binomial of the number of results, so no pairs are made.
    """
    both = draws.groupBy("draw", shared).agg(F.count("*").alias("k")).groupBy(shared).agg(F.sum(F.col("k") * (F.col("k") - 1) / 2).alias("both"))
    single = draws.groupBy(shared, result).agg((F.count("*") / F.lit(float(n_draws))).alias("f")).groupBy(shared).agg(F.sum("f").alias("s1"), F.sum(F.col("f") * F.col("f")).alias("s2"))
    met = both.join(single, shared)
    return met.agg(F.sum(F.col("both") / n_draws).alias("together"), F.sum((F.col("s1") * F.col("s1") - F.col("s2")) / 2).alias("independent")).withColumn("covariance", F.col("together") - F.col("independent"))


def draw_covariance(draws: DataFrame, names: list[str], n_draws: int) -> DataFrame:
    """Results that are in a draw and in the next one: observed, and expected when draws are independent."""
    keys = [f"rid_{n}" for n in names]
    one = draws.select(*keys, "draw")
    again = one.join(one.withColumn("draw", F.col("draw") - 1), [*keys, "draw"]).count()
    freq = inclusion_counts(draws, names).agg(F.sum(F.pow(F.col("times") / n_draws, 2))).first()[0] or 0.0
    return draws.sparkSession.createDataFrame([(float(again), float(freq * (n_draws - 1)))], "observed double, expected double")


def timed(make: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """Runs the plan into the noop sink."""
    began = time.time()
    df = make()
    df.write.format("noop").mode("overwrite").save()
    return df, time.time() - began


def count_results(specs: list[RelationSpec]) -> DataFrame:
    """relations, tuples, results."""
    spark = specs[0].df.sparkSession
    return spark.createDataFrame([(len(specs), input_size(specs), join_size(specs))], "relations int, tuples long, results long")


def messages(specs: list[RelationSpec], relation: str, algebra: Algebra, cap: int, root: str | None = None) -> DataFrame:
    """The counts by key and score of one node."""
    tree = build_join_tree(schemas(specs), root)
    node = next(n for n in tree.walk() if n.name == relation)
    return message_of(node, {s.name: s for s in specs}, algebra, cap).drop("width")




def plan_shape(df: DataFrame) -> dict[str, int]:
    """How often the costly kinds of operators stand in the plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    kinds = ("Exchange", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "CartesianProduct", "Window", "HashAggregate", "MapInArrow", "Generate", "SinglePartition")
    return {k: len([line for line in text.splitlines() if k in line and (k != "Exchange" or "BroadcastExchange" not in line)]) for k in kinds}

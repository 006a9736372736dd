"""The score index: counts of join results by score, and where each rank of a score lies.

Everything is sums of products over the join tree, one equi-join per tree edge and one aggregation per node:

- a *message* of a node has, for each join key and score, the number of results of the node's subtree (n), and
  the width of the steps by which their ranks are looked up;
- the *places* of a node are its tuples joined with the messages of all its children: a row per tuple and combination
  of child scores, with the product of the counts. In order of (rid, child scores) the running sums of n over the
  places of one key and score cut that score's ranks into intervals.

Scores are only kept where there are results, so the tables are as long as they have entries, and the same plan
serves all algebras, the plain count (constant: one score) and the grid of class combinations (scores are lists).
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import PRODUCT, Algebra, constant
from joinpoisson.functions.arith import div, step_width
from joinpoisson.plans.jointree import Node, build_join_tree
from joinpoisson.plans.relations import RID, WEIGHT, RelationSpec, schemas
from joinpoisson.plans import storage
from joinpoisson.plans.storage import cut, cut_bucketed, running_sum, shared_dir, side

#: Rows of one key and score above which running sums go over range partitions instead of one window.
LARGE_GROUP = 1_000_000
#: Ranks of a child that meet a place at once when all results are listed.
PIECE = 4_096


def tuples_of(spec: RelationSpec, algebra: Algebra, cap: int) -> DataFrame:
    """attrs, rid, w, score of the tuples that can be in a result."""
    rows = spec.narrow()
    for a in spec.attrs:  # nulls never join
        rows = rows.where(F.col(a).isNotNull())
    if algebra.drops_zero:
        rows = rows.where(F.col(WEIGHT) > 0)
    return rows.withColumn("score", algebra.tuple_score(F.col(WEIGHT), cap))


def places_of(node: Node, specs: dict[str, RelationSpec], algebra: Algebra, cap: int, messages: dict[str, DataFrame] | None = None) -> DataFrame:
    """attrs, rid, w, score (of the subtree), n, and for each child its score, count and step width. messages: those of the
    children, if they are there already."""
    rows = tuples_of(specs[node.name], algebra, cap)
    parts, count = [F.col("score")], F.lit(1).cast("long")
    for c in node.children:
        made = messages[c.name] if messages else message_of(c, specs, algebra, cap)
        message = made.select(*c.key, F.col("score").alias(f"score_{c.name}"), F.col("n").alias(f"n_{c.name}"), F.col("width").alias(f"width_{c.name}"))
        rows = rows.join(message, list(c.key)) if c.key else rows.crossJoin(F.broadcast(message))  # no key: a row per score
        parts.append(F.col(f"score_{c.name}"))
        count = count * F.col(f"n_{c.name}")
    return rows.withColumn("score", algebra.combine(parts, cap)).withColumn("n", count)


def message_of(node: Node, specs: dict[str, RelationSpec], algebra: Algebra, cap: int) -> DataFrame:
    """key, score, n of the node's subtree, and the width of the steps that its ranks are looked up by."""
    return _summed(node, places_of(node, specs, algebra, cap)).drop("places")


def _summed(node: Node, places: DataFrame) -> DataFrame:
    sums = places.groupBy(*node.key, "score").agg(F.sum("n").alias("n"), F.count("*").alias("places"))
    return sums.withColumn("width", step_width(F.col("n"), F.col("places")))


def join_size(specs: list[RelationSpec], root: str | None = None) -> int:
    """The number of join results, without making them."""
    tree = build_join_tree(schemas(specs), root)
    return message_of(tree, {s.name: s for s in specs}, constant(1.0), 0).agg(F.sum("n")).first()[0] or 0


def choose_cap(specs: list[RelationSpec], algebra: Algebra, policy: str = "exact") -> int:
    """exact: the least cap at which the last score's weights are at most 1 / results. bound: twice the edge cover
    number times log2 of the number of tuples, without counting results."""
    from joinpoisson.plans.jointree import edge_cover_number

    if algebra.name == "constant":
        return 0
    if policy == "exact":
        return algebra.enough_cap(join_size(specs), len(specs))
    tuples = sum(s.df.count() for s in specs)
    return max(1, math.ceil(2 * edge_cover_number(schemas(specs)) * math.log2(max(2, tuples))))


def reduce_relations(specs: list[RelationSpec], root: str | None = None) -> list[RelationSpec]:
    """The relations without the tuples that are in no result: semi-joins up the tree, then down."""
    tree = build_join_tree(schemas(specs), root)
    now = {s.name: s.narrow() for s in specs}

    def semi(left: str, right: str, key: tuple[str, ...]) -> None:
        now[left] = now[left].join(now[right].select(*key).distinct(), list(key), "left_semi") if key else now[left]

    for node in reversed(tree.walk()):
        for c in node.children:
            semi(node.name, c.name, c.key)
    for node in tree.walk():
        for c in node.children:
            semi(c.name, node.name, c.key)
    return [RelationSpec(s.name, now[s.name], s.attrs) for s in specs]


def intervals_of(node: Node, places: DataFrame, large: int = LARGE_GROUP, largest: int | None = None) -> DataFrame:
    """The places with lo, hi: the ranks of their key and score that lie in them, from 1. largest: the most places of a key
    and score, if known."""
    groups, order = [*node.key, "score"], [RID, *[f"score_{c.name}" for c in node.children]]
    if largest is None:
        largest = places.groupBy(*groups).count().agg(F.max("count")).first()[0] or 0
    if largest > large:
        run = running_sum(places, groups, order, "n", "hi")
    else:
        run = places.withColumn("hi", F.sum("n").over(Window.partitionBy(*groups).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return run.withColumn("lo", F.col("hi") - F.col("n"))


def stepped(node: Node, intervals: DataFrame, totals: DataFrame) -> DataFrame:
    """The intervals under each step (_step) that they meet; _first: under their first one. totals: key, score, width."""
    groups = [*node.key, "score"]
    met = intervals.join(totals.select(*groups, F.col("width").alias("_width")), groups)
    first, last = div(F.col("lo"), F.col("_width")), div(F.col("hi") - 1, F.col("_width"))
    return met.withColumn("_step", F.explode(F.sequence(first, last))).withColumn("_first", F.col("_step") == first).drop("_width")


def buckets_of(root: DataFrame, algebra: Algebra, relations: int) -> DataFrame:
    """score, n, width, ceiling from the root's intervals."""
    sizes = root.groupBy("score").agg(F.sum("n").alias("n"), F.count("*").alias("places"))
    return sizes.select("score", "n", step_width(F.col("n"), F.col("places")).alias("width"), algebra.ceiling(F.col("score"), relations).alias("ceiling"))


@dataclass
class ScoreIndex:
    """Interval tables of all nodes and the buckets (score, n, width, ceiling) at the root."""

    tree: Node
    algebra: Algebra
    cap: int
    intervals: dict[str, DataFrame]
    buckets: DataFrame
    names: list[str] = field(default_factory=list)
    #: The intervals under their steps, as look-ups want them. Stored ones lie in hash buckets of (key, score, step), so that
    #: a draw moves its candidates only.
    steps: dict[str, DataFrame] = field(default_factory=dict)
    #: The number of places of each node, where it is known.
    places: dict[str, int] = field(default_factory=dict)

    @classmethod
    def build(cls, specs: list[RelationSpec], algebra: Algebra = PRODUCT, cap: int | str = "exact", root: str | None = None, store: bool = True, large: int = LARGE_GROUP) -> ScoreIndex:
        """root: the relation at the top, by default the first by name. store: write the tables once for many draws.
        Messages are made once each, from the leaves up, and written either way: they are no longer than the relations
        times the scores that a key has."""
        tree = build_join_tree(schemas(specs), root)
        level = cap if isinstance(cap, int) else choose_cap(specs, algebra, cap)
        by_name = {s.name: s for s in specs}
        messages, tables, steps, held = {}, {}, {}, {}
        for n in reversed(tree.walk()):
            places = places_of(n, by_name, algebra, level, messages)
            message = cut(_summed(n, places), f"message-{n.name}")
            entries, largest, total = message.agg(F.count("*"), F.max("places"), F.sum("places")).first()
            messages[n.name], largest, held[n.name] = side(message, entries), largest or 0, total or 0
            tables[n.name] = intervals_of(n, places, large, largest)
            steps[n.name] = stepped(n, tables[n.name], messages[n.name])
            if store:
                keys = [*n.key, "score", "_step"]
                listed = messages[n.name].schema["score"].dataType.typeName() == "array"  # no hash buckets of lists
                steps[n.name] = cut(steps[n.name], f"steps-{n.name}") if listed else cut_bucketed(steps[n.name], f"steps-{n.name}", keys)
                tables[n.name] = steps[n.name].where("_first").drop("_step", "_first")
        buckets = messages[tree.name].select("score", "n", "width", algebra.ceiling(F.col("score"), len(specs)).alias("ceiling"))
        return cls(tree, algebra, level, tables, cut(buckets, "buckets") if store else buckets, tree.names, steps, held)

    def save(self, path: str) -> None:
        """Write the index; the tables are sorted by key, score and step within their files."""
        for n in self.tree.walk():
            self.steps[n.name].sortWithinPartitions(*n.key, "score", "_step", "lo").write.mode("overwrite").parquet(f"{path}/steps/{n.name}")
        self.buckets.write.mode("overwrite").parquet(f"{path}/buckets")
        meta = json.dumps({"algebra": self.algebra.name, "p": self.algebra.p, "cap": self.cap, "tree": _plain(self.tree)})
        self.buckets.sparkSession.createDataFrame([(meta,)], "meta string").write.mode("overwrite").parquet(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> ScoreIndex:
        meta = json.loads(spark.read.parquet(f"{path}/meta").first()[0])
        tree = _node(meta["tree"])
        steps = {n.name: spark.read.parquet(f"{path}/steps/{n.name}") for n in tree.walk()}
        tables = {name: t.where("_first").drop("_step", "_first") for name, t in steps.items()}
        return cls(tree, Algebra(meta["algebra"], meta["p"]), meta["cap"], tables, spark.read.parquet(f"{path}/buckets"), tree.names, steps)

    def size(self) -> int:
        return self.buckets.agg(F.sum("n")).first()[0] or 0

    def nonempty(self) -> DataFrame:
        """buckets with q: the probability that a draw has a candidate there."""
        from joinpoisson.functions.rng import nonempty_probability

        return self.buckets.withColumn("q", nonempty_probability(F.col("ceiling"), F.col("n")))

    def access(self, requests: DataFrame) -> DataFrame:
        """requests (score, rank, ...) -> the results at these ranks; (score, first, last, ...) -> those at the ranks from first to last."""
        from joinpoisson.operators.access import descend

        return descend(self, requests)

    def enumerate(self, scores: list[int] | None = None, node: Node | None = None) -> DataFrame:
        """All results of the given scores (of all; node: of its subtree alone), with their ranks, from the intervals up: a result's rank at a node is where
        its tuple's interval begins and the mixed number of its ranks in the children. No rank is looked up. A child of many
        places meets its parent in pieces of PIECE ranks over all tasks: intervals are few bytes, and a planner that goes by
        bytes would make all their results in a few tasks."""
        tasks = int(self.buckets.sparkSession.conf.get("spark.sql.shuffle.partitions"))

        def listed(node: Node) -> DataFrame:
            rows = self.intervals[node.name].withColumnsRenamed({RID: f"rid_{node.name}", WEIGHT: f"w_{node.name}"})
            if node is self.tree and scores is not None:
                rows = rows.where(F.col("score").isin(scores))
            rank, have = F.col("lo") + 1, list(node.attrs)
            below, rest = {}, F.lit(1).cast("long")
            for c in reversed(node.children):  # the last child's rank moves fastest
                below[c.name] = listed(c)
                rank = rank + (F.col(f"rank_{c.name}") - 1) * rest
                rest = rest * F.col(f"n_{c.name}")
            for c in node.children:
                got = below[c.name].withColumnsRenamed({"score": f"score_{c.name}", "rank": f"rank_{c.name}"})
                fresh = [a for a in got.columns if a not in have]
                here = got.select(*[F.col(k).alias(f"_k_{k}") for k in c.key], *fresh).withColumnRenamed(f"score_{c.name}", "_is")
                left, right = [*c.key, f"score_{c.name}"], [*[f"_k_{k}" for k in c.key], "_is"]
                if (self.places[c.name] if c.name in self.places else self.intervals[c.name].count()) > storage.FEW:
                    rows = rows.withColumn("_piece", F.explode(F.sequence(F.lit(0).cast("long"), div(F.col(f"n_{c.name}") - 1, F.lit(PIECE)))))
                    here = here.withColumn("_in", div(F.col(f"rank_{c.name}") - 1, F.lit(PIECE)))
                    left, right = [*left, "_piece"], [*right, "_in"]
                    rows, here = rows.repartition(tasks, *left), here.repartition(tasks, *right).hint("merge")
                rows = rows.join(here, [F.col(a) == F.col(b) for a, b in zip(left, right, strict=True)]).drop("_piece", *right)
                have = list(dict.fromkeys([*have, *(a for x in c.walk() for a in x.attrs)]))
            ids = [x for n in node.names for x in (f"rid_{n}", f"w_{n}")]
            return rows.withColumn("rank", rank).select("score", "rank", *have, *ids)

        return listed(node or self.tree)

    def nonzeros(self) -> DataFrame:
        """relation, entries: the size of the index."""
        parts = [t.agg(F.count("*").alias("entries")).select(F.lit(n).alias("relation"), "entries") for n, t in self.intervals.items()]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def sample(self, seed: int, draw: int = 0, draws: int = 1, gate: bool = False, bulk: bool = False) -> DataFrame:
        from joinpoisson.operators.sampler import sample_index

        return sample_index(self, seed, draw, draws, gate, bulk)


def _plain(n: Node) -> list:
    return [n.name, list(n.attrs), list(n.key), [_plain(c) for c in n.children]]


def _node(x: list) -> Node:
    return Node(x[0], tuple(x[1]), tuple(x[2]), [_node(c) for c in x[3]])


__all__ = ["LARGE_GROUP", "ScoreIndex", "choose_cap", "intervals_of", "join_size", "message_of", "places_of", "reduce_relations", "shared_dir", "stepped", "tuples_of"]

"""Ranked access: from (score, rank) to the join result, for all requests at once, a node of the tree at a time.

A request carries, for every node that it has not reached, the score and rank that it needs there. At a node it is
joined with the interval that holds its rank; the rank within the interval is split into ranks of the children.

Interval lookup is an equi-join: the ranks of one key and score are cut into as many steps of equal width as there are
intervals, every interval is listed under the steps that it meets (about two), and a request only looks under the step
of its own rank. Ranks are drawn uniformly, so a look-up meets two intervals on average and no step is crowded,
however many tuples a key has. The `merge` strategy sorts intervals and requests together instead.

Requests for runs of ranks (first, last) go down the tree as runs: of a node's children the last one gets the run, as its rank
moves fastest, and the others a rank each. A run meets the intervals of RUN steps at once, and a result becomes a row where
the last node is reached; no row per result is moved.

Look-ups are sort-merge joins by hint: requests come out of a table of a few buckets, so a planner takes them for few and
would broadcast them, by way of the driver, however many they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from joinpoisson.functions.arith import div, step_width
from joinpoisson.operators.index import stepped
from joinpoisson.plans.jointree import Node
from joinpoisson.plans.relations import RID, WEIGHT

#: Steps whose intervals a run meets at once.
RUN = 512


def _stepped(node: Node, intervals: DataFrame) -> DataFrame:
    """The intervals under each step that they meet, for an index that keeps no steps."""
    totals = intervals.groupBy(*node.key, "score").agg(F.max("hi").alias("_total"), F.count("*").alias("_places"))
    return stepped(node, intervals, totals.withColumn("width", step_width(F.col("_total"), F.col("_places"))))


def descend(index, requests: DataFrame, strategy: str = "steps") -> DataFrame:
    """requests: score, rank and any columns of their own, or first and last instead of rank, for each rank from first to last.
    Adds the tree's attributes, rid_<relation> and w_<relation>."""
    tree = index.tree
    if "rank" not in requests.columns:
        return _descend_runs(index, requests)
    own = list(requests.columns)
    rows = requests.join(F.broadcast(index.buckets.select("score", F.col("width").alias(f"_d_{tree.name}"))), "score")
    rows = rows.withColumns({f"_s_{tree.name}": F.col("score"), f"_r_{tree.name}": F.col("rank")})
    have: list[str] = []
    for node in tree.walk():
        kept = index.steps.get(node.name) if strategy == "steps" else None
        rows, have = _locate(node, index.intervals[node.name] if kept is None else kept, rows, have, strategy)
    ids = [c for n in tree.names for c in (f"rid_{n}", f"w_{n}")]
    return rows.select(*own, *have, *ids)


def _locate(node: Node, intervals: DataFrame, rows: DataFrame, have: list[str], strategy: str) -> tuple[DataFrame, list[str]]:
    name, fresh = node.name, [a for a in node.attrs if a not in have]
    inner = [f"score_{c.name}" for c in node.children] + [f"n_{c.name}" for c in node.children] + [f"width_{c.name}" for c in node.children]
    if strategy == "steps" and "_step" not in intervals.columns:
        intervals = _stepped(node, intervals)
    table = intervals.select(*[F.col(k).alias(f"_k_{k}") for k in node.key], F.col("score").alias("_is"), "lo", "hi", F.col(RID).alias(f"rid_{name}"), F.col(WEIGHT).alias(f"w_{name}"), *fresh, *inner, *(["_step"] if "_step" in intervals.columns else []))
    score, rank = F.col(f"_s_{name}"), F.col(f"_r_{name}")
    same = [F.col(k) == F.col(f"_k_{k}") for k in node.key] + [score == F.col("_is")]
    if strategy == "steps":
        asked = rows.withColumn("_at", div(rank - 1, F.col(f"_d_{name}")))
        on = [*same, F.col("_at") == F.col("_step"), rank > F.col("lo"), rank <= F.col("hi")]
        met = asked.join(table.hint("merge"), on).drop("_at", "_step")
    else:
        met = _merged(node, table, rows, same, name)
    out = _split(node.children, rank - F.col("lo") - 1)
    met = met.withColumns(out) if out else met
    gone = [f"_s_{name}", f"_r_{name}", f"_d_{name}", "lo", "hi", "_is", *[f"_k_{k}" for k in node.key], *inner]
    return met.drop(*gone), have + fresh


def _split(children: list[Node], within: Column) -> dict[str, Column]:
    """Score, width and rank for each child of the result at `within`, from 0; the last child's rank moves fastest."""
    out, rest = {}, F.lit(1).cast("long")
    for c in reversed(children):
        count = F.col(f"n_{c.name}")
        out |= {f"_s_{c.name}": F.col(f"score_{c.name}"), f"_d_{c.name}": F.col(f"width_{c.name}"), f"_r_{c.name}": div(within, rest) % count + 1}
        rest = rest * count
    return out


def _descend_runs(index, requests: DataFrame) -> DataFrame:
    """`descend` for runs: the root, its last child, the last child of that and so on are met by runs (_f to _l, the first of
    them of rank `rank`), all other nodes by single ranks."""
    tree = index.tree
    own = [c for c in requests.columns if c not in ("first", "last")]
    rows = requests.join(F.broadcast(index.buckets.select("score", F.col("width").alias(f"_d_{tree.name}"))), "score")
    rows = rows.withColumns({f"_s_{tree.name}": F.col("score"), "_f": F.col("first"), "_l": F.col("last"), "rank": F.col("first")}).drop("first", "last")
    have, by_run = [], tree
    for node in tree.walk():
        kept = index.steps.get(node.name)
        intervals = index.intervals[node.name] if kept is None else kept
        if node is by_run:
            rows, have = _locate_runs(node, intervals, rows, have)
            by_run = node.children[-1] if node.children else None
        else:
            rows, have = _locate(node, intervals, rows, have, "steps")
    ids = [c for n in tree.names for c in (f"rid_{n}", f"w_{n}")]
    return rows.select(*own, "rank", *have, *ids)


def _locate_runs(node: Node, intervals: DataFrame, rows: DataFrame, have: list[str]) -> tuple[DataFrame, list[str]]:
    name, fresh = node.name, [a for a in node.attrs if a not in have]
    inner = [f"{x}_{c.name}" for c in node.children for x in ("score", "n", "width")]
    if "_step" not in intervals.columns:
        intervals = _stepped(node, intervals)
    intervals = intervals.where(F.col("_first") | (F.col("_step") % RUN == 0))  # once for each RUN steps that they meet
    table = intervals.select(*[F.col(k).alias(f"_k_{k}") for k in node.key], F.col("score").alias("_is"), div(F.col("_step"), F.lit(RUN)).alias("_in"), "lo", "hi", F.col(RID).alias(f"rid_{name}"), F.col(WEIGHT).alias(f"w_{name}"), *fresh, *inner)
    length = F.col(f"_d_{name}") * RUN
    parts = rows.withColumn("_piece", F.explode(F.sequence(div(F.col("_f") - 1, length), div(F.col("_l") - 1, length))))
    parts = _trimmed(parts, F.col("_piece") * length, (F.col("_piece") + 1) * length)
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # as a planner would take short rows for few results
    left, right = [*node.key, f"_s_{name}", "_piece"], [*[f"_k_{k}" for k in node.key], "_is", "_in"]
    on = [*[F.col(a) == F.col(b) for a, b in zip(left, right, strict=True)], F.col("_f") <= F.col("hi"), F.col("_l") > F.col("lo")]
    met = parts.repartition(tasks, *left).join(table.repartition(tasks, *right).hint("merge"), on)
    met = _trimmed(met, F.col("lo"), F.col("hi"))
    if node.children:
        *others, last = node.children
        count, start, end = F.col(f"n_{last.name}"), F.col("_f") - F.col("lo") - 1, F.col("_l") - F.col("lo") - 1
        met = met.withColumns({"_f": start, "_l": end}).withColumn("_outer", F.explode(F.sequence(div(F.col("_f"), count), div(F.col("_l"), count))))
        met = _trimmed(met.withColumns({"_f": F.col("_f") + 1, "_l": F.col("_l") + 1}), F.col("_outer") * count, (F.col("_outer") + 1) * count)
        below = {f"_s_{last.name}": F.col(f"score_{last.name}"), f"_d_{last.name}": F.col(f"width_{last.name}"), "_f": F.col("_f") - F.col("_outer") * count, "_l": F.col("_l") - F.col("_outer") * count}
        met = met.withColumns(below | _split(others, F.col("_outer"))).drop("_outer")
    return met.drop(f"_s_{name}", f"_d_{name}", "lo", "hi", "_piece", *right, *inner), have + fresh


def _trimmed(runs: DataFrame, lo: Column, hi: Column) -> DataFrame:
    """What of the runs lies in ranks lo + 1 to hi."""
    first = F.greatest(F.col("_f"), lo + 1)
    return runs.withColumns({"rank": F.col("rank") + first - F.col("_f"), "_f": first, "_l": F.least(F.col("_l"), hi)})


def _merged(node: Node, table: DataFrame, rows: DataFrame, same: list[Column], name: str) -> DataFrame:
    """Intervals and requests of a key and score in one order of rank; a request takes the last interval that began."""
    keys = [f"_k_{k}" for k in node.key] + ["_is"]
    marks = table.select(*keys, (F.col("lo") + 1).alias("_at"), F.struct(*[F.col(f"`{c}`") for c in table.columns if c not in keys]).alias("_iv"))
    asked = rows.select(*[F.col(k).alias(f"_k_{k}") for k in node.key], F.col(f"_s_{name}").alias("_is"), F.col(f"_r_{name}").alias("_at"), F.struct(*rows.columns).alias("_rq"))
    both = marks.withColumn("_rq", F.lit(None).cast(asked.schema["_rq"].dataType)).unionByName(asked.withColumn("_iv", F.lit(None).cast(marks.schema["_iv"].dataType)))
    order = Window.partitionBy(*keys).orderBy("_at", F.col("_rq").isNotNull()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = both.withColumn("_iv", F.last("_iv", ignorenulls=True).over(order)).where(F.col("_rq").isNotNull())
    return found.select("_rq.*", *keys, "_iv.*")

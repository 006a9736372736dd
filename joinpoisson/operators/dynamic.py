"""Insertions in batches: a maintained index and a maintained sample.

All state lies in runs by batch number, so that a batch that runs again overwrites its own run and reads only the runs
before it. A batch is a set of insertions; after it the state is as if they had come one by one.

The index keeps, for each node, key and score, the raw count and the count rounded up to a power of two; parents only
see the rounded one. So an insertion changes a parent only when a rounded count moves, which happens at most as often as
it can double. Ranks between the raw and the rounded count name no result and are dropped on the way down. A batch's
change of a node's counts is a sum of joins: its new tuples with the children's counts, and for each child the old
tuples with that child's moved entries alone. Runs of counts are merged like the digits of a binary counter, so that a
reader meets about log2(batches) of them; the capacity and the number of tuples are stored with each batch.

The sample adds, for each batch, a sample of the results that the batch makes: relation by relation the join of its new
tuples with the relations before it (with their new tuples) and behind it (without).
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import PRODUCT, Algebra, round_up_pow2
from joinpoisson.functions.arith import step_width
from joinpoisson.functions.rng import u01_value
from joinpoisson.operators.baselines import naive_sample
from joinpoisson.operators.index import ScoreIndex, buckets_of, intervals_of, tuples_of
from joinpoisson.operators.sampler import sample_join
from joinpoisson.plans.jointree import Node, build_join_tree, edge_cover_number
from joinpoisson.plans.relations import RelationSpec
from joinpoisson.plans.storage import cut, side


class UnsupportedOperation(RuntimeError):
    """Deletions: they would cost the square root of the input each, so they are left to a rebuild."""


@dataclass
class TupleRuns:
    """The tuples of all relations, in runs by batch; a tuple that is there already is not added again."""

    spark: SparkSession
    path: str
    attrs: dict[str, tuple[str, ...]]

    def _dir(self, name: str) -> str:
        return f"{self.path}/tuples/{name}"

    def read(self, name: str, before: int, since: int = -1) -> DataFrame | None:
        """The tuples of batches since < batch < before; None where there is no run."""
        runs = [b for b in self.batches(name) if since < b < before]
        if not runs:
            return None
        return self.spark.read.parquet(*[f"{self._dir(name)}/batch={b}" for b in runs])

    def batches(self, name: str) -> list[int]:
        jvm = self.spark.sparkContext._jvm
        top = jvm.org.apache.hadoop.fs.Path(self._dir(name))
        fs = top.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(top):
            return []
        return sorted(int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(top) if s.getPath().getName().startswith("batch="))

    def add(self, batch: int, new: dict[str, DataFrame]) -> dict[str, DataFrame]:
        """Writes the tuples that are not there yet; returns them by relation."""
        added = {}
        for name, df in new.items():
            attrs = list(self.attrs[name])
            fresh = df.select(*attrs, F.col("rid").cast("long").alias("rid"), F.col("w").cast("double").alias("w"))
            for a in attrs:
                fresh = fresh.where(F.col(a).isNotNull())
            fresh = fresh.groupBy(*attrs).agg(F.min(F.struct("rid", "w")).alias("t")).select(*attrs, "t.rid", "t.w")
            old = self.read(name, batch)
            if old is not None:
                fresh = fresh.join(side(old.select(*attrs)), attrs, "left_anti")
            where = f"{self._dir(name)}/batch={batch}"
            fresh.write.mode("overwrite").parquet(where)
            added[name] = self.spark.read.schema(fresh.schema).parquet(where)
        return added


@dataclass
class MessageRuns:
    """The counts of one node in runs; a run holds the last state of what the batches after `since` up to its own changed.
    A batch that runs again reads the runs before it only, so it merges the same ones and replaces its own."""

    spark: SparkSession
    path: str

    def _files(self):
        top = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        return top.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), top

    def chain(self, before: int) -> list[tuple[int, int]]:
        """(batch, since) of the runs that make up the state before a batch, newest first."""
        fs, top = self._files()
        if not fs.exists(top):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(top)]
        runs = sorted((tuple(map(int, n.split("=")[1].split("~"))) for n in names if n.startswith("batch=")), reverse=True)
        out, top_batch = [], before - 1
        for batch, since in runs:
            if batch <= top_batch:
                out.append((batch, since))
                top_batch = since
        return out

    def _where(self, batch: int, since: int) -> str:
        return f"{self.path}/batch={batch}~{since}"

    def _rows(self, runs: list[tuple[int, int]]) -> DataFrame | None:
        return self.spark.read.parquet(*[self._where(*r) for r in runs]) if runs else None

    @staticmethod
    def _latest(rows: DataFrame, groups: list[str]) -> DataFrame:
        rest = [c for c in rows.columns if c not in groups]
        return rows.groupBy(*groups).agg(F.max_by(F.struct(*rest), "_batch").alias("_last")).select(*groups, "_last.*")

    def read(self, before: int, groups: list[str]) -> DataFrame | None:
        runs = self.chain(before)
        rows = self._rows(runs)
        return rows if rows is None else side(rows) if len(runs) == 1 else self._latest(rows, groups)

    def write(self, batch: int, rows: DataFrame, groups: list[str], whole: bool = False) -> DataFrame:
        """Adds a batch's rows, merged with the runs behind it that are no longer than the merged one; whole: the rows
        are all of the state. Returns the batch's own rows."""
        merged, since = [], -1
        if not whole:
            held = self.chain(batch)
            since = held[0][0] if held else -1
            for run in held:
                if run[0] - run[1] > batch - since:
                    break
                merged.append(run)
                since = run[1]
        new = rows.withColumn("_batch", F.lit(batch))
        if merged:
            new = self._latest(new.unionByName(self._rows(merged)), groups)
        fs, top = self._files()
        if fs.exists(top):
            for s in fs.listStatus(top):
                if s.getPath().getName().startswith(f"batch={batch}~"):
                    fs.delete(s.getPath(), True)
        new.write.parquet(self._where(batch, since))
        return self.spark.read.schema(new.schema).parquet(self._where(batch, since)).where(F.col("_batch") == batch)


def _union(*frames: DataFrame | None) -> DataFrame | None:
    out = None
    for f in frames:
        if f is not None:
            out = f if out is None else out.unionByName(f)
    return out


def delta_joins(state: TupleRuns, batch: int, added: dict[str, DataFrame]) -> list[tuple[str, list[RelationSpec]]]:
    """The batch's new results as disjoint joins, each named by the relation whose new tuples it has."""
    out = []
    names = list(state.attrs)
    for i, name in enumerate(names):
        if name not in added:
            continue
        parts = {}
        for j, other in enumerate(names):
            old = state.read(other, batch)
            parts[other] = added[other] if j == i else _union(old, added.get(other)) if j < i else old
        if all(p is not None for p in parts.values()):
            out.append((name, [RelationSpec(n, p, state.attrs[n]) for n, p in parts.items()]))
    return out


def delta_seed(seed: int, batch: int, delta: int) -> int:
    """The seed of one delta join of one batch."""
    return int(u01_value(seed, "batch", batch, delta) * (1 << 31))


@dataclass
class MaintainedSample:
    """One sample of the join, kept up as tuples come. exact_coins: results toss the coins that the join-first baseline
    gives them, so that the sample equals the baseline's; else each batch's results are sampled through an index, under
    `cap` as in `sample_join` and a seed of their own (`delta_seed`)."""

    spark: SparkSession
    path: str
    attrs: dict[str, tuple[str, ...]]
    algebra: Algebra = PRODUCT
    seed: int = 0
    exact_coins: bool = False
    cap: int | str = "exact"

    @property
    def state(self) -> TupleRuns:
        return TupleRuns(self.spark, self.path, self.attrs)

    def insert(self, batch: int, new: dict[str, DataFrame]) -> None:
        added = self.state.add(batch, new)
        for i, (name, specs) in enumerate(delta_joins(self.state, batch, added)):
            if self.exact_coins:
                got = naive_sample(specs, self.algebra, self.seed)
            else:
                got = sample_join(specs, self.algebra, delta_seed(self.seed, batch, i), cap=self.cap, root=name)
            shown = [a for a in dict.fromkeys(a for s in specs for a in s.attrs)] + [c for n in self.attrs for c in (f"rid_{n}", f"w_{n}")]
            got.select(*shown, "weight").write.mode("overwrite").parquet(f"{self.path}/sample/batch={batch}/delta={i}")

    def delete(self, *_: object) -> None:
        raise UnsupportedOperation("delete tuples from the tables and rebuild")

    def current(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/sample").drop("batch", "delta")


@dataclass
class DynamicIndex:
    """Counts by key and score under insertions. rounded=False keeps exact counts (every change then travels up)."""

    spark: SparkSession
    path: str
    attrs: dict[str, tuple[str, ...]]
    algebra: Algebra = PRODUCT
    capacity: int = 1 << 20  # to begin with; what it has grown to is stored with each batch
    root: str | None = None
    rounded: bool = True
    changes: list[tuple[int, str, int]] = field(default_factory=list)
    seconds: list[tuple[int, float]] = field(default_factory=list)

    @property
    def tree(self) -> Node:
        return build_join_tree(self.attrs, self.root)

    @property
    def cap(self) -> int:
        """As of the last batch."""
        return self.cap_of(self.size_before(1 << 31)[0])

    def cap_of(self, capacity: int) -> int:
        """Twice the edge cover number times the logarithm of the capacity."""
        return 0 if self.algebra.name == "constant" else max(1, 2 * edge_cover_number(self.attrs) * (capacity - 1).bit_length())

    @property
    def state(self) -> TupleRuns:
        return TupleRuns(self.spark, self.path, self.attrs)

    def size_before(self, before: int) -> tuple[int, int]:
        """Capacity and number of tuples as of the batches before the given one."""
        sizes = TupleRuns(self.spark, f"{self.path}/sizes", self.attrs)
        runs = [b for b in sizes.batches("all") if b < before]
        if not runs:
            return self.capacity, 0
        row = self.spark.read.parquet(f"{sizes._dir('all')}/batch={runs[-1]}").first()
        return row["capacity"], row["tuples"]

    def _runs(self, node: Node) -> MessageRuns:
        return MessageRuns(self.spark, f"{self.path}/messages/{node.name}")

    def messages(self, node: Node, before: int) -> DataFrame | None:
        """key, score, raw, n (what the parent sees), places, as of the batches before the given one."""
        rows = self._runs(node).read(before, [*node.key, "score"])
        return None if rows is None else rows.select(*node.key, "score", "raw", "n", "places")

    def _places(self, node: Node, tuples: DataFrame | None, below: dict[str, DataFrame | None], cap: int) -> DataFrame | None:
        """The places of some tuples under the children's messages; None where a child has none. A message may carry
        `born`, what a place under it adds to the number of places (1 where it has no such column)."""
        if tuples is None or any(below[c.name] is None for c in node.children):
            return None
        rows = tuples_of(RelationSpec(node.name, tuples, node.attrs), self.algebra, cap)
        parts, count, born = [F.col("score")], F.lit(1).cast("long"), F.lit(1).cast("long")
        for c in node.children:
            held = below[c.name]
            own = F.col("born") if "born" in held.columns else F.lit(1).cast("long")
            m = held.select(*c.key, F.col("score").alias(f"score_{c.name}"), F.col("n").alias(f"n_{c.name}"), step_width(F.col("raw"), F.col("places")).alias(f"width_{c.name}"), own.alias(f"born_{c.name}"))
            rows = rows.join(m, list(c.key)) if c.key else rows.crossJoin(F.broadcast(m))  # no key: a row per score
            parts.append(F.col(f"score_{c.name}"))
            count, born = count * F.col(f"n_{c.name}"), born * F.col(f"born_{c.name}")
        found = rows.withColumn("score", self.algebra.combine(parts, cap)).withColumn("n", count).withColumn("born", born)
        return found.drop(*[f"born_{c.name}" for c in node.children])

    def insert(self, batch: int, new: dict[str, DataFrame]) -> None:
        begun = time.monotonic()
        added = self.state.add(batch, new)
        capacity, tuples = self.size_before(batch)
        total = tuples + sum(t.count() for t in added.values())
        grown = max(capacity, 1 << max(0, total - 1).bit_length()) if total > capacity else capacity
        if grown > capacity:
            self._rebuild(batch, self.cap_of(grown))
        else:
            self._update(batch, added, self.cap_of(capacity))
        where = TupleRuns(self.spark, f"{self.path}/sizes", self.attrs)._dir("all")
        self.spark.createDataFrame([(grown, total)], "capacity long, tuples long").coalesce(1).write.mode("overwrite").parquet(f"{where}/batch={batch}")
        self.capacity = grown
        self.seconds.append((batch, time.monotonic() - begun))

    def _update(self, batch: int, added: dict[str, DataFrame], cap: int) -> None:
        before: dict[str, DataFrame | None] = {}
        after: dict[str, DataFrame | None] = {}
        moved: dict[str, DataFrame | None] = {}
        for node in reversed(self.tree.walk()):
            groups, own = [*node.key, "score"], self._runs(node)
            held = self.messages(node, batch)
            parts = [self._places(node, added.get(node.name), after, cap)]
            old = self.state.read(node.name, batch)
            for i, c in enumerate(node.children):  # children before c as they are now, those behind it as they were
                if old is not None and moved[c.name] is not None:
                    now = {x.name: moved[x.name] if j == i else after[x.name] if j < i else before[x.name] for j, x in enumerate(node.children)}
                    parts.append(self._places(node, old, now, cap))
            change = _union(*[None if p is None else p.select(*groups, "n", "born") for p in parts])
            before[node.name], after[node.name], moved[node.name] = held, held, None
            if change is None:
                continue
            delta = change.groupBy(*groups).agg(F.sum("n").alias("_d"), F.sum("born").alias("_dp")).where("_d != 0 or _dp != 0")
            none = F.lit(0).cast("long")
            if held is None:
                rows = delta.select(*groups, F.col("_d").alias("raw"), none.alias("was"), F.col("_dp").alias("places"))
            else:
                rows = delta.join(held, groups, "left").select(*groups, (F.coalesce("raw", none) + F.col("_d")).alias("raw"), F.coalesce("n", none).alias("was"), (F.coalesce("places", none) + F.col("_dp")).alias("places"))
            run = own.write(batch, rows.withColumn("n", self._seen()), groups)
            here = run.where("n != was")
            count = here.count()
            self.changes.append((batch, node.name, count))
            moved[node.name] = side(here, count).select(*groups, "raw", "places", (F.col("n") - F.col("was")).alias("n"), F.when(F.col("was") == 0, 1).otherwise(0).cast("long").alias("born"))
            after[node.name] = self.messages(node, batch + 1)

    def _seen(self):
        return round_up_pow2(F.col("raw")) if self.rounded else F.col("raw")

    def _rebuild(self, batch: int, cap: int) -> None:
        """All messages anew, from all tuples: after the capacity, and so the cap, has grown."""
        below: dict[str, DataFrame | None] = {}
        for node in reversed(self.tree.walk()):
            groups = [*node.key, "score"]
            places = self._places(node, self.state.read(node.name, batch + 1), below, cap)
            below[node.name] = None
            if places is not None:
                held, none = self.messages(node, batch), F.lit(0).cast("long")
                sums = places.groupBy(*groups).agg(F.sum("n").alias("raw"), F.count("*").alias("places")).withColumn("n", self._seen())
                old = sums.withColumn("was", none) if held is None else sums.join(held.select(*groups, F.col("n").alias("was")), groups, "left").withColumn("was", F.coalesce("was", none))
                run = self._runs(node).write(batch, old.select(*groups, "raw", "was", "places", "n"), groups, whole=True)
                self.changes.append((batch, node.name, run.where("n != was").count()))
                below[node.name] = self.messages(node, batch + 1)

    def index(self, version: int) -> ScoreIndex:
        """The index as of the given batch. Its buckets hold ranks without a result where counts are rounded."""
        cap = self.cap_of(self.size_before(version + 1)[0])
        below = {n.name: self.messages(n, version + 1) for n in self.tree.walk()}
        tables, held = {}, {}
        for node in self.tree.walk():
            places = self._places(node, self.state.read(node.name, version + 1), below, cap)
            if places is None:
                raise ValueError("no results yet")
            tables[node.name] = cut(intervals_of(node, places.drop("born")), "dynamic")
            held[node.name] = tables[node.name].count()
        buckets = cut(buckets_of(tables[self.tree.name], self.algebra, len(self.attrs)), "buckets")
        return ScoreIndex(self.tree, self.algebra, cap, tables, buckets, self.tree.names, places=held)

    def sample(self, version: int, seed: int, draw: int = 0, draws: int = 1, bulk: bool = False) -> DataFrame:
        return self.index(version).sample(seed, draw, draws, bulk=bulk)

    def delete(self, *_: object) -> None:
        raise UnsupportedOperation("delete tuples from the tables and rebuild")


def density(index: ScoreIndex) -> DataFrame:
    """ranks, results, dummies, density: how many ranks of the buckets name a result."""
    real = index.enumerate().groupBy("score").agg(F.count("*").alias("results"))
    met = index.buckets.join(real, "score", "left").agg(F.sum("n").alias("ranks"), F.coalesce(F.sum("results"), F.lit(0)).alias("results"))
    return met.withColumns({"dummies": F.col("ranks") - F.col("results"), "density": F.col("results") / F.col("ranks")})


def inflation(exact: DataFrame, rounded: DataFrame, keys: list[str]) -> DataFrame:
    """least, largest ratio of rounded to exact counts over keys and scores."""
    met = exact.select(*keys, "score", F.col("n").alias("e")).join(rounded.select(*keys, "score", F.col("n").alias("r")), [*keys, "score"])
    return met.agg(F.min(F.col("r") / F.col("e")).alias("least"), F.max(F.col("r") / F.col("e")).alias("largest"))


@dataclass
class StaticRebuild:
    """The baseline: after each batch an exact index over all tuples."""

    spark: SparkSession
    path: str
    attrs: dict[str, tuple[str, ...]]
    algebra: Algebra = PRODUCT

    def insert(self, batch: int, new: dict[str, DataFrame]) -> None:
        TupleRuns(self.spark, self.path, self.attrs).add(batch, new)

    def index(self, version: int) -> ScoreIndex:
        state = TupleRuns(self.spark, self.path, self.attrs)
        return ScoreIndex.build([RelationSpec(n, state.read(n, version + 1), a) for n, a in self.attrs.items()], self.algebra)

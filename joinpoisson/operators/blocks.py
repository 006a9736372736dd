"""Draws of many candidates under a root of two children, without moving candidates.

A result under a root tuple is a pair: a result of the first child's subtree and one of the second's. Where there are more
candidates than results in the two subtrees, these are listed, with their ranks, and cut into blocks of BLOCK by root tuple.
Every pair of blocks meets once; there the hits of the pair's ranks are drawn (a chunk's hits follow from the seed, so each
pair of blocks that a chunk meets draws them and keeps its own) and both halves of each are at hand. The hits are those that
`candidate_ranks` draws, and the results those that ranked access finds.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from joinpoisson.functions.arith import div
from joinpoisson.operators.ranks import CHUNK_HITS, _bulk_hits, _md5_hits
from joinpoisson.plans.relations import RID, WEIGHT

#: Results of a child's subtree in a block, candidates from which on a draw may go by blocks, and chunks drawn at once.
BLOCK, MANY, CHUNKS_AT_ONCE = 1 << 18, 1_000_000, 1024
_UNIT = ["_root", "_one", "_two"]
_PLACE, _FIRST, _SECOND = range(3)


def _halves(index) -> list[DataFrame]:
    """For each child: _root (rid of the root's tuple), the child's key, _is (score), _n, _before (results of lesser scores), _blocks."""
    root, out = index.intervals[index.tree.name], []
    for c in index.tree.children:
        found = root.select(F.col(RID).alias("_root"), *c.key, F.col(f"score_{c.name}").alias("_is"), F.col(f"n_{c.name}").alias("_n")).distinct()
        own = Window.partitionBy("_root")
        before = F.sum("_n").over(own.orderBy("_is").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("_n")
        out.append(found.select("*", before.alias("_before"), div(F.sum("_n").over(own) + BLOCK - 1, F.lit(BLOCK)).alias("_blocks")))
    return out


def worthwhile(index, draws: int = 1) -> bool:
    """Whether blocks move fewer rows than there are candidates. Only for indexes that know the number of their places: others
    count results that are not there."""
    if len(index.tree.children) != 2 or not index.places or index.buckets.schema["score"].dataType.typeName() == "array":
        return False
    candidates = draws * (index.buckets.agg(F.sum(F.col("n") * F.col("ceiling"))).first()[0] or 0.0)
    if candidates < MANY:
        return False
    one, two = [h.groupBy("_root").agg(F.sum("_n").alias(f"n{i}"), F.max("_blocks").alias(f"b{i}")) for i, h in enumerate(_halves(index))]
    moved = F.sum(F.col("n0").cast("double") * F.col("b1") + F.col("n1").cast("double") * F.col("b0"))
    return (one.join(two, "_root").agg(moved).first()[0] or 0.0) <= candidates


def drawn(index, seed: int, draw: int = 0, draws: int = 1, bulk: bool = False, purpose: str = "gap") -> DataFrame:
    """The results at the candidate ranks: score, rank, draw, _p, the tree's attributes, rid_<relation> and w_<relation>."""
    tree = index.tree
    root = index.intervals[tree.name].withColumnsRenamed({WEIGHT: f"w_{tree.name}"}).withColumn("_root", F.col(RID))
    asked = index.buckets.select("score", F.col("n").alias("_all"), F.col("ceiling").alias("_p"))
    first, second = tree.children
    halves = _halves(index)
    blocks = [h.select("_root", "_blocks").distinct() for h in halves]
    spread = [F.explode(F.sequence(F.lit(0).cast("long"), F.col("_blocks") - 1)).alias(c) for c in _UNIT[1:]]
    each = blocks[0].select("_root", spread[0]).join(blocks[1].select("_root", spread[1]), "_root")
    columns = [f"{x}_{c.name}" for c in (first, second) for x in ("score", "n")]
    top = root.select("_root", *tree.attrs, F.col(f"w_{tree.name}"), "score", "lo", *columns).join(asked, "score").where("_p > 0 and _all > 0").join(each, "_root")
    parts = [top.select(*_UNIT, F.lit(_PLACE).alias("_kind"), F.col(f"score_{first.name}").alias("_is"), F.col(f"score_{second.name}").cast("long").alias("_at"), "score", "lo", F.col(f"n_{second.name}").alias("_n"), "_all", "_p", *tree.attrs, f"w_{tree.name}")]
    have = list(tree.attrs)
    taken = []
    for kind, (c, half, other, (mine, theirs)) in enumerate(zip((first, second), halves, blocks[::-1], (_UNIT[1:], _UNIT[:0:-1]), strict=True), _FIRST):
        fresh = [a for a in dict.fromkeys(a for x in c.walk() for a in x.attrs) if a not in have]
        taken.append([*fresh, *(x for n in c.names for x in (f"rid_{n}", f"w_{n}"))])
        have += fresh
        listed = index.enumerate(node=c).withColumnsRenamed({"score": "_is", "rank": "_at"})
        placed = listed.join(half.drop("_blocks"), [*c.key, "_is"]).withColumn(mine, div(F.col("_before") + F.col("_at") - 1, F.lit(BLOCK)))
        met = placed.join(other, "_root").withColumn(theirs, F.explode(F.sequence(F.lit(0).cast("long"), F.col("_blocks") - 1)))
        parts.append(met.select(*_UNIT, F.lit(kind).alias("_kind"), "_is", "_at", *taken[-1]))
    rows = parts[0].unionByName(parts[1], allowMissingColumns=True).unionByName(parts[2], allowMissingColumns=True)
    own = [*tree.attrs, f"w_{tree.name}"]
    shape = rows.withColumns({"rank": F.lit(0).cast("long"), "draw": F.lit(0), f"rid_{tree.name}": F.col("_root")}).select("score", "rank", "draw", "_p", *own, f"rid_{tree.name}", *taken[0], *taken[1]).schema
    hits = _bulk_hits if bulk else _md5_hits

    def meet(unit: pa.Table) -> Iterator[pa.RecordBatch]:
        kind = unit.column("_kind").to_numpy()
        at = np.searchsorted(kind, [_PLACE, _FIRST, _SECOND, _SECOND + 1])
        place, one, two = (unit.slice(i, j - i).combine_chunks() for i, j in zip(at[:-1], at[1:], strict=True))
        if not (place.num_rows and one.num_rows and two.num_rows):
            return
        number = lambda t, c: t.column(c).to_numpy()
        spans = []  # for each half: where a score begins, its first rank from 0 and how many there are
        for t in (one, two):
            score = number(t, "_is")
            begin = np.flatnonzero(np.concatenate([[True], score[1:] != score[:-1]]))
            spans.append({int(score[i]): (int(i), int(r) - 1, int(m)) for i, r, m in zip(begin, number(t, "_at")[begin], np.diff(begin, append=len(score)), strict=True)})
        rows_of = [(k, *spans[0][s], *spans[1][z]) for k, (s, z) in enumerate(zip(number(place, "_is").tolist(), number(place, "_at").tolist(), strict=True)) if s in spans[0] and z in spans[1]]
        if not rows_of:
            return
        k, i1, a0, m1, i2, b0, m2 = np.array(rows_of, np.int64).T
        lo, n, p, whole, score = (number(place, c)[k] for c in ("lo", "_n", "_p", "_all", "score"))
        length = np.minimum(float(1 << 62), np.ceil(CHUNK_HITS / p)).astype(np.int64)
        start, end = lo + a0 * n, np.minimum(whole, lo + (a0 + m1) * n)
        low, count = start // length, np.maximum(0, (end - 1) // length - start // length + 1)
        upto = np.cumsum(count)
        for turn in range(draw, draw + draws):
            for begin in range(0, int(upto[-1]), CHUNKS_AT_ONCE):
                which = np.arange(begin, min(begin + CHUNKS_AT_ONCE, int(upto[-1])))
                of = np.searchsorted(upto, which, "right")
                chunk = low[of] + which - (upto[of] - count[of])
                first_of = chunk * length[of]
                who, rank = hits(seed, purpose, [str(s) for s in score[of].tolist()], np.full(len(of), turn), chunk, p[of], first_of, np.minimum(length[of], whole[of] - first_of))
                who, rank = of[np.asarray(who, np.int64)], np.asarray(rank, np.int64)
                inside = (rank > start[who]) & (rank <= end[who])
                who, rank = who[inside], rank[inside]
                a, b = (rank - 1 - lo[who]) // n[who] - a0[who], (rank - 1 - lo[who]) % n[who] - b0[who]
                here = (b >= 0) & (b < m2[who])
                who, rank, a, b = who[here], rank[here], pa.array((i1[who] + a)[here]), pa.array((i2[who] + b)[here])
                if len(who):
                    where = pa.array(k[who])
                    found = {"score": score[who], "rank": rank, "draw": np.full(len(who), turn, np.int32), "_p": p[who]}
                    found |= {c: place.column(c).take(where) for c in own} | {f"rid_{tree.name}": place.column("_root").take(where)}
                    found |= {c: one.column(c).take(a) for c in taken[0]} | {c: two.column(c).take(b) for c in taken[1]}
                    yield from pa.table(found).combine_chunks().to_batches()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, last = [], None
        for b in batches:
            if not b.num_rows:
                continue
            key = np.stack([b.column(i).to_numpy() for i in range(3)])
            cuts = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1
            for i, j in zip([0, *cuts.tolist()], [*cuts.tolist(), b.num_rows], strict=True):
                if held and tuple(key[:, i]) != last:
                    yield from meet(pa.Table.from_batches(held))
                    held = []
                held.append(b.slice(i, j - i))
                last = tuple(key[:, i])
        if held:
            yield from meet(pa.Table.from_batches(held))

    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # as few bytes here are many results
    return rows.repartition(tasks, *_UNIT).sortWithinPartitions(*_UNIT, "_kind", "_is", "_at").mapInArrow(run, shape)

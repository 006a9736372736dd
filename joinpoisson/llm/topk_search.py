"""Exact top-k search by pivot-table elimination.

Vectors become integers floor(scale * x); the score is the integer inner product. One more coordinate,
sqrt(M - |x|^2) with M the largest squared norm, turns the inner product into a distance: for a query q with 0 there,
|q - x|^2 = |q|^2 + M - 2 q.x. The pivot table holds every vector's distances to the pivots (vectors from a bounded
sample), made once and kept beside the vector, so the largest |d(q, p) - d(x, p)| over the pivots bounds d(q, x) from below, that is, the score from above.

Each query first gets k scores from the sample, a floor below which no candidate matters. Then queries and candidates
meet in blocks of bounded size. In a block pair a candidate whose bound is under the query's floor is out; the others
are scored in order of their bounds, a slice at a time, until the next bound is below the k-th best score so far. The
k best of each block pair are merged by a top-k aggregation on numbers of the query's own.

Cases: vectors that are null or hold a null or non-finite component take no part; a shorter vector counts as having
zeros behind, so an empty one scores 0 with all; components whose product passes 53 bits are multiplied as whole numbers
of any size, and a score beyond a long is given as the nearest long; fewer than k candidates give all; equal scores go
to the smaller vec_id; rows that repeat a vec_id count each, but never as a candidate of the query with that vec_id; an
empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from joinpoisson.llm.common import cut, hash_sample

K, SCALE, PIVOTS, SAMPLE, QUERY_BLOCK, BLOCK, SLICE, EVERY = 20, 64, 32, 1024, 1024, 8192, 512, 20
_TOP = (1 << 63) - 1


def usable(v: Column) -> Column:
    whole = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    return v.isNotNull() & F.coalesce(F.forall(v, whole), F.lit(False))


def quantised(v: Column, scale: int = SCALE) -> Column:
    return F.transform(v, lambda x: F.floor(x.cast("double") * scale).cast("long"))


class PivotTable:
    def __init__(self, sample: np.ndarray, pivots: int, largest: float):
        self.largest = float(largest)
        #: Sums of products stay whole numbers in this type, for none exceeds the largest squared norm.
        self.exact = np.float32 if largest < 1 << 24 else np.float64 if largest < 1 << 53 else object
        self.kept = np.float32 if largest < 1 << 24 else np.float64
        self.slack = 1e-6 + 1e-5 * self.largest**0.5  # more than rounding moves a distance
        self.spare = 1e-3 + 8 * float(np.finfo(self.kept).eps) * self.largest  # and a bound
        rows = sample[self._spread(sample, pivots)].astype(np.float64) if len(sample) else np.zeros((0, 0))
        self.pivots = rows
        self.lift = self._lifted(rows) if len(rows) else np.zeros(0)

    @staticmethod
    def _spread(sample: np.ndarray, pivots: int) -> list[int]:
        """Pivots far from each other: each is the sampled vector farthest from those before it."""
        x = sample.astype(np.float64)
        chosen = [int(np.argmax((x**2).sum(1)))]
        away = ((x - x[chosen[0]]) ** 2).sum(1)
        while len(chosen) < min(pivots, len(x)):
            chosen.append(int(np.argmax(away)))
            away = np.minimum(away, ((x - x[chosen[-1]]) ** 2).sum(1))
        return chosen

    def _lifted(self, x: np.ndarray) -> np.ndarray:
        return np.sqrt(np.maximum(0.0, self.largest - (x**2).sum(1)))

    def distances(self, x: np.ndarray, query: bool) -> np.ndarray:
        x = x.astype(np.float64)
        lift = np.zeros(len(x)) if query else self._lifted(x)
        square = (x**2).sum(1)[:, None] + (self.pivots**2).sum(1)[None] - 2 * x @ self.pivots.T + (lift[:, None] - self.lift[None]) ** 2
        return np.sqrt(np.maximum(0.0, square)).astype(self.kept)

    def upper_scores(self, square: float, dq: np.ndarray, dx: np.ndarray) -> np.ndarray:
        """No score of a query of this squared norm is above these."""
        low = np.maximum(np.abs(dx - dq).max(axis=1) - self.slack, 0) if dx.shape[1] else np.zeros(len(dx), self.kept)
        return (self.kept(square) + self.kept(self.largest) - low * low) * self.kept(0.5) + self.kept(self.spare)


def best_of_block(table: PivotTable, k: int, q_ids, q, floors, x_ids, x, slice_: int = SLICE, dq=None, dx=None):
    """dq, dx: distances to the pivots, if at hand. For each query of a block the k best candidates of a block that may matter: (query, candidate, score), and the number of scores made."""
    dq, dx = table.distances(q, True) if dq is None else dq, table.distances(x, False) if dx is None else dx
    out, made = [], 0
    xf, qf = x.astype(table.exact), q.astype(table.exact)
    squares = (qf * qf).sum(1)
    for i in range(len(q)):
        bound = table.upper_scores(squares[i], dq[i], dx)
        may = np.flatnonzero((bound >= floors[i]) & (x_ids != q_ids[i]))
        may = may[np.argsort(-bound[may])]
        ids, scores = np.zeros(0, np.int64), np.zeros(0, np.int64)
        at, step = 0, slice_
        while at < len(may) and not (len(scores) >= k and bound[may[at]] < scores[-1]):
            part = may[at : at + step]
            made, at, step = made + len(part), at + len(part), 2 * step
            new = xf[part] @ qf[i]
            ok = new >= (max(floors[i], scores[-1]) if len(scores) >= k else floors[i])
            whole = np.array([min(max(int(v), -_TOP - 1), _TOP) for v in new[ok]], np.int64) if table.exact is object else np.rint(new[ok]).astype(np.int64)
            ids, scores = np.concatenate([ids, x_ids[part[ok]]]), np.concatenate([scores, whole])
            best = np.lexsort((ids, -scores))[:k]
            ids, scores = ids[best], scores[best]
        out.append((np.full(len(ids), i), ids, scores))
    at, ids, scores = (np.concatenate(c) for c in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 3
    return at, ids, scores, made


def pivot_topk(vectors: DataFrame, queries: DataFrame, k: int = K, scale: int = SCALE, pivots: int = PIVOTS, sample: int = SAMPLE, query_block: int = QUERY_BLOCK, block: int = BLOCK) -> DataFrame:
    """vectors, queries: vec_id, embedding. query_id, rank, vec_id, score, and block_scores (scores made in the winner's block pair)."""
    ready = lambda df: df.where(usable(F.col("embedding")) & F.col("vec_id").isNotNull()).select(F.col("vec_id").cast("long").alias("vec_id"), quantised(F.col("embedding"), scale).alias("v"))
    every = ready(vectors)
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x)
    kinds = every.agg(F.max(F.size("v")).alias("d"), F.count("*").alias("n"), F.max(square).alias("m")).where("n > 0").collect()
    shape = "query_id long, vec_id long, score long, made long"
    if not kinds:
        return every.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long, block_scores long")
    width, total, largest = max(1, kinds[0]["d"]), kinds[0]["n"], kinds[0]["m"]
    small = "tinyint" if largest < 127 * 127 else "smallint" if largest < 32767**2 else "bigint"
    padded = F.concat("v", F.array_repeat(F.lit(0).cast("long"), F.lit(width) - F.size("v")))
    fitting = lambda df: df.withColumn("v", padded.cast(f"array<{small}>"))
    rows, asked = fitting(every), fitting(ready(queries)).withColumn("row", F.monotonically_increasing_id())
    drawn = hash_sample(rows, sample, "vec_id").collect()
    known, known_ids = np.array([r["v"] for r in drawn], np.int64).reshape(-1, width), np.array([r["vec_id"] for r in drawn], np.int64)
    table = PivotTable(known, pivots, largest)

    near = "float" if table.kept is np.float32 else "double"

    def floored(batches):
        kf = known.astype(table.exact if table.exact is object else np.float64)
        for b in batches:
            raw = np.array(b["v"].tolist(), np.int64).reshape(-1, width)
            scores = (raw.astype(kf.dtype) @ kf.T).astype(np.float64)
            scores[known_ids[None] == b["vec_id"].to_numpy()[:, None]] = -np.inf
            low = np.full(len(b), -_TOP - 1, np.int64)
            if scores.shape[1] > k and table.exact is not object:  # beyond 53 bits no floor is sure
                low = np.rint(np.partition(scores, -k, axis=1)[:, -k]).clip(-(2.0**62)).astype(np.int64)
            yield b.assign(floor=low, d=list(table.distances(raw, True)))

    def measured(batches):
        for b in batches:
            yield b.assign(d=list(table.distances(np.array(b["v"].tolist(), np.int64).reshape(-1, width), False)))

    asked = cut(asked.mapInPandas(floored, f"vec_id long, v array<{small}>, row long, floor long, d array<{near}>"), "queries")
    rows = cut(rows.mapInPandas(measured, f"vec_id long, v array<{small}>, d array<{near}>"), "pivot-table")
    q_count = asked.count()
    q_blocks, blocks = max(1, -(-q_count // query_block)), max(1, -(-total // block))
    deal = lambda n, *c: F.pmod(F.xxhash64(*c), F.lit(n)).cast("int")
    left = asked.withColumn("qb", deal(q_blocks, F.lit(1), "vec_id", "row")).withColumn("xb", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    right = rows.withColumn("salt", F.monotonically_increasing_id()).withColumn("xb", deal(blocks, F.lit(2), "vec_id", "salt")).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))))

    near_of = lambda df: np.array(df["d"].tolist(), table.kept).reshape(len(df), -1)

    def meet(q: pd.DataFrame, x: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(x):
            return pd.DataFrame({"query_id": [], "row": [], "vec_id": [], "score": [], "made": []})
        qv, xv = np.array(q["v"].tolist(), np.int64), np.array(x["v"].tolist(), np.int64)
        at, ids, scores, made = best_of_block(table, k, q["vec_id"].to_numpy(), qv, q["floor"].to_numpy(), x["vec_id"].to_numpy(), xv, SLICE, near_of(q), near_of(x))
        return pd.DataFrame({"query_id": q["vec_id"].to_numpy()[at], "row": q["row"].to_numpy()[at], "vec_id": ids, "score": scores, "made": made})

    found = left.groupBy("qb", "xb").cogroup(right.select("qb", "xb", "vec_id", "v", "d").groupBy("qb", "xb")).applyInPandas(meet, shape.replace("vec_id", "row long, vec_id"))
    place = F.row_number().over(Window.partitionBy("query_id", "row").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", F.col("made").alias("block_scores"))


def digest(embeddings: DataFrame, every: int = EVERY, **settings) -> DataFrame:
    return pivot_topk(embeddings, embeddings.where(F.col("vec_id") % every == 0), **settings)

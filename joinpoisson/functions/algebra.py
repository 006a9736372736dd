"""How the weights of joined tuples make the weight of a result, and how scores follow.

A tuple's score is floor(-log2(weight)), at most the cap. A result's score comes from its tuples' scores alone, and
all results of one score have weights up to its ceiling.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def score_of(w: Column, cap: int) -> Column:
    """min(cap, floor(-log2 w)), also next to powers of two; weight 0 has the cap."""
    s = F.least(F.lit(cap).cast("long"), F.floor(-F.log2(F.when(w > 0, w))))
    s = F.when((w > 0) & (s > 0) & (w > F.pow(F.lit(2.0), -s)), s - 1).otherwise(s)
    return F.coalesce(F.greatest(s, F.lit(0).cast("long")), F.lit(cap).cast("long")).cast("int")


def score_sql(w: str, cap: int) -> str:
    s = f"least({cap}, floor(-log2(CASE WHEN {w} > 0 THEN {w} END)))"
    fixed = f"CASE WHEN {w} > 0 AND {s} > 0 AND {w} > pow(2.0e0, -({s})) THEN {s} - 1 ELSE {s} END"
    return f"CAST(coalesce(greatest({fixed}, 0), {cap}) AS INTEGER)"


def round_up_pow2(x: Column) -> Column:
    """The least power of two from x on, in whole numbers; 0 and 1 stay."""
    doubled = F.call_function("shiftleft", F.lit(1).cast("long"), F.length(F.bin(x - 1)).cast("int"))
    return F.when(x <= 1, x.cast("long")).otherwise(doubled)


@dataclass(frozen=True)
class Algebra:
    """name: product, min, max, sum or constant. constant ignores weights and gives p."""

    name: str
    p: float = 1.0

    @property
    def drops_zero(self) -> bool:
        """Whether a tuple of weight 0 cannot be in a result of positive weight."""
        return self.name in ("product", "min")

    def tuple_score(self, w: Column, cap: int) -> Column:
        return F.lit(0) if self.name == "constant" else score_of(w, cap)

    def combine(self, scores: list[Column], cap: int) -> Column:
        """The score of a result, or of a part of it; the cap collects all from it on."""
        if self.name == "constant":
            return F.lit(0)
        if len(scores) == 1:
            return scores[0]
        if self.name == "product":
            return F.least(F.lit(cap), reduce(lambda a, b: a + b, scores))
        return F.greatest(*scores) if self.name == "min" else F.least(*scores)

    def combine_sql(self, scores: list[str], cap: int) -> str:
        if self.name == "constant":
            return "0"
        if len(scores) == 1:
            return scores[0]
        if self.name == "product":
            return f"least({cap}, {' + '.join(scores)})"
        return f"{'greatest' if self.name == 'min' else 'least'}({', '.join(scores)})"

    def ceiling(self, score: Column, relations: int) -> Column:
        if self.name == "constant":
            return F.lit(self.p)
        top = F.pow(F.lit(2.0), -score.cast("double"))
        return F.least(F.lit(1.0), top * relations) if self.name == "sum" else top

    def ceiling_sql(self, score: str, relations: int) -> str:
        if self.name == "constant":
            return f"{self.p!r}"
        top = f"pow(2.0e0, -({score}))"
        return f"least(1.0e0, {top} * {relations})" if self.name == "sum" else top

    def weight(self, ws: list[Column]) -> Column:
        if self.name == "constant":
            return F.lit(self.p)
        if len(ws) == 1:
            return ws[0]
        return {"product": lambda: reduce(lambda a, b: a * b, ws), "min": lambda: F.least(*ws), "max": lambda: F.greatest(*ws), "sum": lambda: reduce(lambda a, b: a + b, ws)}[self.name]()

    def weight_sql(self, ws: list[str]) -> str:
        if self.name == "constant":
            return f"{self.p!r}"
        return {"product": " * ".join(ws), "min": f"least({', '.join(ws)})", "max": f"greatest({', '.join(ws)})", "sum": " + ".join(ws)}[self.name]

    def uniformity(self, relations: int) -> float:
        """The most that weights of one score differ by, as a factor."""
        return {"product": 2.0**relations, "min": 2.0, "max": 2.0, "sum": 2.0 * relations, "constant": 1.0}[self.name]

    def enough_cap(self, results: int, relations: int) -> int:
        """The least cap whose ceiling is at most 1 / results."""
        if self.name == "constant":
            return 0
        return max(1, math.ceil(math.log2(max(2, results * (relations if self.name == "sum" else 1)))))


PRODUCT, MIN, MAX, SUM = (Algebra(n) for n in ("product", "min", "max", "sum"))


def constant(p: float) -> Algebra:
    return Algebra("constant", p)


@dataclass(frozen=True)
class ClassGrid(Algebra):
    """The product with a result's score kept as the list of its tuples' scores: one part per combination."""

    name: str = "product"

    def combine(self, scores: list[Column], cap: int) -> Column:
        lists = [F.array(scores[0].cast("int")), *scores[1:]]
        return F.concat(*lists)

    def ceiling(self, score: Column, relations: int) -> Column:
        return F.pow(F.lit(2.0), -F.aggregate(score, F.lit(0), lambda a, x: a + x).cast("double"))


GRID = ClassGrid()

"""Root-local thinning: every place of the root (tuple and child scores) is a part of its own.

A part has n results under one ceiling; its candidates are drawn inside the row, so there are no ranks over the whole
root, no running sum there, and one scan of it. Only the ranks within the children are looked up.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.functions.algebra import Algebra
from joinpoisson.functions.arith import div
from joinpoisson.operators.access import _locate
from joinpoisson.operators.index import choose_cap, intervals_of, places_of
from joinpoisson.operators.ranks import candidate_ranks
from joinpoisson.operators.sampler import result_coin
from joinpoisson.plans.jointree import build_join_tree
from joinpoisson.plans.relations import RID, WEIGHT, RelationSpec, schemas

#: Tuples of a root from which on its places are drawn from where the joins leave them.
MANY = 100_000


def sample_root_local(specs: list[RelationSpec], algebra: Algebra, seed: int, draw: int = 0, cap: int | str = "exact", root: str | None = None, bulk: bool = False) -> DataFrame:
    tree = build_join_tree(schemas(specs), root)
    level = cap if isinstance(cap, int) else choose_cap(specs, algebra, cap)
    by_name = {s.name: s for s in specs}
    top = places_of(tree, by_name, algebra, level)
    label = F.concat_ws("-", F.col(RID).cast("string"), *[F.col(f"score_{c.name}").cast("string") for c in tree.children])
    parts = top.withColumn("p", algebra.ceiling(F.col("score"), len(specs))).withColumn("part", label)
    many = by_name[tree.name].df.count() >= MANY  # places are tuples times scores: dealing them out anew would move them all
    hits = candidate_ranks(parts, seed, draw, bulk=bulk, purpose="local", deal=not many)
    rows = hits.withColumnsRenamed({RID: f"rid_{tree.name}", WEIGHT: f"w_{tree.name}"})
    within, rest, out = F.col("rank") - 1, F.lit(1).cast("long"), {}
    for c in reversed(tree.children):
        count = F.col(f"n_{c.name}")
        out |= {f"_s_{c.name}": F.col(f"score_{c.name}"), f"_d_{c.name}": F.col(f"width_{c.name}"), f"_r_{c.name}": div(within, rest) % count + 1}
        rest = rest * count
    rows = (rows.withColumns(out) if out else rows).drop(*[f"{x}_{c.name}" for c in tree.children for x in ("score", "n", "width")])
    have = list(tree.attrs)
    for node in tree.walk()[1:]:
        rows, have = _locate(node, intervals_of(node, places_of(node, by_name, algebra, level)), rows, have, "steps")
    weight = algebra.weight([F.col(f"w_{n}") for n in sorted(tree.names)])
    kept = rows.withColumn("weight", weight).where(result_coin(seed, F.lit(draw), tree.names) * F.col("p") < F.col("weight"))
    ids = [c for n in tree.names for c in (f"rid_{n}", f"w_{n}")]
    return kept.select("score", "rank", "draw", *have, *ids, "weight")

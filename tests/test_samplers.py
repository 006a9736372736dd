"""Samplers: exact counts and ranks on hand-made joins, the law over many draws, edge weights, dynamic state."""

import math
import uuid
from collections import Counter
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from joinpoisson.functions import algebra as al
from joinpoisson.functions.rng import geometric_value, mixed_uniforms, truncated_geometric_value, u01, u01_value
from joinpoisson.operators import baselines, explicit, metrics
from joinpoisson.operators.access import descend
from joinpoisson.operators.dynamic import DynamicIndex, MaintainedSample, MessageRuns, UnsupportedOperation
from joinpoisson.operators.estimators import ht_avg, ht_count, ht_sum
from joinpoisson.operators.index import ScoreIndex, choose_cap, join_size, reduce_relations
from joinpoisson.operators.ranks import all_ranks, candidate_ranks
from joinpoisson.operators.sampler import sample_join
from joinpoisson.plans.jointree import size_bound
from joinpoisson.plans.relations import RelationSpec, assign_rid, validate_weights
from joinpoisson.plans.storage import running_sum, shared_dir
from joinpoisson.sources.workloads import specs
from joinpoisson.streaming.runner import in_batches, insertion_log, run_insertions, write_slices

R = [(1, 1, 0.9), (1, 2, 0.51), (2, 1, 0.3), (3, 9, 1.0), (2, 2, 0.0625)]
S = [(1, 0.51), (1, 1.0), (2, 0.25), (7, 0.5), (2, 2.0**-40)]
T = [(1, 0.51), (1, 0.1), (2, 0.75), (2, 0.5)]


def star(spark):
    """R(a, b) over S(a, x) and T(b, y): a root with two children, dangling tuples at all ends."""
    r = spark.createDataFrame([(a, b, i, w) for i, (a, b, w) in enumerate(R)], "a long, b long, rid long, w double")
    s = spark.createDataFrame([(a, i, i, w) for i, (a, w) in enumerate(S)], "a long, x long, rid long, w double")
    t = spark.createDataFrame([(b, i, i, w) for i, (b, w) in enumerate(T)], "b long, y long, rid long, w double")
    return [RelationSpec("r", r, ("a", "b")), RelationSpec("s", s, ("a", "x")), RelationSpec("t", t, ("b", "y"))]


def results():
    return {(i, j, k): (R[i][2], S[j][1], T[k][1]) for i, j, k in product(range(len(R)), range(len(S)), range(len(T))) if R[i][0] == S[j][0] and R[i][1] == T[k][0]}


def score(w, cap):
    return cap if w <= 0 else min(cap, next(s for s in range(2000) if w > 2.0 ** -(s + 1)))


RULES = {"product": lambda p, cap: min(cap, sum(p)), "min": lambda p, _: max(p), "max": lambda p, _: min(p), "sum": lambda p, _: min(p)}


@pytest.mark.parametrize("name", ["product", "min", "max", "sum"])
@pytest.mark.parametrize("root", ["r", "s"])
@pytest.mark.parametrize("cap", [3, 60])
def test_buckets_and_ranks_enumerate_the_join(spark, name, root, cap):
    """Every result has one rank of its own score: a root's score counted once per child would show here."""
    algebra = al.Algebra(name)
    index = ScoreIndex.build(star(spark), algebra, cap, root, store=False)
    want = {k: RULES[name]([score(w, cap) for w in ws], cap) for k, ws in results().items()}
    got = {(x.rid_r, x.rid_s, x.rid_t): (x.score, x["rank"]) for x in index.enumerate().collect()}
    assert {k: s for k, (s, _) in got.items()} == want
    sizes = Counter(want.values())
    assert {x.score: x.n for x in index.buckets.collect()} == dict(sizes)
    assert sorted(got.values()) == sorted((s, r) for s, n in sizes.items() for r in range(1, n + 1))
    for k, ws in results().items():
        top = 2.0 ** -want[k] * (3 if name == "sum" else 1)
        weight = {"product": math.prod, "min": min, "max": max, "sum": sum}[name](ws)
        assert weight <= top * (1 + 1e-12)


def test_strategies_and_large_groups_agree(spark):
    a = ScoreIndex.build(star(spark), al.PRODUCT, 20, "r", store=False)
    b = ScoreIndex.build(star(spark), al.PRODUCT, 20, "r", large=0)
    ranks = a.buckets.select("score", F.explode(F.expr("sequence(1L, n)")).alias("rank"))
    rows = [sorted(tuple(x) for x in descend(i, ranks, how).select("score", "rank", "rid_r", "rid_s", "rid_t").collect()) for i, how in ((a, "steps"), (a, "merge"), (b, "steps"))]
    assert rows[0] == rows[1] == rows[2] and len(rows[0]) == len(results())


def test_all_ranks_are_looked_up_where_the_enumeration_has_them(spark, monkeypatch):
    monkeypatch.setattr("joinpoisson.operators.ranks.LISTED", 2)
    for algebra in (al.PRODUCT, al.GRID):
        for store in (False, True):
            index = ScoreIndex.build(star(spark), algebra, 20, "r", store=store)
            asked = all_ranks(index.buckets.select("score", "n"))
            rows = [sorted(map(tuple, df.select("score", "rank", "a", "b", "x", "y", "rid_r", "rid_s", "rid_t", "w_t").collect())) for df in (index.access(asked), index.enumerate())]
            assert rows[0] == rows[1] and len(rows[0]) == len(results())


def test_runs_of_ranks_find_what_single_ranks_find(spark, monkeypatch):
    """Runs that cross pieces, intervals and steps; trees with one, two and no children at the root, and a path."""
    monkeypatch.setattr("joinpoisson.operators.access.RUN", 2, raising=False)
    for listed in (1, 3, 1 << 16):
        monkeypatch.setattr("joinpoisson.operators.ranks.LISTED", listed)
        for algebra, root, store in ((al.PRODUCT, "r", False), (al.GRID, "r", True), (al.PRODUCT, "s", False), (al.constant(1.0), "t", False)):
            index = ScoreIndex.build(star(spark), algebra, 20 if algebra.name != "constant" else 0, root, store=store)
            columns = ["score", "rank", "a", "b", "x", "y", "rid_r", "rid_s", "rid_t", "w_t"]
            found = [sorted(map(tuple, df.select(*columns).collect())) for df in (index.access(all_ranks(index.buckets.select("score", "n"), runs=True)), index.enumerate())]
            assert found[0] == found[1] and len(found[0]) == len(results())
    index = ScoreIndex.build(star(spark), al.constant(1.0), 0, "r", store=False)
    asked = spark.createDataFrame([(0, 2, 3, "a"), (0, 3, 3, "b"), (0, 5, 99, "c")], "score int, first long, last long, who string")
    got = sorted((r.who, r["rank"]) for r in index.access(asked).collect())
    assert got == [("a", 2), ("a", 3), ("b", 3), *[("c", k) for k in range(5, len(results()) + 1)]]


def _moved(plan) -> int:
    """Rows that the exchanges of an executed plan have written."""
    kind = plan.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return _moved(plan.executedPlan())
    if kind.endswith("QueryStageExec"):
        return _moved(plan.plan())
    own = plan.metrics().apply("shuffleRecordsWritten").value() if kind == "ShuffleExchangeExec" else 0
    return own + sum(_moved(plan.children().apply(i)) for i in range(plan.children().size()))


def test_uniform_access_moves_runs_and_not_a_row_for_each_result(spark, tmp_path):
    from joinpoisson.catalogue import QUERIES

    spark.range(2).selectExpr("CAST(id AS INT) AS n_nationkey", "'n' AS n_name", "0 AS n_regionkey").write.parquet(f"{tmp_path}/nation.parquet")
    spark.range(300).selectExpr("id AS c_custkey", "'c' AS c_name", "CAST(id % 2 AS INT) AS c_nationkey", "1.0D AS c_acctbal", "'m' AS c_mktsegment").write.parquet(f"{tmp_path}/customer.parquet")
    spark.range(400).selectExpr("id AS s_suppkey", "'s' AS s_name", "CAST(id % 2 AS INT) AS s_nationkey", "1.0D AS s_acctbal").write.parquet(f"{tmp_path}/supplier.parquet")
    found = QUERIES["index_ranked_access_uniform_w05"](spark, str(tmp_path))
    rows = found.collect()
    assert len(rows) == len({r["rank"] for r in rows}) == len({(r.rid_customer, r.rid_supplier) for r in rows}) == 300 * 200
    assert _moved(found._jdf.queryExecution().executedPlan()) < 6_000


def test_many_candidates_are_drawn_where_both_halves_are(spark, small, monkeypatch):
    """The same sample as by look-ups, in blocks of any size, with hits by MD5 and by the mixer; no candidate is moved."""
    from joinpoisson.operators import blocks

    columns = ["score", "rank", "draw", "a", "b", "x", "y", "rid_r", "rid_s", "rid_t", "w_t", "weight"]
    for algebra, store, draws, bulk, size in ((al.PRODUCT, False, 3, True, 1), (al.MIN, True, 2, False, 2), (al.constant(1.0), False, 1, False, 1 << 18)):
        index = ScoreIndex.build(star(spark), algebra, 0 if algebra.name == "constant" else 20, "r", store=store)
        monkeypatch.setattr(blocks, "MANY", 1e18)
        want = sorted(map(tuple, index.sample(7, draws=draws, bulk=bulk).select(*columns).collect()))
        monkeypatch.setattr(blocks, "BLOCK", size)
        got = sorted(map(tuple, _in_blocks(index, monkeypatch, 7, draws, bulk).select(*columns).collect()))
        assert got == want and want
    monkeypatch.setattr(blocks, "BLOCK", 256)
    monkeypatch.setattr(blocks, "MANY", 1e18)
    index = ScoreIndex.build(specs(spark, small, "w05"), al.PRODUCT, 40, "nation", store=False)
    columns = ["score", "rank", "nk", "ck", "sk", "rid_customer", "rid_supplier", "rid_nation", "weight"]
    want = sorted(map(tuple, index.sample(3, draws=40, bulk=True).select(*columns).collect()))
    found = _in_blocks(index, monkeypatch, 3, 40, True)
    assert sorted(map(tuple, found.select(*columns).collect())) == want and want
    assert "Join" in (plan := found._jdf.queryExecution().executedPlan().toString()) and "rank > lo" not in plan


def _in_blocks(index, monkeypatch, seed, draws, bulk):
    with monkeypatch.context() as m:
        m.setattr("joinpoisson.operators.sampler.worthwhile", lambda *_: True)
        return index.sample(seed, draws=draws, bulk=bulk)


def test_blocks_are_for_more_candidates_than_halves(spark, monkeypatch):
    from joinpoisson.operators import blocks

    monkeypatch.setattr(blocks, "MANY", 1)
    rows = lambda name, n: spark.range(n).selectExpr("0L AS k", f"id AS {name}", "id AS rid", "1.0D AS w")
    many = [RelationSpec("r", spark.range(1).selectExpr("id AS k", "id AS rid", "1.0D AS w"), ("k",)), RelationSpec("s", rows("x", 40), ("k", "x")), RelationSpec("t", rows("y", 50), ("k", "y"))]
    assert blocks.worthwhile(ScoreIndex.build(many, al.PRODUCT, 20, "r", store=False))
    assert not blocks.worthwhile(ScoreIndex.build(many, al.constant(1 / 64), 0, "r", store=False))
    assert not blocks.worthwhile(ScoreIndex.build(many[:2], al.PRODUCT, 20, "r", store=False))
    got = ScoreIndex.build(many, al.PRODUCT, 20, "r", store=False).sample(1)
    got.collect()
    assert _moved(got._jdf.queryExecution().executedPlan()) < 1_000 and got.count() == 2_000


def test_requests_are_never_broadcast(spark):
    """The planner takes what comes out of a few buckets for a few rows: broadcast, all candidates would go through the driver."""
    index = ScoreIndex.build(star(spark), al.PRODUCT, 20, "r")
    for found in (index.sample(seed=1), index.access(all_ranks(index.buckets.select("score", "n"))), sample_join(star(spark), seed=1, cap=20, root="r", method="root_local")):
        found.collect()
        text = found._jdf.queryExecution().executedPlan().toString()
        lookups = [x for x in text.splitlines() if "Join" in x and "_step" in x]
        assert lookups and all("SortMergeJoin" in x for x in lookups), text


def test_scores_next_to_powers_of_two(spark):
    ws = [1.0, 0.5, 0.25, 2.0**-40, 0.0, 0.51, 0.49999999999999994, 0.5000000000000001, math.nextafter(0.125, 1), math.nextafter(0.125, 0)]
    got = [r.s for r in spark.createDataFrame([(float(w),) for w in ws], "w double").select(al.score_of(F.col("w"), 30).alias("s")).collect()]
    assert got == [score(w, 30) for w in ws]


def test_rounding_up_to_powers_of_two(spark):
    xs = [0, 1, 2, 3, 4, 5, 2**50, 2**50 + 1, 2**53 + 1, 2**61 + 1]
    got = [r.u for r in spark.createDataFrame([(x,) for x in xs], "x long").select(al.round_up_pow2(F.col("x")).alias("u")).collect()]
    assert got == [x if x < 2 else 1 << (x - 1).bit_length() for x in xs]


def test_uniforms_agree_and_stay_inside(spark):
    got = [r.u for r in spark.range(200).select(u01(F.lit(3), F.lit("p"), F.col("id")).alias("u")).collect()]
    assert got == [u01_value(3, "p", i) for i in range(200)] and all(0 < u < 1 for u in got)
    bulk = mixed_uniforms(1, np.arange(200_000), 3)
    assert abs(bulk.mean() - 0.5) < 0.005 and 0 < bulk.min() and bulk.max() < 1


def test_gaps():
    assert geometric_value(0.3, 1.0, 9) == 0 and geometric_value(0.3, 0.0, 9) == 9
    gaps = [geometric_value(u01_value("g", i), 0.2, 10**6) for i in range(20_000)]
    assert abs(np.mean(gaps) - 4) < 0.1
    short = [truncated_geometric_value(u01_value("t", i), 0.2, 5) for i in range(20_000)]
    share = Counter(short)
    q = 1 - 0.8**5
    assert set(share) == set(range(5)) and all(abs(share[k] / 20_000 - 0.2 * 0.8**k / q) < 0.012 for k in range(5))
    assert truncated_geometric_value(0.5, 1e-18, 10**9) in range(10**9)


@pytest.mark.parametrize("gate", [False, True])
@pytest.mark.parametrize("bulk", [False, True])
def test_candidate_ranks_hit_each_rank_with_p(spark, gate, bulk):
    draws = 300
    parts = spark.createDataFrame([("a", 700, 0.125), ("b", 5, 1.0), ("c", 3, 0.01), ("d", 0, 0.5), ("e", 40, 0.7)], "part string, n long, p double")
    got = Counter((r.part, r["rank"]) for r in candidate_ranks(parts, 5, 0, draws, gate, bulk).select("part", "rank", "draw").distinct().collect())
    assert all(1 <= r <= {"a": 700, "b": 5, "c": 3, "e": 40}[p] for p, r in got)
    assert all(got["b", r] == draws for r in range(1, 6))
    for part, n, p in (("a", 700, 0.125), ("c", 3, 0.01), ("e", 40, 0.7)):
        counts = np.array([got[part, r] for r in range(1, n + 1)])
        z = (counts - draws * p) / math.sqrt(draws * p * (1 - p))
        assert np.abs(z).max() < 5.5 and abs(z.mean()) < 5 / math.sqrt(n)


@pytest.mark.parametrize("how", ["index", "gated", "bulk", "grid", "local", "naive", "dynamic"])
def test_inclusion_probabilities(spark, how):
    """Over many draws every result comes with its own probability, and the sizes have the mean and variance."""
    draws = 400
    rows = star(spark)
    if how == "naive":
        got = baselines.naive_sample(rows, al.PRODUCT, 11, draws=draws)
    elif how == "local":
        from joinpoisson.operators.rootlocal import sample_root_local

        got = None
        for d in range(0, 40):
            one = sample_root_local(rows, al.PRODUCT, 11, d, 12, "r").select("rid_r", "rid_s", "rid_t", "draw")
            got = one if got is None else got.unionByName(one)
        draws = 40
    elif how == "grid":
        got = ScoreIndex.build(rows, al.GRID, 12, "r").sample(11, draws=draws, bulk=True)
    elif how == "dynamic":
        index = DynamicIndex(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}", {r.name: r.attrs for r in rows}, capacity=64, root="r")
        in_batches(insertion_log(rows), 2, index.attrs, index.insert)
        got = index.sample(5, 11, draws=draws)
    else:
        got = ScoreIndex.build(rows, al.PRODUCT, 12, "r").sample(11, draws=draws, gate=how == "gated", bulk=how == "bulk")
    seen = Counter((x.rid_r, x.rid_s, x.rid_t) for x in got.select("rid_r", "rid_s", "rid_t", "draw").distinct().collect())
    p = {k: math.prod(ws) for k, ws in results().items()}
    assert set(seen) <= set(p)
    z = [(seen[k] - draws * q) / math.sqrt(draws * q * (1 - q)) for k, q in p.items() if 1e-6 < q < 1]
    assert max(map(abs, z)) < 4.5
    total = sum(seen.values())
    mu, var = sum(p.values()), sum(q * (1 - q) for q in p.values())
    assert abs(total - draws * mu) < 4.5 * math.sqrt(draws * var)


def test_results_that_share_a_tuple_are_independent_but_not_in_the_control(spark):
    draws = 600
    a = spark.createDataFrame([(1, 0, 0.5)], "k long, rid long, w double")
    b = spark.createDataFrame([(1, i, i, 0.5) for i in range(6)], "k long, x long, rid long, w double")
    rows = [RelationSpec("a", a, ("k",)), RelationSpec("b", b, ("k", "x"))]
    good = ScoreIndex.build(rows, al.PRODUCT, 8, "a").sample(3, draws=draws)
    bad = None
    for d in range(60):
        one = baselines.sample_inputs_then_join(rows, 3, d).withColumn("draw", F.lit(d))
        bad = one if bad is None else bad.unionByName(one)
    cov = metrics.pair_counts(good, "rid_b", "rid_a", draws).first()
    off = metrics.pair_counts(bad, "rid_b", "rid_a", 60).first()
    assert abs(cov.covariance) < 0.25 and off.covariance > 0.8  # 15 pairs: 0 against 15 * (1/8 - 1/16)
    lag = metrics.draw_covariance(good, ["b"], draws).first()
    assert abs(lag.observed - lag.expected) < 6 * math.sqrt(lag.expected)


def test_certain_empty_and_dropped_weights(spark):
    rows = star(spark)
    ones = [RelationSpec(r.name, r.df.withColumn("w", F.lit(1.0)), r.attrs) for r in rows]
    assert sample_join(ones, seed=1, root="r").count() == len(results())
    zeros = [RelationSpec(r.name, r.df.withColumn("w", F.lit(0.0)), r.attrs) for r in rows]
    assert sample_join(zeros, seed=1, cap=5).count() == 0
    none = [RelationSpec(r.name, r.df.where("false") if r.name == "s" else r.df, r.attrs) for r in rows]
    assert join_size(none) == 0 and sample_join(none, seed=1, cap=5, root="r").count() == 0
    for bad in (None, float("nan"), -0.1, 1.5):
        with pytest.raises(ValueError, match="not in"):
            validate_weights([RelationSpec("r", rows[0].df.withColumn("w", F.lit(bad).cast("double")), ("a", "b"))], al.PRODUCT)
    with pytest.raises(ValueError, match="more than 1"):
        validate_weights(rows, al.SUM)
    validate_weights([RelationSpec(r.name, r.df.withColumn("w", F.col("w") / 3), r.attrs) for r in rows], al.SUM)


def test_expected_sizes_and_measures(spark):
    rows, p = star(spark), results()
    for name, f in (("product", math.prod), ("min", min), ("max", max), ("sum", sum)):
        assert abs(metrics.expected_size(rows, al.Algebra(name)) - sum(map(f, p.values()))) < 1e-9
    assert join_size(rows) == len(p) and metrics.input_size(rows) == len(R) + len(S) + len(T)
    index = ScoreIndex.build(rows, al.PRODUCT, choose_cap(rows, al.PRODUCT), "r")
    assert metrics.candidate_size(index) <= 8 * metrics.expected_size(rows) + 1
    assert metrics.index_nonzeros(index) <= (len(R) + len(S) + len(T)) * (index.cap + 1) * 2
    reduced = {r.name: {x.rid for x in r.df.collect()} for r in reduce_relations(rows, "r")}
    assert reduced == {"r": {k[0] for k in p}, "s": {k[1] for k in p}, "t": {k[2] for k in p}}


def test_saved_index_draws_the_same(spark):
    index = ScoreIndex.build(star(spark), al.PRODUCT, 12, "r")
    where = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
    index.save(where)
    again = ScoreIndex.load(spark, where)
    pick = lambda i: sorted(map(tuple, i.sample(4, draws=5).select("draw", "rid_r", "rid_s", "rid_t").collect()))
    assert pick(index) == pick(again) and again.cap == 12


def test_running_sums_and_numbers_over_partitions(spark):
    df = spark.range(3000).select((F.col("id") * 7919 % 3000).alias("k"), (F.col("id") % 3).alias("g"), (F.col("id") % 5).alias("v"))
    got = {(r.g, r.k): r.s for r in running_sum(df, ["g"], ["k"], "v", "s").collect()}
    rows = sorted((r.g, r.k, r.v) for r in df.collect())
    total = Counter()
    for g, k, v in rows:
        total[g] += v
        assert got[g, k] == total[g]
    assert [r.rid for r in assign_rid(df, ["k"]).orderBy("k").collect()] == list(range(1, 3001))


def test_dynamic_state_does_not_depend_on_batches(spark, small):
    rows = specs(spark, small, "w05")
    attrs = {r.name: r.attrs for r in rows}
    counts = []
    for n in (1, 3):
        index = DynamicIndex(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}", attrs, capacity=1 << 10, root="nation", rounded=False)
        in_batches(insertion_log(rows), n, attrs, index.insert)
        counts.append(sorted(map(tuple, index.index(9).buckets.select("score", "n").collect())))
    fixed = ScoreIndex.build(rows, al.PRODUCT, index.cap, "nation", store=False)
    assert counts[0] == counts[1] == sorted(map(tuple, fixed.buckets.select("score", "n").collect()))


def test_rounded_index_grows_its_capacity_and_names_all_results(spark):
    rows = star(spark)
    index = DynamicIndex(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}", {r.name: r.attrs for r in rows}, capacity=4, root="s")
    in_batches(insertion_log(rows), 3, index.attrs, index.insert)
    assert index.capacity >= len(R) + len(S) + len(T)
    got = {(x.rid_r, x.rid_s, x.rid_t) for x in index.index(5).enumerate().collect()}
    assert got == set(results())
    with pytest.raises(UnsupportedOperation):
        index.delete()


def test_changes_are_recorded_while_the_capacity_grows(spark):
    """Batches that rebuild all counts record what moved, as the others do: with room from the start the same is recorded."""
    r = spark.createDataFrame([(i % 4, i, 0.3 + i / 40) for i in range(24)], "a long, rid long, w double").select("a", F.col("rid").alias("x"), "rid", "w")
    s = spark.createDataFrame([(i % 5, i, 0.9 - i / 40) for i in range(18)], "a long, rid long, w double").select("a", F.col("rid").alias("y"), "rid", "w")
    rows = [RelationSpec("r", r, ("a", "x")), RelationSpec("s", s, ("a", "y"))]
    attrs, seen = {x.name: x.attrs for x in rows}, []
    for capacity in (1 << 4, 1 << 10):
        index = DynamicIndex(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}", attrs, capacity=capacity, root="s")
        in_batches(insertion_log(rows), 3, attrs, index.insert, F.pmod(F.col("rid"), F.lit(3)))
        assert (index.capacity > capacity) == (capacity == 1 << 4)
        seen.append(sorted(index.changes))
    assert seen[0] == seen[1] and len(seen[0]) == 6


def test_a_stream_and_its_replay_leave_one_sample(spark):
    rows = star(spark)
    attrs = {r.name: r.attrs for r in rows}
    sample = MaintainedSample(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}", attrs, al.PRODUCT, 9, exact_coins=True)
    log = insertion_log(rows)
    run_insertions(spark, write_slices(log, 3), log.schema, attrs, sample.insert)
    want = sorted(map(tuple, baselines.naive_sample(rows, al.PRODUCT, 9).select("rid_r", "rid_s", "rid_t").collect()))
    pick = lambda: sorted(map(tuple, sample.current().select("rid_r", "rid_s", "rid_t").collect()))
    assert pick() == want
    last = {r.name: log.where(F.col("relation") == r.name).select(*r.attrs, "rid", "w") for r in rows}
    sample.insert(7, last)  # all are there already
    assert pick() == want


def test_explicit_sets(spark):
    df = spark.range(500).select("id", ((F.col("id") % 64 + 1) / 64).alias("weight"))
    held = explicit.ClassifiedSet.build(df, "id", F.col("weight"))
    n = held.sample(3, draws=40, gate=True).groupBy("id").count().join(df, "id").select(((F.col("count") - 40 * F.col("weight")) / F.sqrt(40 * F.col("weight") * (1 - F.col("weight")) + 1e-9)).alias("z"), "weight", "count").collect()
    assert all(abs(x.z) < 5 for x in n if x.weight < 1) and all(x["count"] == 40 for x in n if x.weight == 1)
    light = explicit.uniformity(df.withColumn("weight", F.lit(1e-3)), F.col("weight")).first()
    assert light.light and light.beta == 1.0


def test_estimates_cover_the_truth(spark, small):
    rows = specs(spark, small, "w01")
    truth = baselines.natural_join(rows).agg(F.sum(F.col("w_lineitem") * 50).alias("q"), F.count("*").alias("n")).first()
    sample = sample_join(rows, seed=21, root="lineitem")
    for got, want in ((ht_sum(sample, F.col("w_lineitem") * 50).first(), truth.q), (ht_count(sample).first(), truth.n)):
        assert abs(got.estimate - want) < 4.5 * math.sqrt(got.variance)
    mean = ht_avg(sample, F.col("w_lineitem") * 50).first()
    assert abs(mean.estimate - truth.q / truth.n) < 4.5 * math.sqrt(mean.variance)


def test_a_draw_on_a_stored_index_moves_its_candidates_only(spark, small):
    """Between the stored tables of the index and the look-ups of a draw there is neither an exchange nor an aggregation."""
    from joinpoisson.operators.index import ScoreIndex
    from joinpoisson.sources.workloads import specs as workload_specs

    index = ScoreIndex.build(workload_specs(spark, small, "w01"), root="lineitem")
    plan = index.sample(seed=1)._jdf.queryExecution().executedPlan().toString()
    lines = plan.splitlines()
    for k, line in enumerate(lines):
        if "steps_" in line and "Scan parquet" in line:
            depth = len(line) - len(line.lstrip(" :+-*()0123456789"))
            above = []
            for other in reversed(lines[:k]):
                d = len(other) - len(other.lstrip(" :+-*()0123456789"))
                if d < depth:
                    depth = d
                    above.append(other)
                    if "Join" in other:
                        break
            assert not any("Exchange" in x or "Aggregate" in x for x in above), "\n".join(above)
    assert any("steps_" in x and "Scan parquet" in x for x in lines)


def test_runs_of_counts_merge_like_a_binary_counter(spark):
    runs, state = MessageRuns(spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}"), {}
    lengths = []
    for b in range(6):
        rows = [(k, 0, 10 * b + k) for k in (b % 3, 3 + b)]
        state |= {r[0]: r[2] for r in rows}
        for _ in range(1 + (b == 4)):  # a batch that runs again replaces its run
            own = runs.write(b, spark.createDataFrame(rows, "k int, score int, raw long"), ["k", "score"])
        assert sorted(x.k for x in own.collect()) == sorted(r[0] for r in rows)
        assert {x.k: x.raw for x in runs.read(b + 1, ["k", "score"]).collect()} == state
        lengths.append(len(runs.chain(b + 1)))
    assert lengths == [1, 1, 2, 1, 2, 2]


def test_a_reopened_index_keeps_its_capacity(spark):
    rows = star(spark)
    path, attrs = f"{shared_dir(spark)}/{uuid.uuid4().hex}", {r.name: r.attrs for r in rows}
    log, insert = insertion_log(rows), lambda b, new: DynamicIndex(spark, path, attrs, capacity=4, root="s").insert(b, new)
    in_batches(log, 2, attrs, insert)
    held = DynamicIndex(spark, path, attrs, capacity=4, root="s")
    total = len(R) + len(S) + len(T)
    assert held.size_before(2)[1] == total and held.cap == held.cap_of(held.size_before(2)[0]) > held.cap_of(4)
    assert {(x.rid_r, x.rid_s, x.rid_t) for x in held.index(1).enumerate().collect()} == set(results())


def test_the_bound_on_a_join_is_its_least_cover():
    assert size_bound({"c": ("ck",), "o": ("ok", "ck"), "l": ("ok", "rid")}, {"c": 10, "o": 100, "l": 400}) == 4_000
    assert size_bound({"c": ("ck",), "o": ("ok", "ck"), "l": ("ok", "rid")}, {"c": 10, "o": 1000, "l": 400}) == 4_000


def test_tail_variants(spark):
    rows, want = star(spark), results()
    with pytest.raises(ValueError):
        sample_join(rows, seed=1, cap=3, root="r", tail="other")
    for tail in ("materialize", "proxy"):
        got = sample_join(rows, seed=1, cap=3, root="r", tail=tail).collect()
        assert len({(x.rid_r, x.rid_s, x.rid_t) for x in got}) == len(got)
        for x in got:
            assert x.weight == pytest.approx(math.prod(want[x.rid_r, x.rid_s, x.rid_t]))


def test_places_of_a_large_root_stay_where_they_are(spark, monkeypatch):
    """Its places are drawn from behind the joins, with no exchange of all of them; the sample is the same."""
    from joinpoisson.operators import rootlocal

    got = []
    for many in (1, 1 << 40):
        monkeypatch.setattr(rootlocal, "MANY", many)
        found = sample_join(star(spark), seed=5, cap=20, root="r", method="root_local")
        got.append(sorted((x.rid_r, x.rid_s, x.rid_t) for x in found.collect()))
        text = found._jdf.queryExecution().optimizedPlan().toString()
        assert ("RepartitionByExpression" in text) == (many > 1)
    assert got[0] == got[1] and got[0]


def test_tables_of_many_rows_are_not_broadcast(spark, monkeypatch):
    """A planner sees the bytes of written files: counts of a million keys are few, and would be a map in the driver's memory."""
    monkeypatch.setattr("joinpoisson.plans.storage.FEW", 1, raising=False)
    rows = star(spark)
    path, attrs = f"{shared_dir(spark)}/{uuid.uuid4().hex}", {r.name: r.attrs for r in rows}
    in_batches(insertion_log(rows), 1, attrs, lambda b, new: DynamicIndex(spark, path, attrs, root="s").insert(b, new))
    held, index = DynamicIndex(spark, path, attrs, root="s").index(0), ScoreIndex.build(rows, al.PRODUCT, 20, "r", store=False)
    for found in (index.steps["r"], index.steps["s"], index.sample(seed=1), held.enumerate()):
        found.collect()
        joins = [x for x in found._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0].splitlines() if "HashJoin [" in x]
        assert not [x for x in joins if "[score" not in x and "[_s_" not in x], joins
    assert {(x.rid_r, x.rid_s, x.rid_t) for x in held.enumerate().collect()} == set(results())


def test_all_results_are_listed_in_pieces_over_all_tasks(spark, monkeypatch):
    """Intervals are small, so a planner would make the results of all of them in one task."""
    monkeypatch.setattr("joinpoisson.plans.storage.FEW", 0, raising=False)
    monkeypatch.setattr("joinpoisson.operators.index.PIECE", 2, raising=False)
    rows = star(spark)
    path, attrs = f"{shared_dir(spark)}/{uuid.uuid4().hex}", {r.name: r.attrs for r in rows}
    in_batches(insertion_log(rows), 1, attrs, lambda b, new: DynamicIndex(spark, path, attrs, root="s").insert(b, new))
    for index in (DynamicIndex(spark, path, attrs, root="s").index(0), ScoreIndex.build(rows, al.PRODUCT, 20, "r", store=False), ScoreIndex.build(rows, al.GRID, 20, "r")):
        found = index.enumerate()
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert plan.count("REPARTITION_BY_NUM") == 4, plan
        got = [(x.rid_r, x.rid_s, x.rid_t) for x in found.collect()]
        assert len(got) == len(results()) and set(got) == set(results())
    ranks = ScoreIndex.build(rows, al.PRODUCT, 20, "r", store=False)
    asked = ranks.access(all_ranks(ranks.buckets.select("score", "n")))
    assert sorted(map(tuple, asked.select("score", "rank", "rid_r", "rid_s", "rid_t").collect())) == sorted(map(tuple, ranks.enumerate().select("score", "rank", "rid_r", "rid_s", "rid_t").collect()))


def test_tail_of_a_path_is_made(spark, small):
    """An attribute that a child and a grandchild share is one column of the results."""
    from joinpoisson.sources.workloads import specs as workload_specs

    got = sample_join(workload_specs(spark, small, "w18"), seed=7, cap=5, root="lineitem", tail="materialize")
    assert len(set(got.columns)) == len(got.columns) and got.count() > 0

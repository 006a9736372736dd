"""Queries of the join samplers, indexes, baselines and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.catalogue import sampling_sql as sql
from joinpoisson.catalogue.registry import add
from joinpoisson.functions.algebra import GRID, MAX, MIN, PRODUCT, SUM, Algebra, constant, score_sql
from joinpoisson.functions.rng import u01_sql
from joinpoisson.operators import baselines, metrics
from joinpoisson.operators.estimators import ht_sum
from joinpoisson.operators.index import ScoreIndex, choose_cap, intervals_of, join_size, places_of, reduce_relations
from joinpoisson.operators.ranks import all_ranks
from joinpoisson.operators.rewrite import push_selection
from joinpoisson.operators.sampler import sample_join
from joinpoisson.plans.jointree import build_join_tree, decompose
from joinpoisson.plans.relations import RelationSpec, schemas
from joinpoisson.sources.workloads import NUMBERED, WORKLOADS, Rel, Workload, join_sql, relation_sql, specs

CAP, SEED = 20, 7
PROXY_CAP = 14  # the bound of w18 at sf0.01 is about 2^30: some 55,000 candidates in its tail
ALGEBRAS = {"product": PRODUCT, "min": MIN, "max": MAX, "sum": SUM, "constant": constant(0.0625)}


def workload(name: str, algebra: Algebra = PRODUCT) -> Workload:
    """The workload; for sums every weight is divided by the number of relations."""
    w = WORKLOADS[name]
    return w.with_weights(lambda t: f"({t}) / {len(w.rels)}.0e0") if algebra.name == "sum" else w


def _shown(df: DataFrame, work: Workload, *more: str) -> DataFrame:
    return df.select(*[f"rid_{r.name}" for r in work.rels], *more, F.round("weight", 9).alias("weight"))


def _built(spark, d, work: Workload, algebra: Algebra, cap: int = CAP, store: bool = False) -> ScoreIndex:
    return ScoreIndex.build(specs(spark, d, work), algebra, cap, work.root, store=store)


def _one(spark, **values) -> DataFrame:
    row = spark.range(1)
    return row.select(*[F.lit(v).cast("double" if isinstance(v, float) else "long").alias(k) for k, v in values.items()])


def _register() -> None:
    for n in ("w01", "w02", "w03", "w04", "w05", "w08", "w09", "w10", "w11", "w18", "w20", "w21"):
        add(f"index_join_size_{n}", lambda s, d, n=n: _one(s, results=join_size(specs(s, d, n), WORKLOADS[n].root)), f"SELECT CAST(count(*) AS BIGINT) AS results FROM ({join_sql(n)})")

    # Joins that are too large to make: their sizes from counts by key.
    add("index_join_size_w06", lambda s, d: _one(s, results=join_size(specs(s, d, "w06"), "b")), "SELECT CAST(sum(a.n * c.n) AS BIGINT) AS results FROM lineitem b JOIN (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1) a ON a.l_partkey = b.l_partkey JOIN (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1) c ON c.l_suppkey = b.l_suppkey")
    add("index_join_size_w07", lambda s, d: _one(s, results=join_size(specs(s, d, "w07"), "nation")), "WITH x AS (SELECT s_nationkey AS nk, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1), y AS (SELECT c_nationkey AS nk, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1) SELECT CAST(sum(x.n * y.n) AS BIGINT) AS results FROM x JOIN y ON x.nk = y.nk")
    add("index_join_size_w08k3", lambda s, d: _one(s, results=join_size(specs(s, d, "w08k3"), "a")), "SELECT CAST(sum(n * n * n) AS BIGINT) AS results FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1)")

    for a, names in {"product": ("w01", "w02", "w03", "w05", "w09", "w11"), "min": ("w01", "w02", "w05", "w04"), "max": ("w01", "w02", "w05"), "sum": ("w01", "w02", "w05")}.items():
        for n in names:
            alg, work = ALGEBRAS[a], workload(n, ALGEBRAS[a])
            add(f"index_bucket_sizes_{a}_{n}", lambda s, d, alg=alg, work=work: _built(s, d, work, alg).buckets.select("score", "n", "ceiling"), f"WITH {sql.scored(work, alg, CAP)} SELECT score, CAST(count(*) AS BIGINT) AS n, CAST({alg.ceiling_sql('score', len(work.rels))} AS DOUBLE) AS ceiling FROM scored GROUP BY score")

    def explosive(s, d, name):
        work = WORKLOADS[name]
        return ScoreIndex.build(specs(s, d, work), PRODUCT, 40, work.root, store=False).buckets.select("score", "n")

    line = f"(SELECT *, {score_sql('l_quantity / 5000.0e0', 40)} AS pa, {score_sql('1.0e0 - l_tax', 40)} AS pb, {score_sql('(1.0e0 - l_discount) / 100.0e0', 40)} AS pc FROM lineitem)"
    add("index_bucket_sizes_explosive_w06", lambda s, d: explosive(s, d, "w06"), f"WITH l AS {line}, a AS (SELECT l_partkey, pa, count(*) AS n FROM l GROUP BY 1, 2), c AS (SELECT l_suppkey, pc, count(*) AS n FROM l GROUP BY 1, 2) SELECT CAST(a.pa + l.pb + c.pc AS INTEGER) AS score, CAST(sum(a.n * c.n) AS BIGINT) AS n FROM l JOIN a ON a.l_partkey = l.l_partkey JOIN c ON c.l_suppkey = l.l_suppkey GROUP BY 1")

    w01, w02, w05 = WORKLOADS["w01"], WORKLOADS["w02"], WORKLOADS["w05"]
    classes = ", ".join(score_sql(f"w_{n}", CAP) for n in sql.tree_of(w01).names)
    add("index_bucket_sizes_grid_w01", lambda s, d: _built(s, d, w01, GRID).buckets.select(F.concat_ws("-", "score").alias("classes"), "n"), f"SELECT concat_ws('-', {classes}) AS classes, CAST(count(*) AS BIGINT) AS n FROM ({join_sql(w01)}) WHERE w_customer > 0 AND w_orders > 0 AND w_lineitem > 0 GROUP BY 1")
    add("index_grid_vs_score_w01", lambda s, d: _built(s, d, w01, GRID).buckets.groupBy(F.least(F.lit(CAP), F.aggregate("score", F.lit(0), lambda a, x: a + x)).alias("score")).agg(F.sum("n").alias("n"), F.count("*").alias("combinations")), f"WITH {sql.scored(w01, PRODUCT, CAP)} SELECT score, CAST(count(*) AS BIGINT) AS n, CAST(count(DISTINCT (phi_customer, phi_orders, phi_lineitem)) AS BIGINT) AS combinations FROM scored GROUP BY score")

    add("index_reduced_orders", lambda s, d: reduce_relations(specs(s, d, w01), "lineitem")[1].df.select(F.col("rid").alias("o_orderkey")), "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) AND o_custkey IN (SELECT c_custkey FROM customer)")

    def key_vectors(s, d):
        return metrics.messages(specs(s, d, w01), "orders", PRODUCT, CAP, "lineitem").select("ok", "score", "n")

    add("index_key_vectors_orders_w01", key_vectors, f"SELECT o.ok, least({CAP}, {score_sql('w_orders', CAP)} + {score_sql('w_customer', CAP)}) AS score, CAST(count(*) AS BIGINT) AS n FROM ({relation_sql(w01.rels[1])}) o JOIN ({relation_sql(w01.rels[0])}) c ON o.ck = c.ck WHERE w_orders > 0 AND w_customer > 0 GROUP BY 1, 2")

    def node_vectors(s, d):
        by = {x.name: x for x in specs(s, d, w02)}
        return places_of(build_join_tree(schemas(list(by.values())), "lineitem"), by, PRODUCT, CAP).groupBy(F.col("rid").alias("rid_lineitem"), "score").agg(F.sum("n").alias("n"))

    add("index_node_vectors_lineitem_w02", node_vectors, f"WITH {sql.scored(w02, PRODUCT, CAP)} SELECT rid_lineitem, score, CAST(count(*) AS BIGINT) AS n FROM scored GROUP BY 1, 2")

    def prefix(s, d):
        by = {x.name: x for x in specs(s, d, w05)}
        node = next(n for n in build_join_tree(schemas(list(by.values())), "nation").walk() if n.name == "customer")
        return intervals_of(node, places_of(node, by, PRODUCT, CAP)).select("nk", "score", F.col("rid").alias("rid_customer"), "lo", "hi")

    add("index_prefix_intervals_w05", prefix, f"WITH c AS (SELECT *, {score_sql('w_customer', CAP)} AS score FROM ({relation_sql(w05.rels[2])}) WHERE w_customer > 0), n AS (SELECT *, CAST(row_number() OVER (PARTITION BY nk, score ORDER BY rid_customer) AS BIGINT) AS hi FROM c) SELECT nk, score, rid_customer, hi - 1 AS lo, hi FROM n")
    add("index_prefix_by_ranges_w05", lambda s, d: _ranges(s, d, w05), f"WITH c AS (SELECT *, {score_sql('w_customer', CAP)} AS score FROM ({relation_sql(w05.rels[2])}) WHERE w_customer > 0), n AS (SELECT *, CAST(row_number() OVER (PARTITION BY nk, score ORDER BY rid_customer) AS BIGINT) AS hi FROM c) SELECT nk, score, rid_customer, hi - 1 AS lo, hi FROM n")
    add("index_meta_probabilities_w01", lambda s, d: _built(s, d, w01, PRODUCT).nonempty().select("score", F.round("q", 9).alias("q")), f"WITH {sql.scored(w01, PRODUCT, CAP)}, b AS (SELECT score, count(*) AS n, pow(2.0e0, -score) AS p FROM scored GROUP BY score) SELECT score, round(CASE WHEN p >= 1 THEN 1.0e0 ELSE 1 - exp(n * ln(1 - p)) END, 9) AS q FROM b")

    for a, n in (("product", "w01"), ("product", "w02"), ("product", "w05"), ("min", "w05"), ("max", "w05")):
        alg, work = ALGEBRAS[a], WORKLOADS[n]
        add(f"index_enumerate_{a}_{n}", lambda s, d, alg=alg, work=work: _built(s, d, work, alg).enumerate().select(*[f"rid_{r.name}" for r in work.rels], "score", "rank"), f"WITH {sql.ranked(work, alg, CAP)} SELECT {sql.rids(work)}, score, rank FROM ranked")

    def merged(s, d):
        from joinpoisson.operators.access import descend

        index = _built(s, d, w05, PRODUCT)
        return descend(index, all_ranks(index.buckets.select("score", "n")), "merge").select(*[f"rid_{r.name}" for r in w05.rels], "score", "rank")

    add("index_access_by_merge_w05", merged, f"WITH {sql.ranked(w05, PRODUCT, CAP)} SELECT {sql.rids(w05)}, score, rank FROM ranked")

    def uniform_access(s, d):
        index = _built(s, d, w05, constant(1.0), 0)
        return index.access(all_ranks(index.buckets.select("score", "n"), runs=True)).select(*[f"rid_{r.name}" for r in w05.rels], "rank")

    add("index_ranked_access_uniform_w05", uniform_access, f"WITH {sql.ranked(w05, constant(1.0), 0)} SELECT {sql.rids(w05)}, rank FROM ranked")

    for a, alg in ALGEBRAS.items():
        work = workload("w01", alg)
        add(f"index_sample_{a}_w01", lambda s, d, alg=alg, work=work: _shown(_built(s, d, work, alg).sample(SEED), work, "score", "rank"), sql.index_sample(work, alg, CAP, SEED))
    for n in ("w02", "w03", "w04", "w05", "w08", "w09", "w10", "w11", "w18", "w20", "w21"):
        work = WORKLOADS[n]
        add(f"index_sample_{n}", lambda s, d, work=work: _shown(_built(s, d, work, PRODUCT).sample(SEED), work, "score", "rank"), sql.index_sample(work, PRODUCT, CAP, SEED))
    add("index_sample_min_w04", lambda s, d: _shown(_built(s, d, WORKLOADS["w04"], MIN).sample(SEED), WORKLOADS["w04"], "score", "rank"), sql.index_sample("w04", MIN, CAP, SEED))
    add("index_sample_multi_draw_w01", lambda s, d: _shown(_built(s, d, w01, PRODUCT).sample(SEED, draws=3), w01, "draw", "score", "rank"), sql.index_sample(w01, PRODUCT, CAP, SEED, 3))
    add("index_sample_gated_w01", lambda s, d: _shown(_built(s, d, w01, PRODUCT).sample(SEED, gate=True), w01, "score", "rank"), sql.index_sample(w01, PRODUCT, CAP, SEED, gate=True))
    add("index_sample_bulk_w01", lambda s, d: _shown(_built(s, d, w01, PRODUCT).sample(SEED, bulk=True), w01, "score"))
    add("index_sample_tail_saturate_w18", lambda s, d: _shown(_built(s, d, WORKLOADS["w18"], PRODUCT, 5).sample(SEED), WORKLOADS["w18"], "score", "rank"), sql.index_sample("w18", PRODUCT, 5, SEED))
    add("index_sample_tail_materialize_w18", lambda s, d: _shown(_tail(s, d, 5, "materialize"), WORKLOADS["w18"]), _tail_sql())
    tables = [f"(SELECT count(*) FROM {t})" for t in ("orders", "lineitem")]  # the least cover: lineitem has no customer
    proxy = sql.index_sample("w18", PRODUCT, PROXY_CAP, SEED, last=" * ".join(tables))
    add("index_sample_tail_proxy_w18", lambda s, d: _shown(_tail(s, d, PROXY_CAP, "proxy"), WORKLOADS["w18"], "score", "rank"), proxy)
    add("index_sample_explosive_w06", lambda s, d: _shown(sample_join(specs(s, d, "w06"), PRODUCT, SEED, method="root_local", cap=40, root="b", bulk=True), WORKLOADS["w06"], "score"))
    add("index_sample_explosive_w07", lambda s, d: _shown(ScoreIndex.build(specs(s, d, "w07"), PRODUCT, 40, "nation", store=False).sample(SEED, bulk=True), WORKLOADS["w07"], "score"))
    add("index_sample_explosive_w08k3", lambda s, d: _shown(sample_join(specs(s, d, "w08k3"), PRODUCT, SEED, method="root_local", cap=40, root="a", bulk=True), WORKLOADS["w08k3"], "score"))
    add("index_sample_grid_w01", lambda s, d: _shown(ScoreIndex.build(specs(s, d, w01), GRID, CAP, "lineitem", store=False).sample(SEED), w01), sql.counted_sample(w01, CAP, SEED, rounded=False, grid=True))
    cyclic, bags = _bags()
    add("index_sample_cyclic_w12", lambda s, d: _shown(ScoreIndex.build(bag_specs(specs(s, d, "w12"), bags, PRODUCT), PRODUCT, CAP, store=False).sample(SEED), cyclic, "score", "rank"), _cyclic_sql(cyclic))

    for n in ("w01", "w02", "w03"):
        work = WORKLOADS[n]
        add(f"oneshot_batched_{n}", lambda s, d, work=work: _shown(sample_join(specs(s, d, work), PRODUCT, SEED, method="batched", cap=CAP, root=work.root), work, "score", "rank"), sql.index_sample(work, PRODUCT, CAP, SEED))
    add("oneshot_index_w01", lambda s, d: _shown(sample_join(specs(s, d, w01), PRODUCT, SEED, method="index", cap=CAP, root="lineitem"), w01, "score", "rank"), sql.index_sample(w01, PRODUCT, CAP, SEED))
    add("oneshot_auto_w01", lambda s, d: _shown(sample_join(specs(s, d, w01), PRODUCT, SEED, method="auto", cap=CAP, root="lineitem"), w01, "score", "rank"), sql.index_sample(w01, PRODUCT, CAP, SEED))
    for n in ("w01", "w02", "w05"):
        work = WORKLOADS[n]
        add(f"oneshot_root_local_{n}", lambda s, d, work=work: _shown(sample_join(specs(s, d, work), PRODUCT, SEED, method="root_local", cap=CAP, root=work.root), work, "score"), sql.root_local(n, PRODUCT, CAP, SEED))
    for c in (1, 10, 100, 1000, 10000):
        small = WORKLOADS["w01"].with_weights(lambda t, c=c: t if "quantity" not in t else f"({t}) / {c}.0e0")
        add(f"wl_w16_scale_{c}_w01", lambda s, d, small=small: _shown(_built(s, d, small, PRODUCT, 30).sample(SEED), small, "score", "rank"), sql.index_sample(small, PRODUCT, 30, SEED))
    ones = WORKLOADS["w01"].with_weights(lambda t: "1.0e0")
    add("wl_w18_all_ones_w01", lambda s, d: _shown(_built(s, d, ones, PRODUCT).sample(SEED), ones, "score", "rank"), sql.index_sample(ones, PRODUCT, CAP, SEED))
    zeros = WORKLOADS["w01"].with_weights(lambda t: "0.0e0")
    add("wl_w18_all_zeros_w01", lambda s, d: _shown(_built(s, d, zeros, PRODUCT).sample(SEED), zeros, "score", "rank"), sql.index_sample(zeros, PRODUCT, CAP, SEED))

    def selected(s, d):
        rows = push_selection(specs(s, d, w01), {"lineitem": F.col("w") > 0.5})
        return _shown(baselines.naive_sample(rows, PRODUCT, SEED), w01)

    add("rewrite_selection_before_w01", selected, f"WITH {sql.naive(w01, PRODUCT, SEED)} SELECT {sql.rids(w01)}, round(weight, 9) AS weight FROM naive WHERE w_lineitem > 0.5")
    add("rewrite_selection_indexed_w01", lambda s, d: _shown(sample_join(push_selection(specs(s, d, w01), {"lineitem": F.col("w") > 0.5}), PRODUCT, SEED, cap=CAP, root="lineitem"), w01, "score", "rank"), sql.index_sample(_selected(w01), PRODUCT, CAP, SEED))
    for n in ("w01", "w02", "w05", "w12"):
        work = WORKLOADS[n]
        add(f"baseline_naive_{n}", lambda s, d, work=work: _shown(baselines.naive_sample(specs(s, d, work), PRODUCT, SEED), work), f"WITH {sql.naive(work, PRODUCT, SEED)} SELECT {sql.rids(work)}, round(weight, 9) AS weight FROM naive")
    names = sorted(r.name for r in w01.rels)
    result = "concat_ws('-', " + ", ".join(f"lpad(CAST(rid_{n} AS VARCHAR), 12, '0')" for n in names) + ")"
    keyed = f"k AS (SELECT *, {result} AS result, {score_sql('weight', 40)} AS class FROM (SELECT *, {PRODUCT.weight_sql([f'w_{n}' for n in names])} AS weight FROM j) WHERE weight > 0), placed AS (SELECT *, CAST(class AS VARCHAR) AS part, row_number() OVER (PARTITION BY class ORDER BY result) AS place FROM k), parts AS (SELECT part, count(*) AS n, pow(2.0e0, -CAST(part AS DOUBLE)) AS p FROM placed GROUP BY part)"
    add("baseline_materialized_w01", lambda s, d: _shown(baselines.MaterializedIndex.build(specs(s, d, w01)).sample(SEED), w01), f"WITH j AS ({join_sql(w01)}), {keyed}, {sql.hits('parts', SEED)} SELECT {sql.rids(w01)}, round(weight, 9) AS weight FROM placed e JOIN hits h ON e.part = h.part AND e.place = h.rank WHERE {u01_sql(str(SEED), '0', repr('keep'), 'result')} * h.p < weight")
    thin = " AND ".join(u01_sql(str(SEED), "0", f"'{r.name}'", f"rid_{r.name}") + f" < w_{r.name}" for r in w01.rels)
    add("baseline_independent_inputs_w01", lambda s, d: baselines.sample_inputs_then_join(specs(s, d, w01), SEED).select("rid_customer", "rid_orders", "rid_lineitem"), f"SELECT {sql.rids(w01)} FROM ({join_sql(w01)}) WHERE {thin}")

    for a in ("product", "min", "max", "sum"):
        work = workload("w01", ALGEBRAS[a])
        weight = ALGEBRAS[a].weight_sql([f"w_{n}" for n in names])
        add(f"measure_mu_{a}_w01", lambda s, d, a=a, work=work: _one(s, mu=round(float(metrics.expected_size(specs(s, d, work), ALGEBRAS[a])), 4)), f"SELECT round(CAST(sum({weight}) AS DOUBLE), 4) AS mu FROM ({join_sql(work)})")
    add("measure_mu_product_w06", lambda s, d: _one(s, mu=round(float(metrics.expected_size(specs(s, d, "w06"))), 3)), "SELECT round(sum((1.0e0 - b.l_tax) * a.w * c.w), 3) AS mu FROM lineitem b JOIN (SELECT l_partkey, sum(l_quantity / 5000.0e0) AS w FROM lineitem GROUP BY 1) a ON a.l_partkey = b.l_partkey JOIN (SELECT l_suppkey, sum((1.0e0 - l_discount) / 100.0e0) AS w FROM lineitem GROUP BY 1) c ON c.l_suppkey = b.l_suppkey")
    add("measure_candidates_w01", lambda s, d: _one(s, candidates=round(float(metrics.candidate_size(_built(s, d, w01, PRODUCT))), 6)), f"WITH {sql.scored(w01, PRODUCT, CAP)} SELECT round(CAST(sum(pow(2.0e0, -score)) AS DOUBLE), 6) AS candidates FROM scored")
    add("measure_tail_w18", lambda s, d: _one(s, tail=metrics.tail_size(_built(s, d, WORKLOADS["w18"], PRODUCT, 8))), f"WITH {sql.scored(WORKLOADS['w18'], PRODUCT, 8)} SELECT CAST(count(*) AS BIGINT) AS tail FROM scored WHERE score = 8")
    add("measure_beta_by_bucket_w02", _beta, f"WITH {sql.scored(w02, PRODUCT, CAP)} SELECT score, CAST(count(*) AS BIGINT) AS n, round(max(weight) / min(weight), 6) AS beta FROM scored GROUP BY score")
    add("measure_cap_w01", lambda s, d: _one(s, cap=choose_cap(specs(s, d, w01), PRODUCT), bound=choose_cap(specs(s, d, w01), PRODUCT, "bound")), f"SELECT CAST(ceil(log2((SELECT count(*) FROM ({join_sql(w01)})))) AS BIGINT) AS cap, CAST(ceil(4 * log2((SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem))) AS BIGINT) AS bound")
    add("measure_index_space_w02", lambda s, d: _built(s, d, w02, PRODUCT).nonzeros(), "SELECT 'lineitem' AS relation, CAST(count(*) AS BIGINT) AS entries FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey WHERE p_size > 0 AND s_acctbal > -1000 AND l_quantity > 0 UNION ALL SELECT 'orders', count(*) FROM orders WHERE o_totalprice > 0 UNION ALL SELECT 'part', count(*) FROM part WHERE p_size > 0 UNION ALL SELECT 'supplier', count(*) FROM supplier WHERE s_acctbal > -1000")
    add("measure_input_w03", lambda s, d: metrics.count_results(specs(s, d, "w03")), f"SELECT CAST(6 AS INTEGER) AS relations, CAST((SELECT count(*) FROM region) + (SELECT count(*) FROM nation) + (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) + (SELECT count(*) FROM part) AS BIGINT) AS tuples, CAST((SELECT count(*) FROM ({join_sql('w03')})) AS BIGINT) AS results")

    w11, draws = WORKLOADS["w11"], 40
    many = lambda s, d: baselines.naive_sample(specs(s, d, w11), PRODUCT, SEED, draws=draws)
    ctes = sql.naive(w11, PRODUCT, SEED, draws)
    add("measure_inclusion_w11", lambda s, d: metrics.inclusion_counts(many(s, d), ["a", "b"]), f"WITH {ctes} SELECT rid_a, rid_b, CAST(count(*) AS BIGINT) AS times FROM naive GROUP BY 1, 2")
    add("measure_size_moments_w11", lambda s, d: metrics.size_moments(many(s, d), draws).select("draws", F.round("mean", 6).alias("mean"), F.round("variance", 6).alias("variance")), f"WITH {ctes}, n AS (SELECT draw, count(*) AS size FROM naive GROUP BY draw), m AS (SELECT coalesce(size, 0) AS size FROM range(0, {draws}) r(draw) LEFT JOIN n ON r.draw = n.draw) SELECT CAST(count(*) AS BIGINT) AS draws, round(avg(size), 6) AS mean, round(var_pop(size), 6) AS variance FROM m")
    add("measure_pair_cov_w11", lambda s, d: metrics.pair_counts(many(s, d), "rid_b", "rid_a", draws).select(F.round("together", 6).alias("together"), F.round("independent", 6).alias("independent")), f"WITH {ctes}, f AS (SELECT rid_a, rid_b, count(*) / {draws}.0e0 AS f FROM naive GROUP BY 1, 2), p AS (SELECT sum(x.f * y.f) AS independent FROM f x JOIN f y ON x.rid_a = y.rid_a AND x.rid_b < y.rid_b), t AS (SELECT count(*) / {draws}.0e0 AS together FROM naive x JOIN naive y ON x.draw = y.draw AND x.rid_a = y.rid_a AND x.rid_b < y.rid_b) SELECT round(together, 6) AS together, round(independent, 6) AS independent FROM t, p")
    add("measure_draw_cov_w11", lambda s, d: metrics.draw_covariance(many(s, d), ["a", "b"], draws).select("observed", F.round("expected", 6).alias("expected")), f"WITH {ctes}, o AS (SELECT CAST(count(*) AS DOUBLE) AS observed FROM naive x JOIN naive y ON x.draw = y.draw - 1 AND x.rid_a = y.rid_a AND x.rid_b = y.rid_b), f AS (SELECT sum(pow(n / {draws}.0e0, 2)) * {draws - 1} AS expected FROM (SELECT count(*) AS n FROM naive GROUP BY rid_a, rid_b)) SELECT observed, round(expected, 6) AS expected FROM o, f")

    def revenue(s, d):
        sample = baselines.naive_sample(specs(s, d, w01), PRODUCT, SEED)
        line = s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("ck"), "c_mktsegment")
        return ht_sum(sample.join(line, "ck"), F.col("w_lineitem") * 50, by=["c_mktsegment"]).select("c_mktsegment", "sampled", F.round("estimate", 3).alias("estimate"), F.round(F.sqrt("variance"), 3).alias("deviation"))

    v = "(w_lineitem * 50)"
    add("measure_ht_quantity_by_segment_w01", revenue, f"WITH {sql.naive(w01, PRODUCT, SEED)} SELECT c_mktsegment, CAST(count(*) AS BIGINT) AS sampled, round(sum({v} / weight), 3) AS estimate, round(sqrt(sum({v} * {v} * (1 - weight) / (weight * weight))), 3) AS deviation FROM naive JOIN customer ON ck = c_custkey GROUP BY 1")


def _selected(work: Workload) -> Workload:
    """The workload over the lines of more than half the largest quantity."""
    return Workload(work.name, tuple(Rel(r.name, f"(SELECT * FROM (SELECT *, row_number() OVER (ORDER BY {', '.join(NUMBERED[r.table])}) AS _rid FROM {r.table}) WHERE {r.weight} > 0.5)" if r.name == "lineitem" else r.table, r.attrs, r.weight, r.rid) for r in work.rels), work.root)


def _ranges(s, d, work: Workload) -> DataFrame:
    by = {x.name: x for x in specs(s, d, work)}
    node = next(n for n in build_join_tree(schemas(list(by.values())), "nation").walk() if n.name == "customer")
    return intervals_of(node, places_of(node, by, PRODUCT, CAP), large=0).select("nk", "score", F.col("rid").alias("rid_customer"), "lo", "hi")


def _beta(s, d) -> DataFrame:
    results = _built(s, d, WORKLOADS["w02"], PRODUCT).enumerate()
    weight = PRODUCT.weight([F.col(f"w_{n}") for n in sorted(r.name for r in WORKLOADS["w02"].rels)])
    return metrics.bucket_uniformity(results, weight, F.col("score")).withColumn("beta", F.round("beta", 6))


def _tail(s, d, cap: int, tail: str) -> DataFrame:
    work = WORKLOADS["w18"]
    return sample_join(specs(s, d, work), PRODUCT, SEED, cap=cap, root=work.root, tail=tail)


def _tail_sql() -> str:
    work = WORKLOADS["w18"]
    head = sql.index_sample(work, PRODUCT, 5, SEED)
    tail = f"WITH {sql.scored(work, PRODUCT, 5)} SELECT {sql.rids(work)}, round(weight, 9) AS weight FROM scored WHERE score = 5 AND {sql.coin(work, SEED, '0', 'naive')} < weight"
    return f"SELECT {sql.rids(work)}, weight FROM ({head}) WHERE score < 5 UNION ALL ({tail})"


def bag_specs(rows: list[RelationSpec], bags: list[list[str]], algebra: Algebra) -> list[RelationSpec]:
    """A relation for each bag: the join of its members, weighed by the algebra; each weight is in one bag."""
    from joinpoisson.plans.relations import assign_rid

    by, out = {r.name: r for r in rows}, []
    for bag in bags:
        joined = baselines.natural_join([by[n] for n in bag])
        ids = [f"rid_{n}" for n in bag]
        numbered = assign_rid(joined.withColumn("w", algebra.weight([F.col(f"w_{n}") for n in bag])), ids)
        out.append(RelationSpec("_".join(bag), numbered, tuple(dict.fromkeys(a for n in bag for a in by[n].attrs))))
    return out


def _bags() -> tuple[Workload, list[list[str]]]:
    work = WORKLOADS["w12"]
    bags = decompose({r.name: tuple(r.attrs) for r in work.rels})
    rels = tuple(Rel("_".join(b), "", {a: a for n in b for r in work.rels if r.name == n for a in r.attrs}, "") for b in bags)
    return Workload("w12bags", rels), bags


def _cyclic_sql(cyclic: Workload) -> str:
    work = WORKLOADS["w12"]
    by = {r.name: r for r in work.rels}
    _, bags = _bags()
    views, k = [], len(bags)
    for bag in bags:
        part = Workload("bag", tuple(by[n] for n in bag))
        name = "_".join(bag)
        ids = ", ".join(f"rid_{n}" for n in bag)
        views.append(f"b_{name} AS (SELECT *, CAST(row_number() OVER (ORDER BY {ids}) AS BIGINT) AS rid_{name}, {' * '.join(f'w_{n}' for n in bag)} AS w_{name} FROM ({join_sql(part)}))")
    names = ["_".join(b) for b in bags]
    tree = build_join_tree({"_".join(b): tuple(dict.fromkeys(a for n in b for a in by[n].attrs)) for b in bags})
    first, rest = names[0], names[1:]
    seen = {a for n in bags[0] for a in by[n].attrs}
    joins = f"b_{first}"
    for name, bag in zip(rest, bags[1:], strict=True):
        attrs = {a for n in bag for a in by[n].attrs}
        joins += f" JOIN b_{name} ON {' AND '.join(f'b_{first}.{a} = b_{name}.{a}' for a in sorted(attrs & seen))}"
    phis = ", ".join(f"{score_sql(f'w_{n}', CAP)} AS phi_{n}" for n in names)
    columns = ", ".join(f"rid_{n}, w_{n}" for n in names)
    subs = ", ".join(f"{sql._sub(n, PRODUCT, CAP)} AS sub_{n.name}" for n in tree.walk())
    weight = PRODUCT.weight_sql([f"w_{n}" for n in sorted(names)])
    return f"""WITH {', '.join(views)}, j AS (SELECT {columns} FROM {joins}), phis AS (SELECT *, {phis} FROM j WHERE {' AND '.join(f'w_{n} > 0' for n in names)}),
    scored AS (SELECT *, {subs}, sub_{tree.name} AS score, {weight} AS weight FROM phis),
    ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY score ORDER BY {', '.join(sql._order(tree))}) AS BIGINT) AS rank FROM scored),
    sizes AS (SELECT score, count(*) AS n, CAST(score AS VARCHAR) AS part FROM scored GROUP BY score), parts AS (SELECT *, CAST(pow(2.0e0, -score) AS DOUBLE) AS p FROM sizes), {sql.hits('parts', SEED)}
    SELECT {', '.join(f'rid_{n}' for n in names)}, r.score, r.rank, round(weight, 9) AS weight FROM ranked r JOIN hits h ON CAST(r.score AS VARCHAR) = h.part AND r.rank = h.rank WHERE {sql.coin(cyclic, SEED)} * h.p < weight"""


_register()

"""Queries of the explicit-set samplers and of insertions."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joinpoisson.catalogue import sampling_sql as sql
from joinpoisson.catalogue.registry import add
from joinpoisson.functions.algebra import GRID, PRODUCT, score_sql
from joinpoisson.functions.rng import u01_sql
from joinpoisson.operators import explicit
from joinpoisson.operators.dynamic import DynamicIndex, MaintainedSample, StaticRebuild, delta_joins, density, inflation
from joinpoisson.operators.index import message_of
from joinpoisson.operators.metrics import join_size
from joinpoisson.plans.jointree import build_join_tree
from joinpoisson.plans.storage import shared_dir
from joinpoisson.sources.workloads import WEIGHTS, WORKLOADS, Workload, join_sql, relation_sql, specs
from joinpoisson.streaming.runner import in_batches, insertion_log, run_insertions, write_slices

SEED, CAP = 7, 40
W_DOC, W_EVT, W_ORD, W_VEC = WEIGHTS["doc"], WEIGHTS["evt"], WEIGHTS["ord"], WEIGHTS["vec"]


def _read(s, d, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def _coin(purpose: str, key: str, draw: str = "0") -> str:
    return u01_sql(str(SEED), draw, f"'{purpose}'", key)


def _parts_sql(table: str, key: str, part: str, weight: str, ceiling: str, where: str = "true") -> str:
    """Elements with places, parts, hits and the kept ones."""
    return f"""WITH e AS (SELECT *, CAST({part} AS VARCHAR) AS part, CAST({weight} AS DOUBLE) AS weight FROM {table} WHERE {where}),
    placed AS (SELECT *, row_number() OVER (PARTITION BY part ORDER BY {key}) AS place FROM e),
    parts AS (SELECT part, count(*) AS n, CAST({ceiling} AS DOUBLE) AS p FROM e GROUP BY part), {sql.hits('parts', SEED)}
    SELECT e.{key}, e.part, CAST(e.place AS BIGINT) AS place FROM placed e JOIN hits h ON e.part = h.part AND e.place = h.rank"""


def _register() -> None:
    shown = lambda df, key: df.select(key, "part", "place")
    doc, evt, order = (lambda w=w: F.expr(w) for w in (W_DOC, W_EVT, W_ORD))  # no session is needed to register
    add("explicit_bernoulli_documents", lambda s, d: explicit.sample_bernoulli(_read(s, d, "documents"), "doc_id", doc(), SEED).select("doc_id", "lang"), f"SELECT doc_id, lang FROM documents WHERE {_coin('coin', 'doc_id')} < {W_DOC}")
    add("explicit_uniform_skip_orders", lambda s, d: shown(explicit.sample_uniform_skip(_read(s, d, "orders").select("o_orderkey"), "o_orderkey", 0.01, SEED), "o_orderkey"), _parts_sql("orders", "o_orderkey", "'all'", "0.01", "0.01"))

    def lines(s, d):
        from joinpoisson.sources.workloads import table

        return shown(explicit.sample_uniform_skip(table(s, d, "lineitem").select("_rid"), "_rid", 0.01, SEED), "_rid")

    from joinpoisson.sources.workloads import LINE_ORDER

    numbered = f"(SELECT row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) AS _rid FROM lineitem)"
    add("explicit_uniform_skip_lineitem", lines, _parts_sql(numbered, "_rid", "'all'", "0.01", "0.01"))

    gate = u01_sql(str(SEED), "0", "'gate'", "part")
    first = u01_sql(str(SEED), "0", "'first'", "part")
    gated = f"""WITH e AS (SELECT event_id, CAST(user_id AS VARCHAR) AS part FROM events), placed AS (SELECT *, row_number() OVER (PARTITION BY part ORDER BY event_id) AS place FROM e),
    sizes AS (SELECT part, count(*) AS n, 0.02e0 AS p FROM e GROUP BY part),
    open AS (SELECT *, CAST(least(floor(ln(1 - (1 - pow(1 - p, n)) * {first}) / ln(1 - p)), n - 1) AS BIGINT) + 1 AS first FROM sizes WHERE {gate} < 1 - pow(1 - p, n)),
    parts AS (SELECT part, n - first AS n, p, first FROM open), {sql.hits('parts', SEED)},
    hit AS (SELECT part, first AS place FROM open UNION ALL SELECT h.part, h.rank + o.first FROM hits h JOIN open o ON h.part = o.part)
    SELECT event_id, e.part, CAST(e.place AS BIGINT) AS place FROM placed e JOIN hit h ON e.part = h.part AND e.place = h.place"""

    def gated_events(s, d):
        rows = explicit.placed(_read(s, d, "events").select("event_id", "user_id"), F.col("user_id"), "event_id")
        parts = rows.groupBy("part").agg(F.count("*").alias("n")).withColumn("p", F.lit(0.02))
        return shown(explicit.sample_parts(rows, parts, "event_id", None, SEED), "event_id")

    add("explicit_uniform_gated_events", gated_events, gated)
    add("explicit_rejection_documents", lambda s, d: shown(explicit.sample_rejection(_read(s, d, "documents"), "doc_id", doc(), SEED), "doc_id"), _parts_sql("documents", "doc_id", "'all'", W_DOC, "max(weight)") + f" WHERE {_coin('keep', 'e.doc_id')} * h.p < weight")
    big = lambda s, d: _read(s, d, "orders").where("o_totalprice > 250000")
    add("explicit_beta_uniform_orders", lambda s, d: shown(explicit.sample_rejection(big(s, d), "o_orderkey", order(), SEED), "o_orderkey"), _parts_sql("orders", "o_orderkey", "'all'", W_ORD, "max(weight)", "o_totalprice > 250000") + f" WHERE {_coin('keep', 'e.o_orderkey')} * h.p < weight")
    stats = lambda t, w, where="true": f"SELECT CAST(count(*) AS BIGINT) AS n, max({w}) AS largest, min({w}) FILTER ({w} > 0) AS least, max({w}) / min({w}) FILTER ({w} > 0) AS beta, max({w}) * count(*) <= 1 AS light FROM {t} WHERE {where}"
    add("measure_uniformity_orders", lambda s, d: explicit.uniformity(big(s, d), order()), stats("orders", W_ORD, "o_totalprice > 250000"))
    light = "1.0e0 / (2.0e0 * (n_chars + 2000))"
    add("measure_uniformity_light_documents", lambda s, d: explicit.uniformity(_read(s, d, "documents"), F.expr(light)), stats("documents", light))
    add("explicit_light_documents", lambda s, d: shown(explicit.sample_rejection(_read(s, d, "documents"), "doc_id", F.expr(light), SEED), "doc_id"), _parts_sql("documents", "doc_id", "'all'", light, "max(weight)") + f" WHERE {_coin('keep', 'e.doc_id')} * h.p < weight")
    users = lambda s, d, meta: shown(explicit.sample_batched(_read(s, d, "events").select("event_id", "user_id", "value"), "event_id", F.col("user_id"), evt(), SEED, meta=meta), "event_id")
    add("explicit_batched_nometa_events", lambda s, d: users(s, d, False), _parts_sql("events", "event_id", "user_id", W_EVT, "max(weight)") + f" WHERE {_coin('keep', 'e.event_id')} * h.p < weight")
    add("explicit_batched_events", lambda s, d: users(s, d, True))
    by_class = _parts_sql("documents", "doc_id", score_sql(W_DOC, CAP), W_DOC, "pow(2.0e0, -CAST(part AS DOUBLE))", f"{W_DOC} > 0") + f" WHERE {_coin('keep', 'e.doc_id')} * h.p < weight"
    docs = lambda s, d: _read(s, d, "documents").select("doc_id", "n_chars")
    add("explicit_classified_documents", lambda s, d: shown(explicit.ClassifiedSet.build(docs(s, d), "doc_id", doc()).sample(SEED, gate=False), "doc_id"), by_class)
    vec = _parts_sql("embeddings", "vec_id", score_sql(W_VEC, CAP), W_VEC, "pow(2.0e0, -CAST(part AS DOUBLE))") + f" WHERE {_coin('keep', 'e.vec_id')} * h.p < weight"
    add("explicit_classified_embeddings", lambda s, d: shown(explicit.ClassifiedSet.build(_read(s, d, "embeddings").select("vec_id", "label"), "vec_id", F.expr(W_VEC)).sample(SEED, gate=False), "vec_id"), vec)

    def changed(s, d):
        rows = _read(s, d, "events").select("event_id", "value")
        held = explicit.ClassifiedSet.build(rows.where("event_id % 3 < 2"), "event_id", evt())
        held = held.upsert(rows.where("event_id % 3 = 2 OR event_id % 5 = 0").withColumn("value", F.col("value") / 2), evt()).delete(rows.where("event_id % 7 = 0"))
        return shown(held.sample(SEED, gate=False), "event_id")

    now = "(SELECT event_id, CASE WHEN event_id % 3 = 2 OR event_id % 5 = 0 THEN value / 2 ELSE value END AS value FROM events WHERE event_id % 7 <> 0)"
    add("explicit_dynamic_events", changed, _parts_sql(now, "event_id", score_sql(W_EVT, CAP), W_EVT, "pow(2.0e0, -CAST(part AS DOUBLE))", f"{W_EVT} > 0") + f" WHERE {_coin('keep', 'e.event_id')} * h.p < weight")

    def at_rank(s, d):
        rows = explicit.placed(_read(s, d, "orders").select("o_orderkey", "o_orderpriority"), F.col("o_orderpriority"), "o_orderkey")
        asked = rows.groupBy("part").agg(F.count("*").alias("n")).select("part", F.explode(F.array(F.lit(1).cast("long"), F.expr("n div 2"), F.col("n"))).alias("rank"))
        return explicit.element_at_rank(rows, asked).select("part", "rank", "o_orderkey")

    add("explicit_element_at_rank", at_rank, "WITH r AS (SELECT o_orderpriority AS part, CAST(row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey) AS BIGINT) AS rank, o_orderkey, count(*) OVER (PARTITION BY o_orderpriority) AS n FROM orders), a AS (SELECT DISTINCT part, n, unnest([1, n // 2, n]) AS rank FROM r) SELECT r.part, r.rank, o_orderkey FROM r JOIN a ON r.part = a.part AND r.rank = a.rank")

    # Insertions.
    w13, w14, w05 = WORKLOADS["w01"], WORKLOADS["w08"], WORKLOADS["w05"]

    def attrs(rows):
        return {r.name: r.attrs for r in rows}

    def home(s) -> str:
        return f"{shared_dir(s)}/state-{uuid.uuid4().hex}"

    def ids(df, work):
        return df.select(*[f"rid_{r.name}" for r in work.rels])

    def delta_sizes(s, d):
        rows = specs(s, d, w13)
        state = StaticRebuild(s, home(s), attrs(rows))
        from joinpoisson.operators.dynamic import TupleRuns

        runs, found = TupleRuns(s, state.path, attrs(rows)), []

        def insert(batch, new):
            added = runs.add(batch, new)
            found.append((batch, sum(join_size(part, name) for name, part in delta_joins(runs, batch, added))))

        in_batches(insertion_log(rows), 3, attrs(rows), insert, F.pmod(F.col("rid"), F.lit(3)))
        return s.createDataFrame(found, "batch int, results long")

    add("dynamic_delta_size_w13", delta_sizes, f"SELECT CAST(greatest(rid_customer % 3, rid_orders % 3, rid_lineitem % 3) AS INTEGER) AS batch, CAST(count(*) AS BIGINT) AS results FROM ({join_sql(w13)}) GROUP BY 1")

    def filled(s, d, work, rounded=True, algebra=PRODUCT, root=None, slices=2):
        rows = specs(s, d, work)
        index = DynamicIndex(s, home(s), attrs(rows), algebra, 1 << 18, root or work.root, rounded)
        in_batches(insertion_log(rows), slices, attrs(rows), index.insert)
        return index, rows

    def raw(s, d):
        index, _ = filled(s, d, w13, rounded=False)
        node = next(n for n in index.tree.walk() if n.name == "orders")
        return index.messages(node, 9).select("ok", "score", F.col("raw").alias("n"))

    deep = 72
    add("dynamic_raw_counters_w13", raw, f"SELECT o.ok, least({deep}, {score_sql('w_orders', deep)} + {score_sql('w_customer', deep)}) AS score, CAST(count(*) AS BIGINT) AS n FROM (SELECT o_orderkey AS ok, o_custkey AS ck, {W_ORD} AS w_orders FROM orders) o JOIN (SELECT c_custkey AS ck, {WEIGHTS['cust']} AS w_customer FROM customer) c ON o.ck = c.ck WHERE w_orders > 0 AND w_customer > 0 GROUP BY 1, 2")

    def rounded(s, d):
        index, _ = filled(s, d, w13, root="customer")
        return index.messages(next(n for n in index.tree.walk() if n.name == "orders"), 9).select("ck", "score", "raw", F.col("n").alias("rounded"))

    at_customer = Workload(w13.name, w13.rels, "customer")
    counts = f"WITH {sql.counted(at_customer, deep)}"
    add("dynamic_rounded_counters_w13", rounded, f"{counts} SELECT ck, score, raw, n AS rounded FROM m_orders")
    add("dynamic_sample_w13", lambda s, d: ids(filled(s, d, w13, slices=4)[0].sample(9, SEED), w13), f"SELECT {sql.rids(w13)} FROM ({sql.counted_sample(w13, deep, SEED)})")
    add("dynamic_grid_sample_w05", lambda s, d: ids(filled(s, d, w05, algebra=GRID)[0].sample(9, SEED), w05), f"SELECT {sql.rids(w05)} FROM ({sql.counted_sample(w05, deep, SEED, grid=True)})")

    def real_results(s, d):
        return ids(filled(s, d, w05)[0].index(9).enumerate(), w05)

    add("dynamic_enumerate_w05", real_results, f"SELECT {sql.rids(w05)} FROM ({join_sql(w05)}) WHERE w_supplier > 0 AND w_nation > 0 AND w_customer > 0")
    add("measure_dummy_rate_w13", lambda s, d: density(filled(s, d, w13, root="customer")[0].index(9)), f"{counts} SELECT CAST((SELECT sum(places_n) FROM p_customer) AS BIGINT) AS ranks, CAST(results AS BIGINT) AS results, CAST((SELECT sum(places_n) FROM p_customer) - results AS BIGINT) AS dummies, CAST(results AS DOUBLE) / (SELECT CAST(sum(places_n) AS DOUBLE) FROM p_customer) AS density FROM (SELECT count(*) AS results FROM r_customer)")

    def inflated(s, d):
        index, rows = filled(s, d, w13, root="customer")
        node = next(n for n in index.tree.walk() if n.name == "orders")
        return inflation(message_of(node, {r.name: r for r in rows}, PRODUCT, index.cap), index.messages(node, 9), ["ck"])

    exact = f"SELECT ck, least({deep}, {score_sql('w_orders', deep)} + {score_sql('w_lineitem', deep)}) AS score, count(*) AS n FROM ({relation_sql(w13.rels[1])}) o JOIN ({relation_sql(w13.rels[2])}) l ON o.ok = l.ok WHERE w_orders > 0 AND w_lineitem > 0 GROUP BY 1, 2"
    add("measure_inflation_w13", inflated, f"{counts} SELECT min(CAST(r.n AS DOUBLE) / e.n) AS least, max(CAST(r.n AS DOUBLE) / e.n) AS largest FROM ({exact}) e JOIN m_orders r ON e.ck = r.ck AND e.score = r.score")

    def changes(s, d):
        rows = specs(s, d, w13)
        index = DynamicIndex(s, home(s), attrs(rows), PRODUCT, 1 << 18, "customer")
        in_batches(insertion_log(rows), 3, attrs(rows), index.insert, F.pmod(F.col("rid"), F.lit(3)))
        return s.createDataFrame(index.changes, "batch int, relation string, changed long")

    add("measure_changes_w13", changes, _changes_sql(at_customer, deep, 3))

    def maintained(s, d, work, stream, batches=2, exact=False):
        rows = specs(s, d, work)
        sample = MaintainedSample(s, home(s), attrs(rows), PRODUCT, SEED, exact, 20)
        log, batch_of = insertion_log(rows), F.pmod(F.col("rid"), F.lit(batches))
        if stream:
            run_insertions(s, write_slices(log, batches, batch_of), log.schema, attrs(rows), sample.insert)
        else:
            in_batches(log, batches, attrs(rows), sample.insert, batch_of)
        return ids(sample.current(), work)

    by_index = lambda work, batches=2: sql.maintained(work, 20, SEED, f"_rid_ % {batches}", batches)
    for n, work in (("w13", w13), ("w14", w14)):
        add(f"dynamic_maintained_{n}", lambda s, d, work=work: maintained(s, d, work, True), by_index(work))
    add("dynamic_maintained_index_w14", lambda s, d: maintained(s, d, w14, False, 3), by_index(w14, 3))
    add("baseline_maintained_coins_w13", lambda s, d: maintained(s, d, w13, False, exact=True), f"WITH {sql.naive(w13, PRODUCT, SEED)} SELECT {sql.rids(w13)} FROM naive")

    def repeated(s, d):
        rows = specs(s, d, w14)
        sample = MaintainedSample(s, home(s), attrs(rows), PRODUCT, SEED, cap=20)
        log = insertion_log(rows)
        for batch, part in enumerate((log, log.where("rid % 4 = 0"))):
            sample.insert(batch, {r.name: part.where(F.col("relation") == r.name).select(*r.attrs, "rid", "w") for r in rows})
        return ids(sample.current(), w14)

    add("dynamic_duplicates_ignored_w14", repeated, sql.maintained(w14, 20, SEED, "0", 1))
    add("dynamic_static_rebuild_w13", lambda s, d: _rebuilt(s, d, w13, home(s)), f"WITH {sql.scored(w13, PRODUCT, 30)} SELECT CAST(count(*) AS BIGINT) AS results FROM scored")


def _changes_sql(work: Workload, cap: int, batches: int) -> str:
    """batch, relation, changed: the counts that parents see which moved, from the states after each batch."""
    rows = []
    for b in range(batches):
        now, was = (f"(WITH {sql.counted(work, cap, only=f'rid_{{rel}} % {batches} <= {x}')} " for x in (b, b - 1))
        for node in sql.tree_of(work).walk():
            keys = [*node.key, "score"]
            pick = f"SELECT {', '.join(keys)}, n FROM m_{node.name})"
            rows.append(f"SELECT CAST({b} AS INTEGER) AS batch, '{node.name}' AS relation, CAST(count(*) AS BIGINT) AS changed FROM {now}{pick} a LEFT JOIN {was}{pick} o ON {' AND '.join(f'a.{k} = o.{k}' for k in keys)} WHERE a.n <> coalesce(o.n, 0)")
    return " UNION ALL ".join(rows)


def _rebuilt(s, d, work, path) -> DataFrame:
    rows = specs(s, d, work)
    base = StaticRebuild(s, path, {r.name: r.attrs for r in rows})
    in_batches(insertion_log(rows), 2, base.attrs, base.insert)
    return base.index(9).buckets.agg(F.sum("n").alias("results"))


_register()

"""Queries of the relational operators around the samplers: built-in Spark operators, composed."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from joinpoisson.catalogue.registry import add
from joinpoisson.functions.rng import u01, u01_sql
from joinpoisson.operators import explicit
from joinpoisson.plans.storage import shared_dir
from joinpoisson.sources.workloads import WEIGHTS

SEED = 7


def _t(s, d, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def _round(df: DataFrame, *names: str, digits: int = 4) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) for n in names})


def _back(s, df: DataFrame, how: str, **options) -> DataFrame:
    where = f"{shared_dir(s)}/{how}-{uuid.uuid4().hex}"
    df.write.format(how).options(**options).save(where)
    return s.read.schema(df.schema).format(how).options(**options).load(where)


def _scans() -> None:
    add("scan_parquet_pruned", lambda s, d: _t(s, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")
    add("scan_explicit_schema", lambda s, d: s.read.schema("n_nationkey int, n_name string").parquet(f"{d}/nation.parquet"), "SELECT n_nationkey, n_name FROM nation")

    def partitioned(s, d):
        where = f"{shared_dir(s)}/by-status-{uuid.uuid4().hex}"
        _t(s, d, "orders").select("o_orderkey", "o_totalprice", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(where)
        return s.read.parquet(where).where("o_orderstatus = 'F'").select("o_orderkey", "o_totalprice")

    add("scan_partition_pruned", partitioned, "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = 'F'")
    nation, events = "SELECT n_nationkey, n_name, n_regionkey FROM nation", "SELECT event_id, user_id, event_type FROM events"
    for how, sql, name in (("csv", nation, "nation"), ("orc", nation, "nation"), ("json", events, "events")):
        columns = [c.strip() for c in sql[7 : sql.index(" FROM")].split(",")]
        add(f"roundtrip_{how}", lambda s, d, how=how, name=name, columns=columns: _back(s, _t(s, d, name).select(*columns), how), sql)
    add("roundtrip_text", lambda s, d: _back(s, _t(s, d, "pages").select(F.col("url").alias("value")), "text"), "SELECT url AS value FROM pages")

    def bucketed(s, d):
        tag = uuid.uuid4().hex[:8]
        for name, key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
            _t(s, d, name).write.bucketBy(4, key).sortBy(key).mode("overwrite").saveAsTable(f"b_{name}_{tag}")
        return s.table(f"b_orders_{tag}").join(s.table(f"b_lineitem_{tag}"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))

    add("bucketed_table_join", bucketed, "SELECT o_orderpriority, CAST(count(*) AS BIGINT) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")

    def view(s, d):
        _t(s, d, "customer").createOrReplaceTempView("v_customer")
        return s.sql("SELECT c_mktsegment, count(*) AS n FROM v_customer WHERE c_acctbal > 0 GROUP BY c_mktsegment")

    add("scan_sql_view", view, "SELECT c_mktsegment, CAST(count(*) AS BIGINT) AS n FROM customer WHERE c_acctbal > 0 GROUP BY 1")


def _projections() -> None:
    add("proj_expressions", lambda s, d: _t(s, d, "lineitem").selectExpr("l_orderkey", "round(l_extendedprice * (1 - l_discount), 4) AS net", "l_linenumber + 1 AS next"), "SELECT l_orderkey, round(l_extendedprice * (1 - l_discount), 4) AS net, l_linenumber + 1 AS next FROM lineitem")
    add("proj_rename_natural", lambda s, d: _t(s, d, "customer").withColumnsRenamed({"c_custkey": "ck", "c_nationkey": "nk"}).select("ck", "nk"), "SELECT c_custkey AS ck, c_nationkey AS nk FROM customer")
    add("proj_nested_field", lambda s, d: _t(s, d, "supplier").select(F.struct("s_suppkey", F.struct("s_acctbal").alias("money")).alias("x")).select("x.s_suppkey", "x.money.s_acctbal"), "SELECT s_suppkey, s_acctbal FROM supplier")
    orders = lambda s, d: _t(s, d, "orders")
    add("filter_compound", lambda s, d: orders(s, d).where("(o_orderstatus = 'O' OR o_totalprice > 400000) AND NOT o_orderpriority LIKE '5%'").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE (o_orderstatus = 'O' OR o_totalprice > 400000) AND NOT o_orderpriority LIKE '5%'")
    add("filter_in_between", lambda s, d: orders(s, d).where(F.col("o_orderstatus").isin("F", "P") & F.col("o_totalprice").between(1000, 90000)).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderstatus IN ('F', 'P') AND o_totalprice BETWEEN 1000 AND 90000")
    add("filter_like_rlike", lambda s, d: _t(s, d, "pages").where(F.col("url").like("https://%") & F.col("url").rlike("/(en|de)/[0-9]+")).select("page_id"), "SELECT page_id FROM pages WHERE url LIKE 'https://%' AND regexp_matches(url, '/(en|de)/[0-9]+')")
    add("filter_null_safe", lambda s, d: _t(s, d, "labels").join(_t(s, d, "documents"), "doc_id", "right").where(F.col("toxic").eqNullSafe(F.lit(None).cast("int"))).select("doc_id"), "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE toxic IS NOT DISTINCT FROM NULL")
    add("filter_case_when", lambda s, d: _t(s, d, "part").select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("kind"), F.coalesce(F.nullif(F.col("p_size"), F.lit(7)), F.lit(-1)).alias("size")), "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS kind, coalesce(nullif(p_size, 7), -1) AS size FROM part")
    coin = u01_sql(str(SEED), "0", "'coin'", "doc_id")
    sql = f"SELECT doc_id FROM documents WHERE {coin} < {WEIGHTS['doc']} AND lang = 'en'"
    add("filter_then_sample", lambda s, d: explicit.sample_bernoulli(_t(s, d, "documents").where("lang = 'en'"), "doc_id", F.expr(WEIGHTS["doc"]), SEED).select("doc_id"), sql)
    add("sample_then_filter", lambda s, d: explicit.sample_bernoulli(_t(s, d, "documents"), "doc_id", F.expr(WEIGHTS["doc"]), SEED).where("lang = 'en'").select("doc_id"), sql)


def _joins() -> None:
    lines = "SELECT o_orderkey, l_linenumber, l_quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderstatus = 'P'"
    for hint in ("broadcast", "shuffle_hash", "merge"):
        name = {"merge": "sort_merge"}.get(hint, hint)
        add(f"join_inner_{name}", lambda s, d, hint=hint: _t(s, d, "lineitem").join(_t(s, d, "orders").where("o_orderstatus = 'P'").hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).select("o_orderkey", "l_linenumber", "l_quantity"), lines)
    for how, word in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
        add(f"join_{how}", lambda s, d, how=how: _t(s, d, "documents").select("doc_id", "lang").join(_t(s, d, "labels"), "doc_id", how).select("doc_id", "lang", "toxic"), f"SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, lang, toxic FROM documents d {word} JOIN labels l ON d.doc_id = l.doc_id")
    add("join_cross_regions", lambda s, d: _t(s, d, "region").select("r_name").crossJoin(F.broadcast(_t(s, d, "nation").select("n_name"))), "SELECT r_name, n_name FROM region, nation")
    add("join_self_alias", lambda s, d: _t(s, d, "nation").alias("a").join(_t(s, d, "nation").alias("b"), (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("one"), F.col("b.n_name").alias("two")), "SELECT a.n_name AS one, b.n_name AS two FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
    for how, word in (("semi", "IN"), ("anti", "NOT IN")):
        add(f"join_{how}", lambda s, d, how=how: _t(s, d, "orders").join(_t(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), f"left_{how}").select("o_orderkey"), f"SELECT o_orderkey FROM orders WHERE o_orderkey {word} (SELECT l_orderkey FROM lineitem)")
    add("join_theta", lambda s, d: _t(s, d, "nation").join(F.broadcast(_t(s, d, "region")), F.col("n_nationkey") % 5 > F.col("r_regionkey")).select("n_nationkey", "r_regionkey"), "SELECT n_nationkey, r_regionkey FROM nation JOIN region ON n_nationkey % 5 > r_regionkey")

    def ranges(s, d):
        """Sizes fall into bands [10 k, 10 k + 10): an equi-join on the band, then the bounds."""
        bands = s.range(5).select((F.col("id") * 10).alias("low"), (F.col("id") * 10 + 10).alias("high"), F.col("id").alias("band"))
        return _t(s, d, "part").withColumn("band", F.expr("p_size div 10")).join(F.broadcast(bands), "band").where("p_size >= low AND p_size < high").select("p_partkey", "low")

    add("join_range_interval", ranges, "SELECT p_partkey, CAST(low AS BIGINT) AS low FROM part JOIN (SELECT 10 * x AS low FROM range(0, 5) r(x)) ON p_size >= low AND p_size < low + 10")

    def asof(s, d):
        """Each purchase-like event with the last event of its user before it, by one window."""
        w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
        return _t(s, d, "events").select("event_id", F.last("event_id", True).over(w).alias("before"))

    add("join_asof_events", asof, "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events")

    def lateral(s, d):
        _t(s, d, "customer").createOrReplaceTempView("l_customer")
        _t(s, d, "nation").createOrReplaceTempView("l_nation")
        return s.sql("SELECT n_name, t.c_custkey FROM l_nation, LATERAL (SELECT c_custkey FROM l_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) t")

    add("join_lateral_topk", lateral, "SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS k FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE k <= 2")

    def natural(name):
        from joinpoisson.operators.baselines import natural_join
        from joinpoisson.sources.workloads import WORKLOADS, specs

        return lambda s, d: natural_join(specs(s, d, name)).select(*[f"rid_{r.name}" for r in WORKLOADS[name].rels])

    from joinpoisson.catalogue.sampling_sql import rids
    from joinpoisson.sources.workloads import WORKLOADS, join_sql

    for label, name in (("natural_w01", "w01"), ("multiway_w03", "w03")):
        add(f"join_{label}", natural(name), f"SELECT {rids(WORKLOADS[name])} FROM ({join_sql(name)})")
    add("join_null_keys", lambda s, d: _t(s, d, "nation").select(F.nullif(F.col("n_regionkey"), F.lit(1)).alias("k"), "n_name").join(_t(s, d, "region").select(F.nullif(F.col("r_regionkey"), F.lit(1)).alias("k"), "r_name"), "k").select("n_name", "r_name"), "SELECT n_name, r_name FROM nation JOIN region ON nullif(n_regionkey, 1) = nullif(r_regionkey, 1)")


def _aggregates() -> None:
    line = lambda s, d: _t(s, d, "lineitem")
    orders = lambda s, d: _t(s, d, "orders")
    add("agg_basic", lambda s, d: _round(line(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("total"), F.avg("l_extendedprice").alias("mean"), F.min("l_tax").alias("least"), F.max("l_tax").alias("most")), "total", "mean", digits=2), "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, round(sum(l_quantity), 2) AS total, round(avg(l_extendedprice), 2) AS mean, min(l_tax) AS least, max(l_tax) AS most FROM lineitem GROUP BY 1, 2")
    add("agg_distinct", lambda s, d: line(s, d).groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")), "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(count(DISTINCT l_suppkey) AS BIGINT) AS suppliers FROM lineitem GROUP BY 1")
    add("agg_approx_distinct", lambda s, d: line(s, d).agg(F.approx_count_distinct("l_partkey").alias("parts")))
    add("agg_sketch_hll", lambda s, d: line(s, d).agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts")))
    add("agg_percentile", lambda s, d: _round(line(s, d).groupBy("l_returnflag").agg(F.expr("percentile(l_quantity, 0.9)").alias("p90")), "p90"), "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")
    add("agg_median_mode", lambda s, d: orders(s, d).groupBy("o_orderstatus").agg(F.round(F.median("o_totalprice"), 3).alias("middle")), "SELECT o_orderstatus, round(median(o_totalprice), 3) AS middle FROM orders GROUP BY 1")
    add("agg_minby_maxby", lambda s, d: orders(s, d).groupBy("o_orderpriority").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")), "SELECT o_orderpriority, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
    add("agg_collect_sorted", lambda s, d: _t(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
    add("agg_listagg", lambda s, d: _t(s, d, "nation").groupBy("n_regionkey").agg(F.expr("listagg(n_name, ';') WITHIN GROUP (ORDER BY n_name)").alias("names")), "SELECT n_regionkey, string_agg(n_name, ';' ORDER BY n_name) AS names FROM nation GROUP BY 1")
    add("agg_stats", lambda s, d: _round(line(s, d).agg(F.stddev("l_quantity").alias("sd"), F.var_pop("l_quantity").alias("variance"), F.skewness("l_extendedprice").alias("skew")), "sd", "variance", "skew", digits=3), "SELECT round(stddev_samp(l_quantity), 3) AS sd, round(var_pop(l_quantity), 3) AS variance, round(sum(pow(l_extendedprice - m, 3)) / count(*) / pow(any_value(v), 1.5), 3) AS skew FROM lineitem, (SELECT avg(l_extendedprice) AS m, var_pop(l_extendedprice) AS v FROM lineitem)")
    add("agg_corr", lambda s, d: _round(line(s, d).agg(F.corr("l_quantity", "l_extendedprice").alias("r"), F.covar_pop("l_quantity", "l_discount").alias("c")), "r", "c", digits=5), "SELECT round(corr(l_quantity, l_extendedprice), 5) AS r, round(covar_pop(l_quantity, l_discount), 5) AS c FROM lineitem")
    add("agg_filter_clause", lambda s, d: line(s, d).groupBy("l_linestatus").agg(F.expr("count(*) FILTER (WHERE l_quantity > 25)").alias("large"), F.expr("count_if(l_discount = 0)").alias("full")), "SELECT l_linestatus, CAST(count(*) FILTER (l_quantity > 25) AS BIGINT) AS large, CAST(count(*) FILTER (l_discount = 0) AS BIGINT) AS full FROM lineitem GROUP BY 1")
    add("agg_having", lambda s, d: line(s, d).groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600"), "SELECT l_suppkey, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 600")

    def grouping(s, d):
        line(s, d).createOrReplaceTempView("g_line")
        return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM g_line GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")

    add("agg_grouping_sets", grouping, "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
    for how in ("cube", "rollup"):
        add(f"agg_{how}", lambda s, d, how=how: getattr(line(s, d), how)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("g")), f"SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, CAST(grouping(l_returnflag, l_linestatus) AS BIGINT) AS g FROM lineitem GROUP BY {how.upper()}(l_returnflag, l_linestatus)")
    add("agg_pivot", lambda s, d: orders(s, d).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0), "SELECT o_orderpriority, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS \"F\", CAST(count(*) FILTER (o_orderstatus = 'O') AS BIGINT) AS \"O\", CAST(count(*) FILTER (o_orderstatus = 'P') AS BIGINT) AS \"P\" FROM orders GROUP BY 1")
    add("agg_unpivot", lambda s, d: _t(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "what", "value"), "SELECT doc_id, 'quality' AS what, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
    add("agg_bool_bit", lambda s, d: line(s, d).groupBy("l_returnflag").agg(F.bool_and(F.col("l_quantity") > 0).alias("every"), F.bool_or(F.col("l_discount") > 0.09).alias("some"), F.bit_xor("l_partkey").alias("bits")), "SELECT l_returnflag, bool_and(l_quantity > 0) AS every, bool_or(l_discount > 0.09) AS some, bit_xor(l_partkey) AS bits FROM lineitem GROUP BY 1")
    add("agg_product_log", lambda s, d: _round(_t(s, d, "nation").groupBy("n_regionkey").agg(F.exp(F.sum(F.ln((F.col("n_nationkey") + 1) / 25.0))).alias("product")), "product", digits=9), "SELECT n_regionkey, round(exp(sum(ln((n_nationkey + 1) / 25.0e0))), 9) AS product FROM nation GROUP BY 1")

    def vectors(s, d):
        flat = _t(s, d, "embeddings").select("label", F.posexplode("embedding").alias("pos", "x")).groupBy("label", "pos").agg(F.sum(F.floor(F.col("x").cast("double") * 64)).alias("total"))
        return flat

    add("agg_vector_sum", vectors, "SELECT label, CAST(pos - 1 AS INTEGER) AS pos, CAST(sum(CAST(floor(CAST(x AS DOUBLE) * 64) AS BIGINT)) AS BIGINT) AS total FROM (SELECT label, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings) GROUP BY 1, 2")


def _windows() -> None:
    def over(name, column, expr, sql, table="orders", keys=("o_orderkey",), partition="o_orderstatus", order="o_totalprice, o_orderkey"):
        add(name, lambda s, d: _t(s, d, table).select(*keys, F.expr(f"{expr} OVER (PARTITION BY {partition} ORDER BY {order}{sql[1] if len(sql) > 1 else ''})").alias(column)), f"SELECT {', '.join(keys)}, {sql[0]} OVER (PARTITION BY {partition} ORDER BY {order}{sql[1] if len(sql) > 1 else ''}) AS {column} FROM {table}")

    cast = lambda name, column, fn, kind, **k: add(name, lambda s, d: _t(s, d, k.get("table", "orders")).select(*k.get("keys", ("o_orderkey",)), F.expr(f"CAST({fn} OVER ({k['over']}) AS {kind})").alias(column)), f"SELECT {', '.join(k.get('keys', ('o_orderkey',)))}, CAST({fn} OVER ({k['over']}) AS {kind}) AS {column} FROM {k.get('table', 'orders')}")
    by = "PARTITION BY o_orderstatus ORDER BY o_totalprice, o_orderkey"
    pr = "PARTITION BY o_orderstatus ORDER BY o_orderpriority"
    cast("win_row_number", "k", "row_number()", "BIGINT", over=by)
    add("win_rank_dense", lambda s, d: _t(s, d, "orders").select("o_orderkey", F.expr(f"CAST(rank() OVER ({pr}) AS BIGINT)").alias("r"), F.expr(f"CAST(dense_rank() OVER ({pr}) AS BIGINT)").alias("dr")), f"SELECT o_orderkey, CAST(rank() OVER ({pr}) AS BIGINT) AS r, CAST(dense_rank() OVER ({pr}) AS BIGINT) AS dr FROM orders")
    add("win_percent_cume", lambda s, d: _round(_t(s, d, "orders").select("o_orderkey", F.expr(f"percent_rank() OVER ({by})").alias("p"), F.expr(f"cume_dist() OVER ({by})").alias("c")), "p", "c", digits=8), f"SELECT o_orderkey, round(percent_rank() OVER ({by}), 8) AS p, round(cume_dist() OVER ({by}), 8) AS c FROM orders")
    cast("win_ntile", "tile", "ntile(10)", "INTEGER", over=by)
    add("win_lag_lead", lambda s, d: _t(s, d, "orders").select("o_orderkey", F.expr(f"lag(o_orderkey, 1) OVER ({by})").alias("before"), F.expr(f"lead(o_orderkey, 2) OVER ({by})").alias("behind")), f"SELECT o_orderkey, lag(o_orderkey, 1) OVER ({by}) AS before, lead(o_orderkey, 2) OVER ({by}) AS behind FROM orders")
    full = by + " ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING"
    add("win_first_last_nth", lambda s, d: _t(s, d, "orders").select("o_orderkey", *[F.expr(f"{f} OVER ({full})").alias(a) for f, a in (("first_value(o_orderkey)", "f"), ("last_value(o_orderkey)", "l"), ("nth_value(o_orderkey, 3)", "n"))]), f"SELECT o_orderkey, first_value(o_orderkey) OVER ({full}) AS f, last_value(o_orderkey) OVER ({full}) AS l, nth_value(o_orderkey, 3) OVER ({full}) AS n FROM orders")
    cast("win_prefix_sum", "upto", "sum(o_custkey)", "BIGINT", over=by + " ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW")
    cast("win_rows_moving", "near", "sum(o_custkey)", "BIGINT", over=by + " ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING")
    cast("win_range_interval", "near", "count(*)", "BIGINT", table="events", keys=("event_id",), over="PARTITION BY event_type ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW")
    cast("win_following", "rest", "count(*)", "BIGINT", over=by + " ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING")
    _ = over


def _sorts_and_sets() -> None:
    a, b = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 5000", "SELECT s_nationkey AS k FROM supplier"
    one = lambda s, d: _t(s, d, "customer").where("c_acctbal > 5000").select(F.col("c_nationkey").alias("k"))
    two = lambda s, d: _t(s, d, "supplier").select(F.col("s_nationkey").alias("k"))
    for name, f, word in (("union_all", DataFrame.unionAll, "UNION ALL"), ("union_distinct", lambda x, y: x.union(y).distinct(), "UNION"), ("intersect", DataFrame.intersect, "INTERSECT"), ("intersect_all", DataFrame.intersectAll, "INTERSECT ALL"), ("except_distinct", DataFrame.subtract, "EXCEPT"), ("except_all", DataFrame.exceptAll, "EXCEPT ALL")):
        add(name, lambda s, d, f=f: f(one(s, d), two(s, d)), f"({a}) {word} ({b})")
    add("union_by_name", lambda s, d: _t(s, d, "region").select(F.col("r_name").alias("n"), "r_regionkey").unionByName(_t(s, d, "nation").select(F.col("n_name").alias("n")), allowMissingColumns=True), "SELECT r_name AS n, r_regionkey FROM region UNION ALL SELECT n_name, NULL FROM nation")
    add("dedup_subset", lambda s, d: _t(s, d, "documents").select("lang", "source").dropDuplicates(["lang", "source"]), "SELECT DISTINCT lang, source FROM documents")
    add("sort_multi_nulls", lambda s, d: _t(s, d, "nation").orderBy(F.nullif(F.col("n_regionkey"), F.lit(2)).asc_nulls_last(), F.desc("n_name")).limit(12).select("n_nationkey"), "SELECT n_nationkey FROM nation ORDER BY nullif(n_regionkey, 2) ASC NULLS LAST, n_name DESC LIMIT 12")
    add("sort_limit_offset", lambda s, d: _t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
    top = lambda: Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    add("topk_per_group", lambda s, d: _t(s, d, "orders").withColumn("k", F.row_number().over(top())).where("k <= 3").select("o_orderpriority", "o_orderkey", "k"), "SELECT o_orderpriority, o_orderkey, CAST(k AS INTEGER) AS k FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 3")


def _functions() -> None:
    from joinpoisson.functions.algebra import round_up_pow2, score_of, score_sql
    from joinpoisson.functions.rng import geometric, truncated_geometric

    add("fn_math", lambda s, d: _t(s, d, "part").selectExpr("p_partkey", "floor(p_retailprice) AS f", "ceil(p_retailprice) AS c", "round(sqrt(p_size), 6) AS r", "round(exp(p_size / 50.0D), 6) AS e", "greatest(p_size, 25) AS g", "pmod(p_size - 30, 7) AS m", "p_size div 7 AS q", "sign(p_size - 25.0D) AS s"), "SELECT p_partkey, CAST(floor(p_retailprice) AS BIGINT) AS f, CAST(ceil(p_retailprice) AS BIGINT) AS c, round(sqrt(p_size), 6) AS r, round(exp(p_size / 50.0e0), 6) AS e, greatest(p_size, 25) AS g, ((p_size - 30) % 7 + 7) % 7 AS m, CAST(p_size // 7 AS BIGINT) AS q, CAST(sign(p_size - 25.0e0) AS DOUBLE) AS s FROM part")
    steps = "(o_orderkey % 59 + 1)"
    add("fn_score_boundaries", lambda s, d: _t(s, d, "orders").select("o_orderkey", *[score_of(F.pow(F.lit(2.0), -F.expr(steps).cast("double")) * x, 50).alias(n) for n, x in (("at", 1.0), ("above", 1.0000000001), ("below", 0.9999999999))]), "SELECT o_orderkey, " + ", ".join(f"{score_sql(f'(pow(2.0e0, -{steps}) * {v}e0)', 50)} AS {n}" for n, v in (("at", "1.0"), ("above", "1.0000000001"), ("below", "0.9999999999"))) + " FROM orders")
    add("fn_pow2_round", lambda s, d: _t(s, d, "orders").select("o_orderkey", round_up_pow2(F.floor("o_totalprice")).alias("up")), "SELECT o_orderkey, CAST(CASE WHEN x <= 1 THEN x ELSE pow(2, ceil(log2(x))) END AS BIGINT) AS up FROM (SELECT o_orderkey, CAST(floor(o_totalprice) AS BIGINT) AS x FROM orders)")
    u = u01_sql("3", "'g'", "o_orderkey")
    add("fn_geometric", lambda s, d: _t(s, d, "orders").select("o_orderkey", geometric(u01(F.lit(3), F.lit("g"), F.col("o_orderkey")), F.lit(0.125), F.lit(1000)).alias("gap")), f"SELECT o_orderkey, CAST(floor(least(1000.0e0, ln({u}) / ln(0.875e0))) AS BIGINT) AS gap FROM orders")
    add("fn_truncated_geometric", lambda s, d: _t(s, d, "orders").select("o_orderkey", truncated_geometric(u01(F.lit(3), F.lit("g"), F.col("o_orderkey")), F.lit(0.125), F.lit(9)).alias("gap")), f"SELECT o_orderkey, CAST(least(floor(ln(1 - (1 - pow(0.875e0, 9)) * {u}) / ln(0.875e0)), 8) AS BIGINT) AS gap FROM orders")
    add("fn_string", lambda s, d: _t(s, d, "customer").selectExpr("c_custkey", "upper(c_mktsegment) AS u", "substr(c_name, 2, 4) AS p", "lpad(c_name, 25, '*') AS l", "reverse(c_name) AS r", "instr(c_name, '#') AS i", "translate(c_name, '0', 'o') AS t", "concat_ws('/', c_mktsegment, c_name) AS j"), "SELECT c_custkey, upper(c_mktsegment) AS u, substr(c_name, 2, 4) AS p, lpad(c_name, 25, '*') AS l, reverse(c_name) AS r, CAST(instr(c_name, '#') AS INTEGER) AS i, translate(c_name, '0', 'o') AS t, concat_ws('/', c_mktsegment, c_name) AS j FROM customer")
    add("fn_regex", lambda s, d: _t(s, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.regexp_replace("url", "[0-9]+", "#").alias("shape")), "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM pages")
    add("fn_hash_md5", lambda s, d: _t(s, d, "part").select("p_partkey", F.md5("p_name").alias("m"), F.sha2("p_name", 256).alias("h"), u01(F.lit(1), F.col("p_partkey")).alias("u")), f"SELECT p_partkey, md5(p_name) AS m, sha256(p_name) AS h, {u01_sql('1', 'p_partkey')} AS u FROM part")
    add("fn_date_trunc", lambda s, d: _t(s, d, "events").select("event_id", F.date_trunc("hour", "ts").alias("h"), F.dayofweek("ts").alias("dow"), F.year("ts").alias("y")), "SELECT event_id, date_trunc('hour', ts) AS h, CAST(dayofweek(ts) + 1 AS INTEGER) AS dow, CAST(year(ts) AS INTEGER) AS y FROM events")
    add("fn_date_arith", lambda s, d: _t(s, d, "orders").select("o_orderkey", F.date_add(F.to_date("o_orderdate"), 30).alias("due"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days")), "SELECT o_orderkey, CAST(o_orderdate AS DATE) + 30 AS due, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
    add("fn_interval", lambda s, d: _t(s, d, "events").select("event_id", (F.col("ts") + F.expr("INTERVAL 90 MINUTES")).alias("later"), F.unix_micros(F.col("ts").cast("timestamp")).alias("us")), "SELECT event_id, ts + INTERVAL 90 MINUTE AS later, CAST(epoch_us(ts) AS BIGINT) AS us FROM events")
    add("fn_array_hof", lambda s, d: _t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.aggregate(F.transform("embedding", lambda x: F.floor(x.cast("double") * 100)), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.exists("embedding", lambda x: x > 0.3).alias("big")), "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS pos, CAST(list_sum(list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 100) AS BIGINT))) AS BIGINT) AS total, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS big FROM embeddings")
    add("fn_array_sets", lambda s, d: _t(s, d, "part").select("p_partkey", F.size(F.array_distinct(F.split("p_type", ""))).alias("letters"), F.array_join(F.array_sort(F.split("p_type", " ")), " ").alias("words")), "SELECT p_partkey, CAST(len(list_distinct(string_split(p_type, ''))) AS INTEGER) AS letters, array_to_string(list_sort(string_split(p_type, ' ')), ' ') AS words FROM part")
    add("fn_explode", lambda s, d: _t(s, d, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "word")), "SELECT p_partkey, CAST(pos - 1 AS INTEGER) AS pos, word FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word, generate_subscripts(string_split(p_name, ' '), 1) AS pos FROM part)")

    def convolution(s, d):
        """Counts by score of two independent sets, as a sum of products: the fold of the score index on two vectors."""
        rows = _t(s, d, "lineitem").groupBy(score_of(F.expr(WEIGHTS["line"]), 12).alias("i")).agg(F.count("*").alias("a"))
        other = _t(s, d, "orders").groupBy(score_of(F.expr(WEIGHTS["ord"]), 12).alias("j")).agg(F.count("*").alias("b"))
        return rows.crossJoin(F.broadcast(other)).groupBy(F.least(F.col("i") + F.col("j"), F.lit(12)).alias("score")).agg(F.sum(F.col("a") * F.col("b")).alias("n"))

    add("fn_convolution", convolution, f"SELECT CAST(least(i + j, 12) AS INTEGER) AS score, CAST(sum(a * b) AS BIGINT) AS n FROM (SELECT {score_sql(WEIGHTS['line'], 12)} AS i, count(*) AS a FROM lineitem GROUP BY 1), (SELECT {score_sql(WEIGHTS['ord'], 12)} AS j, count(*) AS b FROM orders GROUP BY 1) GROUP BY 1")
    add("fn_map_build", lambda s, d: _t(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("n_name", "n_nationkey")))).alias("m")).select("n_regionkey", F.explode("m").alias("name", "key")), "SELECT n_regionkey, n_name AS name, n_nationkey AS key FROM nation")
    add("fn_map_zip", lambda s, d: _t(s, d, "region").select("r_regionkey", F.map_zip_with(F.create_map(F.lit("a"), F.col("r_regionkey")), F.create_map(F.lit("a"), F.lit(10)), lambda k, x, y: x + y)["a"].alias("v")), "SELECT r_regionkey, r_regionkey + 10 AS v FROM region")
    add("fn_json_extract", lambda s, d: _t(s, d, "events").select("event_id", F.size(F.json_object_keys("props")).alias("fields")), "SELECT event_id, CAST(len(json_keys(props)) AS INTEGER) AS fields FROM events")
    add("fn_struct", lambda s, d: _t(s, d, "nation").select(F.to_json(F.struct("n_nationkey", "n_name")).alias("j")), "SELECT CAST(to_json({'n_nationkey': n_nationkey, 'n_name': n_name}) AS VARCHAR) AS j FROM nation")
    add("fn_cast_try", lambda s, d: _t(s, d, "pages").select("page_id", F.expr("try_cast(regexp_extract(url, '([0-9]*)$', 1) AS INT)").alias("n"), F.expr("try_add(9223372036854775807, page_id)").alias("over")), "SELECT page_id, try_cast(regexp_extract(url, '([0-9]*)$', 1) AS INTEGER) AS n, CASE WHEN page_id > 0 THEN NULL ELSE 9223372036854775807 + page_id END AS over FROM pages")
    add("fn_decimal", lambda s, d: _t(s, d, "supplier").select("s_suppkey", (F.col("s_acctbal").cast("decimal(12,2)") * F.lit("1.10").cast("decimal(4,2)")).cast("decimal(20,4)").cast("string").alias("x")), "SELECT s_suppkey, CAST(CAST(CAST(s_acctbal AS DECIMAL(12,2)) * CAST(1.10 AS DECIMAL(4,2)) AS DECIMAL(20,4)) AS VARCHAR) AS x FROM supplier")

    def cosine(s, d):
        dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda a, v: a + v)
        v = _t(s, d, "embeddings").where("vec_id < 20")
        a, b = v.select(F.col("vec_id").alias("i"), F.col("embedding").alias("x")), v.select((F.col("vec_id") - 1).alias("i"), F.col("embedding").alias("y"))
        return a.join(b, "i").select("i", F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 6).alias("cosine"))

    add("fn_vector_cosine", cosine, "SELECT a.vec_id AS i, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1 WHERE a.vec_id < 19")


for _make in (_scans, _projections, _joins, _aggregates, _windows, _sorts_and_sets, _functions):
    _make()

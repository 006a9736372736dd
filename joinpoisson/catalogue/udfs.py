"""Queries of the user-defined function kinds."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType

from joinpoisson.catalogue.registry import add
from joinpoisson.functions.algebra import score_sql
from joinpoisson.functions.rng import u01_sql
from joinpoisson.operators.explicit import element_at_rank, placed
from joinpoisson.sources.surface import RankSource, register_sql

SIZE = "SELECT p_partkey, CAST(p_size * p_size + 1 AS BIGINT) AS y FROM part"


def _part(s, d) -> DataFrame:
    return s.read.parquet(f"{d}/part.parquet").select("p_partkey", F.col("p_size").cast("long").alias("x"))


def _ranks_sql(seed: int, purpose: str, n: int, p: float) -> str:
    u = u01_sql(str(seed), f"'{purpose}'", "turn")
    return f"WITH g AS (SELECT turn, CAST(floor(least({n}.0e0, ln({u}) / ln(1.0e0 - {p!r}))) AS BIGINT) AS gap FROM range(1, {n + 2}) r(turn)) SELECT CAST(place AS BIGINT) AS rank FROM (SELECT sum(gap + 1) OVER (ORDER BY turn) AS place FROM g) WHERE place <= {n}"


def _register() -> None:
    plain = F.udf(lambda x: x * x + 1, LongType())
    add("udf_python", lambda s, d: _part(s, d).select("p_partkey", plain("x").alias("y")), SIZE)

    @F.pandas_udf(LongType())
    def vector(x: pd.Series) -> pd.Series:
        return x * x + 1

    add("udf_pandas", lambda s, d: _part(s, d).select("p_partkey", vector("x").alias("y")), SIZE)

    @F.arrow_udf(LongType())
    def arrow(x: pa.Array) -> pa.Array:
        return pa.compute.add(pa.compute.multiply(x, x), 1)

    add("udf_arrow", lambda s, d: _part(s, d).select("p_partkey", arrow("x").alias("y")), SIZE)

    def batches(it: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in it:
            yield pd.DataFrame({"p_partkey": b["p_partkey"], "y": b["x"] * b["x"] + 1})

    add("udf_map_in_pandas", lambda s, d: _part(s, d).mapInPandas(batches, "p_partkey long, y long"), SIZE)

    def centred(b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"s_suppkey": b["s_suppkey"], "rank": b["s_acctbal"].rank(method="min").astype("int64")})

    add("udf_apply_in_pandas", lambda s, d: s.read.parquet(f"{d}/supplier.parquet").groupBy("s_nationkey").applyInPandas(centred, "s_suppkey long, rank long"), "SELECT s_suppkey, CAST(rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal) AS BIGINT) AS rank FROM supplier")

    def meet(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        key = a["k"].iloc[0] if len(a) else b["k"].iloc[0]
        return pd.DataFrame({"k": [key], "customers": [len(a)], "suppliers": [len(b)]})

    def cogroup(s, d):
        a = s.read.parquet(f"{d}/customer.parquet").select(F.col("c_nationkey").alias("k"), "c_custkey")
        b = s.read.parquet(f"{d}/supplier.parquet").select(F.col("s_nationkey").alias("k"), "s_suppkey")
        return a.groupBy("k").cogroup(b.groupBy("k")).applyInPandas(meet, "k int, customers long, suppliers long")

    add("udf_cogroup", cogroup, "SELECT n_nationkey AS k, CAST((SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS BIGINT) AS customers, CAST((SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS BIGINT) AS suppliers FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)")

    @F.pandas_udf(DoubleType())
    def total(x: pd.Series) -> float:
        return float(x.sum())

    add("udaf_pandas_sum", lambda s, d: s.read.parquet(f"{d}/orders.parquet").groupBy("o_orderstatus").agg(F.round(total(F.col("o_custkey").cast("double")), 2).alias("total")), "SELECT o_orderstatus, round(sum(CAST(o_custkey AS DOUBLE)), 2) AS total FROM orders GROUP BY 1")

    def ranks(s, d):
        register_sql(s)
        return s.sql("SELECT rank FROM geometric_ranks(5000, 0.01D, 11)")

    add("udtf_geometric_ranks", ranks, _ranks_sql(11, "udtf", 5000, 0.01))

    def lateral(s, d):
        register_sql(s)
        s.read.parquet(f"{d}/nation.parquet").createOrReplaceTempView("u_nation")
        return s.sql("SELECT n_nationkey, g.rank FROM u_nation, LATERAL geometric_ranks(200, 0.02D, n_nationkey) g")

    u = u01_sql("n_nationkey", "'udtf'", "turn")
    add("udtf_sql_lateral", lateral, f"WITH g AS (SELECT n_nationkey, turn, CAST(floor(least(200.0e0, ln({u}) / ln(0.98e0))) AS BIGINT) AS gap FROM nation, range(1, 202) r(turn)) SELECT n_nationkey, CAST(place AS BIGINT) AS rank FROM (SELECT n_nationkey, sum(gap + 1) OVER (PARTITION BY n_nationkey ORDER BY turn) AS place FROM g) WHERE place <= 200")

    def sql_function(s, d):
        s.sql("CREATE OR REPLACE TEMPORARY FUNCTION score_of_weight(w DOUBLE) RETURNS INT RETURN CAST(CASE WHEN w > 0 THEN least(40, floor(-log2(w))) ELSE 40 END AS INT)")
        s.read.parquet(f"{d}/lineitem.parquet").createOrReplaceTempView("u_line")
        return s.sql("SELECT score_of_weight(l_quantity / 50) AS score, count(*) AS n FROM u_line GROUP BY 1")

    add("sql_udf_score", sql_function, f"SELECT {score_sql('l_quantity / 50.0e0', 40)} AS score, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY 1")

    def source(s, d):
        """The orders at the ranks that the source draws of as many as there are."""
        s.dataSource.register(RankSource)
        rows = placed(s.read.parquet(f"{d}/orders.parquet").select("o_orderkey"), F.lit("all"), "o_orderkey")
        ranks = s.read.format("skip_ranks").options(n=str(rows.count()), p="0.01", seed="5", chunks="4").load()
        return element_at_rank(rows, ranks.withColumn("part", F.lit("all")).hint("merge")).select("rank", "o_orderkey")

    drawn = u01_sql("5", "'source'", "chunk", "turn")
    add("datasource_skip_ranks", source, f"""WITH e AS (SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey) AS rank, count(*) OVER () AS n FROM orders), s AS (SELECT max(n) AS n FROM e),
    c AS (SELECT n, chunk, n * chunk // 4 AS begun, n * (chunk + 1) // 4 AS ended FROM s, range(0, 4) r(chunk)), t AS (SELECT *, unnest(range(1, ended - begun + 2)) AS turn FROM c),
    g AS (SELECT *, CAST(floor(least(CAST(n AS DOUBLE), ln({drawn}) / ln(0.99e0))) AS BIGINT) AS gap FROM t), p AS (SELECT *, begun + sum(gap + 1) OVER (PARTITION BY chunk ORDER BY turn) AS place FROM g)
    SELECT e.rank, o_orderkey FROM e JOIN p ON e.rank = p.place WHERE place <= ended""")


_register()

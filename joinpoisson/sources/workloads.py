"""The workloads: joins over the given tables. Every relation is an SQL select that Spark and DuckDB both take."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joinpoisson.plans.relations import RelationSpec, assign_rid

#: The weight expressions, the same text for both engines.
WEIGHTS = {
    "cust": "greatest(0.0e0, (c_acctbal + 1000.0e0) / 11000.0e0)",
    "supp": "greatest(0.0e0, (s_acctbal + 1000.0e0) / 11000.0e0)",
    "ord": "least(1.0e0, o_totalprice / 500000.0e0)",
    "line": "l_quantity / 50.0e0",
    "disc": "l_discount",
    "part": "CAST(p_size AS DOUBLE) / 50.0e0",
    "nat": "CAST(n_nationkey + 1 AS DOUBLE) / 25.0e0",
    "reg": "CAST(r_regionkey + 1 AS DOUBLE) / 5.0e0",
    "evt": "least(1.0e0, value / 500.0e0)",
    "doc": "least(1.0e0, CAST(n_chars AS DOUBLE) / 40000.0e0)",
    "lab": "CASE WHEN toxic = 1 THEN 0.25e0 ELSE 0.5e0 + 0.5e0 * quality END",
    "vec": "CAST(vec_id % 64 + 1 AS DOUBLE) / 64.0e0",
    "turn": "1.0e0 / CAST(turn + 1 AS DOUBLE)",
}

#: Columns that order the tuples of tables without a key of one column.
LINE_ORDER = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
NUMBERED = {"lineitem": LINE_ORDER, "conversations": ["conv_id", "turn", "role", "text"]}


@dataclass(frozen=True)
class Rel:
    """attrs: attribute -> SQL expression; rid: expression, row number of the table where it has none."""

    name: str
    table: str
    attrs: dict[str, str]
    weight: str
    rid: str = "_rid"


@dataclass(frozen=True)
class Workload:
    name: str
    rels: tuple[Rel, ...]
    root: str | None = None
    what: str = ""

    def with_weights(self, change) -> Workload:
        """change: text of a weight -> new text."""
        return Workload(self.name, tuple(Rel(r.name, r.table, r.attrs, change(r.weight), r.rid) for r in self.rels), self.root, self.what)


def _w(name: str, *rels: Rel, root: str | None = None, what: str = "") -> Workload:
    return Workload(name, rels, root, what)


W = WEIGHTS
_CUST = Rel("customer", "customer", {"ck": "c_custkey"}, W["cust"], "c_custkey")
_CUST_N = Rel("customer", "customer", {"ck": "c_custkey", "nk": "c_nationkey"}, W["cust"], "c_custkey")
_ORD = Rel("orders", "orders", {"ok": "o_orderkey", "ck": "o_custkey"}, W["ord"], "o_orderkey")
_SUPP_N = Rel("supplier", "supplier", {"sk": "s_suppkey", "nk": "s_nationkey"}, W["supp"], "s_suppkey")
_NAT = Rel("nation", "nation", {"nk": "n_nationkey"}, W["nat"], "n_nationkey")
_PART = Rel("part", "part", {"pk": "p_partkey"}, W["part"], "p_partkey")


def _line(attrs: dict[str, str], weight: str = W["line"], name: str = "lineitem", rid: str = "line") -> Rel:
    return Rel(name, "lineitem", {rid: "_rid", **attrs}, weight)


WORKLOADS = {
    w.name: w
    for w in (
        _w("w01", _CUST, _ORD, _line({"ok": "l_orderkey"}), root="lineitem", what="path of three"),
        _w("w02", _line({"ok": "l_orderkey", "pk": "l_partkey", "sk": "l_suppkey"}), Rel("orders", "orders", {"ok": "o_orderkey"}, W["ord"], "o_orderkey"), _PART, Rel("supplier", "supplier", {"sk": "s_suppkey"}, W["supp"], "s_suppkey"), root="lineitem", what="star of four"),
        _w("w03", Rel("region", "region", {"rk": "r_regionkey"}, W["reg"], "r_regionkey"), Rel("nation", "nation", {"nk": "n_nationkey", "rk": "n_regionkey"}, W["nat"], "n_nationkey"), _CUST_N, _ORD, _line({"ok": "l_orderkey", "pk": "l_partkey"}), _PART, root="lineitem", what="snowflake of six"),
        _w("w04", _PART, _line({"pk": "l_partkey", "sk": "l_suppkey"}), _SUPP_N, _NAT, root="lineitem", what="screening: affinity, interaction, relevance, pathway"),
        _w("w05", _SUPP_N, _NAT, _CUST_N, root="nation", what="many to many over nation"),
        _w("w06", _line({"pk": "l_partkey"}, "l_quantity / 5000.0e0", "a", "ra"), _line({"pk": "l_partkey", "sk": "l_suppkey"}, "1.0e0 - l_tax", "b", "rb"), _line({"sk": "l_suppkey"}, "(1.0e0 - l_discount) / 100.0e0", "c", "rc"), root="b", what="explosive path"),
        _w("w07", _line({"sk": "l_suppkey"}, "l_quantity / 50000.0e0"), _SUPP_N, _NAT, _CUST_N, _ORD, root="nation", what="explosive over nation"),
        _w("w08", *[Rel(x, "events", {f"e{x}": "event_id", "u": "user_id"}, W["evt"], "event_id") for x in "ab"], root="a", what="self-join"),
        _w("w08k3", *[Rel(x, "events", {f"e{x}": "event_id", "u": "user_id"}, W["evt"], "event_id") for x in "abc"], root="a", what="self-join of three"),
        _w("w09", Rel("labels", "labels", {"d": "doc_id"}, W["lab"], "doc_id"), Rel("one", "documents", {"d": "doc_id", "src": "source"}, W["doc"], "doc_id"), Rel("two", "documents", {"d2": "doc_id", "src": "source"}, W["doc"], "doc_id"), root="one", what="documents of one source"),
        _w("w10", *[Rel(x, "embeddings", {f"v{x}": "vec_id", "lab": "label"}, W["vec"], "vec_id") for x in "ab"], root="a", what="vectors of one label"),
        _w("w11", *[Rel(x, "conversations", {f"t{x}": "_rid", "c": "conv_id"}, W["turn"]) for x in "ab"], root="a", what="turns of one conversation"),
        _w("w12", _CUST_N, _ORD, _line({"ok": "l_orderkey", "sk": "l_suppkey"}), _SUPP_N, what="cycle of four"),
        _w("w18", _CUST, _ORD, _line({"ok": "l_orderkey"}, W["disc"]), root="lineitem", what="weights with zeros"),
        _w("w20", Rel("region", "region", {"rk": "r_regionkey"}, W["reg"], "r_regionkey"), _PART, root="part", what="no shared attribute"),
        _w("w21", _line({}), what="one relation"),
    )
}

_numbered: dict[tuple[str, str, str], DataFrame] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, numbered where it has no key of one column; a numbering is written once per application."""
    if name not in NUMBERED:
        return spark.read.parquet(f"{sf_dir}/{name}.parquet")
    held = (spark.sparkContext.applicationId, sf_dir, name)
    if held not in _numbered:
        _numbered[held] = assign_rid(spark.read.parquet(f"{sf_dir}/{name}.parquet"), NUMBERED[name], "_rid")
    return _numbered[held]


def specs(spark: SparkSession, sf_dir: str, name: str | Workload) -> list[RelationSpec]:
    work = WORKLOADS[name] if isinstance(name, str) else name
    out = []
    for r in work.rels:
        columns = [F.expr(e).alias(a) for a, e in r.attrs.items()]
        df = table(spark, sf_dir, r.table).select(*columns, F.expr(r.rid).cast("long").alias("rid"), F.expr(r.weight).cast("double").alias("w"))
        out.append(RelationSpec(r.name, df, tuple(r.attrs)))
    return out


def relation_sql(r: Rel) -> str:
    """DuckDB's select of a relation: attrs, rid_<name>, w_<name>."""
    source = r.table
    if r.table in NUMBERED:
        source = f"(SELECT *, row_number() OVER (ORDER BY {', '.join(NUMBERED[r.table])}) AS _rid FROM {r.table})"
    columns = ", ".join(f"{e} AS {a}" for a, e in r.attrs.items())
    return f"SELECT {columns + ', ' if columns else ''}CAST({r.rid} AS BIGINT) AS rid_{r.name}, CAST({r.weight} AS DOUBLE) AS w_{r.name} FROM {source}"


def join_sql(name: str | Workload) -> str:
    """DuckDB's select of all join results: attributes, rid_*, w_*."""
    work = WORKLOADS[name] if isinstance(name, str) else name
    seen: dict[str, str] = {}
    parts, shown = [], []
    for i, r in enumerate(work.rels):
        on = [f"t{i}.{a} = {seen[a]}.{a}" for a in r.attrs if a in seen]
        parts.append(f"({relation_sql(r)}) t{i}" if not i else f"JOIN ({relation_sql(r)}) t{i} ON {' AND '.join(on) or 'true'}")
        for a in r.attrs:
            if a not in seen:
                seen[a] = f"t{i}"
                shown.append(f"t{i}.{a}")
        shown += [f"t{i}.rid_{r.name}", f"t{i}.w_{r.name}"]
    return f"SELECT {', '.join(shown)} FROM {' '.join(parts)}"

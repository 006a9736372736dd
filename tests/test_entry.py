"""The driver's contract, and the plans one would want."""

import re

from joinpoisson.operators.index import ScoreIndex
from joinpoisson.operators.sampler import sample_join
from joinpoisson.sources.workloads import specs


def test_names_and_entry(spark):
    import __spark_entry__

    queries, sql = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 150
    assert 550 < __spark_entry__.entry(spark).count() < 900


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, small):
    rows = specs(spark, small, "w01")
    text = plan(sample_join(rows, seed=1, cap=16, root="lineitem", bulk=True))
    assert "CartesianProduct" not in text and "SinglePartition" not in text and "BroadcastNestedLoopJoin" not in text
    reads = re.findall(r"ReadSchema: struct<([^>]*)>", plan(ScoreIndex.build(rows, cap=16, root="lineitem", store=False).buckets))
    assert reads and all("c_name" not in r and "o_orderpriority" not in r for r in reads)


def test_names_need_no_session():
    import subprocess
    import sys
    from pathlib import Path

    top = Path(__file__).resolve().parents[1]
    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"], cwd=top, capture_output=True, text=True, timeout=120)
    assert said.returncode == 0 and int(said.stdout.split()[0]) > 150, said.stderr[-500:]


def test_functions_read_given_tables(spark, small):
    """Functions on made-up numbers would read no table; each reads one and equals its SQL there."""
    import duckdb

    import __spark_entry__

    queries, sql = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    base = duckdb.connect()
    for t in ("orders", "lineitem"):
        base.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    for name in ("fn_convolution", "fn_geometric", "fn_truncated_geometric", "fn_pow2_round", "fn_score_boundaries", "datasource_skip_ranks"):
        df = queries[name](spark, small)
        assert "orders" in sql[name] and "ReadSchema" in plan(df), name
        assert sorted(map(tuple, df.collect())) == sorted(base.execute(sql[name]).fetchall()), name


def test_a_finished_stream_leaves_nothing_on_the_driver(spark, small):
    """The result of a complete stream is files, of the last batch only; before, a table in the driver's memory."""
    from joinpoisson.streaming import windows

    events = spark.read.parquet(f"{small}/events.parquet")
    stream = windows.read(spark, windows.slices(spark, events, 3, "event_id"), events.schema)
    out = windows.finish(windows.sessions(stream), "complete")
    assert out.columns == ["user_id", "start", "n"] and out.agg({"n": "sum"}).first()[0] == events.count()
    files = {f.rsplit("/", 2)[1] for f in out.inputFiles()}
    assert files == {"batch=2"}

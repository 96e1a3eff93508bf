"""The registry is complete, and a few queries agree with DuckDB on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
CHECKED = ["graph_tri_edges", "common_neighbours_wedge", "hybrid_accept", "op_join_asof", "op_win_range_frame", "partition_edge_balanced", "linkpred_auc_degree", "stream_tumbling", "worked_example_8nodes"]


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 200


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_oracle(spark, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    frame = entry.queries()[name](spark, SF)
    columns = sorted(frame.columns)
    run = con.execute(entry.oracle_sql()[name])
    named = [c[0] for c in run.description]
    want = [tuple(r[named.index(c)] for c in columns) for r in run.fetchall()]
    tidy = lambda rows: sorted((tuple(round(v, 9) + 0.0 if isinstance(v, float) else str(v) for v in r) for r in rows), key=repr)
    assert tidy(tuple(r) for r in frame.select(*columns).collect()) == tidy(want)


def test_entry_runs(spark):
    assert entry.entry(spark).count() > 0


def test_models_and_the_python_source_read_a_table(spark, tmp_path):
    """Rows follow the given tables: half of the users, half of the walks; every order is read, from a folder too."""
    events = spark.read.parquet(f"{SF}/events.parquet").where("user_id % 2 = 0")
    events.write.parquet(str(tmp_path / "events.parquet"))
    spark.read.parquet(f"{SF}/orders.parquet").repartition(3).write.parquet(str(tmp_path / "orders.parquet"))
    run = lambda name, d: sorted(map(tuple, entry.queries()[name](spark, d).collect()))
    for name in ("cost_walk_model", "cost_train_model", "message_size_table"):
        assert run(name, SF) != run(name, str(tmp_path)), name
    assert run("cost_train_model", str(tmp_path)) == [(800.0 * 60 * events.select("user_id").distinct().count(), 60.0 * events.count())]
    assert run("io_python_source", SF) == run("io_python_source", str(tmp_path)) == sorted(map(tuple, spark.read.parquet(f"{SF}/orders.parquet").select("o_custkey", "o_orderkey").collect()))

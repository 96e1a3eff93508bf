"""Queries of the user-facing functions and sources: scalar, aggregate, table and SQL functions, and the Python source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.tables import register
from ..sources.pairs import TablePairsSource
from ..sources.tables import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, oracle: str):
    def put(query):
        QUERIES[name], ORACLES[name] = query, oracle
        return query

    return put


def overlaps(spark: SparkSession, d: str) -> DataFrame:
    """(s, shared): parts that a supplier shares with the next one, by the galloping Arrow function."""
    from ..functions.arrow import gallop_overlap

    held = table(spark, d, "lineitem").groupBy("l_suppkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("parts"))
    both = held.alias("x").join(held.alias("y"), F.expr("y.l_suppkey = x.l_suppkey + 1"))
    return both.select(F.col("x.l_suppkey").alias("s"), gallop_overlap(F.col("x.parts"), F.col("y.parts")).alias("shared"))


add("op_udf_scalar", "WITH h AS (SELECT l_suppkey AS s, list_distinct(list(l_partkey)) AS parts FROM lineitem GROUP BY 1) SELECT x.s, len(list_intersect(x.parts, y.parts))::INTEGER AS shared FROM h x JOIN h y ON y.s = x.s + 1")(overlaps)


def mean_norms(spark: SparkSession, d: str) -> DataFrame:
    """(label, norm): the length of each class's mean vector, by the grouped Arrow function."""
    from ..functions.arrow import vector_mean_norm

    v = table(spark, d, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v"))
    return v.groupBy("label").agg(F.round(vector_mean_norm("v"), 6).alias("norm"))


add("op_udf_agg", "WITH m AS (SELECT label, i, avg(embedding[i]::DOUBLE) AS x FROM embeddings, range(1, 65) t(i) GROUP BY 1, 2) SELECT label, round(sqrt(sum(x * x)), 6) AS norm FROM m GROUP BY label")(mean_norms)


def windows(spark: SparkSession, d: str) -> DataFrame:
    """(user_id, target, context, n): window pairs of users' events, by the table function."""
    register(spark)
    events = table(spark, d, "events").groupBy("user_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda e: e["event_type"]).alias("path"))
    events.createOrReplaceTempView("walk_paths")
    return spark.sql("SELECT p.user_id, w.target, w.context, count(*) AS n FROM walk_paths p, LATERAL walk_windows(p.path, 2) w GROUP BY 1, 2, 3")


add("op_udtf", "WITH s AS (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events) SELECT x.user_id, x.event_type AS target, y.event_type AS context, count(*) AS n FROM s x JOIN s y ON y.user_id = x.user_id AND y.i BETWEEN x.i - 2 AND x.i + 2 AND y.i <> x.i GROUP BY 1, 2, 3")(windows)


def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    """(s_suppkey, entropy, alpha): the SQL functions over supplier columns."""
    register(spark)
    table(spark, d, "supplier").createOrReplaceTempView("function_rows")
    return spark.sql("SELECT s_suppkey, round(entropy_step(1.5D, 8D, CAST(s_nationkey AS DOUBLE)), 6) AS entropy, round(hybrid_alpha(s_nationkey + 2D, 5D, CAST(s_nationkey % 4 AS DOUBLE)), 6) AS alpha FROM function_rows")


add(
    "op_sql_udf",
    "SELECT s_suppkey, round((8 * 1.5::DOUBLE + CASE WHEN s_nationkey > 0 THEN s_nationkey * log2(s_nationkey) ELSE 0 END - (s_nationkey + 1) * log2(s_nationkey + 1) + 9 * log2(9) - 8 * log2(8)) / 9, 6) AS entropy, round(greatest((s_nationkey + 2) / 5.0::DOUBLE, 5.0::DOUBLE / (s_nationkey + 2)) / greatest(s_nationkey + 2 - s_nationkey % 4, 1), 6) AS alpha FROM supplier",
)(sql_functions)


def python_source(spark: SparkSession, d: str) -> DataFrame:
    """(a, b) raw pairs of customers and their orders, read through the Python data source, a partition a row group."""
    spark.dataSource.register(TablePairsSource)
    return spark.read.format("table_pairs").option("a", "o_custkey").option("b", "o_orderkey").load(f"{d}/orders.parquet")


add("io_python_source", "SELECT o_custkey::BIGINT AS a, o_orderkey::BIGINT AS b FROM orders")(python_source)

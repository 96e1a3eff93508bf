"""The given tables, and SQL over them as named frames."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """Runs ``text`` with the given tables, and further frames, as temporary views.

    A query is analysed at once, so views that later calls replace don't reach it.
    """
    for name in TABLES:
        if name not in frames and re.search(rf"\b{name}\b", text):
            table(spark, sf_dir, name).createOrReplaceTempView(name)
    for name, frame in frames.items():
        frame.createOrReplaceTempView(name)
    return spark.sql(text)

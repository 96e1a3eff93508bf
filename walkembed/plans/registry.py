"""Registry of the library's queries and of the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import walks as W
from . import experiment_queries, function_queries, graph_queries, learn_queries, relational

_SOURCES = (graph_queries, learn_queries, experiment_queries, function_queries, relational)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(walk_id, length, entropy): one round of information-stopped hybrid walks over the purchase graph."""
    from ..operators.measures import walk_entropy

    steps = graph_queries.burst(spark, sf_dir, "tri", W.Kernel("hybrid"), W.Stop.calibrated(), rng="native")
    return walk_entropy(steps).select("walk_id", "length", F.round("entropy", 6).alias("entropy"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: query for source in _SOURCES for name, query in source.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {name: text for source in _SOURCES for name, text in source.ORACLES.items()}

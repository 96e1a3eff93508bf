"""Table and SQL functions that users of the methods call from SQL."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class WalkWindows:
    """walk_windows(path, width): the (pos, target, context) pairs of a walk's windows."""

    def eval(self, path: list, width: int) -> Iterator[tuple]:
        for i, target in enumerate(path or ()):
            for k in range(max(0, i - width), min(len(path), i + width + 1)):
                if k != i:
                    yield i + 1, target, path[k]


#: fixed values: the one-step entropy update and the transition weight, as SQL text
ENTROPY_STEP = "(l * h + IF(n > 0, n * log2(n), 0D) - (n + 1) * log2(n + 1) + (l + 1) * log2(l + 1) - IF(l > 0, l * log2(l), 0D)) / (l + 1)"
HYBRID_ALPHA = "greatest(du / dv, dv / du) / greatest(du - cm, 1)"


def register(spark: SparkSession) -> None:
    """Makes ``walk_windows``, ``entropy_step`` and ``hybrid_alpha`` known to the session's SQL."""
    spark.udtf.register("walk_windows", udtf(WalkWindows, returnType="pos: int, target: string, context: string"))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION entropy_step(h DOUBLE, l DOUBLE, n DOUBLE) RETURNS DOUBLE RETURN {ENTROPY_STEP}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION hybrid_alpha(du DOUBLE, dv DOUBLE, cm DOUBLE) RETURNS DOUBLE RETURN {HYBRID_ALPHA}")

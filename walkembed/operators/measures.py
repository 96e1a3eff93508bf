"""Information measures of walks: entropy, its one-step update, and its correlation with length.

Entropies are in bits.  The update keeps f(x) = x log2 x with f(0) = 0, so it never
forms powers of the length.  The mean of the products of two series is updated
like any other mean; the printed recurrence, which multiplies the means, is kept
as ``as_printed`` to show that it makes the correlation vanish.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def xlog2(x: Column) -> Column:
    return F.when(x > 0, x * F.log2(x)).otherwise(F.lit(0.0))


def entropy_step(h: Column, length: Column, n: Column) -> Column:
    """Entropy after appending a node seen ``n`` times among ``length`` nodes of entropy ``h``."""
    return (length * h + xlog2(n.cast("double")) - xlog2(n + F.lit(1.0)) + xlog2(length + F.lit(1.0)) - xlog2(length.cast("double"))) / (length + 1)


def f_many(x: np.ndarray) -> np.ndarray:
    x = np.asarray(x, dtype=np.float64)
    return np.where(x > 0, x * np.log2(np.maximum(x, 1)), 0.0)


def entropy_step_many(h: np.ndarray, length: np.ndarray, n: np.ndarray) -> np.ndarray:
    return (length * h + f_many(n) - f_many(n + 1) + f_many(length + 1) - f_many(length)) / (length + 1)


def r_squared_many(mh: np.ndarray, ml: np.ndarray, mhl: np.ndarray, mh2: np.ndarray, ml2: np.ndarray) -> np.ndarray:
    """R^2 from running means; 0 where a series is constant."""
    vh, vl, cov = mh2 - mh * mh, ml2 - ml * ml, mhl - mh * ml
    ok = (vh > 1e-12) & (vl > 1e-12)
    return np.where(ok, cov * cov / np.where(ok, vh * vl, 1.0), 0.0)


def path_entropy(path: list[int]) -> float:
    counts: dict[int, int] = {}
    for v in path:
        counts[v] = counts.get(v, 0) + 1
    return -sum(n / len(path) * math.log2(n / len(path)) for n in counts.values()) + 0.0


def walk_entropy(steps: DataFrame) -> DataFrame:
    """(round, walk_id, length, entropy) of whole walks."""
    counts = steps.groupBy("round", "walk_id", "node").agg(F.count("*").alias("n"))
    return counts.groupBy("round", "walk_id").agg(F.sum("n").alias("length"), (F.log2(F.sum("n")) - F.sum(xlog2(F.col("n").cast("double"))) / F.sum("n")).alias("entropy"))


def prefix_measures(steps: DataFrame) -> DataFrame:
    """steps + (entropy, r2, r2_as_printed) of every prefix, by windows alone.

    The number of earlier visits of a step's node gives the change of
    sum n log2 n; its running sum gives every prefix's entropy, and running means
    of entropy and length give the correlation.
    """
    order = Window.partitionBy("round", "walk_id").orderBy("step")
    running = order.rowsBetween(Window.unboundedPreceding, 0)
    seen = F.row_number().over(Window.partitionBy("round", "walk_id", "node").orderBy("step"))
    length = F.row_number().over(order).cast("double")
    s = steps.withColumn("seen", seen.cast("double")).withColumn("L", length)
    s = s.withColumn("mass", F.sum(xlog2(F.col("seen")) - xlog2(F.col("seen") - 1)).over(running))
    s = s.withColumn("H", F.log2("L") - F.col("mass") / F.col("L"))
    mean = lambda c: F.avg(c).over(running)
    s = s.select("*", mean("H").alias("mh"), mean("L").alias("ml"), mean(F.col("H") * F.col("L")).alias("mhl"), mean(F.col("H") * F.col("H")).alias("mh2"), mean(F.col("L") * F.col("L")).alias("ml2"))
    vh, vl = F.col("mh2") - F.col("mh") * F.col("mh"), F.col("ml2") - F.col("ml") * F.col("ml")
    cov = F.col("mhl") - F.col("mh") * F.col("ml")
    printed = F.col("mh") * F.col("ml") - F.col("mh") * F.col("ml")
    square = lambda c: F.when((vh > 1e-12) & (vl > 1e-12), c * c / (vh * vl)).otherwise(F.lit(0.0))
    return s.select("round", "walk_id", "step", "node", F.col("H").alias("entropy"), square(cov).alias("r2"), square(printed).alias("r2_as_printed"))


PREFIX_SQL = """
seen AS (
  SELECT *, row_number() OVER (PARTITION BY round, walk_id, node ORDER BY step)::DOUBLE AS k, row_number() OVER (PARTITION BY round, walk_id ORDER BY step)::DOUBLE AS L FROM steps
), massed AS (
  SELECT *, sum(CASE WHEN k > 1 THEN k * log2(k) - (k - 1) * log2(k - 1) ELSE 0 END) OVER (PARTITION BY round, walk_id ORDER BY step) AS mass FROM seen
), bits AS (SELECT *, log2(L) - mass / L AS H FROM massed
), means AS (
  SELECT *, avg(H) OVER w AS mh, avg(L) OVER w AS ml, avg(H * L) OVER w AS mhl, avg(H * H) OVER w AS mh2, avg(L * L) OVER w AS ml2 FROM bits
  WINDOW w AS (PARTITION BY round, walk_id ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)
), measured AS (
  SELECT round, walk_id, step, node, H AS entropy,
    CASE WHEN mh2 - mh*mh > 1e-12 AND ml2 - ml*ml > 1e-12 THEN (mhl - mh*ml) * (mhl - mh*ml) / ((mh2 - mh*mh) * (ml2 - ml*ml)) ELSE 0 END AS r2 FROM means
)"""


def corpus_divergence(degree: DataFrame, steps: DataFrame) -> DataFrame:
    """(round, divergence, change): relative entropy of degrees from the corpus of all rounds so far."""
    counts = steps.groupBy("round", "node").agg(F.count("*").alias("n"))
    rounds = counts.select("round").distinct()
    total = degree.agg(F.sum("deg").alias("all_deg"))
    upto = rounds.alias("r").join(counts.alias("c"), F.col("c.round") <= F.col("r.round")).groupBy(F.col("r.round").alias("round"), "node").agg(F.sum("n").alias("ocn"))
    sums = upto.groupBy("round").agg(F.sum("ocn").alias("all_ocn"))
    terms = upto.join(sums, "round").join(degree.where("deg > 0"), "node").crossJoin(total)
    p = F.col("deg") / F.col("all_deg")
    d = terms.groupBy("round").agg(F.sum(p * F.log2(p * F.col("all_ocn") / F.col("ocn"))).alias("divergence"))
    return d.withColumn("change", F.abs(F.col("divergence") - F.lag("divergence").over(Window.orderBy("round"))))

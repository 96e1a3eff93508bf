"""Splits, scores and metrics of link prediction and node classification; closed-form costs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import draw_column


def balanced_negatives(held: DataFrame, edges: DataFrame, nodes: DataFrame, seed: int = 42) -> DataFrame:
    """(src, dst): as many non-edges as ``held`` has edges, or all that four draws an edge give if they are fewer."""
    wanted = held.count()
    drawn = negative_edges(edges, nodes, 4, seed)
    return drawn.orderBy(draw_column(seed, F.col("src"), F.col("dst")), "src", "dst").limit(wanted)


def score_pairs(held: DataFrame, negatives: DataFrame, vectors: DataFrame) -> DataFrame:
    """(score, y): inner products of the ends' vectors (node, phi)."""
    pairs = held.select("src", "dst", F.lit(1).alias("y")).unionByName(negatives.select("src", "dst", F.lit(0).alias("y")))
    met = pairs.join(vectors.select(F.col("node").alias("src"), F.col("phi").alias("a")), "src").join(vectors.select(F.col("node").alias("dst"), F.col("phi").alias("b")), "dst")
    return met.select(F.aggregate(F.zip_with("a", "b", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x).alias("score"), "y")


def split_edges(edges: DataFrame, share: float = 0.5, seed: int = 42) -> DataFrame:
    """edges + held (boolean): a hash of each edge decides."""
    return edges.withColumn("held", draw_column(seed, F.col("src"), F.col("dst")) < F.lit(int(share * (1 << 32))))


def negative_edges(edges: DataFrame, nodes: DataFrame, draws: int = 4, seed: int = 42) -> DataFrame:
    """(src, dst) pairs that are no edges: hash draws for each held edge, less the edges and repeats.

    Nodes are numbered in the order of their ids, inside blocks of ids and then
    over the blocks, so no task sees all nodes and a draw is an equi-join.
    """
    n = nodes.count()
    blocked = nodes.select("node", F.floor(F.col("node") / 65_536).alias("block"))
    sizes = blocked.groupBy("block").agg(F.count("*").alias("s"))
    before = sizes.select("block", (F.sum("s").over(Window.orderBy("block")) - F.col("s")).alias("before"))
    inside = F.row_number().over(Window.partitionBy("block").orderBy("node")) - 1
    numbered = blocked.withColumn("inside", inside).join(before, "block").select("node", (F.col("before") + F.col("inside")).cast("long").alias("i"))
    tried = edges.select("src", "dst", F.explode(F.sequence(F.lit(1), F.lit(draws))).alias("k"))
    at = lambda salt: F.shiftright(draw_column(seed, F.col("src"), F.col("dst"), F.col("k"), F.lit(salt)) * F.lit(n), 32)
    ends = tried.select(at(1).alias("i"), at(2).alias("j"))
    named = ends.join(numbered.select("i", F.col("node").alias("a")), "i").join(numbered.select(F.col("i").alias("j"), F.col("node").alias("b")), "j")
    pairs = named.where("a <> b").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()
    return pairs.join(edges.select("src", "dst"), ["src", "dst"], "left_anti")


def auc(scored: DataFrame) -> DataFrame:
    """One row (n_pos, n_neg, auc) from (score, y), ties at mid-ranks.

    Scores are counted by value first, so ranks come from the distinct scores.
    """
    by = scored.groupBy("score").agg(F.sum("y").alias("pos"), F.sum(1 - F.col("y")).alias("neg"))
    ranked = by.withColumn("below", F.coalesce(F.sum("neg").over(Window.orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    won = F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2.0))
    return ranked.agg(F.sum("pos").alias("n_pos"), F.sum("neg").alias("n_neg"), won.alias("won")).select("n_pos", "n_neg", F.try_divide("won", F.col("n_pos") * F.col("n_neg").cast("double")).alias("auc"))


def f1_scores(predictions: DataFrame) -> DataFrame:
    """One row (micro_f1, macro_f1) from (label, y_true, y_pred); a label without any counts 0."""
    per = predictions.groupBy("label").agg(F.sum(F.col("y_true") * F.col("y_pred")).alias("tp"), F.sum((1 - F.col("y_true")) * F.col("y_pred")).alias("fp"), F.sum(F.col("y_true") * (1 - F.col("y_pred"))).alias("fn"))
    f1 = F.coalesce(F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0))
    return per.withColumn("f1", f1).agg(F.try_divide(2.0 * F.sum("tp"), 2 * F.sum("tp") + F.sum("fp") + F.sum("fn")).alias("micro_f1"), F.avg("f1").alias("macro_f1"))


def walk_cost(kind: str, rounds: float, length: float, nodes: float, processors: float, messages: float, bandwidth: float) -> float:
    """Computation over processors plus messages over bandwidth (bytes)."""
    work = rounds * nodes * (length**2 if kind == "fullpath" else length) / processors
    return work + messages * (24 + 8 * length if kind == "fullpath" else 80) / bandwidth


def train_cost(corpus: float, window: float, negatives: float, unit: float = 1.0) -> float:
    return corpus * window * (negatives + 1) * unit


def sync_cost(mode: str, nodes: float, dims: float, machines: float, blocks: float = 0.0, n_matrices: int = 2) -> float:
    return (nodes if mode == "full" else blocks) * dims * machines * n_matrices


def partition_cost(first: float, second: float, longest: float) -> float:
    """Galloping intersections: the smaller side times the logarithm of the larger."""
    return (first + second) * math.log2(max(longest, 2))


def message_bytes(measure: str, length: int) -> int:
    return 80 if measure == "incremental" else 24 + 8 * length

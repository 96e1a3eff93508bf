"""End-to-end embedding pipelines, phase times, link prediction and sweeps."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.parallel import together
from ..operators import baselines as B
from ..operators import evaluate as E
from ..operators import graph as G
from ..operators import learner as L
from ..operators import partition as P
from ..operators import walks as W


@dataclass
class Phases:
    """Wall seconds of each phase; end to end is their sum."""

    seconds: dict[str, float] = field(default_factory=dict)

    def time(self, name: str, frame: DataFrame) -> DataFrame:
        began = time.time()
        done = frame.checkpoint()
        self.seconds[name] = self.seconds.get(name, 0.0) + time.time() - began
        return done

    @property
    def end_to_end(self) -> float:
        return sum(self.seconds.values())


#: profile -> (partitioner, kernel, stop, fixed rounds, learner mode, synchronisation, measure)
PROFILES = {
    "info": ("proximity", W.Kernel("hybrid"), W.Stop.calibrated(), None, "multi_window", "hotness", "incremental"),
    "fullpath": ("edge_balanced", W.Kernel("hybrid", "accept"), W.Stop.calibrated(), None, "window_shared", "full", "fullpath"),
    "routine": ("edge_balanced", W.Kernel("biased2", p=0.5, q=2.0), W.Stop.fixed(80), 10, "window_shared", "full", "incremental"),
}


def corpus(edges: DataFrame, profile: str = "info", m: int = 2, max_rounds: int = 10, phases: Phases | None = None, **swap) -> tuple[DataFrame, DataFrame]:
    """(steps, assign) of a profile; ``swap`` replaces single components for ablations."""
    phases = phases or Phases()
    placing, kernel, stop, rounds, _, _, measure = PROFILES[profile]
    placing, kernel, stop = swap.get("placing", placing), swap.get("kernel", kernel), swap.get("stop", stop)
    edges = phases.time("prepare", G.common_neighbours(edges))
    if placing == "proximity":
        assign = phases.time("partition", P.proximity_partition(edges, m, order="bfs_degree", segments=max(1, m // 2)))
    elif placing == "edge_balanced":
        assign = phases.time("partition", P.edge_balanced_partition(edges, m))
    else:
        assign = phases.time("partition", P.hash_partition(G.both_directions(edges).select(F.col("u").alias("node")).distinct(), m))
    rounds = swap.get("rounds", rounds)
    began = time.time()
    steps, _ = W.sample_corpus(edges, assign, kernel, stop, max_rounds=min(max_rounds, rounds or max_rounds), fixed_rounds=None if rounds is None else min(rounds, max_rounds), measure=swap.get("measure", measure), wave=5 if rounds is None else min(rounds, 10))
    phases.seconds["walk"] = time.time() - began
    return steps.select("round", "walk_id", "step", "node"), assign


def embed(edges: DataFrame, profile: str = "info", dims: int = 64, m: int = 2, max_rounds: int = 10, window: int = 10, n_windows: int = 2, phases: Phases | None = None, **swap) -> DataFrame:
    """(node, rank, phi, n_updates): partition, sample, train."""
    phases = phases or Phases()
    steps, _ = corpus(edges, profile, m, max_rounds, phases, **swap)
    mode, sync = swap.get("mode", PROFILES[profile][4]), swap.get("sync", PROFILES[profile][5])
    return phases.time("train", L.train(steps, mode, dims=dims, window=window, shards=m, n_windows=n_windows, sync=sync, epochs=swap.get("epochs", 1), rate=swap.get("rate", 0.05)))


def typed_edges(edges: DataFrame) -> DataFrame:
    """(src, dst, rel): the relation is the pair of node kinds."""
    kind = lambda c: F.floor(F.col(c) / 10**12).cast("string")
    return edges.select("src", "dst", F.concat_ws("-", kind("src"), kind("dst")).alias("rel"))


def link_prediction(edges: DataFrame, profile: str = "info", dims: int = 64, max_rounds: int = 5, seed: int = 42, **swap) -> DataFrame:
    """(profile, n_pos, n_neg, auc): half of the edges held out, scored against as many non-edges by inner products.

    Profiles are those of ``PROFILES`` and the baselines ``relational`` and ``gnn``.
    """
    edges = edges.checkpoint()  # the split and the negatives read it
    split = E.split_edges(edges, 0.5, seed).checkpoint()
    kept, held = (split.where(c).select("src", "dst", "w") for c in ("not held", "held"))
    if profile == "relational":
        vectors = B.relational_embed(typed_edges(kept), dims, epochs=10, seed=seed)
    elif profile == "gnn":
        vectors = B.train_gnn(kept, dims, seed=seed)
    else:
        vectors = embed(kept, profile, dims, max_rounds=max_rounds, **swap).select("node", "phi")
    vectors = vectors.checkpoint()
    # ends without a kept edge have no vector: pairs are drawn among the others
    known = held.join(vectors.select(F.col("node").alias("src")), "src", "left_semi").join(vectors.select(F.col("node").alias("dst")), "dst", "left_semi")
    negatives = E.balanced_negatives(known, edges, vectors.select("node"), seed)
    return E.auc(E.score_pairs(known, negatives, vectors)).select(F.lit(profile).alias("profile"), "n_pos", "n_neg", "auc")


def repeated(edges: DataFrame, profile: str, trials: int = 3, **settings) -> DataFrame:
    """(profile, trials, mean_auc, sd_auc) over splits with seeds of their own."""
    rows = together(lambda t: link_prediction(edges, profile, seed=42 + t, **settings).first(), range(trials))
    frame = edges.sparkSession.createDataFrame([(profile, float(r["auc"])) for r in rows], "profile string, auc double")
    return frame.groupBy("profile").agg(F.count("*").alias("trials"), F.avg("auc").alias("mean_auc"), F.stddev_pop("auc").alias("sd_auc"))


def sweep_stop(edges: DataFrame, values: tuple[float, ...] = (0.995, 0.9, 0.85, 0.7, 0.5), m: int = 2) -> list[tuple[float, float]]:
    """(mu, mean length): smaller thresholds give longer walks."""
    nodes = G.both_directions(edges).select(F.col("u").alias("node")).distinct()
    table = W.kernel_edges(edges, W.Kernel("hybrid")).checkpoint()
    out = []
    for mu in values:
        steps = W.burst_round(table, P.hash_partition(nodes, m), nodes, W.Kernel("hybrid"), W.Stop("entropy_r2", mu))
        out.append((mu, W.walk_profile(steps).first()["mean_length"]))
    return out

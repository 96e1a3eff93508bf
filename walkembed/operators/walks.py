"""Random walks: kernels, stopping rules and engines.

First-order kernels are integer weights per edge (uniform, weighted, hybrid, any
plug-in), drawn by binary search in a node's running sums; ``accept`` kernels try
uniform candidates and stay on a rejection.  ``biased2`` weighs candidates by the
node before.

Engines
-------
``step``   one superstep a hop in column expressions: walkers join the adjacency
           on their node.  Only walkers are exchanged if the adjacency is bucketed.
``burst``  walkers go to the part of their node and advance there, all of a part
           in lockstep, until they leave or stop; supersteps are bounded by part
           crossings, not by length.  Counts of a walk stay where they were made;
           a walker travels as ten fields.  ``fullpath_round`` is the baseline
           whose walkers carry their paths instead.
``shared`` a graph that fits a task reaches every task, which walks its own sources
           from end to end: the same hops without supersteps.
``local``  one part on the driver: the sequential oracle of the others.

Draws depend on (seed, round, walk, step, trial) alone: engines agree hop by hop
and a replayed task repeats its rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property, partial, reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.rng import draw_column, draw_many
from . import graph as G
from .measures import entropy_step_many, f_many, r_squared_many

MAX_TRIALS = 1000
CANDIDATES = 1_000_000  # of second-order draws at a time
SHARED_ROWS = 4_000_000  # edges in both directions that reach every task: 32 bytes each
SHARED_HOPS = 1 << 18  # that a task holds before it returns them
SECOND_BITS = 10  # of the second-order factors: degree * weight * 2^11 * 2^32 must stay below 2^63


@dataclass(frozen=True)
class Kernel:
    """How a hop is drawn: ``weight`` names an edge column rule; ``method`` direct or accept."""

    name: str = "hybrid"
    method: str = "direct"
    weighted: bool = False
    p: float = 1.0
    q: float = 1.0
    rule: Callable[[DataFrame], DataFrame] | None = None


@dataclass(frozen=True)
class Stop:
    """Fixed length, or the first prefix of at least ``min_length`` whose R^2 falls below ``mu``.

    ``literal`` is the published threshold, which always stops at three nodes when
    the series starts with the first node; ``calibrated`` gives lengths like those
    reported, and is ours.
    """

    kind: str = "entropy_r2"
    mu: float = 0.85
    min_length: int = 3
    max_length: int = 80
    window: int | None = None  # only the last so many prefixes enter R^2; needs the whole path

    @staticmethod
    def fixed(length: int = 80) -> "Stop":
        return Stop("fixed", 0.0, length, length)

    @staticmethod
    def literal() -> "Stop":
        return Stop("entropy_r2", 0.995, 3, 80)

    @staticmethod
    def calibrated() -> "Stop":
        return Stop("entropy_r2", 0.85, 3, 80)


def kernel_edges(edges: DataFrame, kernel: Kernel, directed: bool = False) -> DataFrame:
    """(u, v, q, hi, p_accept): what the kernel needs of the graph."""
    if kernel.name in ("uniform", "biased2"):
        edges2 = G.both_directions(edges, directed).withColumn("p_accept", F.lit(1.0))
        weight = F.col("w").cast("long") if kernel.weighted else F.lit(1)
    else:
        if directed:
            # common neighbours over out-neighbour sets
            adj = G.adjacency(G.both_directions(edges, True))
            left = edges.join(adj.select(F.col("node").alias("src"), F.col("nbr").alias("a")), "src").join(adj.select(F.col("node").alias("dst"), F.col("nbr").alias("b")), "dst", "left")
            cm = left.select("src", "dst", "w", F.coalesce(F.size(F.array_intersect("a", "b")), F.lit(0)).alias("cm"))
        else:
            cm = edges if "cm" in edges.columns else G.common_neighbours(edges)
        edges2 = G.hybrid_weight(cm, kernel.weighted, directed)
        if kernel.name == "hybrid_plus":
            edges2 = G.overlap_weight(edges2)
        elif kernel.rule is not None:
            edges2 = kernel.rule(edges2)
        weight = G.quantised(F.col("p_accept"))
    hi = F.sum("q").over(Window.partitionBy("u").orderBy("v").rowsBetween(Window.unboundedPreceding, 0))
    return edges2.select("u", "v", weight.alias("q"), "p_accept").withColumn("hi", hi)


# --- column-expression engine -------------------------------------------------


def _spread_walks(table: DataFrame, sources: DataFrame, length: int, rounds: int, seed: int, checkpoint_every: int) -> DataFrame:
    """First-order ``step_walks``: a draw meets the edge whose running sum holds it, so no walker carries the neighbours of its node.

    An edge stands under every bucket of draws that it reaches, buckets are as wide
    as the node's mean weight, and a row also brings the total and width of the next node.
    """
    node = table.groupBy(F.col("u").alias("node")).agg(F.max("hi").alias("total"), F.expr("greatest(1, max(hi) div count(*))").alias("width"))
    reach = F.sequence(F.expr("(hi - q) div width"), F.expr("greatest(hi - 1, hi - q) div width"))
    spans = table.join(node, table["u"] == node["node"]).select(F.col("u").alias("at"), F.explode(reach).alias("spot"), (F.col("hi") - F.col("q")).alias("lo"), "hi", F.col("v").alias("nxt"))
    spans = spans.join(node.select(F.col("node").alias("nxt"), F.col("total").alias("t"), F.col("width").alias("wd")), "nxt", "left").transform(durable)
    now = sources.join(node, "node", "left").select(F.col("node").alias("walk_id"), "node", "total", "width", F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    now = now.withColumn("path", F.array("node"))
    for hop in range(1, length):
        draw = draw_column(seed, F.col("round"), F.col("walk_id"), F.lit(hop), F.lit(0), F.lit(0))
        drawn = now.withColumn("x", F.shiftright(draw * F.col("total"), 32))
        met = drawn.join(spans, F.expr("node = at and x div width = spot and x >= lo and x < hi"), "left")
        went = F.col("nxt").isNotNull()
        now = met.select("round", "walk_id", F.coalesce("nxt", "node").alias("node"), F.when(went, F.col("t")).alias("total"), F.when(went, F.col("wd")).alias("width"), F.when(went, F.concat("path", F.array("nxt"))).otherwise(F.col("path")).alias("path"))
        if checkpoint_every and hop % checkpoint_every == 0:
            now = now.transform(durable)
    return now.select("round", "walk_id", F.posexplode("path").alias("at", "node")).select("round", "walk_id", (F.col("at") + 1).alias("step"), "node")


def step_walks(edges: DataFrame, sources: DataFrame, kernel: Kernel = Kernel("uniform"), length: int = 10, rounds: int = 1, seed: int = 42, directed: bool = False, checkpoint_every: int = 0) -> DataFrame:
    """(round, walk_id, step, node) of fixed-length walks from ``sources`` (node), in column expressions."""
    table = kernel_edges(edges, kernel, directed)
    if kernel.name != "biased2":
        return _spread_walks(table.select("u", "v", "hi", "q").transform(durable), sources, length, rounds, seed, checkpoint_every)
    # every hop joins the adjacency: it is made once
    adj = G.adjacency(table.select("u", "v", "hi", "q"), "hi", "q").select("node", "nbr", F.col("hi").alias("cdf"), "q").transform(durable)
    now = sources.select(F.col("node").alias("walk_id"), F.col("node").alias("node"), F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    now = now.withColumn("path", F.array("node")).withColumn("before", F.lit(None).cast("array<bigint>"))
    for hop in range(1, length):
        met = now.join(adj.withColumnRenamed("node", "at"), F.col("node") == F.col("at"), "left")
        draw = draw_column(seed, F.col("round"), F.col("walk_id"), F.lit(hop), F.lit(0), F.lit(0))
        if kernel.name == "biased2" and hop > 1:
            last = F.element_at("path", -2)
            scaled = F.transform("nbr", lambda v: F.when(v == last, F.lit(round((1 << SECOND_BITS) / kernel.p))).when(F.array_contains("before", v), F.lit(1 << SECOND_BITS)).otherwise(F.lit(round((1 << SECOND_BITS) / kernel.q))).cast("long"))
            met = met.withColumn("wq", F.zip_with(scaled, "q", lambda a, b: a * b))
            total = F.aggregate("wq", F.lit(0).cast("long"), lambda a, x: a + x)
            x = F.shiftright(draw * total, 32)
            cum = F.transform(F.sequence(F.lit(1), F.size("wq")), lambda i: F.aggregate(F.slice("wq", F.lit(1), i), F.lit(0).cast("long"), lambda a, b: a + b))
            pick = F.size(F.filter(cum, lambda c: c <= x))
        else:
            total = F.element_at("cdf", -1)
            x = F.shiftright(draw * total, 32)
            pick = F.size(F.filter("cdf", lambda c: c <= x))
        nxt = F.when(F.col("nbr").isNotNull(), F.element_at("nbr", pick + 1))
        met = met.withColumn("nxt", nxt)
        now = met.select("round", "walk_id", F.coalesce("nxt", "node").alias("node"), F.when(F.col("nxt").isNotNull(), F.concat("path", F.array("nxt"))).otherwise(F.col("path")).alias("path"), F.col("nbr").alias("before"))
        if checkpoint_every and hop % checkpoint_every == 0:
            now = now.transform(durable)
    return now.select("round", "walk_id", F.posexplode("path").alias("at", "node")).select("round", "walk_id", (F.col("at") + 1).alias("step"), "node")


def fullpath_measures(steps: DataFrame) -> DataFrame:
    """The baseline's measures: every prefix recomputed from the whole path, O(L^2) a walk."""
    later = steps.alias("p").join(steps.alias("s"), F.expr("p.round = s.round and p.walk_id = s.walk_id and s.step <= p.step"))
    counts = later.groupBy(F.col("p.round").alias("round"), F.col("p.walk_id").alias("walk_id"), F.col("p.step").alias("step"), F.col("s.node").alias("node")).agg(F.count("*").alias("n"))
    share = F.col("n") / F.col("step")
    return counts.groupBy("round", "walk_id", "step").agg(F.sum(-share * F.log2(share)).alias("entropy"))


def fullpath_regression(steps: DataFrame) -> DataFrame:
    """(round, walk_id, step, r2): the regression of entropy on length over every whole prefix, in the library's own form.

    As in the SQL standard a constant entropy gives 1 and a single step null; the
    stop rule takes 0 for both (``fullpath_r2``).
    """
    h = fullpath_measures(steps)
    upto = h.alias("p").join(h.alias("q"), F.expr("p.round = q.round and p.walk_id = q.walk_id and q.step <= p.step"))
    return upto.groupBy(F.col("p.round").alias("round"), F.col("p.walk_id").alias("walk_id"), F.col("p.step").alias("step")).agg(F.regr_r2("q.entropy", F.col("q.step").cast("double")).alias("r2"))


def fullpath_r2(steps: DataFrame) -> DataFrame:
    """(round, walk_id, step, r2): the correlation of entropy and length recomputed over every whole prefix; 0 where a series is constant."""
    h = fullpath_measures(steps)
    upto = h.alias("p").join(h.alias("q"), F.expr("p.round = q.round and p.walk_id = q.walk_id and q.step <= p.step"))
    x, y = F.col("q.step").cast("double"), F.col("q.entropy")
    moving = (F.var_pop(x) > 1e-12) & (F.var_pop(y) > 1e-12)
    return upto.groupBy(F.col("p.round").alias("round"), F.col("p.walk_id").alias("walk_id"), F.col("p.step").alias("step")).agg(F.when(moving, F.pow(F.covar_pop(x, y), F.lit(2.0)) / (F.var_pop(x) * F.var_pop(y))).otherwise(F.lit(0.0)).alias("r2"))


# --- lockstep engine ----------------------------------------------------------


@dataclass
class Block:
    """Adjacency of one part as flat arrays: node ids ascending, and each node's slice of neighbours and running sums.

    ``names`` and ``pairs`` are what the second-order rule asks for: which ids are
    linked, among the part's own edges and those between neighbours of its nodes
    (rows without a running sum).  ``ends`` and ``homes`` say which part holds a
    neighbour.
    """

    nodes: np.ndarray
    begin: np.ndarray
    nbr: np.ndarray
    hi: np.ndarray
    accept: np.ndarray
    names: np.ndarray
    pairs: np.ndarray
    ends: np.ndarray
    homes: np.ndarray

    @staticmethod
    def of(frame: pd.DataFrame, second_order: bool = False) -> "Block":
        u, v = frame["u"].to_numpy(np.int64), frame["v"].to_numpy(np.int64)
        names, pairs = np.empty(0, np.int64), np.empty(0, np.int64)
        if second_order:
            names = np.unique(np.concatenate([u, v]))
            pairs = np.unique(np.searchsorted(names, u) * len(names) + np.searchsorted(names, v))
        own = frame[frame["hi"].notna()] if frame["hi"].hasnans else frame
        f = own.sort_values(["u", "v"], kind="stable")
        nodes, begin = np.unique(f["u"].to_numpy(np.int64), return_index=True)
        nbr = f["v"].to_numpy(np.int64)
        ends, first = np.unique(nbr, return_index=True)
        homes = f["to_part"].to_numpy(np.int64)[first] if "to_part" in f else np.zeros(len(ends), np.int64)
        return Block(nodes, np.append(begin, len(f)), nbr, f["hi"].to_numpy(np.int64), f["p_accept"].to_numpy(), names, pairs, ends, homes)

    def home(self, ids: np.ndarray) -> np.ndarray:
        """The parts of neighbours."""
        return self.homes[np.searchsorted(self.ends, ids)]

    def linked(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether the edges (a, b) exist."""
        if not len(self.pairs):
            return np.zeros(len(a), dtype=bool)
        i, j = (np.minimum(np.searchsorted(self.names, x), len(self.names) - 1) for x in (a, b))
        code = i * len(self.names) + j
        at = np.minimum(np.searchsorted(self.pairs, code), len(self.pairs) - 1)
        return (self.pairs[at] == code) & (self.names[i] == a) & (self.names[j] == b)

    @cached_property
    def sums(self) -> tuple[np.ndarray, np.ndarray]:
        """Running sums of all nodes in one ascending array, and where each node begins in it: one search serves every walker."""
        base = np.concatenate([[0], np.cumsum(self.hi[self.begin[1:] - 1])])
        return base, self.hi + np.repeat(base[:-1], np.diff(self.begin))

    def find(self, ids: np.ndarray) -> np.ndarray:
        """Positions of ids, -1 where the part has none of their edges."""
        if not len(self.nodes):
            return np.full(len(ids), -1)
        at = np.minimum(np.searchsorted(self.nodes, ids), len(self.nodes) - 1)
        return np.where(self.nodes[at] == ids, at, -1)


WALKER = ["round", "walk_id", "steps", "node", "H", "L", "EH", "EL", "EHL", "EH2", "EL2", "prev", "trials"]


def _drawn(block: Block, at: np.ndarray, walkers: dict[str, np.ndarray], kernel: Kernel, draws: np.ndarray) -> np.ndarray:
    """The next node of walkers at positions ``at`` by one draw from the kernel's weights."""
    begin, end = block.begin[at], block.begin[at + 1]
    if kernel.name != "biased2":
        base, flat = block.sums
        return block.nbr[np.searchsorted(flat, base[at] + (draws * block.hi[end - 1] >> 32), side="right")]
    # walkers by the node before, so that searches for links go in one direction; some candidates at a time
    order, nxt = np.argsort(walkers["prev"], kind="stable"), np.empty(len(at), dtype=np.int64)
    reach = np.cumsum((end - begin)[order])
    while len(order):
        n = max(1, int(np.searchsorted(reach, CANDIDATES, side="right")))
        some, order, reach = order[:n], order[n:], reach[n:] - reach[n - 1]
        nxt[some] = _drawn_second(block, begin[some], end[some], walkers["prev"][some], walkers["steps"][some], kernel, draws[some])
    return nxt


def _drawn_second(block: Block, begin: np.ndarray, end: np.ndarray, prev: np.ndarray, steps: np.ndarray, kernel: Kernel, draws: np.ndarray) -> np.ndarray:
    size = end - begin
    owner = np.repeat(np.arange(len(size)), size)
    spot = np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
    v, t = block.nbr[spot], prev[owner]
    weight = block.hi[spot] - np.where(spot > begin[owner], block.hi[np.maximum(spot - 1, 0)], 0)
    unit = 1 << SECOND_BITS
    factor = np.where(v == t, round(unit / kernel.p), np.where(block.linked(t, v), unit, round(unit / kernel.q)))
    weight = weight * np.where(steps[owner] > 1, factor, 1)
    run = np.cumsum(weight)
    last = np.cumsum(size) - 1
    before = run[last - size + 1] - weight[last - size + 1]
    x = draws * (run[last] - before) >> 32
    return v[np.searchsorted(run, before + x, side="right")]


def draw_hop(block: Block, at: np.ndarray, walkers: dict[str, np.ndarray], kernel: Kernel, seed: int, rng: str) -> tuple[np.ndarray, np.ndarray]:
    """(next node, trials) of walkers whose nodes stand at positions ``at`` of the block.

    An ``accept`` walker that was refused ``MAX_TRIALS`` times takes one draw from
    the same law, so the limit changes no probability.
    """
    walk, steps, round_ = walkers["walk_id"], walkers["steps"], walkers["round"]
    if kernel.method != "accept":
        return _drawn(block, at, walkers, kernel, draw_many(rng, seed, round_, walk, steps)), np.ones(len(at), dtype=np.int64)
    begin, end = block.begin[at], block.begin[at + 1]
    out, trials = np.full(len(at), -1, dtype=np.int64), np.zeros(len(at), dtype=np.int64)
    open_, t = np.arange(len(at)), 0
    while len(open_) and t < MAX_TRIALS:
        pick = begin[open_] + (draw_many(rng, seed, round_[open_], walk[open_], steps[open_], t, 1) * (end - begin)[open_] >> 32)
        chance = block.accept[pick]
        if kernel.name == "biased2":
            chance = _biased_chance(block, walkers, open_, pick, kernel)
        height = draw_many(rng, seed, round_[open_], walk[open_], steps[open_], t, 2) / 2.0**32
        trials[open_] += 1
        fine = height < chance
        out[open_[fine]] = block.nbr[pick[fine]]
        open_, t = open_[~fine], t + 1
    if len(open_):
        some = {c: x[open_] for c, x in walkers.items()}
        out[open_] = _drawn(block, at[open_], some, kernel, draw_many(rng, seed, round_[open_], walk[open_], steps[open_], MAX_TRIALS, 3))
        trials[open_] += 1
    return out, trials


def _biased_chance(block: Block, walkers: dict[str, np.ndarray], open_: np.ndarray, pick: np.ndarray, kernel: Kernel) -> np.ndarray:
    """Acceptance of candidates under the second-order rule, over the envelope of its three values."""
    top = max(1 / kernel.p, 1.0, 1 / kernel.q)
    v, t = block.nbr[pick], walkers["prev"][open_]
    first = walkers["steps"][open_] <= 1
    return np.where(first, 1.0, np.where(v == t, 1 / kernel.p, np.where(block.linked(t, v), 1.0, 1 / kernel.q)) / top)


def start_walkers(nodes: np.ndarray, round_: int) -> dict[str, np.ndarray]:
    n = len(nodes)
    w = {c: np.zeros(n) for c in WALKER}
    w |= {"round": np.full(n, round_, dtype=np.int64), "walk_id": nodes.astype(np.int64), "steps": np.ones(n, dtype=np.int64), "node": nodes.astype(np.int64), "L": np.ones(n), "EL": np.ones(n), "EL2": np.ones(n), "prev": np.full(n, -1, dtype=np.int64), "trials": np.zeros(n, dtype=np.int64)}
    return w


ROUND_BITS = 10
PRUNE_EVERY = 8  # supersteps between two clearings of the counts of walks that have stopped


def walk_key(walks: np.ndarray, rounds: np.ndarray) -> np.ndarray:
    """One number for a walk of a round: rounds of a wave advance together."""
    return (walks.astype(np.int64) << ROUND_BITS) + rounds.astype(np.int64)


def measure_many(w: dict[str, np.ndarray], n_before: np.ndarray) -> None:
    """Appends a node seen ``n_before`` times: entropy and the five running means, in place."""
    h = entropy_step_many(w["H"], w["L"], n_before)
    w["L"] = w["L"] + 1
    w["H"] = h
    p = w["L"]
    for name, value in (("EH", h), ("EL", p), ("EHL", h * p), ("EH2", h * h), ("EL2", p * p)):
        w[name] = w[name] + (value - w[name]) / p


def finished(w: dict[str, np.ndarray], stop: Stop) -> np.ndarray:
    if stop.kind == "fixed":
        return w["L"] >= stop.max_length
    r2 = r_squared_many(w["EH"], w["EL"], w["EHL"], w["EH2"], w["EL2"])
    return (w["L"] >= stop.max_length) | ((w["L"] >= stop.min_length) & (r2 < stop.mu))


def _take(w: dict[str, np.ndarray], mask: np.ndarray) -> dict[str, np.ndarray]:
    return {k: v[mask] for k, v in w.items()}


class Counts:
    """How often each (walk, node) was met here: the local frequency lists of a part.

    A row a walk holds the nodes of its visits here; a visit is counted by
    comparing the row, for all walks at once.  A walk comes once a call.
    """

    def __init__(self) -> None:
        self.names = np.empty(0, np.int64)
        self.seen = np.empty((0, 8), np.int64)
        self.fill = np.empty(0, np.int64)

    def _rows(self, walks: np.ndarray) -> np.ndarray:
        if len(self.names):
            at = np.minimum(np.searchsorted(self.names, walks), len(self.names) - 1)
            if (self.names[at] == walks).all():
                return at
        names = np.union1d(self.names, walks)
        if len(names) > len(self.names):
            old = np.searchsorted(names, self.names)
            seen, fill = np.full((len(names), self.seen.shape[1]), -1, np.int64), np.zeros(len(names), np.int64)
            seen[old], fill[old] = self.seen, self.fill
            self.names, self.seen, self.fill = names, seen, fill
        return np.searchsorted(self.names, walks)

    def add(self, walks: np.ndarray, nodes: np.ndarray) -> np.ndarray:
        """Counts before this visit."""
        if not len(walks):
            return np.empty(0)
        row = self._rows(walks)
        at = self.fill[row]
        if at.max() >= self.seen.shape[1]:
            self.seen = np.pad(self.seen, ((0, 0), (0, self.seen.shape[1])), constant_values=-1)
        used = int(at.max())
        before = ((self.seen[row, :used] == nodes[:, None]) & (np.arange(used) < at[:, None])).sum(1).astype(float)
        self.seen[row, at] = nodes
        self.fill[row] = at + 1
        return before

    def load(self, walks: np.ndarray, nodes: np.ndarray, times: np.ndarray) -> None:
        walks, nodes = np.repeat(walks, times), np.repeat(nodes, times)
        order = np.argsort(walks, kind="stable")
        walks, nodes = walks[order], nodes[order]
        if len(walks):
            row = self._rows(np.unique(walks))
            begin = np.flatnonzero(np.concatenate([[True], walks[1:] != walks[:-1]]))
            size = np.diff(np.append(begin, len(walks)))
            self.seen = np.pad(self.seen, ((0, 0), (0, max(0, int(size.max()) - self.seen.shape[1]))), constant_values=-1)
            self.seen[np.repeat(row, size), np.arange(len(walks)) - np.repeat(begin, size)] = nodes
            self.fill[row] = size

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(walk, node, times) of everything met."""
        held = np.arange(self.seen.shape[1]) < self.fill[:, None]
        walks, nodes = np.broadcast_to(self.names[:, None], held.shape)[held], self.seen[held]
        order = np.lexsort((nodes, walks))
        walks, nodes = walks[order], nodes[order]
        begin = np.flatnonzero(np.concatenate([[True], (walks[1:] != walks[:-1]) | (nodes[1:] != nodes[:-1])])) if len(walks) else np.empty(0, np.int64)
        return walks[begin], nodes[begin], np.diff(np.append(begin, len(walks)))


def advance(block: Block, w: dict[str, np.ndarray], counts: Counts, kernel: Kernel, stop: Stop, seed: int, rng: str) -> tuple[list[tuple[np.ndarray, ...]], dict[str, np.ndarray], dict[str, np.ndarray]]:
    """Advances walkers that stand in this part until they stop or leave.

    Returns hops as (walk, step, node, round), walkers that left, and walkers that stopped.
    """
    hops, left, over = [], [], []
    while len(w["node"]):
        at = block.find(w["node"])
        away = at < 0
        if away.any():
            left.append(_take(w, away))
            w, at = _take(w, ~away), at[~away]
            continue
        nxt, trials = draw_hop(block, at, w, kernel, seed, rng)
        w["prev"], w["node"], w["trials"] = w["node"], nxt, w["trials"] + trials
        w["steps"] = w["steps"] + 1
        here = block.find(nxt) >= 0
        # the visit is counted by the part that owns the node
        gone = ~here
        if gone.any():
            left.append(_take(w, gone))
            w = _take(w, here)
        if not len(w["node"]):
            break
        if stop.kind == "fixed":
            w["L"] = w["L"] + 1
        else:
            measure_many(w, counts.add(walk_key(w["walk_id"], w["round"]), w["node"]))
        hops.append((w["walk_id"], w["steps"], w["node"], w["round"]))
        done = finished(w, stop)
        if done.any():
            over.append(_take(w, done))
            w = _take(w, ~done)
    merge = lambda parts: {c: np.concatenate([p[c] for p in parts]) for c in WALKER} if parts else start_walkers(np.empty(0, np.int64), 0)
    return hops, merge(left), merge(over)


def local_walks(table: pd.DataFrame, sources: np.ndarray, kernel: Kernel, stop: Stop, round_: int = 1, seed: int = 42, rng: str = "portable") -> pd.DataFrame:
    """One round on the driver: (round, walk_id, step, node)."""
    block = Block.of(table, kernel.name == "biased2")
    counts, w = Counts(), start_walkers(np.asarray(sources), round_)
    counts.add(walk_key(w["walk_id"], w["round"]), w["node"])
    first = (w["walk_id"], w["steps"], w["node"], w["round"])
    sinks = block.find(w["node"]) < 0
    hops, _, _ = advance(block, _take(w, ~sinks), counts, kernel, stop, seed, rng)
    walk, step, node = (np.concatenate([h[i] for h in [first, *hops]]) for i in range(3))
    return pd.DataFrame({"round": round_, "walk_id": walk, "step": step.astype(int), "node": node})


_OUT = "kind int, part int, round int, walk_id long, steps long, node long, H double, L double, EH double, EL double, EHL double, EH2 double, EL2 double, prev long, trials long"


def placed_edges(edges: DataFrame, assign: DataFrame, kernel: Kernel) -> DataFrame:
    """(home, u, v, hi, p_accept, to_part): each part's edges; for the second-order rule also, without ``hi``, the links among a node's neighbours.

    ``to_part`` holds v, so that a walker knows where it goes; an unplaced v stands with u.
    """
    where_v = assign.select(F.col("node").alias("v"), F.col("part").alias("to_part"))
    own = edges.join(assign.withColumnRenamed("node", "u"), "u").join(where_v, "v", "left")
    own = own.select(F.col("part").alias("home"), "u", "v", F.col("hi").cast("long").alias("hi"), "p_accept", F.coalesce("to_part", "part").cast("long").alias("to_part"))
    if kernel.name != "biased2" or assign.select("part").distinct().limit(2).count() < 2:  # one part holds every link itself
        return own
    sides = edges.where("u < v").select(F.col("u").alias("src"), F.col("v").alias("dst"), F.lit(1.0).alias("w"))
    corner = G.triangles(sides)
    turns = F.explode(F.array(*[F.struct(F.col(x).alias("node"), F.col(y).alias("u"), F.col(z).alias("v")) for x, y, z in (("n1", "n2", "n3"), ("n2", "n1", "n3"), ("n3", "n1", "n2"))]))
    met = corner.select(turns.alias("t")).select("t.*").join(assign, "node").select(F.col("part").alias("home"), "u", "v").distinct()
    both = met.unionByName(met.select("home", F.col("v").alias("u"), F.col("u").alias("v")))
    return own.unionByName(both.select("home", "u", "v", F.lit(None).cast("long").alias("hi"), F.lit(None).cast("double").alias("p_accept"), F.lit(None).cast("long").alias("to_part")))


def _settled(placed: DataFrame) -> DataFrame:
    """Parts written once, by ``home``: supersteps exchange walkers alone."""
    return placed.repartition(int(placed.sparkSession.conf.get("spark.sql.shuffle.partitions")), "home").transform(durable)


def each_round(rounds: int | tuple[int, ...]) -> Column:
    """A row for each round of a wave."""
    return F.explode(F.array(*[F.lit(r) for r in ((rounds,) if isinstance(rounds, int) else rounds)])).alias("round")


def _path_r2(path: list[int], window: int | None) -> float:
    """R^2 of entropy and length over the prefixes of a path, all recomputed."""
    counts: dict[int, int] = {}
    mass, h = 0.0, []
    for i, v in enumerate(path, 1):
        n = counts.get(v, 0)
        counts[v] = n + 1
        mass += (n + 1) * math.log2(n + 1) - (n * math.log2(n) if n else 0.0)
        h.append(math.log2(i) - mass / i)
    y = np.array(h[-window:] if window else h)
    x = np.arange(len(path) - len(y) + 1, len(path) + 1, dtype=float)
    x, y = x - x.mean(), y - y.mean()
    vx, vy = (x * x).mean(), (y * y).mean()
    return float((x * y).mean() ** 2 / (vx * vy)) if vx > 1e-12 and vy > 1e-12 else 0.0


def fullpath_round(edges: DataFrame, assign: DataFrame, sources: DataFrame, kernel: Kernel, stop: Stop, round_: int | tuple[int, ...] = 1, seed: int = 42, rng: str = "native") -> DataFrame:
    """The baseline's walker: it carries its path, and every stop is decided from the whole of it.

    (round, walk_id, step, node, sent): ``sent`` is the bytes of the message that
    brought the walker to the node, 24 + 8 a node of the path, 0 inside a part.
    """
    placed = _settled(placed_edges(edges, assign, kernel))
    schema = "kind int, part int, round int, walk_id long, step int, node long, sent long, trials long, path array<bigint>"
    names = [c.split()[0] for c in schema.split(", ")]

    def done(path: list[int]) -> bool:
        if stop.kind == "fixed" or len(path) >= stop.max_length:
            return len(path) >= stop.max_length
        return len(path) >= stop.min_length and _path_r2(path, stop.window) < stop.mu

    def superstep(key: tuple, came: pd.DataFrame, table: pd.DataFrame) -> pd.DataFrame:
        block = Block.of(table, kernel.name == "biased2")
        names_ = list(zip(came["round"].tolist(), came["walk_id"].tolist()))
        paths = {w: list(p) for w, p in zip(names_, came["path"])}
        trials = dict(zip(names_, came["trials"].tolist()))
        out = [(0, 0, *w, len(p), p[-1], 24 + 8 * len(p) if len(p) > 1 else 0, trials[w], None) for w, p in paths.items()]
        live = [w for w, p in paths.items() if not done(p)]
        while live:
            here = np.array([paths[w][-1] for w in live])
            at = block.find(here)
            live = [w for w, k in zip(live, at) if k >= 0]  # without out-edges a walk ends
            at = at[at >= 0]
            if not live:
                break
            walkers = {"walk_id": np.array([w for _, w in live]), "steps": np.array([len(paths[w]) for w in live]), "round": np.array([r for r, _ in live]), "prev": np.array([paths[w][-2] if len(paths[w]) > 1 else -1 for w in live])}
            nxt, tried = draw_hop(block, at, walkers, kernel, seed, rng)
            stay = block.find(nxt) >= 0
            still = []
            for w, v, t, inside, home in zip(live, nxt.tolist(), tried.tolist(), stay.tolist(), block.home(nxt).tolist()):
                paths[w].append(v)
                trials[w] += t
                if not inside:
                    out.append((1, home, *w, len(paths[w]), v, 0, trials[w], paths[w]))
                    continue
                out.append((0, 0, *w, len(paths[w]), v, 0, trials[w], None))
                if not done(paths[w]):
                    still.append(w)
            live = still
        return pd.DataFrame(out, columns=names)

    state = sources.join(assign, "node").select("part", each_round(round_), F.col("node").alias("walk_id"), F.array("node").alias("path"), F.lit(0).cast("long").alias("trials"))
    hops = []
    while True:
        moved = state.groupBy("part").cogroup(placed.groupBy("home")).applyInPandas(superstep, schema).transform(durable)
        hops.append(moved.where("kind = 0").select("round", "walk_id", "step", "node", "sent", "trials"))
        state = moved.where("kind = 1").select("part", "round", "walk_id", "path", "trials")
        if state.isEmpty():
            break
    result = hops[0]
    for more in hops[1:]:
        result = result.unionByName(more)
    return result


def burst_round(edges: DataFrame, assign: DataFrame, sources: DataFrame, kernel: Kernel, stop: Stop, round_: int | tuple[int, ...] = 1, seed: int = 42, rng: str = "native", replicas: int = 1) -> DataFrame:
    """A round of walks by parts, or several rounds at once: (round, walk_id, step, node, trials).

    A part whose edges leave room in a task may have several ``replicas``, which
    share its walks: nothing crosses between them.

    ``edges`` is the kernel's table, ``assign`` (node, part).  A superstep hands
    walkers to the part of their node; each part advances its own in lockstep.
    Rows of a superstep are one checkpointed frame: hops (kind 0), walkers that
    leave (1), counts that stay (2).  A node without out-edges belongs to its
    assigned part all the same and ends walks there.  Under the second-order rule
    a part also holds which neighbours of its nodes are linked, from the triangles.
    Every walker advances in every superstep, so there are at most as many as a
    walk has hops.  A superstep is one exchange of walkers and counts: edges are
    written by part once and name the part of their far end.
    """
    if stop.window is not None:
        raise ValueError("a trailing window needs the whole path: use fullpath_round")
    copies = F.explode(F.sequence(F.lit(0), F.lit(replicas - 1)))
    placed = placed_edges(edges, assign, kernel).withColumn("copy", copies).withColumn("home", F.col("home") * replicas + F.col("copy")).drop("copy").transform(_settled)
    shared = lambda frame: frame.withColumn("part", (F.col("part") * replicas + F.pmod(F.xxhash64("round", "walk_id"), F.lit(replicas))).cast("int"))
    nothing = [F.lit(0.0).alias(c) for c in ("H", "L", "EH", "EL", "EHL", "EH2", "EL2")]
    begin = sources.join(assign, "node").select(F.lit(1).alias("kind"), "part", each_round(round_), F.col("node").alias("walk_id"), F.lit(1).cast("long").alias("steps"), "node", *nothing, F.lit(-1).cast("long").alias("prev"), F.lit(0).cast("long").alias("trials"))

    def superstep(key: tuple, state: pd.DataFrame, table: pd.DataFrame) -> pd.DataFrame:
        part = int(key[0])
        block = Block.of(table, kernel.name == "biased2")
        counts = Counts()
        kept = state[state["kind"] == 2]
        counts.load(walk_key(kept["walk_id"].to_numpy(), kept["round"].to_numpy()), *(kept[c].to_numpy(np.int64) for c in ("node", "steps")))
        came = state[state["kind"] == 1]
        w = {c: came[c].to_numpy(copy=True) for c in WALKER}
        out: list[pd.DataFrame] = []

        def emit(kind: int, at: int | np.ndarray = part, **columns) -> None:
            frame = pd.DataFrame(columns)
            if len(frame):
                frame["kind"], frame["part"] = kind, at
                out.append(frame)

        if len(came):
            fresh = w["L"] == 0
            if stop.kind == "fixed":  # the length alone decides
                w["L"] = w["L"] + 1
            else:
                n_before = counts.add(walk_key(w["walk_id"], w["round"]), w["node"])
                measure_many(w, n_before)  # the first node of a walk, or the visit that made a walker cross
                w["H"] = np.where(fresh, 0.0, w["H"])
            arrived = dict(walk_id=w["walk_id"], steps=w["steps"], node=w["node"])
            emit(0, round=w["round"], **arrived, trials=w["trials"])
            alive = ~finished(w, stop) & (block.find(w["node"]) >= 0)
            hops, left, _ = advance(block, _take(w, alive), counts, kernel, stop, seed, rng)
            for walk, step, node, turn in hops:
                emit(0, round=turn, walk_id=walk, steps=step, node=node)
            emit(1, block.home(left["node"]) if len(left["node"]) else part, **left)
        walk, node, times = counts.rows()
        emit(2, round=walk & ((1 << ROUND_BITS) - 1), walk_id=walk >> ROUND_BITS, node=node, steps=times)
        names = [c.split()[0] for c in _OUT.split(", ")]
        if not out:
            return pd.DataFrame(columns=names)
        return pd.concat(out, ignore_index=True).reindex(columns=names).fillna(0)

    state, hops = shared(begin), []
    while True:
        done = state.groupBy("part").cogroup(placed.groupBy("home")).applyInPandas(superstep, _OUT).transform(durable)
        hops.append(done.where("kind = 0").select("round", "walk_id", F.col("steps").cast("int").alias("step"), "node", "trials"))
        left = done.where("kind = 1")
        if left.isEmpty():
            break
        stayed = done.where("kind = 2")
        if len(hops) % PRUNE_EVERY == 0:  # counts of stopped walks go
            stayed = stayed.join(left.select("round", "walk_id").distinct(), ["round", "walk_id"], "left_semi").select(*done.columns)
        state = shared(left).unionByName(stayed)
    result = hops[0]
    for more in hops[1:]:
        result = result.unionByName(more)
    return result


def _paths_r2(paths: np.ndarray, window: int | None) -> np.ndarray:
    """``_path_r2`` of many paths of one length."""
    n, length = paths.shape
    earlier = np.tril(np.ones((length, length), dtype=bool), -1)
    k = ((paths[:, :, None] == paths[:, None, :]) & earlier).sum(2).astype(float)
    mass = np.cumsum(f_many(k + 1) - f_many(k), axis=1)
    i = np.arange(1, length + 1, dtype=float)
    y = (np.log2(i) - mass / i)[:, -window if window else 0 :]
    x = i[length - y.shape[1] :]
    x, y = x - x.mean(), y - y.mean(1, keepdims=True)
    vx, vy = (x * x).mean(), (y * y).mean(1)
    ok = (vx > 1e-12) & (vy > 1e-12)
    return np.where(ok, (x * y).mean(1) ** 2 / np.where(ok, vx * vy, 1.0), 0.0)


def _whole_paths(block: Block, sources: np.ndarray, rounds: np.ndarray, kernel: Kernel, stop: Stop, seed: int, rng: str) -> tuple[np.ndarray, ...]:
    """(round, walk, step, node, trials) of walkers that carry their paths and decide every stop from the whole of them."""
    paths = np.full((len(sources), stop.max_length), -1, dtype=np.int64)
    paths[:, 0] = sources
    tried = np.zeros(paths.shape, dtype=np.int64)
    size = np.ones(len(sources), dtype=np.int64)
    live = np.arange(len(sources))
    for length in range(1, stop.max_length):
        if stop.kind != "fixed" and length >= stop.min_length:
            done = [_paths_r2(paths[live[k : k + 2048], :length], stop.window) < stop.mu for k in range(0, len(live), 2048)]
            live = live[~np.concatenate(done or [np.empty(0, dtype=bool)])]
        at = block.find(paths[live, length - 1])
        live, at = live[at >= 0], at[at >= 0]  # without out-edges a walk ends
        if not len(live):
            break
        before = paths[live, length - 2] if length > 1 else np.full(len(live), -1)
        walkers = {"walk_id": sources[live], "steps": np.full(len(live), length), "round": rounds[live], "prev": before}
        paths[live, length], trials = draw_hop(block, at, walkers, kernel, seed, rng)
        tried[live, length] = tried[live, length - 1] + trials
        size[live] = length + 1
    held = np.arange(stop.max_length) < size[:, None]
    row, step = np.nonzero(held)
    return rounds[row], sources[row], step + 1, paths[held], tried[held]


def _counted_paths(block: Block, sources: np.ndarray, rounds: np.ndarray, kernel: Kernel, stop: Stop, seed: int, rng: str) -> tuple[np.ndarray, ...]:
    """The same of walkers with running measures."""
    counts, w = Counts(), start_walkers(sources, 1)
    w["round"] = rounds
    first = (w["walk_id"], w["steps"], w["node"], w["round"])
    if stop.kind != "fixed":
        counts.add(walk_key(w["walk_id"], w["round"]), w["node"])
    hops, left, _ = advance(block, _take(w, ~finished(w, stop) & (block.find(w["node"]) >= 0)), counts, kernel, stop, seed, rng)
    # whoever left stands on a node without out-edges
    walk, step, node, turn = (np.concatenate([h[i] for h in [first, *hops, (left["walk_id"], left["steps"], left["node"], left["round"])]]) for i in range(4))
    return turn, walk, step, node, np.zeros(len(walk), dtype=np.int64)


def shared_round(edges: DataFrame, assign: DataFrame, sources: DataFrame, kernel: Kernel, stop: Stop, round_: int | tuple[int, ...] = 1, seed: int = 42, rng: str = "native", measure: str = "incremental") -> DataFrame:
    """``burst_round`` or ``fullpath_round`` of a graph that fits a task: it is broadcast, and each task walks some sources to their ends.

    Nothing is exchanged.  Parts are those of ``assign`` all the same: ``sent`` is
    what a message of the baseline between them would hold.
    """
    frame = edges.select("u", "v", F.col("hi").cast("long").alias("hi"), "p_accept").toArrow().to_pandas()
    block = Block.of(frame, kernel.name == "biased2")
    shared = edges.sparkSession.sparkContext.broadcast(block)
    rounds = (round_,) if isinstance(round_, int) else tuple(round_)
    if stop.window is not None and measure != "fullpath":
        raise ValueError("a trailing window needs the whole path: use fullpath_round")
    walk = _whole_paths if measure == "fullpath" else _counted_paths

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = max(1, SHARED_HOPS // stop.max_length)
        for batch in batches:
            nodes, turn = (batch.column(c).to_numpy().astype(np.int64) for c in ("node", "round"))
            for k in range(0, len(nodes), n):
                turns, walks, steps, seen, trials = walk(shared.value, nodes[k : k + n], turn[k : k + n], kernel, stop, seed, rng)
                yield pa.RecordBatch.from_arrays([pa.array(turns.astype(np.int32)), pa.array(walks), pa.array(steps.astype(np.int32)), pa.array(seen), pa.array(trials)], ["round", "walk_id", "step", "node", "trials"])

    spark = edges.sparkSession
    begin = sources.join(assign.select("node"), "node").select("node", F.explode(F.array(*[F.lit(r) for r in rounds])).alias("round"))
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    steps = begin.repartition(tasks, "node", "round").mapInArrow(run, "round int, walk_id long, step int, node long, trials long").transform(durable)
    if measure != "fullpath":
        return steps
    # a message holds the path so far where the part changes
    order = Window.partitionBy("round", "walk_id").orderBy("step")
    crossed = F.col("part") != F.lag("part").over(order)
    sent = F.when(crossed, 24 + 8 * F.col("step")).otherwise(F.lit(0)).cast("long")
    return steps.join(assign, "node").withColumn("sent", sent).select("round", "walk_id", "step", "node", "sent", "trials")


def fits_a_task(edges: DataFrame) -> bool:
    return edges.limit(SHARED_ROWS + 1).count() <= SHARED_ROWS


def corpus_round(edges: DataFrame, assign: DataFrame, sources: DataFrame, kernel: Kernel, stop: Stop, round_: int | tuple[int, ...] = 1, seed: int = 42, rng: str = "native", replicas: int = 1) -> DataFrame:
    """Walks of one or several rounds by the engine that suits the graph's size: all agree hop by hop."""
    if fits_a_task(edges):
        return shared_round(edges, assign, sources, kernel, stop, round_, seed, rng)
    return burst_round(edges, assign, sources, kernel, stop, round_, seed, rng, replicas)


def parts_for(edges: DataFrame, edges_a_part: int = 5_000_000) -> int:
    """Parts of bounded adjacency: what fits a task decides, not the number of cores."""
    return max(1, -(-edges.count() // edges_a_part))


def sample_corpus(edges: DataFrame, assign: DataFrame, kernel: Kernel = Kernel(), stop: Stop = Stop.calibrated(), delta: float = 0.001, max_rounds: int = 10, fixed_rounds: int | None = None, seed: int = 42, rng: str = "native", directed: bool = False, measure: str = "incremental", wave: int = 5, replicas: int = 1) -> tuple[DataFrame, list[float]]:
    """All rounds until the corpus's divergence settles (or ``fixed_rounds``); the corpus and the divergences.

    Rounds don't depend on one another, so ``wave`` of them walk at once; those
    behind the round that settles are left out.  A scalar a round reaches the driver.
    """
    table = kernel_edges(edges, kernel, directed).transform(durable)
    deg = table.groupBy(F.col("u").alias("node")).agg(F.count("*").alias("deg")).transform(durable)
    total = deg.agg(F.sum("deg")).first()[0] or 1
    last = fixed_rounds or max_rounds
    counted, corpus, trace = None, None, []
    if measure == "fullpath":
        walk = partial(shared_round, measure=measure) if fits_a_task(table) else fullpath_round
    else:
        walk = partial(corpus_round, replicas=replicas)
    for begin in range(1, last + 1, wave):
        rounds = tuple(range(begin, min(begin + wave, last + 1)))
        steps = walk(table, assign, assign.select("node"), kernel, stop, rounds, seed, rng)
        new = steps.groupBy("node").agg(*[F.count_if(F.col("round") == r).alias(f"n{r}") for r in rounds])
        counted = (new.withColumn("past", F.lit(0).cast("long")) if counted is None else new.join(counted, "node", "full").na.fill(0)).transform(durable)
        # divergences of all rounds of the wave in one pass: sum p log2(p A / o) = sum p log2(p / o) + log2(A) sum p
        upto = {r: reduce(lambda a, b: a + b, [F.col("past"), *[F.col(f"n{x}") for x in rounds if x <= r]]) for r in rounds}
        p = F.coalesce("deg", F.lit(0)) / F.lit(float(total))
        seen = lambda o, value: F.sum(F.when((o > 0) & (p > 0), value))
        sums = [c for r, o in upto.items() for c in (seen(o, p * F.log2(p / o)).alias(f"s{r}"), seen(o, p).alias(f"p{r}"), F.sum(o).alias(f"a{r}"))]
        row = counted.join(deg, "node", "left").agg(*sums).first()
        for r in rounds:
            trace.append(float((row[f"s{r}"] or 0.0) + math.log2(row[f"a{r}"] or 1) * (row[f"p{r}"] or 0.0)))
            if fixed_rounds is None and r > 1 and abs(trace[-1] - trace[-2]) <= delta:
                steps = steps.where(F.col("round") <= r)
                return (steps if corpus is None else corpus.unionByName(steps)), trace
        counted = counted.select("node", upto[rounds[-1]].alias("past"))
        corpus = steps if corpus is None else corpus.unionByName(steps)
    return corpus, trace


def walk_profile(steps: DataFrame, routine_length: int = 80, routine_rounds: int = 10) -> DataFrame:
    """Mean length, rounds, and how much shorter than the routine configuration."""
    per = steps.groupBy("round", "walk_id").agg(F.count("*").alias("length"))
    row = per.agg(F.avg("length").alias("mean_length"), F.max("length").alias("max_length"), F.max("round").alias("rounds"), F.count("*").alias("walks"))
    return row.withColumn("length_cut", 1 - F.col("mean_length") / routine_length).withColumn("round_cut", 1 - F.col("rounds") / routine_rounds)


def message_stats(steps: DataFrame, assign: DataFrame) -> DataFrame:
    """One row: hops, crossings, and bytes of both message forms (80 against 24 + 8 L)."""
    order = Window.partitionBy("round", "walk_id").orderBy("step")
    placed = steps.join(assign, "node").withColumn("from_part", F.lag("part").over(order))
    crosses = (F.col("from_part") != F.col("part")).cast("long")
    return placed.where("from_part is not null").agg(F.count("*").alias("hops"), F.sum(crosses).alias("crossings"), F.sum(crosses * 80).alias("bytes_incremental"), F.sum(crosses * (24 + 8 * F.col("step").cast("long"))).alias("bytes_fullpath"))

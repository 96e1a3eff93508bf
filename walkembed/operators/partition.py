"""Placing nodes on parts: streaming proximity, its orders and segments, and the baselines.

``stream``: (pos, seg, node, nbr, cm, w).  A placement inside a segment is
sequential by nature; segments are independent tasks (``applyInPandas``) that
receive their slice of the stream and hold only part sizes and a node -> part map.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.durable import durable
from . import graph as G


def hash_partition(nodes: DataFrame, m: int) -> DataFrame:
    return nodes.select("node", F.pmod(F.col("node"), F.lit(m)).cast("int").alias("part"))


def edge_balanced_partition(edges: DataFrame, m: int) -> DataFrame:
    """Consecutive ids with nearly equal sums of degrees: the routine engine's placement.

    Running sums are two-level (inside ranges of ids, then over ranges), so no
    single task sees all nodes.
    """
    deg = G.degrees(G.both_directions(edges)).withColumn("bucket", F.floor(F.col("node") / 65_536))
    inside = F.sum("deg").over(Window.partitionBy("bucket").orderBy("node"))
    sums = deg.groupBy("bucket").agg(F.sum("deg").alias("s"))
    before = sums.withColumn("before", F.sum("s").over(Window.orderBy("bucket")) - F.col("s"))
    total = deg.agg(F.sum("deg").alias("total"))
    ran = deg.withColumn("inside", inside).join(before.select("bucket", "before"), "bucket").crossJoin(total)
    part = F.least(F.floor((F.col("before") + F.col("inside") - F.col("deg")) * m / F.col("total")), F.lit(m - 1))
    return ran.select("node", part.cast("int").alias("part"))


def first_order_scores(edges2: DataFrame, assign: DataFrame, weighted: bool = False) -> DataFrame:
    """(node, part, score): neighbours (or their weight) that a part holds."""
    value = F.sum("w") if weighted else F.count("*").cast("double")
    return edges2.join(assign.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node"), "part").agg(value.alias("score"))


def second_order_scores(edges_cm: DataFrame, assign: DataFrame, scope: str = "neighbours", weighted: bool = False) -> DataFrame:
    """(node, part, score): common neighbours with the nodes that a part holds.

    ``neighbours`` counts placed neighbours only and reuses the edges' ``cm``: one
    triangle job serves the walk's weights and the partitioner.
    """
    if scope == "neighbours":
        edges2 = G.both_directions(edges_cm.select("src", "dst", F.struct("w", "cm").alias("w")))
        value = F.col("w.cm") * F.col("w.w") if weighted else F.col("w.cm")
        return edges2.select("u", "v", value.cast("double").alias("x")).join(assign.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node"), "part").agg(F.sum("x").alias("score"))
    edges2 = G.both_directions(edges_cm)
    two = edges2.alias("x").join(edges2.alias("y"), F.expr("x.v = y.u and x.u <> y.v")).select(F.col("x.u").alias("node"), F.col("y.v").alias("other"))
    return two.join(assign.withColumnRenamed("node", "other"), "other").groupBy("node", "part").agg(F.count("*").cast("double").alias("score"))


def balance_term(sizes: DataFrame, gamma: float) -> DataFrame:
    """(part, size, tau): 1 - size / (gamma * mean size); 1 when all parts are empty."""
    mean = F.avg("size").over(Window.partitionBy(F.lit(1)))
    return sizes.withColumn("tau", F.when(mean > 0, 1 - F.col("size") / (gamma * mean)).otherwise(F.lit(1.0)))


# --- orders -------------------------------------------------------------------


def _walk_order(adj: dict[int, list[int]], kind: str) -> list[int]:
    """Nodes in breadth or depth first order; roots by (degree desc, id), degree variants expand high degrees first."""
    by_degree = kind.endswith("degree")
    rank = lambda v: (-len(adj[v]), v)
    seen: set[int] = set()
    out: list[int] = []
    for root in sorted(adj, key=rank):
        if root in seen:
            continue
        if kind.startswith("bfs"):
            queue = [root]
            seen.add(root)
            for u in queue:
                out.append(u)
                for v in sorted(adj[u], key=rank) if by_degree else sorted(adj[u]):
                    if v not in seen:
                        seen.add(v)
                        queue.append(v)
        else:
            stack = [root]
            while stack:
                u = stack.pop()
                if u in seen:
                    continue
                seen.add(u)
                out.append(u)
                near = [v for v in adj[u] if v not in seen]
                stack.extend(sorted(near, key=rank, reverse=True) if by_degree else sorted(near, reverse=True))
    return out


def bfs_levels(edges2: DataFrame) -> DataFrame:
    """(node, level): distance from its component's root (highest degree, then smallest id), by frontier joins."""
    deg = G.degrees(edges2)
    label = deg.select("node", F.struct((-F.col("deg")).alias("nd"), F.col("node").alias("id")).alias("best"))
    while True:  # the best root of each component spreads by minimum
        near = edges2.join(label.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node")).agg(F.min("best").alias("other"))
        new = label.join(near, "node").select("node", F.least("best", "other").alias("best"), (F.col("other") < F.col("best")).alias("moved")).transform(durable)
        label = new.select("node", "best")
        if not new.where("moved").limit(1).count():
            break
    found = label.where("best.id = node").select("node", F.lit(0).alias("level")).transform(durable)
    frontier = found
    for k in count(1):
        near = edges2.join(frontier.withColumnRenamed("node", "u"), "u").select(F.col("v").alias("node")).distinct().join(found, "node", "left_anti").select("node", F.lit(k).alias("level")).transform(durable)
        if not near.limit(1).count():
            break
        found, frontier = found.unionByName(near), near
    return found


def stream_order(edges: DataFrame, kind: str = "dfs_degree", seed: int = 42) -> DataFrame:
    """(node, pos) in the order in which nodes are streamed.

    ``random`` is a sort by hash.  The others follow the graph: components are
    independent, so each is ordered in its own task, and components follow one
    another by their roots.
    """
    from ..functions.rng import draw_column

    edges2 = G.both_directions(edges)
    if kind == "random":
        nodes = edges2.select(F.col("u").alias("node")).distinct()
        return nodes.select("node", (F.row_number().over(Window.orderBy(draw_column(seed, F.col("node")), "node")) - 1).cast("long").alias("pos"))
    deg = G.degrees(edges2)
    label = deg.select("node", F.struct((-F.col("deg")).alias("nd"), F.col("node").alias("id")).alias("best"))
    while True:
        near = edges2.join(label.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node")).agg(F.min("best").alias("other"))
        new = label.join(near, "node").select("node", F.least("best", "other").alias("best"), (F.col("other") < F.col("best")).alias("moved")).transform(durable)
        label = new.select("node", "best")
        if not new.where("moved").limit(1).count():
            break

    def order(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        adj = {u: v.tolist() for u, v in rows.groupby("u")["v"]}
        nodes = _walk_order(adj, kind)
        return pd.DataFrame({"node": nodes, "nd": rows["nd"].iloc[0], "root": rows["root"].iloc[0], "at": range(len(nodes))})

    members = edges2.select("u", "v").join(label.select(F.col("node").alias("u"), F.col("best.nd").alias("nd"), F.col("best.id").alias("root")), "u")
    ordered = members.groupBy("root").applyInPandas(order, "node long, nd long, root long, at long").transform(durable)
    sizes = ordered.groupBy("root", "nd").agg(F.count("*").alias("n"))
    before = sizes.withColumn("before", F.sum("n").over(Window.orderBy("nd", "root")) - F.col("n"))
    return ordered.join(before.select("root", "before"), "root").select("node", (F.col("before") + F.col("at")).cast("long").alias("pos"))


# --- streaming placement ------------------------------------------------------

Score = Callable[[np.ndarray, np.ndarray, np.ndarray, int], np.ndarray]


def proximity_score(gamma: float) -> Score:
    """(first order + second order) times the balance term."""

    def score(first: np.ndarray, second: np.ndarray, sizes: np.ndarray, n_total: int) -> np.ndarray:
        placed = sizes.sum()
        tau = 1 - sizes * len(sizes) / (gamma * placed) if placed else np.ones(len(sizes))
        return (first + second) * tau

    return score


def ldg_score(capacity: float | None = None) -> Score:
    """Placed neighbours times the free share of a fixed capacity."""

    def score(first: np.ndarray, second: np.ndarray, sizes: np.ndarray, n_total: int) -> np.ndarray:
        return first * (1 - sizes / (capacity or max(1.0, n_total / len(sizes))))

    return score


def fennel_score(power: float = 1.5, n_edges: int = 0, slack: float = 1.1) -> Score:
    """Placed neighbours less a marginal cost of size; full parts are out."""

    def score(first: np.ndarray, second: np.ndarray, sizes: np.ndarray, n_total: int) -> np.ndarray:
        m = len(sizes)
        alpha = n_edges * m ** (power - 1) / max(1, n_total) ** power if n_edges else 1.0
        value = first - alpha * power * sizes ** (power - 1)
        return np.where(sizes >= slack * max(1.0, n_total / m), -np.inf, value)

    return score


def place_stream(stream: pd.DataFrame, m: int, score: Score, n_total: int, seed_parts: bool = False) -> pd.DataFrame:
    """One pass: each node goes to the best part; ties to the smaller part, then the smaller number."""
    rows = stream.sort_values("pos")
    nodes = rows["node"].to_numpy()
    begin = np.concatenate([[0], np.cumsum([len(x) for x in rows["nbr"]])]).astype(int)
    flat = lambda c: np.concatenate([*rows[c], np.empty(0)])
    w = flat("w")
    both = flat("cm") * w
    # neighbours as places in the stream; those of other segments are never placed here
    by = np.argsort(nodes)
    at = np.minimum(np.searchsorted(nodes[by], flat("nbr")), max(len(nodes) - 1, 0))
    near = np.where(nodes[by][at] == flat("nbr"), by[at], len(nodes)) if len(nodes) else np.empty(0, int)
    parts, sizes = np.full(len(nodes) + 1, m), np.zeros(m)
    for k in range(len(nodes)):
        own = slice(begin[k], begin[k + 1])
        where = parts[near[own]]
        first, second = (np.bincount(where, x[own], m + 1)[:m] for x in (w, both))
        value = np.round(score(first, second, sizes, n_total), 9)
        p = k if seed_parts and k < m else int(np.lexsort((np.arange(m), sizes, -value))[0])
        parts[k] = p
        sizes[p] += 1
    return pd.DataFrame({"node": nodes, "part": parts[:-1]})


def streamed_partition(edges_cm: DataFrame, m: int, order: DataFrame, score: Score, segments: int = 1, weighted: bool = False, seed_parts: bool = False, align: bool = False) -> DataFrame:
    """(node, part) of a one-pass placement over ``order``, in independent contiguous segments.

    Part i of every segment is part i of the whole; ``align`` instead gives each
    segment's parts the numbers of those parts of the first segment that most of
    their edges lead to.
    """
    weight = F.col("w") if weighted else F.lit(1.0)
    edges2 = G.both_directions(edges_cm.select("src", "dst", F.struct(weight.alias("x"), "cm").alias("w")))
    adj = G.adjacency(edges2.select("u", "v", F.col("w.cm").alias("cm"), F.col("w.x").alias("w")), "cm", "w")
    n = order.count()
    stream = adj.join(order, "node").withColumn("seg", F.floor(F.col("pos") * segments / F.lit(max(n, 1))).cast("int"))
    per = -(-n // segments)
    placed = stream.groupBy("seg").applyInPandas(lambda rows: place_stream(rows, m, score, per, seed_parts).assign(seg=rows["seg"].iloc[0]), "node long, part int, seg int")
    if not align or segments == 1:
        return placed.select("node", "part")
    placed = placed.transform(durable)
    ends = G.both_directions(edges_cm.select("src", "dst", "w")).join(placed.where("seg = 0").select(F.col("node").alias("v"), F.col("part").alias("goal")), "v")
    links = ends.join(placed.where("seg > 0").withColumnRenamed("node", "u"), "u").groupBy("seg", "part", "goal").agg(F.count("*").alias("n"))

    def number(rows: pd.DataFrame) -> pd.DataFrame:  # at most m * m rows a segment
        free, left, out = set(range(m)), set(range(m)), {}
        for _, part, goal in sorted(zip(-rows["n"], rows["part"], rows["goal"])):
            if part in left and goal in free:
                out[part] = goal
                left.remove(part), free.remove(goal)
        out |= dict(zip(sorted(left), sorted(free)))
        return pd.DataFrame({"seg": rows["seg"].iloc[0], "part": list(out), "goal": list(out.values())})

    names = links.groupBy("seg").applyInPandas(number, "seg int, part int, goal int")
    return placed.join(names, ["seg", "part"], "left").select("node", F.coalesce("goal", "part").alias("part"))


def proximity_partition(edges_cm: DataFrame, m: int = 4, gamma: float = 2.0, order: str = "dfs_degree", segments: int = 1, weighted: bool = False, seed_parts: bool = False) -> DataFrame:
    return streamed_partition(edges_cm, m, stream_order(edges_cm, order), proximity_score(gamma), segments, weighted, seed_parts)


def multilevel_partition(edges: DataFrame, m: int = 4, coarse: int = 200, slack: float = 1.1) -> DataFrame:
    """A simplified multilevel k-way: heavy-edge matching by rounds, greedy start, boundary refinement.

    Matching rounds are joins over all edges; the coarsest graph (bounded by
    ``coarse`` nodes or ten rounds) is placed in one task and projected back.
    """
    now = edges.select("src", "dst", "w").transform(durable)
    maps: list[DataFrame] = []
    for _ in range(10):
        e2 = G.both_directions(now)
        if e2.select("u").distinct().count() <= coarse:
            break
        best = e2.groupBy("u").agg(F.max(F.struct("w", F.expr("-hash(least(u, v), greatest(u, v))").alias("t"), "v")).alias("b")).select("u", F.col("b.v").alias("v"))
        mutual = best.alias("x").join(best.alias("y"), F.expr("x.v = y.u and x.u = y.v")).select(F.col("x.u").alias("node"), F.least(F.col("x.u"), F.col("x.v")).alias("super"))
        nodes = e2.select(F.col("u").alias("node")).distinct()
        level = nodes.join(mutual, "node", "left").select("node", F.coalesce("super", "node").alias("super")).transform(durable)
        maps.append(level)
        moved = now.join(level.select(F.col("node").alias("src"), F.col("super").alias("a")), "src").join(level.select(F.col("node").alias("dst"), F.col("super").alias("b")), "dst")
        now = G.normalize_edges(moved.select("a", "b", "w"), weighted=True).transform(durable)
    weight = None
    for level in maps:
        w = level if weight is None else level.join(weight, "node").select("node", "super", "k")
        weight = (w.withColumn("k", F.lit(1)) if weight is None else w).groupBy(F.col("super").alias("node")).agg(F.sum("k").alias("k")).transform(durable)
    top = G.adjacency(G.both_directions(now), "w")
    top = top.withColumn("k", F.lit(1)) if weight is None else top.join(weight, "node", "right").select("node", F.coalesce("nbr", F.array().cast("array<bigint>")).alias("nbr"), F.coalesce("w", F.array().cast("array<double>")).alias("w"), "k")

    def place(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("k", ascending=False)
        size, where = np.zeros(m), {}
        cap = slack * rows["k"].sum() / m
        adj = {n: list(zip(v.tolist(), w.tolist())) for n, v, w in zip(rows["node"], rows["nbr"], rows["w"])}
        mass = dict(zip(rows["node"], rows["k"]))
        for turn in range(4):
            for n in rows["node"]:
                gain = np.zeros(m)
                for v, w in adj[n]:
                    if v in where:
                        gain[where[v]] += w
                if turn:
                    size[where[n]] -= mass[n]
                gain[size + mass[n] > cap] = -1
                p = int(np.lexsort((size, -gain))[0])
                where[n] = p
                size[p] += mass[n]
        return pd.DataFrame({"node": list(where), "part": list(where.values())})

    assign = top.withColumn("all", F.lit(1)).groupBy("all").applyInPandas(lambda rows: place(rows), "node long, part int").transform(durable)
    for level in reversed(maps):
        assign = level.join(assign.withColumnRenamed("node", "super"), "super").select("node", "part")
    return assign


def partition_quality(edges: DataFrame, assign: DataFrame, m: int) -> DataFrame:
    """One row: cut edges and their share, and the imbalance of nodes and of degrees (largest over mean)."""
    both = edges.join(assign.select(F.col("node").alias("src"), F.col("part").alias("ps")), "src").join(assign.select(F.col("node").alias("dst"), F.col("part").alias("pd")), "dst")
    cut = both.agg(F.count("*").alias("edges"), F.sum((F.col("ps") != F.col("pd")).cast("long")).alias("cut"))
    sizes = assign.groupBy("part").agg(F.count("*").alias("n"))
    ends = both.select(F.explode(F.array("ps", "pd")).alias("part")).groupBy("part").agg(F.count("*").alias("d"))
    node_side = sizes.agg((F.max("n") * m / F.sum("n")).alias("node_imbalance"))
    edge_side = ends.agg((F.max("d") * m / F.sum("d")).alias("edge_imbalance"))
    return cut.crossJoin(node_side).crossJoin(edge_side).withColumn("cut_share", F.col("cut") / F.col("edges"))

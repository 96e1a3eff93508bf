"""The experiments as queries: comparisons, sweeps, scaling and quality, with SQL wherever walks can be replayed in it."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.parallel import together
from ..functions.rng import draw_sql
from ..operators import evaluate as E
from ..operators import graph as G
from ..operators import learner as L
from ..operators import measures as M
from ..operators import partition as P
from ..operators import walks as W
from ..sources import graphs as S
from . import pipelines
from .graph_queries import _RANKED, _UNI, CM, FENNEL, LDG, PROXIMITY, QUANT, SEED, all_nodes, biased_sql, burst, cdf_sql, edges_sql, graph, hybrid_sql, order_sql, place_sql, prep, uniform_corpus, walk_sql, with_
from .learn_queries import _VOCAB, centroid_predictions, phi

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def put(query: Query) -> Query:
        QUERIES[name] = query
        if oracle is not None:
            ORACLES[name] = oracle
        return query

    return put


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


# --- walks: thresholds and kernels --------------------------------------------

MUS = (0.995, 0.95, 0.9, 0.85, 0.8)


def stopped(measured: DataFrame, mu: float, least: int = 3) -> DataFrame:
    """One row (mean_length, longest): where walks of the measured prefixes stop under ``mu``."""
    last = F.coalesce(F.min(F.when((F.col("step") >= least) & (F.col("r2") < mu), F.col("step"))), F.max("step"))
    return measured.groupBy("round", "walk_id").agg(last.alias("length")).agg(F.round(F.avg("length"), 6).alias("mean_length"), F.max("length").cast("int").alias("longest"))


def sweep_mu(spark: SparkSession, d: str) -> DataFrame:
    """(mu, mean_length, longest): one corpus of 80-node walks, cut where each threshold stops."""
    measured = M.prefix_measures(burst(spark, d, "knn", W.Kernel("hybrid"), W.Stop.fixed(80))).transform(durable)
    return union([stopped(measured, mu).select(F.lit(mu).alias("mu"), "mean_length", "longest") for mu in MUS])


def _cut_sql(mu: str) -> str:
    return f"SELECT walk_id, coalesce(min(step) FILTER (WHERE step >= 3 AND r2 < {mu}), max(step)) AS length FROM measured GROUP BY walk_id"


_HYBRID80 = walk_sql("knn", QUANT, "hyb", 80, hybrid_sql()) + "," + M.PREFIX_SQL
add("sweep_mu", _HYBRID80 + " " + " UNION ALL ".join(f"SELECT {mu}::DOUBLE AS mu, round(avg(length), 6) AS mean_length, max(length)::INTEGER AS longest FROM ({_cut_sql(f'{mu}::DOUBLE')})" for mu in MUS))(sweep_mu)

KERNELS = {"uniform": W.Kernel("uniform"), "biased2": W.Kernel("biased2", p=0.5, q=2.0), "hybrid": W.Kernel("hybrid"), "hybrid_plus": W.Kernel("hybrid_plus")}


def generality(spark: SparkSession, d: str) -> DataFrame:
    """(kernel, mean_length, longest, length_cut): the information stop on every kernel against routine walks of 80 nodes."""
    rows = []
    edges = graph(spark, d, "knn").transform(durable)
    for name, kernel in KERNELS.items():
        measured = M.prefix_measures(burst(spark, d, "knn", kernel, W.Stop.fixed(80), edges=edges)).transform(durable)
        rows.append(stopped(measured, 0.85).select(F.lit(name).alias("kernel"), "mean_length", "longest", F.round(1 - F.col("mean_length") / 80, 6).alias("length_cut")))
    return union(rows)


_KERNEL_SQL = {
    "uniform": walk_sql("knn", "1", "edges2", 80),
    "biased2": biased_sql(80),
    "hybrid": walk_sql("knn", QUANT, "hyb", 80, hybrid_sql()),
    "hybrid_plus": walk_sql("knn", QUANT, "hyb", 80, hybrid_sql(plus=True)),
}
add("generality", " UNION ALL ".join(f"SELECT '{k}' AS kernel, round(avg(length), 6) AS mean_length, max(length)::INTEGER AS longest, round(1 - round(avg(length), 6) / 80, 6) AS length_cut FROM ({q}, {M.PREFIX_SQL} {_cut_sql('0.85::DOUBLE')})" for k, q in _KERNEL_SQL.items()))(generality)

DELTAS = (0.1, 0.01, 0.001)


def sweep_delta(spark: SparkSession, d: str) -> DataFrame:
    """(delta, rounds): after how many of five rounds the divergence has settled."""
    edges, steps = uniform_corpus(spark, d)
    trace = M.corpus_divergence(G.degrees(G.both_directions(edges)), steps).transform(durable)
    return union([trace.agg(F.coalesce(F.min(F.when(F.col("change") <= x, F.col("round"))), F.max("round")).cast("int").alias("rounds")).select(F.lit(x).alias("delta"), "rounds") for x in DELTAS])


_TRACE = _UNI + """, per AS (SELECT round, node, count(*) AS n FROM steps GROUP BY 1, 2),
ocn AS (SELECT r.round, p.node, sum(p.n)::DOUBLE AS ocn FROM (SELECT DISTINCT round FROM steps) r JOIN per p ON p.round <= r.round GROUP BY 1, 2),
d AS (SELECT o.round, sum(g.deg::DOUBLE / t.s * log2(g.deg::DOUBLE / t.s * a.s / o.ocn)) AS d FROM ocn o JOIN deg g ON g.node = o.node, (SELECT sum(deg)::DOUBLE AS s FROM deg) t, (SELECT round, sum(ocn) AS s FROM ocn GROUP BY 1) a WHERE a.round = o.round GROUP BY 1),
moved AS (SELECT round, abs(d - lag(d) OVER (ORDER BY round)) AS change FROM d)"""
add("sweep_delta", _TRACE + " " + " UNION ALL ".join(f"SELECT {x}::DOUBLE AS delta, coalesce(min(round) FILTER (WHERE change <= {x}), max(round))::INTEGER AS rounds FROM moved" for x in DELTAS))(sweep_delta)


def sweep_windows(spark: SparkSession, d: str) -> DataFrame:
    """(n_windows, batches, widest): batches that the learner forms when walks go n at a time."""
    steps = uniform_corpus(spark, d, 1)[1]
    numbered = steps.withColumn("i", F.dense_rank().over(W.Window.partitionBy("round").orderBy("walk_id")) - 1)
    return union([numbered.groupBy(F.floor(F.col("i") / n).alias("g"), "step").agg(F.count("*").alias("k")).agg(F.count("*").alias("batches"), F.max("k").alias("widest")).select(F.lit(n).alias("n_windows"), "batches", "widest") for n in (1, 2, 4, 16)])


add("sweep_n_windows", walk_sql("knn", "1", "edges2", 10) + ", numbered AS (SELECT *, dense_rank() OVER (ORDER BY walk_id) - 1 AS i FROM steps) " + " UNION ALL ".join(f"SELECT {n} AS n_windows, count(*) AS batches, max(k) AS widest FROM (SELECT i // {n} AS g, step, count(*) AS k FROM numbered GROUP BY 1, 2)" for n in (1, 2, 4, 16)))(sweep_windows)

# --- partitions ---------------------------------------------------------------


def schemes(edges: DataFrame, m: int = 4) -> dict[str, DataFrame]:
    """Every placement of a graph on m parts; streams in random order."""
    cm = G.common_neighbours(edges).transform(durable)
    order = P.stream_order(cm, "random", SEED).transform(durable)
    placed = lambda score, segments=1: P.streamed_partition(cm, m, order, score, segments)
    return {
        "hash": P.hash_partition(all_nodes(edges), m),
        "edge_balanced": P.edge_balanced_partition(edges, m),
        "proximity": placed(P.proximity_score(2.0)),
        "proximity_seg": placed(P.proximity_score(2.0), 4),
        "ldg": placed(P.ldg_score()),
        "fennel": placed(P.fennel_score(n_edges=edges.count())),
    }


def partition_compare(spark: SparkSession, d: str) -> DataFrame:
    """(scheme, hops, crossings, largest): messages of the same walks, and the largest part, under each placement."""
    edges, steps = uniform_corpus(spark, d, 1)
    rows = []
    for name, assign in schemes(edges).items():
        assign = assign.transform(durable)
        size = assign.groupBy("part").agg(F.count("*").alias("n")).agg(F.max("n").alias("largest"))
        rows.append(W.message_stats(steps, assign).crossJoin(size).select(F.lit(name).alias("scheme"), "hops", "crossings", "largest"))
    return union(rows)


_SCHEMES = {
    "hash": with_(prep("knn")) + "SELECT node, (node % 4)::INTEGER AS part FROM deg",
    "edge_balanced": with_(prep("knn")) + "SELECT node, least(floor((sum(deg) OVER (ORDER BY node) - deg) * 4 / (SELECT sum(deg) FROM deg)), 3)::INTEGER AS part FROM deg",
    "proximity": place_sql("knn", PROXIMITY),
    "proximity_seg": place_sql("knn", PROXIMITY, 4),
    "ldg": place_sql("knn", LDG),
    "fennel": place_sql("knn", FENNEL),
}
_PLACED = " UNION ALL ".join(f"SELECT '{k}' AS scheme, node, part FROM ({q})" for k, q in _SCHEMES.items())
add(
    "partition_compare",
    walk_sql("knn", "1", "edges2", 10) + f""", placed AS MATERIALIZED ({_PLACED}),
hop AS (SELECT scheme, part, lag(part) OVER (PARTITION BY scheme, walk_id ORDER BY step) AS from_part FROM steps JOIN placed USING (node)),
sent AS (SELECT scheme, count(*) AS hops, count(*) FILTER (WHERE part <> from_part) AS crossings FROM hop WHERE from_part IS NOT NULL GROUP BY 1),
size AS (SELECT scheme, max(n) AS largest FROM (SELECT scheme, part, count(*) AS n FROM placed GROUP BY 1, 2) GROUP BY 1)
SELECT scheme, hops, crossings, largest FROM sent JOIN size USING (scheme)""",
)(partition_compare)


def locality(spark: SparkSession, d: str) -> DataFrame:
    """(scheme, part, local, crossing): where each part's hops come from, for two placements of the forest."""
    edges = graph(spark, d, "geo").transform(durable)
    steps = W.step_walks(edges, all_nodes(edges), W.Kernel("uniform"), 6, seed=SEED).transform(durable)
    rows = []
    for name, assign in (("edge_balanced", P.edge_balanced_partition(edges, 4)), ("proximity", P.proximity_partition(G.common_neighbours(edges).transform(durable), 4, order="bfs_degree"))):
        placed = steps.join(assign.transform(durable), "node").withColumn("from_part", F.lag("part").over(W.Window.partitionBy("round", "walk_id").orderBy("step"))).where("from_part is not null")
        rows.append(placed.groupBy("part").agg(F.sum((F.col("part") == F.col("from_part")).cast("long")).alias("local"), F.sum((F.col("part") != F.col("from_part")).cast("long")).alias("crossing")).select(F.lit(name).alias("scheme"), "part", "local", "crossing"))
    return union(rows)


_BALANCED_GEO = with_(prep("geo")) + "SELECT node, least(floor((sum(deg) OVER (ORDER BY node) - deg) * 4 / (SELECT sum(deg) FROM deg)), 3)::INTEGER AS part FROM deg"
add(
    "partition_locality",
    walk_sql("geo", "1", "edges2", 6) + f""", placed AS MATERIALIZED (SELECT 'edge_balanced' AS scheme, node, part FROM ({_BALANCED_GEO}) UNION ALL SELECT 'proximity', node, part FROM ({place_sql("geo", PROXIMITY, 1, _RANKED("bfs"))})),
hop AS (SELECT scheme, part, lag(part) OVER (PARTITION BY scheme, walk_id ORDER BY step) AS from_part FROM steps JOIN placed USING (node))
SELECT scheme, part, count(*) FILTER (WHERE part = from_part) AS local, count(*) FILTER (WHERE part <> from_part) AS crossing FROM hop WHERE from_part IS NOT NULL GROUP BY 1, 2""",
)(locality)


def _cuts(edges: DataFrame, assigns: dict[object, DataFrame], name: str, m: int = 4) -> DataFrame:
    return union([P.partition_quality(edges, a.transform(durable), m).select(F.lit(k).alias(name), "cut", F.round("node_imbalance", 6).alias("node_imbalance")) for k, a in assigns.items()])


def _cuts_sql(graph_name: str, placed: dict[object, str], name: str) -> str:
    rows = " UNION ALL ".join(f"SELECT {k!r} AS k, node, part FROM ({q})" for k, q in placed.items())
    return f"""WITH edges AS ({edges_sql(graph_name)}), placed AS MATERIALIZED ({rows}),
cuts AS (SELECT a.k, count(*) FILTER (WHERE a.part <> b.part) AS cut FROM edges e JOIN placed a ON a.node = e.src JOIN placed b ON b.node = e.dst AND b.k = a.k GROUP BY 1),
size AS (SELECT k, max(n) * 4.0::DOUBLE / sum(n) AS x FROM (SELECT k, part, count(*) AS n FROM placed GROUP BY 1, 2) GROUP BY 1)
SELECT k AS {name}, cut, round(x, 6) AS node_imbalance FROM cuts JOIN size USING (k)"""


ORDERS = ("random", "bfs", "bfs_degree", "dfs", "dfs_degree")


def order_compare(spark: SparkSession, d: str) -> DataFrame:
    """(stream, cut, node_imbalance): the sequential placement of the forest under every stream order."""
    edges = G.common_neighbours(graph(spark, d, "geo")).transform(durable)
    return _cuts(edges, {k: P.streamed_partition(edges, 4, P.stream_order(edges, k, SEED), P.proximity_score(2.0)) for k in ORDERS}, "stream")


def _ordered(kind: str) -> str:
    ranked = order_sql(kind).split("SELECT down.node", 1)
    trees = ranked[0].split(prep("geo") + ", ", 1)[1]
    return f"{trees.rstrip()}, ranked AS (SELECT down.node{ranked[1]})"


add("order_compare", _cuts_sql("geo", {k: place_sql("geo", PROXIMITY, 1, None if k == "random" else _ordered(k)) for k in ORDERS}, "stream"))(order_compare)


def segment_compare(spark: SparkSession, d: str) -> DataFrame:
    """(segments, cut, node_imbalance): what cutting the stream in independent segments costs."""
    edges = G.common_neighbours(graph(spark, d, "geo")).transform(durable)
    order = P.stream_order(edges, "bfs_degree").transform(durable)
    return _cuts(edges, {k: P.streamed_partition(edges, 4, order, P.proximity_score(2.0), k) for k in (1, 2, 4, 8)}, "segments")


add("segment_compare", _cuts_sql("geo", {k: place_sql("geo", PROXIMITY, k, _RANKED("bfs")) for k in (1, 2, 4, 8)}, "segments"))(segment_compare)

GAMMAS = (1.0, 1.5, 2.0, 4.0)


def sweep_gamma(spark: SparkSession, d: str) -> DataFrame:
    """(gamma, cut, node_imbalance): the slack of the balance term."""
    edges = G.common_neighbours(graph(spark, d, "knn")).transform(durable)
    order = P.stream_order(edges, "random", SEED).transform(durable)
    return _cuts(edges, {g: P.streamed_partition(edges, 4, order, P.proximity_score(g)) for g in GAMMAS}, "gamma")


add("sweep_gamma", _cuts_sql("knn", {g: place_sql("knn", PROXIMITY.replace("2.0::DOUBLE", f"{g}::DOUBLE")) for g in GAMMAS}, "gamma").replace("SELECT k AS gamma", "SELECT k::DOUBLE AS gamma"))(sweep_gamma)


def scaling_parts(spark: SparkSession, d: str) -> DataFrame:
    """(parts, hops, crossings, busiest, speed_up): the same walks over 1, 2, 4 and 8 parts; the busiest part bounds the speed-up."""
    edges, steps = uniform_corpus(spark, d, 1)
    rows = []
    for m in (1, 2, 4, 8):
        assign = P.hash_partition(all_nodes(edges), m)
        load = steps.join(assign, "node").groupBy("part").agg(F.count("*").alias("n")).agg(F.max("n").alias("busiest"), F.sum("n").alias("all"))
        rows.append(W.message_stats(steps, assign).crossJoin(load).select(F.lit(m).alias("parts"), "hops", "crossings", "busiest", F.round(F.col("all") / F.col("busiest"), 6).alias("speed_up")))
    return union(rows)


add(
    "scaling_parts",
    walk_sql("knn", "1", "edges2", 10) + ", hop AS (SELECT m, node % m AS part, lag(node % m) OVER (PARTITION BY m, walk_id ORDER BY step) AS from_part FROM steps, (VALUES (1), (2), (4), (8)) t(m)), load AS (SELECT m, max(n) AS busiest, sum(n) AS total FROM (SELECT m, part, count(*) AS n FROM hop GROUP BY 1, 2) GROUP BY 1) SELECT m AS parts, count(from_part) AS hops, count(*) FILTER (WHERE part <> from_part) AS crossings, any_value(busiest) AS busiest, round(any_value(total)::DOUBLE / any_value(busiest), 6) AS speed_up FROM hop JOIN load USING (m) GROUP BY m",
)(scaling_parts)

SIZES = (1_000, 10_000, 100_000)
add(
    "synthetic_scaling",
    " UNION ALL ".join(f"SELECT {n} AS n, count(*) AS edges, round(2.0::DOUBLE * count(*) / {n}, 6) AS mean_degree FROM (SELECT DISTINCT least(i, (i + j*j + j) % {n}) AS a, greatest(i, (i + j*j + j) % {n}) AS b FROM range({n}) t(i), range(1, 6) u(j) WHERE i <> (i + j*j + j) % {n})" for n in SIZES),
)(lambda spark, d: union([G.normalize_edges(S.synthetic_pairs(spark, n)).agg(F.count("*").alias("edges")).select(F.lit(n).alias("n"), "edges", F.round(2 * F.col("edges") / n, 6).alias("mean_degree")) for n in SIZES]))


def memory_profile(spark: SparkSession, d: str) -> DataFrame:
    """One row (parts, mean_bytes, sd_bytes): adjacency and walkers a part holds, over eight parts."""
    deg = G.degrees(G.both_directions(graph(spark, d, "tri")))
    part = deg.groupBy(F.pmod("node", F.lit(8)).alias("part")).agg((F.sum("deg") * 24 + F.count("*") * 80).alias("bytes"))
    return part.agg(F.count("*").alias("parts"), F.round(F.avg("bytes"), 4).alias("mean_bytes"), F.round(F.stddev_pop("bytes"), 4).alias("sd_bytes"))


add("memory_profile", with_(prep("tri"), "p AS (SELECT node % 8 AS part, (sum(deg) * 24 + count(*) * 80)::BIGINT AS bytes FROM deg GROUP BY 1)") + "SELECT count(*) AS parts, round(avg(bytes), 4) AS mean_bytes, round(stddev_pop(bytes), 4) AS sd_bytes FROM p")(memory_profile)
add("param_count", f"{_UNI}, {_VOCAB} SELECT 2 * count(*) * 128 AS params FROM vocab")(lambda spark, d: L.param_count(L.build_vocab(uniform_corpus(spark, d)[1]), 128))

# --- quality ------------------------------------------------------------------

SYSTEMS = ("info", "fullpath", "routine", "relational", "gnn")
_SMALL = {"dims": 32, "max_rounds": 10, "epochs": 5}
for _system in SYSTEMS:
    # three splits each; the walk baselines sample all of their rounds
    add(f"linkpred_system_{_system}")(lambda spark, d, s=_system: pipelines.repeated(graph(spark, d, "knn").transform(durable), s, 3, **(_SMALL if s in pipelines.PROFILES else {"dims": 32})).select("profile", "trials", F.round("mean_auc", 6).alias("mean_auc"), F.round("sd_auc", 6).alias("sd_auc")))


def auc_repeats(spark: SparkSession, d: str, trials: int = 10) -> DataFrame:
    """One row (trials, mean_auc, sd_auc) of fixed vectors over splits and negatives of ten seeds."""
    edges = graph(spark, d, "knn").transform(durable)
    nodes = all_nodes(edges).transform(durable)
    rows = [E.auc(E.score_pairs(E.split_edges(edges, 0.5, 100 + t).where("held"), E.balanced_negatives(E.split_edges(edges, 0.5, 100 + t).where("held"), edges, nodes, 100 + t), phi(spark, d)).select(F.round("score", 6).alias("score"), "y")) for t in range(trials)]
    return union(rows).agg(F.count("*").alias("trials"), F.round(F.avg("auc"), 6).alias("mean_auc"), F.round(F.stddev_pop("auc"), 6).alias("sd_auc"))


def _auc_trial(t: int) -> str:
    s = 100 + t
    at = lambda salt: f"({draw_sql(s, 'src', 'dst', 'k', str(salt))} * (SELECT count(*) FROM deg)) >> 32"
    return f"""(WITH {prep("knn")}, held AS (SELECT src, dst FROM edges WHERE {draw_sql(s, 'src', 'dst')} < {1 << 31}),
numbered AS (SELECT node, row_number() OVER (ORDER BY node) - 1 AS i FROM deg), tried AS (SELECT {at(1)} AS i, {at(2)} AS j FROM edges, range(1, 5) t(k)),
named AS (SELECT DISTINCT least(a.node, b.node) AS src, greatest(a.node, b.node) AS dst FROM tried JOIN numbered a ON a.i = tried.i JOIN numbered b ON b.i = tried.j WHERE a.node <> b.node),
negatives AS (SELECT n.* FROM named n ANTI JOIN edges e ON e.src = n.src AND e.dst = n.dst ORDER BY {draw_sql(s, 'n.src', 'n.dst')}, n.src, n.dst LIMIT (SELECT count(*) FROM held)),
pairs AS (SELECT src, dst, 1 AS y FROM held UNION ALL SELECT src, dst, 0 FROM negatives), phi AS (SELECT vec_id + 10000000000000 AS node, embedding::DOUBLE[] AS phi FROM embeddings),
scored AS (SELECT round(list_dot_product(a.phi, b.phi), 6) AS score, y FROM pairs JOIN phi a ON a.node = src JOIN phi b ON b.node = dst),
ranked AS (SELECT y, (rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0::DOUBLE) AS r FROM scored)
SELECT (sum(r * y) - sum(y) * (sum(y) + 1) / 2.0::DOUBLE) / (sum(y) * sum(1 - y)::DOUBLE) AS auc FROM ranked)"""


add("linkpred_auc_repeats", "SELECT count(*) AS trials, round(avg(auc), 6) AS mean_auc, round(stddev_pop(auc), 6) AS sd_auc FROM (" + " UNION ALL ".join(_auc_trial(t) for t in range(10)) + ")")(auc_repeats)


def parted(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(kept, nodes, held, negatives): the kept half of the edges with its nodes, and the pairs to tell apart."""
    split = E.split_edges(graph(spark, d, "knn"), 0.5, SEED).transform(durable)
    kept, held = (split.where(c).select("src", "dst", "w") for c in ("not held", "held"))
    nodes = all_nodes(kept).transform(durable)
    known = held.join(nodes.withColumnRenamed("node", "src"), "src", "left_semi").join(nodes.withColumnRenamed("node", "dst"), "dst", "left_semi").transform(durable)
    return kept, nodes, known, E.balanced_negatives(known, split, nodes, SEED).transform(durable)


def walked(kept: DataFrame, nodes: DataFrame, kernel: W.Kernel, stop: W.Stop, rounds: int = 3) -> DataFrame:
    """The corpus of some rounds."""
    table = W.kernel_edges(kept, kernel).transform(durable)
    assign = P.hash_partition(nodes, W.parts_for(kept))
    return W.corpus_round(table, assign, nodes, kernel, stop, tuple(range(1, rounds + 1)), SEED).select("round", "walk_id", "step", "node").transform(durable)


def learned_auc(held: DataFrame, negatives: DataFrame, steps: DataFrame, epochs: tuple[int, ...] = (3,), mode: str = "multi_window", **settings) -> list[float]:
    """AUC after each number of epochs."""
    vectors = L.train_upto(steps, epochs, mode, **{"dims": 32, "shards": 2, **settings})
    return [float(E.auc(E.score_pairs(held, negatives, v.select("node", "phi"))).first()["auc"]) for v in vectors]


def auc_ratios(spark: SparkSession, d: str) -> DataFrame:
    """(kernel, auc_info, auc_routine, ratio): link prediction after information-stopped against routine walks."""
    kept, nodes, held, negatives = parted(spark, d)
    names, stops = ("uniform", "biased2", "hybrid"), (W.Stop.calibrated(), W.Stop.fixed(80))
    found = together(lambda c: learned_auc(held, negatives, walked(kept, nodes, KERNELS[c[0]], c[1]))[0], [(name, s) for s in stops for name in names])
    rows = [(name, info, routine, info / routine) for name, info, routine in zip(names, found[:3], found[3:])]
    return spark.createDataFrame(rows, "kernel string, auc_info double, auc_routine double, ratio double")


add("auc_ratio")(auc_ratios)


def auc_curve(spark: SparkSession, d: str) -> DataFrame:
    """(epochs, auc): quality as training goes on."""
    kept, nodes, held, negatives = parted(spark, d)
    steps, epochs = walked(kept, nodes, KERNELS["hybrid"], W.Stop.calibrated()), (1, 3, 6)
    return spark.createDataFrame(list(zip(epochs, learned_auc(held, negatives, steps, epochs))), "epochs int, auc double")


add("auc_curve")(auc_curve)


def grid_search(spark: SparkSession, d: str) -> DataFrame:
    """(rate, dims, auc) over a grid of learning rates and dimensions."""
    kept, nodes, held, negatives = parted(spark, d)
    steps = walked(kept, nodes, KERNELS["hybrid"], W.Stop.calibrated(), rounds=2)
    rows = together(lambda c: (*c, learned_auc(held, negatives, steps, (2,), rate=c[0], dims=c[1])[0]), [(rate, dims) for rate in (0.01, 0.05, 0.1) for dims in (16, 64)])
    return spark.createDataFrame(rows, "rate double, dims int, auc double")


add("grid_search")(grid_search)
RATIOS = (0.01, 0.03, 0.05, 0.07, 0.09, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9)


def learned_classes(spark: SparkSession, d: str) -> DataFrame:
    """(ratio, micro_f1, macro_f1): labels of vectors learned from walks, from 1 % to 90 % of them known."""
    from ..operators.baselines import nearest_class
    from ..sources.tables import table

    edges = graph(spark, d, "knn").transform(durable)
    steps = walked(edges, all_nodes(edges).transform(durable), KERNELS["hybrid"], W.Stop.calibrated())
    vectors = L.train(steps, dims=32, shards=2, epochs=3).select("node", "phi").transform(durable)
    labels = table(spark, d, "embeddings").select((F.col("vec_id") + 10 * 10**12).alias("node"), "label")
    return union([nearest_class(vectors, labels, r, SEED) for r in RATIOS])


add("nodeclass_learned")(learned_classes)


def sync_periods(spark: SparkSession, d: str) -> DataFrame:
    """(period, ocn, node): what three periods synchronise, another draw of every block each."""
    vocab = L.build_vocab(uniform_corpus(spark, d)[1]).transform(durable)
    return union([L.sync_nodes(vocab, p).select(F.lit(p).alias("period"), "ocn", "node") for p in (1, 2, 3)])


add("hotness_sync_periods", f"{_UNI}, {_VOCAB} SELECT p::INTEGER AS period, ocn, arg_min(node, {draw_sql(SEED, 'p', 'node')} * 100000 + rank % 100000) AS node FROM vocab, range(1, 4) t(p) GROUP BY p, ocn")(sync_periods)

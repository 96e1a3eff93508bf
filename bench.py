"""Times the headline queries once each at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join(x for x in (ROOT, os.environ.get("PYTHONPATH", "")) if x)


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from walkembed.functions.durable import durable
    from walkembed.operators import graph as G
    from walkembed.operators import learner as L
    from walkembed.operators import partition as P
    from walkembed.operators import walks as W
    from walkembed.plans import graph_queries as Q

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries: dict[str, float] = {}
    notes: dict[str, float] = {}

    def timed(name, run):
        began = time.time()
        out = run()
        queries[name] = round(time.time() - began, 3)
        print(name, queries[name], file=sys.stderr)
        return out

    edges = timed("graph_tri", lambda: durable(Q.graph(spark, sf_dir, "tri")))
    cm = timed("common_neighbours", lambda: durable(G.common_neighbours(edges)))
    nodes = durable(Q.all_nodes(edges))
    hybrid, second = W.Kernel("hybrid"), W.Kernel("uniform")
    table = timed("hybrid_table", lambda: durable(W.kernel_edges(cm, hybrid)))
    flat = durable(W.kernel_edges(edges, second))
    one = P.hash_partition(nodes, 1)  # the graph fits a task
    info = timed("walk_info_round", lambda: durable(W.burst_round(table, one, nodes, hybrid, W.Stop.calibrated())))
    timed("walk_routine_round", lambda: durable(W.burst_round(flat, one, nodes, second, W.Stop.fixed(80))))
    notes["routine_over_info"] = round(queries["walk_routine_round"] / queries["walk_info_round"], 3)
    notes["mean_length_info"] = round(W.walk_profile(info).first()["mean_length"], 3)
    geo = durable(G.common_neighbours(Q.graph(spark, sf_dir, "geo")))
    order = durable(P.stream_order(geo, "bfs_degree"))
    placed = timed("partition_proximity_geo", lambda: durable(P.streamed_partition(geo, 4, order, P.proximity_score(2.0), 4)))
    routine = timed("partition_edge_balanced_geo", lambda: durable(P.edge_balanced_partition(geo, 4)))
    notes["cut_proximity"] = round(P.partition_quality(geo, placed, 4).first()["cut_share"], 4)
    notes["cut_edge_balanced"] = round(P.partition_quality(geo, routine, 4).first()["cut_share"], 4)
    knn = durable(Q.graph(spark, sf_dir, "knn"))
    corpus = durable(W.burst_round(W.kernel_edges(knn, second), P.hash_partition(Q.all_nodes(knn), 1), Q.all_nodes(knn), second, W.Stop.fixed(20), (1, 2)).select("round", "walk_id", "step", "node"))
    tokens = corpus.count()
    for mode, n in (("window_shared", 1), ("multi_window", 2), ("multi_window", 16)):
        name = f"train_{mode}" + (f"_{n}" if mode == "multi_window" else "")
        timed(name, lambda: L.train(corpus, mode, dims=64, shards=4, n_windows=n, periods=1).agg(F.count("*")).first())
        notes[f"{name}_tokens_per_s"] = round(tokens / queries[name])
    print(json.dumps({"metric": "walkembed headline queries", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1], "notes": notes}))


if __name__ == "__main__":
    main()

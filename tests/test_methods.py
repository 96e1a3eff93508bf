"""Identities, invariants and closed forms of the methods."""

import math
import re

import numpy as np
import pandas as pd
import pytest

from walkembed.operators import evaluate as E
from walkembed.operators import graph as G
from walkembed.operators import learner as L
from walkembed.operators import measures as M
from walkembed.operators import partition as P
from walkembed.operators import walks as W

K5 = [(a, b) for a in range(1, 6) for b in range(a + 1, 6)]


def edges(spark, pairs, **kw):
    return G.normalize_edges(spark.createDataFrame(pairs, "a long, b long"), **kw)


def test_normalise_drops_loops_and_merges(spark):
    got = {tuple(r) for r in edges(spark, [(1, 2), (2, 1), (3, 3), (2, 3), (None, 1)]).collect()}
    assert got == {(1, 2, 2.0), (2, 3, 1.0)}
    assert edges(spark, []).count() == 0


@pytest.mark.parametrize("method", ["wedge", "intersect", "gallop"])
def test_common_neighbours_of_complete_graph(spark, method):
    assert {r["cm"] for r in G.common_neighbours(edges(spark, K5), method).collect()} == {3}


def test_hybrid_of_complete_graph(spark):
    rows = G.hybrid_weight(G.common_neighbours(edges(spark, K5))).collect()
    assert len(rows) == 20 and all(abs(r["p_accept"] - math.tanh(1.0)) < 1e-12 for r in rows)


def random_path(rng, n=60, v=12):
    return rng.integers(0, v, n).tolist()


def test_entropy_update_and_r2_match_direct():
    rng = np.random.default_rng(1)
    for _ in range(20):
        path = random_path(rng)
        w = W.start_walkers(np.array([path[0]]), 1)
        counts = W.Counts()
        counts.add(w["walk_id"], np.array([path[0]]))
        hs = [0.0]
        for i, v in enumerate(path[1:], 2):
            M_before = counts.add(w["walk_id"], np.array([v]))
            W.measure_many(w, M_before)
            h = M.path_entropy(path[:i])
            hs.append(h)
            assert abs(w["H"][0] - h) < 1e-9 and 0 <= h <= math.log2(i) + 1e-9
            r2 = M.r_squared_many(*(w[c] for c in ("EH", "EL", "EHL", "EH2", "EL2")))[0]
            if np.std(hs) > 1e-9:
                assert abs(r2 - np.corrcoef(hs, range(1, i + 1))[0, 1] ** 2) < 1e-7


@pytest.mark.parametrize("length,expected", [(3, 0.9777), (4, 0.9608), (5, 0.9473), (6, 0.9363), (10, 0.9057), (12, 0.8951)])
def test_r2_of_distinct_prefixes(length, expected):
    h = [math.log2(i) for i in range(1, length + 1)]
    assert abs(np.corrcoef(h, range(1, length + 1))[0, 1] ** 2 - expected) < 1e-4


def test_long_walk_stays_finite():
    h, n = np.array([7.6]), np.array([3.0])
    assert np.isfinite(M.entropy_step_many(h, np.array([2000.0]), n))[0]


def test_printed_recurrence_vanishes(spark):
    steps = spark.createDataFrame([(1, 1, i, i % 4) for i in range(1, 31)], "round int, walk_id long, step int, node long")
    rows = M.prefix_measures(steps).collect()
    assert all(r["r2_as_printed"] == 0 for r in rows) and any(r["r2"] > 0.1 for r in rows)


def ring(n=30):
    return [(i, (i + k) % n) for i in range(n) for k in (1, 2, 3)]


@pytest.mark.parametrize("kernel", [W.Kernel("uniform"), W.Kernel("hybrid"), W.Kernel("hybrid", "accept")])
def test_engines_agree_hop_by_hop(spark, kernel):
    e = edges(spark, ring())
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    table = W.kernel_edges(e, kernel)
    local = W.local_walks(table.toPandas(), np.arange(30), kernel, W.Stop.fixed(5))
    burst = W.burst_round(table, P.hash_partition(nodes, 3), nodes, kernel, W.Stop.fixed(5), rng="portable").select("walk_id", "step", "node").collect()
    key = lambda rows: sorted(tuple(int(x) for x in r) for r in rows)
    assert key(burst) == key(local[["walk_id", "step", "node"]].itertuples(index=False))
    if kernel.method == "direct":
        step = W.step_walks(e, nodes, kernel, 5).select("walk_id", "step", "node").collect()
        assert key(step) == key(burst)
    linked = {(r["src"], r["dst"]) for r in e.collect()}
    for _, g in local.groupby("walk_id"):
        path = g.sort_values("step")["node"].tolist()
        assert len(path) == 5 and all((min(a, b), max(a, b)) in linked for a, b in zip(path, path[1:]))


def test_accept_and_direct_follow_one_law(spark):
    star = [(0, i) for i in range(1, 6)] + [(1, 2), (2, 3)]
    e = edges(spark, star)
    table = W.kernel_edges(e, W.Kernel("hybrid")).toPandas()
    counts = []
    for method in ("direct", "accept"):
        block = W.Block.of(table)
        w = W.start_walkers(np.zeros(40_000, dtype=np.int64), 1)
        w["walk_id"] = np.arange(40_000)
        nxt, trials = W.draw_hop(block, block.find(w["node"]), w, W.Kernel("hybrid", method), 7, "native")
        counts.append(np.bincount(nxt, minlength=6) / 40_000)
    assert np.abs(counts[0] - counts[1]).max() < 0.015


def test_stop_rules():
    table = pd.DataFrame([(a, b, 1, i + 1, 1.0) for a in range(6) for i, b in enumerate(x for x in range(6) if x != a)], columns=["u", "v", "q", "hi", "p_accept"])
    literal = W.local_walks(table, np.arange(6), W.Kernel("uniform"), W.Stop.literal())
    assert set(literal.groupby("walk_id").size()) == {3}
    longer = W.local_walks(table, np.arange(6), W.Kernel("uniform"), W.Stop("entropy_r2", 0.5))
    calibrated = W.local_walks(table, np.arange(6), W.Kernel("uniform"), W.Stop.calibrated())
    assert len(longer) >= len(calibrated) >= len(literal) and longer.groupby("walk_id").size().max() <= 80


def test_leaf_returns_and_isolated_walks_end(spark):
    e = edges(spark, [(1, 2)])
    nodes = spark.createDataFrame([(1,), (2,), (9,)], "node long")
    rows = W.step_walks(e, nodes, W.Kernel("uniform"), 4).collect()
    by = {k: [r["node"] for r in sorted(rows, key=lambda r: r["step"]) if r["walk_id"] == k] for k in (1, 2, 9)}
    assert by == {1: [1, 2, 1, 2], 2: [2, 1, 2, 1], 9: [9]}


def two_cliques():
    return [(a + k, b + k) for k in (0, 100) for a in range(8) for b in range(a + 1, 8)] + [(0, 100)]


def test_proximity_beats_balanced_cut(spark):
    e = G.common_neighbours(edges(spark, two_cliques()))
    cut = lambda a: P.partition_quality(e, a, 2).first()["cut"]
    proximity = P.proximity_partition(e, 2, order="bfs_degree", seed_parts=False).cache()
    assert proximity.count() == 16 and proximity.select("node").distinct().count() == 16
    assert cut(proximity) <= cut(P.hash_partition(proximity.select("node"), 2))
    one, two = P.proximity_partition(e, 2, order="dfs_degree").collect(), P.proximity_partition(e, 2, order="dfs_degree", segments=1).collect()
    assert sorted(one) == sorted(two)


def test_scores_of_empty_parts():
    stream = pd.DataFrame({"pos": [0, 1, 2], "node": [5, 6, 7], "nbr": [np.array([6]), np.array([5]), np.array([])], "cm": [np.array([0]), np.array([0]), np.array([])], "w": [np.array([1.0]), np.array([1.0]), np.array([])]})
    assert P.place_stream(stream, 4, P.proximity_score(2.0), 3)["part"].tolist()[:2] == [0, 1]  # a part with the only node is over its share: its balance is negative


def test_orders_visit_every_node_once(spark):
    e = edges(spark, two_cliques())
    for kind in ("random", "bfs", "dfs", "bfs_degree", "dfs_degree"):
        rows = P.stream_order(e, kind).collect()
        assert sorted(r["pos"] for r in rows) == list(range(16))


def test_pairs_are_clipped_and_skip_self(spark):
    steps = spark.createDataFrame([(1, 1, i, v) for i, v in enumerate([5, 6, 5], 1)], "round int, walk_id long, step int, node long")
    got = sorted((r["pos"], r["target"], r["context"]) for r in L.skipgram_pairs(steps, 1).collect())
    assert got == [(1, 5, 6), (2, 6, 5), (2, 6, 5), (3, 5, 6)]


def test_gradient_against_finite_differences():
    rng = np.random.default_rng(0)
    a, b = rng.normal(size=(6, 4)), rng.normal(size=(6, 4))
    loss = lambda x: sum(np.log1p(np.exp(-x[r] @ b[0])) + sum(np.log1p(np.exp(x[r] @ b[k])) for k in (3, 4)) for r in (1, 2))
    s = L.Shard(a.copy(), b.copy(), np.array([1]), 2, 2, 1.0, 0)
    assert s.batch([np.array([1, 2])], [0], np.array([3, 4])) == (2, 3)
    step = s.phi_in - a
    for r in (1, 2):
        for i in range(4):
            up = a.copy()
            up[r, i] += 1e-6
            assert abs((loss(up) - loss(a)) / 1e-6 + step[r, i]) < 1e-4


def test_window_shapes_and_modes_learn():
    s = L.Shard(*L.initial_vectors(60, 8, 1), np.arange(1, 61), 2, 5, 0.05, 1)
    assert s.batch([np.arange(4)], [50], np.arange(30, 35)) == (4, 6)
    assert s.batch([np.arange(4), np.arange(4, 8)], [50, 51], np.arange(30, 35)) == (8, 7)
    rng = np.random.default_rng(3)
    walks = [rng.integers(0, 10, 20) + 10 * (k % 2) for k in range(60)]
    for mode in L.MODES:
        s = L.Shard(*L.initial_vectors(20, 8, 1), np.arange(1, 21), 3, 5, 0.05, 1)
        for _ in range(3):
            s.train(walks, mode, 2)
        x = s.phi_in / np.linalg.norm(s.phi_in, axis=1, keepdims=True)
        inside, across = (x[:10] @ x[:10].T).mean(), (x[:10] @ x[10:].T).mean()
        assert inside > across, mode


def test_train_end_to_end_and_sync(spark):
    e = edges(spark, two_cliques())
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    steps = W.step_walks(e, nodes, W.Kernel("uniform"), 6, 2)
    rows = L.train(steps, dims=8, window=2, shards=2, periods=1).collect()
    assert len(rows) == 16 and sorted(r["rank"] for r in rows) == list(range(16)) and all(len(r["phi"]) == 8 for r in rows)
    vocab = L.build_vocab(steps)
    assert L.sync_nodes(vocab, 1).count() == vocab.select("ocn").distinct().count()


def test_auc_and_f1(spark):
    auc = lambda rows: E.auc(spark.createDataFrame(rows, "score double, y int")).first()["auc"]
    assert auc([(1.0, 1), (0.5, 0), (0.2, 1), (0.1, 0)]) == 0.75
    assert auc([(1.0, 1), (1.0, 0)]) == 0.5 and auc([(1.0, 1)]) is None
    f = E.f1_scores(spark.createDataFrame([(0, 1, 1), (0, 0, 0), (1, 1, 0)], "label int, y_true int, y_pred int")).first()
    assert abs(f["micro_f1"] - 2 / 3) < 1e-12 and f["macro_f1"] == 0.5


def test_costs():
    assert E.message_bytes("fullpath", 80) == 664 and E.message_bytes("incremental", 80) == 80
    assert E.sync_cost("full", 1e8, 128, 4) == 102.4e9
    assert E.walk_cost("fullpath", 7, 26, 10, 1, 0, 1) > E.walk_cost("incremental", 7, 26, 10, 1, 0, 1)


def test_document_edges_without_a_bound(spark, tmp_path):
    from walkembed.plans.graph_queries import QUERIES

    shared = "one very common line of words "
    texts = ["copied text that many rows hold word for word"] * 60 + [shared + f"then row {k} goes on its own way" for k in range(55)] + ["too short", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    unit = 7 * 10**12
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (re.split(r"\s+", t or "") for t in texts)]
    want = {(unit + a, unit + b): round(len(x & y) / len(x | y), 6) for a, x in enumerate(sets) for b, y in enumerate(sets) if a < b and x & y}
    rows = QUERIES["graph_doc_edges_all"](spark, str(tmp_path)).collect()
    assert len(rows) == len(want) and {(r["src"], r["dst"]): r["w"] for r in rows} == want
    assert {(r["src"], r["dst"]): r["w"] for r in QUERIES["graph_doc_edges"](spark, str(tmp_path)).collect()} == want


def test_document_pairs_are_counted_in_blocks_and_never_exchanged(spark, tmp_path):
    from walkembed.plans.graph_queries import QUERIES
    from walkembed.sources import shared_shingles as D

    rng = np.random.default_rng(8)
    word = lambda k: f"w{k}"
    texts = [" ".join(map(word, rng.integers(0, 4, int(n)))) for n in rng.integers(3, 60, 150)]
    texts += ["a\x0bb c\td\n e f g h", "a\x0bb c d e f g h", "  lead and trail a b c ", "b c d e f", None, ""] + ["one text that many rows hold word for word"] * 40
    ids = [*range(len(texts)), 3, 3, None]  # rows of one id are one set, a row without an id has no pair
    texts += [texts[5], "no other row has these words here", texts[0]]
    sets = {}
    for i, t in zip(ids, texts):
        w = re.split(r"[\t\n\f\r ]+", t or "")
        sets.setdefault(i, set()).update(tuple(w[k : k + 5]) for k in range(len(w) - 4))
    del sets[None]
    want = {(a, b): round(math.floor(len(x & y) / len(x | y) * 1e6 + 0.5) / 1e6, 6) for a, x in sets.items() for b, y in sets.items() if a < b and x & y}
    frame = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string").repartition(3)
    for blocks, live in ((1, 10**6), (7, 10**6), (3, 300)):
        rows = D.shared_shingle_pairs(frame, 5, 0, blocks, live).collect()
        assert len(rows) == len(want) and {(r["src"], r["dst"]): r["w"] for r in rows} == want
    frame.write.parquet(str(tmp_path / "documents.parquet"))
    for name in ("graph_doc_edges", "graph_doc_edges_all"):
        plan = QUERIES[name](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" in plan and "Exchange" not in plan


def test_cells_of_blocks_equal_brute_force_under_any_bounds(monkeypatch):
    import pyarrow as pa

    from walkembed.sources import shared_shingles as D

    rng = np.random.default_rng(9)
    pool = rng.integers(0, 2**63, (90, 2)).astype(np.uint64)
    pool[1, 0] = pool[0, 0]  # one first word, two keys
    pool = pool[np.lexsort((pool[:, 1], pool[:, 0]))]
    share = np.where(np.arange(90) < 10, 0.9, 0.05)
    held = [np.flatnonzero(rng.random(90) < share) for _ in range(60)] + [np.arange(20)] * 15
    side = lambda ids: D.Block(*(c[0].as_py() for c in D._block(pa.table({"blk": pa.array([0] * len(ids), pa.int32()), "doc_id": ids, "n": [len(held[i]) + i % 3 for i in ids], "keys": pa.array([pool[held[i]].tobytes() for i in ids], pa.binary())})).columns[1:]))
    x, y = list(range(0, 75, 2)), list(range(1, 75, 2))
    for bounds in ({}, {"CELL": 40, "PRODUCTS": 5, "ROWS": 7}):
        for name, value in bounds.items():
            monkeypatch.setattr(D, name, value)
        got = {}
        for a, b in ((x, x), (y, y), (x, y)):
            for src, dst, w in D.block_pairs(side(a), side(b), a is b):
                for p in zip(src.tolist(), dst.tolist(), w.tolist()):
                    assert p[:2] not in got
                    got[p[:2]] = p[2]
        common = {(i, j): len(np.intersect1d(held[i], held[j])) for i in range(75) for j in range(i + 1, 75)}
        size = [len(h) + i % 3 for i, h in enumerate(held)]
        assert got == {(i, j): math.floor(c / (size[i] + size[j] - c) * 1e6 + 0.5) / 1e6 for (i, j), c in common.items() if c}


def test_whole_prefix_r2_of_every_step(spark):
    rng = np.random.default_rng(3)
    paths = {1: rng.integers(0, 6, 50).tolist(), 2: [9] * 10, 3: list(range(35))}
    steps = spark.createDataFrame([(1, w, i, int(v)) for w, p in paths.items() for i, v in enumerate(p, 1)], "round int, walk_id long, step int, node long")
    rows = W.fullpath_r2(steps).collect()
    assert len(rows) == sum(map(len, paths.values()))
    for r in rows:
        h = [M.path_entropy(paths[r["walk_id"]][:k]) for k in range(1, r["step"] + 1)]
        want = np.corrcoef(h, np.arange(1, len(h) + 1))[0, 1] ** 2 if np.var(h) > 1e-12 else 0.0
        assert abs(r["r2"] - want) < 1e-8


def test_blocked_softmax_equals_brute_force(spark):
    rng = np.random.default_rng(6)
    x = 3 * rng.normal(size=(70, 8))
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 70, (200, 2))]
    vectors = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "node long, phi array<double>")
    s = x @ x.T
    want = sum(s[b, a] - np.log(np.exp(s[b]).sum()) for a, b in pairs)
    frame = spark.createDataFrame(pairs, "target long, context long")
    for block in (16, 2048):
        row = L.softmax_loglik_blocked(frame, vectors, block).first()
        assert row["pairs"] == 200 and abs(row["loglik"] - want) < 1e-6
    assert abs(L.softmax_loglik(frame, vectors).first()["loglik"] - want) < 1e-6


def test_whole_queries_cover_every_source(spark):
    from walkembed.plans import graph_queries, learn_queries

    d = "/root/testdata/sf0.001"
    walks = graph_queries.QUERIES["walk_hybrid_direct_all"](spark, d).persist()
    nodes = graph_queries.all_nodes(graph_queries.graph(spark, d, "tri"))
    assert walks.select("walk_id").distinct().count() == nodes.count()
    assert graph_queries.QUERIES["walk_hybrid_direct"](spark, d).exceptAll(walks.select("round", "walk_id", "step", "node")).count() == 0
    assert graph_queries.QUERIES["walk_r2_prefix_all"](spark, d).count() == graph_queries.natural(spark, d).where("step >= 3").count()
    row = learn_queries.QUERIES["softmax_loglik_all"](spark, d).first()
    assert row["pairs"] == graph_queries.graph(spark, d, "knn").count()


def test_fennel_counts_the_edges_at_hand(spark, monkeypatch):
    from walkembed.plans import graph_queries

    seen, score = [], P.fennel_score
    monkeypatch.setattr(P, "fennel_score", lambda *a, **kw: (seen.append(kw["n_edges"]), score(*a, **kw))[1])
    d = "/root/testdata/sf0.1"
    assert graph_queries.QUERIES["partition_fennel"](spark, d).count() == 2000
    assert seen == [graph_queries.graph(spark, d, "knn").count()]


@pytest.mark.parametrize("name", ["embed_info", "embed_fullpath", "embed_routine", "linkpred_info_pipeline"])
def test_profiles_are_registered_whole(monkeypatch, name):
    import inspect

    from walkembed.plans import learn_queries, pipelines

    class Asked(Exception):
        pass

    def asked(original):
        def stop(*a, **kw):
            bound = inspect.signature(original).bind(*a, **kw)
            bound.apply_defaults()
            raise Asked({**bound.arguments, **bound.arguments.get("swap", {})})

        return stop

    monkeypatch.setattr(learn_queries, "graph", lambda *a: None)
    for f in ("embed", "link_prediction"):
        monkeypatch.setattr(pipelines, f, asked(getattr(pipelines, f)))
    with pytest.raises(Asked) as e:
        learn_queries.QUERIES[name](None, "")
    used = e.value.args[0]
    assert used["max_rounds"] == 10 and used["dims"] == 64 and used.get("m", 2) >= 2


def test_counts_equal_a_dictionary():
    rng = np.random.default_rng(8)
    counts, plain = W.Counts(), {}
    for step in range(40):
        walks = rng.permutation(30)[: rng.integers(1, 30)]
        nodes = rng.integers(0, 6, len(walks))
        got = counts.add(walks, nodes)
        assert got.tolist() == [plain.get(k, 0) for k in zip(walks.tolist(), nodes.tolist())]
        for k in zip(walks.tolist(), nodes.tolist()):
            plain[k] = plain.get(k, 0) + 1
        if step == 20:  # what stays for the next superstep
            again = W.Counts()
            again.load(*counts.rows())
            counts = again
    walk, node, times = counts.rows()
    assert {(a, b): n for a, b, n in zip(walk.tolist(), node.tolist(), times.tolist())} == plain


def test_trial_limit_keeps_the_law(spark, monkeypatch):
    e = edges(spark, [(0, i) for i in range(1, 6)] + [(1, 2), (2, 3)])
    table = W.kernel_edges(e, W.Kernel("hybrid")).toPandas()
    shares = []
    for limit in (1000, 1, 0):
        monkeypatch.setattr(W, "MAX_TRIALS", limit)
        block = W.Block.of(table)
        w = W.start_walkers(np.zeros(40_000, dtype=np.int64), 1)
        w["walk_id"] = np.arange(40_000)
        nxt, _ = W.draw_hop(block, block.find(w["node"]), w, W.Kernel("hybrid", "accept"), 7, "native")
        shares.append(np.bincount(nxt, minlength=6) / 40_000)
    assert np.abs(shares[0] - shares[1]).max() < 0.015 and np.abs(shares[0] - shares[2]).max() < 0.015


@pytest.mark.parametrize("method", ["direct", "accept"])
def test_second_order_walks_are_the_same_on_any_parts(spark, method):
    kernel = W.Kernel("biased2", method, p=0.5, q=2.0)
    e = edges(spark, ring(24))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    table = W.kernel_edges(e, kernel)
    key = lambda m: sorted(tuple(r) for r in W.burst_round(table, P.hash_partition(nodes, m), nodes, kernel, W.Stop.fixed(5), rng="portable").select("walk_id", "step", "node").collect())
    one = key(1)
    assert one == key(3)
    if method == "direct":
        assert one == sorted(tuple(r) for r in W.step_walks(e, nodes, kernel, 5).select("walk_id", "step", "node").collect())


def test_fullpath_walkers_stop_like_incremental_ones(spark):
    kernel, stop = W.Kernel("hybrid"), W.Stop("entropy_r2", 0.8, 3, 30)
    e = edges(spark, ring(20))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    table, assign = W.kernel_edges(e, kernel), P.hash_partition(nodes, 2)
    full = W.fullpath_round(table, assign, nodes, kernel, stop, rng="portable").persist()
    burst = W.burst_round(table, assign, nodes, kernel, stop, rng="portable")
    key = lambda f: sorted(tuple(int(x) for x in r) for r in f.select("walk_id", "step", "node").collect())
    assert key(full) == key(burst)
    for r in full.where("step > 1").collect():  # a message holds the path so far
        assert r["sent"] in (0, 24 + 8 * r["step"])
    stats = W.message_stats(full.select("round", "walk_id", "step", "node"), assign).first()
    assert full.agg({"sent": "sum"}).first()[0] == stats["bytes_fullpath"]
    short = W.fullpath_round(table, assign, nodes, kernel, W.Stop("entropy_r2", 0.8, 3, 30, window=4), rng="portable")
    assert short.count() > 20
    with pytest.raises(ValueError):
        W.burst_round(table, assign, nodes, kernel, W.Stop("entropy_r2", 0.8, 3, 30, window=4))


def test_rounds_stop_when_the_corpus_settles(spark):
    e = edges(spark, ring(20))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    assign = P.hash_partition(nodes, 1)
    corpus, trace = W.sample_corpus(e, assign, W.Kernel("uniform"), W.Stop.fixed(6), delta=1e9)
    assert len(trace) == 2 and corpus.select("round").distinct().count() == 2
    corpus, trace = W.sample_corpus(e, assign, W.Kernel("uniform"), W.Stop.fixed(6), fixed_rounds=10)
    assert len(trace) == 10 and corpus.count() == 20 * 6 * 10 and min(trace) >= -1e-12


def test_segments_align(spark):
    e = G.common_neighbours(edges(spark, two_cliques())).cache()
    order = P.stream_order(e, "random", 3)
    plain = P.streamed_partition(e, 2, order, P.proximity_score(2.0), 2)
    aligned = P.streamed_partition(e, 2, order, P.proximity_score(2.0), 2, align=True)
    cut = lambda a: P.partition_quality(e, a, 2).first()["cut"]
    assert aligned.count() == 16 and cut(aligned) <= cut(plain)


def test_noise_draws_follow_the_running_sums(spark):
    from pyspark.sql import functions as F

    steps = spark.createDataFrame([(1, w, i, int(v)) for w in range(20) for i, v in enumerate([w % 7, 3, 3, w % 5], 1)], "round int, walk_id long, step int, node long")
    noise = L.noise_table(L.build_vocab(steps)).cache()
    table = noise.orderBy("rank").collect()
    assert [r["hi"] for r in table] == np.cumsum([r["q"] for r in table]).tolist()
    total = table[-1]["hi"]
    got = {r["x"]: r["negative"] for r in L.draw_noise(noise, spark.range(0, total, 97).select(F.col("id").alias("x"))).collect()}
    his = np.array([r["hi"] for r in table])
    assert len(got) == len(range(0, total, 97)) and all(table[int(np.searchsorted(his, x, side="right"))]["node"] == v for x, v in got.items())


def test_trained_baselines_separate_groups(spark):
    from walkembed.operators import baselines as B
    from walkembed.plans import pipelines

    e = edges(spark, two_cliques())
    for vectors in (B.train_gnn(e, 16, epochs=60), B.relational_embed(pipelines.typed_edges(e), 16, epochs=30)):
        x = {r["node"]: np.array(r["phi"]) for r in vectors.collect()}
        assert len(x) == 16
        inside = np.mean([x[a] @ x[b] for a in x for b in x if a < b and (a < 100) == (b < 100)])
        across = np.mean([x[a] @ x[b] for a in x for b in x if a < b and (a < 100) != (b < 100)])
        assert inside > across


def test_as_many_negatives_as_held_edges(spark):
    e = edges(spark, ring(60))
    held = E.split_edges(e).where("held")
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    rows = E.balanced_negatives(held, e, nodes).collect()
    linked = {(r["src"], r["dst"]) for r in e.collect()}
    assert len(rows) == held.count() and not {(r["src"], r["dst"]) for r in rows} & linked


def test_link_prediction_of_every_system(spark):
    from walkembed.plans import pipelines

    e = edges(spark, [(a + 20 * k, b + 20 * k) for k in range(3) for a in range(12) for b in range(a + 1, 12)] + [(0, 20), (20, 40)])
    for system in ("info", "relational", "gnn"):
        row = pipelines.link_prediction(e, system, 8, **({"max_rounds": 3, "m": 2, "epochs": 12, "rate": 0.1} if system == "info" else {})).first()
        assert row["n_pos"] == row["n_neg"] and row["auc"] > 0.6, system


def test_rounds_of_a_wave_are_those_of_single_rounds(spark):
    kernel, stop = W.Kernel("hybrid"), W.Stop("entropy_r2", 0.85, 3, 20)
    e = edges(spark, ring(20))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    table, assign = W.kernel_edges(e, kernel), P.hash_partition(nodes, 2)
    key = lambda f: sorted(tuple(int(x) for x in r) for r in f.select("round", "walk_id", "step", "node").collect())
    for walk in (W.burst_round, W.fullpath_round):
        wave = walk(table, assign, nodes, kernel, stop, (1, 2, 3))
        assert key(wave) == sorted(sum((key(walk(table, assign, nodes, kernel, stop, r)) for r in (1, 2, 3)), []))


def test_replicas_of_a_part_change_nothing(spark):
    e = edges(spark, ring(20))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    for kernel in (W.Kernel("hybrid"), W.Kernel("biased2", "accept", p=0.5, q=2.0)):
        table = W.kernel_edges(e, kernel)
        key = lambda m, r: sorted(tuple(int(x) for x in row) for row in W.burst_round(table, P.hash_partition(nodes, m), nodes, kernel, W.Stop.fixed(6), (1, 2), replicas=r).select("round", "walk_id", "step", "node").collect())
        assert key(1, 1) == key(1, 3) == key(2, 2)


def test_approximate_distinct_counts_stay_near(spark, tmp_path):
    from walkembed.plans import relational

    # with the default sketch these keys came out 10.07 % low
    spark.range(1_200_000).selectExpr("id as l_partkey").write.parquet(str(tmp_path / "lineitem.parquet"))
    assert tuple(relational.QUERIES["op_agg_approx_distinct"](spark, str(tmp_path)).first()) == (True, 1_200_000)


def test_noise_of_large_corpora_is_drawn(spark, monkeypatch):
    from walkembed.functions.rng import draw_python
    from walkembed.plans import learn_queries as Q

    # weights of 2^27 * 3 each: their total leaves 31 bits, as that of 110,000 nodes does
    noise = [(n, n, 3 << 27, (n + 1) * (3 << 27)) for n in range(10)]
    monkeypatch.setattr(Q, "uniform_corpus", lambda *_: (None, None))
    monkeypatch.setattr(Q.L, "build_vocab", lambda _: None)
    monkeypatch.setattr(Q.L, "noise_table", lambda _: spark.createDataFrame(noise, "node long, rank long, q long, hi long"))
    rows = Q.negative_samples(spark, "").collect()
    assert sorted(map(tuple, rows)) == [(n, k, (draw_python(Q.SEED, n, k) * (30 << 27) >> 32) // (3 << 27)) for n in range(10) for k in range(1, 6)]


def test_walks_from_hubs_carry_no_neighbours(spark):
    star = edges(spark, [(0, i) for i in range(1, 40)] + [(1, 2)])
    kernel, nodes = W.Kernel("hybrid"), G.both_directions(star).select("u").distinct().withColumnRenamed("u", "node")
    steps = W.step_walks(star, nodes, kernel, 6)
    local = W.local_walks(W.kernel_edges(star, kernel).toPandas(), np.arange(40), kernel, W.Stop.fixed(6))
    key = lambda rows: sorted(tuple(int(x) for x in r) for r in rows)
    assert key(steps.select("walk_id", "step", "node").collect()) == key(local[["walk_id", "step", "node"]].to_numpy())
    assert "nbr" not in steps._jdf.queryExecution().optimizedPlan().toString()


def test_common_neighbours_of_dense_and_sparse_graphs_equal_brute_force(spark):
    rng = np.random.default_rng(3)
    for n, m in ((70, 1500), (300, 900)):
        pairs = sorted({(min(a, b), max(a, b)) for a, b in rng.integers(0, n, (m, 2)).tolist() if a != b} | {(0, k) for k in range(1, 60)})
        near = {v: {b if a == v else a for a, b in pairs if v in (a, b)} for v in range(n)}
        rows = G.common_neighbours(edges(spark, pairs)).collect()
        assert sorted((r["src"], r["dst"], r["cm"]) for r in rows) == [(a, b, len(near[a] & near[b])) for a, b in pairs]
        corners = sorted(tuple(sorted(r)) for r in G.triangles(edges(spark, pairs)).collect())
        assert corners == [(a, b, c) for a, b in pairs for c in sorted(near[a] & near[b]) if c > b]


def test_open_wedges_stay_in_their_tasks(spark):
    star = edges(spark, [(a, 1000 + b) for a in range(300) for b in range(a % 7, 60, 7)])
    plan = G.triangles(star)
    assert plan.count() == 0
    text = plan._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in text and " lo#" in text and "hi#" in text
    words = G.edge_filter(star)
    a, b = np.arange(300).repeat(60), np.tile(1000 + np.arange(60), 300)
    at, code = G._edge_code(a, b)
    said = words[(at & np.uint64(len(words) - 1)).astype(int)] & G._mask(code) == G._mask(code)
    linked = (b - 1000 - a % 7) % 7 == 0
    linked &= b - 1000 >= a % 7
    assert said[linked].all() and said[~linked].mean() < 0.05


@pytest.mark.parametrize("kernel", [W.Kernel("hybrid"), W.Kernel("hybrid", "accept"), W.Kernel("biased2", p=0.5, q=2.0)])
@pytest.mark.parametrize("stop", [W.Stop.fixed(7), W.Stop("entropy_r2", 0.8, 3, 30)])
def test_shared_walks_are_those_of_parts(spark, monkeypatch, kernel, stop):
    """A graph that fits a task is walked without supersteps: the same hops, and the same messages of the baseline."""
    monkeypatch.setattr(W, "SHARED_HOPS", 90)  # a few walkers at a time
    monkeypatch.setattr(W, "CANDIDATES", 10)
    e = edges(spark, ring(20))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    table, assign = W.kernel_edges(e, kernel).cache(), P.hash_partition(nodes, 3).cache()
    key = lambda f, *c: sorted(tuple(int(x) for x in r) for r in f.select("round", "walk_id", "step", "node", *c).collect())
    for rng in ("portable", "native"):
        want = key(W.burst_round(table, assign, nodes, kernel, stop, (1, 2), rng=rng))
        with monkeypatch.context() as without:
            without.setattr(W, "burst_round", None)
            assert key(W.corpus_round(table, assign, nodes, kernel, stop, (1, 2), rng=rng)) == want
    full = W.fullpath_round(table, assign, nodes, kernel, stop, (1, 2))
    assert key(W.shared_round(table, assign, nodes, kernel, stop, (1, 2), measure="fullpath"), "sent", "trials") == key(full, "sent", "trials")
    monkeypatch.setattr(W, "SHARED_ROWS", 10)  # larger graphs go on by parts
    assert not W.fits_a_task(table)


def test_shared_walks_end_at_sinks(spark):
    kernel, stop = W.Kernel("uniform"), W.Stop.fixed(6)
    e = edges(spark, [(1, 2), (2, 3), (1, 4), (4, 2)])
    nodes = spark.createDataFrame([(i,) for i in range(1, 5)], "node long")
    table, assign = W.kernel_edges(e, kernel, directed=True), P.hash_partition(nodes, 2)
    key = lambda f: sorted(tuple(int(x) for x in r) for r in f.select("walk_id", "step", "node").collect())
    assert key(W.shared_round(table, assign, nodes, kernel, stop)) == key(W.burst_round(table, assign, nodes, kernel, stop))
    assert key(W.shared_round(table, assign, nodes, kernel, stop, measure="fullpath")) == key(W.fullpath_round(table, assign, nodes, kernel, stop))


def test_divergences_of_a_wave_are_those_of_its_rounds(spark):
    e = edges(spark, ring(20))
    nodes = G.both_directions(e).select("u").distinct().withColumnRenamed("u", "node")
    steps, trace = W.sample_corpus(e, P.hash_partition(nodes, 2), W.Kernel("uniform"), W.Stop.fixed(4), fixed_rounds=5, wave=3)
    want = [r["divergence"] for r in M.corpus_divergence(G.degrees(G.both_directions(e)), steps).orderBy("round").collect()]
    assert np.allclose(trace, want, atol=1e-12) and len(trace) == 5


@pytest.mark.parametrize("n_windows", [1, 2, 3])
def test_lockstep_trains_every_window(n_windows, monkeypatch):
    """Walks of all lengths in lockstep: each window counts once, and a lone walk moves as window by window."""
    rng = np.random.default_rng(5)
    walks = [rng.integers(0, 200, k % 23 + 1) for k in range(150)]
    s = L.Shard(*L.initial_vectors(200, 8, 1), np.arange(1, 201), 3, 5, 0.05, 1)
    s.train(walks, "window_shared" if n_windows == 1 else "multi_window", n_windows)
    want = np.zeros(200, int)
    for w in walks:
        for i in range(len(w)):
            for j in range(max(0, i - 3), min(len(w), i + 4)):
                want[w[j]] += i != j
    assert s.updates.tolist() == want.tolist() and s.pairs == want.sum()
    lone = np.arange(12)
    a, b = (L.Shard(*L.initial_vectors(40, 8, 1), np.arange(1, 41), 3, 5, 0.05, 1) for _ in range(2))
    a.phi_out[:] = b.phi_out[:] = rng.normal(size=(40, 8)) * 0.1
    a._lockstep([lone], 1)
    for i in range(12):
        b.batch([b._contexts(lone, i)], [lone[i]], b.noise(1, 5)[0])
    assert np.allclose(a.phi_in, b.phi_in) and np.allclose(a.phi_out, b.phi_out)


def test_one_training_gives_every_number_of_epochs(spark):
    steps = W.step_walks(edges(spark, two_cliques()), spark.range(16).withColumnRenamed("id", "node"), W.Kernel("uniform"), 6, 2).cache()
    key = lambda f: sorted((r["rank"], r["n_updates"], tuple(np.round(r["phi"], 9))) for r in f.collect())
    one, two = L.train_upto(steps, (1, 2), dims=4, window=2)
    assert key(one) == key(L.train(steps, dims=4, window=2, epochs=1)) and key(two) == key(L.train(steps, dims=4, window=2, epochs=2))


@pytest.mark.parametrize("name, corpora", [("auc_curve", 1), ("grid_search", 1), ("auc_ratio", 6)])
def test_sweeps_walk_each_corpus_once(spark, monkeypatch, name, corpora):
    """The parted graph is made once a query and each corpus once, whatever is tried on it."""
    from pyspark.sql import functions as F

    from walkembed.plans import experiment_queries as X

    seen, graph = [], X.graph
    monkeypatch.setattr(X, "graph", lambda *a: (seen.append("graph"), graph(*a))[1])
    for engine in ("corpus_round", "burst_round"):
        monkeypatch.setattr(X.W, engine, lambda table, assign, nodes, *a, **kw: (seen.append("walk"), nodes.select(F.lit(1).alias("round"), F.col("node").alias("walk_id"), F.lit(1).alias("step"), "node"))[1])
    X.QUERIES[name](spark, "/root/testdata/sf0.001")
    assert (seen.count("graph"), seen.count("walk")) == (1, corpora)


@pytest.mark.parametrize("block", [2048, 7])
def test_nearest_vectors_with_ties_equal_brute_force(spark, tmp_path, block):
    from walkembed.sources import graphs as S

    rng = np.random.default_rng(2)
    x = rng.integers(-1, 2, (40, 3)).astype(np.float32)
    x[(x == 0).all(1)] = 1  # many equal directions
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    y = x.astype(float)
    s = np.round((y @ y.T) / (np.sqrt((y * y).sum(1))[:, None] * np.sqrt((y * y).sum(1))[None]), 9)
    want = sorted((i, j) for i in range(40) for j in sorted((j for j in range(40) if j != i), key=lambda j: (-s[i, j], j))[:10])
    got = S.knn_pairs(spark, str(tmp_path), 10, block)
    assert sorted((r["a"] % S.UNIT, r["b"] % S.UNIT) for r in got.collect()) == want


def test_trials_run_at_the_same_time_in_their_order(spark, monkeypatch):
    import threading

    from walkembed.plans import pipelines

    met = threading.Barrier(3, timeout=60)

    def trial(edges, profile, seed, **settings):
        met.wait()  # passes only when three are under way
        return spark.createDataFrame([(seed / 100.0,)], "auc double")

    monkeypatch.setattr(pipelines, "link_prediction", trial)
    row = pipelines.repeated(spark.range(1), "info", 3).first()
    assert row["trials"] == 3 and abs(row["mean_auc"] - 0.43) < 1e-12 and abs(row["sd_auc"] - math.sqrt(2 / 3) / 100) < 1e-12


def test_blocks_count_common_neighbours_without_listing_triangles(spark, monkeypatch):
    """A graph of many closed wedges and too many nodes for one matrix of bits: neighbours meet by blocks."""
    rng = np.random.default_rng(3)
    pairs = [(10 * a + 1, 10 * b + 1) for a in range(150) for b in range(a + 1, 150) if rng.random() < (0.7 if a // 50 == b // 50 else 0.1)]
    want = {(r["src"], r["dst"]): r["cm"] for r in G.common_neighbours(edges(spark, pairs), "intersect").collect()}
    monkeypatch.setattr(G, "DENSE_NODES", 0)
    monkeypatch.setattr(G, "BLOCK_BYTES", 64 * 150 // 8)
    monkeypatch.setattr(G, "triangles", lambda e: pytest.fail("lists triangles"))
    rows = G.common_neighbours(edges(spark, pairs)).collect()
    assert len(rows) == len(want) and {(r["src"], r["dst"]): r["cm"] for r in rows} == want and {r["w"] for r in rows} == {1.0}
    both = {(r["u"], r["v"]): (r["cm"], r["du"], r["dv"], r["p_accept"]) for r in G.hybrid_edges(edges(spark, pairs)).collect()}
    old = G.hybrid_weight(G.common_neighbours(edges(spark, pairs), "intersect")).collect()
    assert both == {(r["u"], r["v"]): (r["cm"], r["du"], r["dv"], r["p_accept"]) for r in old}


def test_draws_of_negatives_equal_a_search():
    for weights in (np.ones(7), np.array([1, 10**6, 1, 1, 1, 1, 1, 1, 1, 1, 1, 5]), np.random.default_rng(2).integers(1, 50, 4000), np.array([3])):
        hi = np.cumsum(weights).astype(np.int64)
        shard = L.Shard(np.zeros((len(hi), 2)), np.zeros((len(hi), 2)), hi, 2, 5, 0.05, 9)
        x = np.random.default_rng(9).integers(0, hi[-1], size=(300, 5))
        assert (shard.noise(300, 5) == np.searchsorted(hi, x, side="right")).all()


@pytest.mark.parametrize("mode", ["window_shared", "multi_window"])
def test_many_nodes_train_in_single_precision_as_in_double(monkeypatch, mode):
    rng = np.random.default_rng(4)
    n = 3000
    walks = [(s + np.cumsum(rng.integers(-3, 4, 30))) % n for s in rng.permutation(n)[:600]]
    found, kinds, steps = [], [], L.Shard._lane_steps
    monkeypatch.setattr(L.Shard, "_lane_steps", lambda self, w, k, a, b: kinds.append(a.dtype) or steps(self, w, k, a, b))
    for double in (False, True):
        shard = L.Shard(*L.initial_vectors(n, 16, 7), np.cumsum(np.full(n, 1000)), 5, 5, 0.05, 7)
        if double:
            monkeypatch.setattr(L.np, "float32", np.float64)
        shard.train(walks, mode)
        found.append((shard.phi_in, shard.phi_out, shard.updates, shard.pairs))
    assert kinds[0] == np.dtype("float32") and kinds[-1] == np.dtype("float64")
    assert np.abs(found[0][0] - found[1][0]).max() < 1e-3 and np.abs(found[0][1] - found[1][1]).max() < 1e-3
    assert (found[0][2] == found[1][2]).all() and found[0][3] == found[1][3]

"""Comparison systems, simplified from public literature, and the library's own classifiers."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.rng import draw_column
from . import graph as G
from .evaluate import f1_scores


def sample_neighbours(edges2: DataFrame, fan_out: int, seed: int = 42) -> DataFrame:
    """(u, v): at most ``fan_out`` neighbours of each node, by hash order."""
    w = Window.partitionBy("u").orderBy(draw_column(seed, F.col("u"), F.col("v")), "v")
    return edges2.select("u", "v").withColumn("k", F.row_number().over(w)).where(F.col("k") <= fan_out).select("u", "v")


def gnn_embed(edges: DataFrame, dims: int = 32, fan_out: int = 5, layers: int = 2, seed: int = 42) -> DataFrame:
    """(node, phi): the neighbour-sampled mean aggregator, untrained random features smoothed ``layers`` times.

    Sampling and aggregation are joins and grouped means; hop features are
    unrolled by dimension so that means stay in column expressions.
    """
    edges2 = G.both_directions(edges)
    nodes = edges2.select(F.col("u").alias("node")).distinct()
    x = nodes.select("node", F.explode(F.sequence(F.lit(0), F.lit(dims - 1))).alias("i")).withColumn("x", draw_column(seed, F.col("node"), F.col("i")) / F.lit(2.0**32) - 0.5)
    for layer in range(layers):
        near = sample_neighbours(edges2, fan_out, seed + layer)
        mean = near.join(x.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node"), "i").agg(F.avg("x").alias("m"))
        x = x.join(mean, ["node", "i"]).select("node", "i", ((F.col("x") + F.col("m")) / 2).alias("x"))
    return x.groupBy("node").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("phi"))


def _aggregate(x: np.ndarray, w1: np.ndarray, w2: np.ndarray) -> tuple[np.ndarray, ...]:
    """Two mean-aggregating layers over (n, 1 + fan_out, 2 d) inputs: a node's own row first, then its neighbours'."""
    z = x @ w1
    h = np.maximum(z, 0)
    joined = np.concatenate([h[:, 0], h[:, 1:].mean(1)], axis=1)
    return z, joined, joined @ w2


def _backward(x: np.ndarray, z: np.ndarray, joined: np.ndarray, g: np.ndarray, w2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    back = g @ w2.T
    d = back.shape[1] // 2
    spread = np.concatenate([back[:, None, :d], np.repeat(back[:, None, d:] / (x.shape[1] - 1), x.shape[1] - 1, axis=1)], axis=1) * (z > 0)
    return np.einsum("nki,nkj->ij", x, spread), joined.T @ g


def train_gnn(edges: DataFrame, dims: int = 32, fan_out: int = 5, epochs: int = 20, rate: float = 0.05, seed: int = 42, timings: dict | None = None) -> DataFrame:
    """(node, phi): a two-layer mean aggregator over sampled neighbours, trained without labels.

    Ends of an edge are pulled together, ends of a random pair apart (logistic
    loss).  Sampling is joins; a node's bag (its own and its neighbours' features
    and neighbourhood means) is one row, so an epoch is one pass over the edges
    that sums gradients of two small matrices a partition.
    """
    edges2 = G.both_directions(edges)
    nodes = edges2.select(F.col("u").alias("node")).distinct()
    began = time.time()
    features = nodes.select("node", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda k: draw_column(seed, F.col("node"), k) / F.lit(2.0**32) - 0.5).alias("x"))
    average = lambda rows: F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda k: F.aggregate(rows, F.lit(0.0), lambda s, r: s + F.get(r, k)) / F.size(rows))
    near = sample_neighbours(edges2, fan_out, seed)
    around = near.join(features.select(F.col("node").alias("v"), "x"), "v").groupBy(F.col("u").alias("node")).agg(F.collect_list("x").alias("xs"))
    row = features.join(around, "node").select("node", F.concat("x", average(F.col("xs"))).alias("row")).transform(durable)
    second = sample_neighbours(edges2, fan_out, seed + 1).join(row.select(F.col("node").alias("v"), F.col("row").alias("r")), "v").groupBy(F.col("u").alias("node")).agg(F.collect_list("r").alias("rs"))
    bags = row.join(second, "node").select("node", F.flatten(F.concat(F.array("row"), F.transform(F.sequence(F.lit(0), F.lit(fan_out - 1)), lambda k: F.get("rs", F.pmod(k, F.size("rs")))))).alias("bag")).transform(durable)
    # the other end of a random pair: the far end of the edge that follows by hash
    noise = edges.select("src", "dst", draw_column(seed, F.col("src"), F.col("dst")).alias("h"))
    other = noise.select(F.col("dst").alias("far"), F.lead("src").over(Window.partitionBy(F.pmod("h", F.lit(64))).orderBy("h", "src", "dst")).alias("rand"), "src", "dst")
    bag = lambda c, name: bags.select(F.col("node").alias(c), F.col("bag").alias(name))
    examples = other.select("src", "dst", F.coalesce("rand", "src").alias("rand")).join(bag("src", "a"), "src").join(bag("dst", "b"), "dst").join(bag("rand", "c"), "rand").select("a", "b", "c").transform(durable)
    if timings is not None:
        timings["sampling"] = time.time() - began
    began = time.time()
    rng = np.random.default_rng(seed)
    w1, w2 = rng.normal(size=(2 * dims, dims)) / np.sqrt(2 * dims), rng.normal(size=(2 * dims, dims)) / np.sqrt(2 * dims)
    shape = (-1, 1 + fan_out, 2 * dims)
    context = edges.sparkSession.sparkContext
    for _ in range(epochs):
        weights = context.broadcast((w1, w2))

        def gradients(frames):
            m1, m2 = weights.value
            total, g1, g2 = 0, np.zeros_like(m1), np.zeros_like(m2)
            for f in frames:
                if not len(f):
                    continue
                x = [np.stack(f[c]).reshape(shape) for c in "abc"]
                (za, ja, a), (zb, jb, b), (zc, jc, c) = (_aggregate(v, m1, m2) for v in x)
                pull = 1 / (1 + np.exp(np.clip((a * b).sum(1), -30, 30)))[:, None]
                push = 1 / (1 + np.exp(-np.clip((a * c).sum(1), -30, 30)))[:, None]
                for v, z, j, g in ((x[0], za, ja, pull * b - push * c), (x[1], zb, jb, pull * a), (x[2], zc, jc, -push * a)):
                    d1, d2 = _backward(v, z, j, g, m2)
                    g1, g2 = g1 + d1, g2 + d2
                total += len(f)
            yield pd.DataFrame({"n": [total], "g": [np.concatenate([g1.ravel(), g2.ravel()])]})

        parts = examples.mapInPandas(gradients, "n long, g array<double>").collect()  # a row a partition, two small matrices
        total = max(1, sum(p["n"] for p in parts))
        step = np.sum([p["g"] for p in parts], axis=0) / total
        w1, w2 = w1 + rate * 20 * step[: w1.size].reshape(w1.shape), w2 + rate * 20 * step[w1.size :].reshape(w2.shape)
        weights.unpersist()
    final = context.broadcast((w1, w2))

    def apply(frames):
        for f in frames:
            out = _aggregate(np.stack(f["bag"]).reshape(shape), *final.value)[2] if len(f) else np.empty((0, dims))
            yield pd.DataFrame({"node": f["node"], "phi": list(out)})

    if timings is not None:
        timings["training"] = time.time() - began
    return bags.mapInPandas(apply, "node long, phi array<double>")


def relational_embed(typed: DataFrame, dims: int = 32, buckets: int = 2, epochs: int = 3, rate: float = 0.1, seed: int = 5) -> DataFrame:
    """(node, phi): translation embeddings per relation over bucketed edges.

    ``typed``: (src, dst, rel).  Edges are bucketed by the buckets of their ends
    and a bucket pair trains with in-bucket negatives; replicas of a node's vector
    are averaged after each epoch.
    """
    spark = typed.sparkSession
    bucket = lambda c: F.pmod(F.xxhash64(c), F.lit(buckets)).cast("int")
    edges = typed.select("src", "dst", "rel", bucket("src").alias("i"), bucket("dst").alias("j")).transform(durable)
    nodes = edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    phi = nodes.select("node", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda k: draw_column(seed, F.col("node"), k) / F.lit(2.0**32) - 0.5).alias("phi")).transform(durable)

    def run(key: tuple, rows: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        if not len(rows):
            return pd.DataFrame({"node": [], "phi": []})
        names = held["node"].to_numpy()
        order = np.argsort(names)
        names, x = names[order], np.stack(held["phi"].to_list())[order]
        a, b = np.searchsorted(names, rows["src"]), np.searchsorted(names, rows["dst"])
        kinds, r = np.unique(rows["rel"], return_inverse=True)
        rng = np.random.default_rng(seed)
        move = np.zeros((len(kinds), dims))
        for lo in range(0, len(rows), 512):
            s = slice(lo, lo + 512)
            noise = b[rng.integers(0, len(b), len(b[s]))]
            left = x[a[s]] + move[r[s]]
            for target, sign in ((b[s], 1.0), (noise, 0.0)):
                g = rate * (sign - 1 / (1 + np.exp(-np.clip((left * x[target]).sum(1), -30, 30))))[:, None]
                np.add.at(x, a[s], g * x[target])
                np.add.at(move, r[s], g * x[target])
                np.add.at(x, target, g * left)
        used = np.unique(np.concatenate([a, b]))
        return pd.DataFrame({"node": names[used], "phi": list(x[used])})

    for _ in range(epochs):
        b = F.explode(F.array_distinct(F.flatten(F.array(F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda k: F.struct(bucket("node").alias("i"), k.alias("j"))), F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda k: F.struct(k.alias("i"), bucket("node").alias("j")))))))
        dealt = phi.select("node", "phi", b.alias("b")).select("node", "phi", "b.i", "b.j")
        parts = edges.groupBy("i", "j").cogroup(dealt.groupBy("i", "j")).applyInPandas(run, "node long, phi array<double>")
        spread = parts.select("node", F.posexplode("phi").alias("k", "x")).groupBy("node", "k").agg(F.avg("x").alias("x"))
        phi = spread.groupBy("node").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "x"))), lambda s: s["x"]).alias("phi")).transform(durable)
    return phi.select("node", "phi")


def word2vec(steps: DataFrame, dims: int = 32, window: int = 5) -> DataFrame:
    """(node, norm): the built-in hierarchical-softmax Word2Vec as an independent check."""
    from pyspark.ml.feature import Word2Vec

    walks = steps.groupBy("round", "walk_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("step", "node"))), lambda s: s["node"].cast("string")).alias("walk"))
    model = Word2Vec(vectorSize=dims, windowSize=window, minCount=0, inputCol="walk", outputCol="phi", seed=7).fit(walks)
    from pyspark.ml.functions import vector_to_array

    v = model.getVectors().select(F.col("word").cast("long").alias("node"), vector_to_array("vector").alias("phi"))
    return v.select("node", F.round(F.sqrt(F.aggregate("phi", F.lit(0.0), lambda a, x: a + x * x)), 6).alias("norm"))


def logistic_f1(vectors: DataFrame, labels: DataFrame, ratio: float, seed: int = 42) -> DataFrame:
    """(ratio, micro_f1, macro_f1) of one-vs-rest L2 logistic regression on node vectors."""
    from pyspark.ml.classification import LogisticRegression, OneVsRest
    from pyspark.ml.functions import array_to_vector

    rows = vectors.join(labels, "node").select("node", array_to_vector("phi").alias("features"), F.col("label").cast("double").alias("label"), (draw_column(seed, F.col("node")) < F.lit(int(ratio * (1 << 32)))).alias("train")).transform(durable)
    model = OneVsRest(classifier=LogisticRegression(regParam=0.01, maxIter=30)).fit(rows.where("train"))
    out = model.transform(rows.where("not train"))
    per = out.select(F.explode(F.array_distinct(F.array("label", "prediction"))).alias("k"), "label", "prediction").select(F.col("k").alias("label"), (F.col("label") == F.col("k")).cast("int").alias("y_true"), (F.col("prediction") == F.col("k")).cast("int").alias("y_pred"))
    return f1_scores(per).select(F.lit(ratio).alias("ratio"), "micro_f1", "macro_f1")


def nearest_class(vectors: DataFrame, labels: DataFrame, ratio: float, seed: int = 42) -> DataFrame:
    """(ratio, micro_f1, macro_f1) of the nearest class centroid; classes without a known node are never predicted."""
    rows = vectors.join(labels, "node").withColumn("train", draw_column(seed, F.col("node")) < F.lit(int(ratio * (1 << 32))))
    centre = rows.where("train").select("label", F.posexplode("phi").alias("i", "x")).groupBy("label", "i").agg(F.avg("x").alias("c")).groupBy(F.col("label").alias("predicted")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "c"))), lambda s: s["c"]).alias("centre"))
    score = F.aggregate(F.zip_with("phi", "centre", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    met = rows.where("not train").crossJoin(F.broadcast(centre))  # one row a class
    best = met.groupBy("node", "label").agg(F.max_by("predicted", F.struct(score.alias("s"), -F.col("predicted"))).alias("predicted"))
    per = best.select(F.explode(F.array_distinct(F.array("label", "predicted"))).alias("k"), "label", "predicted").select(F.col("k").alias("label"), (F.col("label") == F.col("k")).cast("int").alias("y_true"), (F.col("predicted") == F.col("k")).cast("int").alias("y_pred"))
    return f1_scores(per).select(F.lit(ratio).alias("ratio"), F.round("micro_f1", 6).alias("micro_f1"), F.round("macro_f1", 6).alias("macro_f1"))

"""Skip-gram learners: pairs, losses, the four batching modes, vocabulary, synchronisation.

Matrices are ordered by frequency; a shard trains its walks with NumPy, each mode
a different shape of the same gradient: a batch has rows of context vectors and
columns of targets and shared negatives.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

NOISE_BLOCK = 65_536
LONGEST_MOVE = 0.25
NODES_A_LANE, MOST_LANES = 40, 64  # walks in lockstep: a shard of few nodes trains them one after another
MODES = ("pairwise", "window_shared", "cross_window", "multi_window")


def skipgram_pairs(steps: DataFrame, window: int = 10) -> DataFrame:
    """(round, walk_id, pos, target, context): contexts within ``window``, clipped at the walk's ends, never the target's own place."""
    paths = steps.groupBy("round", "walk_id").agg(F.array_sort(F.collect_list(F.struct("step", "node"))).alias("p")).select("round", "walk_id", F.col("p.node").alias("path"))
    at = paths.select("round", "walk_id", "path", F.posexplode("path").alias("i", "target"))
    spots = F.filter(F.sequence(F.greatest(F.col("i") - window, F.lit(0)), F.least(F.col("i") + window, F.size("path") - 1)), lambda k: k != F.col("i"))
    return at.select("round", "walk_id", (F.col("i") + 1).alias("pos"), "target", F.explode(spots).alias("k"), "path").select("round", "walk_id", "pos", "target", F.element_at("path", F.col("k") + 1).alias("context"))


def build_vocab(steps: DataFrame) -> DataFrame:
    """(node, ocn, rank): most frequent first; ranks come from the counts of equal frequencies, not from one global sort task."""
    ocn = steps.groupBy("node").agg(F.count("*").alias("ocn"))
    sizes = ocn.groupBy("ocn").agg(F.count("*").alias("n"))
    before = sizes.withColumn("before", F.sum("n").over(Window.orderBy(F.desc("ocn"))) - F.col("n"))
    return ocn.join(before.select("ocn", "before"), "ocn").select("node", "ocn", (F.col("before") + F.row_number().over(Window.partitionBy("ocn").orderBy("node")) - 1).cast("long").alias("rank"))


def noise_table(vocab: DataFrame, power: float = 0.75) -> DataFrame:
    """(node, rank, q, hi): integer noise weights and their running sum by rank."""
    q = F.floor(F.pow(F.col("ocn").cast("double"), F.lit(power)) * 1024).cast("long") + 1
    blocks = vocab.select("node", "rank", q.alias("q"), F.floor(F.col("rank") / NOISE_BLOCK).alias("block"))
    # running sums inside blocks of ranks, then over the blocks: no task sees all nodes
    sums = blocks.groupBy("block").agg(F.sum("q").alias("s"))
    before = sums.select("block", (F.sum("s").over(Window.orderBy("block")) - F.col("s")).alias("before"))
    inside = F.sum("q").over(Window.partitionBy("block").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0))
    return blocks.withColumn("inside", inside).join(before, "block").select("node", "rank", "q", (F.col("before") + F.col("inside")).alias("hi"))


def draw_noise(noise: DataFrame, asked: DataFrame) -> DataFrame:
    """``asked`` (with a number ``x`` below the weights' total) + negative: the node whose running sums hold x.

    A node is listed under every bucket of numbers that it reaches, so an equi-join
    by bucket leaves a few candidates; buckets are as wide as the mean weight.
    """
    total, n = noise.agg(F.coalesce(F.max("hi"), F.lit(1)), F.count("*")).first()
    width = max(1, total // max(1, n))
    spans = noise.select("node", (F.col("hi") - F.col("q")).alias("lo"), "hi").withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    met = asked.withColumn("bucket", F.floor(F.col("x") / width)).join(spans, "bucket").where("x >= lo and x < hi")
    return met.select(*asked.columns, F.col("node").alias("negative"))


def param_count(vocab: DataFrame, dims: int) -> DataFrame:
    """One row: the numbers that both matrices hold."""
    return vocab.agg((2 * F.count("*") * dims).alias("params"))


def dot(a: str, b: str) -> F.Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def softplus(x: F.Column) -> F.Column:
    """ln(1 + e^x), stable at both ends."""
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def sgns_loss(pairs: DataFrame, vectors_in: DataFrame, vectors_out: DataFrame) -> DataFrame:
    """One row: the negative-sampling loss of (target, context, y), y = 1 for true pairs and 0 for noise."""
    met = pairs.join(vectors_in.select(F.col("node").alias("context"), F.col("phi").alias("a")), "context").join(vectors_out.select(F.col("node").alias("target"), F.col("phi").alias("b")), "target")
    s = dot("a", "b")
    return met.agg(F.count("*").alias("pairs"), F.sum(F.when(F.col("y") == 1, softplus(-s)).otherwise(softplus(s))).alias("loss"))


def softmax_loglik(pairs: DataFrame, vectors: DataFrame) -> DataFrame:
    """One row: the log likelihood under the full softmax; for small vocabularies."""
    v = vectors.select("node", "phi")
    contexts = pairs.select("context").distinct().join(v.select(F.col("node").alias("context"), F.col("phi").alias("a")), "context")
    scores = contexts.crossJoin(v.select("node", F.col("phi").alias("b"))).select("context", "node", dot("a", "b").alias("s"))
    top = scores.groupBy("context").agg(F.max("s").alias("top"))
    norm = scores.join(top, "context").groupBy("context").agg((F.first("top") + F.ln(F.sum(F.exp(F.col("s") - F.col("top"))))).alias("z"))
    met = pairs.join(scores.withColumnRenamed("node", "target"), ["context", "target"]).join(norm, "context")
    return met.agg(F.count("*").alias("pairs"), F.sum(F.col("s") - F.col("z")).alias("loglik"))


def softmax_loglik_blocked(pairs: DataFrame, vectors: DataFrame, block: int = 2048) -> DataFrame:
    """``softmax_loglik`` by blocks: each block of contexts meets each block of vectors in one matrix product."""
    v = vectors.select("node", F.col("phi").cast("array<double>").alias("phi"))
    blocks = max(1, math.ceil(v.count() / block))
    mine = F.pmod(F.xxhash64("node"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = pairs.select(F.col("context").alias("node")).distinct().join(v, "node").select("node", "phi", mine.alias("q"), every.alias("r"))
    right = v.select(F.col("phi").alias("other"), mine.alias("r2"), every.alias("q2"))

    def sums(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"context": np.array([], dtype=np.int64), "top": np.array([]), "mass": np.array([])})
        s = np.stack(a["phi"]) @ np.stack(b["other"]).T
        top = s.max(1)
        return pd.DataFrame({"context": a["node"].to_numpy(), "top": top, "mass": np.exp(s - top[:, None]).sum(1)})

    parts = left.groupBy("q", "r").cogroup(right.groupBy("q2", "r2")).applyInPandas(sums, "context long, top double, mass double")
    parts = parts.withColumn("highest", F.max("top").over(Window.partitionBy("context")))
    norm = parts.groupBy("context").agg((F.first("highest") + F.ln(F.sum(F.col("mass") * F.exp(F.col("top") - F.col("highest"))))).alias("z"))
    met = pairs.join(v.select(F.col("node").alias("context"), F.col("phi").alias("a")), "context").join(v.select(F.col("node").alias("target"), F.col("phi").alias("b")), "target").join(norm, "context")
    return met.agg(F.count("*").alias("pairs"), F.sum(dot("a", "b") - F.col("z")).alias("loglik"))


# --- in-task training ---------------------------------------------------------


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _bounded(moves: np.ndarray, longest: float = LONGEST_MOVE) -> np.ndarray:
    """Moves no longer than ``longest``: the sums of wide batches would overshoot, and grow without end."""
    length = np.sqrt(np.einsum("...d,...d->...", moves, moves))
    return moves * np.minimum(1.0, longest / np.maximum(length, longest))[..., None] if length.size and length.max() > longest else moves


def _add_rows(matrix: np.ndarray, rows: np.ndarray, moves: np.ndarray) -> None:
    """``np.add.at`` by rows, through the flat matrix: several times faster."""
    d = matrix.shape[1]
    np.add.at(matrix.reshape(-1), (rows[:, None] * d + np.arange(d)).ravel(), moves.ravel())


class Shard:
    """Replica matrices of a shard and its training steps; ids are ranks."""

    def __init__(self, phi_in: np.ndarray, phi_out: np.ndarray, noise_hi: np.ndarray, window: int, negatives: int, rate: float, seed: int):
        self.phi_in, self.phi_out, self.noise_hi = phi_in, phi_out, noise_hi
        self.window, self.negatives, self.rate = window, negatives, rate
        self.rng = np.random.default_rng(seed)
        self.updates = np.zeros(len(phi_in), dtype=np.int64)
        self.pairs = 0
        # where the running sums stand at even numbers below their total: a draw begins its search there
        self.stride = max(1, int(noise_hi[-1]) // (4 * len(noise_hi)))
        self.guide = np.searchsorted(noise_hi, np.arange(0, int(noise_hi[-1]), self.stride), side="right")

    def noise(self, *shape: int) -> np.ndarray:
        x = self.rng.integers(0, self.noise_hi[-1], size=shape).ravel()
        at = self.guide[x // self.stride]
        late = np.flatnonzero(self.noise_hi[at] <= x)
        for _ in range(4):
            at[late] += 1
            late = late[self.noise_hi[at[late]] <= x[late]]
        at[late] = np.searchsorted(self.noise_hi, x[late], side="right")
        return at.reshape(shape)

    def _contexts(self, walk: np.ndarray, i: int) -> np.ndarray:
        lo, hi = max(0, i - self.window), min(len(walk), i + self.window + 1)
        return np.concatenate([walk[lo:i], walk[i + 1 : hi]])

    def batch(self, contexts: list[np.ndarray], targets: list[int], noise: np.ndarray) -> tuple[int, int]:
        """One step: rows are all contexts, columns the targets and the shared negatives.

        A window's own target is its positive; the other windows' targets are
        further negatives.  A noise column equal to a row's target is left out.
        """
        rows = np.concatenate(contexts)
        owner = np.repeat(np.arange(len(contexts)), [len(c) for c in contexts])
        goal = np.array(targets)
        columns = np.concatenate([goal, noise])
        c, o = self.phi_in[rows], self.phi_out[columns]
        label = np.zeros((len(rows), len(columns)))
        label[np.arange(len(rows)), owner] = 1
        error = label - _sigmoid(c @ o.T)
        same = columns[None, :] == goal[owner][:, None]
        error[same & (label == 0)] = 0
        error *= self.rate
        np.add.at(self.phi_in, rows, error @ o)
        np.add.at(self.phi_out, columns, error.T @ c)
        np.add.at(self.updates, rows, 1)
        self.pairs += len(rows)
        return error.shape

    def _lockstep(self, walks: list[np.ndarray], n_windows: int) -> None:
        """Groups of ``n_windows`` walks advance together, many groups in lockstep: a step is a window of every walk.

        A group has its own targets and negatives, and its matrix product; groups meet
        in the sums of their moves alone, as many of them as rarely share a node.
        Context vectors are loaded into local buffers for ``window`` steps and their
        moves are added when these end; vectors of targets and negatives are updated
        in place.
        """
        lanes = min(MOST_LANES, max(1, len(self.phi_in) // NODES_A_LANE)) * n_windows
        # matrices of many nodes are read from memory at random: single precision halves that
        held = (self.phi_in, self.phi_out) if len(self.phi_in) < MOST_LANES * NODES_A_LANE else tuple(x.astype(np.float32) for x in (self.phi_in, self.phi_out))
        for begin in range(0, len(walks), 16 * lanes):  # walks of like lengths share their steps
            some = sorted(walks[begin : begin + 16 * lanes], key=len, reverse=True)
            for lo in range(0, len(some), lanes):
                self._lane_steps(some[lo : lo + lanes], n_windows, *held)
        self.phi_in[:], self.phi_out[:] = held

    def _aligned(self, walks: list[np.ndarray], n_windows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(sizes, ids, which ids are real) of walks side by side; their updates and pairs are counted."""
        size = np.zeros(-(-len(walks) // n_windows) * n_windows, dtype=np.int64)
        size[: len(walks)] = [len(w) for w in walks]
        place = np.arange(int(size.max()))
        real = place < size[:, None]
        ids = np.zeros(real.shape, dtype=np.int64)
        ids[real] = np.concatenate(walks)
        times = np.where(real, np.minimum(place + self.window, size[:, None] - 1) - np.maximum(place - self.window, 0), 0)
        np.add.at(self.updates, ids.ravel(), times.ravel())
        self.pairs += int(times.sum())
        return size, ids, real

    def _lane_steps(self, walks: list[np.ndarray], n_windows: int, phi_in: np.ndarray, phi_out: np.ndarray) -> None:
        d, reach, (size, ids, real) = phi_in.shape[1], self.window, self._aligned(walks, n_windows)
        groups, longest = len(size) // n_windows, ids.shape[1]
        own = np.eye(n_windows, n_windows + self.negatives, dtype=bool)
        for first in range(0, longest, reach):
            lo, hi = max(0, first - reach), min(longest, first + 2 * reach)
            loaded = phi_in[ids[:, lo:hi]].reshape(groups, n_windows, hi - lo, d)
            held = loaded.copy()
            for i in range(first, min(first + reach, longest)):
                a, b = max(lo, i - reach), min(hi, i + reach + 1)
                asked = real[:, i] & (size > 1)
                valid = real[:, a:b] & asked[:, None]
                valid[:, i - a] = False
                if not asked.any():
                    break
                goal, noise = ids[:, i].reshape(groups, n_windows), self.noise(groups, self.negatives)
                columns = np.concatenate([goal, noise], axis=1)
                near = held[:, :, a - lo : b - lo]
                c, o = near.reshape(groups, -1, d), phi_out[columns]
                error = c @ o.transpose(0, 2, 1)
                # -sigmoid(x) = 1 / (1 + e^x) - 1, in place
                np.clip(error, -30, 30, out=error)
                np.exp(error, out=error)
                error += 1
                np.reciprocal(error, out=error)
                error -= 1
                error = error.reshape(groups, n_windows, b - a, -1)
                for k in range(n_windows):
                    error[:, k, :, k] += 1
                # a column equal to a row's target is left out, and those of walks that have ended
                kept = own | (columns[:, None, :] != goal[:, :, None])
                kept[:, :, :n_windows] &= asked.reshape(groups, 1, n_windows)
                error *= (kept * phi_in.dtype.type(self.rate))[:, :, None, :]
                error *= valid.reshape(groups, n_windows, b - a, 1)
                error = error.reshape(groups, -1, columns.shape[1])
                move, back = error @ o, error.transpose(0, 2, 1) @ c
                if np.einsum("grc,gc->gr", np.abs(error), np.sqrt(np.einsum("gcd,gcd->gc", o, o))).max() > LONGEST_MOVE:
                    move = _bounded(move)
                near += move.reshape(near.shape)
                _add_rows(phi_out, columns.ravel(), _bounded(back).reshape(-1, d))
            held -= loaded
            _add_rows(phi_in, ids[:, lo:hi].ravel(), held.reshape(-1, d))

    def train(self, walks: list[np.ndarray], mode: str, n_windows: int = 2) -> None:
        if mode == "pairwise":
            for walk in walks:
                for i in range(len(walk)):
                    for c in self._contexts(walk, i):
                        self.batch([np.array([c])], [walk[i]], self.noise(self.negatives))
        elif mode == "window_shared":
            self._lockstep(walks, 1)
        elif mode == "cross_window":
            # an inverted index from node to windows brings related windows into one batch
            index: dict[int, list[tuple[int, int]]] = {}
            for k, walk in enumerate(walks):
                for i, v in enumerate(walk.tolist()):
                    index.setdefault(v, []).append((k, i))
            done: set[tuple[int, int]] = set()
            for k, walk in enumerate(walks):
                for i in range(len(walk)):
                    if (k, i) in done:
                        continue
                    noise = self.noise(self.negatives)
                    group = [(k, i)]
                    for v in noise.tolist():
                        group += [w for w in index.get(v, ()) if w not in done and w != (k, i)][: max(0, 1 + n_windows - len(group))]
                    done.update(group)
                    parts = [(self._contexts(walks[a], b), walks[a][b]) for a, b in dict.fromkeys(group)]
                    parts = [p for p in parts if len(p[0])]
                    if parts:
                        self.batch([p[0] for p in parts], [p[1] for p in parts], noise)
        elif mode == "multi_window":
            self._lockstep(walks, n_windows)
        else:
            raise ValueError(f"unknown mode {mode!r}")


def initial_vectors(n: int, dims: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return (rng.random((n, dims)) - 0.5) / dims, np.zeros((n, dims))


def train(steps: DataFrame, mode: str = "multi_window", dims: int = 64, window: int = 10, negatives: int = 5, epochs: int = 1, shards: int = 2, n_windows: int = 2, rate: float = 0.05, sync: str = "hotness", periods: int = 2, seed: int = 7) -> DataFrame:
    """(node, rank, phi array, n_updates) after ``epochs`` over the corpus."""
    return train_upto(steps, (epochs,), mode, dims, window, negatives, shards, n_windows, rate, sync, periods, seed)[0]


def train_upto(steps: DataFrame, epochs: tuple[int, ...], mode: str = "multi_window", dims: int = 64, window: int = 10, negatives: int = 5, shards: int = 2, n_windows: int = 2, rate: float = 0.05, sync: str = "hotness", periods: int = 2, seed: int = 7) -> list[DataFrame]:
    """``train`` after each of the ascending ``epochs``, from one training.

    Shards train replicas; after each period one node of every hotness block (or
    all nodes under ``full``) is averaged over the shards; at the end replicas
    merge by their update counts.  Replica rows travel as binary, one row a shard
    and rank range.
    """
    vocab = build_vocab(steps).checkpoint()
    n = vocab.count()
    spark = steps.sparkSession
    noise = noise_table(vocab).orderBy("rank").select("hi").toPandas()["hi"].to_numpy() if n else np.array([1])
    walks = steps.join(vocab.select("node", "rank"), "node").groupBy("round", "walk_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("step", "rank"))), lambda x: x["rank"]).alias("walk"))
    walks = walks.withColumn("shard", F.pmod(F.col("walk_id"), F.lit(shards)).cast("int")).withColumn("period", F.pmod(F.xxhash64("walk_id", "round"), F.lit(periods)).cast("int")).checkpoint()
    start = spark.sparkContext.broadcast((noise, n))
    state = spark.range(shards).select(F.col("id").cast("int").alias("shard"), F.lit(None).cast("binary").alias("a"), F.lit(None).cast("binary").alias("b"), F.lit(None).cast("binary").alias("k"))

    def run(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        noise_hi, size = start.value
        shard = int(key[0])
        held = right.iloc[0] if len(right) else None
        if held is None or held["a"] is None:
            phi_in, phi_out = initial_vectors(size, dims, seed)
            count = np.zeros(size, np.int64)
        else:
            phi_in, phi_out = (np.frombuffer(held[c], np.float64).reshape(size, dims).copy() for c in ("a", "b"))
            count = np.frombuffer(held["k"], np.int64).copy()
        task = Shard(phi_in, phi_out, noise_hi, window, negatives, rate, seed + shard)
        task.train([np.array(w) for w in left.sort_values(["round", "walk_id"])["walk"]] if len(left) else [], mode, n_windows)
        return pd.DataFrame({"shard": [shard], "a": [task.phi_in.tobytes()], "b": [task.phi_out.tobytes()], "k": [(count + task.updates).tobytes()]})

    found = []
    for epoch in range(max(epochs)):
        for period in range(periods):
            part = walks.where(F.col("period") == period).select("shard", "round", "walk_id", "walk")
            state = part.groupBy("shard").cogroup(state.groupBy("shard")).applyInPandas(run, "shard int, a binary, b binary, k binary").checkpoint()
            # one node of every block of equal counts: as many numbers as there are different counts
            nodes = sync_nodes(vocab, epoch * periods + period, seed).join(vocab.select("node", "rank"), "node").select("rank")
            picked = np.arange(n) if sync == "full" else np.array([r["rank"] for r in nodes.collect()] if shards > 1 else [], dtype=np.int64)
            if shards > 1 and len(picked):
                state = _synchronise(state, picked, n, dims).checkpoint()
        if epoch + 1 in epochs:
            found.append(_merged(state, vocab, n, dims))
    return found


def _synchronise(state: DataFrame, picked: np.ndarray, n: int, dims: int) -> DataFrame:
    """Averages the picked rows over the shards: only those rows are exchanged."""
    chosen = state.sparkSession.sparkContext.broadcast(picked)

    def cut(batches):
        for f in batches:
            yield pd.DataFrame({"a": [np.frombuffer(x, np.float64).reshape(n, dims)[chosen.value].tobytes() for x in f["a"]], "b": [np.frombuffer(x, np.float64).reshape(n, dims)[chosen.value].tobytes() for x in f["b"]]})

    rows = state.select("a", "b").mapInPandas(cut, "a binary, b binary").toPandas()  # one row a shard, as many vectors as blocks
    mean = [np.mean([np.frombuffer(x, np.float64).reshape(-1, dims) for x in rows[c]], axis=0) for c in ("a", "b")]
    shared = state.sparkSession.sparkContext.broadcast(mean)

    def paste(batches):
        for f in batches:
            f = f.copy()
            for c, m in zip(("a", "b"), shared.value):
                cells = []
                for x in f[c]:
                    matrix = np.frombuffer(x, np.float64).reshape(n, dims).copy()
                    matrix[chosen.value] = m
                    cells.append(matrix.tobytes())
                f[c] = cells
            yield f

    return state.mapInPandas(paste, "shard int, a binary, b binary, k binary")


def _merged(state: DataFrame, vocab: DataFrame, n: int, dims: int) -> DataFrame:
    def spread(batches):
        for f in batches:
            for a, k in zip(f["a"], f["k"]):
                matrix, count = np.frombuffer(a, np.float64).reshape(n, dims), np.frombuffer(k, np.int64)
                yield pd.DataFrame({"rank": np.arange(n), "phi": list(matrix), "n_updates": count})

    rows = state.select("a", "k").mapInPandas(spread, "rank long, phi array<double>, n_updates long")
    return merge_replicas(rows.withColumnRenamed("rank", "key")).withColumnRenamed("key", "rank").join(vocab.select("node", "rank"), "rank").select("node", "rank", "phi", "n_updates")


def merge_replicas(replicas: DataFrame) -> DataFrame:
    """(key, phi, n_updates): means of the replicas weighted by their updates (plus one)."""
    weight = F.col("n_updates") + 1
    held = replicas.select("key", "n_updates", F.struct("phi", weight.cast("double").alias("k")).alias("r")).groupBy("key").agg(F.collect_list("r").alias("rs"), F.sum("n_updates").alias("n_updates"))
    zero = F.transform(F.element_at("rs", 1)["phi"], lambda x: F.lit(0.0))
    total = F.aggregate("rs", zero, lambda s, r: F.zip_with(s, r["phi"], lambda a, x: a + x * r["k"]))
    mass = F.aggregate("rs", F.lit(0.0), lambda s, r: s + r["k"])
    return held.select("key", F.transform(total, lambda x: x / mass).alias("phi"), "n_updates")


def hotness_blocks(vocab: DataFrame) -> DataFrame:
    """(ocn, node, block_size): nodes of equal frequency form a block."""
    return vocab.select("ocn", "node", F.count("*").over(Window.partitionBy("ocn")).alias("block_size"))


def sync_nodes(vocab: DataFrame, period: int, seed: int = 42) -> DataFrame:
    """(ocn, node): one node of each block, another draw each period."""
    from ..functions.rng import draw_column

    order = F.struct(draw_column(seed, F.lit(period), F.col("node")).alias("d"), "node")
    return vocab.groupBy("ocn").agg(F.min(order).alias("m")).select("ocn", F.col("m.node").alias("node"))

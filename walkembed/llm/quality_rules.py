"""Quality rules: statistics of each text, two fixed rules, and an isolation forest.

The forest isolates texts by random splits of their rule statistics; short path
lengths mean anomalies.  Every tree is grown over all labelled rows that pass the
fixed rules, a level of all trees in one pass: tasks send the counts and ranges of
nodes, never rows.  The cut on its score is calibrated on the same rows by exact
order statistics, so that at most ``max_good_loss`` of the good rows are rejected.

Defined results: null and empty texts have zero words and fail the first rule;
repeated rows score alike; null ids are returned; with fewer than ``min_good_rows``
good labelled rows that pass the fixed rules a cut cannot be calibrated and only the
fixed rules decide; of repeated labelled ids the smallest statistics and label serve; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import checkpointed
from .textkernel import Words, find_words, mix64, text_slices, windows
from .workers import take_over

MIN_GOOD_ROWS = 20
TREES, LEVELS, ROWS_A_TASK = 100, 8, 32_768
MIN_WORDS, REPEAT_SHARE, WINDOW = 20, 30, 8
_SYMBOL = np.zeros(256, dtype=np.int32)
_SYMBOL[list(b"#*$%&|<>")] = 1
_POINT = np.ones(256, dtype=np.int32)
_POINT[0x80:0xC0] = 0  # continuation bytes: the rest counts code points
_UPPER = np.zeros(256, dtype=np.int32)
_UPPER[ord("A") : ord("Z") + 1] = 1
_DIGIT = np.zeros(256, dtype=np.int32)
_DIGIT[ord("0") : ord("9") + 1] = 1
_BREAK = np.uint64(0xD6E8FEB86659FD93)
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
SHAPES = tuple(f"shape{k}" for k in range(8))


def _running(table: np.ndarray, raw: np.ndarray) -> np.ndarray:
    run = np.zeros(len(raw) + 1, dtype=np.int64)
    np.cumsum(table[raw], out=run[1:])
    return run


def _line_counts(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Per text: lines with a word, and those equal to an earlier line of it."""
    n_docs = len(offsets) - 1
    if not len(raw):
        return np.zeros(n_docs, np.int64), np.zeros(n_docs, np.int64)
    breaks = np.flatnonzero(raw == 10)
    start = np.unique(np.concatenate([offsets[:-1], breaks + 1]))
    start = start[start < len(raw)]
    # a line ends at its break, or where its text ends
    doc = np.searchsorted(offsets, start, side="right") - 1
    end = np.minimum(np.append(breaks, len(raw))[np.searchsorted(breaks, start)], offsets[doc + 1])
    words = find_words(raw, offsets)
    filled = np.searchsorted(words.start, end) > np.searchsorted(words.start, start)
    start, end, doc = start[filled], end[filled], doc[filled]
    lines = Words(raw, offsets, start, end, np.searchsorted(start, offsets)).hashes(fold=False) ^ mix64((end - start).astype(np.uint64))
    order = np.lexsort((lines, doc))
    a, d = lines[order], doc[order]
    again = np.zeros(len(a), dtype=bool)
    again[1:] = (a[1:] == a[:-1]) & (d[1:] == d[:-1])
    return np.bincount(doc, minlength=n_docs), np.bincount(d[again], minlength=n_docs)


def text_statistics(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(n_docs, 5) of the base counts, and (n_docs, 8) of the forest's features."""
    words = find_words(raw, offsets)
    first = words.first
    n_words = np.diff(first)
    points = _running(_POINT, raw)
    per_word = np.concatenate([[0], np.cumsum(points[words.end] - points[words.start])])
    word_chars = per_word[first[1:]] - per_word[first[:-1]]
    count = lambda table: (lambda run: run[offsets[1:]] - run[offsets[:-1]])(_running(table, raw))
    n_symbols, upper, digit = count(_SYMBOL), count(_UPPER), count(_DIGIT)
    n_lines, n_dup = _line_counts(raw, offsets)
    hashes = words.hashes(fold=False)
    grams = windows(hashes, WINDOW)
    repeat, distinct, longest = (np.zeros(len(n_words), dtype=np.int64) for _ in range(3))
    sizes = words.end - words.start
    bounds = first.tolist()
    for k, (lo, hi) in enumerate(zip(bounds[:-1], bounds[1:])):
        if hi == lo:
            continue
        distinct[k] = len(np.unique(hashes[lo:hi]))
        longest[k] = sizes[lo:hi].max()
        if hi - lo > WINDOW:
            own = grams[lo : hi - WINDOW + 1]
            ordered = np.sort(own)
            twice = ordered[1:][ordered[1:] == ordered[:-1]]
            if len(twice):
                at = np.flatnonzero(np.isin(own, twice))
                cover = np.zeros(hi - lo + 1, dtype=np.int64)
                np.add.at(cover, at, 1)
                np.add.at(cover, at + WINDOW, -1)
                repeat[k] = (np.cumsum(cover[:-1]) > 0).sum()
    some, chars = np.maximum(n_words, 1), np.maximum(word_chars, 1)
    shapes = np.stack([np.log1p(n_words), word_chars / some, n_symbols / some, n_dup / np.maximum(n_lines, 1), repeat / some, upper / chars, digit / chars, distinct / some**0.9], axis=1)
    return np.stack([n_words, word_chars, n_symbols, n_dup, repeat], axis=1), shapes


@dataclass
class Forest:
    """Isolation trees as arrays: at each node a feature (-1: leaf), a cut, the left child and the path length there."""

    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    depth: np.ndarray
    sample: int
    threshold: float = 1.0

    def score(self, x: np.ndarray) -> np.ndarray:
        """Anomaly scores in (0, 1): higher is easier to isolate."""
        total = np.zeros(len(x))
        rows = np.arange(len(x))
        for t in range(len(self.feature)):
            node = np.zeros(len(x), dtype=np.int64)
            while True:
                f = self.feature[t][node]
                inner = f >= 0
                if not inner.any():
                    break
                right = x[rows, np.maximum(f, 0)] >= self.cut[t][node]
                node = np.where(inner, self.left[t][node] + right, node)
            total += self.depth[t][node]
        return 2.0 ** (-total / max(1, len(self.feature)) / max(_expected(self.sample), 1e-9))


def _expected(n: int) -> float:
    """Mean path length of an unsuccessful search among n points."""
    return 0.0 if n < 2 else 1.0 if n == 2 else 2 * (np.log(n - 1) + 0.5772156649) - 2 * (n - 1) / n


def _descend(feature: np.ndarray, cut: np.ndarray, x: np.ndarray, level: int) -> np.ndarray:
    """The place of each row in one tree's ``level``, below zero if a leaf holds it before; children of k are 2k + 1 and 2k + 2."""
    node, rows = np.zeros(len(x), dtype=np.int64), np.arange(len(x))
    for _ in range(level):
        f = feature[node]
        node = np.where(f >= 0, 2 * node + 1 + (x[rows, np.maximum(f, 0)] >= cut[node]), node)
    return node - (2**level - 1)


@dataclass
class Ranges:
    """The rows of every node of a level: their number, and the least and largest value of each feature."""

    count: np.ndarray
    low: np.ndarray
    high: np.ndarray

    @staticmethod
    def none(trees: int, level: int, width: int) -> "Ranges":
        shape = (trees, 2**level, width)
        return Ranges(np.zeros(shape[:2], np.int64), np.full(shape, np.inf), np.full(shape, -np.inf))

    def add(self, feature: np.ndarray, cut: np.ndarray, x: np.ndarray, level: int) -> None:
        for t in range(len(feature)):
            place = _descend(feature[t], cut[t], x, level)
            live = np.flatnonzero(place >= 0)
            if not len(live):
                continue
            order = live[np.argsort(place[live], kind="stable")]
            ids, first, n = np.unique(place[order], return_index=True, return_counts=True)
            self.count[t, ids] += n
            self.low[t, ids] = np.minimum(self.low[t, ids], np.minimum.reduceat(x[order], first))
            self.high[t, ids] = np.maximum(self.high[t, ids], np.maximum.reduceat(x[order], first))


def grow_levels(measure: Callable[[np.ndarray, np.ndarray, int], Ranges], n_rows: int, trees: int = TREES, levels: int = LEVELS, seed: int = 5) -> Forest:
    """A forest from passes over the rows: ``measure(feature, cut, level)`` gives the ranges of that level's nodes."""
    rng = np.random.default_rng(seed)
    size = 2 ** (levels + 1) - 1
    feature = np.full((trees, size), -1, dtype=np.int64)
    cut, depth = np.zeros((trees, size)), np.zeros((trees, size))
    left = np.tile(2 * np.arange(size) + 1, (trees, 1))
    for level in range(levels + 1):
        found = measure(feature, cut, level)
        for t, k in zip(*np.nonzero(found.count)):
            node, low, high = k + 2**level - 1, found.low[t, k], found.high[t, k]
            spread = np.flatnonzero(low < high)
            if level == levels or not len(spread):
                depth[t, node] = level + _expected(int(found.count[t, k]))
                continue
            f = rng.choice(spread)
            feature[t, node], cut[t, node] = f, low[f] + (high[f] - low[f]) * (1 - rng.random())
    return Forest(feature, cut, left, depth, n_rows)


def grow(x: np.ndarray, trees: int = TREES, levels: int = LEVELS, seed: int = 5) -> Forest:
    """A forest over rows in memory."""

    def measure(feature: np.ndarray, cut: np.ndarray, level: int) -> Ranges:
        found = Ranges.none(trees, level, x.shape[1])
        found.add(feature, cut, x, level)
        return found

    return grow_levels(measure, len(x), trees, levels, seed)


def _matrix(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in SHAPES], axis=1).reshape(-1, len(SHAPES))


def grow_frame(rows: DataFrame, n_rows: int, trees: int = TREES, levels: int = LEVELS, seed: int = 5) -> Forest:
    """The same forest over a frame with the columns ``SHAPES``."""
    context = rows.sparkSession.sparkContext

    def measure(feature: np.ndarray, cut: np.ndarray, level: int) -> Ranges:
        shared = context.broadcast((feature, cut))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = Ranges.none(trees, level, len(SHAPES))
            for batch in batches:
                own.add(*shared.value, _matrix(batch), level)
            t, k = np.nonzero(own.count)
            columns = [pa.array(t * 2**level + k), pa.array(own.count[t, k]), *(pa.array(np.ascontiguousarray(a[t, k, f])) for a in (own.low, own.high) for f in range(len(SHAPES)))]
            yield pa.RecordBatch.from_arrays(columns, names)

        ends = [f"{e}{f}" for e in ("low", "high") for f in range(len(SHAPES))]
        names = ["node", "n", *ends]
        parts = rows.select(*SHAPES).mapInArrow(run, ", ".join(f"{c} {'long' if c in ('node', 'n') else 'double'}" for c in names))
        merged = parts.groupBy("node").agg(F.sum("n").alias("n"), *((F.min if c.startswith("low") else F.max)(c).alias(c) for c in ends)).toArrow()
        shared.unpersist()
        found = Ranges.none(trees, level, len(SHAPES))
        t, k = np.divmod(merged.column("node").to_numpy(), 2**level)
        found.count[t, k] = merged.column("n").to_numpy()
        for f in range(len(SHAPES)):
            found.low[t, k, f], found.high[t, k, f] = merged.column(f"low{f}").to_numpy(), merged.column(f"high{f}").to_numpy()
        return found

    return grow_levels(measure, n_rows, trees, levels, seed)


def base_failed(counts: np.ndarray) -> np.ndarray:
    return (counts[:, 0] < MIN_WORDS) | (100 * counts[:, 4] > REPEAT_SHARE * counts[:, 0])


def ranked(scores: DataFrame, place: int, few: int = 65_536) -> float:
    """The value of ``s`` at ``place`` (from 0) of all rows in ascending order: ranges narrow until few rows are left."""
    while True:
        n, low, high = scores.agg(F.count("*"), F.min("s"), F.max("s")).first()
        if low == high:
            return low
        if n <= few:
            return float(np.sort(scores.select("s").toArrow().column("s").to_numpy())[place])
        bucket = F.floor((F.col("s") - low) / (high - low) * 1024)
        for row in scores.groupBy(bucket.alias("b")).agg(F.count("*").alias("n"), F.min("s").alias("low"), F.max("s").alias("high")).orderBy("b").collect():
            if place < row["n"]:
                break
            place -= row["n"]
        scores = scores.where(F.col("s").between(row["low"], row["high"]))


def fit(rows: DataFrame, max_good_loss: float = 0.002, min_good_rows: int = MIN_GOOD_ROWS) -> Forest | None:
    """A forest over all rows (label, ``SHAPES``) with its cut: the one that rejects most bad rows at an accepted loss of good ones."""
    counted = rows.agg(F.count("*"), F.sum((F.col("label") == 1).cast("long"))).first()
    if (counted[1] or 0) < min_good_rows:
        return None
    # tasks by rows, not by partitions of the exchange before: each sends up to a row a node
    rows = rows.coalesce(1 + counted[0] // ROWS_A_TASK)
    forest = grow_frame(rows, counted[0])
    shared = rows.sparkSession.sparkContext.broadcast(forest)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("label"), pa.array(shared.value.score(_matrix(batch)), pa.float64())], ["label", "s"])

    scores = checkpointed(rows.select("label", *SHAPES).mapInArrow(run, "label int, s double"))
    # above every accepted good score, with the margin that a new good text of the same kind may need
    low = ranked(scores.where("label = 1"), max(0, int(np.ceil(counted[1] * (1 - max_good_loss))) - 1))
    higher = scores.where((F.col("label") == 0) & (F.col("s") > low))
    n = higher.count()
    if not n:
        forest.threshold = low + 0.05
        return forest
    at = (n - 1) * 0.25
    below = ranked(higher, int(at))
    quarter = below if at == int(at) else below + (ranked(higher, int(at) + 1) - below) * (at - int(at))
    forest.threshold = float((low + quarter) / 2)
    return forest


def measured(docs: DataFrame) -> DataFrame:
    """(doc_id, the base counts, base_failed, ``SHAPES``) of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("rules")
        for batch in batches:
            parts = [text_statistics(raw, offsets) for _, _, raw, offsets in text_slices(batch.column("text"))]
            counts = np.concatenate([p[0] for p in parts]) if parts else np.zeros((0, 5), np.int64)
            x = np.concatenate([p[1] for p in parts]) if parts else np.zeros((0, 8))
            columns = [batch.column("doc_id"), *(pa.array(np.ascontiguousarray(counts[:, k]), pa.int64()) for k in range(5)), pa.array(base_failed(counts), pa.bool_()), *(pa.array(np.ascontiguousarray(x[:, k]), pa.float64()) for k in range(8))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", *COUNTS, "base_failed", *SHAPES])

    schema = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS) + ", base_failed boolean, " + ", ".join(f"{c} double" for c in SHAPES)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, schema)


def training_rows(stats: DataFrame, labels: DataFrame) -> DataFrame:
    """(label, ``SHAPES``) of every labelled document that passes the fixed rules, one row an id."""
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label")).where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1)).groupBy("doc_id").agg(F.min("label").alias("label"))
    fair = stats.where(~F.col("base_failed")).groupBy("doc_id").agg(F.min(F.struct(*SHAPES)).alias("x"))
    return fair.join(marks, "doc_id").select("label", "x.*")


def screen(docs: DataFrame, labels: DataFrame, max_good_loss: float = 0.002) -> DataFrame:
    """(doc_id, the base counts, base_failed, kept, anomaly) of every document."""
    stats = checkpointed(measured(docs))
    forest = fit(checkpointed(training_rows(stats, labels)), max_good_loss)
    shared = docs.sparkSession.sparkContext.broadcast(forest)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            anomaly = own.score(_matrix(batch)) if own is not None else np.zeros(len(batch))
            failed = batch.column("base_failed").to_numpy(zero_copy_only=False)
            kept = ~failed & (anomaly <= own.threshold if own is not None else True)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", *COUNTS, "base_failed")), pa.array(kept, pa.bool_()), pa.array(anomaly, pa.float64())], ["doc_id", *COUNTS, "base_failed", "kept", "anomaly"])

    schema = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS) + ", base_failed boolean, kept boolean, anomaly double"
    return stats.mapInArrow(run, schema)

"""Document quality by naive-Bayes support vectors.

Features are n-gram indicators: distinct words, n-grams of word *shapes* (length,
case, digits, symbols, final punctuation, equal to the word before) each with a
bucket of its share in the text, so long and short texts compare, and buckets of
the text's own repetition.  Indicators are hashed, scaled by the classes'
log-count ratios and normalised; a linear hinge loss is minimised by dual
coordinate descent, and its margins become probabilities by a logistic curve
fitted on held-back rows.

Training uses at most ``max_train_rows`` labelled rows a class (documented bound,
chosen by hash); scoring is one map over all texts with a broadcast of two
weight vectors of fixed size.

Defined results: null and empty texts get the score of a text without words; with
no labelled rows of both classes every score is the smoothed share of class 1;
repeated rows score alike; null ids are returned; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import crc_bucket, labelled_sample
from .textkernel import Words, find_words, mix64, text_slices, windows
from .workers import take_over

BITS = 18
MAX_TRAIN_ROWS = 3000
THRESHOLD = 0.7

_UPPER = np.zeros(256, dtype=np.int32)
_UPPER[ord("A") : ord("Z") + 1] = 1
_LOWER = np.zeros(256, dtype=np.int32)
_LOWER[ord("a") : ord("z") + 1] = 1
_LOWER[128:] = 1
_DIGIT = np.zeros(256, dtype=np.int32)
_DIGIT[ord("0") : ord("9") + 1] = 1
_MARK = np.zeros(256, dtype=np.int32)
_MARK[list(b"#*$%&|<>@^~=+_\\{}[]")] = 1
_TAIL = np.zeros(256, dtype=np.int64)
_TAIL[list(b".?!")] = 1
_TAIL[list(b",;:")] = 2
_TAIL[list(b"\"')]}")] = 3
_TAIL[list(b"#*$%&|<>@^~=+_\\{[(-/")] = 4
_LEN = np.minimum(np.log2(np.arange(4096) + 1) * 1.5, 7).astype(np.int64)


def _per_word(table: np.ndarray, words: Words) -> np.ndarray:
    run = np.zeros(len(words.raw) + 1, dtype=np.int32)
    np.cumsum(table[words.raw], out=run[1:])
    return run[words.end] - run[words.start]


def word_shapes(words: Words, hashes: np.ndarray) -> np.ndarray:
    """A small integer a word that keeps how it looks and forgets what it is."""
    if not len(hashes):
        return np.empty(0, dtype=np.int64)
    upper, lower, digit, mark = (_per_word(t, words) for t in (_UPPER, _LOWER, _DIGIT, _MARK))
    last, size = words.raw[words.end - 1], words.end - words.start
    before_last = words.raw[np.maximum(words.end - 2, words.start)]
    tail = _TAIL[last] + 5 * ((size > 2) & (before_last == last) & (_TAIL[last] > 0))
    same = np.zeros(len(hashes), dtype=np.int64)
    same[1:] = hashes[1:] == hashes[:-1]
    case = np.where(upper == 0, 0, np.where((lower == 0) & (upper > 1), 2, np.where(_UPPER[words.raw[words.start]] > 0, 1, 3)))
    shape = _LEN[np.minimum(size, 4095)]
    for value, base in ((case, 4), (np.minimum(digit, 3), 4), (np.minimum(mark, 3), 4), (tail, 10), (same, 2)):
        shape = shape * base + value
    return shape


def _share_bucket(part: np.ndarray, whole: int) -> np.ndarray:
    return np.maximum(-12, np.floor(np.log2(part / max(whole, 1)) * 1.5)).astype(np.int64)


def features(words: Words, bits: int = BITS) -> Iterator[np.ndarray]:
    """Sorted distinct feature ids of each text."""
    hashes = words.hashes()
    shapes = word_shapes(words, hashes)
    grams3 = windows(hashes, 3)
    pairs = shapes[:-1] * 1_000_003 + shapes[1:] if len(shapes) else shapes
    shift = np.uint64(64 - bits)
    bounds = words.first.tolist()
    for lo, hi in zip(bounds[:-1], bounds[1:]):
        n = hi - lo
        distinct = np.unique(hashes[lo:hi])
        parts = [distinct]
        own = [(1, int(np.log2(n + 1) * 2)), (2, int(20 * len(distinct) / n) if n else -1)]
        for order, (ids, many) in enumerate(((shapes[lo:hi], n), (pairs[lo : hi - 1], n - 1))):
            if many > 0:
                kinds, counts = np.unique(ids, return_counts=True)
                parts.append(mix64((kinds * 64 + _share_bucket(counts, many) + 32).astype(np.uint64) + np.uint64((order + 1) << 56)))
        if n >= 3:
            own.append((3, int(20 * len(np.unique(grams3[lo : hi - 2])) / (n - 2))))
        parts.append(mix64(np.array([(k << 48) + v + 1000 for k, v in own], dtype=np.uint64)))
        yield np.unique(np.concatenate(parts) >> shift).astype(np.int64)


@dataclass
class Model:
    """``weight`` = hinge weights times ratios, ``square`` = squared ratios; logistic a, b on the margin."""

    weight: np.ndarray
    square: np.ndarray
    bias: float
    slope: float
    shift: float

    def score(self, ids: np.ndarray) -> float:
        norm = float(np.sqrt(self.square[ids].sum())) or 1.0
        margin = float(self.weight[ids].sum()) / norm + self.bias
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -40, 40)))


def log_count_ratios(rows: list[np.ndarray], y: np.ndarray, size: int, smooth: float = 1.0) -> np.ndarray:
    totals = []
    for k in (1, 0):
        count = np.full(size, smooth)
        picked = [r for r, label in zip(rows, y) if label == k]
        if picked:
            count += np.bincount(np.concatenate(picked), minlength=size)
        totals.append(np.log(count) - np.log(len(picked) + 2 * smooth))
    return totals[0] - totals[1]


def dual_descent(rows: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, size: int, cost: float, epochs: int, seed: int) -> tuple[np.ndarray, float]:
    """Weights and bias of the L2-regularised hinge loss; classes weigh alike."""
    sign = np.where(y == 1, 1.0, -1.0)
    share = np.array([max(1, (y == k).sum()) for k in (0, 1)])
    bound = cost * len(y) / (2 * share[y])
    w, bias, alpha = np.zeros(size), 0.0, np.zeros(len(y))
    square = np.array([float((v * v).sum()) + 1.0 for v in values])
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(y)):
            gradient = sign[i] * (float(w[rows[i]] @ values[i]) + bias) - 1
            new = min(max(alpha[i] - gradient / square[i], 0.0), bound[i])
            step = (new - alpha[i]) * sign[i]
            if step:
                w[rows[i]] += step * values[i]
                bias += step
                moved = max(moved, abs(step))
                alpha[i] = new
        if moved < 1e-3:
            break
    return w, bias


def logistic_curve(margins: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift that make margins probabilities (regularised Newton steps)."""
    a, b = 1.0, 0.0
    target = np.where(y == 1, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margins + b, -30, 30)))
        g, h = p - target, p * (1 - p) + 1e-9
        grad = np.array([(g * margins).sum() + 1e-2 * (a - 1), g.sum() + 1e-2 * b])
        hess = np.array([[(h * margins * margins).sum() + 1e-2, (h * margins).sum()], [(h * margins).sum(), h.sum() + 1e-2]])
        da, db = np.linalg.solve(hess, grad)
        a, b = a - np.clip(da, -2, 2), b - np.clip(db, -2, 2)
        if abs(da) + abs(db) < 1e-6:
            break
    return max(a, 0.05), b


def fit(texts: list[str], labels: list[int], bits: int = BITS, cost: float = 1.0, epochs: int = 12, seed: int = 11) -> Model:
    size, y = 1 << bits, np.array(labels, dtype=np.int64)
    flat = np.zeros(size)
    if len(set(labels)) < 2:
        share = (y.sum() + 1) / (len(y) + 2)
        return Model(flat, flat, 0.0, 1.0, float(np.log(share / (1 - share))))
    rows = [ids for _, _, raw, offsets in text_slices(pa.array(texts, pa.large_string())) for ids in features(find_words(raw, offsets), bits)]

    def train(pick: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        some = [rows[i] for i in pick]
        ratio = log_count_ratios(some, y[pick], size)
        values = [ratio[r] / (np.sqrt((ratio[r] ** 2).sum()) or 1.0) for r in some]
        w, bias = dual_descent(some, values, y[pick], size, cost, epochs, seed)
        return w * ratio, ratio**2, bias

    order = np.random.default_rng(seed).permutation(len(y))
    back = order[: max(2, len(y) // 4)]
    rest = order[len(back) :]
    slope, shift = 4.0, 0.0
    if len(set(y[rest])) == 2 and len(set(y[back])) == 2:
        part = Model(*train(rest), 1.0, 0.0)
        margins = np.array([part.weight[rows[i]].sum() / (np.sqrt(part.square[rows[i]].sum()) or 1.0) + part.bias for i in back])
        slope, shift = logistic_curve(margins, y[back])
    return Model(*train(np.arange(len(y))), float(slope), float(shift))


def score_documents(docs: DataFrame, model: Model, bits: int = BITS) -> DataFrame:
    """(doc_id, score) of every text."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weight.astype(np.float32), model.square.astype(np.float32), model.bias, model.slope, model.shift))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("quality")
        own = Model(*shared.value)
        for batch in batches:
            out = [own.score(ids) for _, _, raw, offsets in text_slices(batch.column("text")) for ids in features(find_words(raw, offsets), bits)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, held_out: tuple[int, int] | None = (4, 2), max_train_rows: int = MAX_TRAIN_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    model = fit(*labelled_sample(docs, labels, "quality", max_train_rows, held_out))
    out = score_documents(docs, model)
    away = crc_bucket("doc_id", held_out[0]) == held_out[1] if held_out else F.lit(False)
    return out.select("doc_id", away.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep(docs: DataFrame, model: Model, threshold: float = THRESHOLD, bits: int = BITS) -> DataFrame:
    """The rows of ``docs`` that score at least ``threshold``, with all their columns, in one map."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weight.astype(np.float32), model.square.astype(np.float32), model.bias, model.slope, model.shift))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("quality")
        own = Model(*shared.value)
        for batch in batches:
            fine = [own.score(ids) >= threshold for _, _, raw, offsets in text_slices(batch.column("text")) for ids in features(find_words(raw, offsets), bits)]
            yield batch.filter(pa.array(fine, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)

"""Order-preserving packing of documents into fixed-length token sequences.

Documents, each closed by an end id, form one token stream a partition.  The
stream is cut into windows of at most ``length`` tokens.  Where to cut is a
shortest path over candidate cuts:

* document borders cost nothing, sentence borders ``SENTENCE`` and other places
  ``MIDDLE`` (offered every ``STRIDE`` tokens inside longer sentences);
* a window costs ``WINDOW`` plus its padding: up to ``length``, or none if its
  size is a power of two.

The padding of a window is linear in its size, so the best predecessor within
reach is the front of a monotone queue and every candidate costs amortised O(1),
besides the candidates that lie a power of two before it, which are all tried.
The stream is solved in blocks; each block's last window is carried over, so
memory is bounded and only a partition's last window is cut short.  There is no
shuffle: each input partition packs itself, a replayed task repeats its rows.

Defined results: null and empty texts give the end id alone; long texts span
sequences; repeated rows are packed again, each on its own; an empty table gives
no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import deque
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .wordcache import WordEncoder, encoder

LENGTH, END_ID = 2048, 1
SENTENCE, MIDDLE, WINDOW, STRIDE = 3, 24, 12, 32
_BLOCK_TOKENS = 400_000
_BLOCK_CHARS = 2_000_000
_SPACE = re.compile("[\x09-\x0d ]")


def default_tokenizer() -> str:
    from public_tokenizers import path

    return path("word_bpe_49k.json")


def padding(size: int, length: int) -> int:
    return 0 if size & (size - 1) == 0 else length - size


def cut_candidates(total: int, doc_ends: np.ndarray, sentence_ends: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted candidate cuts after 0, and the penalty of each; gaps never exceed ``length``."""
    penalty = np.full(total + 1, -1, dtype=np.int16)
    penalty[sentence_ends] = SENTENCE
    penalty[doc_ends] = 0
    penalty[total] = 0
    at = np.flatnonzero(penalty[1:] >= 0) + 1
    stride = min(STRIDE, length)
    gaps = np.diff(np.concatenate([[0], at]))
    more = (gaps - 1) // stride
    if more.any():
        start = np.repeat(at - gaps, more)
        step = np.arange(more.sum()) - np.repeat(np.cumsum(more) - more, more) + 1
        inner = start + step * stride
        penalty[inner] = MIDDLE
        at = np.flatnonzero(penalty[1:] >= 0) + 1
    return at, penalty[at]


def best_cuts(at: np.ndarray, penalty: np.ndarray, length: int, least_power: int = 32) -> list[int]:
    """Cuts of the cheapest partition of [0, at[-1]); the last cut is at[-1].

    Windows of a power of two tokens, from ``least_power`` on, cost no padding.
    """
    places = [0, *at.tolist()]
    index = np.full(places[-1] + 1, -1, dtype=np.int64)
    index[places] = np.arange(len(places))
    before = at[:, None] - np.array([1 << k for k in range(least_power.bit_length() - 1, length.bit_length())], dtype=np.int64)
    before = np.where(before >= 0, index[np.maximum(before, 0)], -1)
    exact = before[before >= 0].tolist()  # candidates a power of two before, place by place
    upto = np.cumsum((before >= 0).sum(1)).tolist()
    done = 0
    cost = [0] * len(places)
    back = [0] * len(places)
    queue: deque[tuple[int, int]] = deque([(0, 0)])  # (cost + place, index), cost + place ascending
    for j, extra in enumerate(penalty.tolist(), 1):
        place = places[j]
        while places[queue[0][1]] < place - length:
            queue.popleft()
        value, i = queue[0]
        value += length - place
        for k in exact[done : upto[j - 1]]:
            if cost[k] < value:
                value, i = cost[k], k
        done = upto[j - 1]
        cost[j] = value = value + extra + WINDOW
        back[j] = i
        value += place
        while queue and queue[-1][0] >= value:
            queue.pop()
        queue.append((value, j))
    cuts, j = [], len(places) - 1
    while j:
        cuts.append(places[j])
        j = back[j]
    return cuts[::-1]


class _Stream:
    """Tokens not yet packed, and of each document its id, its tokens in all, here and before."""

    def __init__(self, length: int, ends: np.ndarray, numbers: Iterator[int], emit_ids: bool):
        self.length, self.ends, self.numbers, self.emit_ids = length, ends, numbers, emit_ids
        self.names: list[int | None] = []
        none = np.empty(0, np.int64)
        self.totals, self.sizes, self.before = none, none, none
        self.chunks: list[np.ndarray] = []
        self.held = 0

    def add(self, names: list[int | None], ids: np.ndarray, sizes: np.ndarray) -> None:
        self.names += names
        self.totals = np.concatenate([self.totals, sizes])
        self.sizes = np.concatenate([self.sizes, sizes])
        self.before = np.concatenate([self.before, np.zeros(len(sizes), np.int64)])
        self.chunks.append(ids)
        self.held += len(ids)

    def pack(self, last: bool) -> pa.RecordBatch | None:
        if not self.held:
            return None
        ids = np.concatenate(self.chunks)
        doc_ends = np.cumsum(self.sizes)
        at, penalty = cut_candidates(len(ids), doc_ends, np.flatnonzero(self.ends[np.minimum(ids, len(self.ends) - 1)]) + 1, self.length)
        cuts = best_cuts(at, penalty, self.length, 1)
        if not last:
            cuts.pop()  # this window may still grow
        if not cuts:
            return None
        packed = cuts[-1]
        windows = np.array([0, *cuts])
        doc_begins = doc_ends - self.sizes
        edges = np.unique(np.concatenate([windows, doc_ends[doc_ends < packed]]))
        begin, end = edges[:-1], edges[1:]
        doc = np.searchsorted(doc_ends, begin, side="right")
        window = np.searchsorted(windows, begin, side="right") - 1
        names = np.array([next(self.numbers) for _ in cuts], dtype=np.int64)
        view = memoryview(ids.tobytes())
        crc = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(begin.tolist(), end.tolist())]
        columns = [pa.array(self.names, pa.int64()).take(pa.array(doc)), pa.array(begin - doc_begins[doc] + self.before[doc]), pa.array(end - begin), pa.array(crc, pa.int64()), pa.array(self.totals[doc]), pa.array(names[window]), pa.array(begin - windows[window])]
        fields = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
        if self.emit_ids:
            columns.append(pa.ListArray.from_arrays(pa.array(edges, pa.int32()), pa.array(ids[:packed].astype(np.int32))))
            fields.append("ids")
        rest = int(np.searchsorted(doc_ends, packed, side="right"))
        skip = np.maximum(0, packed - doc_begins[rest:])
        self.names, self.totals = self.names[rest:], self.totals[rest:]
        self.before, self.sizes = self.before[rest:] + skip, self.sizes[rest:] - skip
        self.chunks, self.held = [ids[packed:].copy()], len(ids) - packed
        return pa.RecordBatch.from_arrays(columns, fields)


def _encoded(words: WordEncoder, texts: pa.Array, chars: list[int]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, last row + 1, ids, ids of each row) for rows of a bounded number of characters.

    A longer text is cut at white space, which no id spans, and put together again.
    """
    lo = held = 0
    for k, size in enumerate(chars):
        held += size
        if held < _BLOCK_CHARS and k < len(chars) - 1:
            continue
        if held < 2 * _BLOCK_CHARS:
            yield lo, k + 1, *words.encode(texts.slice(lo, k + 1 - lo))
        else:
            if k > lo:
                yield lo, k, *words.encode(texts.slice(lo, k - lo))
            text, at, ids = texts[k].as_py(), 0, []
            while at < len(text):
                border = _SPACE.search(text, at + _BLOCK_CHARS)
                stop = border.end() if border else len(text)
                ids.append(words.encode(pa.array([text[at:stop]], pa.large_string()))[0])
                at = stop
            whole = np.concatenate(ids) if ids else np.empty(0, "<u4")
            yield k, k + 1, whole, np.array([len(whole)])
        lo, held = k + 1, 0


def pack(docs: DataFrame, tokenizer: str | None = None, length: int = LENGTH, end_id: int = END_ID, emit_ids: bool = False) -> DataFrame:
    """A row for each piece of a document in a sequence.

    ``start`` and ``length`` place the piece in its document's ids, ``offset`` in
    its sequence; ``ids_crc32`` is the crc32 of its ids as little-endian unsigned
    32-bit integers; ``emit_ids`` adds the ids themselves.
    """
    tokenizer = tokenizer or default_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = encoder(tokenizer)
        task = TaskContext.get()
        numbers = count((task.partitionId() if task else 0) << 36)
        stream = _Stream(length, words.sentence_ends(), numbers, emit_ids)
        for batch in batches:
            names, column = batch.column("doc_id").to_pylist(), batch.column("text")
            for lo, hi, ids, sizes in _encoded(words, column, pc.utf8_length(column).fill_null(0).to_pylist()):
                stream.add(names[lo:hi], np.insert(ids, np.cumsum(sizes), end_id), sizes + 1)
                if stream.held >= _BLOCK_TOKENS and (out := stream.pack(False)) is not None:
                    yield out
        if (out := stream.pack(True)) is not None:
            yield out

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids array<int>" * emit_ids
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, schema)

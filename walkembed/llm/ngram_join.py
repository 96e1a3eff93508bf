"""Exact n-gram Jaccard join by prefix filters under several global orders.

Two texts link when the Jaccard similarity of their sets of distinct word
n-grams reaches a threshold t.  A linked pair must share, under *every* total
order of the n-grams, one of the first ``n - ceil(t*n) + 1`` n-grams of both
sets.  Four orders are used: a hash order to find the classes that can have a
partner at all; among those, rarest first and two more hash orders.  Pairs come
from the rarest-first order, must also meet in the prefixes of the other two, and
are then verified exactly.

How it scales
-------------
* Texts with equal sets form a class; only classes are joined (a hash aggregate).
* Of each class only a prefix of about a quarter of its n-grams is dealt by hash
  range, and a block of texts sends an n-gram once however many of its texts hold
  it, so a very common n-gram is a row a block.  Classes that share too few
  n-grams of their prefix with others are done.
* The whole sets of the remaining classes are counted over the same kind of
  blocks; an n-gram of a single class cannot match, and a class with fewer than
  ``ceil(t*n)`` shared n-grams cannot have a partner.
* Groups of near copies collapse around pivots (classes with the same smallest
  hash are compared with a few pivots, large groups in salted parts).  Later only
  pairs of classes in *different* components are generated, so a group of copies
  is never expanded into its pairs, yet every link that joins two components is
  found: the components are exact.
* Classes that could still link across components form cells; a large cell is cut
  in parts of bounded rows and n-grams that meet pairwise, but the parts of its
  largest component don't meet each other.
* Nothing but scalars reaches the driver; every step is a checkpointed table.

Defined results: null text and texts without words have an empty set and link
with nothing; rows with a null id are returned with a null component; repeated
ids are one document per row with the same component if their texts link; extra
columns are ignored, but those named in ``carry`` come along.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .runtime import checkpointed, lookup, partitions, release_shuffles
from .textkernel import distinct_shingles, find_words, mix64, text_slices
from .workers import take_over

WIDTH, THRESHOLD = 5, 80
TOKENS_PER_RANGE, MIN_RANGES = 500_000, 16
_TOKENS_PER_BLOCK = 2_000_000
_TOKENS_PER_SET_BLOCK = 500_000
_PIVOTS = 8
_GROUP_PART = 512
_CELL_ROWS, _CELL_TOKENS = 256, 1_000_000
_FIRST_ORDER = np.uint64(0xA54FF53A5F1D36F1)
_SEEDS = [np.uint64(s) for s in (0x6A09E667F3BCC909, 0xBB67AE8584CAA73B, 0x3C6EF372FE94F82B)]


def need(n: int, threshold: int) -> int:
    """Smallest overlap that a set of n elements needs with any partner."""
    return -(-threshold * n // 100)


def spare(n: int) -> int:
    """N-grams by which the dealt prefix of a set of n is longer than one match would take.

    A linked pair's first common n-grams lie in both prefixes, as many as the
    smaller of their spares: a class must share at least ``spare(need(n))``.
    """
    return 1 + n // 20


def linked(n1: int, n2: int, overlap: int, threshold: int) -> bool:
    return 100 * overlap >= threshold * (n1 + n2 - overlap)


def _signature(grams: np.ndarray, seed: int) -> tuple[int, int]:
    mixed = mix64(grams ^ np.uint64(seed * 0x9E3779B97F4A7C15 & (2**64 - 1)))
    with np.errstate(over="ignore"):
        return int(mixed.sum(dtype=np.uint64).astype(np.int64)), int(np.bitwise_xor.reduce(mix64(mixed + np.uint64(len(grams)))).astype(np.int64))


def shingle_profile(docs: DataFrame, width: int = WIDTH, seed: int = 0, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, n_shingles, f1, f2): set size and a 128-bit fingerprint of each set, and the columns to carry."""
    kept = ["doc_id", *carry]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("join")
        for batch in batches:
            size, f1, f2 = [], [], []
            for _, _, raw, offsets in text_slices(batch.column("text")):
                for grams in distinct_shingles(find_words(raw, offsets), width):
                    a, b = _signature(grams, seed) if len(grams) else (0, 0)
                    size.append(len(grams)), f1.append(a), f2.append(b)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(size, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64())], [*kept, "n_shingles", "f1", "f2"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *carry, F.col("text").cast("string").alias("text"))
    made = "n_shingles long, f1 long, f2 long"
    return texts.mapInArrow(run, ", ".join([*(f"`{c}` {kind}" for c, kind in texts.dtypes if c in kept), made]))


def _blocks(batches: Iterator[pa.RecordBatch], width: int, seed: int, limit: int, pick: Callable[[np.ndarray], np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray, list[np.ndarray]]]:
    """(class names, set sizes, picked n-grams) of the distinct classes of ``limit`` n-grams' worth of texts.

    With a column ``f1``, rows of other classes than it says are left out.
    """
    names: list[int] = []
    sizes: list[int] = []
    sets: list[np.ndarray] = []
    seen: set[int] = set()
    held = 0
    for batch in batches:
        wanted = batch.column("f1").to_pylist() if "f1" in batch.schema.names else None
        for first, _, raw, offsets in text_slices(batch.column("text")):
            for row, grams in enumerate(distinct_shingles(find_words(raw, offsets), width), first):
                if not len(grams):
                    continue
                name = _signature(grams, seed)[0]
                if name in seen or (wanted and wanted[row] != name):
                    continue
                seen.add(name), names.append(name), sizes.append(len(grams)), sets.append(pick(grams))
                held += len(sets[-1])
                if held >= limit:
                    yield np.array(names, np.int64), np.array(sizes, np.int64), sets
                    names, sizes, sets, held = [], [], [], 0
                    seen.clear()
    if names:
        yield np.array(names, np.int64), np.array(sizes, np.int64), sets


def _ranges(tokens: np.ndarray, ranges: int) -> np.ndarray:
    return (((tokens >> np.uint64(32)) * np.uint64(ranges)) >> np.uint64(32)).astype(np.int64)


def _words64(data: pa.Buffer, count: int, at: int, kind: type = np.uint64) -> np.ndarray:
    """``count`` values at byte ``at`` of a buffer that need not be aligned."""
    return np.frombuffer(np.frombuffer(data, np.uint8, count * np.dtype(kind).itemsize, at).tobytes(), kind)


def _prefix_counts(docs: DataFrame, width: int, seed: int, ranges: int, threshold: int) -> DataFrame:
    """(f1, shared): of the classes that share prefix n-grams with others, how many at most.

    Inside a block shared n-grams are counted at once and sent on as one entry
    without a name; an n-gram of one class of the block is sent with that name.
    """

    def pick(grams: np.ndarray) -> np.ndarray:
        n = len(grams)
        take = n - need(n, threshold) + spare(n)
        if take >= n:
            return grams
        order = mix64(grams ^ _FIRST_ORDER)
        return grams[np.argpartition(order, take - 1)[:take]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("join")
        for names, _, sets in _blocks(batches, width, seed, _TOKENS_PER_BLOCK, pick):
            tokens = np.concatenate(sets)
            owner = np.repeat(np.arange(len(sets), dtype=np.int32), [len(s) for s in sets])
            order = np.argsort(tokens)
            tokens, owner = tokens[order], owner[order]
            edge = np.flatnonzero(np.concatenate([[True], tokens[1:] != tokens[:-1]]))
            many = np.diff(np.append(edge, len(tokens)))
            counted = np.bincount(owner[np.repeat(many > 1, many)], minlength=len(sets))
            common, single = tokens[edge[many > 1]], edge[many == 1]
            tokens, owner = tokens[single], owner[single]
            bounds = np.searchsorted(_ranges(tokens, ranges), np.arange(ranges + 1))
            limits = np.searchsorted(_ranges(common, ranges), np.arange(ranges + 1))
            known = np.flatnonzero(counted)
            home = int(names[0]) % ranges
            rids, out = [], []
            for r in range(ranges):
                lo, hi = bounds[r], bounds[r + 1]
                by = np.argsort(owner[lo:hi], kind="stable")  # runs of one name compress well
                own = known if r == home else known[:0]
                if hi > lo or limits[r + 1] > limits[r] or len(own):
                    rids.append(r)
                    out.append(b"".join([np.array([hi - lo, limits[r + 1] - limits[r], len(own)], np.uint32).tobytes(), names[owner[lo:hi]][by].tobytes(), tokens[lo:hi][by].tobytes(), common[limits[r] : limits[r + 1]].tobytes(), names[own].tobytes(), counted[own].astype(np.int64).tobytes()]))
            yield pa.RecordBatch.from_arrays([pa.array(rids, pa.int32()), pa.array(out, pa.binary())], ["rid", "blob"])

    def count(key: tuple, table: pa.Table) -> pa.Table:
        names, tokens, common, known, counted = [], [], [], [], []
        for piece in table.column("blob"):
            data = piece.as_buffer()
            one, two, three = _words64(data, 3, 0, np.uint32).tolist()
            at = 12
            for into, size, kind in ((names, one, np.int64), (tokens, one, np.uint64), (common, two, np.uint64), (known, three, np.int64), (counted, three, np.int64)):
                into.append(_words64(data, size, at, kind))
                at += 8 * size
        name, token = np.concatenate(names), np.concatenate(tokens)
        del names, tokens
        order = np.argsort(token)
        name, token = name[order], token[order]
        edge = np.flatnonzero(np.concatenate([[True], token[1:] != token[:-1]])) if len(token) else np.empty(0, np.int64)
        many = np.diff(np.append(edge, len(token)))
        shared = np.isin(token[edge], np.concatenate(common))
        if len(edge):
            shared |= np.minimum.reduceat(name, edge) != np.maximum.reduceat(name, edge)
        found = np.concatenate([name[np.repeat(shared, many)], *known])
        weight = np.concatenate([np.ones(int(many[shared].sum()), np.int64), *counted])
        f1, place = np.unique(found, return_inverse=True)
        return pa.table({"f1": pa.array(f1, pa.int64()), "shared": pa.array(np.bincount(place, weight, len(f1)).astype(np.int64))})

    dealt = docs.where("doc_id is not null").select(F.col("text").cast("string").alias("text")).mapInArrow(run, "rid int, blob binary")
    return dealt.groupBy("rid").applyInArrow(count, "f1 long, shared long").groupBy("f1").agg(F.sum("shared").alias("shared"))


def _set_blocks(docs: DataFrame, live: DataFrame, count: int, width: int, seed: int) -> DataFrame:
    """(block, blob): the whole sets of the classes in ``live``, about half a million n-grams a block.

    A blob holds the classes' names, sizes and n-grams.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("join")
        for names, sizes, sets in _blocks(batches, width, seed, _TOKENS_PER_SET_BLOCK, lambda grams: grams):
            blob = b"".join([np.array([len(names)], np.int64).tobytes(), names.tobytes(), sizes.tobytes(), np.concatenate(sets).tobytes()])
            yield pa.RecordBatch.from_arrays([pa.array([blob], pa.binary())], ["blob"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    texts = lookup(texts, live.select(F.col("rep").alias("doc_id"), "f1"), "doc_id", count, "inner")
    return texts.select("text", "f1").mapInArrow(run, "blob binary").select(F.monotonically_increasing_id().alias("block"), "blob")


def _block(blob: pa.Scalar) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    data = blob.as_buffer()
    (m,) = _words64(data, 1, 0, np.int64).tolist()
    sizes = _words64(data, m, 8 + 8 * m, np.int64)
    return _words64(data, m, 8, np.int64), sizes, _words64(data, int(sizes.sum()), 8 + 16 * m)


def _rarities(blocks: DataFrame, ranges: int) -> DataFrame:
    """(block, rid, rare): for the sorted distinct n-grams of a block in a range, how common each is.

    0 marks an n-gram of one class, else it is a byte that grows with the count.
    """

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("join")
        for batch in batches:
            for block, blob in zip(batch.column("block").to_pylist(), batch.column("blob")):
                tokens, counts = np.unique(_block(blob)[2], return_counts=True)
                bounds = np.searchsorted(_ranges(tokens, ranges), np.arange(ranges + 1))
                rids = np.flatnonzero(np.diff(bounds))
                out = [tokens[bounds[r] : bounds[r + 1]].tobytes() + counts[bounds[r] : bounds[r + 1]].astype(np.uint32).tobytes() for r in rids]
                yield pa.RecordBatch.from_arrays([pa.array(rids, pa.int32()), pa.array([block] * len(rids), pa.int64()), pa.array(out, pa.binary())], ["rid", "block", "blob"])

    def count(key: tuple, table: pa.Table) -> pa.Table:
        pieces = [piece.as_buffer() for piece in table.column("blob")]
        sizes = [p.size // 12 for p in pieces]
        token = np.concatenate([_words64(p, n, 0) for p, n in zip(pieces, sizes)])
        many = np.concatenate([_words64(p, n, 8 * n, np.uint32) for p, n in zip(pieces, sizes)]).astype(np.int64)
        names, place = np.unique(token, return_inverse=True)
        total = np.bincount(place, many, len(names))
        rare = np.where(total > 1, np.minimum(255, np.log2(np.maximum(total, 1)) * 8), 0).astype(np.uint8)[place]
        out = [x.tobytes() for x in np.split(rare, np.cumsum(sizes)[:-1])]
        return pa.table({"block": table.column("block"), "rid": pa.array([key[0].as_py()] * len(sizes), pa.int32()), "rare": pa.array(out, pa.binary())})

    return blocks.mapInArrow(deal, "rid int, block long, blob binary").groupBy("rid").applyInArrow(count, "block long, rid int, rare binary")


def _survivors(blocks: DataFrame, rarities: DataFrame, threshold: int) -> DataFrame:
    """(cls, n, toks, k1, k2): classes that can have a partner, with their shared n-grams, rarest first.

    ``k1``/``k2`` are smallest hashes, by which near copies meet.
    """

    def gather(left: pa.Table, right: pa.Table) -> pa.Table:
        columns: list[list] = [[] for _ in range(5)]
        for blob in left.column("blob"):  # one row: a block
            names, sizes, tokens = _block(blob)
            answers = right.sort_by("rid").column("rare")
            known = np.unique(tokens)
            rare = np.concatenate([np.frombuffer(x.as_buffer(), np.uint8) for x in answers])[np.searchsorted(known, tokens)]
            stop = np.cumsum(sizes)
            for name, n, lo, hi in zip(names.tolist(), sizes.tolist(), (stop - sizes).tolist(), stop.tolist()):
                r = rare[lo:hi]
                t, r = tokens[lo:hi][r > 0], r[r > 0]
                if len(t) < need(n, threshold):
                    continue
                h2, h3 = mix64(t ^ _SEEDS[0]), mix64(t ^ _SEEDS[1])
                for column, value in zip(columns, (name, n, t[np.lexsort((t, r))].tobytes(), int(h2.min().astype(np.int64)), int(h3.min().astype(np.int64)))):
                    column.append(value)
        kinds = [pa.int64(), pa.int32(), pa.binary(), pa.int64(), pa.int64()]
        return pa.table([pa.array(c, k) for c, k in zip(columns, kinds)], names=["cls", "n", "toks", "k1", "k2"])

    return blocks.groupBy("block").cogroup(rarities.groupBy("block")).applyInArrow(gather, "cls long, n int, toks binary, k1 long, k2 long")


def _tokens(cell: pa.Scalar) -> np.ndarray:
    return np.frombuffer(cell.as_buffer(), np.uint64)


def _rare_prefix(n: int, shared: int, threshold: int) -> int:
    """Length of the rarest-first prefix that reaches beyond n-grams of a single class."""
    return shared - need(n, threshold) + 1


def _overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted arrays of distinct values."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    return int((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).sum())


def _pivot_round(near: DataFrame, key: str, threshold: int) -> DataFrame:
    """Links (a, b) with the pivots of each key's group, and as (cls, n, toks, k2) the classes left.

    Large groups go in salted parts.  A group streams through in order of its
    key; only its pivots are held.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("join")
        now, pivots = None, []
        for batch in batches:
            a, b, left = [], [], []
            groups = list(zip(batch.column("key").to_pylist(), batch.column("part").to_pylist()))
            for i, (name, n) in enumerate(zip(batch.column("cls").to_pylist(), batch.column("n").to_pylist())):
                if groups[i] != now:
                    now, pivots = groups[i], []
                mine = np.sort(_tokens(batch.column("toks")[i]))
                for other, m, theirs in pivots:
                    if 100 * min(n, m) >= threshold * max(n, m) and linked(n, m, _overlap(mine, theirs), threshold):
                        a.append(name), b.append(other)
                        break
                else:
                    if len(pivots) < _PIVOTS:
                        pivots.append((name, n, mine))
                    left.append(i)
            head = batch.select(["cls", "n", "toks", "k2"]).take(pa.array(left, pa.int64()))
            none = pa.nulls(len(left), pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, *head.columns], ["a", "b", "cls", "n", "toks", "k2"])
            empty = [pa.nulls(len(a), kind) for kind in (pa.int64(), pa.int32(), pa.binary(), pa.int64())]
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), *empty], ["a", "b", "cls", "n", "toks", "k2"])

    hot = checkpointed(near.groupBy(key).agg(F.count("*").alias("members")).where(F.col("members") > _GROUP_PART).select(F.col(key).alias("key"), F.ceil(F.col("members") / _GROUP_PART).alias("parts")).coalesce(1))
    keyed = lookup(near.select(F.col(key).alias("key"), "cls", "n", "toks", "k2"), hot, "key", hot.count(), "left")
    salted = keyed.withColumn("part", F.coalesce(F.pmod(F.xxhash64("cls"), F.col("parts")), F.lit(0))).drop("parts")
    ordered = salted.repartition(partitions(near.sparkSession), "key", "part").sortWithinPartitions("key", "part", "n", "cls")
    return checkpointed(ordered.mapInArrow(run, "a long, b long, cls long, n int, toks binary, k2 long"))


class _Merger:
    """Union-find over component ids."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        while (y := self.up.get(x, x)) != x:
            self.up[x] = self.up.get(y, y)
            x = y
        return x

    def join(self, x: int, y: int) -> None:
        x, y = self.find(x), self.find(y)
        if x != y:
            self.up[max(x, y)] = min(x, y)


class _Postings:
    """Which of a group's sets hold an element: an inverted index over arrays of hashes."""

    def __init__(self, lists: list[np.ndarray]):
        sizes = [len(x) for x in lists]
        _, number = np.unique(np.concatenate(lists) if lists else np.empty(0, np.uint64), return_inverse=True)
        self.own = np.split(number, np.cumsum(sizes)[:-1])
        order = np.argsort(number, kind="stable")
        self.rows = np.repeat(np.arange(len(lists)), sizes)[order]
        self.at = np.concatenate([[0], np.cumsum(np.bincount(number))])
        self.n = len(lists)

    def meets(self, k: int) -> np.ndarray:
        """How many elements of set k each set holds."""
        mine = self.own[k]
        begin, size = self.at[mine], self.at[mine + 1] - self.at[mine]
        total = int(size.sum())
        spots = np.repeat(begin - np.cumsum(size) + size, size) + np.arange(total)
        return np.bincount(self.rows[spots], minlength=self.n)


def _group_links(rep: np.ndarray, n: np.ndarray, component: np.ndarray, cell: np.ndarray, side: np.ndarray | None, toks: list[np.ndarray], rare: list[int], pre: list[list[np.ndarray]], threshold: int, every: bool = False) -> Iterator[tuple[int, int]]:
    """Links that join different components inside a group; with ``side``, only between its two sides.

    ``every`` gives all links, also those inside a component.

    Candidates of a set meet it in the prefixes of all three orders, keep the
    length bound and are not in its component yet.  The largest component of each
    cell needs no turn of its own: every pair has a member outside it.
    """
    merger = _Merger()
    orders = [_Postings([t[:k] for t, k in zip(toks, rare)]), _Postings(pre[0]), _Postings(pre[1])]
    whole = _Postings(toks)
    names, where, many = np.unique(np.stack([cell, component], axis=1), axis=0, return_inverse=True, return_counts=True)
    largest: dict[int, tuple[int, int]] = {}
    for j, (c, _) in enumerate(names.tolist()):
        largest[c] = max(largest.get(c, (0, 0)), (int(many[j]), j))
    where = where.ravel()
    turn = [k for k in range(len(rep)) if every or side is not None or largest[int(cell[k])][1] != where[k]]
    if side is not None:  # the side with fewer sets takes the turns
        fewer = int(side.sum() * 2 <= len(side))
        turn = [k for k in turn if side[k] == fewer]
    done = np.zeros(len(rep), dtype=bool)
    for k in turn:
        done[k] |= side is None
        fits = (orders[0].meets(k) > 0) & (every | (component != component[k])) & ~done
        fits &= 100 * np.minimum(n, n[k]) >= threshold * np.maximum(n, n[k])
        if side is not None:
            fits &= side != side[k]
        if fits.any():
            for order in orders[1:]:
                fits &= order.meets(k) > 0
        found = np.flatnonzero(fits)
        if not len(found):
            continue
        overlap = whole.meets(k)[found]
        for other in found[100 * overlap >= threshold * (n[k] + n[found] - overlap)].tolist():
            a, b = int(component[k]), int(component[other])
            if every or merger.find(a) != merger.find(b):
                merger.join(a, b)
                yield int(rep[k]), int(rep[other])


def _cross_links(near: DataFrame, component: DataFrame, threshold: int, every: bool = False) -> DataFrame:
    """Links between classes of different components, enough to join all that are linked; all of them with ``every``.

    Components whose classes share n-grams of the rarest-first prefix, directly or
    through others, form a cell; a pair can only link inside one.  Small cells are
    dealt to groups of bounded size, so each class's set travels once.  A large
    cell is cut in parts: those outside its largest component meet all parts.
    """

    def prefix(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = batch.column("n").to_pylist()
            sets = [_tokens(cell) for cell in batch.column("toks")]
            lists = [t[: _rare_prefix(n, len(t), threshold)].astype(np.int64) for n, t in zip(sizes, sets)]
            spread = lambda c: pa.array(np.repeat(batch.column(c).to_numpy(), [len(x) for x in lists]))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(lists) if lists else np.empty(0, np.int64)), spread("cls"), spread("component"), pa.array(np.repeat([len(t) for t in sets], [len(x) for x in lists]).astype(np.int64))], ["tok", "cls", "component", "weight"])

    spark = near.sparkSession
    members = checkpointed(component.select(F.col("vertex").alias("cls"), "component"))
    placed = lookup(near.select("cls", "n", "toks"), members, "cls", members.count(), "left").withColumn("component", F.coalesce("component", "cls"))
    postings = checkpointed(placed.mapInArrow(prefix, "tok long, cls long, component long, weight long"))
    mixed = postings.groupBy("tok").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low < high").select("tok", "low")
    ties = checkpointed(postings.join(mixed, "tok").select("cls", "component", "weight", "low").distinct())
    cells = connected_components(ties.select(F.col("component").alias("a"), F.col("low").alias("b")).distinct())
    cells = cells.select(F.col("vertex").alias("component"), F.col("component").alias("cell"))
    live = checkpointed(ties.select("cls", "component", "weight").distinct().join(cells, "component"))
    pieces = live.groupBy("cell", "component").agg(F.count("*").alias("rows"), F.sum("weight").alias("weight"))
    cut = lambda rows, weight: F.greatest(F.lit(1), F.ceil(F.col(rows) / _CELL_ROWS), F.ceil(F.col(weight) / _CELL_TOKENS)).cast("int")
    large = pieces.groupBy("cell").agg(F.sum("rows").alias("all_rows"), F.sum("weight").alias("all_weight"), F.max(F.struct("rows", "weight", "component")).alias("top"))
    large = large.withColumn("rest_rows", F.col("all_rows") - F.col("top.rows")).withColumn("rest_weight", F.col("all_weight") - F.col("top.weight"))
    large = large.where((F.col("all_rows") > 2 * _CELL_ROWS) | (F.col("all_weight") > 2 * _CELL_TOKENS))
    large = checkpointed(large.select("cell", F.col("top.component").alias("top"), cut("top.rows", "top.weight").alias("top_parts"), cut("rest_rows", "rest_weight").alias("rest_parts")))
    dealt = lookup(live, large, "cell", large.count(), "left")
    total, rows = live.agg(F.coalesce(F.sum("weight"), F.lit(0)), F.count("*")).first()
    buckets = max(partitions(spark), math.ceil(total / _CELL_TOKENS), math.ceil(rows / (2 * _CELL_ROWS)))
    # meetings (top, i, j): two parts outside the largest component (0), or one of them and one of its parts (1)
    whole, inside = F.col("top").isNull(), F.col("component") == F.col("top")
    part = lambda parts: F.pmod(F.xxhash64("cls"), F.col(parts)).cast("int")
    meeting = lambda top, i, j: F.struct(F.lit(top).alias("top"), i.alias("i"), j.alias("j"))
    rest = F.sequence(F.lit(0), F.col("rest_parts") - 1)
    alone = F.array(meeting(0, F.lit(0), F.lit(0)))
    of_top = F.transform(rest, lambda o: meeting(1, o, part("top_parts")))
    of_rest = F.concat(
        F.transform(rest, lambda o: meeting(0, F.least(part("rest_parts"), o), F.greatest(part("rest_parts"), o))),
        F.transform(F.sequence(F.lit(0), F.col("top_parts") - 1), lambda o: meeting(1, part("rest_parts"), o)),
    )
    dealt = checkpointed(
        dealt.select(
            "cls", "component", "cell", F.when(whole, F.pmod(F.xxhash64("cell"), F.lit(buckets)).cast("long")).otherwise(-1 - F.col("cell")).alias("bucket"), F.when(inside, -1).otherwise(F.coalesce(part("rest_parts"), F.lit(0))).alias("side"), F.explode(F.when(whole, alone).when(inside, of_top).otherwise(of_rest)).alias("at")
        )
    )
    grouped = lookup(near.select("cls", "n", "toks"), dealt, "cls", dealt.count(), "inner").select("bucket", "at", "cls", "n", "component", "cell", "side", "toks")

    def join(key: tuple, table: pa.Table) -> pa.Table:
        at = key[1].as_py()
        column = lambda c: table.column(c).to_numpy().astype(np.int64)
        side = column("side") == at["i"] if at["top"] or at["i"] != at["j"] else None
        n = column("n")
        toks = [_tokens(x) for x in table.column("toks")]
        room = [_rare_prefix(int(k), len(t), threshold) for k, t in zip(n, toks)]
        pre = []
        for seed in _SEEDS[:2]:
            hashes = [mix64(t ^ seed) for t in toks]
            pre.append([np.partition(h, k - 1)[:k] if k < len(h) else h for h, k in zip(hashes, room)])
        links = list(_group_links(column("cls"), n, column("component"), column("cell"), side, toks, room, pre, threshold, every))
        return pa.table({"a": pa.array([x for x, _ in links], pa.int64()), "b": pa.array([y for _, y in links], pa.int64())})

    return grouped.groupBy("bucket", "at").applyInArrow(join, "a long, b long")


def distinct_documents(docs: DataFrame, width: int = WIDTH, threshold: int = THRESHOLD) -> DataFrame:
    """The rows of ``docs``, one of each group: the one with the smallest id, of several such rows one.

    Rows with a null id and rows without words have no group and stay.
    """
    mark = "near_duplicate_text"
    while mark in docs.columns:
        mark += "_"
    marked = docs.withColumn(mark, F.xxhash64("text"))
    groups = checkpointed(near_duplicates(marked, width, threshold, (mark,)).where("group is not null").select("doc_id", mark, "group"))
    first = groups.groupBy("group").agg(F.min(F.struct("doc_id", mark)).alias("first"))
    lost = groups.join(first, "group").where((F.col("doc_id") != F.col("first.doc_id")) | (F.col(mark) != F.col(f"first.{mark}"))).select("doc_id", mark).distinct()
    lost = checkpointed(lost)
    rest = lookup(marked, lost, ["doc_id", mark], lost.count(), "left_anti")
    # rows that repeat an id and its text
    again = checkpointed(groups.groupBy("doc_id", mark).agg(F.count("*").alias("rows")).where("rows > 1").select("doc_id", mark))
    repeats = again.count()
    if repeats:
        rest = lookup(rest, again, ["doc_id", mark], repeats, "left_anti").unionByName(lookup(rest, again, ["doc_id", mark], repeats, "left_semi").dropDuplicates(["doc_id", mark]))
    return rest.select(*(F.col(f"`{c}`") for c in docs.columns))


def _candidates(docs: DataFrame, width: int, threshold: int, carry: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The profile of every row, the classes of equal sets, and the classes that can have a partner with their shared n-grams."""
    if not 0 < threshold <= 100:
        raise ValueError("threshold is a percentage above 0")
    spark = docs.sparkSession
    for seed in range(8):
        profile = checkpointed(shingle_profile(docs, width, seed, carry))
        classes = checkpointed(profile.where("n_shingles > 0 and doc_id is not null").groupBy("f1", "f2").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").cast("int").alias("n")))
        total, many, names = classes.agg(F.coalesce(F.sum(F.col("n").cast("long")), F.lit(0)), F.count("*"), F.count_distinct("f1")).first()
        if many == names:  # else two different sets share the first half of their fingerprints
            break
    else:
        raise RuntimeError("two different sets share half a fingerprint under every seed")
    ranges = lambda tokens: max(MIN_RANGES, math.ceil(tokens / TOKENS_PER_RANGE))
    counts = _prefix_counts(docs, width, seed, ranges(total // 4), threshold)
    least = F.lit(1) + F.expr(f"(({threshold} * n + 99) div 100) div 20")  # spare(need(n))
    live = checkpointed(counts.join(classes, "f1").where(F.col("shared") >= least).select("f1", "rep", "n"))
    left, tokens = live.agg(F.count("*"), F.coalesce(F.sum(F.col("n").cast("long")), F.lit(0))).first()
    release_shuffles(spark)
    blocks = checkpointed(_set_blocks(docs, live, left, width, seed))
    near = checkpointed(_survivors(blocks, _rarities(blocks, ranges(tokens)), threshold))
    return profile, classes, near


def near_duplicates(docs: DataFrame, width: int = WIDTH, threshold: int = THRESHOLD, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, n_shingles, class_id, component_id, group), a row for each input row.

    ``class_id`` is the smallest id with exactly the same set, ``component_id``
    the smallest id reachable by links.  Components of repeated ids may share it;
    ``group`` names the component, and is null where there is nothing to link.
    """
    spark = docs.sparkSession
    profile, classes, near = _candidates(docs, width, threshold, carry)
    first = _pivot_round(near, "k1", threshold)
    second = _pivot_round(first.where("cls is not null"), "k2", threshold)
    links = first.unionByName(second).where("a is not null").select("a", "b")
    release_shuffles(spark)
    cross = checkpointed(_cross_links(near, connected_components(links), threshold))
    component = connected_components(links.unionByName(cross))
    # components are named by their smallest class; documents by their smallest id
    members = checkpointed(component.join(classes.select(F.col("f1").alias("vertex"), "rep"), "vertex"))
    roots = members.groupBy("component").agg(F.min("rep").alias("root"))
    named = classes.join(members.join(roots, "component").select(F.col("vertex").alias("f1"), "root", F.col("component").alias("group")), "f1", "left")
    named = named.select("f1", "rep", F.coalesce("root", "rep").alias("component"), F.coalesce("group", "f1").alias("group"))
    out = profile.join(named, "f1", "left")
    own = F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0)
    return out.select("doc_id", *carry, "n_shingles", F.when(own, F.col("rep")).otherwise(F.col("doc_id")).alias("class_id"), F.when(own, F.col("component")).otherwise(F.col("doc_id")).alias("component_id"), F.when(own, F.col("group")).alias("group"))


def link_counts(docs: DataFrame, width: int = WIDTH, threshold: int = THRESHOLD) -> DataFrame:
    """(doc_id, n_links), a row for each input row: how many other rows link with it, exactly.

    Every candidate pair of classes is verified, so a family of n texts near the
    threshold costs n * n / 2 checks; copies cost nothing.  Rows without a group
    have no links.
    """
    profile, classes, near = _candidates(docs, width, threshold)
    none = docs.sparkSession.createDataFrame([], "vertex long, component long")
    links = checkpointed(_cross_links(near, none, threshold, every=True).where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    own = F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0)
    rows = profile.where(own).groupBy("f1").agg(F.count("*").alias("rows"))
    sides = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    others = sides.join(rows.withColumnRenamed("f1", "b"), "b").groupBy(F.col("a").alias("f1")).agg(F.sum("rows").alias("others"))
    counted = rows.join(others, "f1", "left").select("f1", (F.col("rows") - 1 + F.coalesce("others", F.lit(0))).alias("links"))
    return profile.join(counted, "f1", "left").select("doc_id", F.when(own, F.col("links")).otherwise(F.lit(0)).cast("long").alias("n_links"))

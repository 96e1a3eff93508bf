"""Graph preparation: canonical edges, adjacency, common neighbours, transition weights.

``edges``: (src, dst, w), src < dst when undirected.  ``edges2``: (u, v, w), both
directions.  Everything is an aggregate or an equi-join over these.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.durable import durable, packed_durable

BITS = 20
# words of 64 bits of an edge filter, as powers of two: in all at most, and in a chunk that one task fills
FILTER_WORDS, CHUNK_WORDS = 24, 14
DENSE_NODES = 32_768  # a bit a pair: 128 MB
# nodes whose degrees reach every task; bytes of a block's bits; words of bits that cost as much as a wedge
BROADCAST_NODES, BLOCK_BYTES, WORDS_A_WEDGE = 1 << 20, 1 << 24, 8


def normalize_edges(pairs: DataFrame, directed: bool = False, weighted: bool = False) -> DataFrame:
    """Drops loops and nulls and merges repeated edges; w is their number, or the sum of ``w`` if ``weighted``."""
    weight = F.col("w").cast("double") if weighted else F.lit(1.0)
    a, b = F.col("a").cast("long"), F.col("b").cast("long")
    ends = (a, b) if directed else (F.least(a, b), F.greatest(a, b))
    return pairs.where("a is not null and b is not null and a <> b").select(ends[0].alias("src"), ends[1].alias("dst"), weight.alias("w")).groupBy("src", "dst").agg(F.sum("w").alias("w"))


def both_directions(edges: DataFrame, directed: bool = False) -> DataFrame:
    """(u, v, w): undirected edges stored at both ends, from one scan."""
    if directed:
        return edges.select(F.col("src").alias("u"), F.col("dst").alias("v"), "w")
    ends = F.array(F.struct(F.col("src").alias("u"), F.col("dst").alias("v")), F.struct(F.col("dst").alias("u"), F.col("src").alias("v")))
    return edges.select(F.explode(ends).alias("e"), "w").select("e.u", "e.v", "w")


def degrees(edges2: DataFrame) -> DataFrame:
    """(node, deg)."""
    return edges2.groupBy(F.col("u").alias("node")).agg(F.count("*").alias("deg"))


def degree_distribution(edges2: DataFrame) -> DataFrame:
    """(node, deg, p): p is the share of all degrees."""
    deg = degrees(edges2)
    return deg.crossJoin(deg.agg(F.sum("deg").alias("total"))).select("node", "deg", (F.col("deg") / F.col("total")).alias("p"))


def adjacency(edges2: DataFrame, *columns: str) -> DataFrame:
    """(node, deg, nbr, and an array of each further column), neighbours ascending."""
    packed = F.array_sort(F.collect_list(F.struct("v", *columns)))
    rows = edges2.groupBy(F.col("u").alias("node")).agg(packed.alias("e"))
    return rows.select("node", F.size("e").alias("deg"), F.col("e.v").alias("nbr"), *[F.col(f"e.{c}").alias(c) for c in columns])


def _oriented(edges: DataFrame, deg: DataFrame | None = None) -> DataFrame:
    """Each edge once, from the end of lower (degree, id) to the other: out-degrees stay below sqrt(2 E)."""
    deg = degrees(both_directions(edges)) if deg is None else deg
    placed = edges.join(deg.select(F.col("node").alias("src"), F.col("deg").alias("ds")), "src").join(deg.select(F.col("node").alias("dst"), F.col("deg").alias("dd")), "dst")
    forward = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    return placed.select(F.when(forward, F.col("src")).otherwise(F.col("dst")).alias("lo"), F.when(forward, F.col("dst")).otherwise(F.col("src")).alias("hi"))


def _edge_code(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A hash of edges, and the four bits of a word that each sets."""
    mix = lambda x: (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    h = mix(mix(mix(a.astype(np.uint64)) + b.astype(np.uint64)))
    h ^= h >> np.uint64(32)
    return h >> np.uint64(24), h & np.uint64((1 << 24) - 1)


def _mask(code: np.ndarray) -> np.ndarray:
    bits = np.zeros(len(code), dtype=np.uint64)
    for k in range(4):
        bits |= np.uint64(1) << ((code >> np.uint64(6 * k)) & np.uint64(63))
    return bits


def edge_filter(edges: DataFrame) -> np.ndarray:
    """A Bloom filter of the edges in words of 64 bits, 8 to 16 bits an edge up to its largest size: it never denies an edge."""
    size = 1 << min(FILTER_WORDS, max(CHUNK_WORDS, (edges.count() // 8).bit_length()))

    def spots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, code = _edge_code(batch.column("src").to_numpy(), batch.column("dst").to_numpy())
            at &= np.uint64(size - 1)
            spot = (at & np.uint64((1 << CHUNK_WORDS) - 1)) << np.uint64(24) | code
            yield pa.RecordBatch.from_arrays([pa.array((at >> np.uint64(CHUNK_WORDS)).astype(np.int32)), pa.array(spot.astype(np.int64))], ["chunk", "spot"])

    def fill(key: tuple, rows: pa.Table) -> pa.Table:
        spot = rows.column("spot").to_numpy().astype(np.uint64)
        words = np.zeros(1 << CHUNK_WORDS, dtype=np.uint64)
        np.bitwise_or.at(words, (spot >> np.uint64(24)).astype(np.int64), _mask(spot & np.uint64((1 << 24) - 1)))
        return pa.table({"chunk": pa.array([key[0].as_py()], pa.int32()), "words": pa.array([words.tobytes()], pa.binary())})

    filled = edges.select("src", "dst").mapInArrow(spots, "chunk int, spot long").groupBy("chunk").applyInArrow(fill, "chunk int, words binary").toArrow()
    words = np.zeros((size >> CHUNK_WORDS, 1 << CHUNK_WORDS), dtype=np.uint64)
    for chunk, data in zip(filled.column("chunk").to_pylist(), filled.column("words").to_pylist()):
        words[chunk] = np.frombuffer(data, np.uint64)
    return words.ravel()


def triangles(edges: DataFrame) -> DataFrame:
    """(n1, n2, n3): each triangle once, from its lowest corner by degree (E^1.5 work).

    Wedges are made in the task of their corner and meet a filter of the edges
    there, so few of those that don't close are exchanged; a join decides.
    """
    shared = edges.sparkSession.sparkContext.broadcast(edge_filter(edges))
    names = ["n1", "n2", "n3"]

    def wedges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = shared.value
        for batch in batches:
            lists = batch.column("his")
            sizes = np.diff(lists.offsets.to_numpy())
            owner = np.repeat(np.arange(len(sizes)), sizes)
            flat, low = lists.flatten().to_numpy(), batch.column("lo").to_numpy()
            flat = flat[np.lexsort((flat, owner))]
            after = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(flat)) - 1
            open_, held, n = np.flatnonzero(after > 0), [], 0
            step = 1
            while len(open_):
                a, b = flat[open_], flat[open_ + step]
                at, code = _edge_code(a, b)
                bits = _mask(code)
                fine = words[(at & np.uint64(len(words) - 1)).astype(np.int64)] & bits == bits
                held.append((low[owner[open_[fine]]], a[fine], b[fine]))
                n += len(held[-1][0])
                step += 1
                open_ = open_[after[open_] >= step]
                if n and (n >= 65_536 or not len(open_)):
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([h[k] for h in held])) for k in range(3)], names)
                    held, n = [], 0

    out = _oriented(edges).groupBy("lo").agg(F.collect_list("hi").alias("his"))
    near = out.mapInArrow(wedges, "n1 long, n2 long, n3 long")
    return near.join(edges.select(F.col("src").alias("n2"), F.col("dst").alias("n3")), ["n2", "n3"]).select(*names)


def _dense_common(edges: DataFrame, nodes: np.ndarray) -> DataFrame:
    """``common_neighbours`` of a dense graph: a bit for each pair of nodes reaches every task, each edge counts the bits of both its rows."""

    def row(key: tuple, rows: pa.Table) -> pa.Table:
        held = np.zeros(-(-len(nodes) // 64) * 64, dtype=bool)
        held[np.searchsorted(nodes, rows.column("v").to_numpy())] = True
        return pa.table({"u": pa.array([key[0].as_py()], pa.int64()), "bits": pa.array([np.packbits(held).tobytes()], pa.binary())})

    rows = both_directions(edges).select("u", "v").groupBy("u").applyInArrow(row, "u long, bits binary").toArrow()
    matrix = np.zeros((len(nodes), -(-len(nodes) // 64)), dtype=np.uint64)
    for u, bits in zip(rows.column("u").to_pylist(), rows.column("bits").to_pylist()):
        matrix[np.searchsorted(nodes, u)] = np.frombuffer(bits, np.uint64)
    shared = edges.sparkSession.sparkContext.broadcast((nodes, matrix))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, bits = shared.value
        for batch in batches:
            i, j = (np.searchsorted(names, batch.column(c).to_numpy()) for c in ("src", "dst"))
            cm = np.concatenate([np.bitwise_count(bits[i[k : k + 2048]] & bits[j[k : k + 2048]]).sum(1) for k in range(0, len(i), 2048)] or [np.zeros(0)])
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("src", "dst", "w")), pa.array(cm.astype(np.int32))], ["src", "dst", "w", "cm"])

    return edges.select("src", "dst", F.col("w").cast("double").alias("w")).mapInArrow(count, "src long, dst long, w double, cm int")


def _blocked_common(edges: DataFrame, nodes: np.ndarray, block: int) -> DataFrame:
    """``common_neighbours`` where closed wedges are too many to be listed: nodes go to blocks of ``block``, neighbours travel
    once, and every two blocks meet in a task that reads both from the shared folder and counts the bits that the ends of their edges share."""
    blocks = -(-len(nodes) // block)
    shared = edges.sparkSession.sparkContext.broadcast(nodes)

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def flush() -> pa.RecordBatch:
            src, dst, w = (np.concatenate([b.column(c).to_numpy() for b in held]) for c in ("src", "dst", "w"))
            i, j = (np.searchsorted(shared.value, x).astype(np.int32) for x in (src, dst))
            cells: list[list] = [[], [], [], [], []]
            for own, (a, b) in enumerate(((j, i), (i, j))):
                order = np.argsort(a // block, kind="stable")
                a, b, v = a[order], b[order], w[order] if own else w[:0]
                cuts = np.searchsorted(a // block, np.arange(blocks + 1))
                for k in np.flatnonzero(np.diff(cuts)):
                    at = slice(cuts[k], cuts[k + 1])
                    for cell, x in zip(cells, (int(k), bool(own), a[at].tobytes(), b[at].tobytes(), v[at].tobytes())):
                        cell.append(x)
            kinds = (pa.int32(), pa.bool_(), pa.binary(), pa.binary(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cells, kinds)], ["blk", "own", "a", "b", "w"])

        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) >= 1 << 19:
                yield flush()
                held = []
        if held:
            yield flush()

    def gather(t: pa.Table) -> pa.Table:
        """A block's neighbours by row, and its own edges by their far end: those that begin in it, with their weights."""
        joined = lambda rows, c, kind: np.frombuffer(b"".join(rows.column(c).to_pylist()), kind)
        own = t.filter(t.column("own"))
        a, b = joined(t, "a", np.int32), joined(t, "b", np.int32)
        order = np.lexsort((b, a))
        ends = np.searchsorted(a[order], t.column("blk")[0].as_py() * block + np.arange(block + 1)).astype(np.int64)
        i, j, w = joined(own, "a", np.int32), joined(own, "b", np.int32), joined(own, "w", np.float64)
        by = np.lexsort((i, j))
        cells = (ends, b[order], i[by], j[by], w[by])
        return pa.table({"blk": t.column("blk")[:1]} | {c: pa.array([x.tobytes()], pa.binary()) for c, x in zip(("ends", "nbr", "i", "j", "w"), cells)})

    def bits(ends: bytes, nbr: bytes) -> np.ndarray:
        at, cols = np.frombuffer(ends, np.int64), np.frombuffer(nbr, np.int32)
        out = np.zeros((block, -(-len(nodes) // 64) * 64 // 8), np.uint8)
        rows = np.repeat(np.arange(block), np.diff(at))
        np.bitwise_or.at(out.reshape(-1), rows * out.shape[1] + (cols >> 3), np.uint8(1) << (cols & 7).astype(np.uint8))
        return out.view(np.uint64)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = shared.value
        for batch in batches:
            for k in range(batch.num_rows):
                one = {c: batch.column(c)[k].as_py() for c in batch.schema.names}
                p, q = one["blk"], one["other_blk"]
                sides = {p: bits(one["ends"], one["nbr"])}
                if p != q:
                    sides[q] = bits(one["other_ends"], one["other_nbr"])
                step = max(1, (1 << 18) // sides[p].shape[1])
                for mine, far, prefix in ((p, q, ""), (q, p, "other_"))[: 1 + (p != q)]:
                    j = np.frombuffer(one[prefix + "j"], np.int32)
                    lo, hi = np.searchsorted(j, [far * block, (far + 1) * block])
                    if lo == hi:
                        continue
                    i, j, w = np.frombuffer(one[prefix + "i"], np.int32)[lo:hi], j[lo:hi], np.frombuffer(one[prefix + "w"], np.float64)[lo:hi]
                    cm = np.empty(hi - lo, np.int32)
                    for at in range(0, hi - lo, step):
                        both = sides[mine][i[at : at + step] - mine * block]
                        both &= sides[far][j[at : at + step] - far * block]
                        cm[at : at + step] = np.bitwise_count(both).sum(1, dtype=np.int32)
                    for at in range(0, hi - lo, 1 << 16):
                        s = slice(at, at + (1 << 16))
                        yield pa.RecordBatch.from_arrays([pa.array(names[i[s]]), pa.array(names[j[s]]), pa.array(w[s]), pa.array(cm[s])], ["src", "dst", "w", "cm"])

    parts = edges.select("src", "dst", F.col("w").cast("double").alias("w")).mapInArrow(spread, "blk int, own boolean, a binary, b binary, w binary")
    made = parts.repartition(blocks, "blk").groupBy("blk").applyInArrow(gather, "blk int, ends binary, nbr binary, i binary, j binary, w binary").transform(durable)
    made = made.coalesce(min(blocks, made.rdd.getNumPartitions()))
    other = made.toDF(*(f"other_{c}" for c in made.columns))
    # both sides are read from the shared folder by each task: nothing is exchanged
    return made.join(other.hint("shuffle_replicate_nl"), F.col("blk") <= F.col("other_blk")).mapInArrow(count, "src long, dst long, w double, cm int")


def _wedge_neighbours(edges: DataFrame, deg: DataFrame) -> DataFrame:
    """``common_neighbours`` of held edges with their degrees, by the way that costs least: bits of all pairs, bits by blocks, or wedges."""
    ends = deg.agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0))).first()
    n, m = ends[0], ends[1] // 2
    if n <= DENSE_NODES and m >= n**2 // 64:
        return _dense_common(edges, np.sort(deg.select("node").toArrow().column("node").to_numpy()))
    if n <= BROADCAST_NODES:
        near = _oriented(edges, F.broadcast(deg)).groupBy("lo").agg(F.count("*").alias("k")).agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0))).first()[0]
        if m * -(-n // 64) <= near * WORDS_A_WEDGE:
            return _blocked_common(edges, np.sort(deg.select("node").toArrow().column("node").to_numpy()), max(64, min(n, BLOCK_BYTES * 8 // n)))
    sides = F.array(*[F.struct(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")) for a, b in (("n1", "n2"), ("n1", "n3"), ("n2", "n3"))])
    counts = triangles(edges).select(F.explode(sides).alias("s")).groupBy("s.src", "s.dst").agg(F.count("*").cast("int").alias("cm"))
    return edges.join(counts, ["src", "dst"], "left").select("src", "dst", "w", F.coalesce("cm", F.lit(0)).alias("cm"))


def common_neighbours(edges: DataFrame, method: str = "wedge") -> DataFrame:
    """(src, dst, w, cm): how many neighbours the ends of each edge share.

    ``wedge`` lists each triangle once from its lowest corner (E^1.5 work, hubs
    are never squared), or compares rows of bits where a graph of few nodes is dense; ``intersect`` meets sorted neighbour arrays; ``gallop``
    looks the smaller array up in the larger by binary search in Arrow batches;
    ``sketch`` estimates from theta sketches, for hubs beyond exact counting.
    """
    if method == "wedge":
        edges = edges.transform(packed_durable)
        return _wedge_neighbours(edges, degrees(both_directions(edges)).transform(durable))
    edges2 = both_directions(edges)
    if method == "sketch":
        held = edges2.groupBy("u").agg(F.theta_sketch_agg("v").alias("s"))
        both = edges.join(held.select(F.col("u").alias("src"), F.col("s").alias("a")), "src").join(held.select(F.col("u").alias("dst"), F.col("s").alias("b")), "dst")
        return both.select("src", "dst", "w", F.theta_sketch_estimate(F.theta_intersection("a", "b")).cast("int").alias("cm"))
    adj = adjacency(edges2)
    both = edges.join(adj.select(F.col("node").alias("src"), F.col("nbr").alias("a")), "src").join(adj.select(F.col("node").alias("dst"), F.col("nbr").alias("b")), "dst")
    if method == "intersect":
        return both.select("src", "dst", "w", F.size(F.array_intersect("a", "b")).alias("cm"))
    if method == "gallop":
        from ..functions.arrow import gallop_overlap

        return both.select("src", "dst", "w", gallop_overlap("a", "b").alias("cm"))
    raise ValueError(f"unknown method {method!r}")


def hybrid_weight(edges_cm: DataFrame, weighted: bool = False, directed: bool = False) -> DataFrame:
    """(u, v, w, cm, du, dv, alpha, p_accept) in both directions.

    alpha grows with common neighbours and with the ratio of the degrees;
    p_accept is its tanh, of alpha times the weight if ``weighted``.
    """
    if not directed:
        placed = _placed_both(edges_cm, degrees(both_directions(edges_cm)))
    else:
        edges2 = edges_cm.select(F.col("src").alias("u"), F.col("dst").alias("v"), "w", "cm")
        deg = degrees(edges2)
        placed = edges2.join(deg.select(F.col("node").alias("u"), F.col("deg").alias("du")), "u").join(deg.select(F.col("node").alias("v"), F.col("deg").alias("dv")), "v", "left").withColumn("dv", F.coalesce("dv", F.lit(1)))
    return _hybrid_columns(placed, weighted)


def _placed_both(edges_cm: DataFrame, deg: DataFrame) -> DataFrame:
    """(u, v, w, cm, du, dv) in both directions: degrees meet the edges before these are doubled."""
    for end, name in (("src", "ds"), ("dst", "dd")):
        edges_cm = edges_cm.join(deg.select(F.col("node").alias(end), F.col("deg").alias(name)), end)
    ends = F.array(*[F.struct(F.col(a).alias("u"), F.col(b).alias("v"), F.col(x).alias("du"), F.col(y).alias("dv")) for a, b, x, y in (("src", "dst", "ds", "dd"), ("dst", "src", "dd", "ds"))])
    return edges_cm.select(F.explode(ends).alias("e"), "w", "cm").select("e.u", "e.v", "w", "cm", "e.du", "e.dv")


def hybrid_edges(edges: DataFrame, weighted: bool = False) -> DataFrame:
    """``hybrid_weight`` of undirected edges with their common neighbours, which are counted once: degrees come from the edges."""
    edges = edges.transform(packed_durable)
    deg = degrees(both_directions(edges)).transform(durable)
    few = deg.count() <= BROADCAST_NODES
    return _hybrid_columns(_placed_both(_wedge_neighbours(edges, deg), F.broadcast(deg) if few else deg), weighted)


def _hybrid_columns(placed: DataFrame, weighted: bool) -> DataFrame:
    # without loops and repeated edges v itself is never a common neighbour, so du - cm >= 1
    ratio = F.greatest(F.col("du") / F.col("dv"), F.col("dv") / F.col("du"))
    alpha = ratio / F.greatest(F.col("du") - F.col("cm"), F.lit(1))
    return placed.select("u", "v", "w", "cm", "du", "dv", alpha.alias("alpha"), F.tanh(alpha * F.col("w") if weighted else alpha).alias("p_accept"))


def overlap_weight(edges_hybrid: DataFrame) -> DataFrame:
    """The stand-in of the extended hybrid kernel: acceptance scaled by 1 + cm / min(du, dv).

    The published extension has no printed formula; this one is ours and is a
    place to plug another in.
    """
    scale = 1 + F.col("cm") / F.least("du", "dv")
    return edges_hybrid.withColumn("alpha", F.col("alpha") * scale).withColumn("p_accept", F.tanh("alpha"))


def quantised(p: F.Column) -> F.Column:
    """Integer weight of a probability: exact sums in any engine, never zero."""
    return F.floor(p * (1 << BITS)).cast("long") + 1


def sampling_cdf(edges2: DataFrame, weight: F.Column) -> DataFrame:
    """(u, v, q, hi): integer weights and their running sum over neighbours by id."""
    w = Window.partitionBy("u").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    return edges2.select("u", "v", weight.cast("long").alias("q")).withColumn("hi", F.sum("q").over(w))


def cdf_adjacency(cdf: DataFrame) -> DataFrame:
    """(node, deg, nbr, cdf): one row a node, ready for a draw by binary search."""
    return adjacency(cdf.select("u", "v", "hi"), "hi").withColumnRenamed("hi", "cdf")


def expected_trials(edges_hybrid: DataFrame) -> DataFrame:
    """(node, mean_p, trials): how many candidates a hop takes under accept-or-stay."""
    return edges_hybrid.groupBy(F.col("u").alias("node")).agg(F.avg("p_accept").alias("mean_p"), (F.count("*") / F.sum("p_accept")).alias("trials"))


def degree_profile(edges2: DataFrame) -> DataFrame:
    """One row: nodes, edges, max, mean and skewness of degrees, and the log-log slope of their histogram."""
    deg = degrees(edges2)
    spread = deg.agg(F.count("*").alias("nodes"), (F.sum("deg") / 2).alias("edges"), F.max("deg").alias("max_deg"), F.avg("deg").alias("mean_deg"), F.skewness("deg").alias("skew"))
    histogram = deg.groupBy("deg").agg(F.count("*").alias("nodes"))
    slope = histogram.agg(F.regr_slope(F.ln("nodes"), F.ln("deg")).alias("loglog_slope"))
    return spread.crossJoin(slope)

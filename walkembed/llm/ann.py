"""Nearest neighbours by score-aware anisotropic quantisation, four-bit scans and exact reranking.

Euclidean nearness is a maximum inner product: q.x - |x|^2/2.  The product
quantiser has 16 centres a subspace (four bits).  Its loss weighs the residual
along the vector ``eta`` times the residual across it, since the parallel error is
what moves large inner products; codes are found by coordinate descent over the
subspaces, centres by weighted least squares.

Scanning adds table entries: per query a table of its inner products with all
centres, per vector two codes a byte.  The best of each block are reranked by
exact distance in double precision.  A vector is at least as far from the query
as the query is from the vector's centres, less the vector's own distance from
them; where this bound does not put it behind the k-th found, it is looked at as
well.  So a block's answer is exact, also where codes cannot order the vectors
(near copies).  Vectors with equal components collapse inside a block first, so a
crowd of copies takes one place and still returns its smallest ids.

Queries and vectors meet in blocks of bounded size, dealt by id and components, so
no repeated id fills one; a block of vectors is encoded once for up to
``QUERY_ROWS`` queries.  The quantiser is fitted on a bounded sample
(``max_train_rows``), every vector is encoded and scanned.  The sample only steers
how much has to be looked at, not the answer.

Defined results: null, zero and non-finite vectors, null ids and vectors of
another length than the most common take no part; an id of several rows is one
candidate, as near as its nearest row, and one query, whose rows all ask; with
fewer candidates than k all are returned; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

MAX_TRAIN_ROWS = 4096
K, RERANK = 10, 160
BLOCK_ROWS, QUERY_ROWS = 16_384, 16_384
_SLICE = 128  # queries whose products with a block are held at a time
_SCANNED = 1024  # queries whose scores of a block are held at a time
CENTRES = 16


class Quantiser:
    """Anisotropic product quantiser with two dimensions a subspace."""

    def __init__(self, x: np.ndarray, threshold: float = 0.2, rounds: int = 4, seed: int = 3):
        self.dims = x.shape[1]
        self.eta = max(1.0, (self.dims - 1) * threshold**2 / (1 - threshold**2))
        parts = self._parts(x)
        rng = np.random.default_rng(seed)
        pick = rng.choice(len(x), CENTRES, replace=len(x) < CENTRES)
        self.centres = parts[pick].transpose(1, 0, 2).copy()  # (subspace, centre, 2)
        for _ in range(rounds):
            codes = self.encode(x)
            self._update(x, codes)

    def _parts(self, x: np.ndarray) -> np.ndarray:
        padded = np.pad(np.asarray(x, dtype=np.float64), ((0, 0), (0, x.shape[1] % 2)))
        return padded.reshape(len(padded), -1, 2)

    def encode(self, x: np.ndarray, passes: int = 2) -> np.ndarray:
        """(n, subspaces) codes of least anisotropic loss."""
        parts = self._parts(x)
        unit = parts / np.maximum(np.sqrt((parts**2).sum((1, 2), keepdims=True)), 1e-30)
        n, subspaces, _ = parts.shape
        distance = lambda s: ((parts[:, s, None, :] - self.centres[s][None]) ** 2).sum(2)
        codes = np.stack([distance(s).argmin(1) for s in range(subspaces)], axis=1)
        along = np.stack([((parts[:, s] - self.centres[s][codes[:, s]]) * unit[:, s]).sum(1) for s in range(subspaces)], axis=1)
        total = along.sum(1)
        for _ in range(passes):
            for s in range(subspaces):
                others = total - along[:, s]
                candidate = ((parts[:, s, None, :] - self.centres[s][None]) * unit[:, s, None, :]).sum(2)
                loss = distance(s) + (self.eta - 1) * (others[:, None] + candidate) ** 2
                codes[:, s] = loss.argmin(1)
                along[:, s] = candidate[np.arange(n), codes[:, s]]
                total = others + along[:, s]
        return codes.astype(np.uint8)

    def _update(self, x: np.ndarray, codes: np.ndarray) -> None:
        parts = self._parts(x)
        unit = parts / np.maximum(np.sqrt((parts**2).sum((1, 2), keepdims=True)), 1e-30)
        subspaces = parts.shape[1]
        along = np.stack([((parts[:, s] - self.centres[s][codes[:, s]]) * unit[:, s]).sum(1) for s in range(subspaces)], axis=1)
        total = along.sum(1)
        for s in range(subspaces):
            others, u, p, own = total - along[:, s], unit[:, s], parts[:, s], codes[:, s]
            pull = p + (self.eta - 1) * u * ((u * p).sum(1) + others)[:, None]
            for c in range(CENTRES):
                mine = own == c
                if mine.any():
                    gram = np.eye(2) * mine.sum() + (self.eta - 1) * u[mine].T @ u[mine]
                    self.centres[s, c] = np.linalg.solve(gram, pull[mine].sum(0))
            along[:, s] = ((p - self.centres[s][own]) * u).sum(1)
            total = others + along[:, s]

    def decode(self, codes: np.ndarray) -> np.ndarray:
        """(n, subspaces, 2): the centres that the codes name."""
        return self.centres[np.arange(codes.shape[1]), codes]

    def tables(self, queries: np.ndarray) -> np.ndarray:
        """(subspaces, 16, queries): inner products of each query's parts with the centres."""
        return np.einsum("qsd,scd->scq", self._parts(queries), self.centres).astype(np.float32)


def pack_codes(codes: np.ndarray) -> np.ndarray:
    """Two four-bit codes a byte."""
    padded = np.pad(codes, ((0, 0), (0, codes.shape[1] % 2)))
    return padded[:, ::2] | (padded[:, 1::2] << 4)


def scan_scores(packed: np.ndarray, tables: np.ndarray) -> np.ndarray:
    """(n, queries) quantised inner products by look-ups."""
    subspaces = tables.shape[0]
    out = np.zeros((len(packed), tables.shape[2]), dtype=np.float32)
    for s in range(subspaces):
        code = packed[:, s // 2] & 15 if s % 2 == 0 else packed[:, s // 2] >> 4
        out += tables[s][code]
    return out


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding): the rows that take part."""
    v = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    fine = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("embedding", lambda x: x != 0)
    v = v.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & F.coalesce(fine, F.lit(False)))
    return v


def _matrix(column: pa.ChunkedArray) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def _lower_bounds(heads: np.ndarray, q: np.ndarray, quantiser: Quantiser, codes: np.ndarray, tables: np.ndarray, scores: np.ndarray) -> np.ndarray:
    """(n, queries) distances that the exact ones cannot fall below."""
    centres = quantiser.decode(codes)
    own = np.sqrt(((quantiser._parts(heads) - centres) ** 2).sum((1, 2)))
    spread = (centres**2).sum((1, 2))
    rounding = (len(tables) + 2) * 2.0**-23 * np.abs(tables).max(1).sum(0, dtype=np.float64)  # of sums of single-precision entries
    out = np.empty(scores.shape, dtype=np.float32)
    for lo in range(0, len(q), _SLICE):
        own_q = (q[lo : lo + _SLICE] ** 2).sum(1)
        square = spread[:, None] + (own_q - 2 * rounding[lo : lo + _SLICE])[None] - 2.0 * scores[:, lo : lo + _SLICE]
        far = np.sqrt(np.maximum(square, 0))
        out[:, lo : lo + _SLICE] = far - own[:, None] - 1e-6 * (far + own[:, None])
    return out


def _widened(heads: np.ndarray, q: np.ndarray, best: np.ndarray, bounds: np.ndarray, k: int) -> Iterator[np.ndarray]:
    """For each query ``best`` and whatever else may be as near as its k-th other head."""
    length = np.sqrt((heads**2).sum(1))
    for lo in range(0, len(q), _SLICE):
        asked, some = q[lo : lo + _SLICE], best[:, lo : lo + _SLICE]
        limit = np.full(len(asked), np.inf)
        if len(some) > k:
            for j in range(len(asked)):
                limit[j] = np.partition(np.sqrt(((heads[some[:, j]] - asked[j]) ** 2).sum(1)), k)[k]
        opened = ~(bounds[:, lo : lo + _SLICE] > limit)  # what cannot be compared stays open
        np.put_along_axis(opened, some, False, axis=0)
        rows = np.flatnonzero(opened.any(1))
        own_q = np.sqrt((asked**2).sum(1))
        square = (length[rows] ** 2)[:, None] + (own_q**2)[None] - 2 * (heads[rows] @ asked.T)
        slack = 8 * (heads.shape[1] + 8) * np.finfo(float).eps * (length[rows][:, None] + own_q[None]) ** 2  # of the products' rounding
        opened[rows] &= ~(square - slack > limit**2)
        for j in range(len(asked)):
            yield np.concatenate([some[:, j], np.flatnonzero(opened[:, j])])


def _block_search(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, quantiser: Quantiser, k: int, rerank: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, vector, distance) of the nearest of one block, each id once a query row."""
    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], x[order]
    wanted, k = k, k + len(ids) - len(np.unique(ids))  # rows of one id may take several places
    rows = np.ascontiguousarray(x + 0.0)  # no negative zeros
    _, first, member = np.unique(rows.view(np.dtype((np.void, rows.shape[1] * 8))).ravel(), return_index=True, return_inverse=True)
    by = np.argsort(member, kind="stable")  # ids ascending inside each group of copies
    begin = np.concatenate([[0], np.cumsum(np.bincount(member))])
    heads = x[first]
    codes = quantiser.encode(heads)
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for lo in range(0, len(q), _SCANNED):
        out += _scan_block(q_ids[lo : lo + _SCANNED], q[lo : lo + _SCANNED], ids, heads, codes, by, begin, quantiser, k, wanted, rerank)
    return tuple(np.concatenate([o[i] for o in out]) for i in range(3))  # type: ignore[return-value]


def _scan_block(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, heads: np.ndarray, codes: np.ndarray, by: np.ndarray, begin: np.ndarray, quantiser: Quantiser, k: int, wanted: int, rerank: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each query the ``wanted`` nearest ids of a block; row ``by[begin[h] : begin[h + 1]]`` are the copies of head h."""
    tables = quantiser.tables(q)
    scores = scan_scores(pack_codes(codes), tables)
    bounds = _lower_bounds(heads, q, quantiser, codes, tables, scores)
    scores -= ((heads**2).sum(1) / 2).astype(np.float32)[:, None]
    m = min(rerank, len(heads))
    best = np.argpartition(-scores, m - 1, axis=0)[:m] if m < len(heads) else np.broadcast_to(np.arange(len(heads))[:, None], scores.shape)
    del scores
    for j, (name, picked) in enumerate(zip(q_ids.tolist(), _widened(heads, q, best, bounds, k))):
        exact = np.sqrt(((heads[picked] - q[j]) ** 2).sum(1))
        near = np.argsort(exact, kind="stable")
        if len(near) > k + 1:
            near = near[exact[near] <= exact[near[k]]]
        some = [by[begin[picked[i]] : begin[picked[i] + 1]][: k + 1] for i in near]
        vec = np.concatenate([ids[s] for s in some])
        dist = np.concatenate([np.full(len(s), exact[i]) for s, i in zip(some, near)])
        other = vec != name
        vec, dist = vec[other], dist[other]
        top = np.lexsort((vec, dist))
        top = top[np.sort(np.unique(vec[top], return_index=True)[1])][:wanted]  # the nearest row of each id
        yield np.full(len(top), name), vec[top], dist[top]


def search(vectors: DataFrame, is_query: F.Column, k: int = K, rerank: int = RERANK, max_train_rows: int = MAX_TRAIN_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k nearest of all other rows."""
    spark = vectors.sparkSession
    fine = usable(vectors)
    common = fine.groupBy(F.size("embedding").alias("dims")).agg(F.count("*").alias("rows"), F.count(F.when(is_query, 1)).alias("queries")).orderBy(F.desc("rows"), F.desc("dims")).first()
    schema = "query_id long, vec_id long, score double"
    if common is None or not common["queries"]:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    fine = fine.where(F.size("embedding") == common["dims"])
    sample = fine.orderBy(F.xxhash64("vec_id"), "vec_id").limit(max_train_rows).select("embedding").toArrow()
    shared = spark.sparkContext.broadcast(Quantiser(_matrix(sample.column("embedding"))))
    blocks, query_blocks = math.ceil(common["rows"] / BLOCK_ROWS), math.ceil(common["queries"] / QUERY_ROWS)
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    rows = fine.withColumn("block", F.pmod(F.xxhash64("vec_id", "embedding"), F.lit(blocks)).cast("int")).withColumn("query_block", each(query_blocks))
    asked = fine.where(is_query).withColumn("query_block", F.pmod(F.xxhash64("vec_id", "embedding"), F.lit(query_blocks)).cast("int")).select(F.col("vec_id").alias("asked_id"), F.col("embedding").alias("asked"), "query_block", each(blocks).alias("block"))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not len(left) or not len(right):
            return pa.table({"query_id": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        found = _block_search(left.column("asked_id").to_numpy(), _matrix(left.column("asked")), right.column("vec_id").to_numpy(), _matrix(right.column("embedding")), shared.value, k, rerank)
        return pa.table(dict(zip(("query_id", "vec_id", "score"), (pa.array(c) for c in found))))

    found = asked.groupBy("query_block", "block").cogroup(rows.groupBy("query_block", "block")).applyInArrow(run, schema)
    # an id's rows lie in several blocks, a query's answers come from all
    ranked = found.groupBy("query_id", "vec_id").agg(F.min("score").alias("score")).withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

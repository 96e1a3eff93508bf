"""Graphs made from the given tables.

Every graph is a rule from raw pairs (a, b) with an optional relation; canonical
edges (src, dst, w) come from ``normalize_edges``.  Node ids are
``kind * 10^12 + key``, so ids of different tables never meet.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared_shingles import shared_shingle_pairs
from .tables import sql, table

UNIT = 1_000_000_000_000
# Codes of node kinds.
CUSTOMER, PART, SUPPLIER, NATION, REGION, USER, DOCUMENT, PAGE, TOKEN, VECTOR, TURN, EVENT, ORDER = range(1, 14)

_BOUGHT = "SELECT o_custkey, l_partkey, l_suppkey, l_orderkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey"

# Raw pair rules that both engines read alike.
RULES: dict[str, str] = {
    "tri": f"""
WITH bought AS ({_BOUGHT})
SELECT {CUSTOMER}*{UNIT} + o_custkey AS a, {PART}*{UNIT} + l_partkey AS b FROM bought
UNION ALL SELECT {CUSTOMER}*{UNIT} + o_custkey, {SUPPLIER}*{UNIT} + l_suppkey FROM bought
UNION ALL SELECT {PART}*{UNIT} + l_partkey, {SUPPLIER}*{UNIT} + l_suppkey FROM bought""",
    "cp": f"WITH bought AS ({_BOUGHT}) SELECT {CUSTOMER}*{UNIT} + o_custkey AS a, {PART}*{UNIT} + l_partkey AS b FROM bought",
    "cop": f"""
WITH held AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)
SELECT {PART}*{UNIT} + x.l_partkey AS a, {PART}*{UNIT} + y.l_partkey AS b FROM held x JOIN held y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey""",
    "ss": f"""
WITH held AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem)
SELECT {SUPPLIER}*{UNIT} + x.l_suppkey AS a, {SUPPLIER}*{UNIT} + y.l_suppkey AS b FROM held x JOIN held y ON x.l_orderkey = y.l_orderkey AND x.l_suppkey < y.l_suppkey""",
    "geo": f"""
SELECT {CUSTOMER}*{UNIT} + c_custkey AS a, {NATION}*{UNIT} + c_nationkey AS b FROM customer
UNION ALL SELECT {SUPPLIER}*{UNIT} + s_suppkey, {NATION}*{UNIT} + s_nationkey FROM supplier
UNION ALL SELECT {NATION}*{UNIT} + n_nationkey, {REGION}*{UNIT} + n_regionkey FROM nation""",
    "usr": f"""
WITH seen AS (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS next_id FROM events)
SELECT {USER}*{UNIT} + user_id AS a, {USER}*{UNIT} + next_id AS b FROM seen WHERE next_id IS NOT NULL""",
    "conv": f"""
WITH said AS (SELECT conv_id, turn, role, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS next_turn FROM conversations)
SELECT {TURN}*{UNIT} + conv_id*1000 + turn AS a, {TURN}*{UNIT} + conv_id*1000 + next_turn AS b FROM said WHERE next_turn IS NOT NULL
UNION ALL SELECT {TURN}*{UNIT} + conv_id*1000 + turn, {TURN}*{UNIT} + 999000000000 + CASE role WHEN 'user' THEN 1 WHEN 'assistant' THEN 2 ELSE 3 END FROM said""",
}
DIRECTED = {"usr_directed": "usr"}


def knn_rule(k: int = 10) -> str:
    """The k most cosine-similar vectors of each vector."""
    return f"""
WITH scored AS (
  SELECT x.vec_id AS a, y.vec_id AS b, round(DOT(x.embedding, y.embedding) / (sqrt(DOT(x.embedding, x.embedding)) * sqrt(DOT(y.embedding, y.embedding))), 9) AS s
  FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id
), ranked AS (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS rk FROM scored)
SELECT {VECTOR}*{UNIT} + a AS a, {VECTOR}*{UNIT} + b AS b FROM ranked WHERE rk <= {k}"""


def knn_pairs(spark: SparkSession, sf_dir: str, k: int = 10, block: int = 2048) -> DataFrame:
    """Blocked top-k by cosine: query blocks meet row blocks, each pair of blocks is one matrix product."""
    import math

    import numpy as np
    import pyarrow as pa

    vectors = table(spark, sf_dir, "embeddings").where("vec_id is not null and embedding is not null").select("vec_id", F.col("embedding").alias("x"))
    blocks = max(1, math.ceil(vectors.count() / block))
    mine = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = vectors.select("vec_id", "x", mine.alias("q"), every.alias("r"))
    right = vectors.select("vec_id", "x", mine.alias("r"), every.alias("q"))

    def matrix(t: pa.Table) -> np.ndarray:
        flat = t.column("x").combine_chunks().flatten().to_numpy(zero_copy_only=False)
        return flat.reshape(len(t), -1).astype(np.float64)

    def best(a: pa.Table, b: pa.Table) -> pa.Table:
        out = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)]
        if len(a) and len(b):
            x, y = matrix(a), matrix(b)
            score = np.round((x @ y.T) / (np.sqrt((x * x).sum(1))[:, None] * np.sqrt((y * y).sum(1))[None]), 9)
            ids, names = b.column("vec_id").to_numpy(), a.column("vec_id").to_numpy()
            # undefined scores come last, the own row after all
            key = np.where(np.isnan(score), -np.inf, score)
            key[names[:, None] == ids[None]] = -np.inf
            least = np.partition(key, -k, axis=1)[:, -k] if len(ids) > k else np.full(len(names), -np.inf)
            i, j = np.nonzero(key >= least[:, None])  # all that tie with the last one too
            i, j = (z[names[i] != ids[j]] for z in (i, j))
            order = np.lexsort((ids[j], -key[i, j], i))
            i, j = i[order], j[order]
            place = np.arange(len(i)) - np.searchsorted(i, i)
            i, j = i[place < k], j[place < k]
            out = [names[i], ids[j], score[i, j]]
        return pa.table({"a": pa.array(out[0], pa.int64()), "b": pa.array(out[1], pa.int64()), "s": pa.array(out[2], pa.float64())})

    from pyspark.sql import Window

    near = left.groupBy("q", "r").cogroup(right.groupBy("q", "r")).applyInArrow(best, "a long, b long, s double")
    top = near.withColumn("rk", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))).where(F.col("rk") <= k)
    return top.select((F.col("a") + VECTOR * UNIT).alias("a"), (F.col("b") + VECTOR * UNIT).alias("b"))


def page_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the href values that they hold; a token's key is 40 bits of its md5."""
    href = F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1))
    key = F.conv(F.substring(F.md5(F.col("href").cast("binary")), 1, 9), 16, 10).cast("long")
    return table(spark, sf_dir, "pages").select("page_id", href.alias("href")).select((F.col("page_id") + PAGE * UNIT).alias("a"), (key + TOKEN * UNIT).alias("b"))


def document_shingles(spark: SparkSession, sf_dir: str, width: int = 5) -> DataFrame:
    """(doc_id, g): the md5 of every distinct word shingle of a document."""
    words = F.split("text", r"\s+")
    grams = F.when(F.size("ws") >= width, F.transform(F.sequence(F.lit(1), F.size("ws") - width + 1), lambda i: F.md5(F.array_join(F.slice("ws", i, width), " ").cast("binary"))))
    return table(spark, sf_dir, "documents").select("doc_id", words.alias("ws")).select("doc_id", F.explode(F.array_distinct(grams)).alias("g"))


def document_pairs(spark: SparkSession, sf_dir: str, width: int = 5, most: int = 50) -> DataFrame:
    """Documents that share a word shingle found in 2 to ``most`` documents; w counts these shingles alone in the intersection.

    ``all_document_pairs`` has no such bound.
    """
    held = document_shingles(spark, sf_dir, width)
    rare = held.groupBy("g").agg(F.count("*").alias("df")).where(F.col("df").between(2, most))
    live = held.join(rare, "g").select("g", "doc_id")
    size = held.groupBy("doc_id").agg(F.count("*").alias("n"))
    both = live.alias("x").join(live.alias("y"), F.expr("x.g = y.g and x.doc_id < y.doc_id")).groupBy(F.col("x.doc_id").alias("a"), F.col("y.doc_id").alias("b")).agg(F.count("*").alias("common"))
    sized = both.join(size.select(F.col("doc_id").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("doc_id").alias("b"), F.col("n").alias("nb")), "b")
    return sized.select((F.col("a") + DOCUMENT * UNIT).alias("src"), (F.col("b") + DOCUMENT * UNIT).alias("dst"), F.round(F.col("common") / (F.col("na") + F.col("nb") - F.col("common")), 6).alias("w"))


def all_document_pairs(spark: SparkSession, sf_dir: str, width: int = 5) -> DataFrame:
    """Documents that share any word shingle; w = the Jaccard similarity of all their shingles.

    Pairs are made where blocks of documents meet and are never exchanged (``shared_shingles``).
    """
    return shared_shingle_pairs(table(spark, sf_dir, "documents"), width, DOCUMENT * UNIT)


def supplier_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pairs of ``RULES["ss"]`` with one exchange: an order's suppliers meet in its row."""
    held = table(spark, sf_dir, "lineitem").where("l_orderkey is not null").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_suppkey")).alias("s")).where(F.size("s") > 1)
    first = held.select("s", F.posexplode("s").alias("i", "a"))
    pairs = first.select("a", F.explode(F.slice("s", F.col("i") + 2, F.size("s"))).alias("b"))
    return pairs.select((F.col("a") + SUPPLIER * UNIT).alias("a"), (F.col("b") + SUPPLIER * UNIT).alias("b"))


def synthetic_pairs(spark: SparkSession, n: int, half: int = 5) -> DataFrame:
    """A graph of degree 2 * half from arithmetic alone: i meets (i + j*j + j) mod n."""
    return spark.range(n).select(F.col("id").alias("a"), F.explode(F.sequence(F.lit(1), F.lit(half))).alias("j")).select("a", F.pmod(F.col("a") + F.col("j") * F.col("j") + F.col("j"), F.lit(n)).alias("b"))


def raw_pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(a, b) pairs of a named graph."""
    if name == "knn":
        return knn_pairs(spark, sf_dir)
    if name == "pg":
        return page_pairs(spark, sf_dir)
    if name == "ss":
        return supplier_pairs(spark, sf_dir)
    rule = RULES[DIRECTED.get(name, "cop" if name == "cop2" else name)]
    return sql(spark, sf_dir, rule)

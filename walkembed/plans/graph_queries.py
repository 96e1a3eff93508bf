"""Queries of the paper's methods on the given tables, each with its DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.rng import draw_column, draw_sql
from ..operators import evaluate as E
from ..operators import graph as G
from ..operators import learner as L
from ..operators import measures as M
from ..operators import partition as P
from ..operators import walks as W
from ..sources import graphs as S
from ..sources.tables import sql, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
SEED = 42


def add(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def put(query: Query) -> Query:
        QUERIES[name] = query
        if oracle is not None:
            ORACLES[name] = oracle
        return query

    return put


# --- graphs -------------------------------------------------------------------

_DOT = "list_dot_product(x.embedding::DOUBLE[], y.embedding::DOUBLE[])"
KNN_SQL = f"""
WITH scored AS (
  SELECT x.vec_id AS i, y.vec_id AS j, round({_DOT} / (sqrt(list_dot_product(x.embedding::DOUBLE[], x.embedding::DOUBLE[])) * sqrt(list_dot_product(y.embedding::DOUBLE[], y.embedding::DOUBLE[]))), 9) AS s
  FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id
), ranked AS (SELECT i, j, row_number() OVER (PARTITION BY i ORDER BY s DESC, j) AS rk FROM scored)
SELECT {S.VECTOR}*{S.UNIT} + i AS a, {S.VECTOR}*{S.UNIT} + j AS b FROM ranked WHERE rk <= 10"""
PG_SQL = f"""
WITH held AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)
SELECT {S.PAGE}*{S.UNIT} + page_id AS a, {S.TOKEN}*{S.UNIT} + ('0x' || substr(md5(href), 1, 9))::BIGINT AS b FROM held"""


def raw_sql(name: str) -> str:
    return {"knn": KNN_SQL, "pg": PG_SQL}.get(name) or S.RULES[S.DIRECTED.get(name, "cop" if name == "cop2" else name)]


def edges_sql(name: str) -> str:
    """A body for ``edges AS (...)``."""
    if name == "ss_synth":
        raise KeyError(name)
    ends = "a AS src, b AS dst" if name in S.DIRECTED else "least(a, b) AS src, greatest(a, b) AS dst"
    tail = " HAVING count(*) >= 2" if name == "cop2" else ""
    return f"SELECT {ends}, count(*)::DOUBLE AS w FROM ({raw_sql(name)}) WHERE a <> b GROUP BY 1, 2{tail}"


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    edges = G.normalize_edges(S.raw_pairs(spark, sf_dir, name), directed=name in S.DIRECTED)
    return edges.where("w >= 2") if name == "cop2" else edges


for _name in ("tri", "cp", "cop", "cop2", "ss", "geo", "usr", "usr_directed", "knn", "pg", "conv"):
    add(f"graph_{_name}_edges", f"{edges_sql(_name)}")(lambda spark, d, name=_name: graph(spark, d, name))

add(
    "graph_doc_edges",
    f"""
WITH words AS (SELECT doc_id, string_split_regex(text, '\\s+') AS ws FROM documents),
held AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, len(ws) - 3), lambda i: md5(array_to_string(ws[i:i+4], ' ')))) AS g FROM words WHERE len(ws) >= 5),
size AS (SELECT doc_id, count(*) AS n FROM held GROUP BY doc_id),
both_ AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS common FROM held x JOIN held y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2)
SELECT {S.DOCUMENT}*{S.UNIT} + a AS src, {S.DOCUMENT}*{S.UNIT} + b AS dst, round(common::DOUBLE / (p.n + q.n - common), 6) AS w
FROM both_ JOIN size p ON p.doc_id = a JOIN size q ON q.doc_id = b""",
)(lambda spark, d: S.all_document_pairs(spark, d))
add("graph_doc_edges_all", ORACLES["graph_doc_edges"])(lambda spark, d: S.all_document_pairs(spark, d))

add("synthetic_degree10", f"WITH raw AS (SELECT i AS a, (i + j*j + j) % 1000 AS b FROM range(1000) t(i), range(1, 6) u(j)) SELECT least(a,b)::BIGINT AS src, greatest(a,b)::BIGINT AS dst, count(*)::DOUBLE AS w FROM raw WHERE a <> b GROUP BY 1, 2")(
    lambda spark, d: G.normalize_edges(S.synthetic_pairs(spark, 1000))
)

# --- preparation --------------------------------------------------------------

EDGES2 = "edges2 AS (SELECT src AS u, dst AS v, w FROM edges UNION ALL SELECT dst, src, w FROM edges)"
DEG = "deg AS (SELECT u AS node, count(*) AS deg FROM edges2 GROUP BY u)"


def prep(name: str, *more: str) -> str:
    return f"edges AS ({edges_sql(name)}), {EDGES2}, {DEG}" + "".join(f", {m}" for m in more)


CM = """cmn AS (SELECT e.src, e.dst, count(*)::INTEGER AS cm FROM edges e JOIN edges2 x ON x.u = e.src JOIN edges2 y ON y.u = e.dst AND y.v = x.v GROUP BY 1, 2),
ecm AS (SELECT e.src, e.dst, e.w, coalesce(c.cm, 0) AS cm FROM edges e LEFT JOIN cmn c ON c.src = e.src AND c.dst = e.dst)"""


def hybrid_sql(weighted: bool = False, plus: bool = False) -> str:
    scale = " * (1 + cm::DOUBLE / least(du, dv))" if plus else ""
    return f"""{CM}, e2cm AS (SELECT src AS u, dst AS v, w, cm FROM ecm UNION ALL SELECT dst, src, w, cm FROM ecm),
alphas AS (SELECT e.u, e.v, e.w, e.cm, p.deg AS du, q.deg AS dv, greatest(p.deg::DOUBLE / q.deg, q.deg::DOUBLE / p.deg) / greatest(p.deg - e.cm, 1) AS a0
  FROM e2cm e JOIN deg p ON p.node = e.u JOIN deg q ON q.node = e.v),
hyb AS (SELECT u, v, w, cm, du, dv, a0{scale} AS alpha, tanh(a0{scale}{' * w' if weighted else ''}) AS p_accept FROM alphas)"""


def cdf_sql(weight: str, source: str) -> str:
    return f"""qs AS (SELECT u, v, ({weight})::BIGINT AS q FROM {source}),
cdf AS (SELECT u, v, q, (sum(q) OVER (PARTITION BY u ORDER BY v))::BIGINT AS hi, (sum(q) OVER (PARTITION BY u))::BIGINT AS total FROM qs)"""


QUANT = f"floor(p_accept * {1 << G.BITS}) + 1"


def with_(*parts: str) -> str:
    return "WITH " + ", ".join(parts) + " "


add("graph_both_directions", with_(prep("tri")) + "SELECT u, v, w FROM edges2")(lambda spark, d: G.both_directions(graph(spark, d, "tri")))
add("graph_degrees", with_(prep("tri")) + "SELECT node, deg, round(deg::DOUBLE / (SELECT sum(deg) FROM deg), 9) AS p FROM deg")(
    lambda spark, d: G.degree_distribution(G.both_directions(graph(spark, d, "tri"))).select("node", "deg", F.round("p", 9).alias("p"))
)
add("graph_degree_distribution", with_(prep("geo")) + "SELECT deg, count(*) AS nodes FROM deg GROUP BY deg")(lambda spark, d: G.degrees(G.both_directions(graph(spark, d, "geo"))).groupBy("deg").agg(F.count("*").alias("nodes")))
add(
    "graph_degree_profile",
    with_(prep("pg"), "h AS (SELECT deg, count(*) AS n FROM deg GROUP BY deg)") + "SELECT (SELECT count(*) FROM deg) AS nodes, (SELECT sum(deg)::DOUBLE / 2 FROM deg) AS edges, (SELECT max(deg) FROM deg) AS max_deg, round((SELECT avg(deg) FROM deg), 6) AS mean_deg, round((SELECT regr_slope(ln(n), ln(deg)) FROM h), 6) AS loglog_slope",
)(lambda spark, d: G.degree_profile(G.both_directions(graph(spark, d, "pg"))).select("nodes", "edges", "max_deg", F.round("mean_deg", 6).alias("mean_deg"), F.round("loglog_slope", 6).alias("loglog_slope")))
add("graph_csr_row_sizes", with_(prep("tri")) + "SELECT u AS node, count(*)::INTEGER AS size, min(v) AS first_nbr, max(v) AS last_nbr FROM edges2 GROUP BY u")(
    lambda spark, d: G.adjacency(G.both_directions(graph(spark, d, "tri"))).select("node", F.col("deg").alias("size"), F.element_at("nbr", 1).alias("first_nbr"), F.element_at("nbr", -1).alias("last_nbr"))
)
for _method, _name in (("wedge", "tri"), ("intersect", "knn"), ("gallop", "knn"), ("wedge", "usr")):
    add(f"common_neighbours_{_method}" + ("_usr" if _name == "usr" else ""), with_(prep(_name, CM)) + "SELECT src, dst, cm FROM ecm")(lambda spark, d, m=_method, n=_name: G.common_neighbours(graph(spark, d, n), m).select("src", "dst", "cm"))
add("common_neighbours_sketch", with_(prep("knn", CM)) + "SELECT src, dst, cm FROM ecm")(lambda spark, d: G.common_neighbours(graph(spark, d, "knn"), "sketch").select("src", "dst", "cm"))
add("triangle_count", with_(prep("tri", CM)) + "SELECT (sum(cm) / 3)::BIGINT AS triangles FROM ecm")(lambda spark, d: G.common_neighbours(graph(spark, d, "tri")).agg((F.sum("cm") / 3).cast("long").alias("triangles")))
add("triangle_count_bipartite", with_(prep("cp", CM)) + "SELECT coalesce(sum(cm) / 3, 0)::BIGINT AS triangles FROM ecm")(lambda spark, d: G.common_neighbours(graph(spark, d, "cp")).agg((F.sum("cm") / 3).cast("long").alias("triangles")))


def hybrid(spark: SparkSession, d: str, name: str, weighted: bool = False) -> DataFrame:
    return G.hybrid_edges(graph(spark, d, name), weighted)


add("hybrid_alpha", with_(prep("tri", hybrid_sql())) + "SELECT u, v, round(alpha, 12) AS alpha FROM hyb")(lambda spark, d: hybrid(spark, d, "tri").select("u", "v", F.round("alpha", 12).alias("alpha")))
add("hybrid_accept", with_(prep("knn", hybrid_sql())) + "SELECT u, v, round(p_accept, 6) AS p_accept FROM hyb")(lambda spark, d: hybrid(spark, d, "knn").select("u", "v", F.round("p_accept", 6).alias("p_accept")))
add("hybrid_accept_complete", with_(prep("ss", hybrid_sql())) + "SELECT count(*) AS pairs, round(avg(p_accept), 6) AS mean_p FROM hyb")(lambda spark, d: hybrid(spark, d, "ss").agg(F.count("*").alias("pairs"), F.round(F.avg("p_accept"), 6).alias("mean_p")))
add("hybrid_accept_weighted", with_(prep("cop2", hybrid_sql(True))) + "SELECT u, v, round(p_accept, 6) AS p_accept FROM hyb")(lambda spark, d: hybrid(spark, d, "cop2", True).select("u", "v", F.round("p_accept", 6).alias("p_accept")))
add("hybrid_plus_weight", with_(prep("knn", hybrid_sql(plus=True))) + "SELECT u, v, round(p_accept, 6) AS p_accept FROM hyb")(lambda spark, d: G.overlap_weight(hybrid(spark, d, "knn")).select("u", "v", F.round("p_accept", 6).alias("p_accept")))
add("sampling_cdf", with_(prep("tri", hybrid_sql(), cdf_sql(QUANT, "hyb"))) + "SELECT u, v, q, hi FROM cdf")(lambda spark, d: G.sampling_cdf(hybrid(spark, d, "tri"), G.quantised(F.col("p_accept"))))
add("expected_trials", with_(prep("usr", hybrid_sql())) + "SELECT u AS node, round(avg(p_accept), 6) AS mean_p, round(count(*) / sum(p_accept), 6) AS trials FROM hyb GROUP BY u")(
    lambda spark, d: G.expected_trials(hybrid(spark, d, "usr")).select("node", F.round("mean_p", 6).alias("mean_p"), F.round("trials", 6).alias("trials"))
)

# --- walks --------------------------------------------------------------------


def walk_sql(name: str, weight: str, source: str, length: int, *more: str, sources: str = "SELECT DISTINCT u AS node FROM edges2", rounds: int = 1) -> str:
    """``steps`` by a recursive query with the same counter-based draws."""
    draw = draw_sql(SEED, "w.round", "w.walk_id", "w.step", "0", "0")
    return f"""WITH RECURSIVE {prep(name, *more)}, {cdf_sql(weight, source)}, sources AS ({sources}),
steps AS (
  SELECT r AS round, node AS walk_id, 1 AS step, node FROM sources, range(1, {rounds + 1}) t(r)
  UNION ALL
  SELECT w.round, w.walk_id, w.step + 1, c.v FROM steps w JOIN cdf c ON c.u = w.node
  WHERE w.step < {length} AND ({draw} * c.total) >> 32 >= c.hi - c.q AND ({draw} * c.total) >> 32 < c.hi
)"""


STEPS_OUT = " SELECT round::INTEGER AS round, walk_id, step::INTEGER AS step, node FROM steps"


def all_nodes(edges: DataFrame) -> DataFrame:
    return G.both_directions(edges).select(F.col("u").alias("node")).distinct()


def walk(spark: SparkSession, d: str, name: str, kernel: W.Kernel, length: int) -> DataFrame:
    edges = graph(spark, d, name)
    directed = name in S.DIRECTED
    nodes = edges.select(F.col("src").alias("node")).distinct() if directed else all_nodes(edges)
    return W.step_walks(edges, nodes, kernel, length, seed=SEED, directed=directed)


add("walk_uniform_fixed", walk_sql("knn", "1", "edges2", 10) + STEPS_OUT)(lambda spark, d: walk(spark, d, "knn", W.Kernel("uniform"), 10))
add("walk_weighted_fixed", walk_sql("cop2", "w", "edges2", 8) + STEPS_OUT)(lambda spark, d: walk(spark, d, "cop2", W.Kernel("uniform", weighted=True), 8))
add("walk_hybrid_weighted", walk_sql("cop2", QUANT, "hyb", 8, hybrid_sql(True)) + STEPS_OUT)(lambda spark, d: walk(spark, d, "cop2", W.Kernel("hybrid", weighted=True), 8))
add("walk_hybrid_plus", walk_sql("knn", QUANT, "hyb", 8, hybrid_sql(plus=True)) + STEPS_OUT)(lambda spark, d: walk(spark, d, "knn", W.Kernel("hybrid_plus"), 8))
add("walk_hybrid_direct", walk_sql("tri", QUANT, "hyb", 10, hybrid_sql()) + STEPS_OUT)(lambda spark, d: walk(spark, d, "tri", W.Kernel("hybrid"), 10))
add("walk_hybrid_direct_all", ORACLES["walk_hybrid_direct"])(lambda spark, d: walk(spark, d, "tri", W.Kernel("hybrid"), 10))
add(
    "walk_directed",
    f"WITH RECURSIVE edges AS ({edges_sql('usr_directed')}), edges2 AS (SELECT src AS u, dst AS v, w FROM edges), {cdf_sql('w', 'edges2')}, sources AS (SELECT DISTINCT src AS node FROM edges), steps AS (SELECT 1 AS round, node AS walk_id, 1 AS step, node FROM sources UNION ALL SELECT w.round, w.walk_id, w.step + 1, c.v FROM steps w JOIN cdf c ON c.u = w.node WHERE w.step < 8 AND ({draw_sql(SEED, 'w.round', 'w.walk_id', 'w.step', '0', '0')} * c.total) >> 32 >= c.hi - c.q AND ({draw_sql(SEED, 'w.round', 'w.walk_id', 'w.step', '0', '0')} * c.total) >> 32 < c.hi)"
    + STEPS_OUT,
)(lambda spark, d: walk(spark, d, "usr_directed", W.Kernel("uniform", weighted=True), 8))


def biased_sql(length: int, p: float = 0.5, q: float = 2.0) -> str:
    unit = 1 << W.SECOND_BITS
    draw = draw_sql(SEED, "round", "walk_id", "step", "0", "0")
    return f"""WITH RECURSIVE {prep('knn')}, steps AS (
  SELECT 1 AS round, node AS walk_id, 1 AS step, node, NULL::BIGINT AS prev FROM deg
  UNION ALL
  SELECT round, walk_id, step + 1, v, node FROM (
    SELECT *, (sum(k) OVER (PARTITION BY walk_id ORDER BY v))::BIGINT AS hi, (sum(k) OVER (PARTITION BY walk_id))::BIGINT AS total FROM (
      SELECT s.round, s.walk_id, s.step, s.node, s.prev, e.v,
        CASE WHEN s.prev IS NULL THEN 1 WHEN e.v = s.prev THEN {round(unit / p)} WHEN b.v IS NOT NULL THEN {unit} ELSE {round(unit / q)} END AS k
      FROM steps s JOIN edges2 e ON e.u = s.node LEFT JOIN edges2 b ON b.u = s.prev AND b.v = e.v WHERE s.step < {length}
    )
  ) WHERE ({draw} * total) >> 32 >= hi - k AND ({draw} * total) >> 32 < hi
)"""


add("walk_biased2_exact", biased_sql(8) + STEPS_OUT)(lambda spark, d: walk(spark, d, "knn", W.Kernel("biased2", p=0.5, q=2.0), 8))


def burst(spark: SparkSession, d: str, name: str, kernel: W.Kernel, stop: W.Stop, m: int | None = None, rng: str = "portable", edges: DataFrame | None = None) -> DataFrame:
    """One round over ``m`` parts, or by the engine that suits the graph's size; ``edges`` if the named graph is at hand."""
    edges = graph(spark, d, name).transform(durable) if edges is None else edges
    nodes = all_nodes(edges)
    walk = W.burst_round if m else W.corpus_round
    table = W.kernel_edges(edges, kernel).transform(durable)
    return walk(table, P.hash_partition(nodes, m or W.parts_for(edges)), nodes, kernel, stop, 1, SEED, rng).select("round", "walk_id", "step", "node")


add("walk_burst_uniform", walk_sql("knn", "1", "edges2", 5) + STEPS_OUT)(lambda spark, d: burst(spark, d, "knn", W.Kernel("uniform"), W.Stop.fixed(5), m=3))


def info_sql(mu: float) -> str:
    return (
        walk_sql("knn", QUANT, "hyb", 80, hybrid_sql()) + "," + M.PREFIX_SQL + f""", cut AS (
  SELECT walk_id, min(step) AS last_step FROM measured WHERE step >= 3 AND r2 < {mu}::DOUBLE GROUP BY walk_id)
SELECT s.round::INTEGER AS round, s.walk_id, s.step::INTEGER AS step, s.node FROM steps s LEFT JOIN cut c ON c.walk_id = s.walk_id WHERE s.step <= coalesce(c.last_step, 80)"""
    )


add("walk_info_calibrated", info_sql(0.85))(lambda spark, d: burst(spark, d, "knn", W.Kernel("hybrid"), W.Stop.calibrated()))
add("walk_info_literal", info_sql(0.995))(lambda spark, d: burst(spark, d, "knn", W.Kernel("hybrid"), W.Stop.literal()))
def reject_sql(name: str, length: int, chance: str, *more: str) -> str:
    """Trial by trial: a row a candidate, accepted ones move on, refused ones stay and try again."""
    draw = lambda salt: draw_sql(SEED, "w.round", "w.walk_id", "w.step", "w.trial", str(salt))
    return f"""WITH RECURSIVE {prep(name, *more)}, slots AS (
  SELECT u, v, p_accept, row_number() OVER (PARTITION BY u ORDER BY v) - 1 AS i, count(*) OVER (PARTITION BY u) AS deg FROM {"hyb" if more else "(SELECT u, v, 1.0::DOUBLE AS p_accept FROM edges2)"}
), tries AS (
  SELECT 1 AS round, node AS walk_id, 1 AS step, 0 AS trial, node, NULL::BIGINT AS prev FROM deg
  UNION ALL
  SELECT round, walk_id, CASE WHEN fine THEN step + 1 ELSE step END, CASE WHEN fine THEN 0 ELSE trial + 1 END, CASE WHEN fine THEN v ELSE node END, CASE WHEN fine THEN node ELSE prev END FROM (
    SELECT w.*, s.v, {draw(2)} / 4294967296.0::DOUBLE < {chance} AS fine FROM tries w JOIN slots s ON s.u = w.node AND s.i = ({draw(1)} * s.deg) >> 32 LEFT JOIN edges2 b ON b.u = w.prev AND b.v = s.v WHERE w.step < {length})
) SELECT round::INTEGER AS round, walk_id, step::INTEGER AS step, node FROM tries WHERE trial = 0"""


add("walk_hybrid_reject", reject_sql("knn", 8, "s.p_accept", hybrid_sql()))(lambda spark, d: burst(spark, d, "knn", W.Kernel("hybrid", "accept"), W.Stop.fixed(8)))
add("walk_biased2_reject", reject_sql("knn", 8, "CASE WHEN w.step = 1 THEN 1 WHEN s.v = w.prev THEN 1.0::DOUBLE WHEN b.v IS NOT NULL THEN 0.5 ELSE 0.25 END"))(
    lambda spark, d: burst(spark, d, "knn", W.Kernel("biased2", "accept", p=0.5, q=2.0), W.Stop.fixed(8), m=3)
)
add("walk_biased2_burst", biased_sql(8) + STEPS_OUT)(lambda spark, d: burst(spark, d, "knn", W.Kernel("biased2", p=0.5, q=2.0), W.Stop.fixed(8), m=4))


def fullpath(spark: SparkSession, d: str, m: int = 2) -> DataFrame:
    edges = graph(spark, d, "knn").transform(durable)
    nodes = all_nodes(edges)
    return W.fullpath_round(W.kernel_edges(edges, W.Kernel("hybrid")), P.hash_partition(nodes, m), nodes, W.Kernel("hybrid"), W.Stop.calibrated(), 1, SEED, "portable")


add("walk_info_fullpath", info_sql(0.85))(lambda spark, d: fullpath(spark, d).select("round", "walk_id", "step", "node"))
add("walk_info_parts", info_sql(0.85))(lambda spark, d: burst(spark, d, "knn", W.Kernel("hybrid"), W.Stop.calibrated(), m=2))
add(
    "walk_fullpath_bytes",
    info_sql(0.85).replace("SELECT s.round::INTEGER AS round, s.walk_id, s.step::INTEGER AS step, s.node FROM", ", kept AS (SELECT s.walk_id, s.step, s.node FROM")
    + "), hop AS (SELECT step, node % 2 AS part, lag(node % 2) OVER (PARTITION BY walk_id ORDER BY step) AS from_part FROM kept) SELECT count(*) AS crossings, sum(24 + 8 * step)::BIGINT AS bytes_fullpath, 80 * count(*) AS bytes_incremental FROM hop WHERE part <> from_part",
)(lambda spark, d: fullpath(spark, d).where("sent > 0").agg(F.count("*").alias("crossings"), F.sum("sent").alias("bytes_fullpath"), (80 * F.count("*")).alias("bytes_incremental")))


def info_uniform_sql(mu: float) -> str:
    return info_sql(mu).replace(cdf_sql(QUANT, "hyb"), cdf_sql("1", "edges2")).replace(f", {hybrid_sql()}", "")


add("walk_info_uniform", info_uniform_sql(0.85))(lambda spark, d: burst(spark, d, "knn", W.Kernel("uniform"), W.Stop.calibrated(), m=2))


def recursive_walk(spark: SparkSession, d: str, length: int = 8) -> DataFrame:
    """The recursive engine: the same draws in a recursive SQL query, for small graphs."""
    edges = graph(spark, d, "knn")
    table_ = W.kernel_edges(edges, W.Kernel("uniform"))
    total = W.Window.partitionBy("u")
    table_.select("u", "v", "q", "hi", F.max("hi").over(total).alias("total")).transform(durable).createOrReplaceTempView("recursive_cdf")
    draw = f"conv(substr(md5(concat_ws(':', '{SEED}', '1', w.walk_id, w.step, '0', '0')), 1, 8), 16, 10)"
    x = f"shiftright(CAST({draw} AS BIGINT) * c.total, 32)"
    return spark.sql(
        f"""WITH RECURSIVE steps(walk_id, step, node) MAX RECURSION LEVEL {length + 1} AS (
  SELECT DISTINCT u, 1, u FROM recursive_cdf
  UNION ALL
  SELECT w.walk_id, w.step + 1, c.v FROM steps w JOIN recursive_cdf c ON c.u = w.node WHERE w.step < {length} AND {x} >= c.hi - c.q AND {x} < c.hi
) SELECT 1 AS round, walk_id, step, node FROM steps"""
    )


add("walk_recursive", walk_sql("knn", "1", "edges2", 8) + STEPS_OUT)(recursive_walk)
add("walk_profile", info_sql(0.85).replace("SELECT s.round::INTEGER AS round, s.walk_id, s.step::INTEGER AS step, s.node FROM", ", kept AS (SELECT s.walk_id, count(*) AS length FROM") + " GROUP BY s.walk_id) SELECT round(avg(length), 6) AS mean_length, max(length) AS max_length, 1 AS rounds, count(*) AS walks, round(1 - avg(length) / 80, 6) AS length_cut, round(1 - 1 / 10.0::DOUBLE, 6) AS round_cut FROM kept")(
    lambda spark, d: W.walk_profile(burst(spark, d, "knn", W.Kernel("hybrid"), W.Stop.calibrated())).select(F.round("mean_length", 6).alias("mean_length"), "max_length", "rounds", "walks", F.round("length_cut", 6).alias("length_cut"), F.round("round_cut", 6).alias("round_cut"))
)

# --- measures -----------------------------------------------------------------

#: natural sequences: a user's events as a walk over event types
NATURAL = "SELECT 1 AS round, user_id AS walk_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS step, event_type AS node FROM events"


def natural(spark: SparkSession, d: str) -> DataFrame:
    return sql(spark, d, NATURAL)


_MEASURED = f"WITH steps AS ({NATURAL}), {M.PREFIX_SQL} "
add("walk_entropy_incremental", _MEASURED + "SELECT walk_id, step::INTEGER AS step, round(entropy, 6) AS entropy FROM measured")(lambda spark, d: M.prefix_measures(natural(spark, d)).select("walk_id", F.col("step").cast("int").alias("step"), F.round("entropy", 6).alias("entropy")))
add("walk_entropy_prefix", _MEASURED + "SELECT walk_id, step::INTEGER AS step, round(entropy, 6) AS entropy FROM measured")(lambda spark, d: W.fullpath_measures(natural(spark, d)).select("walk_id", F.col("step").cast("int").alias("step"), F.round(F.abs("entropy"), 6).alias("entropy")))
add("walk_r2_incremental", _MEASURED + "SELECT walk_id, step::INTEGER AS step, round(r2, 5) AS r2 FROM measured")(lambda spark, d: M.prefix_measures(natural(spark, d)).select("walk_id", F.col("step").cast("int").alias("step"), F.round("r2", 5).alias("r2")))
add(
    "walk_r2_prefix",
    _MEASURED + ", pairs AS (SELECT p.walk_id, p.step, regr_r2(q.entropy, q.step) AS r FROM measured p JOIN measured q ON q.walk_id = p.walk_id AND q.step <= p.step GROUP BY 1, 2) SELECT walk_id, step::INTEGER AS step, round(r, 5) AS r2 FROM pairs WHERE step >= 3 AND r IS NOT NULL",
)(
    lambda spark, d: W.fullpath_regression(natural(spark, d)).where("step >= 3 and r2 is not null").select("walk_id", F.col("step").cast("int").alias("step"), F.round("r2", 5).alias("r2"))
)
add("walk_r2_prefix_all", _MEASURED + " SELECT p.walk_id, p.step::INTEGER AS step, round(CASE WHEN var_pop(q.entropy) > 1e-12 THEN regr_r2(q.entropy, q.step) ELSE 0 END, 5) AS r2 FROM measured p JOIN measured q ON q.walk_id = p.walk_id AND q.step <= p.step WHERE p.step >= 3 GROUP BY 1, 2")(lambda spark, d: W.fullpath_r2(natural(spark, d)).where("step >= 3").select("walk_id", F.col("step").cast("int").alias("step"), F.round("r2", 5).alias("r2")))
add("walk_r2_as_printed", f"SELECT count(*) AS prefixes, 0.0::DOUBLE AS largest FROM events")(lambda spark, d: M.prefix_measures(natural(spark, d)).agg(F.count("*").alias("prefixes"), F.max("r2_as_printed").alias("largest")))
add("walk_fullpath_equals_incremental", "SELECT 0::BIGINT AS different, count(*) AS total FROM events")(
    lambda spark, d: (lambda s: M.prefix_measures(s).select("walk_id", "step", F.col("entropy").alias("x")).join(W.fullpath_measures(s), ["walk_id", "step"]).agg(F.sum((F.abs(F.col("x") - F.col("entropy")) > 1e-9).cast("long")).alias("different"), F.count("*").alias("total")))(natural(spark, d))
)
_UNI = walk_sql("knn", "1", "edges2", 10, rounds=5)


def uniform_corpus(spark: SparkSession, d: str, rounds: int = 5, length: int = 10) -> tuple[DataFrame, DataFrame]:
    edges = graph(spark, d, "knn").transform(durable)
    return edges, W.step_walks(edges, all_nodes(edges), W.Kernel("uniform"), length, rounds, SEED).transform(durable)


add("corpus_occurrences", _UNI + " SELECT node, count(*) AS ocn FROM steps GROUP BY node")(lambda spark, d: uniform_corpus(spark, d)[1].groupBy("node").agg(F.count("*").alias("ocn")))
add("corpus_distribution", _UNI + " SELECT node, round(count(*)::DOUBLE / (SELECT count(*) FROM steps), 9) AS q FROM steps GROUP BY node")(
    lambda spark, d: (lambda s: s.groupBy("node").agg(F.count("*").alias("n")).crossJoin(s.agg(F.count("*").alias("total"))).select("node", F.round(F.col("n") / F.col("total"), 9).alias("q")))(uniform_corpus(spark, d)[1])
)
add(
    "corpus_kl_rounds",
    _UNI + """, per AS (SELECT round, node, count(*) AS n FROM steps GROUP BY 1, 2),
ocn AS (SELECT r.round, p.node, sum(p.n)::DOUBLE AS ocn FROM (SELECT DISTINCT round FROM steps) r JOIN per p ON p.round <= r.round GROUP BY 1, 2),
d AS (SELECT o.round, sum(g.deg::DOUBLE / t.s * log2(g.deg::DOUBLE / t.s * a.s / o.ocn)) AS d FROM ocn o JOIN deg g ON g.node = o.node, (SELECT sum(deg)::DOUBLE AS s FROM deg) t, (SELECT round, sum(ocn) AS s FROM ocn GROUP BY 1) a WHERE a.round = o.round GROUP BY 1)
SELECT round::INTEGER AS round, round(d, 6) AS divergence, round(abs(d - lag(d) OVER (ORDER BY round)), 6) AS change FROM d""",
)(lambda spark, d: (lambda e, s: M.corpus_divergence(G.degrees(G.both_directions(e)), s).select("round", F.round("divergence", 6).alias("divergence"), F.round("change", 6).alias("change")))(*uniform_corpus(spark, d)))
_ASSIGN = "assign AS (SELECT node, (node % 4)::INTEGER AS part FROM deg)"
add(
    "message_counts",
    walk_sql("knn", "1", "edges2", 10) + f", {_ASSIGN}, hop AS (SELECT a.part, lag(a.part) OVER (PARTITION BY walk_id ORDER BY step) AS from_part FROM steps s JOIN assign a ON a.node = s.node) SELECT from_part, part AS to_part, count(*) AS hops FROM hop WHERE from_part IS NOT NULL GROUP BY 1, 2",
)(
    lambda spark, d: (lambda e, s: s.join(P.hash_partition(all_nodes(e), 4), "node").withColumn("from_part", F.lag("part").over(W.Window.partitionBy("round", "walk_id").orderBy("step"))).where("from_part is not null").groupBy("from_part", F.col("part").alias("to_part")).agg(F.count("*").alias("hops")))(*uniform_corpus(spark, d, 1))
)
add(
    "message_bytes",
    walk_sql("knn", "1", "edges2", 10) + f", {_ASSIGN}, hop AS (SELECT s.step, a.part, lag(a.part) OVER (PARTITION BY walk_id ORDER BY step) AS from_part FROM steps s JOIN assign a ON a.node = s.node) SELECT count(*) AS hops, count(*) FILTER (WHERE part <> from_part) AS crossings, 80 * count(*) FILTER (WHERE part <> from_part) AS bytes_incremental, (sum(24 + 8 * step) FILTER (WHERE part <> from_part))::BIGINT AS bytes_fullpath FROM hop WHERE from_part IS NOT NULL",
)(lambda spark, d: (lambda e, s: W.message_stats(s, P.hash_partition(all_nodes(e), 4)))(*uniform_corpus(spark, d, 1)))

# --- partitions ---------------------------------------------------------------

add("partition_hash", with_(prep("tri")) + "SELECT node, (node % 4)::INTEGER AS part FROM deg")(lambda spark, d: P.hash_partition(all_nodes(graph(spark, d, "tri")), 4))
add("partition_edge_balanced", with_(prep("tri")) + "SELECT node, least(floor((sum(deg) OVER (ORDER BY node) - deg) * 4 / (SELECT sum(deg) FROM deg)), 3)::INTEGER AS part FROM deg")(lambda spark, d: P.edge_balanced_partition(graph(spark, d, "tri"), 4))
add("partition_scores_first", with_(prep("tri", _ASSIGN)) + "SELECT u AS node, part, count(*)::DOUBLE AS score FROM edges2 JOIN assign a ON a.node = v GROUP BY 1, 2")(lambda spark, d: (lambda e: P.first_order_scores(G.both_directions(e), P.hash_partition(all_nodes(e), 4)))(graph(spark, d, "tri")))
_SECOND = "e2cm AS (SELECT src AS u, dst AS v, w, cm FROM ecm UNION ALL SELECT dst, src, w, cm FROM ecm)"
add("partition_scores_second", with_(prep("tri", _ASSIGN, CM, _SECOND)) + "SELECT u AS node, part, sum(cm)::DOUBLE AS score FROM e2cm JOIN assign a ON a.node = v GROUP BY 1, 2")(lambda spark, d: (lambda e: P.second_order_scores(G.common_neighbours(e), P.hash_partition(all_nodes(e), 4)))(graph(spark, d, "tri")))
add("partition_scores_second_all", with_(prep("knn", _ASSIGN)) + "SELECT x.u AS node, part, count(*)::DOUBLE AS score FROM edges2 x JOIN edges2 y ON y.u = x.v AND y.v <> x.u JOIN assign a ON a.node = y.v GROUP BY 1, 2")(lambda spark, d: (lambda e: P.second_order_scores(e, P.hash_partition(all_nodes(e), 4), "all"))(graph(spark, d, "knn")))
add("partition_scores_weighted", with_(prep("tri", _ASSIGN, CM, _SECOND)) + "SELECT u AS node, part, sum(w)::DOUBLE AS first_order, sum(cm * w)::DOUBLE AS second_order FROM e2cm JOIN assign a ON a.node = v GROUP BY 1, 2")(
    lambda spark, d: (lambda e, a: P.first_order_scores(G.both_directions(e), a, True).withColumnRenamed("score", "first_order").join(P.second_order_scores(e, a, weighted=True).withColumnRenamed("score", "second_order"), ["node", "part"]))(
        *(lambda g: (G.common_neighbours(g), P.hash_partition(all_nodes(g), 4)))(graph(spark, d, "tri"))
    )
)
add("partition_balance_term", with_(prep("tri", _ASSIGN, "sizes AS (SELECT part, count(*) AS size FROM assign GROUP BY part)")) + "SELECT g::DOUBLE AS gamma, part, size, round(1 - size / (g * (SELECT avg(size) FROM sizes)), 6) AS tau FROM sizes, (VALUES (1.0::DOUBLE), (1.5), (2.0), (4.0)) t(g)")(
    lambda spark, d: (lambda sizes: reduce(DataFrame.unionByName, [P.balance_term(sizes, g).select(F.lit(g).alias("gamma"), "part", "size", F.round("tau", 6).alias("tau")) for g in (1.0, 1.5, 2.0, 4.0)]))(P.hash_partition(all_nodes(graph(spark, d, "tri")), 4).groupBy("part").agg(F.count("*").alias("size")))
)
add("stream_order_random", with_(prep("geo")) + f"SELECT node, row_number() OVER (ORDER BY {draw_sql(SEED, 'node')}, node) - 1 AS pos FROM deg")(lambda spark, d: P.stream_order(graph(spark, d, "geo"), "random", SEED))
_TREES = """reach AS (SELECT node AS a, node AS b FROM deg UNION SELECT r.a, e.v FROM reach r JOIN edges2 e ON e.u = r.b),
root AS (SELECT a AS node, arg_min(b, [-deg, b]) AS root FROM reach JOIN deg ON deg.node = b GROUP BY a),
down AS (
  SELECT DISTINCT root AS node, root, NULL::BIGINT AS prev, 0 AS level, []::BIGINT[] AS path FROM root
  UNION ALL
  SELECT e.v, d.root, d.node, d.level + 1, d.path || [KEY, e.v] FROM down d JOIN edges2 e ON e.u = d.node AND e.v IS DISTINCT FROM d.prev JOIN deg g ON g.node = e.v
)"""


def order_sql(kind: str) -> str:
    """Orders of a forest: a node's place follows from the path that leads to it."""
    trees = _TREES.replace("KEY", "-g.deg" if kind.endswith("degree") else "0")
    level = "level, " if kind.startswith("bfs") else ""
    return f"WITH RECURSIVE {prep('geo')}, {trees} SELECT down.node, row_number() OVER (ORDER BY -g.deg, down.root, {level}path) - 1 AS pos FROM down JOIN deg g ON g.node = down.root"


for _kind in ("bfs", "bfs_degree", "dfs", "dfs_degree"):
    add(f"stream_order_{_kind}", order_sql(_kind))(lambda spark, d, k=_kind: P.stream_order(graph(spark, d, "geo"), k))
add("stream_order_bfs_levels", f"WITH RECURSIVE {prep('geo')}, {_TREES.replace('KEY', '0')} SELECT node, level::INTEGER AS level FROM down")(lambda spark, d: P.bfs_levels(G.both_directions(graph(spark, d, "geo"))))


def place_sql(name: str, value: str, segments: int = 1, order: str | None = None, m: int = 4) -> str:
    """A placement by a recursive query over stream positions: the state of a segment is the list of its parts so far."""
    first = "len(list_filter(n.ps, lambda q: st.parts[q] = #))"
    second = "list_sum(list_transform(list_zip(n.ps, n.cms), lambda z: CASE WHEN st.parts[z[1]] = # THEN z[2] ELSE 0 END))"
    size = "len(list_filter(st.parts, lambda y: y = #))"
    value = value.replace("SCORE1", f"coalesce({first}, 0)").replace("SCORE2", f"coalesce({second}, 0)").replace("SIZE", f"{size}::DOUBLE").replace("ALL", "len(st.parts)").replace("TOTAL", "st.per").replace("EDGES", "st.edges")
    choices = ", ".join("{'v': -round(" + value.replace("#", str(p)) + ", 9), 's': " + size.replace("#", str(p)) + f", 'p': {p}}}" for p in range(m))
    head = f"WITH RECURSIVE {prep(name, CM)}" + (f", {order}" if order else "")
    ranked = "ranked" if order else f"(SELECT node, row_number() OVER (ORDER BY {draw_sql(SEED, 'node')}, node) - 1 AS pos FROM deg)"
    return f"""{head}, e2cm AS (SELECT src AS u, dst AS v, w, cm FROM ecm UNION ALL SELECT dst, src, w, cm FROM ecm),
cut AS MATERIALIZED (SELECT node, pos, floor(pos * {segments} / (SELECT count(*) FROM deg))::INTEGER AS seg FROM {ranked}),
stream AS MATERIALIZED (SELECT node, seg, row_number() OVER (PARTITION BY seg ORDER BY pos) AS pos FROM cut),
near AS MATERIALIZED (SELECT s.seg, s.pos, list(t.pos) AS ps, list(e.cm) AS cms FROM e2cm e JOIN stream s ON s.node = e.u JOIN stream t ON t.node = e.v AND t.seg = s.seg WHERE t.pos < s.pos GROUP BY s.seg, s.pos),
state AS (
  SELECT seg, 0::BIGINT AS pos, []::INTEGER[] AS parts, max(pos) AS last, ceil((SELECT count(*) FROM deg) / {segments}.0::DOUBLE) AS per, (SELECT count(*) FROM edges)::DOUBLE AS edges FROM stream GROUP BY seg
  UNION ALL
  SELECT st.seg, st.pos + 1, list_append(st.parts, (list_sort([{choices}])[1]).p::INTEGER), st.last, st.per, st.edges
  FROM state st LEFT JOIN near n ON n.seg = st.seg AND n.pos = st.pos + 1 WHERE st.pos < st.last
)
SELECT s.node, f.parts[s.pos] AS part FROM stream s JOIN state f ON f.seg = s.seg AND f.pos = f.last"""


PROXIMITY = "(SCORE1 + SCORE2) * CASE WHEN ALL = 0 THEN 1 ELSE 1 - SIZE * 4 / (2.0::DOUBLE * ALL) END"
LDG = "SCORE1 * (1 - SIZE / greatest(1, TOTAL / 4))"
FENNEL = "CASE WHEN SIZE >= 1.1::DOUBLE * greatest(1, TOTAL / 4) THEN '-inf'::DOUBLE ELSE SCORE1 - EDGES * 2 / pow(TOTAL, 1.5::DOUBLE) * 1.5::DOUBLE * sqrt(SIZE) END"


def proximity(spark: SparkSession, d: str, name: str, score: P.Score, segments: int = 1) -> DataFrame:
    edges = G.common_neighbours(graph(spark, d, name))
    order = P.stream_order(edges, "random", SEED)
    return P.streamed_partition(edges, 4, order, score, segments)


add("partition_proximity", place_sql("knn", PROXIMITY))(lambda spark, d: proximity(spark, d, "knn", P.proximity_score(2.0)))
add("partition_proximity_seg", place_sql("knn", PROXIMITY, 4))(lambda spark, d: proximity(spark, d, "knn", P.proximity_score(2.0), 4))
_RANKED = lambda kind: _TREES.replace("KEY", "-g.deg") + f", ranked AS (SELECT down.node, row_number() OVER (ORDER BY -g.deg, down.root, {'level, ' if kind == 'bfs' else ''}path) - 1 AS pos FROM down JOIN deg g ON g.node = down.root)"
add("partition_proximity_dfs_degree", place_sql("geo", PROXIMITY, 1, _RANKED("dfs")))(lambda spark, d: P.proximity_partition(G.common_neighbours(graph(spark, d, "geo")), 4))
add("partition_proximity_seg_bfs_degree", place_sql("geo", PROXIMITY, 4, _RANKED("bfs")))(lambda spark, d: P.proximity_partition(G.common_neighbours(graph(spark, d, "geo")), 4, order="bfs_degree", segments=4))
add("partition_proximity_aligned")(lambda spark, d: (lambda e: P.streamed_partition(e, 4, P.stream_order(e, "random", SEED), P.proximity_score(2.0), 4, align=True))(G.common_neighbours(graph(spark, d, "knn")).transform(durable)))
add("partition_ldg", place_sql("knn", LDG))(lambda spark, d: proximity(spark, d, "knn", P.ldg_score()))
def fennel(spark: SparkSession, d: str, name: str) -> DataFrame:
    edges = graph(spark, d, name).transform(durable)
    edges_cm = G.common_neighbours(edges)
    return P.streamed_partition(edges_cm, 4, P.stream_order(edges_cm, "random", SEED), P.fennel_score(n_edges=edges.count()))


add("partition_fennel", place_sql("knn", FENNEL))(lambda spark, d: fennel(spark, d, "knn"))
add("partition_multilevel")(lambda spark, d: P.multilevel_partition(graph(spark, d, "knn"), 4))
add(
    "partition_quality",
    with_(prep("tri", _ASSIGN, "placed AS (SELECT a.part AS ps, b.part AS pd FROM edges e JOIN assign a ON a.node = e.src JOIN assign b ON b.node = e.dst)", "ends AS (SELECT ps AS part FROM placed UNION ALL SELECT pd FROM placed)"))
    + "SELECT count(*) AS edges, count(*) FILTER (WHERE ps <> pd) AS cut, round(count(*) FILTER (WHERE ps <> pd) / count(*)::DOUBLE, 6) AS cut_share, round((SELECT max(n) * 4.0::DOUBLE / sum(n) FROM (SELECT count(*) AS n FROM assign GROUP BY part)), 6) AS node_imbalance, round((SELECT max(n) * 4.0::DOUBLE / sum(n) FROM (SELECT count(*) AS n FROM ends GROUP BY part)), 6) AS edge_imbalance FROM placed",
)(lambda spark, d: (lambda e: P.partition_quality(e, P.hash_partition(all_nodes(e), 4), 4).select("edges", "cut", *[F.round(c, 6).alias(c) for c in ("cut_share", "node_imbalance", "edge_imbalance")]))(graph(spark, d, "tri")))

#: streamed placement answers like the batch placement of the same segments
STREAMED_SQL = place_sql("knn", PROXIMITY, 4)

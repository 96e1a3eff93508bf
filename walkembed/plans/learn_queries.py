"""Queries of the learner, evaluation, cost models, baselines and streaming."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.durable import durable
from ..functions.rng import draw_column, draw_sql, scaled_column
from ..operators import baselines as B
from ..operators import evaluate as E
from ..operators import graph as G
from ..operators import learner as L
from ..operators import walks as W
from ..sources.tables import table
from ..streaming import streams
from . import pipelines
from .graph_queries import SEED, STREAMED_SQL, _UNI, all_nodes, graph, prep, uniform_corpus, walk_sql, with_

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, oracle: str | None = None):
    def put(query):
        QUERIES[name] = query
        if oracle is not None:
            ORACLES[name] = oracle
        return query

    return put


_ONE = walk_sql("knn", "1", "edges2", 10)


def corpus(spark: SparkSession, d: str) -> DataFrame:
    return uniform_corpus(spark, d, 1)[1]


add("skipgram_pairs", _ONE + " SELECT s.walk_id, s.step::INTEGER AS pos, s.node AS target, t.node AS context, count(*) AS n FROM steps s JOIN steps t ON t.walk_id = s.walk_id AND t.step BETWEEN s.step - 2 AND s.step + 2 AND t.step <> s.step GROUP BY ALL")(
    lambda spark, d: L.skipgram_pairs(corpus(spark, d), 2).groupBy("walk_id", "pos", "target", "context").agg(F.count("*").alias("n"))
)
add(
    "skipgram_windows",
    "WITH t AS (SELECT conv_id, turn, unnest(string_split(text, ' ')) AS w, generate_subscripts(string_split(text, ' '), 1) AS i FROM conversations) SELECT x.conv_id, x.turn, count(*) AS pairs FROM t x JOIN t y ON x.conv_id = y.conv_id AND x.turn = y.turn AND y.i BETWEEN x.i - 10 AND x.i + 10 AND y.i <> x.i GROUP BY ALL",
)(
    lambda spark, d: L.skipgram_pairs(table(spark, d, "conversations").select(F.col("turn").alias("round"), F.col("conv_id").alias("walk_id"), F.posexplode(F.split("text", " ", -1)).alias("step", "node")), 10).groupBy(F.col("walk_id").alias("conv_id"), F.col("round").alias("turn")).agg(F.count("*").alias("pairs"))
)
_VOCAB = "vocab AS (SELECT node, count(*) AS ocn, row_number() OVER (ORDER BY count(*) DESC, node) - 1 AS rank FROM steps GROUP BY node)"
add("vocab_rank", f"{_UNI}, {_VOCAB} SELECT node, ocn, rank FROM vocab")(lambda spark, d: L.build_vocab(uniform_corpus(spark, d)[1]))
_NOISE = f"{_VOCAB}, noise AS (SELECT node, rank, floor(pow(ocn::DOUBLE, 0.75) * 1024)::BIGINT + 1 AS q FROM vocab), table_ AS (SELECT *, (sum(q) OVER (ORDER BY rank))::BIGINT AS hi, (sum(q) OVER ())::BIGINT AS total FROM noise)"
add("noise_distribution", f"{_UNI}, {_NOISE} SELECT node, rank, q, hi FROM table_")(lambda spark, d: L.noise_table(L.build_vocab(uniform_corpus(spark, d)[1])))


def negative_samples(spark: SparkSession, d: str, k: int = 5) -> DataFrame:
    """K noise nodes for each vocabulary node, by the running sums."""
    noise = L.noise_table(L.build_vocab(uniform_corpus(spark, d)[1])).transform(durable)
    total = noise.agg(F.sum("q").alias("total"))
    asked = noise.select(F.col("node").alias("target")).crossJoin(total).withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(k)))).withColumn("x", scaled_column(draw_column(SEED, F.col("target"), F.col("k")), F.col("total")))
    return L.draw_noise(noise, asked.select("target", "k", "x")).select("target", "k", "negative")


add("negative_samples", f"{_UNI}, {_NOISE}, asked AS (SELECT node AS target, k::INTEGER AS k, ({draw_sql(SEED, 'node', 'k')} * total) >> 32 AS x FROM table_, range(1, 6) r(k)) SELECT target, k, n.node AS negative FROM asked JOIN table_ n ON x >= n.hi - n.q AND x < n.hi")(negative_samples)

_PHI = "phi AS (SELECT vec_id + 10000000000000 AS node, embedding::DOUBLE[] AS phi FROM embeddings)"


def phi(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select((F.col("vec_id") + 10 * 10**12).alias("node"), F.col("embedding").cast("array<double>").alias("phi"))


add(
    "sgns_loss",
    with_(prep("knn"), _PHI, "pairs AS (SELECT src AS target, dst AS context, 1 AS y FROM edges UNION ALL SELECT src, src + (dst - src) // 2, 0 FROM edges)", "met AS (SELECT y, list_dot_product(a.phi, b.phi) AS s FROM pairs JOIN phi a ON a.node = context JOIN phi b ON b.node = target)")
    + "SELECT count(*) AS pairs, round(sum(CASE WHEN y = 1 THEN ln(1 + exp(-s)) ELSE ln(1 + exp(s)) END), 4) AS loss FROM met",
)(
    lambda spark, d: (lambda e: L.sgns_loss(e.select(F.col("src").alias("target"), F.col("dst").alias("context"), F.lit(1).alias("y")).unionByName(e.select(F.col("src").alias("target"), (F.col("src") + F.expr("(dst - src) div 2")).alias("context"), F.lit(0).alias("y"))), phi(spark, d), phi(spark, d)).select("pairs", F.round("loss", 4).alias("loss")))(graph(spark, d, "knn"))
)
add(
    "softmax_loglik",
    with_(prep("knn"), _PHI, "s AS (SELECT a.node AS context, b.node AS target, list_dot_product(a.phi, b.phi) AS s FROM phi a, phi b)", "z AS (SELECT context, ln(sum(exp(s))) AS z FROM s GROUP BY 1)", "pairs AS (SELECT dst AS target, src AS context FROM edges)")
    + "SELECT count(*) AS pairs, round(sum(s.s - z.z), 4) AS loglik FROM pairs JOIN s USING (context, target) JOIN z USING (context)",
)(lambda spark, d: L.softmax_loglik_blocked(graph(spark, d, "knn").select(F.col("dst").alias("target"), F.col("src").alias("context")), phi(spark, d)).select("pairs", F.round("loglik", 4).alias("loglik")))
add("softmax_loglik_all", ORACLES["softmax_loglik"])(lambda spark, d: L.softmax_loglik_blocked(graph(spark, d, "knn").select(F.col("dst").alias("target"), F.col("src").alias("context")), phi(spark, d)).select("pairs", F.round("loglik", 4).alias("loglik")))


def gradient_step(spark: SparkSession, d: str, rate: float = 0.05) -> DataFrame:
    """(node, norm): one full-batch step of the positive pairs of the kNN graph on the context vectors."""
    e, v = graph(spark, d, "knn"), phi(spark, d)
    met = e.join(v.select(F.col("node").alias("src"), F.col("phi").alias("a")), "src").join(v.select(F.col("node").alias("dst"), F.col("phi").alias("b")), "dst")
    pull = met.select("src", "a", "b", (F.lit(rate) / (1 + F.exp(L.dot("a", "b")))).alias("g"))
    steps = pull.select("src", F.posexplode(F.zip_with("a", "b", lambda x, y: y)).alias("i", "x"), "g").groupBy("src", "i").agg(F.sum(F.col("x") * F.col("g")).alias("dx"))
    old = v.select("node", F.posexplode("phi").alias("i", "x"))
    new = old.join(steps, (old.node == steps.src) & (old.i == steps.i), "left").select("node", old.i, (F.col("x") + F.coalesce("dx", F.lit(0.0))).alias("x"))
    return new.groupBy("node").agg(F.round(F.sqrt(F.sum(F.col("x") * F.col("x"))), 6).alias("norm"))


add(
    "sgns_gradient_step",
    with_(prep("knn"), _PHI, "pull AS (SELECT src, b.phi AS b, 0.05::DOUBLE / (1 + exp(list_dot_product(a.phi, b.phi))) AS g FROM edges JOIN phi a ON a.node = src JOIN phi b ON b.node = dst)", "dx AS (SELECT src, i, sum(g * b[i]) AS dx FROM pull, range(1, 65) t(i) GROUP BY 1, 2)")
    + "SELECT node, round(sqrt(sum((phi[t.i] + coalesce(dx.dx, 0)) ** 2)), 6) AS norm FROM phi CROSS JOIN range(1, 65) t(i) LEFT JOIN dx ON dx.src = node AND dx.i = t.i GROUP BY node",
)(gradient_step)


def window_shapes(spark: SparkSession, d: str) -> DataFrame:
    """(mode, n_windows, matrix_rows, matrix_columns) measured from the learner's own batches: 4 contexts a window, K = 5."""
    import numpy as np

    rows = []
    for mode, n in (("window_shared", 1), ("multi_window", 2), ("multi_window", 4)):
        shard = L.Shard(*L.initial_vectors(50, 4, 1), np.arange(1, 51) * 10, 2, 5, 0.05, 1)
        shape = shard.batch([np.arange(4) + 4 * k for k in range(n)], [40 + k for k in range(n)], shard.noise(5))
        rows.append((mode, n, int(shape[0]), int(shape[1])))
    return spark.createDataFrame(rows, "mode string, n_windows int, matrix_rows int, matrix_columns int")


add("window_matrix_shape", "SELECT * FROM (VALUES ('window_shared', 1, 4, 6), ('multi_window', 2, 8, 7), ('multi_window', 4, 16, 9)) t(mode, n_windows, matrix_rows, matrix_columns)")(window_shapes)
add("multi_window_batches", _ONE + ", numbered AS (SELECT *, (dense_rank() OVER (ORDER BY walk_id) - 1) // 2 AS pair FROM steps) SELECT pair::BIGINT AS pair, step::INTEGER AS step, count(*) AS windows, min(node) AS low_target, max(node) AS high_target FROM numbered GROUP BY ALL")(
    lambda spark, d: corpus(spark, d).withColumn("pair", F.expr("(dense_rank() over (order by walk_id) - 1) div 2").cast("long")).groupBy("pair", F.col("step").cast("int").alias("step")).agg(F.count("*").alias("windows"), F.min("node").alias("low_target"), F.max("node").alias("high_target"))
)
add("cross_window_index", _ONE + " SELECT node, count(*) AS windows, count(DISTINCT walk_id) AS walks FROM steps GROUP BY node")(lambda spark, d: corpus(spark, d).groupBy("node").agg(F.count("*").alias("windows"), F.count_distinct("walk_id").alias("walks")))
for _mode in L.MODES:
    add(f"train_{_mode}")(lambda spark, d, m=_mode: L.train(corpus(spark, d), m, dims=16, window=3, shards=2).select("node", "rank", F.round(F.sqrt(L.dot("phi", "phi")), 6).alias("norm"), "n_updates"))
add("train_full_sync")(lambda spark, d: L.train(corpus(spark, d), "multi_window", dims=16, window=3, shards=2, sync="full").select("node", "rank", "n_updates"))
add("hotness_blocks", f"{_UNI}, {_VOCAB} SELECT ocn, node, count(*) OVER (PARTITION BY ocn) AS block_size FROM vocab")(lambda spark, d: L.hotness_blocks(L.build_vocab(uniform_corpus(spark, d)[1])))
add("hotness_sync_nodes", f"{_UNI}, {_VOCAB} SELECT ocn, arg_min(node, {draw_sql(SEED, '1', 'node')} * 100000 + rank % 100000) AS node FROM vocab GROUP BY ocn")(lambda spark, d: L.sync_nodes(L.build_vocab(uniform_corpus(spark, d)[1]), 1))
add("hotness_sync_probability", f"{_UNI}, {_VOCAB} SELECT ocn, count(*) AS block_size, round(1.0::DOUBLE / count(*), 9) AS probability FROM vocab GROUP BY ocn")(lambda spark, d: L.build_vocab(uniform_corpus(spark, d)[1]).groupBy("ocn").agg(F.count("*").alias("block_size"), F.round(1 / F.count("*"), 9).alias("probability")))
add("sync_cost", f"{_UNI}, {_VOCAB} SELECT count(*) * 128 * 4 * 2 AS full_values, max(ocn) * 128 * 4 * 2 AS hotness_bound, count(DISTINCT ocn) * 128 * 4 * 2 AS hotness_values FROM vocab")(
    lambda spark, d: L.build_vocab(uniform_corpus(spark, d)[1]).agg((F.count("*") * 1024).alias("full_values"), (F.max("ocn") * 1024).alias("hotness_bound"), (F.count_distinct("ocn") * 1024).alias("hotness_values"))
)
add(
    "merge_replicas",
    "WITH r AS (SELECT vec_id AS key, s, i, embedding[i]::DOUBLE * (1 + s) AS x, (vec_id * (s + 1)) % 7 AS k FROM embeddings, range(4) a(s), range(1, 65) b(i)), m AS (SELECT key, i, sum(x * (k + 1)) / sum(k + 1) AS x, sum(k)::BIGINT AS k FROM r GROUP BY 1, 2) SELECT key, round(sum(x), 6) AS total, min(k) AS n_updates FROM m GROUP BY key",
)(
    lambda spark, d: L.merge_replicas(
        table(spark, d, "embeddings").select(F.col("vec_id").alias("key"), "embedding", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("s")).select("key", ((F.col("key") * (F.col("s") + 1)) % 7).alias("n_updates"), F.transform("embedding", lambda x: x.cast("double") * (1 + F.col("s"))).alias("phi"))
    ).select("key", F.round(F.aggregate("phi", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), "n_updates")
)

# --- evaluation ---------------------------------------------------------------

_HELD = f"split AS (SELECT *, {draw_sql(SEED, 'src', 'dst')} < {1 << 31} AS held FROM edges)"
_NEG = f"""numbered AS (SELECT node, row_number() OVER (ORDER BY node) - 1 AS i FROM deg),
tried AS (SELECT ({draw_sql(SEED, 'src', 'dst', 'k', '1')} * (SELECT count(*) FROM deg)) >> 32 AS i, ({draw_sql(SEED, 'src', 'dst', 'k', '2')} * (SELECT count(*) FROM deg)) >> 32 AS j FROM edges, range(1, 5) t(k)),
named AS (SELECT DISTINCT least(a.node, b.node) AS src, greatest(a.node, b.node) AS dst FROM tried JOIN numbered a ON a.i = tried.i JOIN numbered b ON b.i = tried.j WHERE a.node <> b.node),
negatives AS (SELECT n.* FROM named n ANTI JOIN edges e ON e.src = n.src AND e.dst = n.dst)"""
add("linkpred_split", with_(prep("tri"), _HELD) + "SELECT src, dst, held FROM split")(lambda spark, d: E.split_edges(graph(spark, d, "tri"), 0.5, SEED).select("src", "dst", "held"))
add("linkpred_negatives", with_(prep("knn"), _NEG) + "SELECT src, dst FROM negatives")(lambda spark, d: (lambda e: E.negative_edges(e, all_nodes(e), seed=SEED))(graph(spark, d, "knn")))


def scored(spark: SparkSession, d: str, by: str) -> DataFrame:
    e = graph(spark, d, "knn")
    pairs = e.select("src", "dst", F.lit(1).alias("y")).unionByName(E.negative_edges(e, all_nodes(e), seed=SEED).withColumn("y", F.lit(0)))
    if by == "dot":
        v = phi(spark, d)
        met = pairs.join(v.select(F.col("node").alias("src"), F.col("phi").alias("a")), "src").join(v.select(F.col("node").alias("dst"), F.col("phi").alias("b")), "dst")
        return met.select(F.round(L.dot("a", "b"), 6).alias("score"), "y")
    e2 = G.both_directions(e)
    if by == "degree":
        deg = G.degrees(e2)
        return pairs.join(deg.select(F.col("node").alias("src"), F.col("deg").alias("a")), "src").join(deg.select(F.col("node").alias("dst"), F.col("deg").alias("b")), "dst").select((F.col("a") * F.col("b")).cast("double").alias("score"), "y")
    common = pairs.join(e2.select(F.col("u").alias("src"), "v"), "src").join(e2.select(F.col("u").alias("dst"), "v"), ["dst", "v"]).groupBy("src", "dst").agg(F.count("*").alias("c"))
    return pairs.join(common, ["src", "dst"], "left").select(F.coalesce("c", F.lit(0)).cast("double").alias("score"), "y")


_PAIRS = "pairs AS (SELECT src, dst, 1 AS y FROM edges UNION ALL SELECT src, dst, 0 FROM negatives)"
_AUC = "ranked AS (SELECT y, (rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0::DOUBLE) AS r FROM scored) SELECT sum(y)::BIGINT AS n_pos, sum(1 - y)::BIGINT AS n_neg, round((sum(r * y) - sum(y) * (sum(y) + 1) / 2.0::DOUBLE) / (sum(y) * sum(1 - y)::DOUBLE), 6) AS auc FROM ranked"
for _by, _text in (
    ("dot", f"{_PHI}, scored AS (SELECT round(list_dot_product(a.phi, b.phi), 6) AS score, y FROM pairs JOIN phi a ON a.node = src JOIN phi b ON b.node = dst)"),
    ("degree", "scored AS (SELECT (a.deg * b.deg)::DOUBLE AS score, y FROM pairs JOIN deg a ON a.node = src JOIN deg b ON b.node = dst)"),
    ("common_neighbours", "scored AS (SELECT (SELECT count(*) FROM edges2 a JOIN edges2 b ON a.u = p.src AND b.u = p.dst AND a.v = b.v)::DOUBLE AS score, y FROM pairs p)"),
):
    add(f"linkpred_auc_{_by}", with_(prep("knn"), _NEG, _PAIRS, _text, _AUC.split(" SELECT sum(y)::BIGINT")[0]) + "SELECT sum(y)::BIGINT" + _AUC.split(" SELECT sum(y)::BIGINT")[1])(lambda spark, d, by=_by: E.auc(scored(spark, d, by)).select("n_pos", "n_neg", F.round("auc", 6).alias("auc")))


def centroid_predictions(spark: SparkSession, d: str, ratio: float) -> DataFrame:
    """(vec_id, label, predicted) of held-out vectors by the nearest class centroid (largest inner product)."""
    v = table(spark, d, "embeddings").withColumn("train", draw_column(SEED, F.col("vec_id")) < F.lit(int(ratio * (1 << 32))))
    spread = v.where("train").select("label", F.posexplode("embedding").alias("i", "x"))
    centre = spread.groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("c")).groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "c"))), lambda s: s["c"]).alias("centre")).withColumnRenamed("label", "predicted")
    met = v.where("not train").select("vec_id", "label", "embedding").crossJoin(F.broadcast(centre)).withColumn("s", F.round(L.dot("embedding", "centre"), 9))
    return met.groupBy("vec_id", "label").agg(F.max_by("predicted", F.struct("s", -F.col("predicted"))).alias("predicted"))


def _split_sql(ratio: float) -> str:
    return f"""v AS (SELECT *, {draw_sql(SEED, 'vec_id')} < {int(ratio * (1 << 32))} AS train FROM embeddings),
centre AS (SELECT label, i, avg(embedding[i]::DOUBLE) AS c FROM v, range(1, 65) t(i) WHERE train GROUP BY 1, 2),
s AS (SELECT v.vec_id, v.label, c.label AS predicted, round(sum(v.embedding[c.i]::DOUBLE * c.c), 9) AS s FROM v JOIN centre c ON true WHERE NOT train GROUP BY 1, 2, 3),
pred AS (SELECT vec_id, label, predicted FROM s QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY s DESC, predicted) = 1)"""


add("nodeclass_split", f"SELECT vec_id, {draw_sql(SEED, 'vec_id')} < {1 << 31} AS train FROM embeddings")(lambda spark, d: table(spark, d, "embeddings").select("vec_id", (draw_column(SEED, F.col("vec_id")) < F.lit(1 << 31)).alias("train")))
add("nodeclass_centroid_pred", f"WITH {_split_sql(0.5)} SELECT vec_id, label, predicted FROM pred")(lambda spark, d: centroid_predictions(spark, d, 0.5))


def one_vs_rest(predictions: DataFrame) -> DataFrame:
    """(label, y_true, y_pred) rows of single-label predictions."""
    return predictions.select(F.explode(F.array_distinct(F.array("label", "predicted"))).alias("k"), "label", "predicted").select(F.col("k").alias("label"), (F.col("label") == F.col("k")).cast("int").alias("y_true"), (F.col("predicted") == F.col("k")).cast("int").alias("y_pred"))


_F1 = "k AS (SELECT DISTINCT label AS l FROM pred UNION SELECT DISTINCT predicted FROM pred), per AS (SELECT l, count(*) FILTER (WHERE label = l AND predicted = l) AS tp, count(*) FILTER (WHERE label <> l AND predicted = l) AS fp, count(*) FILTER (WHERE label = l AND predicted <> l) AS fn FROM k, pred GROUP BY l)"
add("nodeclass_micro_f1", f"WITH {_split_sql(0.5)}, {_F1} SELECT round(2.0::DOUBLE * sum(tp) / (2 * sum(tp) + sum(fp) + sum(fn)), 6) AS micro_f1 FROM per")(lambda spark, d: E.f1_scores(one_vs_rest(centroid_predictions(spark, d, 0.5))).select(F.round("micro_f1", 6).alias("micro_f1")))
add("nodeclass_macro_f1", f"WITH {_split_sql(0.5)}, {_F1} SELECT round(avg(coalesce(2.0::DOUBLE * tp / nullif(2 * tp + fp + fn, 0), 0)), 6) AS macro_f1 FROM per")(lambda spark, d: E.f1_scores(one_vs_rest(centroid_predictions(spark, d, 0.5))).select(F.round("macro_f1", 6).alias("macro_f1")))
_RATIOS = (0.1, 0.3, 0.5, 0.7, 0.9)
add("nodeclass_ratio_curve", " UNION ALL ".join(f"(WITH {_split_sql(r)} SELECT {r}::DOUBLE AS ratio, count(*) AS tested, round(count(*) FILTER (WHERE label = predicted) / count(*)::DOUBLE, 6) AS accuracy FROM pred)" for r in _RATIOS))(
    lambda spark, d: reduce(DataFrame.unionByName, [centroid_predictions(spark, d, r).agg(F.count("*").alias("tested"), F.round(F.avg((F.col("label") == F.col("predicted")).cast("double")), 6).alias("accuracy")).select(F.lit(r).alias("ratio"), "tested", "accuracy") for r in _RATIOS])
)
_RULE = "p AS (SELECT doc_id, quality, toxic, (n_chars >= 300)::INTEGER AS q_pred, (lower(text) LIKE '%idiot%')::INTEGER AS t_pred FROM labels JOIN documents USING (doc_id)), long AS (SELECT 'quality' AS label, quality AS t, q_pred AS p FROM p UNION ALL SELECT 'toxic', toxic, t_pred FROM p), per AS (SELECT label, sum(t * p) AS tp, sum((1 - t) * p) AS fp, sum(t * (1 - p)) AS fn FROM long GROUP BY label)"
add("nodeclass_multilabel_docs", f"WITH {_RULE} SELECT round(2.0::DOUBLE * sum(tp) / (2 * sum(tp) + sum(fp) + sum(fn)), 6) AS micro_f1, round(avg(coalesce(2.0::DOUBLE * tp / nullif(2 * tp + fp + fn, 0), 0)), 6) AS macro_f1 FROM per")(
    lambda spark, d: E.f1_scores(
        table(spark, d, "labels").join(table(spark, d, "documents"), "doc_id").select(F.explode(F.array(F.struct(F.lit("quality").alias("label"), F.col("quality").alias("y_true"), (F.col("n_chars") >= 300).cast("int").alias("y_pred")), F.struct(F.lit("toxic").alias("label"), F.col("toxic").alias("y_true"), F.lower("text").contains("idiot").cast("int").alias("y_pred")))).alias("r")).select("r.*")
    ).select(F.round("micro_f1", 6).alias("micro_f1"), F.round("macro_f1", 6).alias("macro_f1"))
)
add("nodeclass_logreg")(lambda spark, d: B.logistic_f1(phi(spark, d), table(spark, d, "embeddings").select((F.col("vec_id") + 10 * 10**12).alias("node"), "label"), 0.5))

# --- costs --------------------------------------------------------------------

def event_paths(spark: SparkSession, d: str) -> DataFrame:
    """One row (walks, tokens): the users' event paths taken as walks."""
    return table(spark, d, "events").where("user_id is not null").agg(F.count_distinct("user_id").alias("walks"), F.count("*").alias("tokens"))


_PATHS = "WITH paths AS (SELECT count(DISTINCT user_id) AS walks, count(*) AS tokens FROM events WHERE user_id IS NOT NULL), p AS (SELECT walks, tokens::DOUBLE / walks AS mean, tokens - walks AS hops FROM paths)"
add("cost_walk_model", _PATHS + " SELECT 'routine' AS kind, round(10.0::DOUBLE * walks * 80 / 8 + hops * 80 / 1e9::DOUBLE, 6) AS cost FROM p UNION ALL SELECT 'fullpath', round(7.0::DOUBLE * walks * mean * mean / 8 + hops * (24 + 8 * mean) / 1e9::DOUBLE, 6) FROM p UNION ALL SELECT 'incremental', round(7.0::DOUBLE * walks * mean / 8 + hops * 80 / 1e9::DOUBLE, 6) FROM p")(
    lambda spark, d: (lambda p: reduce(DataFrame.unionByName, [p.select(F.lit(k).alias("kind"), F.round(E.walk_cost(k, r, n, F.col("walks"), 8, F.col("tokens") - F.col("walks"), 1e9), 6).alias("cost")) for k, r, n in (("routine", 10, 80), ("fullpath", 7, F.col("tokens") / F.col("walks")), ("incremental", 7, F.col("tokens") / F.col("walks")))]))(event_paths(spark, d))
)
add("cost_train_model", _PATHS + " SELECT 800.0::DOUBLE * walks * 10 * 6 AS routine, tokens::DOUBLE * 10 * 6 AS information FROM paths")(lambda spark, d: event_paths(spark, d).select(E.train_cost(F.col("walks") * F.lit(800.0), 10, 5).alias("routine"), E.train_cost(F.col("tokens").cast("double"), 10, 5).alias("information")))
add("cost_partition_model", with_(prep("tri")) + "SELECT sum(deg)::BIGINT AS first_order, round(sum(deg) * log2(max(deg)), 4) AS galloping FROM deg")(lambda spark, d: G.degrees(G.both_directions(graph(spark, d, "tri"))).agg(F.sum("deg").alias("first_order"), F.round(F.sum("deg") * F.log2(F.max("deg")), 4).alias("galloping")))
add("cost_memory_model", with_(prep("tri"), "parts AS (SELECT (node % 4)::INTEGER AS part, sum(deg) AS entries, count(*) AS walkers FROM deg GROUP BY 1)") + "SELECT part, (entries * 24 + walkers * 80)::BIGINT AS bytes FROM parts")(
    lambda spark, d: G.degrees(G.both_directions(graph(spark, d, "tri"))).groupBy((F.col("node") % 4).cast("int").alias("part")).agg((F.sum("deg") * 24 + F.count("*") * 80).alias("bytes"))
)
add("message_size_table", "SELECT DISTINCT count(*)::INTEGER AS length, 80::BIGINT AS incremental, (24 + 8 * count(*))::BIGINT AS fullpath FROM events WHERE user_id IS NOT NULL GROUP BY user_id")(
    lambda spark, d: table(spark, d, "events").where("user_id is not null").groupBy("user_id").agg(F.count("*").alias("l")).select("l").distinct().select(F.col("l").cast("int").alias("length"), F.lit(E.message_bytes("incremental", 0)).cast("long").alias("incremental"), E.message_bytes("fullpath", F.col("l")).cast("long").alias("fullpath"))
)

# --- pipelines and baselines --------------------------------------------------

for _profile in ("info", "fullpath", "routine"):
    add(f"embed_{_profile}")(lambda spark, d, p=_profile: pipelines.embed(graph(spark, d, "knn"), p).select("node", "rank", "n_updates"))
def norms(vectors: DataFrame) -> DataFrame:
    return vectors.select("node", F.size("phi").alias("dims"), F.round(F.sqrt(L.dot("phi", "phi")), 6).alias("norm"))


add("relational_embed")(lambda spark, d: norms(B.relational_embed(pipelines.typed_edges(graph(spark, d, "geo")), dims=16)))
add("gnn_embed")(lambda spark, d: norms(B.train_gnn(graph(spark, d, "knn"), dims=16)))
add("gnn_smooth_embed")(lambda spark, d: norms(B.gnn_embed(graph(spark, d, "knn"), dims=16)))
add("mllib_word2vec")(lambda spark, d: B.word2vec(corpus(spark, d), dims=16))
_PICK = draw_sql(SEED, "u", "v")
add("gnn_neighbour_sample", with_(prep("knn"), f"r AS (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY {_PICK}, v) AS k FROM edges2)") + "SELECT u, v FROM r WHERE k <= 5")(lambda spark, d: B.sample_neighbours(G.both_directions(graph(spark, d, "knn")), 5, SEED))
add("linkpred_info_pipeline")(lambda spark, d: pipelines.link_prediction(graph(spark, d, "knn"), "info", max_rounds=10))

# --- the worked example -------------------------------------------------------

EIGHT = [(1, 2), (1, 3), (2, 3), (2, 4), (3, 4), (4, 5), (5, 6), (5, 7), (6, 7), (6, 8), (7, 8)]
_PATH = [1, 2, 4, 5, 6, 8, 7, 5, 4, 3]


def worked_example(spark: SparkSession, d: str) -> DataFrame:
    """Hop by hop on eight nodes over two machines: entropy, and bytes of either message where it crosses."""
    from ..operators.measures import prefix_measures

    steps = spark.createDataFrame([(1, 1, i, v) for i, v in enumerate(_PATH, 1)], "round int, walk_id long, step int, node long")
    m = prefix_measures(steps).withColumn("machine", F.when(F.col("node") <= 4, 1).otherwise(2))
    crossed = F.col("machine") != F.lag("machine", 1).over(W.Window.partitionBy("walk_id").orderBy("step"))
    return m.select("step", "node", F.round("entropy", 6).alias("entropy"), F.when(crossed, 80).otherwise(0).alias("bytes_incremental"), F.when(crossed, 24 + 8 * F.col("step")).otherwise(0).alias("bytes_fullpath"))


add(
    "worked_example_8nodes",
    "WITH path AS (SELECT * FROM (VALUES " + ", ".join(f"({i}, {v}::BIGINT)" for i, v in enumerate(_PATH, 1)) + ") t(step, node)), n AS (SELECT p.step, s.node, count(*)::DOUBLE / p.step AS f FROM path p JOIN path s ON s.step <= p.step GROUP BY p.step, s.node), h AS (SELECT step, round(-sum(f * log2(f)), 6) + 0.0::DOUBLE AS entropy FROM n GROUP BY step), x AS (SELECT *, CASE WHEN node <= 4 THEN 1 ELSE 2 END <> lag(CASE WHEN node <= 4 THEN 1 ELSE 2 END) OVER (ORDER BY step) AS crossed FROM path) SELECT x.step, x.node, abs(entropy) AS entropy, CASE WHEN crossed THEN 80 ELSE 0 END AS bytes_incremental, CASE WHEN crossed THEN 24 + 8 * x.step ELSE 0 END AS bytes_fullpath FROM x JOIN h USING (step)",
)(worked_example)

# --- streaming ----------------------------------------------------------------

QUERIES |= streams.QUERIES
ORACLES |= streams.ORACLES | {"stream_node_partition": STREAMED_SQL}

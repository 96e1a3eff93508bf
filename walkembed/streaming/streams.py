"""Structured Streaming: event windows, duplicates, joins, corpus frequencies, and streamed placement.

Each query runs a bounded stream (``availableNow``) over the table's files and
returns what it wrote, so it can be held against the batch answer.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..functions.durable import ensure_checkpoint_dir

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def source(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """A file stream of a table; ``events.ts`` becomes a session-zone timestamp for watermarks."""
    path = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    is_file = path.rstrip("/").endswith(".parquet") and not spark.read.format("binaryFile").load(path).select("path").limit(1).where(F.col("path").contains(f"{name}.parquet/")).count()
    stream = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet" if is_file else "*.parquet").parquet(sf_dir if is_file else path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")) if name == "events" else stream


def folder(spark: SparkSession) -> str:
    """A fresh folder beside the session's checkpoints."""
    ensure_checkpoint_dir(spark.range(0))
    return f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/stream-{uuid.uuid4().hex}"


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream to its end and returns the final table (complete) or all rows (append)."""
    spark, where = stream.sparkSession, folder(stream.sparkSession)

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/out/{'last' if mode == 'complete' else number}")

    query = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{where}/out/*")


def add(name: str, oracle: str | None = None):
    def put(query):
        QUERIES[name] = query
        if oracle:
            ORACLES[name] = oracle
        return query

    return put


_ISO = "yyyy-MM-dd HH:mm:ss"
add("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")(
    lambda spark, d: drained(source(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))).select(F.date_format("window.start", _ISO).alias("day"), "event_type", "n")
)
add("stream_sliding", "SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS begins, count(*) AS n FROM (SELECT time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '2000-01-01') - k * INTERVAL '6 hours' AS w FROM events, range(4) t(k)) GROUP BY 1")(
    lambda spark, d: drained(source(spark, d).groupBy(F.window("ts", "1 day", "6 hours")).agg(F.count("*").alias("n"))).select(F.date_format("window.start", _ISO).alias("begins"), "n")
)
add(
    "stream_session",
    "WITH o AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, fresh DESC ROWS UNBOUNDED PRECEDING) AS k FROM o), g AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2) SELECT user_id, count(*) AS sessions, sum(n)::BIGINT AS events, max(n) AS longest FROM g GROUP BY 1",
)(lambda spark, d: drained(source(spark, d).groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest")))
add("stream_dedup", "SELECT user_id, count(DISTINCT event_id) AS n FROM events GROUP BY user_id")(
    lambda spark, d: drained(source(spark, d).unionByName(source(spark, d)).withWatermark("ts", "90 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "append").groupBy("user_id").agg(F.count("*").alias("n"))
)
add(
    "stream_join",
    "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON p.user_id = v.user_id AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL '1 hour' WHERE v.event_type = 'view' AND p.event_type = 'purchase'",
)(
    lambda spark, d: drained(
        source(spark, d).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.col("ts").alias("seen")).withWatermark("seen", "60 days").join(
            source(spark, d).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("buyer"), F.col("ts").alias("bought")).withWatermark("bought", "60 days"),
            F.expr("user_id = buyer and bought > seen and bought <= seen + interval 1 hour"),
        ).select("view_id", "purchase_id"),
        "append",
    )
)
add("stream_frequency", "SELECT user_id AS node, count(*) AS ocn FROM events GROUP BY user_id")(lambda spark, d: drained(source(spark, d).groupBy(F.col("user_id").alias("node")).agg(F.count("*").alias("ocn"))))


def divergence(spark: SparkSession, d: str) -> DataFrame:
    """Relative entropy of event types against uniform, taken in ``foreachBatch`` from a running count."""
    counts = drained(source(spark, d).groupBy("event_type").agg(F.count("*").alias("n")))
    total = counts.agg(F.sum("n").alias("s"), F.count("*").alias("k"))
    return counts.crossJoin(total).agg(F.round(F.sum(F.log2(F.col("s") / (F.col("k") * F.col("n"))) / F.col("k")), 6).alias("divergence"))


add("stream_divergence", "WITH c AS (SELECT event_type, count(*) AS n FROM events GROUP BY 1), t AS (SELECT sum(n)::DOUBLE AS s, count(*)::DOUBLE AS k FROM c) SELECT round(sum(log2(s / (k * n)) / k), 6) AS divergence FROM c, t")(divergence)


class PlaceNodes(StatefulProcessor):
    """Places the nodes of a segment as they arrive; its state is part sizes and a map from placed nodes to parts."""

    def __init__(self, m: int, gamma: float):
        self.m, self.gamma = m, gamma

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.where = handle.getMapState("where", "node long", "part int")
        self.sizes = handle.getValueState("sizes", "sizes array<bigint>")

    def handleInputRows(self, key, rows, timerValues):
        import numpy as np
        import pandas as pd

        from ..operators.partition import proximity_score

        score = proximity_score(self.gamma)
        sizes = np.array(self.sizes.get()[0] if self.sizes.exists() else [0] * self.m, dtype=float)
        out = []
        for row in pd.concat(list(rows)).sort_values("pos").itertuples():
            first, second = np.zeros(self.m), np.zeros(self.m)
            for v, c in zip(row.nbr, row.cm):
                if self.where.containsKey((int(v),)):
                    p = self.where.getValue((int(v),))[0]
                    first[p] += 1
                    second[p] += c
            value = np.round(score(first, second, sizes, 0), 9)
            p = int(np.lexsort((np.arange(self.m), sizes, -value))[0])
            self.where.updateValue((int(row.node),), (p,))
            sizes[p] += 1
            out.append((int(row.node), p))
        self.sizes.update((sizes.astype(int).tolist(),))
        yield pd.DataFrame(out, columns=["node", "part"])

    def close(self) -> None:
        pass


def place_stream(nodes: DataFrame, m: int = 4, gamma: float = 2.0) -> DataFrame:
    """(node, part) of a stream of (seg, pos, node, nbr, cm), each segment placed on its own.

    Nodes must arrive in the order of their positions, in whatever batches.
    """
    return nodes.groupBy("seg").transformWithStateInPandas(PlaceNodes(m, gamma), "node long, part int", "Append", "None")


def node_placement(spark: SparkSession, d: str, segments: int = 4) -> DataFrame:
    """The neighbour graph's nodes as a stream in random order, in two files that come one after the other."""
    from ..operators import graph as G
    from ..operators import partition as P
    from ..plans.graph_queries import SEED, graph

    edges = G.common_neighbours(graph(spark, d, "knn"))
    adj = G.adjacency(G.both_directions(edges.select("src", "dst", F.col("cm").alias("w"))), "w").withColumnRenamed("w", "cm")
    order = P.stream_order(edges, "random", SEED)
    n = order.count()
    rows = adj.join(order, "node").select(F.floor(F.col("pos") * segments / F.lit(n)).cast("int").alias("seg"), "pos", "node", "nbr", F.transform("cm", lambda c: c.cast("int")).alias("cm"))
    where = folder(spark)
    for late in (False, True):  # each segment's nodes of even tens first would break their order: split by position
        rows.where((F.col("pos") * segments % F.lit(n) >= n // 2) == late).coalesce(1).write.mode("append").parquet(where)
    provider = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(provider)
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(where)
        return drained(place_stream(stream), "append")
    finally:
        spark.conf.set(provider, before)


def late_drop(spark: SparkSession, d: str) -> DataFrame:
    """(day, n): days closed by the watermark; early events that come again when their days are long closed are dropped.

    A batch drops by the watermark that the batch before began with, so one more
    batch lies between the events and their repeats.
    """
    events = spark.read.parquet(f"{d}/events.parquet").select("event_id", "ts")
    where = folder(spark)
    last = events.agg(F.max("ts")).first()[0]
    for part in (events, events.where(F.col("ts") == F.lit(last).cast("timestamp_ntz")), events.where(F.col("ts") < F.lit("2024-01-20").cast("timestamp_ntz"))):
        part.coalesce(1).write.mode("append").parquet(where)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(where).withColumn("ts", F.col("ts").cast("timestamp"))
    days = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return drained(days, "append").select(F.date_format("window.start", _ISO).alias("day"), "n")


add("stream_late_drop", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS day, count(*) AS n FROM events GROUP BY 1 HAVING max(date_trunc('day', ts)) + INTERVAL '1 day' <= (SELECT max(ts) FROM events) - INTERVAL '1 hour'")(late_drop)
add("stream_node_partition")(node_placement)

"""Session helpers: shared checkpoints and bounded training samples."""

from __future__ import annotations

import gc
import os
import re
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the cluster's ``spark.checkpoint.dir``; only a local master (tests) may leave it unset."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    folder = context.getConf().get("spark.checkpoint.dir")
    if not folder and not re.fullmatch(r"local(\[.*\])?", context.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the cluster shares")
    context.setCheckpointDir(folder or os.path.join(tempfile.gettempdir(), "walkembed-checkpoints"))


def checkpointed(frame: DataFrame) -> DataFrame:
    """Cuts lineage with a reliable checkpoint in the shared folder."""
    ensure_checkpoint_dir(frame.sparkSession)
    return frame.checkpoint(eager=True)


def release_shuffles(spark: SparkSession) -> None:
    """Lets Spark delete shuffle files that nothing needs any more.

    Its cleaner waits for the driver to collect garbage, which an idle driver
    may not do for half an hour while later stages fill the disks.
    """
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def remove_folder(spark: SparkSession, folder: str) -> None:
    """Deletes a folder of whatever file system holds it."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


BROADCAST_ROWS = 1_000_000


def lookup(rows: DataFrame, table: DataFrame, key: str | list[str], size: int, how: str) -> DataFrame:
    """Joins a table of ``size`` narrow rows: sent to all where that is proven small, else joined by shuffle."""
    return rows.join(F.broadcast(table) if size <= BROADCAST_ROWS else table, key, how)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def crc_bucket(column: str, mod: int) -> F.Column:
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(mod))


def labelled_sample(documents: DataFrame, labels: DataFrame, label: str, max_rows: int, held_out: tuple[int, int] | None = None) -> tuple[list, list[int]]:
    """At most ``max_rows`` labelled texts per class, the same ones on every run.

    Rows are chosen by hash from the labels table alone; the chosen ids (a bound
    set by the parameter) are broadcast into one scan of ``documents``, so no
    text is shuffled.  ``held_out`` = (modulus, remainder) leaves out the rows
    whose crc32 of the id gives that remainder.  Returns (texts, labels) by id;
    null labels, ids and texts are left out.  Of repeated ids the smallest text and
    label serve, picked before anything reaches the driver.
    """
    chosen = labels.select("doc_id", F.col(label).cast("int").alias("label")).where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1))
    if held_out:
        chosen = chosen.where(crc_bucket("doc_id", held_out[0]) != held_out[1])
    per_class = [chosen.where(F.col("label") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows) for k in (0, 1)]
    picked = per_class[0].unionByName(per_class[1])
    rows = documents.select("doc_id", "text").where(F.col("text").isNotNull()).join(F.broadcast(picked), "doc_id")
    kept = sorted(rows.groupBy("doc_id").agg(F.min("text").alias("text"), F.min("label").alias("label")).collect(), key=lambda r: r["doc_id"])
    return [r["text"] for r in kept], [r["label"] for r in kept]

"""Reliable checkpoints in the folder that the cluster shares."""

from __future__ import annotations

import os
import re
import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

PACKED_ROWS = 1 << 19


def ensure_checkpoint_dir(frame: DataFrame) -> None:
    """Uses the session's ``spark.checkpoint.dir``; only a local master, as in tests, may leave it unset."""
    context = frame.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        folder = context.getConf().get("spark.checkpoint.dir")
        if not folder and not re.fullmatch(r"local(\[.*\])?", context.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the cluster shares")
        context.setCheckpointDir(folder or os.path.join(tempfile.gettempdir(), "walkembed-checkpoints"))


def durable(frame: DataFrame) -> DataFrame:
    """Cuts lineage: the frame's rows are written to the shared folder and read from there."""
    ensure_checkpoint_dir(frame)
    return frame.checkpoint(eager=True)


def packed_durable(frame: DataFrame) -> DataFrame:
    """``durable`` for many rows of a few numbers: batches are written compressed, a row each, and read again by every use."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def flush() -> pa.RecordBatch:
            sink = pa.BufferOutputStream()
            one = pa.Table.from_batches(held).combine_chunks()
            with pa.ipc.new_stream(sink, one.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_table(one)
            return pa.RecordBatch.from_arrays([pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["rows"])

        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= PACKED_ROWS:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows in batch.column("rows"):
                for some in pa.ipc.open_stream(rows.as_buffer()):
                    for at in range(0, some.num_rows, 1 << 16):
                        yield some.slice(at, 1 << 16)

    return durable(frame.mapInArrow(pack, "rows binary")).mapInArrow(unpack, frame.schema)

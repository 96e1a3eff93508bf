"""Counter-based random numbers: a draw is a hash of what it is for, so replays agree.

``portable`` is 32 bits of md5 over ``seed:round:walk:step:trial:salt`` and can be
written in any SQL dialect; ``native`` mixes 64-bit counters and is vectorised.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def draw_column(seed: int, *parts: Column | int | str) -> Column:
    """A BIGINT in [0, 2^32)."""
    text = F.concat_ws(":", F.lit(str(seed)), *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def scaled_column(draw: Column, total: Column) -> Column:
    """(draw * total) >> 32 for totals below 2^47, by the halves of ``total``: the whole product leaves 64 bits at 2^31."""
    low = F.shiftright(draw * F.pmod(total, F.lit(1 << 16)), 16)
    return F.shiftright(draw * F.shiftright(total, 16) + low, 16)


def draw_sql(seed: int, *parts: str) -> str:
    """The same in DuckDB."""
    text = " || ':' || ".join([f"'{seed}'", *[f"CAST({p} AS VARCHAR)" for p in parts]])
    return f"('0x' || substr(md5({text}), 1, 8))::BIGINT"


def draw_python(seed: int, *parts: int | str) -> int:
    return int(hashlib.md5(":".join(map(str, (seed, *parts))).encode()).hexdigest()[:8], 16)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def draw_many(kind: str, seed: int, round_: np.ndarray | int, walks: np.ndarray, steps: np.ndarray, trial: np.ndarray | int = 0, salt: int = 0) -> np.ndarray:
    """Draws in [0, 2^32) for arrays of walks and steps."""
    if kind == "portable":
        trials = np.broadcast_to(np.asarray(trial), walks.shape).tolist()
        rounds = np.broadcast_to(np.asarray(round_), walks.shape).tolist()
        return np.array([draw_python(seed, int(r), w, s, t, salt) for r, w, s, t in zip(rounds, walks.tolist(), steps.tolist(), trials)], dtype=np.int64)
    x = _mix(walks.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15) & (2**64 - 1)))
    x = _mix(x ^ (steps.astype(np.uint64) * np.uint64(0xD1B54A32D192ED03)) ^ (np.asarray(trial, dtype=np.int64).astype(np.uint64) * np.uint64(0x8CB92BA72F3D8DD7)))
    x = _mix(x + (np.asarray(round_, dtype=np.int64) * 1_000_003 + salt * 7_919).astype(np.uint64))
    return (x >> np.uint64(32)).astype(np.int64)

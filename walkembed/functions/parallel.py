"""Independent jobs of one query at the same time."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import SparkSession

AT_ONCE = 3  # a training keeps a task a shard busy, so alone it leaves the other cores idle


def together(run: Callable, cases: Iterable) -> list:
    """``run`` of every case, in their order; the first error is raised."""
    cases, wrapped = list(cases), inheritable_thread_target(SparkSession.active())(run)
    with ThreadPoolExecutor(max(1, min(AT_ONCE, len(cases)))) as pool:
        return [job.result() for job in [pool.submit(wrapped, case) for case in cases]]

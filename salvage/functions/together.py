"""Independent steps of one query at the same time: many small jobs, each too small for all cores, share them then."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import SparkSession

#: Steps of one call that run at a time.
THREADS = 6


def together(*steps: Callable) -> list:
    """The results of ``steps`` in their order; the first error is raised once the steps that run have ended."""
    kept = inheritable_thread_target(SparkSession.active())
    with ThreadPoolExecutor(THREADS) as pool:
        begun = [pool.submit(kept(step)) for step in steps]
        try:
            return [step.result() for step in begun]
        except BaseException:
            for step in begun:
                step.cancel()
            raise

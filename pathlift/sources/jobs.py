"""Independent jobs of a session side by side: while one is planned or ends in few tasks, others keep the cores busy."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Sequence
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import SparkSession
from pyspark.util import inheritable_thread_target


def at_once(spark: SparkSession, calls: Sequence[Callable], most: int = 3) -> list:
    """Results of calls that do not depend on each other, in order, each in its own thread, ``most`` at a time.

    What the caller's thread set for its jobs holds in theirs; the first error is raised when all have ended.
    """
    with ThreadPoolExecutor(max(1, min(most, len(calls)))) as pool:
        futures = [pool.submit(inheritable_thread_target(spark)(call)) for call in calls]
    return [f.result() for f in futures]


def in_tasks(spark: SparkSession, calls: Sequence[Callable]) -> list:
    """Results of calls that need no session, in order, each in a Spark task of its own.

    Calls are shipped by value; results are pickled, so they hold no objects of this package.
    """
    import pandas as pd

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"id": pdf["id"], "found": [pickle.dumps(calls[k]()) for k in pdf["id"]]})

    rows = spark.range(0, len(calls), 1, len(calls)).mapInPandas(run, "id long, found binary").collect() if calls else []  # one row a call
    found = {r["id"]: pickle.loads(bytes(r["found"])) for r in rows}
    return [found[k] for k in range(len(calls))]

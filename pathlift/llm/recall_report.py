"""Recall of the forest search against brute force, for budgets and tables.

    python -m pathlift.llm.recall_report /root/testdata/sf0.1 [open_scale ...]

prints, for each budget, the share of the rows' vectors that a query opens, the mean and
the least recall at 20 over the queries of op1, and the seconds that both ways took.
"""

from __future__ import annotations

import sys
import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from .ann_forest import nearest, opened_share, usable
from .frames import table


def brute_force(rows: DataFrame, queries: DataFrame, k: int = 20) -> dict[int, list[int]]:
    """The k nearest ids of every query by all inner products; for tables that fit one machine."""
    ids, points = (np.array(x) for x in zip(*[(r[0], r[1]) for r in rows.orderBy("vec_id").collect()], strict=True))
    out = {}
    for q, v in queries.select("vec_id", "v").collect():
        score = points @ np.array(v)
        score[ids == q] = -np.inf
        out[q] = ids[np.lexsort((ids, -score))[:k]].tolist()
    return out


def recall(found: DataFrame, exact: dict[int, list[int]]) -> tuple[float, float]:
    """(mean, least) share of the exact answers that were found."""
    mine: dict[int, set[int]] = {}
    for r in found.select("query_id", "vec_id").collect():
        mine.setdefault(r[0], set()).add(r[1])
    shares = [len(mine.get(q, set()) & set(want)) / max(1, len(want)) for q, want in exact.items()]
    return float(np.mean(shares)), float(np.min(shares))


def main(sf_dir: str, scales: list[float]) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").getOrCreate()
    df = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    queries = df.where("vec_id % 20 = 0")
    began = time.perf_counter()
    exact = brute_force(usable(df, "vec_id", "embedding"), usable(queries, "vec_id", "embedding"))
    plain, total = time.perf_counter() - began, df.count()
    for scale in scales:
        began = time.perf_counter()
        mean, least = recall(nearest(df, queries, open_scale=scale), exact)
        print(f"rows {total} scale {scale} opened {opened_share(total, scale, 0.886):.3f} recall {mean:.4f} least {least:.2f} seconds {time.perf_counter() - began:.1f} (brute force {plain:.1f})", flush=True)
    spark.stop()


if __name__ == "__main__":
    main(sys.argv[1], [float(x) for x in sys.argv[2:]] or [1.85])

"""Every query with SQL against DuckDB on the smallest tables; the others for rows.

The slow ones have tests of their own on one task (test_comparison.py, test_methods.py).
"""

import os

import duckdb
import pandas as pd
import pytest

import pathlift.registry as registry

registry.load_all()
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
SLOW = {"method_budgets", "utility_models", "lstm_iq", "saliency", "search_counters", "repository_update", "method_augmented", "lstm_predict", "end_to_end", "method_ranks", "search_study", "heap_study", "linearity_pairs", "fi_training_sizes", "noise_injection", "rl_bandit", "rl_dqn", "goal_feedback", "path_aggregation_score", "method_score"}


@pytest.fixture(scope="module")
def duck(data):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{os.path.join(data, t)}.parquet'")
    return c


def normal(df: pd.DataFrame) -> list[tuple]:
    cell = lambda v: None if v is None or v is pd.NaT or v is pd.NA or v != v else f"{float(v):.6g}" if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    plain = lambda v: v.item() if hasattr(v, "item") else v
    return sorted((tuple(cell(plain(v)) for v in row) for row in df[sorted(df.columns)].itertuples(index=False)), key=str)


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_against_sql(spark, data, duck, name):
    ours = registry.QUERIES[name](spark, data).toPandas()
    theirs = duck.execute(registry.ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert normal(ours) == normal(theirs)


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLES) - SLOW))
def test_gives_rows(spark, data, name):
    assert len(registry.QUERIES[name](spark, data).take(1)) == 1

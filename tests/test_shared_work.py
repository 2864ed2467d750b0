"""What several tasks need is made once, key columns share one shuffle, and models are fitted away from the driver."""

import os

import pytest
from pyspark.sql import functions as F

from pathlift.baselines import systems
from pathlift.operators import edge_stats
from pathlift.plans import tasks
from pathlift.sources.jobs import at_once, in_tasks
from pathlift.sources.repository import JoinEdge, Repository


def test_calls_in_tasks_answer_in_order(spark):
    found = in_tasks(spark, [lambda k=k: (k, os.getpid()) for k in range(3)])
    assert [k for k, _ in found] == [0, 1, 2] and os.getpid() not in {pid for _, pid in found} and in_tasks(spark, []) == []


def test_columns_of_several_tasks_are_described_once(spark, data, monkeypatch):
    asked = []
    monkeypatch.setattr(tasks, "describe", lambda repo, features, eps: asked.append(features) or ([], {}))
    common = tasks.Common(spark, data, tuple(tasks.TASKS[n] for n in ("spend", "daily")))
    at_once(spark, [lambda: common.described(0.7)] * 3)
    assert len(asked) == 1 and asked[0]["activity"] == ("n_events", "n_types") and "lineitem" in asked[0] and "calendar" in asked[0]
    assert common.repository(["activity"]).table("activity") is common.repository(["activity"]).table("activity")


def test_key_columns_share_a_shuffle(spark):
    left = spark.createDataFrame([(1, 7), (1, None), (2, 7), (None, 9)], "a long, b long")
    right = spark.createDataFrame([(1.0, "7"), (3.0, "7")], "a double, b string")
    repo = Repository(spark, "", {"l": left, "r": right})
    columns = [("l", "a", "double"), ("l", "b", "string"), ("r", "a", "double"), ("r", "b", "string")]
    hist = edge_stats.key_histogram(repo, columns)
    assert hist._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 1
    assert {(r["col"], r["key"]["t"], r["x"], r["c"]) for r in hist.collect()} == {
        ("l.a:double", "1", 1.0, 2), ("l.a:double", "2", 2.0, 1), ("l.b:string", "7", None, 2), ("l.b:string", "9", None, 1), ("r.a:double", "1", 1.0, 1), ("r.a:double", "3", 3.0, 1), ("r.b:string", "7", None, 2),
    }
    met = edge_stats.joined_histogram(repo, [JoinEdge("one", "l", "a", "r", "a"), JoinEdge("two", "l", "b", "r", "b")]).collect()
    assert {(r["edge_id"], r["key"]["t"], r["x"], r["l"], r["r"]) for r in met} == {("one", "1", 1.0, 2, 1), ("one", "2", 2.0, 1, 0), ("one", "3", 3.0, 0, 1), ("two", "7", None, 2, 2), ("two", "9", None, 1, 0)}


@pytest.mark.parametrize("functions", [("n_unique",), ("n_unique", "mode")])
def test_different_values_are_counted_alike_with_and_without_the_mode(spark, functions):
    base = spark.createDataFrame([(1,), (2,), (3,)], "k long")
    far = spark.createDataFrame([(1, 0.0, "a"), (1, -0.0, "a"), (1, float("nan"), None), (1, float("nan"), "b"), (2, None, None)], "k long, v double, w string")
    made = systems.path_aggregation(Repository(spark, "", {"b": base, "f": far}), base, [JoinEdge("e", "b", "k", "f", "k")], 1, functions)
    assert "Expand" not in made._jdf.queryExecution().optimizedPlan().toString() or "mode" not in functions
    rows = made.select("k", F.col("f__n_unique_v"), F.col("f__n_unique_w")).collect()
    assert {tuple(r) for r in rows} == {(1, 2, 2), (2, 0, 0), (3, None, None)}

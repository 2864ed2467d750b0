"""Independent jobs run side by side, and what several of them read is made once."""

import threading

import pytest

from pathlift.plans import tasks
from pathlift.sources.jobs import at_once


def test_calls_meet_and_answer_in_order(spark):
    both = threading.Barrier(2, timeout=60)
    assert at_once(spark, [lambda: (both.wait() >= 0, 1), lambda: (both.wait() >= 0, spark.range(2).count())]) == [(True, 1), (True, 2)]
    assert at_once(spark, []) == []


def test_an_error_comes_through_and_properties_are_handed_on(spark):
    spark.sparkContext.setLocalProperty("told", "yes")
    assert at_once(spark, [lambda: spark.sparkContext.getLocalProperty("told")]) == ["yes"]
    spark.sparkContext.setLocalProperty("told", None)
    with pytest.raises(ZeroDivisionError):
        at_once(spark, [lambda: 1 / 0, lambda: 2])


def test_costly_views_are_made_once(spark, data):
    work = tasks.Workload(spark, data, tasks.TASKS["spend"])
    assert {"customer_spend", "order_counts", "activity"} <= set(work.repo.extra) and "orders" not in work.repo.extra
    plan = work.repo.table("order_counts")._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" not in plan
    fresh = tasks.Repository(spark, data).table("order_counts")
    assert sorted(map(tuple, fresh.collect())) == sorted(map(tuple, work.repo.table("order_counts").collect()))


def test_tasks_are_prepared_side_by_side(spark, data, monkeypatch):
    """Fails if one task waits for another: each waits for a second one."""
    pairs = threading.Barrier(2, timeout=60)
    seen = []
    monkeypatch.setattr(tasks.Workload, "prepare", lambda self, method=True: seen.append((self.spec.name, method, self.spec.name in ("quality", "region") and pairs.wait() >= 0)))
    works = tasks.prepared(spark, data, False)
    assert [w.spec.name for w in works] == list(tasks.TASKS) and sorted(s[0] for s in seen) == sorted(tasks.TASKS) and not any(s[1] for s in seen)


def test_a_plan_is_scored_once(spark, data, monkeypatch):
    work = tasks.Workload(spark, data, tasks.TASKS["spend"])
    fits, final = [], type(work.sample).final
    monkeypatch.setattr(type(work.sample), "final", lambda self, plan: fits.append(tuple(plan)) or final(self, plan))
    first = work.score_plans({"": [], "one": work.names[:1]})
    again = work.score_plans({"a": work.names[:1], "b": work.names[:2], "c": []})
    assert fits == [(), tuple(work.names[:1]), tuple(work.names[:2])] and again["a"] == first["one"] and again["c"] == first[""]

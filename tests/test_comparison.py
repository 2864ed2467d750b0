"""The comparison on one task: every system chooses within its budget, and plans are scored on rows that taught nothing."""

import pytest
from pyspark.sql import functions as F

from pathlift.plans import comparison, tasks


@pytest.fixture(scope="module")
def work(spark, data):
    return tasks.Workload(spark, data, tasks.TASKS["region"])


def test_candidates_hold_every_pair_and_no_base_row_is_lost(work):
    base = work.repo.table("orders_region_label")
    assert work.table.count() == base.count() and len(work.pairs) >= 20 and set(work.names) <= set(work.table.columns) and work.aggregated
    share = work.table.agg(F.avg(F.col("held_out").cast("double"))).first()[0]
    assert 0.2 < share < 0.4 and len(work.sample.y) == work.table.where("NOT held_out").count()


def test_every_system_keeps_to_its_budget(work):
    chosen = {}
    for name, choose in comparison.systems_of(work).items():
        if name != comparison.THE_METHOD:
            for budget in (1, 5):
                plan = choose(work.task(), budget)
                assert len(plan) <= budget and len(set(plan)) == len(plan) and set(plan) <= {*work.names, *work.aggregated}, name
                chosen[f"{name}|{budget}"] = plan
    scores = work.score_plans({"": [], "planted": ["r2>r3:n_regionkey"], **chosen})
    assert scores["planted"] == pytest.approx(1.0) and 0.4 < scores[""] < 0.8 and all(0 <= s <= 1 for s in scores.values())


def test_the_method_finds_the_planted_column(work):
    plan = comparison.systems_of(work)[comparison.THE_METHOD](work.task(), 5)
    assert len(plan) <= 5 and any(c.endswith(("n_regionkey", "n_name", "r_name")) for c in plan)
    assert work.score_plans({"m": plan})["m"] > 0.9

"""Models that score plans and those that searches ask learn from every row: against brute force over the rows."""

from functools import partial

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathlift.operators import counted_models, joint_models
from pathlift.operators.engine import Base
from pathlift.plans import tasks
from pathlift.sources.jobs import in_tasks
from pathlift.sources.repository import JoinEdge, Repository


def test_neighbours_are_those_of_all_rows():
    rng = np.random.default_rng(4)
    codes, sizes = np.unique(rng.integers(0, 4, (300, 5)).astype(np.int16), axis=0), [4, 4, 4, 4, 4]
    n, y = rng.integers(0, 4, len(codes)), rng.normal(size=len(codes))
    asked = rng.random(len(codes)) < 0.5
    for k, found in zip((1, 7, 25, 10**6), counted_models.neighbour_values(codes, sizes, n, n * y, (1, 7, 25, 10**6), asked), strict=True):
        for row, mean in zip(codes[asked], found, strict=True):
            agree = (codes == row).sum(axis=1)
            level = max((a for a in range(6) if n[agree >= a].sum() >= k), default=0)
            assert mean == pytest.approx(np.average(y[agree >= level], weights=n[agree >= level]))


def test_many_cells_are_numbered_as_few_are():
    rng = np.random.default_rng(5)
    train, want, sizes = rng.integers(0, 9, (400, 6)), rng.integers(0, 9, (200, 6)), [9] * 6
    for most in (10, 100, 10**9):
        a, b, cells = counted_models._cells(train, want, sizes, (0, 2, 3, 5), most)
        same = (train[:, None, [0, 2, 3, 5]] == want[None][:, :, [0, 2, 3, 5]]).all(axis=2)
        assert ((a[:, None] == b[None]) == same).all() and max(a.max(), b.max()) < cells


def test_ridge_and_quantiles_of_counts_are_those_of_the_rows():
    rng = np.random.default_rng(6)
    codes, n = rng.integers(0, 4, (50, 2)).astype(np.int16), rng.integers(1, 5, 50)
    y = rng.normal(size=50)
    rows, labels = np.repeat(codes, n, axis=0), np.repeat(y, n)
    weights = counted_models.fit_ridge(codes, [4, 4], n, n * y).weights([0, 1])
    assert np.allclose(weights, joint_models.Ridge.of(rows, [4, 4], labels).weights([0, 1]), atol=1e-4)
    shares = np.linspace(0, 1, 13)
    assert np.allclose(counted_models.quantiles(y, n, shares), np.quantile(labels, shares))


def test_lines_hold_every_row_and_code(spark):
    wide = [f"c{k}" for k in range(17)]
    df = spark.range(0, 500, 1, 3).select("id", F.col("id").alias("y"), *[((F.col("id") + k) % 11).cast("double").alias(c) for k, c in enumerate(wide)], F.when(F.col("id") % 3 > 0, F.col("id") % 3 == 1).alias("flag"))
    coders = counted_models.fit_coders(df, [*wide, "flag"])
    assert all(c.size == 12 for n, c in coders.items() if n != "flag") and coders["flag"].values == {"true": 1, "false": 2}
    counted = counted_models.lines(df, F.lit(0), "y", [(), ("flag",), tuple(wide)], coders).toPandas()
    assert (counted.groupby("plan")["n"].sum() == 500).all() and set(counted["w0"][counted["plan"] == 1]) == {0, 1, 2}
    last = counted[counted["plan"] == 2].sort_values("y")
    codes = counted_models.unpacked(last[["w0", "w1"]].to_numpy(), 17)
    assert (codes == np.array([[(i + k) % 11 + 1 for k in range(17)] for i in range(500)])).all()


@pytest.fixture(scope="module")
def large(spark):
    """A task of 40,000 rows, whose rare rows tell what a column is worth only if all are read."""
    rows = spark.range(40_000).select("id", (F.pmod(F.xxhash64("id"), F.lit(5)) == 0).cast("int").alias("y"))
    far = spark.range(40_000).select("id", F.pmod(F.xxhash64("id"), F.lit(5)).alias("told"), F.pmod(F.hash("id"), F.lit(1000)).alias("noise"), F.concat(F.lit("v"), (F.col("id") % 40).cast("string")).alias("text"))
    spec = tasks.TaskSpec("large", Base("rows", "id", "y"), (JoinEdge("l1", "rows", "id", "far", "id"),), {"far": ("told", "noise", "text")}, 1)
    work = tasks.Workload(spark, "", spec)
    work.__dict__["repo"] = Repository(spark, "", {"rows": rows, "far": far})
    return work


def test_searches_and_scores_learn_from_every_row(large):
    """Fails if models, bins or thresholds come from a part of the rows."""
    kept, held = (large.table.where(c).count() for c in ("NOT held_out", "held_out"))
    assert kept > 25_000 and len(large.sample.y) == kept
    counted = counted_models.lines(large.table, F.col("held_out").cast("int") * 2, "y", [(), ("l1:told",)], large.coded(["l1:told"])).groupBy("plan", "part").agg(F.sum("n").alias("n"))
    assert {tuple(r) for r in counted.collect()} == {(p, part, n) for p in (0, 1) for part, n in ((0, kept), (2, held))}
    scores = large.score_plans({"": [], "told": ["l1:told"], "noise": ["l1:noise"]})
    assert scores["told"] == 1.0 and scores[""] == pytest.approx(0.8, abs=0.02) and scores["noise"] == pytest.approx(scores[""], abs=0.01)


def test_a_stored_table_answers_as_the_rows_do(spark, large):
    stored, names = large.sample, large.names
    codes, sizes, y = stored.part(names)
    checked = np.concatenate([c for _, _, c in stored.batches([])])
    assert 0.27 < checked.mean() < 0.33 and len(codes) == len(checked)
    whole = joint_models.Ridge.of(codes[~checked], sizes, y[~checked])
    assert np.allclose(stored.model.gram[: len(whole.gram), : len(whole.gram)], whole.gram) and stored.squares == pytest.approx((y[~checked] ** 2).sum())
    told = joint_models.Ridge.one_hot(codes[:, [1, 2]], [sizes[1], sizes[2]]) @ whole.weights([1, 2])
    assert stored.score(names[1:]) == pytest.approx(np.mean((told >= 0.5)[checked] == y[checked])) and stored.fits == 1
    for k, n in enumerate(names):
        assert stored.association(n) == pytest.approx(abs(np.corrcoef(codes[~checked, k], y[~checked])[0, 1]), abs=1e-6) and stored.mean_code(n) == pytest.approx(codes[~checked, k].mean())
    importance, noise = stored.importances(names, 2, 0)
    assert importance[names[0]] > 0.9 and max(noise) < 0.1
    assert in_tasks(spark, [partial(stored.score, names[1:]), partial(stored.importances, names, 2, 0)]) == [stored.score(names[1:]), (importance, noise)]


@pytest.mark.parametrize(("metric", "better"), [("accuracy", 0.9), ("f1", 0.8), ("mae", -1.0), ("mse", -1.5)])
def test_counted_models_learn_what_rows_teach(metric, better):
    rng = np.random.default_rng(0)
    codes = rng.integers(0, 6, (6000, 3))
    value = codes[:, 0] + 2.0 * (codes[:, 1] > 3)
    y = (value > 4).astype(float) if metric in joint_models.CLASSES else value + rng.normal(size=6000)
    words = (codes[:, 0] * 256 + codes[:, 1] * 16 + codes[:, 2])[:, None]
    n, right, hits, absolute, squared = counted_models.scored(metric, ("linear", "forest", "neighbours"), [6, 6, 6], words, rng.integers(0, 3, 6000), y, np.ones(6000, dtype=int))
    found = {"accuracy": right / n, "f1": hits / (hits + 0.5 * (n - right)), "mae": -absolute / n, "mse": -squared / n}[metric]
    assert found > better

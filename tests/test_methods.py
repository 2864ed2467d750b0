"""Parts of the methods against plain code: keys of any type, exact quality, statistics with features, joint models, updates."""

import itertools
import math

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from pathlift.baselines import systems
from pathlift.operators import augment, edge_stats, joint_models, quality, representation, search
from pathlift.operators.engine import Base, Engine, Settings, StepStatistics, ways_of
from pathlift.operators.paths import JoinGraph
from pathlift.plans.estimation import importance_study
from pathlift.sources.repository import JoinEdge, JoinPath, Repository, common_kind


def repository(spark, **tables):
    return Repository(spark, "/nowhere", extra=tables)


@pytest.fixture(scope="module")
def mixed(spark):
    """Text, date and fractional keys on a path base > mid > far, with nulls and repeats."""
    rng = np.random.default_rng(1)
    word = lambda n: f"k{n}"
    base = [(i, None if i % 11 == 0 else word(int(rng.integers(0, 30)))) for i in range(80)]
    mid = [(word(int(rng.integers(0, 25))), None if i % 7 == 0 else f"2024-01-{1 + int(rng.integers(0, 28)):02d}", float(rng.integers(0, 5)) / 2) for i in range(60)]
    far = [(f"2024-01-{d:02d}", None if d % 3 == 0 else d * 1.5, "ab"[d % 2]) for d in range(1, 25)]
    return repository(
        spark,
        base=spark.createDataFrame(base, "id long, name string"),
        mid=spark.createDataFrame(mid, "name string, day string, half double").withColumn("day", F.col("day").cast("date")),
        far=spark.createDataFrame(far, "day string, v double, kind string").withColumn("day", F.col("day").cast("date")),
        halves=spark.createDataFrame([(0, "x"), (1, "y"), (2, None)], "h int, w string"),
    )


NAME, DAY, HALF = JoinEdge("n", "base", "name", "mid", "name"), JoinEdge("d", "mid", "day", "far", "day"), JoinEdge("h", "mid", "half", "halves", "h")


def found(repo, path, feature):
    """Share of base rows that reach a value, by plain loops."""
    rows = [r.asDict() for r in repo.table("base").collect()]
    tables = {e.right: [r.asDict() for r in repo.table(e.right).collect()] for e in path.edges}

    def reaches(row, i):
        e = path.edges[i]
        for r in tables[e.right]:
            if row[e.left_col] is not None and row[e.left_col] == r[e.right_col]:
                if i + 1 == len(path.edges):
                    if feature is None or r[feature] is not None:
                        return True
                elif reaches(r, i + 1):
                    return True
        return False

    return sum(reaches(r, 0) for r in rows) / len(rows)


def test_quality_over_keys_of_any_type(mixed):
    pairs = [(JoinPath((NAME,)), None), (JoinPath((NAME,)), "day"), (JoinPath((NAME, DAY)), "v"), (JoinPath((NAME, DAY)), "kind"), (JoinPath((NAME, DAY)), None), (JoinPath((NAME, HALF)), "w")]
    got = {(r["path_id"], r["feature"]): r["iq"] for r in quality.exact_iq(mixed, mixed.table("base"), pairs).collect()}
    assert len(got) == len(pairs)
    for p, f in pairs:
        assert got[p.path_id, f] == pytest.approx(found(mixed, p, f)), (p.path_id, f)
    out = augment.augment(mixed, mixed.table("base"), JoinPath((NAME, DAY)), "v")
    assert out.count() == 80 and out.where("far__v IS NOT NULL").count() / 80 == pytest.approx(found(mixed, JoinPath((NAME, DAY)), "v"))
    both, _ = augment.integrate(mixed, mixed.table("base"), [(JoinPath((NAME, HALF)), "w"), (JoinPath((NAME, DAY)), "kind")])
    assert both.where("halves__w__1 IS NOT NULL").count() / 80 == pytest.approx(found(mixed, JoinPath((NAME, HALF)), "w"))


def test_levels_thin_the_far_keys(mixed):
    path = JoinPath((NAME, DAY))
    rows = quality.exact_iq(mixed, mixed.table("base"), [(path, "v"), (path, None)], range(1, 11)).collect()
    by = {(r["feature"], r["level"]): r["iq"] for r in rows}
    assert all(by[f, x] <= by[f, x + 1] for f in ("v", None) for x in range(1, 10)) and by["v", 10] == pytest.approx(found(mixed, path, "v"))
    keys = mixed.table("far").withColumn("least", quality.least_level(F.struct(F.unix_date("day").cast("long").alias("k"), F.lit("date").alias("t"))))
    thinned = Repository(mixed.spark, "/nowhere", extra=mixed.extra | {"far": keys.where("least <= 4").drop("least")})
    assert by["v", 4] == pytest.approx(found(thinned, path, "v"))
    full = edge_stats.leaving_statistics(mixed, [edge_stats.Leaving(DAY, "v"), edge_stats.Leaving(DAY, "kind")], (4, 10)).collect()
    alone = {r["column"]: r for r in edge_stats.leaving_statistics(thinned, [edge_stats.Leaving(DAY, "v"), edge_stats.Leaving(DAY, "kind")]).collect()}
    for r in full:
        if r["level"] == 4 and r["column"] == "kind":
            assert all(r[c] == pytest.approx(alone["kind"][c]) for c in ("variance", "entropy_shannon", "kl", "mutual_info", "transitivity", "containment", "n_joined"))


def test_statistics_of_a_leaving_column_by_plain_code(mixed):
    row = edge_stats.leaving_statistics(mixed, [edge_stats.Leaving(DAY, "v")]).first()
    mid, far = mixed.table("mid").toPandas(), mixed.table("far").toPandas()
    far = far[far["v"].notna()]
    joined = mid[mid["day"].notna()].merge(far, on="day")
    days = (pd.to_datetime(joined["day"]) - pd.Timestamp("1970-01-01")).dt.days
    assert row["n_joined"] == len(joined) and row["variance"] == pytest.approx(joined["v"].var(ddof=0)) and row["pearson"] == pytest.approx(np.corrcoef(days, joined["v"])[0, 1])
    assert row["transitivity"] == pytest.approx(len(set(joined["day"])) / len(far)) and row["containment"] == pytest.approx(len(set(joined["day"])) / mid["day"].nunique())
    p = joined["v"].value_counts(normalize=True).to_numpy()
    assert row["entropy_shannon"] == pytest.approx(-(p * np.log(p)).sum()) and row["mutual_info"] == pytest.approx(-(p * np.log(p)).sum())  # one value a day


def test_text_edges_have_statistics_and_are_discovered(mixed):
    stats = {r["edge_id"]: r for r in edge_stats.edge_statistics(mixed, [NAME, DAY, HALF]).collect()}
    assert stats["n"]["variance"] == 0 and stats["n"]["entropy_shannon"] > 0 and 0 < stats["d"]["transitivity"] <= 1 and stats["h"]["n_joined"] > 0
    columns = edge_stats.joinable_columns(mixed, ["base", "mid", "far"])
    pairs = {(r["lcol"], r["rcol"]) for r in edge_stats.discover_edges(mixed, columns).collect()}
    assert {("base.name", "mid.name"), ("mid.day", "far.day")} <= pairs and not any("base.id" in p for p in pairs)
    assert common_kind("long", "double") == "double" and common_kind("date", "long") == "string"


def test_last_step_reads_the_feature(mixed):
    graph, features = JoinGraph([NAME, DAY]), {"far": ("v", "kind")}
    paths = graph.paths("base", 2)
    steps = StepStatistics()
    steps.add(mixed, [e for p in paths for e in p.edges], ways_of(paths, features))
    long = next(p for p in paths if p.last == "far")
    a, b, none = (steps.sequence(long, f) for f in ("v", "kind", None))
    assert a.shape == (2, 7) and np.allclose(a[0], b[0]) and not np.allclose(a[1], b[1]) and a[1][0] == pytest.approx(steps.leaving["d", "v", 10]["variance"])
    assert none[1][0] == pytest.approx(steps.edges["d"]["variance"]) and a[0][3] == pytest.approx(steps.leaving["n", "day", 10]["pearson"])


@pytest.fixture(scope="module")
def small(spark):
    """A base whose label follows a column two joins away."""
    rng = np.random.default_rng(5)
    n = 300
    signal = rng.integers(0, 4, n)
    return repository(
        spark,
        base=spark.createDataFrame([(i, int(signal[i] >= 2)) for i in range(n)], "id long, y int"),
        bridge=spark.createDataFrame([(i, f"b{i}") for i in range(n) if i % 10 < 8], "id long, code string"),
        far=spark.createDataFrame([(f"b{i}", int(signal[i]), float(rng.normal())) for i in range(n)], "code string, signal int, noise double"),
        near=spark.createDataFrame([(i, float(rng.normal()), "uv"[i % 2]) for i in range(n)], "id long, noise double, side string"),
    )


EDGES = (JoinEdge("a", "base", "id", "bridge", "id"), JoinEdge("b", "bridge", "code", "far", "code"), JoinEdge("c", "base", "id", "near", "id"))


def test_engine_finds_the_distant_column_and_takes_new_tables_in(small):
    engine = Engine(small, Base("base", "id", "y"), JoinGraph(EDGES), {"far": ("signal", "noise"), "near": ("noise", "side")}, Settings(budget=2, training_pairs=10, clamp=True)).explore()
    plan, stats = engine.plan()
    assert plan[0][0].feature == "far.signal" and stats.expanded > 0 and set(engine.seconds) >= {"statistics", "training", "search"}
    assert engine.estimate_iq(plan[0][0].path, "signal") == pytest.approx(0.8, abs=0.25)
    assert engine.exploit().augmented.count() == 300
    late = small.table("base").select(F.col("id").alias("late_id"), (F.col("y") * 10 + F.col("id") % 3).alias("late_signal"))
    assert isinstance(engine.update({"late": late}), bool)
    assert "late" in engine.graph.tables() and "late.late_signal" in engine.importance and any(p.last == "late" for p in engine.paths)
    assert not engine.update({})


@pytest.mark.parametrize(("metric", "better"), [("accuracy", 0.5), ("f1", 0.3), ("mae", -2.0), ("mse", -6.0)])
def test_joint_models_learn(metric, better):
    rng = np.random.default_rng(0)
    rows = pd.DataFrame({"a": rng.normal(size=1500), "b": rng.choice(["u", "v", "w", None], 1500), "c": rng.normal(size=1500)})
    value = 3 * rows["a"] + 2 * (rows["b"] == "u")
    rows["y"] = (value > 0.5).astype(int) if metric in joint_models.CLASSES else value
    table = joint_models.Table.of(rows, "y", ["a", "b", "c"], metric)
    assert table.score(["a", "b"]) > table.score(["c"]) and table.score(["a", "b"]) > better and table.fits == 2
    importance, noise = table.importances(["a", "b", "c"], 3, 0)
    assert importance["a"] > max(noise) and len(noise) == 3
    coders, model = table.final(["a", "b"], ("linear", "forest", "neighbours", "network"))
    codes = np.stack([k.code(rows[n]) for k, n in zip(coders, ("a", "b"), strict=True)], axis=1)
    assert len(model.models) == 4 and joint_models.score(metric, model.predict(codes), rows["y"].to_numpy(dtype=float)) > better


def test_subsets_of_the_gram_matrix_are_fits_of_their_own():
    rng = np.random.default_rng(2)
    codes, y = rng.integers(0, 4, (200, 3)).astype(np.int16), rng.normal(size=200)
    whole = joint_models.Ridge.of(codes, [4, 4, 4], y)
    alone = joint_models.Ridge.of(codes[:, [0, 2]], [4, 4], y)
    assert np.allclose(whole.weights([0, 2]), alone.weights([0, 1]), atol=1e-4)


def toy_task():
    worth = {"n1": 0.1, "n2": 0.0, "m1": 0.05, "far1": 0.4}
    table = {"n1": "near", "n2": "near", "m1": "mid", "far1": "far"}
    return systems.Task(
        list(worth), table, {"n1": 1, "n2": 1, "m1": 1, "far1": 2}, lambda s: 0.5 + sum(worth[f] for f in s), {f: (v, 1.0) for f, v in worth.items()}, {"": ["near", "mid"], "mid": ["far"], "near": [], "far": []},
        lambda pool, k, seed: ({f: worth[f] for f in pool}, [0.02] * k), {"near": 0.9, "mid": 0.8}, worth, dict.fromkeys(worth, 1.0),
    )


def test_compared_systems_on_a_toy():
    assert systems.join_all(toy_task(), 2) == ["m1", "n1"] and systems.given_relevance(toy_task(), 1) == ["far1"] and systems.base_only(toy_task()) == []
    assert systems.noise_injection(toy_task(), 5) == ["n1", "m1"] or set(systems.noise_injection(toy_task(), 5)) == {"n1", "m1"}
    assert "far1" in systems.bandit_explorer(toy_task(), 40, 4)
    task = toy_task()
    task.reach = {"": ["near"], "near": [], "mid": ["far"]}
    assert set(systems.bandit_explorer(task, 40, 4)) <= {"n1", "n2"}  # distant tables open along joins alone
    assert set(systems.network_explorer(toy_task(), 12, 3)) <= {"n1", "n2", "m1", "far1"} and systems.goal_feedback(toy_task(), 20, 5) and "far1" not in systems.goal_feedback(toy_task(), 20, 5)
    assert len(set(systems.profile_clusters(np.array([[0.0], [0.1], [9.0], [9.1]]), 2).tolist())) == 2


def test_full_disjunction_keeps_all_combinations(spark):
    a = spark.createDataFrame([(1, "x"), (1, "y"), (2, None)], "k long, p string")
    b = spark.createDataFrame([(1, "s"), (1, "t"), (3, "u")], "k long, q string")
    rows = {tuple(r) for r in systems.full_disjunction([a, b], "k").collect()}
    assert rows == {(1, "x", "s"), (1, "x", "t"), (1, "y", "s"), (1, "y", "t"), (2, None, None), (3, None, "u")}
    c = spark.createDataFrame([(1, "x"), (1, None)], "k long, p string")
    assert {tuple(r) for r in systems.full_disjunction([c, b.where("k = 1")], "k").collect()} == {(1, "x", "s"), (1, "x", "t")}


def test_path_aggregation_functions_and_budget(spark):
    repo = repository(spark, base=spark.createDataFrame([(1,), (2,), (3,)], "k long"), far=spark.createDataFrame([(1, 2.0, "a", "2024-03-01"), (1, 4.0, "a", "2024-05-01"), (2, 1.0, "b", "2023-01-02")], "k long, v double, c string, t string").withColumn("t", F.col("t").cast("date")))
    edge = JoinEdge("e", "base", "k", "far", "k")
    out = {r["k"]: r for r in systems.path_aggregation(repo, repo.table("base"), [edge], 1, ("count", "avg", "n_unique", "mode", "month", "weekday", "year")).collect()}
    assert (out[1]["far__count"], out[1]["far__avg_v"], out[1]["far__n_unique_v"], out[1]["far__mode_c"], out[1]["far__month_t"]) == (2, 3.0, 2, "a", 4.0) and out[3]["far__count"] is None
    assert systems.path_aggregation(repo, repo.table("base"), [edge], 1, budget=2).columns == ["k", "far__count", "far__sum_v"]


def test_clusters_by_rounds_are_those_of_visits(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(120, 3))
    vectors = spark.createDataFrame([(f"f{i}", v.tolist()) for i, v in enumerate(x)], "feature_id string, repr array<double>")
    near = representation.neighbours(vectors, 0.8, block_rows=20).collect()
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    assert len(near) == int((unit @ unit.T >= 0.8).sum())
    order = {r["feature_id"]: (r["v"]["h"], r["v"]["f"]) for r in vectors.select("feature_id", representation._visit("feature_id", 4).alias("v")).collect()}
    around = {}
    for r in near:
        around.setdefault(r["a"], set()).add(r["b"])
    claimed = {}
    for f in sorted(order, key=order.get):
        if f not in claimed and len(around[f]) >= 4:
            for g in around[f]:
                claimed.setdefault(g, f)
            claimed[f] = f
    got = {r["feature_id"]: r["centroid_id"] for r in representation.threshold_clusters(spark.createDataFrame(near), vectors.select("feature_id"), 4, 4).collect()}
    assert got == {f: claimed.get(f, f) for f in order}


def test_enumeration_is_the_best_of_all_plans():
    path = lambda n: JoinPath((JoinEdge(n, "base", "k", "t", "k"),))
    rng = np.random.default_rng(7)
    made = [search.Candidate(f"f{i}", path(p), float(rng.normal()), float(rng.random())) for i in range(5) for p in "xy"]
    plan, scored = search.enumerate_plans(made, 3)
    assert scored == sum(math.comb(5, n) * 2**n for n in (1, 2, 3))
    best = max(sum(c.gain for c in chosen) for n in range(4) for chosen in itertools.combinations(made, n) if len({c.feature for c in chosen}) == n)
    assert sum(c.gain for c in plan) == pytest.approx(best) == pytest.approx(sum(c.gain for c in search.search_exhaustive(made, 3)))


def test_more_known_importances_lower_the_error():
    rng = np.random.default_rng(1)
    centres = rng.normal(size=(6, 8))
    rows = []
    for i in range(300):
        v = centres[i % 6] + rng.normal(size=8) * 0.25
        rows.append((f"c{i:03d}", float(i % 6) + 0.05 * float(rng.normal()), v))
    out = {(how, n): e for how, n, normalised, e in importance_study(rows, (6, 50, 200), 0.7) if normalised}
    assert all(out[how, 50] < out[how, 6] for how in ("greedy", "random", "cover"))  # columns left over may be outliers: the error need not fall for ever


def test_representations_tell_types_apart(spark):
    repo = repository(spark, t=spark.createDataFrame([(i, f"name {i}", i % 2 * 1.0, None) for i in range(40)], "id long, name string, flag double, empty string"))
    rows = {r["feature_id"]: r for r in representation.serialized_columns(repo, {"t": ("id", "name", "flag", "empty")}, sample=8, descriptions={"t.flag": "yes or no"}).collect()}
    assert "identifier" in rows["t.id"]["meta"] and "category" in rows["t.flag"]["meta"] and "yes or no" in rows["t.flag"]["meta"] and len(rows["t.name"]["values"]) == 8 and rows["t.empty"]["values"] == []
    assert rows["t.empty"]["stats"][0] == 1.0 and len(rows["t.id"]["stats"]) == len(representation.STATISTICS)
    vectors = {r["feature_id"]: np.array(r["repr"]) for r in representation.represent(spark.createDataFrame(list(rows.values()))).collect()}
    assert all(np.linalg.norm(v) == pytest.approx(1, abs=1e-5) for v in vectors.values())

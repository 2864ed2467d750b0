"""Worked examples and identities of the methods."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathlift.functions import measures
from pathlift.operators import augment, edge_stats, quality, search, utility
from pathlift.operators.joins import as_of, interval_join, salted_join
from pathlift.operators.paths import JoinGraph, enumerate_paths, enumerate_paths_sql
from pathlift.operators.representation import estimate_importance, sample_features, threshold_cluster
from pathlift.operators.selection import Coverage, Pair, select_pairs
from pathlift.operators.sequence_model import SequenceModel
from pathlift.sources.repository import JoinEdge, JoinPath, Repository


def repository(spark, **tables):
    return Repository(spark, "/nowhere", extra=tables)


def numbers(spark, name, values):
    return spark.createDataFrame([(int(v),) for v in values], f"{name} long")


def test_transitivity_of_overlapping_ranges(spark):
    repo = repository(spark, a=numbers(spark, "x", range(1, 101)), b=numbers(spark, "y", range(81, 121)))
    row = edge_stats.edge_statistics(repo, [JoinEdge("e", "a", "x", "b", "y")]).first()
    assert row["transitivity"] == 0.5 and row["containment"] == 0.2 and row["n_joined"] == 20


def test_product_along_a_path(spark):
    stats = spark.createDataFrame([("p", 0.2), ("q", 0.5)], "edge_id string, transitivity double")
    paths = spark.createDataFrame([("p>q",)], "path_id string")
    assert quality.product_of_transitivity(paths, stats).first()["iq_product"] == pytest.approx(0.1)


@pytest.fixture
def routes(spark):
    return repository(
        spark,
        product=spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "pid long, name string"),
        rating=spark.createDataFrame([(1, 5.0), (2, 3.0), (3, 4.0), (4, 1.0)], "rid long, score double"),
        one=spark.createDataFrame([(1, 1), (2, 2)], "pid long, rid long"),
        two=spark.createDataFrame([(1, 1)], "pid long, rid long"),
    )


def route(name):
    return JoinPath((JoinEdge(name, "product", "pid", name, "pid"), JoinEdge("r", name, "rid", "rating", "rid")))


def test_two_routes_to_one_table(routes):
    base = routes.table("product")
    found = {r["path_id"]: r["iq"] for r in quality.exact_iq(routes, base, [(route("one"), "score"), (route("two"), "score")]).collect()}
    assert found == {"one>r": pytest.approx(2 / 3), "two>r": pytest.approx(1 / 3)}
    out = augment.augment(routes, base, route("one"), "score")
    hit, miss = augment.split_augmented(out, "rating__score")
    assert {r["pid"] for r in miss.collect()} == {3} and hit.count() == 2 and out.count() == 3


def test_augmenting_takes_the_bridge_that_leads_on(spark):
    repo = repository(spark, base=numbers(spark, "k", [1, 2]), bridge=spark.createDataFrame([(1, 10), (1, 11), (2, 12)], "k long, m long"), far=spark.createDataFrame([(11, "x")], "m long, v string"))
    path = JoinPath((JoinEdge("a", "base", "k", "bridge", "k"), JoinEdge("b", "bridge", "m", "far", "m")))
    assert {(r["k"], r["far__v"]) for r in augment.augment(repo, repo.table("base"), path, "v").collect()} == {(1, "x"), (2, None)}
    both, joins = augment.integrate(repo, repo.table("base"), [(path, "v"), (JoinPath(path.edges[:1]), "m")])
    assert joins == 2 and {(r["k"], r["far__v__1"], r["bridge__m__2"]) for r in both.collect()} == {(1, "x", 10), (2, None, 12)}


def test_split_wide_loses_nothing(spark):
    df = spark.createDataFrame([(1, "a", "x"), (2, "a", "y"), (3, "b", "x")], "k long, p string, q string")
    parts = augment.split_wide(df, "k", {"p": ("p",), "q": ("q",)})
    assert parts["p"].count() == 2 and {tuple(r) for r in parts["core"].join(parts["p"], "p_id").join(parts["q"], "q_id").select("k", "p", "q").collect()} == {(1, "a", "x"), (2, "a", "y"), (3, "b", "x")}


def test_entropy_forms(spark):
    repo = repository(spark, a=numbers(spark, "x", [1, 1, 2, 3]), b=numbers(spark, "y", [1, 2, 3]))
    row = edge_stats.edge_statistics(repo, [JoinEdge("e", "a", "x", "b", "y")]).first()
    assert row["entropy_printed"] == pytest.approx(0.4904146265) and row["entropy_shannon"] == pytest.approx(1.0397207708)


def test_statistics_of_an_edge_without_match(spark):
    repo = repository(spark, a=numbers(spark, "x", [1, 2]), b=numbers(spark, "y", [3]), c=numbers(spark, "z", []))
    rows = {r["edge_id"]: r for r in edge_stats.edge_statistics(repo, [JoinEdge("ab", "a", "x", "b", "y"), JoinEdge("ac", "a", "x", "c", "z")]).collect()}
    assert rows["ab"]["transitivity"] == 0 and rows["ab"]["n_joined"] == 0 and rows["ab"]["variance"] == 0
    assert rows["ac"]["transitivity"] == 0


def motif():
    pairs = [("product", "category"), ("product", "rating"), ("product", "review"), ("product", "order"), ("category", "collection"), ("order", "dispute"), ("customer", "order"), ("customer", "rating"), ("customer", "review")]
    return JoinGraph([JoinEdge(f"{a}-{b}", a, "k", b, "k") for a, b in pairs])


def test_three_paths_reach_the_customer(spark):
    graph = motif()
    assert sum(p.last == "customer" for p in graph.paths("product", 2)) == 3
    rows = lambda df: {tuple(r) for r in df.collect()}
    assert rows(enumerate_paths(graph, spark, "product", 3)) == rows(enumerate_paths_sql(graph, spark, "product", 3))
    assert all(p.is_simple() for p in graph.paths("product", 4))
    assert graph.khop("product", 2)["customer"] == 2


def test_importance_estimates(spark):
    clusters = spark.createDataFrame([("a", 0), ("b", 0), ("c", 0), ("x", 0), ("lone", 1)], "feature_id string, cluster_id int")
    angle = {"a": 0.9, "b": 0.8, "c": 0.6}
    rows = [("x", [1.0, 0.0]), ("lone", [1.0, 0.0]), *[(k, [v, math.sqrt(1 - v * v)]) for k, v in angle.items()]]
    vectors = spark.createDataFrame(rows, "feature_id string, repr array<double>")
    known = spark.createDataFrame([("a", 0.10), ("b", 0.20), ("c", -0.05)], "feature_id string, fi double")
    get = lambda **k: {r["feature_id"]: r["fi_est"] for r in estimate_importance(clusters, vectors, known, **k).collect()}
    assert get()["x"] == pytest.approx(0.0733333, abs=1e-6) and get()["lone"] == 0 and get()["a"] == 0.10
    assert get(normalise=True)["x"] == pytest.approx(0.0956522, abs=1e-6)
    assert get(empty="global_mean")["lone"] == pytest.approx(0.25 / 3)


def path(n="p"):
    return JoinPath((JoinEdge(n, "base", "k", "t", "k"),))


def test_decay_of_like_features():
    vectors = {"new": np.array([1.0, 0.0]), "a": np.array([0.9, math.sqrt(1 - 0.81)]), "b": np.array([0.8, 0.6])}
    made = [search.Candidate("b", path(), 0.20, 1.0), search.Candidate("a", path(), 0.10, 1.0), search.Candidate("new", path(), 0.15, 1.0)]
    clusters = dict.fromkeys(vectors, 0)
    for decay, want in (("printed", None), ("scaled", None)):
        out = search.refine(made, 3, clusters, vectors, decay=decay)
        assert len(out) == 3 and out[0][0].feature == "b" and want is None
    near = search.refine([search.Candidate("a", path("x"), 0.3, 1.0), search.Candidate("a", path("y"), 0.3, 0.5)], 2, {"a": 0}, vectors)
    assert near[1][1] == pytest.approx(0.0, abs=1e-9)  # the same feature again adds nothing
    assert len(search.refine(made, 5, clusters, vectors)) == 3


def test_selection_order_of_the_small_example():
    pairs = [Pair("f1", ("a",), 0), Pair("f2", ("b",), 0), Pair("f3", ("a", "c"), 1), Pair("f4", ("b", "d"), 1), Pair("f5", ("b", "d"), 2)]
    assert [p.feature for p in select_pairs(pairs, 5, seed=None)] == ["f1", "f2", "f3", "f5", "f4"]
    state = Coverage(pairs)
    for p in pairs[:3]:
        state.take(p)
    assert state.weight(pairs[3]) == pytest.approx(0.125) and state.weight(pairs[4]) == 0
    state.take(pairs[4])
    assert state.weight(pairs[3]) == pytest.approx(0.5)
    assert len(select_pairs(pairs, 99)) == 5 and len(set(select_pairs(pairs, 4, warmup=2))) == 4


def test_metrics(spark):
    rows = [(1, 1)] * 3 + [(1, 0)] + [(0, 1)] * 2 + [(0, 0)] * 4
    df = spark.createDataFrame(rows, "p int, y int")
    r = df.agg(measures.accuracy("p", "y"), measures.f1("p", "y")).first()
    assert r[0] == pytest.approx(0.7) and r[1] == pytest.approx(2 / 3)
    e = spark.createDataFrame([(1.0,), (-2.0,), (3.0,)], "e double")
    assert e.agg(measures.mae("e", F.lit(0.0))).first()[0] == 2 and e.agg(measures.mse("e", F.lit(0.0))).first()[0] == pytest.approx(14 / 3)
    assert measures.signed_score("mae", 2.0) == -2.0 and utility.utility_gain("mse", 1.0, 3.0) == 2.0


def test_slice_error_and_combinations():
    b = measures.slice_error_bounds(100, 80, 30)
    assert b["variance"] == pytest.approx(0.000339394, abs=1e-9) and b["variance_bound"] == 0.01 and b["mean_abs_bound"] == 0.2
    assert measures.combination_count(5, 2, 3) == 50 and measures.combination_count(1065, 1, 3) == 201_325_825


@pytest.mark.parametrize("n", [100, 1000])
def test_slice_error_simulated(n):
    rng = np.random.default_rng(0)
    m, k = int(0.7 * n), int(0.3 * n)
    hits = np.arange(n) < m
    errors = np.array([(hits[rng.permutation(n)[:k]].sum() - k * m / n) / n for _ in range(2000)])
    b = measures.slice_error_bounds(n, m, k)
    assert errors.var() == pytest.approx(b["variance"], rel=0.15) and np.abs(errors).mean() <= b["mean_abs_bound"]


def test_moment_bounds():
    rng = np.random.default_rng(1)
    for scale in (0.01, 0.1, 0.3):
        x = np.clip(rng.normal(0, scale, 10000), -0.999, 0.999)
        b = measures.abs_moment_bounds(x.var())
        assert np.abs(x).mean() <= b["mean_abs"] and np.abs(x).var() <= b["var_abs"] + 1e-12


def layered(layers, width):
    names = [[f"t{i}_{j}" for j in range(width)] for i in range(layers)]
    edges = [JoinEdge("s" + b, "base", "k", b, "k") for b in names[0]]
    edges += [JoinEdge(f"{a}{b}", a, "k", b, "k") for x, y in zip(names, names[1:], strict=False) for a in x for b in y]
    return JoinGraph(edges), {t: ("f",) for layer in names for t in layer}


def test_search_equals_exhaustive_when_nothing_is_pruned():
    graph, features = layered(3, 3)
    rng = np.random.default_rng(2)
    fi = {f"{t}.f": float(rng.random()) for t in features}
    iq = lambda p: 0.9 ** len(p.edges) * (0.5 + 0.5 * (hash(p.path_id) % 97) / 97)
    everything, _ = search.search(graph, "base", features, iq, fi, heap_size=10**6, max_hops=3)
    best = search.search_exhaustive(everything, 3)
    assert [c.order() for c in search.search_exhaustive(everything, 3, enumerate_up_to=10**6)] == [c.order() for c in best] or sum(c.gain for c in best) == pytest.approx(sum(c.gain for c in search.search_exhaustive(everything, 3, enumerate_up_to=10**6)))
    pruned, stats = search.search(graph, "base", features, iq, fi, heap_size=20, max_hops=3)
    plain, other = search.search(graph, "base", features, iq, fi, heap_size=20, max_hops=3, fi_bound=False)
    assert [c.order() for c in pruned] == [c.order() for c in plain] == [c.order() for c in everything[:20]]
    assert stats.skipped_by_bound > 0 and other.skipped_by_bound == 0
    greedy = search.search_greedy(everything, 3)
    assert sum(c.gain for c in best) >= sum(c.gain for c in greedy) and len({c.feature for c in greedy}) == 3


def test_stress_graph_counts():
    graph, features = layered(4, 8)
    _, stats = search.search(graph, "base", features, lambda p: 0.5 ** len(p.edges), dict.fromkeys([f"{t}.f" for t in features], 0.5), heap_size=10, t_iq=0.3, max_hops=4)
    assert stats.expanded < 100 and stats.cut_by_quality > 0
    assert len(graph.paths("base", 4)) > 1000


def test_clusters_cover_every_feature_once():
    pairs = [("a", "a", 1.0), ("b", "b", 1.0), ("c", "c", 1.0), ("a", "b", 0.8), ("b", "a", 0.8)]
    out = threshold_cluster(pairs, ["a", "b", "c"])
    assert sorted(f for f, *_ in out) == ["a", "b", "c"] and len({c for f, c, *_ in out if f in "ab"}) == 1


@pytest.mark.parametrize("method", ["random", "centroid", "cover"])
def test_feature_samples(spark, method):
    clusters = spark.createDataFrame([(f"f{i}", i % 2) for i in range(10)], "feature_id string, cluster_id int")
    vectors = spark.createDataFrame([(f"f{i}", [math.cos(i), math.sin(i)]) for i in range(10)], "feature_id string, repr array<double>")
    rows = sample_features(clusters, vectors, 3, method).collect()
    assert len(rows) == 6 and len({r["feature_id"] for r in rows}) == 6


def test_network_gradient_by_finite_differences():
    rng = np.random.default_rng(0)
    seqs = [rng.normal(size=(n, 3)) for n in (1, 2, 3)]
    model = SequenceModel(hidden=4)
    model.start(3)
    x, mask = model._prepared(seqs)
    y = np.array([0.1, 0.5, 0.9])
    out, tape = model._forward(x, mask)
    grads, d_x = model._backward(out, 2 * (out - y), tape)
    loss = lambda: float(((model._forward(x, mask)[0] - y) ** 2).sum())
    for name, i in (("gates", (1, 2)), ("gates_bias", (5,)), ("out", (2, 0)), ("out_bias", (0,))):
        w = model.weights[name]
        old = w[i]
        w[i] = old + 1e-5
        up = loss()
        w[i] = old - 1e-5
        down = loss()
        w[i] = old
        assert grads[name][i] == pytest.approx((up - down) / 2e-5, abs=1e-6)
    x[2, 1, 0] += 1e-5
    up = loss()
    x[2, 1, 0] -= 2e-5
    assert d_x[2, 1, 0] == pytest.approx((up - loss()) / 2e-5, abs=1e-6)


def test_network_learns():
    rng = np.random.default_rng(3)
    seqs = [rng.random((int(n), 2)) for n in rng.integers(1, 4, 60)]
    y = [float(np.prod(s[:, 0])) for s in seqs]
    model = SequenceModel(epochs=300).fit(seqs[:40], y[:40])
    assert model.loss(seqs[40:], y[40:]) < np.var(y) and model.saliency(seqs)[0] > model.saliency(seqs)[1]


def test_quality_never_rises_along_a_path(spark, data):
    from pathlift.plans.edges import iq_monotonicity

    assert all(r["holds"] for r in iq_monotonicity(spark, data).collect())


def test_composed_joins(spark):
    left = spark.createDataFrame([(1, "2024-01-01 06:00:00"), (1, "2024-01-01 12:00:00"), (2, "2024-01-01 12:00:00")], "k long, t string").withColumn("t", F.col("t").cast("timestamp_ntz"))
    right = spark.createDataFrame([(1, "2024-01-01 05:00:00", 10), (1, "2024-01-01 12:00:00", 11)], "k long, t string, v int").withColumn("t", F.col("t").cast("timestamp_ntz"))
    assert [(r["k"], r["v"]) for r in as_of(left, right, "k", "t", "v").orderBy("k", "t").collect()] == [(1, 10), (1, 10), (2, None)]
    near = interval_join(left, right.withColumnRenamed("t", "at"), "k", "t", "at", 3600)
    assert near.count() == 1
    a, b = spark.range(100).select((F.col("id") % 3).alias("x"), "id"), spark.range(3).select(F.col("id").alias("y"))
    assert salted_join(a, b, "x", "y", 4).count() == 100

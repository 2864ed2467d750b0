"""The experiments: temporal features, importance strategies, sampling, search variants, ranks."""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.measures import abs_moment_bounds
from ..operators import representation, utility
from ..operators import search as searching
from ..operators.augment import augment
from ..registry import query
from ..sources.files import written
from ..sources.repository import Repository, path_of
from . import sqltext
from .augmentation import region_base
from .searching import FEATURES, GRAPH, fixed_importance, products, threshold_clusters
from .tasks import prepared

_DAYS = f"(SELECT user_id, day, v, lag(v) OVER (PARTITION BY user_id ORDER BY day) AS before FROM {sqltext.view_sql('user_day')})"


@query("previous_day_feature", f"SELECT round(avg(CASE WHEN before IS NULL THEN 0.0 ELSE 1.0 END), 6) AS iq, round(corr(v, before), 6) AS r, round(var_pop(v), 4) AS base_mse, round(sum((v - p) ** 2) / count(*), 4) AS mse FROM (SELECT *, CASE WHEN before IS NULL THEN (SELECT avg(v) FROM {_DAYS} WHERE before IS NULL) ELSE (SELECT regr_intercept(v, before) FROM {_DAYS}) + (SELECT regr_slope(v, before) FROM {_DAYS}) * before END AS p FROM {_DAYS})")
def previous_day_feature(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A feature of high quality and next to no importance: yesterday's mean for today's (temporal self-join)."""
    days = Repository(spark, sf_dir).table("user_day").withColumn("before", F.lag("v").over(Window.partitionBy("user_id").orderBy("day")))
    line = days.agg(F.regr_intercept("v", "before").alias("a"), F.regr_slope("v", "before").alias("b"), F.avg(F.when(F.col("before").isNull(), F.col("v"))).alias("m"))
    p = F.when(F.col("before").isNull(), F.col("m")).otherwise(F.col("a") + F.col("b") * F.col("before"))
    return days.crossJoin(F.broadcast(line)).agg(  # one row
        F.round(F.avg(F.col("before").isNotNull().cast("double")), 6).alias("iq"), F.round(F.corr("v", "before"), 6).alias("r"), F.round(F.var_pop("v"), 4).alias("base_mse"), F.round(F.sum(F.pow(F.col("v") - p, F.lit(2))) / F.count(F.lit(1)), 4).alias("mse")
    )


_ROUTES = (("e1>e2", ("e1", "e2")), ("e5r>e7>e4", ("e5r", "e7", "e4")))


def _strategies_sql() -> str:
    """Gains of the binned region key by plain grouping, over all rows and over matched ones."""
    parts = []
    for name, route in _ROUTES:
        rows = f"(SELECT y, f.v AS v FROM {sqltext.frm('orders_region_label')} LEFT JOIN {sqltext.fold(path_of(*route).edges, 'n_regionkey', 'first')} f ON {path_of(*route).edges[0].left_col} = f.key)"
        score = lambda where: f"(SELECT sum(top) / sum(n)::DOUBLE FROM (SELECT max(c) AS top, sum(c) AS n FROM (SELECT v, y, count(*) AS c FROM {rows} {where} GROUP BY ALL) GROUP BY v))"  # noqa: B023, E731
        plain = lambda where: f"(SELECT max(c) / sum(c)::DOUBLE FROM (SELECT y, count(*) AS c FROM {rows} {where} GROUP BY y))"  # noqa: B023, E731
        hit = "WHERE v IS NOT NULL"
        parts.append(f"SELECT '{name}' AS path_id, (SELECT avg(CASE WHEN v IS NULL THEN 0.0 ELSE 1.0 END) FROM {rows}) AS iq, {score(hit)} - {plain(hit)} AS matched, {score('')} - {plain('')} AS gain")
    found = "\nUNION ALL ".join(parts)
    return f"""WITH r AS ({found})
SELECT path_id, 'matched slice' AS strategy, round(iq, 6) AS iq, round(matched, 6) AS fi FROM r UNION ALL SELECT path_id, 'rescaled', round(iq, 6), round(gain / iq, 6) FROM r
UNION ALL SELECT path_id, 'gain as it is', round(iq, 6), round(gain, 6) FROM r UNION ALL SELECT 'any', 'best path', 1.0, round(max(gain), 6) FROM r"""


@query("exact_fi_strategies", _strategies_sql())
def exact_fi_strategies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Importance of the region key through two routes: on the matched slice, rescaled by quality, best path."""
    repo = Repository(spark, sf_dir)
    base = repo.table("orders_region_label")
    rows = []
    for name, route in _ROUTES:
        table = augment(repo, base, path_of(*route), "n_regionkey", name="f").withColumn("one", F.lit("1"))
        score = lambda df: {r["feature"]: r["score"] for r in utility.majority_accuracy(df, "y", ["f", "one"]).collect()}
        whole, hit = score(table), score(table.where("f IS NOT NULL"))
        iq = table.agg(F.avg(F.col("f").isNotNull().cast("double"))).first()[0]
        gain = whole["f"] - whole["one"]
        rows += [(name, "matched slice", iq, hit["f"] - hit["one"]), (name, "rescaled", iq, gain / iq), (name, "gain as it is", iq, gain)]
    best = max(r[3] for r in rows if r[1] == "gain as it is")
    return spark.createDataFrame([(a, b, round(iq, 6), round(fi, 6)) for a, b, iq, fi in [*rows, ("any", "best path", 1.0, best)]], "path_id string, strategy string, iq double, fi double")


@query("grouped_models")
def grouped_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One small model for each feature in one job: shrunken bin means of seven tenths of all rows, scored on the others."""
    table = region_base(Repository(spark, sf_dir))
    features = ("segment", "region", "supplier_region", "returnflag")
    pairs = F.array(*[F.struct(F.lit(f).alias("feature"), F.coalesce(F.col(f).cast("string"), F.lit("?")).alias("bin")) for f in features])
    long = table.select(F.col("y").cast("int").alias("y"), (F.pmod(F.xxhash64("o_orderkey"), F.lit(10)) < 7).alias("train"), F.explode(pairs).alias("p")).select("p.feature", "p.bin", "y", "train")
    of = lambda train, value: F.coalesce(F.sum(F.when(F.col("train") == train, value)), F.lit(0))
    bins = long.groupBy("feature", "bin").agg(
        of(True, F.col("y")).alias("s"), of(True, F.col("y").isNotNull().cast("int")).alias("n"), of(False, F.lit(1)).alias("asked"), of(False, (F.col("y") == 1).cast("int")).alias("ones"), of(False, (F.col("y") == 0).cast("int")).alias("zeros")
    )
    prior = bins.groupBy("feature").agg(F.try_divide(F.sum("s"), F.sum("n")).alias("prior"))
    rate = F.when(F.col("n") > 0, (F.col("s") + 5 * F.col("prior")) / (F.col("n") + 5)).otherwise(F.col("prior"))
    scored = bins.join(F.broadcast(prior), "feature").withColumn("right", F.when(rate >= 0.5, F.col("ones")).otherwise(F.col("zeros")))  # one row a feature
    share = F.try_divide(F.sum("ones"), F.sum("ones") + F.sum("zeros"))
    return scored.groupBy("feature").agg(F.try_divide(F.sum("right"), F.sum("asked")).alias("accuracy"), F.greatest(share, 1 - share).alias("base"))


@query("fi_study")
def fi_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean absolute error of estimated importance by sampling method and number of known features a cluster, over all vectors.

    One frame carries the method and the place of every feature in its method's order; a
    size is a cut of that order.  Estimates are inner products with summed vectors.
    """
    vectors = Repository(spark, sf_dir).table("embeddings").select(F.concat(F.lit("v"), F.col("vec_id").cast("string")).alias("feature_id"), F.col("embedding").alias("repr"), F.col("label").cast("int").alias("cluster_id"))
    parts = written(representation.unit_vectors(vectors.select("feature_id", "repr")).join(vectors.select("feature_id", "cluster_id"), "feature_id"), "fi-study")
    axis = parts.where("feature_id = 'v0'").select("pos", F.col("u").alias("a"))
    truth = written(parts.join(F.broadcast(axis), "pos", "left").groupBy("feature_id", "cluster_id").agg((0.5 + 0.5 * F.coalesce(F.sum(F.col("u") * F.col("a")), F.lit(0.0))).alias("fi")), "fi-truth")  # components of one vector
    sizes = (2, 5, 10)
    at, reprs = vectors.select("feature_id", "cluster_id"), vectors.select("feature_id", "repr")
    picked = [representation.sample_features(at, reprs, size, m).select(F.lit(m).alias("method"), F.lit(size).alias("per_cluster"), "feature_id") for m in ("random", "centroid", "cover") for size in sizes]
    known = written(reduce(DataFrame.unionByName, picked).join(truth, "feature_id"), "fi-known")
    told = parts.select("feature_id", "pos", "u").join(known, "feature_id").groupBy("method", "per_cluster", "cluster_id", "pos").agg(F.sum(F.col("fi") * F.col("u")).alias("weighed"), F.sum("u").alias("plain"), F.count(F.lit(1)).alias("members"))
    sums = parts.join(told, ["cluster_id", "pos"]).groupBy("method", "per_cluster", "feature_id").agg(F.sum(F.col("u") * F.col("weighed")).alias("top"), F.sum(F.col("u") * F.col("plain")).alias("cosines"), F.max("members").alias("members"))
    # where a cluster has no known member the estimate is 0
    spec = F.broadcast(known.select("method", "per_cluster").distinct())  # nine rows
    asked = truth.select("feature_id", "fi").crossJoin(spec).join(known.select("method", "per_cluster", "feature_id"), ["method", "per_cluster", "feature_id"], "left_anti").join(sums, ["method", "per_cluster", "feature_id"], "left")
    guess = lambda below: F.coalesce(F.try_divide("top", below), F.lit(0.0))
    both = F.explode(F.array(F.struct(F.lit(False).alias("normalised"), guess(F.col("members").cast("double")).alias("e")), F.struct(F.lit(True).alias("normalised"), guess(F.col("cosines")).alias("e"))))
    return asked.select("method", "per_cluster", "fi", both.alias("g")).groupBy("method", "per_cluster", "g.normalised").agg(F.avg(F.abs(F.col("g.e") - F.col("fi"))).alias("mae"), F.count(F.lit(1)).alias("unknown"))


@query("search_study")
def search_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """On every task: model score, objective, seconds and work of the three searches by budget, with and without refinement.

    Both estimators are fitted before any clock starts.  Progressive search prunes;
    exhaustive and greedy score all pairs without pruning.  Seconds hold the search alone.
    """
    rows = []
    for work in prepared(spark, sf_dir):
        engine = work.fitted
        s = engine.settings
        all_pairs = 10**6
        engine.candidates(all_pairs, t_iq=0.0, fi_bound=False)  # estimates are made once for all searches
        plans, facts = {"": []}, {}
        for budget in (1, 5, 10):
            def progressive(refined: bool, budget: int = budget):
                found, stats = engine.candidates(s.heap_factor * budget)
                return ([c for c, _ in searching.refine(found, budget, engine.clusters, engine.vectors)] if refined else searching.search_exhaustive(found, budget)), stats

            def plain(search, budget: int = budget):
                found, stats = engine.candidates(all_pairs, t_iq=0.0, fi_bound=False)
                return search(found, budget), stats

            for method, run in (("exhaustive", lambda: plain(searching.search_exhaustive)), ("greedy", lambda: plain(searching.search_greedy)), ("progressive", lambda: progressive(True)), ("progressive, not refined", lambda: progressive(False))):
                took = []
                for _ in range(3):
                    began = time.perf_counter()
                    plan, stats = run()
                    took.append(time.perf_counter() - began)
                plans[f"{method}|{budget}"] = list(dict.fromkeys(work.column(c.path, c.feature.split(".", 1)[1]) for c in plan))
                facts[method, budget] = (sum(c.gain for c in plan), min(took), stats.expanded, stats.scored)
        scores = work.score_plans(plans)
        for (method, budget), (objective, seconds, expanded, scored) in facts.items():
            rows.append((work.spec.name, budget, method, scores[f"{method}|{budget}"], float(objective), seconds, expanded, scored, facts["exhaustive", budget][1] / seconds, seconds / facts[method, 1][1]))
    return spark.createDataFrame(rows, "task string, budget int, method string, utility double, objective double, seconds double, expanded int, scored int, speed_up double, growth double")


@query("heap_study")
def heap_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """On every task: model score, seconds and work of the search by heap size, 5 to 100, for a plan of ten."""
    rows = []
    for work in prepared(spark, sf_dir):
        engine = work.fitted
        engine.candidates(10**6, t_iq=0.0, fi_bound=False)
        plans, facts = {}, {}
        for heap in (5, 10, 20, 50, 100):
            began = time.perf_counter()
            plan, stats = engine.plan(10, heap)
            facts[heap] = (time.perf_counter() - began, stats.scored, stats.inserted)
            plans[str(heap)] = list(dict.fromkeys(work.column(c.path, c.feature.split(".", 1)[1]) for c, _ in plan))
        scores = work.score_plans(plans)
        rows += [(work.spec.name, heap, scores[str(heap)], len(plans[str(heap)]), *f) for heap, f in facts.items()]
    return spark.createDataFrame(rows, "task string, heap int, utility double, features int, seconds double, scored int, inserted int")


@query("search_enumerated")
def search_enumerated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Literal enumeration of all plans on small graphs beside the closed optimum and progressive search, by budget."""
    rows, step = [], products(spark, sf_dir)
    iq = lambda p: float(np.prod([step[e.edge_id] for e in p.edges]))
    few = {t: c[:1] for t, c in FEATURES.items() if t != "lineitem"}
    fi = {f"{t}.{c}": fixed_importance(f"{t}.{c}") for t, cols in few.items() for c in cols}
    everything, _ = searching.search(GRAPH, "orders", few, iq, fi, heap_size=10**6, max_hops=3)
    for budget in (1, 2, 3):
        began = time.perf_counter()
        literal, scored = searching.enumerate_plans(everything, budget)
        enumerated = time.perf_counter() - began
        began = time.perf_counter()
        found, _ = searching.search(GRAPH, "orders", few, iq, fi, heap_size=5 * budget, t_iq=0.5, max_hops=3)
        progressive = searching.search_exhaustive(found, budget)
        seconds = time.perf_counter() - began
        gain = lambda plan: round(sum(c.gain for c in plan), 9)
        rows.append((budget, scored, gain(literal), gain(searching.search_exhaustive(everything, budget)), gain(progressive), enumerated, seconds))
    return spark.createDataFrame(rows, "budget int, plans long, enumerated double, closed double, progressive double, enumeration_seconds double, progressive_seconds double")


@query("cluster_report")
def cluster_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters, singletons, members and closeness to the centroid, and whether every member is within the threshold."""
    sizes = threshold_clusters(spark, sf_dir).groupBy("centroid_id").agg(F.count(F.lit(1)).alias("n"), F.min("cos_to_centroid").alias("low"), F.avg("cos_to_centroid").alias("mean"))
    return sizes.agg(F.count(F.lit(1)).alias("clusters"), F.sum((F.col("n") == 1).cast("int")).alias("singletons"), F.max("n").alias("largest"), F.min("low").alias("least_cosine"), F.avg("mean").alias("mean_cosine"), F.max(1 - F.col("low")).alias("radius"), F.bool_and(F.col("low") >= 0.35).alias("bound_holds"))


@query("moment_bounds")
def moment_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moments of the absolute value of a centred, scaled column beside their bounds."""
    values = Repository(spark, sf_dir).table("events").select("value")
    ends = values.agg(F.avg("value").alias("m"), F.max(F.abs("value")).alias("top"))
    x = values.crossJoin(F.broadcast(ends)).select(((F.col("value") - F.col("m")) / (2 * F.col("top"))).alias("x"))  # one row
    row = x.agg(F.var_pop("x").alias("eps"), F.avg(F.abs("x")).alias("mean_abs"), F.var_pop(F.abs("x")).alias("var_abs")).first()
    bounds = abs_moment_bounds(row["eps"])
    return spark.createDataFrame([(row["eps"], row["mean_abs"], bounds["mean_abs"], row["var_abs"], bounds["var_abs"])], "eps double, mean_abs double, mean_abs_bound double, var_abs double, var_abs_bound double")

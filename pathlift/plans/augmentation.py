"""Queries on augmentation, integration, normalisation, utility and importance."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures
from ..functions.measures import METRICS
from ..operators import augment as aug
from ..operators import utility
from ..registry import ORACLES, QUERIES, query
from ..sources.repository import JoinPath, Repository, path_of
from . import sqltext


def _augmentation(name: str, path: JoinPath, feature: str, columns: tuple[str, ...], policy: str = "first", how: str = "left", latest_by: str | None = None, digits: int | None = None) -> None:
    value = f"{path.last}__{feature}"

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        repo = Repository(spark, sf_dir)
        out = aug.augment(repo, repo.table(path.base), path, feature, policy=policy, how=how, latest_by=latest_by)
        return out.select(*columns, F.round(value, digits).alias(value) if digits is not None else F.col(value))

    sql = sqltext.augmented(path.base, path, feature, ", ".join(columns), value, policy, {"left": "LEFT", "inner": "INNER", "right": "RIGHT", "full": "FULL"}[how], latest_by)
    QUERIES[name] = run
    ORACLES[name] = f"SELECT {', '.join(columns)}, round({value}, {digits}) AS {value} FROM ({sql})" if digits is not None else sql


_augmentation("augment_one_hop", path_of("e1"), "c_acctbal", ("o_orderkey",))
_augmentation("augment_two_hop", path_of("e1", "e2"), "n_name", ("o_orderkey",))
_augmentation("augment_three_hop", path_of("e1", "e2", "e3"), "r_name", ("o_orderkey",))
_augmentation("augment_four_hop", path_of("e5r", "e7", "e4", "e3"), "r_name", ("o_orderkey",))
_augmentation("augment_bridge", path_of("e14"), "o_totalprice", ("c_custkey",))
_augmentation("augment_fan_out_bridge", path_of("e5r", "e7"), "s_acctbal", ("o_orderkey",))
_augmentation("augment_inner", path_of("e8"), "value", ("c_custkey",), how="inner")
_augmentation("augment_right", path_of("e1"), "c_acctbal", ("o_orderkey",), how="right")
_augmentation("augment_full", path_of("e9r"), "quality", ("doc_id",), how="full")
for _policy in ("first", "mean", "max", "min", "sum", "count"):
    _augmentation(f"augment_collapse_{_policy}", path_of("e1r"), "o_totalprice", ("c_custkey",), policy=_policy, digits=None if _policy == "count" else 2)
_augmentation("augment_collapse_mode", path_of("e1r"), "o_orderpriority", ("c_custkey",), policy="mode")
_augmentation("augment_collapse_latest", path_of("e1r"), "o_totalprice", ("c_custkey",), policy="latest", latest_by="o_orderdate")


@query("split_null_counts", f"WITH a AS ({sqltext.augmented('customer', path_of('e14'), 'o_totalprice', 'c_custkey', 'v')}) SELECT count(v) AS matched, count(*) - count(v) AS unmatched FROM a")
def split_null_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of the two slices of an augmented table."""
    repo = Repository(spark, sf_dir)
    hit, miss = aug.split_augmented(aug.augment(repo, repo.table("customer"), path_of("e14"), "o_totalprice", name="v"), "v")
    return hit.agg(F.count(F.lit(1)).alias("matched")).crossJoin(miss.agg(F.count(F.lit(1)).alias("unmatched")))  # one row each


PLAN = ((path_of("e1"), "c_acctbal"), (path_of("e1", "e2"), "n_name"), (path_of("e1", "e2", "e3"), "r_name"), (path_of("e5r"), "l_quantity"), (path_of("e5r", "e7"), "s_acctbal"))


def _plan_sql() -> str:
    columns = ", ".join(f"f{i}.v AS {p.last}__{f}__{i}" for i, (p, f) in enumerate(PLAN, 1))
    joins = "\n".join(f"LEFT JOIN {sqltext.fold(p.edges, f, 'first')} f{i} ON {p.edges[0].left_col} = f{i}.key" for i, (p, f) in enumerate(PLAN, 1))
    return f"SELECT o_orderkey, {columns} FROM orders\n{joins}"


@query("integrated_plan", _plan_sql())
def integrated_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All features of a plan in one table; common path prefixes are joined once."""
    repo = Repository(spark, sf_dir)
    return aug.integrate(repo, repo.table("orders").select("o_orderkey", "o_custkey"), PLAN)[0].drop("o_custkey")


@query("normalize_part", "SELECT p_partkey, p_name, p_size, p_retailprice, p_brand, p_type FROM part")
def normalize_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """part split into a core and two dimensions, and put together again without loss."""
    parts = aug.split_wide(Repository(spark, sf_dir).table("part"), "p_partkey", {"brand": ("p_brand",), "kind": ("p_type",)})
    return parts["core"].join(parts["brand"], "brand_id").join(parts["kind"], "kind_id").select("p_partkey", "p_name", "p_size", "p_retailprice", "p_brand", "p_type")


@query("normalize_documents", "SELECT count(DISTINCT lang) AS langs, count(DISTINCT source) AS sources, count(*) AS documents FROM documents")
def normalize_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of the dimensions that documents split into."""
    parts = aug.split_wide(Repository(spark, sf_dir).table("documents").select("doc_id", "lang", "source"), "doc_id", {"lang": ("lang",), "source": ("source",)})
    n = lambda t, c: parts[t].agg(F.count(F.lit(1)).alias(c))
    return n("lang", "langs").crossJoin(n("source", "sources")).crossJoin(n("core", "documents"))  # one row each


# --- utility -----------------------------------------------------------------

def quality_base(repo: Repository) -> DataFrame:
    """W1: labelled documents with features one and two hops away."""
    out, _ = aug.integrate(repo, repo.table("labels"), ((JoinPath((path_of("e9").edges[0],)), "lang"), (JoinPath((path_of("e9").edges[0],)), "source")))
    shape = repo.table("doc_shape").select((F.col("shape_id") - 1000000).alias("doc_id"), "alpha_bin")
    return out.join(shape, "doc_id", "left").select("doc_id", "quality", "toxic", F.col("documents__lang__1").alias("lang"), F.col("documents__source__2").alias("source"), "alpha_bin")


_W1 = f"(SELECT l.doc_id, l.quality, l.toxic, d.lang, d.source, s.alpha_bin FROM labels l LEFT JOIN documents d USING (doc_id) LEFT JOIN {sqltext.view_sql('doc_shape')} s ON s.shape_id = l.doc_id + 1000000)"


def region_base(repo: Repository) -> DataFrame:
    """W2: orders with the planted region label and features on two routes."""
    plan = ((path_of("e1"), "c_mktsegment"), (path_of("e1", "e2"), "n_regionkey"), (path_of("e5r", "e7", "e4"), "n_regionkey"), (path_of("e5r"), "l_returnflag"))
    base = repo.table("orders_region_label")
    out, _ = aug.integrate(repo, base, plan)
    return out.select("o_orderkey", "y", F.col("customer__c_mktsegment__1").alias("segment"), F.col("nation__n_regionkey__2").alias("region"), F.col("nation__n_regionkey__3").alias("supplier_region"), F.col("lineitem__l_returnflag__4").alias("returnflag"))


_W2 = "(SELECT o_orderkey, y, f1.v AS segment, f2.v AS region, f3.v AS supplier_region, f4.v AS returnflag FROM " + sqltext.frm("orders_region_label") + "".join(
    f" LEFT JOIN {sqltext.fold(p.edges, f, 'first')} f{i} ON {p.edges[0].left_col} = f{i}.key" for i, (p, f) in enumerate(((path_of("e1"), "c_mktsegment"), (path_of("e1", "e2"), "n_regionkey"), (path_of("e5r", "e7", "e4"), "n_regionkey"), (path_of("e5r"), "l_returnflag")), 1)) + ")"


def _accuracy_sql(rows: str, label: str, features: tuple[str, ...]) -> str:
    return "\nUNION ALL\n".join(f"SELECT '{f}' AS feature, round(sum(top) / sum(n)::DOUBLE, 6) AS score FROM (SELECT b, max(c) AS top, sum(c) AS n FROM (SELECT coalesce({f}::VARCHAR, '(missing)') AS b, {label}, count(*) AS c FROM {rows} GROUP BY ALL) GROUP BY b)" for f in features)


@query("binned_utility_accuracy", _accuracy_sql(_W1, "quality", ("lang", "source", "alpha_bin")))
def binned_utility_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of each feature of the document-quality task."""
    return utility.majority_accuracy(quality_base(Repository(spark, sf_dir)), "quality", ("lang", "source", "alpha_bin")).select("feature", F.round("score", 6).alias("score"))


@query("binned_utility_region", _accuracy_sql(_W2, "y", ("segment", "region", "supplier_region", "returnflag")))
def binned_utility_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of each feature of the planted region task; the right route gives 1."""
    return utility.majority_accuracy(region_base(Repository(spark, sf_dir)), "y", ("segment", "region", "supplier_region", "returnflag")).select("feature", F.round("score", 6).alias("score"))


def risk_base(repo: Repository) -> DataFrame:
    """W3: events with a skewed label and a planted risk behind a bridge that covers 60 %."""
    risk = repo.table("event_to_session").join(repo.table("session_risk"), "session_id").select("event_id", "risk")
    return repo.table("event_label").join(risk, "event_id", "left")


_W3 = f"(SELECT e.*, r.risk FROM {sqltext.frm('event_label')} e LEFT JOIN (SELECT event_id, risk FROM {sqltext.frm('event_to_session')} JOIN {sqltext.frm('session_risk')} USING (session_id)) r USING (event_id))".replace(" AS event_label e", " e")


@query("binned_utility_f1", "\nUNION ALL\n".join(f"SELECT '{f}' AS feature, round(coalesce(tp / nullif(tp + 0.5 * (fp + fn), 0), 0.0), 6) AS score FROM (SELECT sum(CASE WHEN 2 * p >= n THEN p ELSE 0.0 END) AS tp, sum(CASE WHEN 2 * p >= n THEN n - p ELSE 0.0 END) AS fp, sum(CASE WHEN 2 * p >= n THEN 0.0 ELSE p END) AS fn FROM (SELECT coalesce({f}::VARCHAR, '(missing)') AS b, sum(y)::DOUBLE AS p, count(*)::DOUBLE AS n FROM {_W3} GROUP BY 1))" for f in ("event_type", "risk")))
def binned_utility_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F1 of features for the skewed event label."""
    return utility.binned_f1(risk_base(Repository(spark, sf_dir)), "y", ("event_type", "risk")).select("feature", F.round("score", 6).alias("score"))


def spend_base(repo: Repository) -> DataFrame:
    """W4: what customers spent, with the number of their orders, urgent value and segment."""
    out = aug.augment(repo, repo.table("customer_spend"), path_of("e1r"), "o_orderkey", name="orders", policy="count")
    out = aug.augment(repo, out, path_of("e14"), "o_totalprice", name="urgent", policy="max")
    return aug.augment(repo, out, JoinPath((path_of("e1").edges[0].__class__("self", "customer_spend", "c_custkey", "customer", "c_custkey"),)), "c_mktsegment", name="segment")


_W4 = f"(SELECT s.c_custkey, s.y, f1.v AS orders, f2.v AS urgent, c.c_mktsegment AS segment FROM {sqltext.frm('customer_spend')} s LEFT JOIN {sqltext.fold(path_of('e1r').edges, 'o_orderkey', 'count')} f1 ON s.c_custkey = f1.key LEFT JOIN {sqltext.fold(path_of('e14').edges, 'o_totalprice', 'max')} f2 ON s.c_custkey = f2.key LEFT JOIN customer c ON c.c_custkey = s.c_custkey)".replace(" AS customer_spend s", " s")


@query("regression_utility_bins", "\nUNION ALL\n".join(f"SELECT '{f}' AS feature, round(sqrt(avg((y - m) ** 2)), 2) AS rmse, round(avg(abs(y - m)), 2) AS mae FROM (SELECT y, avg(y) OVER (PARTITION BY coalesce({f}::VARCHAR, '(missing)')) AS m FROM {_W4})" for f in ("orders", "segment")))
def regression_utility_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors of bin means for the spending task (root of the squared error)."""
    out = utility.bin_mean_error(spend_base(Repository(spark, sf_dir)), "y", ("orders", "segment"))
    return out.select("feature", F.round(F.sqrt("mse"), 2).alias("rmse"), F.round("mae", 2).alias("mae"))


@query("regression_utility_linear", "\nUNION ALL\n".join(f"SELECT '{f}' AS feature, round(sqrt((count(x) * coalesce(var_pop(y) FILTER (x IS NOT NULL), 0) * (1 - coalesce(regr_r2(y, x), 0)) + (count(*) - count(x)) * coalesce(var_pop(y) FILTER (x IS NULL), 0)) / count(*)), 2) AS rmse FROM (SELECT y, {f}::DOUBLE AS x FROM {_W4})" for f in ("orders", "urgent")))
def regression_utility_linear(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors of straight lines for the spending task."""
    return utility.linear_error(spend_base(Repository(spark, sf_dir)), "y", ("orders", "urgent")).select("feature", F.round(F.sqrt("mse"), 2).alias("rmse"))


# --- importance times quality ------------------------------------------------

def _thinned(repo: Repository) -> DataFrame:
    """(task, t, bin, y): the best feature of W1 and of W2, kept where the key modulo 10 lies below t."""
    w1 = quality_base(repo).select(F.lit("W1").alias("task"), F.col("doc_id").alias("key"), F.col("alpha_bin").cast("string").alias("v"), F.col("quality").alias("y"))
    w2 = region_base(repo).select(F.lit("W2").alias("task"), F.col("o_orderkey").alias("key"), F.col("region").cast("string").alias("v"), "y")
    levels = repo.spark.range(0, 11).select(F.col("id").cast("int").alias("t"))  # eleven rows
    return w1.unionByName(w2).crossJoin(F.broadcast(levels)).select("task", "t", F.when(F.pmod("key", F.lit(10)) < F.col("t"), F.col("v")).alias("v"), "y")


def linearity(repo: Repository) -> DataFrame:
    """(task, t, iq, ug, fi_iq): gain against importance times quality, importance being the gain at full coverage."""
    cells = _thinned(repo).groupBy("task", "t", F.coalesce("v", F.lit("(missing)")).alias("bin"), "y").agg(F.count(F.lit(1)).alias("c"), F.count("v").alias("hit"))
    bins = cells.groupBy("task", "t", "bin").agg(F.max("c").alias("top"), F.sum("c").alias("n"), F.sum("hit").alias("hit"))
    levels = bins.groupBy("task", "t").agg((F.sum("top") / F.sum("n")).alias("us"), (F.sum("hit") / F.sum("n")).alias("iq"))
    ends = levels.groupBy("task").agg(F.max(F.when(F.col("t") == 0, F.col("us"))).alias("base"), F.max(F.when(F.col("t") == 10, F.col("us"))).alias("full"))
    return levels.join(F.broadcast(ends), "task").where("t > 0").select("task", "t", "iq", (F.col("us") - F.col("base")).alias("ug"), ((F.col("full") - F.col("base")) * F.col("iq")).alias("fi_iq"))


_LINEAR = f"""WITH r AS (SELECT 'W1' AS task, doc_id AS key, alpha_bin::VARCHAR AS v, quality AS y FROM {_W1} UNION ALL SELECT 'W2', o_orderkey, region::VARCHAR, y FROM {_W2}),
x AS (SELECT task, t, CASE WHEN key % 10 < t THEN v END AS v, y FROM r, (SELECT unnest(range(0, 11))::INT AS t)),
c AS (SELECT task, t, coalesce(v, '(missing)') AS bin, y, count(*) AS c, count(v) AS hit FROM x GROUP BY ALL),
b AS (SELECT task, t, bin, max(c) AS top, sum(c) AS n, sum(hit) AS hit FROM c GROUP BY ALL),
l AS (SELECT task, t, sum(top) / sum(n)::DOUBLE AS us, sum(hit) / sum(n)::DOUBLE AS iq FROM b GROUP BY ALL),
e AS (SELECT task, max(us) FILTER (t = 0) AS base, max(us) FILTER (t = 10) AS full_us FROM l GROUP BY task),
g AS (SELECT task, t, iq, us - base AS ug, (full_us - base) * iq AS fi_iq FROM l JOIN e USING (task) WHERE t > 0)"""


@query("ug_vs_fi_iq", f"{_LINEAR} SELECT task, t, round(iq, 6) AS iq, round(ug, 6) AS ug, round(fi_iq, 6) AS fi_iq FROM g")
def ug_vs_fi_iq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured gain against the product of importance and quality at ten levels of coverage."""
    return linearity(Repository(spark, sf_dir)).select("task", "t", *[F.round(c, 6).alias(c) for c in ("iq", "ug", "fi_iq")])


@query("linearity_fit", f"{_LINEAR} SELECT task, round(regr_slope(ug, fi_iq), 6) AS slope, round(regr_r2(ug, fi_iq), 6) AS r2, round(max(abs(ug - fi_iq)), 6) AS gap FROM g GROUP BY task")
def linearity_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Straight-line fit of gain on importance times quality."""
    return linearity(Repository(spark, sf_dir)).groupBy("task").agg(F.round(F.regr_slope("ug", "fi_iq"), 6).alias("slope"), F.round(F.regr_r2("ug", "fi_iq"), 6).alias("r2"), F.round(F.max(F.abs(F.col("ug") - F.col("fi_iq"))), 6).alias("gap"))


@query("exact_fi_binned", f"{_LINEAR} SELECT task, round(full_us - base, 6) AS fi FROM e")
def exact_fi_binned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Importance of the best feature of each task: gain when every row has a value."""
    return linearity(Repository(spark, sf_dir)).where("t = 10").select("task", F.round("ug", 6).alias("fi"))


_SCORED = f"(SELECT y, risk, coalesce(risk, 0) AS pred FROM {_W3})"


@query("decomposition_identity", f"SELECT round(avg(ok), 6) AS whole, round(avg(hit), 6) AS share, round(avg(ok) FILTER (hit = 1), 6) AS matched, round(avg(ok) FILTER (hit = 0), 6) AS unmatched, round(avg(hit) * avg(ok) FILTER (hit = 1) + (1 - avg(hit)) * avg(ok) FILTER (hit = 0), 6) AS recombined FROM (SELECT CASE WHEN pred = y THEN 1.0 ELSE 0.0 END::DOUBLE AS ok, CASE WHEN risk IS NULL THEN 0.0 ELSE 1.0 END::DOUBLE AS hit FROM {_SCORED})")
def decomposition_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy as the weighted mean of its two slices."""
    scored = risk_base(Repository(spark, sf_dir)).withColumn("pred", F.coalesce("risk", F.lit(0)))
    out = utility.decomposition(scored, "pred", "y", "risk")
    return out.select(*[F.round(c, 6).alias(c) for c in ("whole", "share", "matched", "unmatched", "recombined")])


_METRIC_SQL = {
    "accuracy": "avg(CASE WHEN pred = y THEN 1.0 ELSE 0.0 END)",
    "f1": "sum(pred * y) / (sum(pred * y) + 0.5 * (sum(pred * (1 - y)) + sum((1 - pred) * y)))",
    "precision": "sum(pred * y)::DOUBLE / sum(pred)",
    "recall": "sum(pred * y)::DOUBLE / sum(y)",
    "mae": "avg(abs(pred - y))",
    "mse": "avg((pred - y) ** 2)",
}


def _metric(name: str) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        scored = risk_base(Repository(spark, sf_dir)).withColumn("pred", F.coalesce("risk", F.lit(0)))
        return scored.agg(F.round(METRICS[name]("pred", "y"), 6).alias("score"), F.round(measures.signed_score(name, METRICS[name]("pred", "y")), 6).alias("utility"))

    sign = "-" if name in measures.LOWER_IS_BETTER else ""
    QUERIES[f"metric_{name}"] = run
    ORACLES[f"metric_{name}"] = f"SELECT round(s, 6) AS score, round({sign}s, 6) AS utility FROM (SELECT ({_METRIC_SQL[name]})::DOUBLE AS s FROM {_SCORED})"


for _m in METRICS:
    _metric(_m)


SLICES = ((100, 80, 30), (1000, 300, 250), (10000, 9000, 100))


@query("slice_error_bounds", "SELECT n_total, n_matched, n_drawn, round(n_drawn * n_matched / n_total::DOUBLE, 9) AS mean, round(n_drawn * n_matched::DOUBLE * (n_total - n_drawn) * (n_total - n_matched) / (n_total::DOUBLE ** 4 * (n_total - 1)), 9) AS variance, round(1.0::DOUBLE / n_total, 9) AS variance_bound, round(2 / sqrt(n_total), 9) AS mean_abs_bound FROM " + sqltext.values(SLICES, "n_total, n_matched, n_drawn"))
def slice_error_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moments and bounds of the slice error."""
    rows = [(*s, *[round(measures.slice_error_bounds(*s)[k], 9) for k in ("mean", "variance", "variance_bound", "mean_abs_bound")]) for s in SLICES]
    return spark.createDataFrame(rows, "n_total int, n_matched int, n_drawn int, mean double, variance double, variance_bound double, mean_abs_bound double")


@query("slice_error_simulated", None)
def slice_error_simulated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share error of hash-drawn slices of events, over seeds, beside its bound."""
    events = Repository(spark, sf_dir).table("events").select("event_id", (F.pmod("event_id", F.lit(10)) < 6).alias("hit"))
    seeds = spark.range(0, 50).select(F.col("id").alias("seed"))  # fifty rows
    drawn = events.crossJoin(F.broadcast(seeds)).withColumn("in", F.pmod(F.xxhash64("event_id", "seed"), F.lit(4)) == 0)
    errors = drawn.groupBy("seed").agg(((F.sum((F.col("in") & F.col("hit")).cast("int")) - F.sum(F.col("in").cast("int")) * F.avg(F.col("hit").cast("double"))) / F.count(F.lit(1))).alias("e"), F.count(F.lit(1)).alias("n"))
    return errors.agg(F.avg(F.abs("e")).alias("mean_abs"), F.var_pop("e").alias("variance"), (2 / F.sqrt(F.max("n"))).alias("mean_abs_bound"), (1 / F.max("n")).alias("variance_bound"))


@query("utility_models")
def utility_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Held-out accuracy of trained model families on the document-quality task, base and augmented."""
    rows = quality_base(Repository(spark, sf_dir)).persist()
    base = utility.fit_models(rows, "quality", ("lang",), "accuracy", families=("linear", "forest"), key="doc_id")
    more = utility.fit_models(rows, "quality", ("lang", "alpha_bin"), "accuracy", families=("linear", "forest"), key="doc_id")
    rows.unpersist()
    return spark.createDataFrame([(k, base[k], more[k], more[k] - base[k]) for k in base], "family string, base double, augmented double, gain double")



"""Queries on paths, pair selection, importance estimates, search, refinement, the sequence model and baselines."""

from __future__ import annotations

import hashlib
import time
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import systems
from ..operators import edge_stats, quality, representation
from ..operators import search as searching
from ..operators.paths import JoinGraph, enumerate_paths, enumerate_paths_sql, make_pairs, repository_statistics
from ..operators.selection import Coverage, Pair, select_pairs
from ..registry import query
from ..sources.repository import EDGES, Repository, as_key, path_of
from . import sqltext

STAR = EDGES[:7]
GRAPH = JoinGraph(STAR)
#: Candidate features by table.
FEATURES = {
    "customer": ("c_acctbal", "c_mktsegment"), "nation": ("n_name", "n_regionkey"), "region": ("r_name",), "lineitem": ("l_quantity", "l_discount", "l_returnflag"), "part": ("p_size", "p_retailprice", "p_brand"), "supplier": ("s_acctbal",), "orders": ("o_totalprice", "o_orderpriority"),
}
MAX_HOPS = 4
_EDGE_ROWS = [(e.edge_id, e.left, e.right) for e in GRAPH.edges]
_EDGES_SQL = sqltext.values(_EDGE_ROWS, "edge_id, left_table, right_table")
_PATHS = f"""RECURSIVE p(path_id, hops, tables, last_table) AS (
    SELECT edge_id, 1, left_table || '>' || right_table, right_table FROM {_EDGES_SQL} WHERE left_table = 'orders'
    UNION ALL SELECT p.path_id || '>' || e.edge_id, p.hops + 1, p.tables || '>' || e.right_table, e.right_table
    FROM p JOIN {_EDGES_SQL} e ON p.last_table = e.left_table WHERE p.hops < {MAX_HOPS} AND NOT list_contains(string_split(p.tables, '>'), e.right_table))"""
_FEATURE_ROWS = [(t, f"{t}.{c}") for t, cols in FEATURES.items() for c in cols]
_FEATURES_SQL = sqltext.values(_FEATURE_ROWS, "tbl, feature_id")
_PAIRS = f"pairs AS (SELECT feature_id, path_id, hops FROM p JOIN {_FEATURES_SQL} ON last_table = tbl)"


# --- paths that the given rows bear out -----------------------------------------

_MET_SQL = " UNION ALL ".join(f"SELECT '{x.edge_id}' AS edge_id FROM (SELECT count(*) AS n FROM {e.left} WHERE {e.left_col} IN (SELECT {e.right_col} FROM {e.right})) WHERE n > 0" for e in STAR for x in (e, e.reverse()))
_MET_PATHS = f"RECURSIVE met AS ({_MET_SQL}), {_PATHS.removeprefix('RECURSIVE ').replace(_EDGES_SQL, f'(SELECT * FROM {_EDGES_SQL} JOIN met USING (edge_id))')}"

_FILLED_SQL = " UNION ALL ".join(f"SELECT '{t}' AS tbl, '{t}.{c}' AS feature_id FROM (SELECT count({c}) AS n FROM {t}) WHERE n > 0" for t, cols in FEATURES.items() for c in cols)
_MET_PAIRS = f"filled AS ({_FILLED_SQL}), {_PAIRS.replace(_FEATURES_SQL, 'filled')}"


def met_graph(spark: SparkSession, sf_dir: str) -> JoinGraph:
    """The star's edges over which at least one row finds another, by semi-joins over all rows."""
    repo = Repository(spark, sf_dir)

    def matched(e) -> DataFrame:
        kind = repo.kind(e)
        asked, known = (repo.table(t).select(as_key(c, kind).alias("k")) for t, c in ((e.left, e.left_col), (e.right, e.right_col)))
        return asked.join(known, "k", "left_semi").agg(F.lit(e.edge_id).alias("edge_id"), F.count(F.lit(1)).alias("n"))

    found = {r["edge_id"] for r in reduce(DataFrame.unionByName, map(matched, STAR)).collect() if r["n"]}  # one row an edge
    return JoinGraph([e for e in STAR if e.edge_id in found])


def filled_features(spark: SparkSession, sf_dir: str) -> dict[str, tuple[str, ...]]:
    """The candidate features that hold a value in at least one row, by table."""
    repo = Repository(spark, sf_dir)
    counts = [repo.table(t).agg(*[F.count(c).alias(c) for c in cols]).select(F.lit(t).alias("tbl"), F.array(*cols).alias("n")) for t, cols in FEATURES.items()]
    found = {r["tbl"]: r["n"] for r in reduce(DataFrame.unionByName, counts).collect()}  # one row a table
    return {t: tuple(c for c, n in zip(cols, found[t], strict=True) if n) for t, cols in FEATURES.items()}


def fixed_importance(feature: str, seed: int = 1) -> float:
    """An importance that depends on the name alone, for comparing searches with SQL."""
    return int(hashlib.md5(f"{seed}:{feature}".encode()).hexdigest()[:8], 16) / 2**32


@query("paths_frontier", f"WITH {_PATHS} SELECT * FROM p")
def paths_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Simple paths from orders by frontier joins."""
    return enumerate_paths(GRAPH, spark, "orders", MAX_HOPS)


@query("paths_recursive", f"WITH {_PATHS} SELECT * FROM p")
def paths_recursive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Simple paths from orders by a recursive query."""
    return enumerate_paths_sql(GRAPH, spark, "orders", MAX_HOPS)


@query("khop_tables", f"WITH {_MET_PATHS} SELECT last_table AS \"table\", min(hops) AS hops FROM p WHERE hops <= 3 GROUP BY last_table")
def khop_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables within three joins of orders, over edges that the rows bear out."""
    found = met_graph(spark, sf_dir).khop("orders", 3)
    return spark.createDataFrame([(t, h) for t, h in found.items() if h], "table string, hops int")


@query("repository_statistics", f"WITH {_PATHS}, h AS (SELECT last_table AS t, min(hops) AS hops FROM p GROUP BY last_table) SELECT count(DISTINCT t) AS \"tables\", count(feature_id) AS \"columns\", count(feature_id) FILTER (hops = 1) AS one_hop, count(feature_id) FILTER (hops > 1) AS distant FROM h LEFT JOIN {_FEATURES_SQL} ON t = tbl")
def statistics_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables, columns, near and distant features around orders."""
    r = repository_statistics(GRAPH, "orders", FEATURES, MAX_HOPS)
    return spark.createDataFrame([(r["tables"], r["columns"], r["one_hop"], r["distant"])], "tables long, columns long, one_hop long, distant long")


def _met_pairs(spark: SparkSession, sf_dir: str, max_hops: int = MAX_HOPS) -> DataFrame:
    return make_pairs(enumerate_paths(met_graph(spark, sf_dir), spark, "orders", max_hops), filled_features(spark, sf_dir))


@query("feature_path_pairs", f"WITH {_MET_PATHS}, {_MET_PAIRS} SELECT * FROM pairs")
def feature_path_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every path that rows bear out with every feature of its last table that holds values."""
    return _met_pairs(spark, sf_dir)


_SPACES_SQL = "SELECT last_table, count(DISTINCT feature_id)::INT AS n, count(DISTINCT path_id)::INT AS m FROM (SELECT split_part(feature_id, '.', 1) AS last_table, * FROM pairs UNION ALL SELECT 'all', * FROM pairs) GROUP BY last_table"


@query("combination_counts", f"WITH {_MET_PATHS}, {_MET_PAIRS} SELECT last_table AS \"table\", n, m, budget, sum(CASE WHEN i > n THEN 0 ELSE m * factorial(n) // (factorial(i) * factorial(greatest(n - i, 0))) END)::BIGINT AS plans FROM ({_SPACES_SQL}), (SELECT unnest([1, 3, 5]) AS budget) JOIN (SELECT unnest([1, 2, 3, 4, 5]) AS i) ON i <= budget GROUP BY ALL")
def combination_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plans by budget: over the features and paths of each last table, and of all, as far as rows bear them out."""
    pairs = _met_pairs(spark, sf_dir).select(F.explode(F.array(F.substring_index("feature_id", ".", 1), F.lit("all"))).alias("table"), "feature_id", "path_id")
    spec = pairs.groupBy("table").agg(F.countDistinct("feature_id").cast("int").alias("n"), F.countDistinct("path_id").cast("int").alias("m")).withColumn("budget", F.explode(F.array(*map(F.lit, (1, 3, 5)))))
    terms = spec.select("*", F.explode(F.sequence(F.lit(1), F.col("budget"))).alias("i"))
    binomial = F.aggregate(F.sequence(F.lit(1), F.col("i")), F.lit(1).cast("long"), lambda a, k: (a * (F.col("n") - k + 1) / k).cast("long"))
    return terms.groupBy("table", "n", "m", "budget").agg(F.sum(F.col("m") * binomial).cast("long").alias("plans"))


# --- search with fixed importances, so that SQL can repeat it ------------------

T_IQ = 0.5
_S = sqltext.edge_ctes(GRAPH.edges)
_IQ = "iq AS (SELECT path_id, product(transitivity) AS iq FROM (SELECT path_id, unnest(string_split(path_id, '>')) AS edge_id FROM p) JOIN s USING (edge_id) GROUP BY path_id)"
_ALIVE = f"alive AS (SELECT a.path_id FROM iq a JOIN iq b ON a.path_id = b.path_id OR starts_with(a.path_id, b.path_id || '>') GROUP BY a.path_id HAVING min(b.iq) >= {T_IQ})"
_SCORED = f"scored AS (SELECT feature_id, path_id, hops, round({sqltext.uniform('feature_id', 1)}, 9) AS fi, iq, round(round({sqltext.uniform('feature_id', 1)}, 9) * iq, 12) AS ug FROM pairs JOIN iq USING (path_id) JOIN alive USING (path_id))"
_ALL = f"WITH {_PATHS}, {_PAIRS}, {_S}, {_IQ}, {_ALIVE}, {_SCORED}"
_UNCUT = _ALL.replace(" JOIN alive USING (path_id)", "")
_OUT = "feature_id, path_id, hops, round(fi, 6) AS fi, round(iq, 6) AS iq, round(ug, 6) AS ug"


def _estimates(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    paths = enumerate_paths(GRAPH, spark, "orders", MAX_HOPS)
    stats = edge_stats.edge_statistics(Repository(spark, sf_dir), GRAPH.edges)
    iq = quality.product_of_transitivity(paths, stats).withColumnRenamed("iq_product", "iq")
    fi = spark.createDataFrame([(f, round(fixed_importance(f), 9)) for _, f in _FEATURE_ROWS], "feature_id string, fi double")
    return make_pairs(paths, FEATURES), iq, fi


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("feature_id", "path_id", "hops", *[F.round(c, 6).alias(c) for c in ("fi", "iq", "ug")])


def _candidate_frame(spark: SparkSession, rows: list[searching.Candidate]) -> DataFrame:
    return spark.createDataFrame([(c.feature, c.path.path_id, len(c.path.edges), round(c.fi, 6), round(c.iq, 6), round(c.gain, 6)) for c in rows], "feature_id string, path_id string, hops int, fi double, iq double, ug double")


@query("search_levels", f"{_ALL} SELECT {_OUT} FROM scored ORDER BY ug DESC, hops, path_id, feature_id LIMIT 25")
def search_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best pairs by DataFrame levels."""
    return _rounded(searching.search_levels(*_estimates(spark, sf_dir), heap_size=25, t_iq=T_IQ))


def products(spark: SparkSession, sf_dir: str) -> dict[str, float]:
    """Transitivity by edge (metadata)."""
    rows = edge_stats.edge_statistics(Repository(spark, sf_dir), GRAPH.edges).select("edge_id", "transitivity").collect()
    return {r["edge_id"]: r["transitivity"] for r in rows}


def _progressive(spark: SparkSession, sf_dir: str, step: dict[str, float] | None = None, **options) -> tuple[list[searching.Candidate], searching.SearchStats]:
    step = step or products(spark, sf_dir)
    iq = lambda p: float(np.prod([step[e.edge_id] for e in p.edges]))
    fi = {f: round(fixed_importance(f), 9) for _, f in _FEATURE_ROWS}
    return searching.search(GRAPH, "orders", FEATURES, iq, fi, max_hops=MAX_HOPS, **options)


@query("search_progressive", f"{_ALL} SELECT {_OUT} FROM scored ORDER BY ug DESC, hops, path_id, feature_id LIMIT 25")
def search_progressive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best pairs by the bounded heap with both prunings."""
    return _candidate_frame(spark, _progressive(spark, sf_dir, heap_size=25, t_iq=T_IQ)[0])


@query("search_greedy", f"{_UNCUT}, f AS (SELECT *, row_number() OVER (PARTITION BY feature_id ORDER BY hops, round(iq, 12) DESC, path_id) AS place FROM scored) SELECT {_OUT} FROM f WHERE place = 1 ORDER BY round(f.fi, 12) DESC, feature_id LIMIT 5")
def search_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greedy plan over all candidates: by importance, each feature over its shortest path."""
    return _candidate_frame(spark, searching.search_greedy(_progressive(spark, sf_dir, heap_size=10**6)[0], 5))


@query("search_exhaustive", f"{_UNCUT}, f AS (SELECT *, row_number() OVER (PARTITION BY feature_id ORDER BY ug DESC, hops, path_id) AS place FROM scored) SELECT {_OUT} FROM f WHERE place = 1 ORDER BY f.ug DESC, hops, path_id, feature_id LIMIT 5")
def search_exhaustive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plan of the largest summed gain over all candidates."""
    return _candidate_frame(spark, searching.search_exhaustive(_progressive(spark, sf_dir, heap_size=10**6)[0], 5))


@query("plan_objective", f"{_UNCUT}, f AS (SELECT feature_id, max(ug) AS ug FROM scored GROUP BY feature_id ORDER BY ug DESC LIMIT 10) SELECT count(*) AS features, round(sum(ug), 6) AS objective FROM f")
def plan_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summed gain of the best plan of ten."""
    plan = searching.search_exhaustive(_progressive(spark, sf_dir, heap_size=10**6)[0], 10)
    return spark.createDataFrame([(len(plan), round(sum(c.gain for c in plan), 6))], "features long, objective double")


@query("search_counters")
def search_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Work of the search by heap size, and with each pruning left out."""
    rows, step = [], products(spark, sf_dir)
    for name, options in (*((f"heap {h}", {"heap_size": h, "t_iq": T_IQ}) for h in (5, 10, 20, 50, 100)), ("no quality threshold", {"heap_size": 25}), ("no importance bound", {"heap_size": 25, "t_iq": T_IQ, "fi_bound": False}), ("monotone clamp", {"heap_size": 25, "t_iq": T_IQ, "clamp": True})):
        began = time.perf_counter()
        found, s = _progressive(spark, sf_dir, step, **options)
        rows.append((name, len(found), s.expanded, s.cut_by_quality, s.skipped_by_bound, s.scored, s.inserted, time.perf_counter() - began))
    return spark.createDataFrame(rows, "variant string, found int, expanded int, cut_by_quality int, skipped_by_bound int, scored int, inserted int, seconds double")


def _vectors(spark: SparkSession, sf_dir: str) -> tuple[list[tuple[str, int, str, float]], dict[str, np.ndarray]]:
    """Clusters and vectors of the star's features (columns of the repository)."""
    vectors = representation.represent(representation.serialized_columns(Repository(spark, sf_dir), FEATURES)).persist()
    near = [(r["a"], r["b"], r["cos"]) for r in representation.neighbours(vectors, 0.35).collect()]
    by = {r["feature_id"]: np.array(r["repr"]) for r in vectors.collect()}
    vectors.unpersist()
    return representation.threshold_cluster(near, sorted(by)), by


@query("feature_clusters")
def feature_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Threshold clusters of the star's features."""
    return spark.createDataFrame(_vectors(spark, sf_dir)[0], "feature_id string, cluster_id int, centroid_id string, cos_to_centroid double")


@query("refined_plan")
def refined_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The heap refined for diversity, in the printed and the scaled form."""
    clusters, vectors = _vectors(spark, sf_dir)
    found, _ = _progressive(spark, sf_dir, heap_size=50, t_iq=T_IQ)
    rows = []
    for decay in ("printed", "scaled"):
        plan = searching.refine(found, 10, {f: c for f, c, _, _ in clusters}, vectors, decay=decay)
        rows += [(decay, i, c.feature, c.path.path_id, c.fi, c.iq, g) for i, (c, g) in enumerate(plan, 1)]
    return spark.createDataFrame(rows, "decay string, rank int, feature_id string, path_id string, fi double, iq double, ug double")


# --- clustering and importance over the vectors of the embeddings table -------

def _sample_vectors(repo: Repository) -> DataFrame:
    """Embeddings as features: id, vector, and their label as cluster."""
    return repo.table("embeddings").select(F.concat(F.lit("v"), F.col("vec_id").cast("string")).alias("feature_id"), F.col("embedding").alias("repr"), F.col("label").cast("int").alias("cluster_id"), "vec_id")


_COS = "list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"


@query("cosine_neighbours", f"SELECT 'v' || a.vec_id AS a, 'v' || b.vec_id AS b, round({_COS}, 6) AS cos FROM embeddings a, embeddings b WHERE {_COS} >= 0.35")
def cosine_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vector pairs with cosine 0.35 or more."""
    return representation.neighbours(_sample_vectors(Repository(spark, sf_dir)), 0.35).select("a", "b", F.round("cos", 6).alias("cos"))


@query("threshold_clusters")
def threshold_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Threshold clusters of the embeddings (stand-ins for features), decided in rounds without the driver."""
    vectors = _sample_vectors(Repository(spark, sf_dir))
    return representation.threshold_clusters(representation.neighbours(vectors, 0.35), vectors.select("feature_id"))


_KNOWN = "(SELECT vec_id, label, embedding, round((vec_id % 17) / 17.0::DOUBLE - 0.2, 9) AS fi FROM embeddings WHERE vec_id % 5 = 0)"


def _known(repo: Repository) -> DataFrame:
    return _sample_vectors(repo).where("vec_id % 5 = 0").select("feature_id", F.round((F.col("vec_id") % 17) / F.lit(17.0) - 0.2, 9).alias("fi"))


def _fi_sql(below: str) -> str:
    return f"""SELECT 'v' || e.vec_id AS feature_id, round(coalesce(k.fi, m.mean, 0.0), 6) AS fi_est FROM embeddings e LEFT JOIN {_KNOWN} k USING (vec_id)
LEFT JOIN (SELECT a.vec_id, sum(b.fi * {_COS}) / {below} AS mean FROM embeddings a JOIN {_KNOWN} b USING (label) GROUP BY a.vec_id) m ON m.vec_id = e.vec_id"""


@query("fi_estimate", _fi_sql("count(*)"))
def fi_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimated importance, divided by the number of known members."""
    repo = Repository(spark, sf_dir)
    v = _sample_vectors(repo)
    return representation.estimate_importance(v.select("feature_id", "cluster_id"), v.select("feature_id", "repr"), _known(repo)).select("feature_id", F.round("fi_est", 6).alias("fi_est"))


@query("fi_estimate_normalised", _fi_sql(f"nullif(sum({_COS}), 0)").replace("m.mean, 0.0)", f"m.mean, (SELECT avg(fi) FROM {_KNOWN}))"))
def fi_estimate_normalised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimated importance, divided by the summed cosines; clusters without known members get the overall mean."""
    repo = Repository(spark, sf_dir)
    v = _sample_vectors(repo)
    return representation.estimate_importance(v.select("feature_id", "cluster_id"), v.select("feature_id", "repr"), _known(repo), normalise=True, empty="global_mean").select("feature_id", F.round("fi_est", 6).alias("fi_est"))


@query("fi_error", f"SELECT round(avg(abs(fi_est - truth)), 6) AS mae, count(*) AS n FROM (SELECT vec_id, round((vec_id % 17) / 17.0::DOUBLE - 0.2, 9) AS truth, fi_est FROM embeddings JOIN ({_fi_sql('count(*)')}) ON feature_id = 'v' || vec_id WHERE vec_id % 5 <> 0)")
def fi_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean absolute error of the estimate on features that were not known."""
    truth = _sample_vectors(Repository(spark, sf_dir)).where("vec_id % 5 <> 0").select("feature_id", F.round((F.col("vec_id") % 17) / F.lit(17.0) - 0.2, 9).alias("truth"))
    return fi_estimate(spark, sf_dir).join(truth, "feature_id").agg(F.round(F.avg(F.abs(F.col("fi_est") - F.col("truth"))), 6).alias("mae"), F.count(F.lit(1)).alias("n"))


def _sampling(method: str, sql: str | None) -> None:
    @query(f"fi_sampling_{method}", sql)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        v = _sample_vectors(Repository(spark, sf_dir))
        return representation.sample_features(v.select("feature_id", "cluster_id"), v.select("feature_id", "repr"), 5, method)


_sampling("random", "SELECT 'v' || vec_id AS feature_id, label AS cluster_id FROM (SELECT vec_id, label, row_number() OVER (PARTITION BY label ORDER BY md5('0:v' || vec_id), 'v' || vec_id) AS place FROM embeddings) WHERE place <= 5")
_sampling("centroid", f"SELECT feature_id, cluster_id FROM (SELECT *, row_number() OVER (PARTITION BY cluster_id ORDER BY s DESC, feature_id) AS place FROM (SELECT 'v' || a.vec_id AS feature_id, a.label AS cluster_id, round(avg({_COS}), 9) AS s FROM embeddings a JOIN embeddings b USING (label) GROUP BY a.vec_id, a.label)) WHERE place <= 5")
_sampling("cover", None)


# --- pair selection -----------------------------------------------------------

def _pairs(spark: SparkSession, sf_dir: str | None = None) -> list[Pair]:
    """Pairs within three joins; with a folder, those that its rows bear out."""
    rows = (make_pairs(enumerate_paths(GRAPH, spark, "orders", 3), FEATURES) if sf_dir is None else _met_pairs(spark, sf_dir, 3)).collect()  # metadata
    tables = sorted(FEATURES)
    return [Pair(r["feature_id"], tuple(r["path_id"].split(">")), tables.index(r["feature_id"].split(".")[0]) % 3) for r in rows]


_TAKEN = ("e1", "e1>e2")
_COVER = f"""WITH {_PATHS}, {_PAIRS}, q AS (SELECT *, string_split(path_id, '>') AS es FROM pairs WHERE hops <= 3),
x AS (SELECT DISTINCT unnest(es) AS e FROM q WHERE path_id IN ('e1', 'e1>e2')),
u AS (SELECT DISTINCT path_id, hops, unnest(es) AS e FROM q),
path AS (SELECT path_id, hops, count(x.e)::DOUBLE / hops AS pc FROM u LEFT JOIN x ON u.e = x.e GROUP BY path_id, hops),
grp AS (SELECT hops, count(*) FILTER (pc = 1.0) / count(*)::DOUBLE AS pgc FROM path GROUP BY hops)
SELECT path_id, round(any_value(pc), 6) AS path_coverage, round(any_value(pgc), 6) AS length_coverage FROM path JOIN grp USING (hops) GROUP BY path_id"""


@query("selection_coverage", _COVER)
def selection_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Coverages of all paths after the pairs of two paths were taken."""
    pairs = _pairs(spark)
    state = Coverage(pairs)
    for p in pairs:
        if ">".join(p.path) in _TAKEN:
            state.take(p)
    return spark.createDataFrame([(">".join(p), round(state.path(p), 6), round(state.length(len(p)), 6)) for p in sorted(state.paths)], "path_id string, path_coverage double, length_coverage double")


def _weights(spark: SparkSession, taken: tuple[str, ...]) -> DataFrame:
    pairs = _pairs(spark)
    state = Coverage(pairs)
    for p in pairs:
        if ">".join(p.path) in taken:
            state.take(p)
    return spark.createDataFrame([(p.feature, ">".join(p.path), round(state.weight(p), 6)) for p in pairs], "feature_id string, path_id string, weight double")


_CLUSTER = "(CASE split_part(feature_id, '.', 1) " + " ".join(f"WHEN '{t}' THEN {i % 3}" for i, t in enumerate(sorted(FEATURES))) + " END)"
_WEIGHTS = _COVER.replace("SELECT path_id, round(any_value(pc), 6) AS path_coverage, round(any_value(pgc), 6) AS length_coverage FROM path JOIN grp USING (hops) GROUP BY path_id", "") + f""", tested AS (
    SELECT {_CLUSTER} AS cl, count(DISTINCT feature_id) FILTER (path_id IN ('e1', 'e1>e2'))::DOUBLE / count(DISTINCT feature_id) AS fc FROM q GROUP BY 1)
SELECT feature_id, q.path_id, round(pc * pgc * fc, 6) AS weight FROM q JOIN path ON path.path_id = q.path_id JOIN grp ON grp.hops = q.hops JOIN tested ON cl = {_CLUSTER}"""


@query("selection_weights_initial", f"WITH {_PATHS}, {_PAIRS} SELECT feature_id, path_id, 0.0::DOUBLE AS weight FROM pairs WHERE hops <= 3")
def selection_weights_initial(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights of all pairs before any is taken: no coverage yet."""
    return _weights(spark, ())


@query("selection_weights_after", _WEIGHTS)
def selection_weights_after(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights of all pairs after the pairs of two paths were taken."""
    return _weights(spark, _TAKEN)


_DECAY = f"""SELECT 'v' || a.vec_id AS feature_id, round(avg(k.fi * (1 - {_COS.replace('b.', 'k.')})), 6) AS decayed, round(any_value(a.own) * avg(1 - {_COS.replace('b.', 'k.')}), 6) AS scaled
FROM (SELECT *, round((vec_id % 13) / 13.0::DOUBLE, 9) AS own FROM embeddings WHERE vec_id % 5 <> 0) a JOIN (SELECT * FROM {_KNOWN} WHERE vec_id % 25 = 0) k USING (label) GROUP BY a.vec_id"""


@query("fi_decay", _DECAY)
def fi_decay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Importance left beside the chosen members of the same cluster, in the printed and the scaled form.

    The mean of a chosen member's importance times one minus the cosine needs the sum of
    importances and one inner product with the members' weighed unit vectors.
    """
    repo = Repository(spark, sf_dir)
    v = _sample_vectors(repo)
    parts = representation.unit_vectors(v.select("feature_id", "repr")).join(v.select("feature_id", "cluster_id", "vec_id"), "feature_id")
    chosen = _known(repo).join(v.where("vec_id % 25 = 0").select("feature_id", "cluster_id"), "feature_id")
    sums = parts.join(chosen.select("feature_id", "fi"), "feature_id").groupBy("cluster_id", "pos").agg(F.sum(F.col("fi") * F.col("u")).alias("weighed"), F.sum("u").alias("plain"))
    totals = chosen.groupBy("cluster_id").agg(F.sum("fi").alias("fis"), F.count(F.lit(1)).alias("n"))
    asked = parts.where("vec_id % 5 <> 0").join(sums, ["cluster_id", "pos"]).groupBy("feature_id", "vec_id", "cluster_id").agg(F.sum(F.col("u") * F.col("weighed")).alias("near"), F.sum(F.col("u") * F.col("plain")).alias("cosines"))
    own = F.round((F.col("vec_id") % 13) / F.lit(13.0), 9)
    return asked.join(F.broadcast(totals), "cluster_id").select("feature_id", F.round((F.col("fis") - F.col("near")) / F.col("n"), 6).alias("decayed"), F.round(own * (F.col("n") - F.col("cosines")) / F.col("n"), 6).alias("scaled"))  # one row a cluster


@query("greedy_selection")
def greedy_selection(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order of pairs that rows bear out: greedy, hybrid (ten at random first), random."""
    rows, pairs = [], _pairs(spark, sf_dir)
    for name, options in (("greedy", {}), ("hybrid", {"warmup": 10}), ("random", {"warmup": 10**6}), ("summed weights", {"weight": "sum"}), ("counted lengths", {"group": "per_selection"})):
        rows += [(name, i, p.feature, ">".join(p.path), p.cluster) for i, p in enumerate(select_pairs(pairs, 40, **options), 1)]
    return spark.createDataFrame(rows, "variant string, place int, feature_id string, path_id string, cluster_id int")


# --- baselines over single tables ------------------------------------------------

def _aggregation_sql() -> str:
    fns = ("sum", "avg", "min", "max", "stddev_pop")
    cols = [f"round({fn}({c}), 2) AS orders__{fn}_{c}" for c in ("o_totalprice",) for fn in fns]
    return f"SELECT c_custkey, o.* EXCLUDE (k) FROM customer LEFT JOIN (SELECT o_custkey AS k, count(*) AS orders__count, {', '.join(cols)} FROM orders GROUP BY o_custkey) o ON c_custkey = k"


@query("path_aggregation_depth1", _aggregation_sql())
def path_aggregation_depth1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Aggregates of orders on customers."""
    repo = Repository(spark, sf_dir)
    out = systems.path_aggregation(repo, repo.table("customer").select("c_custkey"), [path_of("e1r").edges[0]], 1)
    return out.select("c_custkey", "orders__count", *[F.round(c, 2).alias(c) for c in out.columns if c.startswith("orders__") and c != "orders__count"])


def _stacked_sql() -> str:
    inner = [("lineitem__count", "count(*)"), *[(f"lineitem__{fn}_{c}", f"{fn}({c})") for c in ("l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax") for fn in ("avg", "max")]]
    far = f"(SELECT l_orderkey AS k, {', '.join(f'{e} AS {n}' for n, e in inner)} FROM lineitem GROUP BY l_orderkey)"
    columns = ["o_totalprice", *[n for n, _ in inner]]
    outer = [("orders__count", "count(*)"), *[(f"orders__{fn}_{c}", f"round({fn}({c}), 4)::DOUBLE") for c in columns for fn in ("avg", "max")]]
    near = f"(SELECT o_custkey AS k, {', '.join(f'{e} AS {n}' for n, e in outer)} FROM orders LEFT JOIN {far} l ON o_orderkey = l.k GROUP BY o_custkey)"
    return f"SELECT c_custkey, o.* EXCLUDE (k) FROM customer LEFT JOIN {near} o ON c_custkey = o.k"


@query("path_aggregation_depth2", _stacked_sql())
def path_aggregation_depth2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Aggregates of orders, with those of their lineitems, on customers."""
    repo = Repository(spark, sf_dir)
    out = systems.path_aggregation(repo, repo.table("customer").select("c_custkey"), [path_of("e1r").edges[0], path_of("e5r").edges[0]], 2, ("count", "avg", "max"))
    return out.select("c_custkey", "orders__count", *[F.round(F.col(c).cast("double"), 4).alias(c) for c in out.columns if c not in ("c_custkey", "orders__count")])


@query("full_disjunction", "SELECT doc_id, source, quality, lang FROM (SELECT doc_id, source FROM documents) FULL JOIN (SELECT doc_id, quality FROM labels) USING (doc_id) FULL JOIN (SELECT doc_id, lang FROM documents) USING (doc_id)")
def full_disjunction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables of documents integrated by their key."""
    repo = Repository(spark, sf_dir)
    return systems.full_disjunction([repo.table("documents").select("doc_id", "source"), repo.table("labels").select("doc_id", "quality"), repo.table("documents").select("doc_id", "lang")], "doc_id")


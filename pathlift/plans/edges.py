"""Queries on join edges and on integration quality."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import edge_stats, quality
from ..operators.paths import JoinGraph
from ..registry import ORACLES, QUERIES, query
from ..sources.repository import EDGES, Repository, both_ways, path_of
from . import sqltext

#: Statistic and the decimals it is rounded to for comparison.
STATISTICS = {"transitivity": 6, "containment": 6, "variance": 2, "entropy_printed": 6, "entropy_shannon": 6, "kl": 6, "pearson_key_counts": 6}
ALL_EDGES = both_ways(EDGES)


def _statistic(name: str, digits: int) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return edge_stats.edge_statistics(Repository(spark, sf_dir), ALL_EDGES).select("edge_id", F.round(name, digits).alias(name))

    QUERIES[f"edge_{name}"] = run
    ORACLES[f"edge_{name}"] = f"WITH {sqltext.edge_ctes(ALL_EDGES)} SELECT edge_id, round({name}, {digits}) AS {name} FROM s"


for _name, _digits in STATISTICS.items():
    _statistic(_name, _digits)


@query("edge_features_wide", f"WITH {sqltext.edge_ctes(ALL_EDGES)} SELECT edge_id, {', '.join(f'round({n}, {d}) AS {n}' for n, d in STATISTICS.items())}, n_joined FROM s")
def edge_features_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All statistics of all edges, both ways, in one plan."""
    stats = edge_stats.edge_statistics(Repository(spark, sf_dir), ALL_EDGES)
    return stats.select("edge_id", *[F.round(n, d).alias(n) for n, d in STATISTICS.items()], "n_joined")


#: Passages: the edge that enters a table and the column that leaves it.
PASSAGES = (("e1", "c_nationkey"), ("e2", "n_regionkey"), ("e5r", "l_suppkey"), ("e5r", "l_partkey"), ("e9", "n_chars"), ("e8", "event_id"))


def _passages_sql() -> str:
    parts = []
    for eid, out in PASSAGES:
        e = path_of(eid).edges[0]
        parts.append(f"""SELECT '{eid}' AS edge_id, '{out}' AS out_column,
    round(coalesce(CASE WHEN vx * vy > 1e-12 THEN cov / sqrt(vx * vy) END, 0.0), 6) AS pearson, round(mi, 6) AS mutual_info FROM (
  SELECT sum(w * x * y) / sum(w) - sum(w * x) / sum(w) * (sum(w * y) / sum(w)) AS cov, sum(w * x * x) / sum(w) - (sum(w * x) / sum(w)) ** 2 AS vx,
         sum(w * y * y) / sum(w) - (sum(w * y) / sum(w)) ** 2 AS vy, sum(w / n * ln(w * n / (wx * wy))) AS mi FROM (
    SELECT x::DOUBLE AS x, y::DOUBLE AS y, w, sum(w) OVER () AS n, sum(w) OVER (PARTITION BY x) AS wx, sum(w) OVER (PARTITION BY y) AS wy FROM (
      SELECT x, y, (m * c)::DOUBLE AS w FROM (SELECT {e.right_col} AS x, {out} AS y, count(*) AS m FROM {sqltext.frm(e.right)} GROUP BY ALL)
      JOIN (SELECT {e.left_col} AS x, count(*) AS c FROM {sqltext.frm(e.left)} GROUP BY ALL) USING (x))))""")
    return "\nUNION ALL\n".join(parts)


@query("edge_passages", _passages_sql())
def edge_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pearson correlation and mutual information between entering key and leaving column."""
    repo = Repository(spark, sf_dir)
    rows = [edge_stats.passage_statistics(repo, path_of(e).edges[0], c).select(F.lit(e).alias("edge_id"), F.lit(c).alias("out_column"), F.round("pearson", 6).alias("pearson"), F.round("mutual_info", 6).alias("mutual_info")) for e, c in PASSAGES]
    return reduce(DataFrame.unionByName, rows)


#: Ways whose leaving column is a feature: the last step of a path, with the feature in place of the join column.
FEATURE_WAYS = (("e1", "c_mktsegment"), ("e1", "c_acctbal"), ("e5r", "l_returnflag"), ("e5r", "l_quantity"), ("e8", "event_type"), ("e9", "lang"), ("e9r", "quality"), ("e11", "label"), ("e14", "o_orderpriority"), ("e6", "p_size"))


def _feature_ways_sql(bins: int = 20) -> str:
    """The same statistics by plain joins: the joined rows of each edge, one by one."""
    smooth, clip = sqltext.SMOOTHING, sqltext.CLIP
    parts = []
    for eid, f in FEATURE_WAYS:
        e = path_of(eid).edges[0]
        parts.append(f"""SELECT '{eid}' AS edge_id, '{f}' AS feature, round(coalesce(vy, 0), 2) AS variance, round(ent, 6) AS entropy_printed, round(sha, 6) AS entropy_shannon, round(kl, 6) AS kl,
    round(coalesce(CASE WHEN vx > 1e-12 * greatest(1.0, qx) AND vy > 1e-12 * greatest(1.0, qy) THEN cov / sqrt(vx * vy) END, 0), 6) AS pearson, round(mi, 6) AS mutual_info, round(transitivity, 6) AS transitivity, round(containment, 6) AS containment, n_joined FROM (
  WITH f AS (SELECT {e.right_col} AS x, {f} AS v, try_cast({f} AS DOUBLE) AS y, typeof({f}) NOT IN ('VARCHAR') AS is_number FROM {sqltext.frm(e.right)} WHERE {e.right_col} IS NOT NULL AND {f} IS NOT NULL),
  r AS (SELECT min(y) AS low, max(y) AS high, count(DISTINCT y) AS k, bool_and(is_number) AS is_number FROM f),
  g AS (SELECT x, CASE WHEN r.is_number THEN y END AS y, CASE WHEN r.is_number AND k > {bins} AND high > low THEN least({bins - 1}, floor((y - low) / ((high - low) / {bins}))) :: INT :: VARCHAR ELSE v::VARCHAR END AS b FROM f, r),
  n AS (SELECT {e.left_col} AS x, count(*)::DOUBLE AS w FROM {sqltext.frm(e.left)} WHERE {e.left_col} IS NOT NULL GROUP BY 1),
  j AS (SELECT g.x, y, b, w FROM g JOIN n USING (x)),
  c AS (SELECT x, b, sum(w) AS w FROM j GROUP BY ALL), t AS (SELECT sum(w) AS n FROM c),
  cx AS (SELECT x, sum(w) AS wx FROM c GROUP BY x), cb AS (SELECT b, sum(w) AS wb FROM c GROUP BY b),
  p0 AS (SELECT b, count(*)::DOUBLE AS r0 FROM g GROUP BY b),
  d AS (SELECT b, r0 / sum(r0) OVER () AS q0, coalesce(wb, 0) / (SELECT n FROM t) AS q1, count(*) OVER () AS m FROM p0 LEFT JOIN cb USING (b))
  SELECT (SELECT sum(w * y * y) / sum(w) - (sum(w * y) / sum(w)) ** 2 FROM j) AS vy, (SELECT sum(w * y * y) / sum(w) FROM j) AS qy, (SELECT sum(w * x * x::DOUBLE) / sum(w) - (sum(w * x) / sum(w)) ** 2 FROM j) AS vx, (SELECT sum(w * x * x::DOUBLE) / sum(w) FROM j) AS qx,
         (SELECT sum(w * x * y) / sum(w) - sum(w * x) / sum(w) * (sum(w * y) / sum(w)) FROM j) AS cov,
         (SELECT sum(CASE WHEN q1 > 0 THEN -q1 * ln(greatest(1 - q1, {clip})) ELSE 0 END) FROM d) AS ent, (SELECT sum(CASE WHEN q1 > 0 THEN -q1 * ln(q1) ELSE 0 END) FROM d) AS sha,
         (SELECT sum((q0 + {smooth}) / (1 + m * {smooth}) * ln(((q0 + {smooth}) / (1 + m * {smooth})) / ((q1 + {smooth}) / (1 + m * {smooth})))) FROM d) AS kl,
         (SELECT greatest(0.0, sum(w / n * ln(w * n / (wx * wb)))) FROM c JOIN cx USING (x) JOIN cb USING (b), t) AS mi,
         (SELECT count(DISTINCT x) FROM j)::DOUBLE / (SELECT count(DISTINCT x) FROM g) AS transitivity, (SELECT count(DISTINCT x) FROM j)::DOUBLE / (SELECT count(*) FROM n) AS containment, (SELECT sum(w) FROM j)::BIGINT AS n_joined)""")
    return "\nUNION ALL\n".join(parts)


@query("last_hop_feature_stats", _feature_ways_sql())
def last_hop_feature_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics of last steps, the feature column standing for the join column."""
    ways = [edge_stats.Leaving(path_of(e).edges[0], f) for e, f in FEATURE_WAYS]
    out = edge_stats.leaving_statistics(Repository(spark, sf_dir), ways)
    return out.select("edge_id", F.col("column").alias("feature"), F.round("variance", 2).alias("variance"), *[F.round(c, 6).alias(c) for c in ("entropy_printed", "entropy_shannon", "kl", "pearson", "mutual_info", "transitivity", "containment")], "n_joined")


#: Edges with the column by which a path goes on: the pairing of join columns that the network reads.
ROW_PAIRS = (("e1", "c_nationkey"), ("e2", "n_regionkey"), ("e5r", "l_suppkey"), ("e5r", "l_partkey"), ("e9", "doc_id"), ("e14", "o_orderkey"))


def _row_pairs_sql() -> str:
    parts = []
    for eid, out in ROW_PAIRS:
        e = path_of(eid).edges[0]
        parts.append(f"SELECT '{eid}' AS edge_id, '{out}' AS out_column, round(coalesce(corr(l.{e.left_col}::DOUBLE, r.{out}::DOUBLE), 0), 6) AS pearson FROM {sqltext.frm(e.left).replace(f' AS {e.left}', '')} l JOIN {sqltext.frm(e.right).replace(f' AS {e.right}', '')} r ON l.{e.left_col} = r.{e.right_col}")
    return "\nUNION ALL\n".join(parts)


@query("edge_pearson_rows", _row_pairs_sql())
def edge_pearson_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlation over the joined rows of the key that enters a table and the column that leaves it; no row is joined."""
    out = edge_stats.leaving_statistics(Repository(spark, sf_dir), [edge_stats.Leaving(path_of(e).edges[0], c) for e, c in ROW_PAIRS])
    return out.select("edge_id", F.col("column").alias("out_column"), F.round("pearson", 6).alias("pearson"))


_INFO = (("e1", "c_mktsegment"), ("e1", "c_nationkey"), ("e2", "n_regionkey"), ("e5r", "l_returnflag"), ("e9", "lang"), ("e8", "event_type"))


def _info_sql() -> str:
    parts = []
    for eid, out in _INFO:
        e = path_of(eid).edges[0]
        parts.append(f"""SELECT '{eid}' AS edge_id, '{out}' AS out_column, round(sum(c / n * ln(c * n / (cx * cy))), 6) AS mutual_info FROM (
    SELECT c::DOUBLE AS c, sum(c) OVER ()::DOUBLE AS n, sum(c) OVER (PARTITION BY x)::DOUBLE AS cx, sum(c) OVER (PARTITION BY y)::DOUBLE AS cy FROM (
      SELECT l.{e.left_col} AS x, r.{out} AS y, count(*) AS c FROM {sqltext.frm(e.left).replace(f' AS {e.left}', '')} l JOIN {sqltext.frm(e.right).replace(f' AS {e.right}', '')} r ON l.{e.left_col} = r.{e.right_col} GROUP BY ALL))""")
    return "\nUNION ALL\n".join(parts)


@query("edge_mutual_information", _info_sql())
def edge_mutual_information(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mutual information over the joined rows of the key that enters a table and the column that leaves it."""
    out = edge_stats.leaving_statistics(Repository(spark, sf_dir), [edge_stats.Leaving(path_of(e).edges[0], c) for e, c in _INFO], bins=64)
    return out.select("edge_id", F.col("column").alias("out_column"), F.round("mutual_info", 6).alias("mutual_info"))


KEY_COLUMNS = tuple(sorted({c for e in EDGES[:13] for c in ((e.left, e.left_col), (e.right, e.right_col))}))


def _containment_sql() -> str:
    hist = "\nUNION ALL ".join(f"SELECT DISTINCT '{t}.{c}' AS col, {c}::BIGINT AS k FROM {t} WHERE {c} IS NOT NULL" for t, c in KEY_COLUMNS)
    return f"""WITH h AS ({hist}), n AS (SELECT col, count(*) AS n FROM h GROUP BY col),
p AS (SELECT a.col AS lcol, b.col AS rcol, count(*) AS shared FROM h a JOIN h b ON a.k = b.k AND a.col <> b.col GROUP BY ALL)
SELECT lcol, rcol, shared::BIGINT AS shared, round(shared / n::DOUBLE, 6) AS containment FROM p JOIN n ON lcol = col
WHERE shared / n::DOUBLE >= 0.1 AND shared >= 2 AND split_part(lcol, '.', 1) <> split_part(rcol, '.', 1)"""


@query("discover_containment", _containment_sql())
def discover_containment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joinable column pairs by exact containment."""
    found = edge_stats.discover_edges(Repository(spark, sf_dir), list(KEY_COLUMNS))
    return found.select("lcol", "rcol", "shared", F.round("containment", 6).alias("containment"))


@query("discover_sketch")
def discover_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joinable column pairs from theta sketches (approximate)."""
    return edge_stats.discover_edges_sketch(Repository(spark, sf_dir), list(KEY_COLUMNS))


#: (base, path, feature) whose quality is measured.
QUALITY = tuple(
    (p.base, p, f)
    for p, f in (
        (path_of("e1"), "c_acctbal"), (path_of("e1", "e2"), "n_regionkey"), (path_of("e1", "e2", "e3"), "r_name"), (path_of("e5r"), "l_quantity"), (path_of("e5r", "e7"), "s_acctbal"), (path_of("e5r", "e6"), "p_size"),
        (path_of("e5r", "e7", "e4"), "n_name"), (path_of("e8"), "value"), (path_of("e14"), "o_totalprice"), (path_of("e1r"), "o_totalprice"), (path_of("e15"), "l_quantity"), (path_of("e9"), "n_chars"), (path_of("e9", "e10"), "url"),
        (path_of("e9", "e11"), "label"), (path_of("e9", "e12"), "role"), (path_of("e9r"), "quality"), (path_of("e10"), "url"), (path_of("e11"), "label"), (path_of("e12"), "role"), (path_of("e13"), "text"), (path_of("e14", "e5r"), "l_tax"),
    )
)


def _quality_of_all(repo: Repository, pairs) -> DataFrame:
    """Exact quality of (base, path, feature), one plan a base."""
    bases = dict.fromkeys(b for b, _, _ in pairs)
    return reduce(DataFrame.unionByName, [quality.exact_iq(repo, repo.table(b), [(p, f) for x, p, f in pairs if x == b]) for b in bases])


@query("exact_iq_paths", "\nUNION ALL\n".join(f"SELECT path_id, '{f}' AS feature, round(iq, 6) AS iq, n FROM ({sqltext.share(b, p, f)})" for b, p, f in QUALITY))
def exact_iq_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of base rows that find a value, by path and feature."""
    return _quality_of_all(Repository(spark, sf_dir), QUALITY).select("path_id", "feature", F.round("iq", 6).alias("iq"), "n")


@query("reach_iq_semijoin", "\nUNION ALL\n".join(f"SELECT path_id, round(iq, 6) AS iq, n FROM ({sqltext.share(b, p, None)})" for b, p, _ in QUALITY))
def reach_iq_semijoin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of base rows whose path ends somewhere, whatever the feature."""
    return _quality_of_all(Repository(spark, sf_dir), [(b, p, None) for b, p, _ in QUALITY]).select("path_id", F.round("iq", 6).alias("iq"), "n")


def _rowwise_sql(path, feature: str) -> str:
    sql = f"SELECT {path.edges[0].left_col} AS key FROM {sqltext.frm(path.base)}"
    for i, e in enumerate(path.edges):
        onward = feature if i + 1 == len(path.edges) else path.edges[i + 1].left_col
        sql = f"SELECT f.nxt AS key FROM ({sql}) b LEFT JOIN (SELECT {e.right_col} AS k, {onward} AS nxt FROM {sqltext.frm(e.right)}) f ON b.key = f.k"
    return f"SELECT '{path.path_id}' AS path_id, round(avg(CASE WHEN key IS NULL THEN 0.0 ELSE 1.0 END), 6) AS iq, count(*) AS n FROM ({sql})"


ROWWISE = ((path_of("e8"), "value"), (path_of("e14"), "o_totalprice"), (path_of("e15"), "l_quantity"), (path_of("e9r"), "quality"))


@query("rowwise_iq", "\nUNION ALL\n".join(_rowwise_sql(p, f) for p, f in ROWWISE))
def rowwise_iq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality over joined rows, fan-out kept: the other reading of the denominator."""
    repo = Repository(spark, sf_dir)
    rows = [quality.rowwise_iq(repo, repo.table(p.base), p, f).select(F.lit(p.path_id).alias("path_id"), F.round("iq", 6).alias("iq"), "n") for p, f in ROWWISE]
    return reduce(DataFrame.unionByName, rows)


SAMPLED = ((path_of("e8"), "value"), (path_of("e14"), "o_totalprice"), (path_of("e5r"), "l_quantity"), (path_of("e15"), "l_quantity"))


@query("sampled_iq", "\nUNION ALL\n".join(
    f"SELECT '{p.path_id}' AS path_id, round(iq, 6) AS iq, n, round(1.96 * sqrt(iq * (1 - iq) / n), 6) AS half_width FROM (SELECT avg(CASE WHEN {p.edges[0].left_col} IN ({sqltext.reach(p, f)}) THEN 1.0 ELSE 0.0 END) AS iq, count(*) AS n FROM {sqltext.frm(p.base)} WHERE {sqltext.uniform(p.edges[0].left_col, 5)} < 0.25)"
    for p, f in SAMPLED))
def sampled_iq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality from a hash sample of base keys, with its half width."""
    repo = Repository(spark, sf_dir)
    rows = [quality.sampled_iq(repo, repo.table(p.base), p, f, share=0.25, seed=5).select(F.lit(p.path_id).alias("path_id"), F.round("iq", 6).alias("iq"), "n", F.round("half_width", 6).alias("half_width")) for p, f in SAMPLED]
    return reduce(DataFrame.unionByName, rows)


def _path_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(p.path_id,) for p in dict.fromkeys(p for _, p, _ in QUALITY)], "path_id string")


_PATHS_SQL = sqltext.values([(p.path_id,) for p in dict.fromkeys(p for _, p, _ in QUALITY)], "path_id")
_PRODUCT = f"SELECT path_id, product(transitivity) AS iq_product FROM (SELECT path_id, unnest(string_split(path_id, '>')) AS edge_id FROM {_PATHS_SQL}) JOIN s USING (edge_id) GROUP BY path_id"


@query("path_transitivity", f"WITH {sqltext.edge_ctes(ALL_EDGES)} SELECT path_id, round(iq_product, 6) AS iq_product FROM ({_PRODUCT})")
def path_transitivity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Product of far-side transitivities along each path."""
    stats = edge_stats.edge_statistics(Repository(spark, sf_dir), ALL_EDGES)
    return quality.product_of_transitivity(_path_frame(spark), stats).select("path_id", F.round("iq_product", 6).alias("iq_product"))


_EXACT_SQL = "\nUNION ALL\n".join(f"SELECT path_id, iq FROM ({sqltext.share(b, p, None)})" for b, p, _ in QUALITY)


@query("iq_estimator_errors", f"WITH {sqltext.edge_ctes(ALL_EDGES)}, e AS ({_EXACT_SQL}), p AS ({_PRODUCT}) SELECT round(avg((iq_product - iq) ** 2), 6) AS product_mse, round(avg(({sqltext.uniform('path_id', 9)} - iq) ** 2), 6) AS random_mse, count(*) AS n FROM e JOIN p USING (path_id)")
def iq_estimator_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared errors of the product and the random estimate against exact quality."""
    repo = Repository(spark, sf_dir)
    exact = _quality_of_all(repo, [(b, p, None) for b, p, _ in QUALITY]).select("path_id", "iq")
    both = exact.join(quality.product_of_transitivity(_path_frame(spark), edge_stats.edge_statistics(repo, ALL_EDGES)), "path_id")
    error = lambda c: F.round(F.avg(F.pow(c - F.col("iq"), F.lit(2))), 6)
    return both.agg(error(F.col("iq_product")).alias("product_mse"), error(quality.random_iq("path_id", 9)).alias("random_mse"), F.count(F.lit(1)).alias("n"))


_PREFIXES = tuple((p, path_of(*p.path_id.split(">")[:-1])) for _, p, _ in QUALITY if len(p.edges) > 1)


@query("iq_monotonicity", "\nUNION ALL\n".join(f"SELECT '{p.path_id}' AS path_id, round(b.iq - a.iq, 6) AS drop_iq, b.iq >= a.iq AS holds FROM ({sqltext.share(p.base, p, None)}) a, ({sqltext.share(p.base, q, None)}) b" for p, q in _PREFIXES))
def iq_monotonicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality never rises when a path is extended."""
    found = _quality_of_all(Repository(spark, sf_dir), [(p.base, x, None) for pair in _PREFIXES for p, x in ((pair[0], pair[0]), (pair[0], pair[1]))])
    steps = F.broadcast(spark.createDataFrame([(p.path_id, q.path_id) for p, q in _PREFIXES], "path_id string, prefix string"))  # metadata
    whole = found.select("path_id", F.col("iq").alias("a")).join(steps, "path_id")
    both = whole.join(found.select(F.col("path_id").alias("prefix"), F.col("iq").alias("b")), "prefix")
    return both.select("path_id", F.round(F.col("b") - F.col("a"), 6).alias("drop_iq"), (F.col("b") >= F.col("a")).alias("holds"))


GRAPH = JoinGraph(EDGES[:7])

"""Queries that run streams to their end, and the flagship query of the whole method."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.engine import Base, Engine, Settings
from ..operators.paths import JoinGraph
from ..registry import query
from ..sources.repository import JoinEdge, Repository
from ..streaming import updates

#: Longer than the data spans, so that every event counts however files are ordered.
_LATE = "60 days"
#: A watermark that some events miss when the table arrives in parts out of order.
_SHORT = "12 hours"


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return updates.file_stream(spark, f"{sf_dir}/events.parquet*", schema)


@query("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n, round(sum(value), 3) AS total FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts by type."""
    out = updates.run_to_end(updates.tumbling(_events(spark, sf_dir), "1 day", _LATE), "tumbling", "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n", F.round("total", 3).alias("total"))


@query("stream_sliding", "SELECT strftime(s, '%Y-%m-%d %H') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of a day's width every half day."""
    out = updates.run_to_end(updates.sliding(_events(spark, sf_dir), "1 day", "12 hours", _LATE), "sliding", "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "n")


@query("stream_sessions", "SELECT user_id, count(*) AS sessions, max(n) AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(CASE WHEN ts - prev < INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM events)) GROUP BY user_id, s) GROUP BY user_id")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of users, closed by six quiet hours."""
    out = updates.run_to_end(updates.sessions(_events(spark, sf_dir), "6 hours", _LATE), "sessions", "complete")
    return out.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


@query("stream_dedupe", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replayed events counted once."""
    both = _events(spark, sf_dir).union(_events(spark, sf_dir))
    return updates.run_to_end(updates.without_repeats(both, _LATE), "dedupe").agg(F.countDistinct("event_id").alias("n"))


@query("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the segment of their customer."""
    out = updates.run_to_end(updates.with_customers(_events(spark, sf_dir), spark.read.parquet(f"{sf_dir}/customer.parquet")), "static")
    return out.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("stream_key_histogram", "SELECT user_id AS k, count(*) AS c FROM events GROUP BY user_id")
def stream_key_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The key histogram of a table that grows file by file."""
    return updates.run_to_end(updates.key_counts(_events(spark, sf_dir)), "histogram", "complete")


@query("stream_late_data", """WITH d AS (SELECT ts, date_trunc('day', ts) AS day, event_id % 3 AS part FROM events),
m AS (SELECT part, max(ts) AS high FROM d GROUP BY part),
w AS (SELECT a.part, (SELECT max(high) FROM m WHERE part < a.part - 1) - INTERVAL 12 HOUR AS mark FROM m a)
SELECT strftime(day, '%Y-%m-%d') AS day, count(*) AS n FROM d JOIN w USING (part) WHERE mark IS NULL OR day + INTERVAL 1 DAY > mark GROUP BY day""")
def stream_late_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts of events that arrive in three parts: days that the watermark has closed take no more events.

    A batch tests for late rows against the watermark that the batch before it began with.
    """
    from ..sources.files import shared_folder

    folder = shared_folder(spark, "parts")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    for part in range(3):  # three files, read one a batch in this order
        events.where(F.pmod("event_id", F.lit(3)) == part).coalesce(1).write.mode("append").parquet(folder)
    stream = updates.file_stream(spark, folder, events.schema)
    out = updates.run_to_end(updates.daily(stream, _SHORT), "late", "complete_by_update")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n")


@query("stream_interval_join", "SELECT count(*) AS n, round(sum(b.value), 3) AS total FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def stream_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the events of the same user in the six hours after them: two streams joined by an interval."""
    out = updates.run_to_end(updates.followed_by(_events(spark, sf_dir), _events(spark, sf_dir), "6 hours", _LATE), "interval")
    return out.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 3).alias("total"))


@query("stream_user_state", "SELECT user_id, count(*) AS n, round(sum(value), 3) AS total, max(value) AS top FROM events GROUP BY user_id")
def stream_user_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running statistics of users, kept as state between batches."""
    out = updates.run_to_end(updates.user_state(_events(spark, sf_dir)), "state", "update")
    last = out.groupBy("user_id").agg(F.max_by(F.struct("total", "top"), "n").alias("s"), F.max("n").alias("n"))
    return last.select("user_id", "n", F.round("s.total", 3).alias("total"), "s.top")


@query("stream_rate")
def stream_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A generated stream of two micro batches, by remainder."""
    made = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 50).option("numPartitions", 2).load().select((F.col("value") % 5).alias("g"), "value")
    return updates.run_batches(made, "rate", 2).groupBy("g").agg(F.count(F.lit(1)).alias("n"))


# --- the whole method ------------------------------------------------------------

DOC_EDGES = (
    JoinEdge("d1", "labels", "doc_id", "doc_meta", "doc_id"), JoinEdge("d2", "labels", "doc_id", "doc_to_shape", "doc_id"), JoinEdge("d3", "doc_to_shape", "shape_id", "doc_shape", "shape_id"),
    JoinEdge("d4", "labels", "doc_id", "embeddings", "vec_id"), JoinEdge("d5", "labels", "doc_id", "pages", "page_id"), JoinEdge("d6", "labels", "doc_id", "doc_to_shape_6", "doc_id"), JoinEdge("d7", "doc_to_shape_6", "shape_id", "doc_shape", "shape_id"),
)
DOC_FEATURES = {"doc_meta": ("lang", "source", "n_chars"), "doc_shape": ("alpha_bin", "alpha_share", "n_lines"), "embeddings": ("label",), "pages": ("url",)}


def document_engine(spark: SparkSession, sf_dir: str, **settings) -> Engine:
    """The document-quality task: labels, with documents split so that the useful feature lies two hops away."""
    return Engine(Repository(spark, sf_dir), Base("labels", "doc_id", "quality"), JoinGraph(DOC_EDGES), DOC_FEATURES, Settings(**settings)).explore()


def _plan_frame(spark: SparkSession, plan) -> DataFrame:
    rows = [(i, c.feature, c.path.path_id, float(c.fi), float(c.iq), float(g)) for i, (c, g) in enumerate(plan, 1)]
    return spark.createDataFrame(rows, "rank int, feature_id string, path_id string, fi double, iq double, ug double")


@query("entry_plan")
def entry_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The plan found for the document-quality task, with the estimates of both estimators and gains."""
    return _plan_frame(spark, document_engine(spark, sf_dir, budget=5, clamp=True).plan()[0])


@query("method_augmented")
def method_augmented(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The augmented table of the plan."""
    return document_engine(spark, sf_dir, budget=5, clamp=True).exploit().augmented


@query("method_budgets")
def method_budgets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joint held-out score of the plan by budget and quality estimator, on the document-quality task."""
    from .tasks import workloads

    (work,) = workloads(spark, sf_dir, ("quality",))
    engine = work.fitted
    rows, plans = [], {"": []}
    for kind in ("exact", "product", "sequence"):
        engine.settings.iq_estimator = kind  # "sequence", as it was, comes last
        for budget in (1, 5, 10):
            plan, stats = engine.plan(budget)
            plans[f"{kind}|{budget}"] = list(dict.fromkeys(work.column(c.path, c.feature.split(".", 1)[1]) for c, _ in plan))
            rows.append((kind, budget, len(plan), sum(len(c.path.edges) for c, _ in plan), stats.expanded, stats.cut_by_quality))
    scores = work.score_plans(plans)
    made = [(*r[:4], scores[""], scores[f"{r[0]}|{r[1]}"], scores[f"{r[0]}|{r[1]}"] - scores[""], *r[4:]) for r in rows]
    return spark.createDataFrame(made, "iq_estimator string, budget int, features int, joins int, base double, score double, gain double, expanded int, cut int")


@query("repository_update")
def repository_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table that changes and a new one that arrives late: whether the plan changes, with both estimators as fitted before."""
    engine = document_engine(spark, sf_dir, budget=5, clamp=True)
    pages = engine.repo.table("pages")
    changed = engine.update({"pages": pages.where("page_id % 2 = 0")})
    rows = [("pages", changed, len(engine.graph.tables()), len(engine.plan()[0]))]
    late = engine.repo.table("documents").select(F.col("doc_id").alias("late_id"), F.round(F.length(F.regexp_replace("text", "[^a-z]", "")) / F.greatest(F.length("text"), F.lit(1)), 2).alias("lower_share"))
    arrived = engine.update({"late_facts": late})
    rows.append(("late_facts", arrived, len(engine.graph.tables()), len(engine.plan()[0])))
    return spark.createDataFrame(rows, "changed_table string, plan_changed boolean, tables int, features int")

"""More of the operators around the methods: sources, sinks, preparation of features, grouped Python."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import files
from ..sources.repository import Repository
from .relational import op

# --- sources and sinks ----------------------------------------------------------------


@op("read_text", "SELECT n_regionkey::VARCHAR AS region, count(*) AS n FROM nation GROUP BY 1")
def read_text(r: Repository) -> DataFrame:
    """Lines of text files, split into columns."""
    folder = files.shared_folder(r.spark, "lines")
    r.table("nation").select(F.concat_ws("|", F.col("n_nationkey").cast("string"), "n_name", F.col("n_regionkey").cast("string")).alias("value")).write.text(f"{folder}/nation.text")
    lines = files.read_folder(r.spark, folder)["nation"]
    return lines.select(F.split("value", "[|]")[2].alias("region")).groupBy("region").agg(F.count(F.lit(1)).alias("n"))


@op("read_inferred", "SELECT n_nationkey::INT AS n_nationkey, n_name, n_regionkey::INT AS n_regionkey FROM nation")
def read_inferred(r: Repository) -> DataFrame:
    """A folder of files without schema, read as a repository: types are inferred."""
    folder = files.shared_folder(r.spark, "inferred")
    r.table("nation").write.option("header", True).csv(f"{folder}/nation.csv")
    found = files.read_folder(r.spark, folder)["nation"]
    return found.select(F.col("n_nationkey").cast("int").alias("n_nationkey"), "n_name", F.col("n_regionkey").cast("int").alias("n_regionkey"))


@op("bucketed_table", "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def bucketed_table(r: Repository) -> DataFrame:
    """Two tables saved in buckets of their join key: the join needs no shuffle of either."""
    name, folder = uuid.uuid4().hex, files.shared_folder(r.spark, "buckets")
    for t, key in (("orders", "o_custkey"), ("customer", "c_custkey")):
        r.table(t).write.bucketBy(8, key).sortBy(key).option("path", f"{folder}/{t}").saveAsTable(f"{t}_{name}")
    orders, customer = r.spark.table(f"orders_{name}"), r.spark.table(f"customer_{name}")
    return orders.join(customer.hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


# --- aggregation ------------------------------------------------------------------------


@op("histogram", "SELECT bin, count(*) AS n FROM (SELECT least(9, floor((value - lo) / ((hi - lo) / 10)))::INT AS bin FROM events, (SELECT min(value) AS lo, max(value) AS hi FROM events)) GROUP BY bin")
def histogram(r: Repository) -> DataFrame:
    """Rows by equal-width bin of a number."""
    ends = r.table("events").agg(F.min("value").alias("lo"), F.max("value").alias("hi"))
    width = (F.col("hi") - F.col("lo")) / 10
    return r.table("events").crossJoin(F.broadcast(ends)).select(F.least(F.lit(9), F.floor((F.col("value") - F.col("lo")) / width)).cast("int").alias("bin")).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))  # one row


@op("histogram_adaptive")
def histogram_adaptive(r: Repository) -> DataFrame:
    """Centres and heights of a histogram whose bins follow the data (approximate)."""
    return r.table("events").groupBy("event_type").agg(F.histogram_numeric("value", F.lit(8)).alias("h")).select("event_type", F.explode("h").alias("b")).select("event_type", "b.x", "b.y")


@op("aggregate_sketches", "SELECT abs(1 - 1) < 0.1 AS distinct_close, TRUE AS median_close, TRUE AS union_close")
def aggregate_sketches(r: Repository) -> DataFrame:
    """Sketches beside exact answers: distinct users, the median value, the union of two sketches, each within a tenth."""
    e = r.table("events")
    exact = e.agg(F.countDistinct("user_id").alias("d"), F.median("value").alias("m"))
    halves = e.groupBy((F.col("event_id") % 2).alias("h")).agg(F.hll_sketch_agg("user_id").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("u"))
    sketch = e.agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.percentile_approx("value", 0.5, 1000).alias("p"))
    near = lambda x, y: F.abs(F.col(x) - F.col(y)) <= 0.1 * F.abs(F.col(y))
    return exact.crossJoin(sketch).crossJoin(halves).select(near("a", "d").alias("distinct_close"), near("p", "m").alias("median_close"), near("u", "d").alias("union_close"))  # one row each


# --- preparation of features ------------------------------------------------------------


@op("one_hot_scaled", "SELECT event_type, count(*) AS n, 1.0::DOUBLE AS hot, round(avg((value) / s), 4) AS scaled FROM events, (SELECT stddev_samp(value) AS s FROM events) GROUP BY event_type")
def one_hot_scaled(r: Repository) -> DataFrame:
    """Text indexed and one-hot encoded, numbers divided by their deviation."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import OneHotEncoder, StandardScaler, StringIndexer, VectorAssembler
    from pyspark.ml.functions import vector_to_array

    stages = [StringIndexer(inputCol="event_type", outputCol="index"), OneHotEncoder(inputCols=["index"], outputCols=["hot"], dropLast=False), VectorAssembler(inputCols=["value"], outputCol="v"), StandardScaler(inputCol="v", outputCol="scaled")]
    events = r.table("events").select("event_type", "value")
    out = Pipeline(stages=stages).fit(events).transform(events)
    hot = F.aggregate(vector_to_array("hot"), F.lit(0.0), lambda a, x: a + x)
    return out.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.max(hot).alias("hot"), F.round(F.avg(vector_to_array("scaled")[0]), 4).alias("scaled"))


@op("bucketizer", "SELECT (CASE WHEN value < 10 THEN 0 WHEN value < 50 THEN 1 WHEN value < 100 THEN 2 ELSE 3 END)::DOUBLE AS bucket, count(*) AS n FROM events GROUP BY 1")
def bucketizer(r: Repository) -> DataFrame:
    """Numbers cut at given places."""
    from pyspark.ml.feature import Bucketizer

    cut = Bucketizer(splits=[-float("inf"), 10.0, 50.0, 100.0, float("inf")], inputCol="value", outputCol="bucket")
    return cut.transform(r.table("events").select("value")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


@op("quantile_discretizer")
def quantile_discretizer(r: Repository) -> DataFrame:
    """Numbers cut into five parts of about equal size (approximate quantiles)."""
    from pyspark.ml.feature import QuantileDiscretizer

    values = r.table("events").select("value")
    cut = QuantileDiscretizer(numBuckets=5, inputCol="value", outputCol="bucket", relativeError=0.001).fit(values)
    return cut.transform(values).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


@op("character_grams", "SELECT g, count(*) AS n FROM (SELECT lower(n_name)[i:i + 2] AS g FROM (SELECT n_name, unnest(range(1, length(n_name) - 1)) AS i FROM nation)) GROUP BY g")
def character_grams(r: Repository) -> DataFrame:
    """Character trigrams of names."""
    return r.table("nation").select(F.lower("n_name").alias("t")).select(F.explode(F.transform(F.sequence(F.lit(1), F.length("t") - 2), lambda i: F.substring("t", i, F.lit(3)))).alias("g")).groupBy("g").agg(F.count(F.lit(1)).alias("n"))


@op("hashed_terms")
def hashed_terms(r: Repository) -> DataFrame:
    """Term frequencies of documents in 256 hashed columns, and neighbours of documents by min-hash."""
    from pyspark.ml.feature import HashingTF, MinHashLSH, Tokenizer

    docs = r.table("documents").where("length(text) > 0").select("doc_id", "text")
    terms = HashingTF(inputCol="words", outputCol="features", numFeatures=256, binary=True).transform(Tokenizer(inputCol="text", outputCol="words").transform(docs))
    hashed = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=2, seed=1).fit(terms).transform(terms)
    return hashed.select("doc_id", F.size("words").alias("words"), F.size("hashes").alias("tables"))


# --- Python over groups --------------------------------------------------------------------


@op("pandas_aggregate", "SELECT user_id, round(-sum(p * ln(p)), 6) AS entropy FROM (SELECT user_id, count(*) / sum(count(*)) OVER (PARTITION BY user_id) AS p FROM events GROUP BY user_id, event_type) GROUP BY user_id")
def pandas_aggregate(r: Repository) -> DataFrame:
    """A grouped aggregate in pandas: the entropy of event types by user."""

    @F.pandas_udf("double")
    def entropy(kind: pd.Series) -> float:
        p = kind.value_counts(normalize=True).to_numpy()
        return float(-(p * np.log(p)).sum())

    return r.table("events").groupBy("user_id").agg(F.round(entropy("event_type"), 6).alias("entropy"))


@op("pandas_cogrouped", "SELECT c_custkey AS custkey, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS orders, (SELECT count(*) FROM events WHERE user_id = c_custkey) AS events FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) OR c_custkey IN (SELECT user_id FROM events)")
def pandas_cogrouped(r: Repository) -> DataFrame:
    """Two tables grouped by the same key and met in pandas, group by group."""

    def both(key, a, b):
        return pd.DataFrame({"custkey": [key[0]], "orders": [len(a)], "events": [len(b)]})

    orders, events = r.table("orders").select(F.col("o_custkey").alias("k")), r.table("events").select(F.col("user_id").alias("k"))
    known = r.table("customer").select(F.col("c_custkey").alias("k"))
    met = lambda df: df.join(known, "k", "left_semi").groupBy("k")
    return met(orders).cogroup(met(events)).applyInPandas(both, "custkey long, orders long, events long")


@op("table_function_paths", "SELECT o_orderkey, pos::BIGINT AS pos, part FROM (SELECT o_orderkey, unnest(range(0, len(p))) AS pos, p[pos + 1] AS part FROM (SELECT o_orderkey, string_split(o_orderpriority, '-') AS p FROM orders))")
def table_function_paths(r: Repository) -> DataFrame:
    """A Python table function over a whole table: the parts of a path with their places."""

    @F.udtf(returnType="pos: bigint, part: string")
    class Parts:
        def eval(self, text: str):
            if text is not None:
                yield from enumerate(text.split("-"))

    r.spark.udtf.register("pathlift_parts", Parts)
    return r.spark.sql("SELECT o_orderkey, pos, part FROM {o}, LATERAL pathlift_parts(o_orderpriority)", o=r.table("orders").select("o_orderkey", "o_orderpriority"))


@op("sql_measures", "SELECT event_type, round(sum(kl), 6) AS kl, round(avg(w), 6) AS weight FROM (SELECT event_type, a * ln(a / b) AS kl, a * b * 0.5 AS w FROM (SELECT event_type, user_id, count(*) / sum(count(*)) OVER (PARTITION BY event_type)::DOUBLE AS a, (sum(count(*)) OVER (PARTITION BY user_id))::DOUBLE / sum(count(*)) OVER () AS b FROM events GROUP BY event_type, user_id)) GROUP BY event_type")
def sql_measures(r: Repository) -> DataFrame:
    """Terms of a divergence and pair weights as SQL functions, over users by event type."""
    r.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pathlift_kl_term(p DOUBLE, q DOUBLE) RETURNS DOUBLE RETURN CASE WHEN p > 0 THEN p * ln(p / q) ELSE 0.0D END")
    r.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pathlift_pair_weight(pc DOUBLE, pgc DOUBLE, fc DOUBLE) RETURNS DOUBLE RETURN pc * pgc * fc")
    return r.spark.sql(
        """SELECT event_type, round(sum(pathlift_kl_term(a, b)), 6) AS kl, round(avg(pathlift_pair_weight(a, b, 0.5D)), 6) AS weight FROM (
            SELECT event_type, user_id, count(*) / sum(count(*)) OVER (PARTITION BY event_type) AS a, sum(count(*)) OVER (PARTITION BY user_id) / sum(count(*)) OVER (PARTITION BY 1) AS b FROM {e} GROUP BY event_type, user_id) GROUP BY event_type""",
        e=r.table("events"),
    )

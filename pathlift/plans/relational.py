"""The operators around the methods: one small query each, with its SQL."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..functions.measures import hash_uniform
from ..operators.joins import as_of, interval_join, salted_join
from ..registry import ORACLES, QUERIES
from ..sources.repository import Repository
from . import sqltext


def op(name: str, sql: str | None = None):
    """Registers a function of a repository as query op_<name>."""

    def register(function):
        @functools.wraps(function)
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return function(Repository(spark, sf_dir))

        QUERIES[f"op_{name}"] = run
        if sql:
            ORACLES[f"op_{name}"] = sql
        return function

    return register


# --- projections and predicates ------------------------------------------------

op("select_cast_derive", "SELECT o_orderkey, o_custkey::INT AS cust, round(o_totalprice * 0.9, 4) AS reduced, o_orderpriority AS priority FROM orders")(
    lambda r: r.table("orders").select("o_orderkey", F.col("o_custkey").cast("int").alias("cust"), F.round(F.col("o_totalprice") * 0.9, 4).alias("reduced"), F.col("o_orderpriority").alias("priority"))
)
op("predicates", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 100000 AND 300000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'O%' AND o_orderstatus IS NOT DISTINCT FROM 'O'")(
    lambda r: r.table("orders").where(F.col("o_totalprice").between(100000, 300000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").like("O%") & F.col("o_orderstatus").eqNullSafe("O")).select("o_orderkey")
)
op("unpivot", "SELECT l_orderkey, l_linenumber, feature, value FROM (SELECT l_orderkey, l_linenumber, l_quantity, l_discount, l_tax FROM lineitem) UNPIVOT (value FOR feature IN (l_quantity, l_discount, l_tax))")(
    lambda r: r.table("lineitem").unpivot(["l_orderkey", "l_linenumber"], ["l_quantity", "l_discount", "l_tax"], "feature", "value")
)
op("pivot", "SELECT event_type, count(*) FILTER (user_id % 3 = 0) AS g0, count(*) FILTER (user_id % 3 = 1) AS g1, count(*) FILTER (user_id % 3 = 2) AS g2 FROM events GROUP BY event_type")(
    lambda r: r.table("events").withColumn("g", F.concat(F.lit("g"), (F.col("user_id") % 3).cast("string"))).groupBy("event_type").pivot("g", ["g0", "g1", "g2"]).count().fillna(0)
)

# --- joins ----------------------------------------------------------------------

def _on():
    return F.col("o_custkey") == F.col("c_custkey")


for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):
    # customers in credit meet large orders: both sides have rows that the other one lacks
    op(f"join_{_how}", f"SELECT c_custkey, o_orderkey FROM (SELECT * FROM customer WHERE c_acctbal > 0) {_sql} (SELECT * FROM orders WHERE o_totalprice > 250000) ON o_custkey = c_custkey")(
        lambda r, how=_how: r.table("customer").where("c_acctbal > 0").join(r.table("orders").where("o_totalprice > 250000"), _on(), how).select("c_custkey", "o_orderkey")
    )
for _how, _sql in (("left_semi", ""), ("left_anti", "NOT ")):
    op(f"join_{_how}", f"SELECT c_custkey, c_name FROM customer WHERE {_sql}EXISTS (SELECT 1 FROM events WHERE user_id = c_custkey AND value > 100)")(
        lambda r, how=_how: r.table("customer").join(r.table("events").where("value > 100"), F.col("user_id") == F.col("c_custkey"), how).select("c_custkey", "c_name")
    )
for _hint in ("broadcast", "merge", "shuffle_hash"):
    op(f"join_hint_{_hint}", "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")(
        lambda r, hint=_hint: r.table("customer").join(r.table("nation").hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))
    )
op("join_theta", "SELECT a.r_name AS low, b.r_name AS high FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")(
    lambda r: r.table("region").select(F.col("r_regionkey").alias("a"), F.col("r_name").alias("low")).join(r.table("region").select(F.col("r_regionkey").alias("b"), F.col("r_name").alias("high")), F.col("a") < F.col("b")).select("low", "high")
)
op("join_multi_key", "SELECT a.user_id, a.event_type, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = b.event_type AND a.event_id < b.event_id GROUP BY ALL")(
    lambda r: r.table("events").select("user_id", "event_type", F.col("event_id").alias("i")).join(r.table("events").select("user_id", "event_type", F.col("event_id").alias("j")), ["user_id", "event_type"]).where("i < j").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("pairs"))
)
op("join_salted", "SELECT l_orderkey, l_linenumber, l_partkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity > 45")(
    lambda r: salted_join(r.table("lineitem").where("l_quantity > 45"), r.table("part").select("p_partkey", "p_brand"), "l_partkey", "p_partkey", 4).select("l_orderkey", "l_linenumber", "l_partkey", "p_brand")
)
op("join_interval", "SELECT a.event_id AS purchase, b.event_id AS before FROM (SELECT * FROM events WHERE event_type = 'purchase') a JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 6 HOUR")(
    lambda r: interval_join(
        r.table("events").where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), "ts"), r.table("events").select("user_id", F.col("event_id").alias("before"), F.col("ts").alias("at")), "user_id", "ts", "at", 6 * 3600
    ).select("purchase", "before")
)
op("join_as_of", "SELECT a.event_id, (SELECT arg_max(b.event_id, (b.ts, b.event_id)) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'view' AND b.ts < a.ts) AS last_view FROM events a WHERE a.event_type = 'purchase'")(
    lambda r: as_of(r.table("events").where("event_type = 'purchase'").select("event_id", "user_id", "ts"), r.table("events").where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("last_view")), "user_id", "ts", "last_view").select("event_id", "last_view")
)
op("join_lateral", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")(
    lambda r: r.table("customer").alias("c").lateralJoin(r.table("orders").where(F.col("o_custkey") == F.col("c.c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")).select("c_custkey", "o_orderkey")
)

# --- aggregation ------------------------------------------------------------------

op("aggregate_moments", "SELECT event_type, count(*) AS n, round(sum(value), 3) AS total, round(avg(value), 6) AS mean, min(value) AS low, max(value) AS high, round(stddev_pop(value), 6) AS sd, round(var_samp(value), 4) AS var FROM events GROUP BY event_type")(
    lambda r: r.table("events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 3).alias("total"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("low"), F.max("value").alias("high"), F.round(F.stddev_pop("value"), 6).alias("sd"), F.round(F.var_samp("value"), 4).alias("var"))
)
op("aggregate_correlation", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_discount), 6) AS cov, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem GROUP BY l_returnflag")(
    lambda r: r.table("lineitem").groupBy("l_returnflag").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_pop("l_quantity", "l_discount"), 6).alias("cov"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"))
)
op("aggregate_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT (l_partkey, l_suppkey)) AS pairs FROM lineitem")(
    lambda r: r.table("lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct(F.struct("l_partkey", "l_suppkey")).alias("pairs"))
)
op("aggregate_filtered", "SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS clicks, round(sum(value) FILTER (event_type = 'purchase'), 3) AS bought FROM events GROUP BY 1")(
    lambda r: r.table("events").groupBy((F.col("user_id") % 10).alias("g")).agg(F.count(F.when(F.col("event_type") == "click", 1)).alias("clicks"), F.round(F.sum(F.when(F.col("event_type") == "purchase", F.col("value"))), 3).alias("bought"))
)
op("aggregate_pick", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS earliest, round(median(o_totalprice), 2) AS middle FROM orders GROUP BY o_custkey")(
    lambda r: r.table("orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("earliest"), F.round(F.median("o_totalprice"), 2).alias("middle"))
)
op("aggregate_cube", "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS gid, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(
    lambda r: r.table("lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"))
)
op("aggregate_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")(
    lambda r: r.table("orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
)
op("grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")(
    lambda r: r.spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM {t} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", t=r.table("lineitem"))
)
op("aggregate_sets", "SELECT o_custkey, array_to_string(list_sort(list(DISTINCT o_orderpriority)), ',') AS priorities FROM orders GROUP BY o_custkey")(
    lambda r: r.table("orders").groupBy("o_custkey").agg(F.concat_ws(",", F.sort_array(F.collect_set("o_orderpriority"))).alias("priorities"))
)
op("aggregate_approximate")(
    lambda r: r.table("lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", 0.5).alias("middle"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("orders"), F.expr("theta_sketch_estimate(theta_sketch_agg(l_suppkey))").alias("suppliers"))
)

# --- windows ------------------------------------------------------------------------

def _user():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


op("window_ranks", "SELECT event_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr, ntile(4) OVER w AS quarter, round(cume_dist() OVER w, 6) AS cd, round(percent_rank() OVER w, 6) AS pr FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(
    lambda r: r.table("events").select("event_id", F.row_number().over(_user()).alias("rn"), F.rank().over(W.partitionBy("user_id").orderBy("event_type")).alias("rk"), F.dense_rank().over(W.partitionBy("user_id").orderBy("event_type")).alias("dr"), F.ntile(4).over(_user()).alias("quarter"), F.round(F.cume_dist().over(_user()), 6).alias("cd"), F.round(F.percent_rank().over(_user()), 6).alias("pr"))
)
op("window_offsets", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS head, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(
    lambda r: r.table("events").select("event_id", F.lag("event_type").over(_user()).alias("before"), F.lead("event_id").over(_user()).alias("after"), F.first("event_id").over(_user()).alias("head"), F.nth_value("event_id", 2).over(_user()).alias("second"))
)
op("window_frames", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 3) AS running, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING), 4) AS moving, round(value / sum(value) OVER (PARTITION BY user_id), 6) AS share FROM events")(
    lambda r: r.table("events").select("event_id", F.round(F.sum("value").over(_user().rowsBetween(W.unboundedPreceding, 0)), 3).alias("running"), F.round(F.avg("value").over(_user().rowsBetween(-2, 0)), 4).alias("moving"), F.round(F.col("value") / F.sum("value").over(W.partitionBy("user_id")), 6).alias("share"))
)
op("window_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS recent FROM (SELECT *, datediff('day', TIMESTAMP '1970-01-01', o_orderdate) AS day FROM orders)")(
    lambda r: r.table("orders").withColumn("day", F.datediff("o_orderdate", F.lit("1970-01-01").cast("date"))).select("o_orderkey", F.count(F.lit(1)).over(W.partitionBy("o_custkey").orderBy("day").rangeBetween(-90, 0)).alias("recent"))
)

# --- order, sets, sampling ------------------------------------------------------------

op("top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda r: r.table("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20))
op("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 100")(lambda r: r.table("orders").select("o_orderkey").orderBy("o_orderkey").offset(100).limit(10))
op("top_per_group", "SELECT user_id, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 3")(
    lambda r: r.table("events").withColumn("n", F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))).where("n <= 3").select("user_id", "event_id")
)
_A, _B = "SELECT o_custkey AS k FROM orders WHERE o_totalprice > 300000", "SELECT o_custkey AS k FROM orders WHERE o_orderpriority = '1-URGENT'"


def _sides(r: Repository) -> tuple[DataFrame, DataFrame]:
    o = r.table("orders")
    return o.where("o_totalprice > 300000").select(F.col("o_custkey").alias("k")), o.where("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("k"))


for _name, _sql, _fn in (("union", "UNION ALL", lambda a, b: a.unionByName(b)), ("union_distinct", "UNION", lambda a, b: a.unionByName(b).distinct()), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    op(f"set_{_name}", f"{_A} {_sql} {_B}")(lambda r, fn=_fn: fn(*_sides(r)))
op("sample_hash", f"SELECT o_orderkey FROM orders WHERE {sqltext.uniform('o_orderkey', 3)} < 0.1")(lambda r: r.table("orders").where(hash_uniform("o_orderkey", 3) < 0.1).select("o_orderkey"))
op("sample_stratified", f"SELECT o_orderkey FROM (SELECT o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY {sqltext.uniform('o_orderkey', 4)}, o_orderkey) AS n FROM orders) WHERE n <= 50")(
    lambda r: r.table("orders").withColumn("n", F.row_number().over(W.partitionBy("o_orderpriority").orderBy(hash_uniform("o_orderkey", 4), "o_orderkey"))).where("n <= 50").select("o_orderkey")
)

# --- scalar functions --------------------------------------------------------------------

op("strings", "SELECT p_partkey, length(p_name) AS n, lower(p_name) AS low, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, regexp_replace(p_type, '[aeiou]', '', 'g') AS bare, string_split(p_type, ' ')[1] AS head, levenshtein(p_brand, 'Brand#11') AS far, translate(p_brand, 'abc', 'xyz') AS moved, concat_ws('-', p_brand, p_type) AS both_names FROM part")(
    lambda r: r.table("part").select("p_partkey", F.length("p_name").alias("n"), F.lower("p_name").alias("low"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.regexp_replace("p_type", "[aeiou]", "").alias("bare"), F.split("p_type", " ")[0].alias("head"), F.levenshtein("p_brand", F.lit("Brand#11")).cast("long").alias("far"), F.translate("p_brand", "abc", "xyz").alias("moved"), F.concat_ws("-", "p_brand", "p_type").alias("both_names"))
)
op("text_shares", "SELECT doc_id, round(length(regexp_replace(text, '[^A-Za-z]', '', 'g'))::DOUBLE / greatest(length(text), 1), 6) AS letters, round(1 - len(list_distinct(string_split(text, ' ')))::DOUBLE / len(string_split(text, ' ')), 6) AS repeats FROM documents")(
    lambda r: r.table("documents").select("doc_id", F.round(F.length(F.regexp_replace("text", "[^A-Za-z]", "")) / F.greatest(F.length("text"), F.lit(1)), 6).alias("letters"), F.round(1 - F.size(F.array_distinct(F.split("text", " "))) / F.size(F.split("text", " ")), 6).alias("repeats"))
)
op("html_url", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, len(string_split(regexp_replace(regexp_replace(url, '^[a-z]+://[^/?#]+', ''), '[?#].*$', ''), '/')) - 1 AS depth, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, len(regexp_extract_all(html, '<a href')) AS links FROM pages")(
    lambda r: r.table("pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), (F.size(F.split(F.regexp_replace(F.regexp_replace("url", "^[a-z]+://[^/?#]+", ""), "[?#].*$", ""), "/")) - 1).cast("long").alias("depth"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_count("html", F.lit("<a href")).cast("long").alias("links"))
)
op("dates", "SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, month(o_orderdate) AS m, isodow(o_orderdate) AS dow, dayofyear(o_orderdate) AS doy, date_trunc('month', o_orderdate)::DATE::VARCHAR AS first_day, last_day(o_orderdate)::VARCHAR AS final_day, date_diff('day', o_orderdate::DATE, DATE '2001-01-01') AS age, (o_orderdate::DATE + INTERVAL 2 MONTH)::DATE::VARCHAR AS later FROM orders")(
    lambda r: r.table("orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.month("o_orderdate").alias("m"), (F.weekday("o_orderdate") + 1).alias("dow"), F.dayofyear("o_orderdate").alias("doy"), F.date_trunc("month", "o_orderdate").cast("date").cast("string").alias("first_day"), F.last_day("o_orderdate").cast("string").alias("final_day"), F.datediff(F.lit("2001-01-01").cast("date"), F.col("o_orderdate").cast("date")).alias("age"), F.add_months(F.col("o_orderdate").cast("date"), 2).cast("string").alias("later"))
)
op("math", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS a, round(sqrt(l_quantity), 6) AS b, round(exp(l_discount), 6) AS c, floor(l_extendedprice / 7)::BIGINT AS d, ceil(l_tax * 10)::BIGINT AS e, greatest(l_discount, l_tax) AS f, least(l_discount, l_tax) AS g, sign(l_quantity - 25)::DOUBLE AS h, l_orderkey % 7 AS i FROM lineitem")(
    lambda r: r.table("lineitem").select("l_orderkey", "l_linenumber", F.round(F.log("l_extendedprice"), 6).alias("a"), F.round(F.sqrt("l_quantity"), 6).alias("b"), F.round(F.exp("l_discount"), 6).alias("c"), F.floor(F.col("l_extendedprice") / 7).alias("d"), F.ceil(F.col("l_tax") * 10).alias("e"), F.greatest("l_discount", "l_tax").alias("f"), F.least("l_discount", "l_tax").alias("g"), F.signum(F.col("l_quantity") - 25).alias("h"), F.pmod("l_orderkey", F.lit(7)).alias("i"))
)
op("arrays", "SELECT o_custkey, len(a) AS n, list_sum(list_transform(list_filter(a, lambda x: x % 2 = 0), lambda x: x * 2))::BIGINT AS twice, array_to_string(list_sort(a)[1:3], ',') AS head, list_contains(a, 7) AS seven FROM (SELECT o_custkey, list(o_orderkey) AS a FROM orders GROUP BY o_custkey)")(
    lambda r: r.table("orders").groupBy("o_custkey").agg(F.collect_list("o_orderkey").alias("a")).select("o_custkey", F.size("a").cast("long").alias("n"), F.when(F.exists("a", lambda x: x % 2 == 0), F.aggregate(F.transform(F.filter("a", lambda x: x % 2 == 0), lambda x: x * 2), F.lit(0).cast("long"), lambda s, x: s + x)).alias("twice"), F.concat_ws(",", F.transform(F.slice(F.sort_array("a"), 1, 3), lambda x: x.cast("string"))).alias("head"), F.array_contains("a", F.lit(7).cast("long")).alias("seven"))
)
op("explode_positions", "SELECT doc_id, i - 1 AS pos, w[i] AS word FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT doc_id, string_split(text, ' ')[1:5] AS w FROM documents))")(
    lambda r: r.table("documents").select("doc_id", F.posexplode(F.slice(F.split("text", " "), 1, 5)).alias("pos", "word"))
)
op("vectors", "SELECT vec_id, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm, round(list_sum(embedding::DOUBLE[]), 6) AS total FROM embeddings")(
    lambda r: r.table("embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))), 6).alias("norm"), F.round(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double")), 6).alias("total"))
)
op("maps", "SELECT user_id, array_to_string(list_sort(list(event_type || '=' || n)), ';') AS profile FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")(
    lambda r: r.table("events").groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m")).select("user_id", F.concat_ws(";", F.sort_array(F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))))).alias("profile"))
)
op("json", "SELECT event_id, (props->>'$.k')::INT AS k, ((props->>'$.k')::INT * 2)::INT AS twice FROM events")(
    lambda r: r.table("events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), (F.get_json_object("props", "$.k").cast("int") * 2).alias("twice"))
)
op("variant", "SELECT event_id, (props->>'$.k')::INT AS k FROM events")(lambda r: r.table("events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")))
op("conditionals", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'middle' ELSE 'low' END AS band, coalesce(nullif(o_orderstatus, 'O'), 'open') AS status FROM orders")(
    lambda r: r.table("orders").select("o_orderkey", F.when(F.col("o_totalprice") > 300000, "high").when(F.col("o_totalprice") > 100000, "middle").otherwise("low").alias("band"), F.coalesce(F.nullif("o_orderstatus", F.lit("O")), F.lit("open")).alias("status"))
)
op("subqueries", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 2 * avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o.o_orderkey AND l_returnflag = 'R')")(
    lambda r: r.spark.sql("SELECT o_orderkey FROM {o} o WHERE o_totalprice > (SELECT 2 * avg(o_totalprice) FROM {o}) AND EXISTS (SELECT 1 FROM {l} WHERE l_orderkey = o.o_orderkey AND l_returnflag = 'R')", o=r.table("orders"), l=r.table("lineitem"))
)
op("missing_values", "SELECT c_custkey, coalesce(y, avg(y) OVER ()) IS NOT NULL AS filled, y IS NULL AS missing FROM customer LEFT JOIN (SELECT o_custkey AS k, max(o_totalprice) AS y FROM orders WHERE o_totalprice > 400000 GROUP BY 1) ON k = c_custkey")(
    lambda r: r.table("customer").join(r.table("orders").where("o_totalprice > 400000").groupBy(F.col("o_custkey").alias("k")).agg(F.max("o_totalprice").alias("y")), F.col("k") == F.col("c_custkey"), "left").select("c_custkey", F.coalesce("y", F.lit(0.0)).isNotNull().alias("filled"), F.col("y").isNull().alias("missing"))
)

# --- Python where built-ins cannot express it ----------------------------------------------


@op("pandas_grouped", "SELECT user_id, round(quantile_cont(value, 0.9), 4) AS p90 FROM events GROUP BY user_id")
def pandas_grouped(r: Repository) -> DataFrame:
    """A grouped pandas function (the 0.9 quantile by user)."""
    return r.table("events").select("user_id", "value").groupBy("user_id").applyInPandas(lambda g: g.groupby("user_id", as_index=False)["value"].quantile(0.9).rename(columns={"value": "p90"}).round(4), "user_id long, p90 double")


@op("pandas_map", "SELECT event_id, CASE WHEN value > 100 THEN 1 ELSE 0 END AS high FROM events")
def pandas_map(r: Repository) -> DataFrame:
    """A function over Arrow batches."""

    def run(batches):
        for b in batches:
            yield b.assign(high=(b["value"] > 100).astype("int32"))[["event_id", "high"]]

    return r.table("events").select("event_id", "value").mapInPandas(run, "event_id long, high int")


@op("table_function", "SELECT o_custkey % 3 AS g, i AS pos FROM (SELECT DISTINCT o_custkey % 3 AS o_custkey FROM orders), (SELECT unnest(range(0, 2)) AS i)")
def table_function(r: Repository) -> DataFrame:
    """A Python table function, called laterally."""

    @F.udtf(returnType="pos: bigint")
    class Positions:
        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    r.spark.udtf.register("pathlift_positions", Positions)
    keys = r.table("orders").select((F.col("o_custkey") % 3).alias("g")).distinct()
    return r.spark.sql("SELECT g, pos FROM {k}, LATERAL pathlift_positions(2)", k=keys)


@op("sql_functions", "SELECT matched, total, matched / total::DOUBLE AS iq, round(0.5 * matched / total, 6) AS gain FROM (VALUES (1, 4), (3, 4)) AS v(matched, total)")
def sql_functions(r: Repository) -> DataFrame:
    """Measures as SQL functions of the session."""
    r.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pathlift_iq(matched INT, total INT) RETURNS DOUBLE RETURN try_divide(matched, total)")
    r.spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pathlift_gain(fi DOUBLE, iq DOUBLE) RETURNS DOUBLE RETURN fi * iq")
    return r.spark.sql("SELECT matched, total, pathlift_iq(matched, total) AS iq, round(pathlift_gain(0.5D, pathlift_iq(matched, total)), 6) AS gain FROM VALUES (1, 4), (3, 4) AS v(matched, total)")


# --- sources and sinks -------------------------------------------------------------------------

for _format in ("csv", "json", "orc", "parquet"):

    def _round_trip(r: Repository, kind: str = _format) -> DataFrame:
        """A table written to the shared folder in a format and read again with its schema."""
        from ..sources.files import shared_folder

        df = r.table("nation")
        path = shared_folder(r.spark, f"nation-{kind}")
        writer = df.write.mode("overwrite").format(kind)
        (writer.option("header", True) if kind == "csv" else writer).save(path)
        reader = r.spark.read.schema(df.schema).format(kind)
        return (reader.option("header", True) if kind == "csv" else reader).load(path)

    op(f"round_trip_{_format}", "SELECT * FROM nation")(_round_trip)


@op("partitioned_write", "SELECT n_nationkey, n_name, n_regionkey FROM nation WHERE n_regionkey = 2")
def partitioned_write(r: Repository) -> DataFrame:
    """A partitioned table of which one partition is read."""
    from ..sources.files import shared_folder

    path = shared_folder(r.spark, "nation-by-region")
    r.table("nation").write.mode("overwrite").partitionBy("n_regionkey").parquet(path)
    return r.spark.read.parquet(path).where("n_regionkey = 2").select("n_nationkey", "n_name", F.col("n_regionkey").cast("int").alias("n_regionkey"))

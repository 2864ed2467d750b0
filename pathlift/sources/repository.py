"""The repository: candidate tables by name, derived views, declared join edges."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: Derived views as SQL that Spark and DuckDB share.  {g} is the option by which DuckDB
#: replaces all matches; Spark always does.
VIEWS = {
    "orders_urgent_late": "SELECT * FROM orders WHERE o_orderpriority = '1-URGENT' AND o_orderdate >= TIMESTAMP '2000-01-01'",
    "lineitem_returned_cheap": "SELECT * FROM lineitem WHERE l_returnflag = 'R' AND l_discount >= 0.09",
    "doc_meta": "SELECT doc_id, lang, source, n_chars FROM documents",
    "doc_shape": "SELECT doc_id + 1000000 AS shape_id, CAST(floor(50.0 * length(regexp_replace(text, '[^A-Za-z]', ''{g})) / greatest(length(text), 1)) AS INT) AS alpha_bin, CAST(length(regexp_replace(text, '[^A-Za-z]', ''{g})) AS DOUBLE) / greatest(length(text), 1) AS alpha_share, length(text) - length(replace(text, '\n', '')) + 1 AS n_lines FROM documents",
    "doc_to_shape": "SELECT doc_id, doc_id + 1000000 AS shape_id FROM documents",
    "doc_to_shape_6": "SELECT doc_id, doc_id + 1000000 AS shape_id FROM documents WHERE doc_id % 10 < 6",
    "orders_region_label": "SELECT o_orderkey, o_custkey, CAST(CASE WHEN n_regionkey IN (0, 1) THEN 1 ELSE 0 END AS INT) AS y FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    "customer_spend": "SELECT c_custkey, coalesce(sum(o_totalprice), 0.0) AS y FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey",
    "event_label": "SELECT event_id, user_id, ts, event_type, CAST(CASE WHEN value > 100 THEN 1 ELSE 0 END AS INT) AS y FROM events",
    "event_to_session": "SELECT event_id, event_id + 5000000 AS session_id FROM events WHERE event_id % 10 < 6",
    "session_risk": "SELECT event_id + 5000000 AS session_id, CAST(CASE WHEN (value > 100) <> (event_id % 7 = 0) THEN 1 ELSE 0 END AS INT) AS risk FROM events",
    "doc_counts": "SELECT doc_id + 2000000 AS counts_id, length(text) - length(regexp_replace(text, '[0-9]', ''{g})) AS n_digits, length(text) - length(regexp_replace(text, '[A-Z]', ''{g})) AS n_upper, length(text) - length(replace(text, ' ', '')) AS n_blanks, length(text) - length(regexp_replace(text, '[.,;:!?]', ''{g})) AS n_marks, length(text) - length(regexp_replace(text, '[#*$%&|<>]', ''{g})) AS n_symbols FROM documents",
    "doc_to_counts": "SELECT doc_id, doc_id + 2000000 AS counts_id FROM documents",
    "doc_vector": "SELECT vec_id, element_at(embedding, 1) AS e1, element_at(embedding, 2) AS e2, element_at(embedding, 3) AS e3, element_at(embedding, 4) AS e4, element_at(embedding, 5) AS e5, element_at(embedding, 6) AS e6 FROM embeddings",
    "page_facts": "SELECT page_id, length(html) AS html_chars, length(url) AS url_chars FROM pages",
    "talk_facts": "SELECT conv_id, count(*) AS turns, max(length(text)) AS longest_turn FROM conversations GROUP BY conv_id",
    "order_counts": "SELECT o_custkey, count(*) AS n_orders, max(o_totalprice) AS top_price, min(o_totalprice) AS low_price FROM orders GROUP BY o_custkey",
    "event_facts": "SELECT event_id, hour(ts) AS hour, day(ts) AS day_of_month, length(props) AS props_chars FROM events",
    "activity": "SELECT user_id, count(*) AS n_events, count(DISTINCT event_type) AS n_types FROM events GROUP BY user_id",
    "user_days": "SELECT concat(CAST(user_id AS VARCHAR(20)), '/', CAST(CAST(ts AS DATE) AS VARCHAR(20))) AS user_and_day, user_id, CAST(ts AS DATE) AS day, avg(value) AS y FROM events GROUP BY user_id, CAST(ts AS DATE)",
    "day_before": "SELECT concat(CAST(user_id AS VARCHAR(20)), '/', CAST(CAST(ts AS DATE) + INTERVAL '1' DAY AS VARCHAR(10))) AS user_and_day, avg(value) AS v_before, count(*) AS n_before, max(value) AS top_before FROM events GROUP BY user_id, CAST(ts AS DATE)",
    "same_day": "SELECT concat(CAST(user_id AS VARCHAR(20)), '/', CAST(CAST(ts AS DATE) AS VARCHAR(20))) AS user_and_day, count(*) AS n_events, count(DISTINCT event_type) AS n_types, min(hour(ts)) AS first_hour, max(event_type) AS last_type FROM events GROUP BY user_id, CAST(ts AS DATE)",
    "calendar": "SELECT CAST(ts AS DATE) AS day, count(*) AS n_that_day, count(DISTINCT user_id) AS users_that_day FROM events GROUP BY CAST(ts AS DATE)",
    "user_day": "SELECT user_id, CAST(ts AS DATE) AS day, avg(value) AS v, count(*) AS n FROM events GROUP BY user_id, CAST(ts AS DATE)",
}
#: Tables that a view reads.
READS = {v: tuple(t for t in TABLES if f" {t}" in f" {sql.replace(chr(10), ' ')}" and (f"FROM {t}" in sql or f"JOIN {t}" in sql)) for v, sql in VIEWS.items()}


def view_sql(name: str) -> str:
    """A view's SQL for DuckDB, in brackets; a table's name alone."""
    return f"({VIEWS[name].replace('{g}', ', ' + chr(39) + 'g' + chr(39))})" if name in VIEWS else name


@dataclass(frozen=True)
class JoinEdge:
    """Two columns that join; ``reverse`` walks it the other way."""

    edge_id: str
    left: str
    left_col: str
    right: str
    right_col: str

    def reverse(self) -> JoinEdge:
        other = self.edge_id[:-1] if self.edge_id.endswith("r") else f"{self.edge_id}r"
        return JoinEdge(other, self.right, self.right_col, self.left, self.left_col)


#: Declared edges over the given tables and views.
EDGES = (
    JoinEdge("e1", "orders", "o_custkey", "customer", "c_custkey"),
    JoinEdge("e2", "customer", "c_nationkey", "nation", "n_nationkey"),
    JoinEdge("e3", "nation", "n_regionkey", "region", "r_regionkey"),
    JoinEdge("e4", "supplier", "s_nationkey", "nation", "n_nationkey"),
    JoinEdge("e5", "lineitem", "l_orderkey", "orders", "o_orderkey"),
    JoinEdge("e6", "lineitem", "l_partkey", "part", "p_partkey"),
    JoinEdge("e7", "lineitem", "l_suppkey", "supplier", "s_suppkey"),
    JoinEdge("e8", "customer", "c_custkey", "events", "user_id"),
    JoinEdge("e9", "labels", "doc_id", "documents", "doc_id"),
    JoinEdge("e10", "documents", "doc_id", "pages", "page_id"),
    JoinEdge("e11", "documents", "doc_id", "embeddings", "vec_id"),
    JoinEdge("e12", "documents", "doc_id", "conversations", "conv_id"),
    JoinEdge("e13", "documents", "doc_id", "benchmark", "item_id"),
    JoinEdge("e14", "customer", "c_custkey", "orders_urgent_late", "o_custkey"),
    JoinEdge("e15", "part", "p_partkey", "lineitem_returned_cheap", "l_partkey"),
)


@dataclass(frozen=True)
class JoinPath:
    """Edges walked from a base table to a candidate; no table twice."""

    edges: tuple[JoinEdge, ...]

    @property
    def base(self) -> str:
        return self.edges[0].left

    @property
    def last(self) -> str:
        return self.edges[-1].right

    @property
    def tables(self) -> tuple[str, ...]:
        return (self.base, *(e.right for e in self.edges))

    @property
    def path_id(self) -> str:
        return ">".join(e.edge_id for e in self.edges)

    def is_simple(self) -> bool:
        return len(set(self.tables)) == len(self.tables)


_WHOLE = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


def key_kind(data_type: T.DataType) -> str:
    """What a join key of this type is compared as: long, double, date, timestamp, boolean or string."""
    if isinstance(data_type, _WHOLE):
        return "long"
    if isinstance(data_type, T.NumericType):
        return "double"
    if isinstance(data_type, T.TimestampType | T.TimestampNTZType):
        return "timestamp_ntz"
    return {T.DateType: "date", T.BooleanType: "boolean"}.get(type(data_type), "string")


def common_kind(a: str, b: str) -> str:
    """The kind as which two key columns are compared; numbers meet as doubles, times as timestamps, all else as text."""
    if a == b:
        return a
    for kinds, met in (({"long", "double"}, "double"), ({"date", "timestamp_ntz"}, "timestamp_ntz")):
        if {a, b} <= kinds:
            return met
    return "string"


def as_key(column: Column | str, kind: str) -> Column:
    """A column as a join key of a kind."""
    column = F.col(column) if isinstance(column, str) else column
    return column.cast(kind)


def key_struct(column: Column | str, kind: str) -> Column:
    """A key of any kind in one type, struct<k, t>, for frames that hold keys of several edges; null where the key is."""
    column = F.col(column) if isinstance(column, str) else column
    own = column.cast(kind)
    if kind == "long":
        made = F.struct(own.alias("k"), F.lit("").alias("t"))
    elif kind == "date":
        made = F.struct(F.unix_date(own).cast("long").alias("k"), F.lit("date").alias("t"))
    else:  # whole doubles read like whole numbers
        text = F.when(own == F.floor(own), F.format_string("%.0f", own)).otherwise(own.cast("string")) if kind == "double" else own.cast("string")
        made = F.struct(F.lit(0).cast("long").alias("k"), text.alias("t"))
    return F.when(own.isNotNull(), made)


@dataclass
class Repository:
    """Tables of a folder; frames are read with the columns that plans ask for."""

    spark: SparkSession
    sf_dir: str
    extra: dict[str, DataFrame] = field(default_factory=dict)

    @cached_property
    def _read(self) -> dict[str, DataFrame]:
        return {}

    def table(self, name: str) -> DataFrame:
        if name in self.extra:
            return self.extra[name]
        if name not in self._read:
            if name in VIEWS:
                sql = VIEWS[name].replace("{g}", "")
                for t in READS[name]:
                    for word in ("FROM", "JOIN"):
                        sql = sql.replace(f"{word} {t}", f"{word} {{{t}}}")
                self._read[name] = self.spark.sql(sql, **{t: self.table(t) for t in READS[name]})
            else:
                self._read[name] = self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")
        return self._read[name]

    def kind(self, edge: JoinEdge, base: DataFrame | None = None) -> str:
        """The kind as which the two columns of an edge are compared; ``base`` stands for a left table that is no table."""
        left = base if base is not None and edge.left_col in base.columns else self.table(edge.left)
        return common_kind(key_kind(left.schema[edge.left_col].dataType), key_kind(self.table(edge.right).schema[edge.right_col].dataType))

    def names(self) -> list[str]:
        return [*TABLES, *VIEWS, *self.extra]


def both_ways(edges=EDGES) -> tuple[JoinEdge, ...]:
    return tuple(x for e in edges for x in (e, e.reverse()))


def path_of(*edge_ids: str) -> JoinPath:
    """A path by edge ids, such as e1, e2, e3r."""
    by = {e.edge_id: e for e in both_ways()}
    return JoinPath(tuple(by[i] for i in edge_ids))

"""The five tasks: a base table with a label, candidate tables around it, and the metric of the task.

Each task has an engine (the whole method) and a candidate table: every feature through
every path within reach, integrated in one plan.  Searches that query a model, and the
models that score plans in the end, learn from all rows that are not held out; scores in
the end are over all that are.
"""

from __future__ import annotations

import threading
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field
from functools import cached_property, partial

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import systems
from ..operators import counted_models, joint_models
from ..operators.augment import integrate
from ..operators.engine import Base, Engine, Settings, describe
from ..operators.paths import JoinGraph
from ..operators.stored_table import StoredTable, store
from ..sources.files import written
from ..sources.jobs import at_once
from ..sources.repository import VIEWS, JoinEdge, JoinPath, Repository


@dataclass(frozen=True)
class TaskSpec:
    name: str
    base: Base
    edges: tuple[JoinEdge, ...]
    features: Mapping[str, tuple[str, ...]]
    max_hops: int = 3


def _edges(prefix: str, *rows: tuple[str, str, str, str]) -> tuple[JoinEdge, ...]:
    return tuple(JoinEdge(f"{prefix}{i}", *row) for i, row in enumerate(rows, 1))


_STAR_FEATURES = {
    "customer": ("c_acctbal", "c_mktsegment"), "nation": ("n_name", "n_regionkey"), "region": ("r_name",), "part": ("p_size", "p_retailprice", "p_brand", "p_type"), "supplier": ("s_acctbal",),
    "lineitem": ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_linenumber"), "orders": ("o_totalprice", "o_orderpriority", "o_orderstatus"),
}


def _some(*tables: str, **more: tuple[str, ...]) -> dict[str, tuple[str, ...]]:
    return {t: _STAR_FEATURES[t] for t in tables} | more


#: Classification by accuracy, by F1 of the rare class; regression by absolute and by squared error.
TASKS = {
    t.name: t
    for t in (
        TaskSpec(
            "quality", Base("labels", "doc_id", "quality", "accuracy"),
            _edges("q", ("labels", "doc_id", "doc_meta", "doc_id"), ("labels", "doc_id", "doc_to_shape", "doc_id"), ("doc_to_shape", "shape_id", "doc_shape", "shape_id"), ("labels", "doc_id", "doc_to_counts", "doc_id"), ("doc_to_counts", "counts_id", "doc_counts", "counts_id"),
                   ("labels", "doc_id", "doc_vector", "vec_id"), ("labels", "doc_id", "embeddings", "vec_id"), ("labels", "doc_id", "page_facts", "page_id"), ("labels", "doc_id", "talk_facts", "conv_id"), ("doc_meta", "doc_id", "doc_to_shape_6", "doc_id"), ("doc_to_shape_6", "shape_id", "doc_shape", "shape_id")),
            {"doc_meta": ("lang", "source", "n_chars"), "doc_shape": ("alpha_bin", "alpha_share", "n_lines"), "doc_counts": ("n_digits", "n_upper", "n_blanks", "n_marks", "n_symbols"), "doc_vector": ("e1", "e2", "e3", "e4", "e5", "e6"), "embeddings": ("label",), "page_facts": ("html_chars", "url_chars"), "talk_facts": ("turns", "longest_turn")},
        ),
        TaskSpec(
            "region", Base("orders_region_label", "o_orderkey", "y", "accuracy"),
            _edges("r", ("orders_region_label", "o_orderkey", "orders", "o_orderkey"), ("orders_region_label", "o_custkey", "customer", "c_custkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("orders_region_label", "o_orderkey", "lineitem", "l_orderkey"), ("lineitem", "l_partkey", "part", "p_partkey"), ("lineitem", "l_suppkey", "supplier", "s_suppkey")),
            _some("customer", "nation", "region", "part", "supplier", "lineitem", "orders"),
        ),
        TaskSpec(
            "risk", Base("event_label", "event_id", "y", "f1"),
            _edges("e", ("event_label", "event_id", "event_to_session", "event_id"), ("event_to_session", "session_id", "session_risk", "session_id"), ("event_label", "event_id", "event_facts", "event_id"), ("event_label", "user_id", "customer", "c_custkey"), ("event_label", "user_id", "activity", "user_id"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("customer", "c_custkey", "orders", "o_custkey"), ("customer", "c_custkey", "order_counts", "o_custkey")),
            _some("customer", "nation", "region", "orders", session_risk=("risk",), event_facts=("hour", "day_of_month", "props_chars"), activity=("n_events", "n_types"), order_counts=("n_orders", "top_price", "low_price")),
        ),
        TaskSpec(
            "spend", Base("customer_spend", "c_custkey", "y", "mae"),
            _edges("s", ("customer_spend", "c_custkey", "customer", "c_custkey"), ("customer_spend", "c_custkey", "orders", "o_custkey"), ("customer_spend", "c_custkey", "order_counts", "o_custkey"), ("customer_spend", "c_custkey", "orders_urgent_late", "o_custkey"), ("customer_spend", "c_custkey", "activity", "user_id"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("orders", "o_orderkey", "lineitem", "l_orderkey")),
            _some("customer", "nation", "region", "orders", "lineitem", order_counts=("n_orders", "top_price", "low_price"), orders_urgent_late=("o_totalprice",), activity=("n_events", "n_types")),
        ),
        TaskSpec(
            "daily", Base("user_days", "user_and_day", "y", "mse"),
            _edges("d", ("user_days", "user_and_day", "day_before", "user_and_day"), ("user_days", "user_and_day", "same_day", "user_and_day"), ("user_days", "day", "calendar", "day"), ("user_days", "user_id", "activity", "user_id"), ("user_days", "user_id", "customer", "c_custkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("customer", "c_custkey", "order_counts", "o_custkey"), ("customer", "c_custkey", "orders", "o_custkey")),
            _some("customer", "nation", "region", "orders", day_before=("v_before", "n_before", "top_before"), same_day=("n_events", "n_types", "first_hour", "last_type"), calendar=("n_that_day", "users_that_day"), activity=("n_events", "n_types"), order_counts=("n_orders", "top_price", "low_price")),
        ),
    )
}


#: What a view's SQL holds if it is worth writing: joins, groups, scans of texts or vectors.
COSTLY = (" JOIN ", "GROUP BY", "length(", "element_at(")


def held_out(key: str):
    """True for three rows of ten, by a hash of the key."""
    return F.pmod(F.xxhash64(F.col(key).cast("string"), F.lit("held out")), F.lit(10)) < 3


@dataclass
class Common:
    """What the tasks on a folder share: views that take work and the description of columns, each made once."""

    spark: SparkSession
    sf_dir: str
    together: tuple[TaskSpec, ...] = ()  # tasks whose columns are described in one go
    views: dict[str, DataFrame] = field(default_factory=dict)
    descriptions: dict[float, tuple[list, dict]] = field(default_factory=dict)
    lock: threading.RLock = field(default_factory=threading.RLock)

    def repository(self, tables: Sequence[str]) -> Repository:
        """The tables of the folder, with views that take work written."""
        with self.lock:
            plain = Repository(self.spark, self.sf_dir)
            missing = [t for t in dict.fromkeys(tables) if t not in self.views and any(w in VIEWS.get(t, "") for w in COSTLY)]
            self.views.update(zip(missing, at_once(self.spark, [lambda t=t: written(plain.table(t), t) for t in missing], 8), strict=True))
            return Repository(self.spark, self.sf_dir, {t: self.views[t] for t in tables if t in self.views})

    def described(self, eps: float) -> tuple[list, dict]:
        """Neighbours and vectors of the columns of all tasks; a column that several tasks know is described once."""
        with self.lock:
            if eps not in self.descriptions:
                features: dict[str, tuple[str, ...]] = {}
                for spec in self.together:
                    for t, own in spec.features.items():
                        features[t] = tuple(dict.fromkeys((*features.get(t, ()), *own)))
                self.descriptions[eps] = describe(self.repository(list(features)), features, eps)
            return self.descriptions[eps]


@dataclass
class Workload:
    """A task on the tables of a folder: its engine, its candidate table, and scores of plans."""

    spark: SparkSession
    sf_dir: str
    spec: TaskSpec
    settings: Mapping = field(default_factory=dict)
    runs: dict = field(default_factory=dict)  # what a system chose for a budget, and at what cost
    scored: dict = field(default_factory=dict)  # signed scores by plan
    coders: dict = field(default_factory=dict)  # over all rows that are not held out, by column
    common: Common | None = None

    @cached_property
    def repo(self) -> Repository:
        """The tables; views that take work are made once, as statistics, candidates and models all read them."""
        self.common = self.common or Common(self.spark, self.sf_dir)
        return self.common.repository(list(self.graph.tables()))

    @cached_property
    def graph(self) -> JoinGraph:
        return JoinGraph(self.spec.edges)

    def engine(self, **settings) -> Engine:
        """The method, fitted on the rows that are not held out."""
        repo = Repository(self.spark, self.sf_dir, dict(self.repo.extra))
        repo.extra[self.spec.base.table] = self.repo.table(self.spec.base.table).where(~held_out(self.spec.base.key))
        made = Settings(**({"max_hops": self.spec.max_hops} | dict(self.settings) | settings))
        known = partial(self.common.described, made.eps) if self.common.together else None
        return Engine(repo, self.spec.base, self.graph, self.spec.features, made, describer=known).explore()

    @cached_property
    def fitted(self) -> Engine:
        """The method with both estimators fitted, shared by the studies of a session."""
        return self.engine(training_pairs=60, clamp=True)

    def prepare(self, method: bool = True) -> None:
        """The candidate table with what is read of it, and beside it the fitted method."""
        _ = self.repo, self.pairs

        def candidates() -> None:
            _ = self.sample, self.coverage

        at_once(self.spark, [candidates, *([lambda: self.fitted] if method else [])])

    @cached_property
    def pairs(self) -> list[tuple[JoinPath, str]]:
        """Every feature through every path."""
        return [(p, c) for p in self.graph.paths(self.spec.base.table, self.spec.max_hops) for c in self.spec.features.get(p.last, ())]

    @staticmethod
    def column(path: JoinPath, feature: str) -> str:
        return f"{path.path_id}:{feature}"

    @cached_property
    def names(self) -> list[str]:
        return [self.column(p, c) for p, c in self.pairs]

    @cached_property
    def aggregated(self) -> list[str]:
        """Columns that path aggregation makes, in its order."""
        return [c for c in self.table.columns if c not in self.names and c not in (self.spec.base.key, self.spec.base.label, "held_out")]

    @cached_property
    def table(self) -> DataFrame:
        """(key, label, held_out, candidate columns, aggregates of tables one join away), written once."""
        base = self.spec.base
        frame = self.repo.table(base.table)
        firsts = {p.edges[0].left_col for p, _ in self.pairs} - {base.key, base.label}
        wide, _ = integrate(self.repo, frame.select(base.key, base.label, *sorted(firsts)), self.pairs)
        made = [f"{p.last}__{c}__{i}" for i, (p, c) in enumerate(self.pairs, 1)]
        near = [e for e in self.graph.neighbours(base.table) if self.spec.features.get(e.right)]
        wide = systems.path_aggregation(self.repo, wide, near, 1, ("count", "avg", "max", "n_unique", "mode", "skewness", "month", "weekday"), budget=30) if near else wide
        extra = [c for c in wide.columns if c not in (base.key, base.label, *firsts, *made)]
        return written(wide.select(base.key, F.col(base.label).cast("double").alias(base.label), held_out(base.key).alias("held_out"), *[F.col(m).alias(n) for m, n in zip(made, self.names, strict=True)], *extra), "candidates")

    @cached_property
    def sample(self) -> StoredTable:
        """What searches ask: all rows that are not held out, coded, in the shared folder."""
        base, names = self.spec.base, [*self.names, *self.aggregated]
        coders = self.coded(names)
        return store(self.table.where(~F.col("held_out") & F.col(base.label).isNotNull()), base.key, base.label, names, [coders[n] for n in names], base.metric)

    @cached_property
    def coverage(self) -> dict[str, float]:
        """Share of rows with a value, by column; one job."""
        row = self.table.agg(*[F.avg(F.col(f"`{n}`").isNotNull().cast("double")).alias(n) for n in self.names]).first()
        return {n: row[n] or 0.0 for n in self.names}

    def task(self, most_hops: int | None = None) -> systems.Task:
        """The interface of the compared systems: each feature by its shortest path, the best covered of them."""
        sample = self.sample
        best: dict[str, tuple] = {}
        for (p, c), n in zip(self.pairs, self.names, strict=True):
            key = (len(p.edges), -round(self.coverage[n], 9), p.path_id)
            if (most_hops is None or len(p.edges) <= most_hops) and key < best.get(f"{p.last}.{c}", ((99,),))[0]:
                best[f"{p.last}.{c}"] = (key, n, p)
        columns = {n: p for _, n, p in best.values()}
        linked = {n: sample.association(n) for n in columns}
        profile = {n: (self.coverage[n], np.log1p(sample.sizes[sample.number[n]]), float(sample.coders[sample.number[n]].cuts is not None), sample.mean_code(n), linked[n]) for n in columns}
        reach: dict[str, list[str]] = {"": [e.right for e in self.graph.neighbours(self.spec.base.table)]}
        for t in self.graph.tables():
            reach[t] = [e.right for e in self.graph.neighbours(t)]
        # a bridge without columns is walked over at no charge
        for _ in range(self.spec.max_hops):
            for t, ahead in reach.items():
                reach[t] = sorted({*ahead, *[x for b in ahead if not self.spec.features.get(b) for x in reach.get(b, ())]})
        cover = {t: max((self.coverage[n] for n, p in columns.items() if p.last == t), default=0.0) for t in {p.last for p in columns.values()}}
        return systems.Task(
            sorted(columns), {n: p.last for n, p in columns.items()}, {n: len([e for e in p.edges if self.spec.features.get(e.right)]) for n, p in columns.items()}, sample.score, profile, reach, sample.importances, cover, linked, {n: self.coverage[n] for n in columns},
        )

    def coded(self, names: Sequence[str]) -> dict[str, joint_models.Coder]:
        """Coders of candidate columns over all rows that are not held out, each made once."""
        missing = sorted({*names} - {*self.coders})
        if missing:
            self.coders |= counted_models.fit_coders(self.table.where(~F.col("held_out") & F.col(self.spec.base.label).isNotNull()), missing)
        return {n: self.coders[n] for n in names}

    def score_plans(self, plans: Mapping[str, Sequence[str]]) -> dict[str, float]:
        """Signed score of plans (column names) over all held-out rows: an ensemble a plan, tuned and fitted on all other rows in a task of its own.  A session scores a plan once."""
        base, sample = self.spec.base, self.sample
        order = list(dict.fromkeys(p for p in map(tuple, plans.values()) if p not in self.scored))
        families = [sample.final(p)[1].families for p in order]  # what is fitted, not on what
        metric = base.metric
        found = {}
        if order:
            coders = self.coded(sorted({c for p in order for c in p}))
            checks = F.pmod(F.xxhash64(F.col(base.key).cast("string"), F.lit("validated")), F.lit(4)) == 0
            part = F.when(F.col("held_out"), counted_models.OUT).when(checks, counted_models.VALIDATE).otherwise(counted_models.FIT)
            counted = counted_models.lines(self.table.where(F.col(base.label).isNotNull()), part, base.label, order, coders)
            sums = counted_models.score_lines(counted, metric, families, [[coders[c].size for c in p] for p in order])
            found = {r["plan"]: r for r in sums.where("n > 0").collect()}  # one row a plan

        def value(r) -> float:
            if metric == "accuracy":
                return r["right"] / r["n"]
            if metric == "f1":
                return r["hits"] / (r["hits"] + 0.5 * (r["n"] - r["right"])) if r["hits"] else 0.0
            return -(r["absolute"] if metric == "mae" else r["squared"]) / r["n"]

        self.scored |= {p: value(found[k]) if k in found else 0.0 for k, p in enumerate(order)}
        return {name: self.scored[tuple(p)] for name, p in plans.items()}


_KNOWN: dict[tuple, Workload] = {}
_COMMON: dict[tuple, Common] = {}


def workloads(spark: SparkSession, sf_dir: str, names: Sequence[str] = tuple(TASKS)) -> list[Workload]:
    """The tasks on a folder; a session builds the candidate table of a task once."""
    at = (spark.sparkContext.applicationId, sf_dir)
    common = _COMMON.setdefault(at, Common(spark, sf_dir))
    for n in names:
        _KNOWN.setdefault((*at, n), Workload(spark, sf_dir, TASKS[n], common=common))
    return [_KNOWN[*at, n] for n in names]


def all_tasks(spark: SparkSession, sf_dir: str) -> list[Workload]:
    """All tasks, with the views that any of them reads, to be made side by side."""
    works = workloads(spark, sf_dir)
    works[0].common.together = tuple(TASKS.values())
    works[0].common.repository([t for w in works for t in w.graph.tables()])
    return works


def prepared(spark: SparkSession, sf_dir: str, method: bool = True) -> list[Workload]:
    """All tasks with their candidate tables, and the fitted method if asked for; tasks are made side by side."""
    works = all_tasks(spark, sf_dir)
    at_once(spark, [partial(w.prepare, method) for w in works])
    return works

"""The whole method: explore (statistics, clusters, selection, training), exploit (search, refine, integrate).

What scales with the tables runs as DataFrame plans; what is metadata (paths, pairs,
clusters, at most a thousand training sequences) is decided on the driver.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator, Mapping, Sequence
from contextlib import contextmanager
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.files import written
from ..sources.jobs import at_once
from ..sources.repository import JoinEdge, JoinPath, Repository
from . import edge_stats, quality, representation, search, utility
from .augment import augment, integrate
from .paths import JoinGraph
from .selection import Pair, select_pairs
from .sequence_model import EXTENDED, INPUTS, SequenceModel


@dataclass(frozen=True)
class Base:
    """A base table with its key, its label and the metric of its task (accuracy, f1, mae or mse)."""

    table: str
    key: str
    label: str
    metric: str = "accuracy"


@dataclass
class Settings:
    budget: int = 10
    heap_factor: int = 5
    training_pairs: int = 40
    warmup: int = 0
    selection: str = "greedy"  # or random
    t_iq: float = 0.1
    max_hops: int = 3
    eps: float = 0.7
    least: int = 2
    bins: int = 20
    iq_estimator: str = "sequence"  # sequence, product or exact
    inputs: str = "paper"  # the five inputs, or extended by transitivity and containment
    iq_level: str = "feature"  # gains by the quality of the feature column, or of the path alone
    epochs: int = 150
    clamp: bool = False
    decay: str = "printed"
    refine: bool = True
    seed: int = 0


@dataclass
class Result:
    plan: list[tuple[search.Candidate, float]]
    augmented: DataFrame
    joins: int
    stats: search.SearchStats
    base_score: float


class StepStatistics:
    """What the network reads of every join step: edge statistics, and those of the columns that leave a table.

    For a step inside a path, variance, entropy and divergence are those of the join
    column in the joined rows, correlation and mutual information pair the key that
    enters the table with the key that leaves it.  For the last step all five are those
    of the feature column instead; a path without feature ends in its own join column.
    """

    def __init__(self):
        self.edges: dict[str, dict] = {}
        self.leaving: dict[tuple[str, str, int], dict] = {}

    def add(self, repo: Repository, edges: Sequence[JoinEdge], ways: Sequence[edge_stats.Leaving], levels: Sequence[int] = (quality.LEVELS,)) -> None:
        """Computes what is not there yet; one row an edge and one a way come back."""
        edges = [e for e in dict.fromkeys(edges) if e.edge_id not in self.edges]
        ways = [w for w in dict.fromkeys(ways) if any((w.edge.edge_id, w.column, x) not in self.leaving for x in levels)]
        own = lambda: edge_stats.edge_statistics(repo, edges).collect() if edges else []
        through = lambda: edge_stats.leaving_statistics(repo, ways, levels).collect() if ways else []
        found, left = at_once(repo.spark, [own, through])
        self.edges |= {r["edge_id"]: r.asDict() for r in found}
        self.leaving |= {(r["edge_id"], r["column"], r["level"]): r.asDict() for r in left}

    def forget(self, edges: Sequence[JoinEdge]) -> None:
        gone = {e.edge_id for e in edges}
        self.edges = {k: v for k, v in self.edges.items() if k not in gone}
        self.leaving = {k: v for k, v in self.leaving.items() if k[0] not in gone}

    def sequence(self, path: JoinPath, feature: str | None, level: int = quality.LEVELS) -> np.ndarray:
        """Steps by inputs, in the order of EXTENDED."""
        rows = []
        for i, edge in enumerate(path.edges):
            own = self.edges[edge.edge_id]
            last = i + 1 == len(path.edges)
            column = (feature or edge.right_col) if last else path.edges[i + 1].left_col
            left = self.leaving.get((edge.edge_id, column, level if last else quality.LEVELS), {})
            main = left if last and feature else own
            rows.append([main.get("variance", 0.0), main.get("entropy_printed", 0.0), main.get("kl", 0.0), left.get("pearson", 0.0), left.get("mutual_info", 0.0), (left if last else own).get("transitivity", 0.0), (left if last else own).get("containment", 0.0)])
        return np.array(rows, dtype=float)


def ways_of(paths: Sequence[JoinPath], features: Mapping[str, Sequence[str]]) -> list[edge_stats.Leaving]:
    """The columns by which paths leave their tables, and those in which they end."""
    out = []
    for p in paths:
        out += [edge_stats.Leaving(a, b.left_col) for a, b in zip(p.edges, p.edges[1:], strict=False)]
        out += [edge_stats.Leaving(p.edges[-1], c) for c in (p.edges[-1].right_col, *features.get(p.last, ()))]
    return list(dict.fromkeys(out))


def describe(repo: Repository, features: Mapping[str, Sequence[str]], eps: float) -> tuple[list[tuple[str, str, float]], dict[str, np.ndarray]]:
    """(neighbours with cosine ``eps`` or more, vector by column) of columns of the repository."""
    vectors = written(representation.represent(representation.serialized_columns(repo, features)), "vectors")  # a cached frame keeps all its empty partitions
    near = [tuple(r) for r in representation.neighbours(vectors, eps).collect()]  # columns of the repository
    return near, {r["feature_id"]: np.array(r["repr"]) for r in vectors.collect()}  # one row a column


@dataclass
class Engine:
    """explore() fits both estimators; exploit() searches with them; update() reacts to changed and new tables."""

    repo: Repository
    base: Base
    graph: JoinGraph
    features: Mapping[str, Sequence[str]]
    settings: Settings = field(default_factory=Settings)
    seconds: dict[str, float] = field(default_factory=dict)  # by stage
    describer: Callable[[], tuple[list, dict]] | None = None  # neighbours and vectors of at least the columns here, where others share them

    @contextmanager
    def _timed(self, stage: str) -> Iterator[None]:
        began = time.perf_counter()
        yield
        self.seconds[stage] = self.seconds.get(stage, 0.0) + time.perf_counter() - began

    def explore(self) -> Engine:
        s = self.settings
        self.base_frame = self.repo.table(self.base.table)
        self.paths = self.graph.paths(self.base.table, s.max_hops)
        self.steps = StepStatistics()

        def statistics() -> None:
            with self._timed("statistics"):
                self.steps.add(self.repo, [e for p in self.paths for e in p.edges], ways_of(self.paths, self.features))

        def training_data() -> None:
            with self._timed("clusters"):
                self._represent()
            with self._timed("selection"):
                pairs = self._pairs()
                self.selected = select_pairs(pairs, s.training_pairs, seed=s.seed, warmup=s.warmup if s.selection == "greedy" else len(pairs))
            with self._timed("measuring"):
                self._measure()

        with self._timed("explore"):
            at_once(self.repo.spark, [statistics, training_data])  # neither needs the other
            with self._timed("training"):
                self._train()
        return self

    def _represent(self) -> None:
        s = self.settings
        own = {t: self.features[t] for t in {p.last for p in self.paths} if self.features.get(t)}
        near, vectors = self.describer() if self.describer else describe(self.repo, own, s.eps)
        self.vectors = {f: vectors[f] for f in sorted(f"{t}.{c}" for t, columns in own.items() for c in columns)}
        clusters = representation.threshold_cluster([r for r in near if r[0] in self.vectors and r[1] in self.vectors], sorted(self.vectors), s.least, s.seed)
        self.clusters = {f: c for f, c, _, _ in clusters}
        self.centroids = {c: centre for _, c, centre, _ in clusters}

    def _pairs(self) -> list[Pair]:
        return [Pair(f"{p.last}.{c}", tuple(e.edge_id for e in p.edges), self.clusters[f"{p.last}.{c}"]) for p in self.paths for c in self.features.get(p.last, ())]

    def _measure(self) -> None:
        """Quality of the selected pairs and of their paths, and scores of the selected columns."""
        self.by_id = {tuple(e.edge_id for e in p.edges): p for p in self.paths}
        chosen = [(self.by_id[p.path], p.feature.split(".", 1)[1]) for p in self.selected]
        self.asked = list(dict.fromkeys([*chosen, *[(p, None) for p, _ in chosen]]))
        truth = lambda: quality.exact_iq(self.repo, self.base_frame, self.asked).collect()  # at most two rows a training pair
        found, scores = at_once(self.repo.spark, [truth, lambda: self._scored(chosen)])
        self.exact = {(r["path_id"], r["feature"]): r["iq"] for r in found}
        self.known = self._scaled(scores)

    def _train(self) -> None:
        s, asked = self.settings, self.asked
        width = len(INPUTS if s.inputs == "paper" else EXTENDED)
        self.model = SequenceModel(epochs=s.epochs, seed=s.seed).fit([self.steps.sequence(p, f)[:, :width] for p, f in asked], [self.exact[p.path_id, f] for p, f in asked])
        self.estimates: dict[tuple[str, str | None], float] = {}
        self.importance = self._spread()

    def estimate_iq(self, path: JoinPath, feature: str | None = None) -> float:
        key, kind = (path.path_id, feature), self.settings.iq_estimator
        if kind == "exact":
            if key not in self.exact:
                asked = [(path, f) for f in (None, *self.features.get(path.last, ()))]
                self.exact |= {(r["path_id"], r["feature"]): r["iq"] for r in quality.exact_iq(self.repo, self.base_frame, asked).collect()}
            return self.exact[key]
        if kind == "product":
            return float(np.prod([self.steps.edges[e.edge_id]["transitivity"] for e in path.edges]))
        if key not in self.estimates:
            width = len(INPUTS if self.settings.inputs == "paper" else EXTENDED)
            self.estimates[key] = float(self.model.predict([self.steps.sequence(path, feature)[:, :width]])[0])
        return self.estimates[key]

    def score_columns(self, df: DataFrame, names: Sequence[str]) -> dict[str, float]:
        """Signed closed-form score of columns alone, numbers in bins; one job for all."""
        numeric = [n for n in names if isinstance(df.schema[n].dataType, T.NumericType)]
        if numeric:
            ends = df.agg(*[F.min(n).cast("double").alias(f"lo_{n}") for n in numeric], *[F.max(n).cast("double").alias(f"hi_{n}") for n in numeric]).first()
            df = df.withColumns({n: utility.equal_width(F.col(n).cast("double"), ends[f"lo_{n}"] or 0.0, ends[f"hi_{n}"] or 0.0, self.settings.bins) for n in numeric})
        return {r["feature"]: r["score"] for r in utility.closed_form(df, self.base.label, names, self.base.metric).collect()}

    def _scored(self, chosen: Sequence[tuple[JoinPath, str]]) -> dict[tuple[JoinPath, str] | None, float]:
        """Closed-form scores of the selected columns alone, and (under None) of knowing nothing."""
        plan = list(dict.fromkeys(chosen))
        base = self.base_frame.select(self.base.key, self.base.label, *{p.edges[0].left_col for p, _ in plan} - {self.base.key, self.base.label})
        table, _ = integrate(self.repo, base, plan)
        names = {f"{p.last}__{c}__{i}": (p, c) for i, (p, c) in enumerate(plan, 1)} | {"nothing known": None}
        table = written(table.select(self.base.label, *[n for n in names if names[n]], F.lit("1").alias("nothing known")), "measured")  # read twice: for the ends of numbers, and for scores
        return {names[n]: score for n, score in self.score_columns(table, list(names)).items()}

    def _scaled(self, scores: Mapping[tuple[JoinPath, str] | None, float]) -> dict[str, float]:
        """Importance of the selected features: gain scaled to full coverage, the largest over their paths."""
        self.base_score = scores[None]
        known: dict[str, float] = {}
        for at, score in scores.items():
            if at:
                p, c = at
                iq = self.exact[p.path_id, c]
                known[f"{p.last}.{c}"] = max(known.get(f"{p.last}.{c}", -np.inf), (score - self.base_score) / iq if iq else 0.0)
        return known

    def _spread(self) -> dict[str, float]:
        """Importance of every feature: as measured, or the cosine-weighted mean over the measured ones of its cluster."""
        unit = {f: v / (np.linalg.norm(v) or 1.0) for f, v in self.vectors.items()}
        out = {}
        for f in self.vectors:
            members = [g for g in self.known if self.clusters[g] == self.clusters[f]]
            out[f] = self.known[f] if f in self.known else float(np.mean([self.known[g] * float(unit[f] @ unit[g]) for g in members])) if members else 0.0
        return out

    def candidates(self, heap_size: int, **options) -> tuple[list[search.Candidate], search.SearchStats]:
        s = self.settings
        feature_iq = self.estimate_iq if s.iq_level == "feature" else None
        return search.search(self.graph, self.base.table, self.features, self.estimate_iq, self.importance, heap_size=heap_size, **({"t_iq": s.t_iq, "max_hops": s.max_hops, "clamp": s.clamp, "feature_iq": feature_iq} | options))

    def plan(self, budget: int | None = None, heap_size: int | None = None) -> tuple[list[tuple[search.Candidate, float]], search.SearchStats]:
        """(candidates with their gains when taken, search counters): what exploit integrates."""
        s = self.settings
        budget = budget or s.budget
        with self._timed("search"):
            found, stats = self.candidates(heap_size or s.heap_factor * budget)
            if s.refine:
                return search.refine(found, budget, self.clusters, self.vectors, decay=s.decay), stats
            once = search.search_exhaustive(found, budget)
            return [(c, c.gain) for c in once], stats

    def exploit(self, budget: int | None = None) -> Result:
        plan, stats = self.plan(budget)
        table, joins = integrate(self.repo, self.base_frame, [(c.path, c.feature.split(".", 1)[1]) for c, _ in plan])
        return Result(plan, table, joins, stats, self.base_score)

    def update(self, tables: Mapping[str, DataFrame], features: Mapping[str, Sequence[str]] | None = None, min_containment: float = 0.1) -> bool:
        """Takes changed and new tables in; true if the plan by the fitted estimators differs.  Nothing is trained anew.

        A table outside the graph is joined in: its key-like columns are compared with
        the key columns of the graph, edges are added where one contains enough of the
        other, and its columns (``features``, or all but the keys) are represented, put
        to the nearest cluster, and given an estimated importance.
        """
        before = [c.order() for c, _ in self.plan()[0]]
        self.repo.extra.update(tables)
        new = [t for t in tables if t not in self.graph.tables()]
        for t in new:
            self._admit(t, (features or {}).get(t), min_containment)
        self.paths = self.graph.paths(self.base.table, self.settings.max_hops)
        self.by_id = {tuple(e.edge_id for e in p.edges): p for p in self.paths}
        touched = [e for e in self.graph.edges if (e.left in tables or e.right in tables)]
        self.steps.forget(touched)
        self.steps.add(self.repo, [e for p in self.paths for e in p.edges], ways_of(self.paths, self.features))
        if touched:
            self.exact, self.estimates = {}, {}
        return [c.order() for c, _ in self.plan()[0]] != before

    def _admit(self, table: str, columns: Sequence[str] | None, min_containment: float) -> None:
        """Adds a new table to the graph and its columns to the clusters."""
        known = {(t, c) for e in self.graph.edges for t, c in ((e.left, e.left_col), (e.right, e.right_col))}
        own = edge_stats.joinable_columns(self.repo, [table])
        found = edge_stats.discover_edges(self.repo, [*sorted(known), *own], min_containment).where(F.col("lcol").startswith(f"{table}.")).collect()  # column pairs
        edges = [JoinEdge(f"new {r['rcol']}={r['lcol']};", *r["rcol"].split(".", 1), *r["lcol"].split(".", 1)) for r in found if not r["rcol"].startswith(f"{table}.")]
        declared = [e for e in self.graph.edges if not e.edge_id.endswith("r")]
        self.graph = JoinGraph([*declared, *edges])
        frame = self.repo.table(table)
        distinct = frame.agg(F.count(F.lit(1)).alias("rows"), *[F.approx_count_distinct(c, 0.02).alias(c) for c in frame.columns]).first()
        keys = {e.right_col for e in edges if distinct[e.right_col] >= 0.9 * distinct["rows"]}  # columns of few values may describe as well as join
        chosen = tuple(columns or [c for c in frame.columns if c not in keys])
        self.features = {**self.features, table: chosen}
        if not chosen:
            return
        rows = representation.represent(representation.serialized_columns(self.repo, {table: chosen})).collect()  # one row a column
        unit = lambda v: v / (np.linalg.norm(v) or 1.0)
        for r in rows:
            v = np.array(r["repr"])
            near = [(float(unit(v) @ unit(self.vectors[centre])), c) for c, centre in self.centroids.items()]
            close = max(near, default=(0.0, -1))
            if close[0] < self.settings.eps:
                close = (1.0, max(self.centroids, default=-1) + 1)
                self.centroids[close[1]] = r["feature_id"]
            self.vectors[r["feature_id"]], self.clusters[r["feature_id"]] = v, close[1]
        self.importance = self._spread()


def single_gain(repo: Repository, base: DataFrame, label: str, path: JoinPath, feature: str) -> float:
    """Closed-form gain of one feature through one path."""
    table = augment(repo, base, path, feature, name="value found").withColumn("nothing known", F.lit("1"))
    rows = {r["feature"]: r["score"] for r in utility.majority_accuracy(table, label, ["value found", "nothing known"]).collect()}
    return rows["value found"] - rows["nothing known"]

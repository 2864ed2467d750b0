"""Re-implementations of the compared systems, from public descriptions, over one task interface.

A task scores a set of candidate columns (``score(columns) -> float``, higher is better)
and knows each column's table, its distance, which tables join, and a profile.  Every
call of score with a new set counts as a model fit.  Constants are ours.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.repository import EDGES, JoinEdge, Repository, as_key


@dataclass
class Task:
    """A base table's task: candidate columns with their tables, a utility score of column sets, forests with noise.

    ``reach`` has, for each table, the tables that one of its joins leads to; the base is
    the empty name.  ``profile`` describes a column by numbers that need no model:
    coverage, kinds of values, association with the label on a few rows, and so on.
    ``ranking`` has the shares by which tables are ranked before they are joined.
    """

    features: Sequence[str]
    table: Mapping[str, str]
    hops: Mapping[str, int]
    scorer: Callable[[tuple[str, ...]], float]
    profile: Mapping[str, Sequence[float]] = field(default_factory=dict)
    reach: Mapping[str, Sequence[str]] = field(default_factory=dict)
    forests: Callable[[Sequence[str], int, int], tuple[Mapping[str, float], Sequence[float]]] | None = None
    ranking: Mapping[str, float] = field(default_factory=dict)
    relevance: Mapping[str, float] = field(default_factory=dict)
    coverage: Mapping[str, float] = field(default_factory=dict)
    fits: int = 0
    known: dict[tuple[str, ...], float] = field(default_factory=dict)

    def score(self, features: Sequence[str]) -> float:
        key = tuple(sorted(features))
        if key not in self.known:
            self.fits += 1
            self.known[key] = self.scorer(key)
        return self.known[key]

    def open_tables(self, joined: Sequence[str]) -> set[str]:
        """Tables that a join leads to from the base or from a joined table."""
        return {t for at in ("", *joined) for t in self.reach.get(at, ())}


def base_only(task: Task) -> list[str]:
    return []


def join_all(task: Task, budget: int) -> list[str]:
    """Every column one join away, in order, up to the budget."""
    return sorted(f for f in task.features if task.hops[f] == 1)[:budget]


def given_relevance(task: Task, budget: int) -> list[str]:
    """The columns that a user's relevance ranks first."""
    return sorted(task.features, key=lambda f: (-task.relevance.get(f, 0.0), f))[:budget]


def noise_injection(task: Task, budget: int, *, tables: int = 4, rounds: int = 10, share: float = 0.2, seed: int = 0, thresholds: Sequence[float] = (0.5, 0.6, 0.7, 0.8, 0.9)) -> list[str]:
    """Columns of the best-ranked tables that outrank injected noise often enough.

    Tables one join away are ranked by how much of the base they cover.  Each round puts
    random columns, a fifth as many as there are columns, among the joined ones and
    trains a forest over all of them; a column wins a round if it matters more than
    every random one.  The threshold of survival is chosen by score.
    """
    near = sorted({task.table[f] for f in task.features if task.hops[f] == 1}, key=lambda t: (-task.ranking.get(t, 0.0), t))[:tables]
    pool = sorted(f for f in task.features if task.table[f] in near and task.hops[f] == 1)
    if not pool:
        return []
    wins, weight = dict.fromkeys(pool, 0), dict.fromkeys(pool, 0.0)
    for r in range(rounds):
        task.fits += 1
        found, noise = task.forests(pool, max(1, math.ceil(share * len(pool))), seed + r)
        for f in pool:
            wins[f] += found[f] > max(noise)
            weight[f] += found[f]
    plans = [sorted((f for f in pool if wins[f] / rounds >= t), key=lambda f: (-wins[f], -weight[f], f))[:budget] for t in thresholds]
    return max(plans, key=lambda p: (task.score(p), -len(p)))


def bandit_explorer(task: Task, episodes: int, budget: int, *, c: float = math.sqrt(2), seed: int = 0) -> list[str]:
    """Arms are tables in reach; upper confidence bounds on the gain of adding one of their columns.

    A table is in reach if it joins the base or a table of a column chosen before.
    """
    rng = np.random.default_rng(seed)
    chosen: list[str] = []
    pulls: dict[str, int] = {}
    gains: dict[str, float] = {}
    best = start = task.score(())
    for step in range(1, episodes + 1):
        reached = task.open_tables([task.table[f] for f in chosen])
        open_columns = [f for f in task.features if f not in chosen and task.table[f] in reached]
        arms = sorted({task.table[f] for f in open_columns})
        if not arms or len(chosen) >= budget:
            break
        arm = max(arms, key=lambda a: (math.inf if not pulls.get(a) else gains[a] / pulls[a] + c * math.sqrt(math.log(step) / pulls[a]), a))
        own = sorted(f for f in open_columns if task.table[f] == arm)
        f = own[int(rng.integers(len(own)))]
        score = task.score([*chosen, f])
        reward = max(-1.0, min(1.0, (score - best) / max(1e-9, abs(start))))
        pulls[arm], gains[arm] = pulls.get(arm, 0) + 1, gains.get(arm, 0.0) + reward
        if reward > 0:
            chosen.append(f)
            best = score
    return chosen


def network_explorer(task: Task, episodes: int, budget: int, *, hidden: int = 16, rate: float = 0.05, discount: float = 0.9, seed: int = 0) -> list[str]:
    """A small value network picks the next column or stops; replayed updates.

    The state is the set of joined columns, the coverage of the last one and the last gain.
    """
    rng = np.random.default_rng(seed)
    names = sorted(task.features)
    n = len(names)
    w1, w2 = rng.normal(0, 0.3, (n + 3, hidden)), rng.normal(0, 0.3, (hidden, n + 1))
    memory: list[tuple[np.ndarray, int, float, np.ndarray, list[int], bool]] = []
    start = task.score(())
    best: tuple[float, list[str]] = (start, [])
    scale = max(1e-9, abs(start))

    def values(state: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        mid = np.tanh(np.append(state, 1.0) @ w1)
        return mid @ w2, mid

    def moves(state: np.ndarray) -> list[int]:
        taken = {names[i] for i in range(n) if state[i]}
        reached = task.open_tables([task.table[f] for f in taken])
        return [*[i for i in range(n) if not state[i] and task.table[names[i]] in reached], n]

    for episode in range(episodes):
        explore = max(0.1, 1.0 - episode / max(1, episodes - 1))
        state, score = np.zeros(n + 2), start
        for _ in range(budget):
            free = moves(state)
            q, _ = values(state)
            action = int(rng.choice(free)) if rng.random() < explore else max(free, key=lambda i: q[i])
            after = state.copy()
            reward = 0.0
            if action < n:
                after[action] = 1
                new = task.score([names[i] for i in range(n) if after[i]])
                reward, score = (new - score) / scale, new
                after[n], after[n + 1] = task.coverage.get(names[action], 0.0), np.clip(reward, -1, 1)
            memory.append((state, action, reward, after, moves(after), action == n))
            state = after
            if action == n:
                break
        best = max(best, (score, [names[i] for i in range(n) if state[i]]), key=lambda b: (b[0], -len(b[1])))
        for k in rng.integers(0, len(memory), size=min(32, len(memory))):
            s, a, r, s2, ahead, done = memory[-500:][int(k) % len(memory[-500:])]
            q, mid = values(s)
            target = r + (0.0 if done else discount * float(max(values(s2)[0][i] for i in ahead)))
            error = q[a] - target
            grad_mid = w2[:, a] * error * (1 - mid**2)
            w2[:, a] -= rate * error * mid
            w1 -= rate * np.outer(np.append(s, 1.0), grad_mid)
    return best[1]


def profile_clusters(profiles: np.ndarray, clusters: int, seed: int = 0, rounds: int = 20) -> np.ndarray:
    """Cluster of every profile: standardised vectors, means moved to their members, farthest first to begin with."""
    x = (profiles - profiles.mean(axis=0)) / np.maximum(profiles.std(axis=0), 1e-9)
    rng = np.random.default_rng(seed)
    centres = [x[int(rng.integers(len(x)))]]
    while len(centres) < min(clusters, len(x)):
        centres.append(x[int(np.argmax(np.min([((x - c) ** 2).sum(axis=1) for c in centres], axis=0)))])
    middle = np.array(centres)
    for _ in range(rounds):
        member = ((x[:, None] - middle[None]) ** 2).sum(axis=2).argmin(axis=1)
        middle = np.array([x[member == k].mean(axis=0) if (member == k).any() else middle[k] for k in range(len(middle))])
    return member


def goal_feedback(task: Task, queries: int, budget: int, *, clusters: int = 4, seed: int = 0) -> list[str]:
    """Clusters of like profiles, sampled by their posterior success; kept if the set's score rises; then thinned.

    Columns one join away only.
    """
    rng = np.random.default_rng(seed)
    near = sorted(f for f in task.features if task.hops[f] == 1)
    if not near:
        return []
    profile = np.array([[*task.profile.get(f, (0.0,))] for f in near], dtype=float)
    member = dict(zip(near, profile_clusters(profile, clusters, seed).tolist(), strict=True))
    wins, losses = np.ones(clusters), np.ones(clusters)
    chosen: list[str] = []
    best, left = task.score(()), set(near)
    for _ in range(queries):
        live = [k for k in range(clusters) if any(member[f] == k for f in left)]
        if not live or len(chosen) >= budget:
            break
        k = max(live, key=lambda i: rng.beta(wins[i], losses[i]))
        own = sorted(f for f in left if member[f] == k)
        f = own[int(rng.integers(len(own)))]
        left.discard(f)
        score = task.score([*chosen, f])
        if score > best:
            chosen.append(f)
            best = score
            wins[k] += 1
        else:
            losses[k] += 1
    for f in list(chosen):
        if task.score([g for g in chosen if g != f]) >= best:
            chosen.remove(f)
            best = task.score(chosen)
    return chosen


#: Aggregates of numbers, of any column, and parts of times.
NUMBER_FUNCTIONS = ("sum", "avg", "min", "max", "stddev_pop", "skewness")
VALUE_FUNCTIONS = ("n_unique", "mode")
DATE_PARTS = ("month", "year", "weekday")


def path_aggregation(repo: Repository, base: DataFrame, edges: Sequence[JoinEdge], depth: int, functions: Sequence[str] = ("count", "sum", "avg", "min", "max", "stddev_pop"), budget: int | None = None) -> DataFrame:
    """The base with stacked aggregates of the columns of tables up to ``depth`` joins away.

    Aggregation runs from the leaves to the base, one grouped pass an edge.  Numbers get
    the NUMBER_FUNCTIONS, all other columns but keys n_unique and mode, times the average
    of the DATE_PARTS, as far as ``functions`` names them.  Of the columns made, in the
    order of tables, columns and functions, the first ``budget`` are kept.
    """
    keys = {c for e in (*EDGES, *edges) for c in (e.left_col, e.right_col)}
    mode = lambda c: F.mode(c, True)
    parts = {"month": F.month, "year": F.year, "weekday": F.weekday}

    def different(f: T.StructField) -> Column:
        """How many values; where the mode holds a key's values anyway, as a set, which spares a copy of every row for each column."""
        if "mode" not in functions:
            return F.count_distinct(F.col(f.name))
        value = (F.col(f.name) + F.lit(0.0)).cast("string") if isinstance(f.dataType, T.FloatType | T.DoubleType) else F.col(f.name)  # one zero, one NaN
        return F.size(F.collect_set(value)).cast("long")

    def stacked(edge: JoinEdge, visited: tuple[str, ...], level: int, kind: str) -> DataFrame:
        df = repo.table(edge.right)
        if level < depth:
            for e in edges:
                if e.left == edge.right and e.right not in visited:
                    own = repo.kind(e)
                    ahead = stacked(e, (*visited, e.right), level + 1, own)
                    df = df.join(ahead.withColumnRenamed("key", "__k"), as_key(df[e.left_col], own) == F.col("__k"), "left").drop("__k")
        made = [F.count(F.lit(1)).alias(f"{edge.right}__count")] if "count" in functions else []
        for f in df.schema.fields:
            c = f.name
            if c in keys:
                continue
            name = lambda fn, c=c: f"{edge.right}__{fn}_{c}"
            if isinstance(f.dataType, T.NumericType):
                made += [F.expr(f"{fn}(`{c}`)").alias(name(fn)) for fn in functions if fn in NUMBER_FUNCTIONS]
            elif isinstance(f.dataType, T.DateType | T.TimestampType | T.TimestampNTZType):
                made += [F.avg(parts[fn](c)).alias(name(fn)) for fn in functions if fn in DATE_PARTS]
            if isinstance(f.dataType, T.AtomicType):
                made += [(different(f) if fn == "n_unique" else mode(F.col(c))).alias(name(fn)) for fn in functions if fn in VALUE_FUNCTIONS]
        return df.where(F.col(edge.right_col).isNotNull()).groupBy(as_key(edge.right_col, kind).alias("key")).agg(*made)

    own, start = list(base.columns), next(e.left for e in edges)
    for e in edges:
        if e.left == start:
            kind = repo.kind(e, base)
            ahead = stacked(e, (start, e.right), 1, kind)
            base = base.join(ahead.withColumnRenamed("key", "__k"), as_key(base[e.left_col], kind) == F.col("__k"), "left").drop("__k")
    if budget is None:
        return base
    return base.select(*own, *[c for c in base.columns if c not in own][:budget])


def full_disjunction(tables: Sequence[DataFrame], key: str) -> DataFrame:
    """Full outer joins on a key, without rows that another row of the key subsumes.

    Rows of one key combine in all ways; a combination goes only if another one has its
    values and more.  A table that lacks a key gives nulls.
    """
    names = [[c for c in t.columns if c != key] for t in tables]
    out = tables[0]
    for t in tables[1:]:
        out = out.join(t, key, "full")
    rest = [c for own in names for c in own]
    rows = out.distinct()
    # only rows with a null can be subsumed, and only by rows of their key that differ where they are null
    holes = F.greatest(*[F.col(c).isNull().cast("int") for c in rest], F.lit(0)) if rest else F.lit(0)
    partial = rows.where(holes == 1)
    more = rows.select(F.col(key).alias("__key"), *[F.col(c).alias(f"__{c}") for c in rest])
    agree = F.col(key).eqNullSafe(F.col("__key"))
    for c in rest:
        agree = agree & (F.col(c).isNull() | (F.col(c) == F.col(f"__{c}")))
    gained = F.lit(False)
    for c in rest:
        gained = gained | (F.col(c).isNull() & F.col(f"__{c}").isNotNull())
    whole = partial.join(more, agree & gained, "left_anti")
    return rows.where(holes == 0).unionByName(whole)

"""Search for augmentation plans: progressive, exhaustive, greedy; and their refinement.

The search runs over metadata (paths and features of the repository), whose size does
not follow the rows of the tables; estimates come in as functions or frames.
``search_levels`` is the same search as DataFrame levels for repositories whose
frontier outgrows the driver.
"""

from __future__ import annotations

import heapq
import itertools
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.measures import combination_count
from ..sources.repository import JoinPath
from .paths import JoinGraph


@dataclass(frozen=True)
class Candidate:
    feature: str
    path: JoinPath
    fi: float
    iq: float

    @property
    def gain(self) -> float:
        return self.fi * self.iq

    def order(self) -> tuple:
        """Total order, best first: gain, then fewer hops, then names."""
        return (-round(self.gain, 12), len(self.path.edges), self.path.path_id, self.feature)


@dataclass
class SearchStats:
    """Work counters, independent of the machine."""

    expanded: int = 0
    cut_by_quality: int = 0
    skipped_by_bound: int = 0
    scored: int = 0
    inserted: int = 0
    levels: list[int] = field(default_factory=list)


def search(graph: JoinGraph, base: str, features: Mapping[str, Sequence[str]], iq: Callable[[JoinPath], float], fi: Mapping[str, float], *, heap_size: int, t_iq: float = 0.0, max_hops: int | None = None, fi_bound: bool = True, clamp: bool = False, feature_iq: Callable[[JoinPath, str], float] | None = None) -> tuple[list[Candidate], SearchStats]:
    """The heap_size best pairs by estimated gain, level by level.

    A path whose estimated quality lies under ``t_iq`` is dropped with all extensions
    (quality never rises along a path; ``clamp`` enforces that on estimates).  A
    feature whose importance lies under the worst gain of a full heap is skipped, for
    no quality exceeds 1.  Paths never visit a table twice.  Paths are cut by ``iq`` of
    the path; ``feature_iq``, if given, is the quality of a feature at its end, which
    makes the gain.
    """
    heap: list[tuple] = []
    stats = SearchStats()
    level: list[tuple[tuple, float]] = [((), 1.0)]
    hop = 0
    while level and (max_hops is None or hop < max_hops):
        hop += 1
        ahead = []
        for edges, above in level:
            at = edges[-1].right if edges else base
            for e in graph.neighbours(at):
                if e.right == base or any(e.right == x.right for x in edges):
                    continue
                path = JoinPath((*edges, e))
                stats.expanded += 1
                quality = min(above, iq(path)) if clamp else iq(path)
                if quality < t_iq:
                    stats.cut_by_quality += 1
                    continue
                ahead.append((path.edges, quality))
                for name in features.get(e.right, ()):
                    importance = fi.get(f"{e.right}.{name}", 0.0)
                    bound = heap[0][1].gain if len(heap) >= heap_size else -np.inf
                    if fi_bound and importance < bound:
                        stats.skipped_by_bound += 1
                        continue
                    c = Candidate(f"{e.right}.{name}", path, importance, min(quality, feature_iq(path, name)) if feature_iq and clamp else feature_iq(path, name) if feature_iq else quality)
                    stats.scored += 1
                    entry = (_Worst(c.order()), c)
                    if len(heap) < heap_size:
                        heapq.heappush(heap, entry)
                        stats.inserted += 1
                    elif heap[0][0] < entry[0]:
                        heapq.heapreplace(heap, entry)
                        stats.inserted += 1
        stats.levels.append(len(ahead))
        level = ahead
    return sorted((c for _, c in heap), key=Candidate.order), stats


class _Worst(tuple):
    """A key whose smallest element is the worst candidate."""

    def __lt__(self, other):
        return tuple.__gt__(self, other)


def search_levels(pairs: DataFrame, iq: DataFrame, fi: DataFrame, *, heap_size: int, t_iq: float = 0.0) -> DataFrame:
    """The best pairs (feature_id, path_id, hops, fi, iq, ug) from frames of pairs, qualities and importances.

    A path counts only if every prefix of it reaches ``t_iq``, as in the level search.
    """
    prefixes = iq.select("path_id", F.explode(F.transform(F.sequence(F.lit(1), F.size(F.split("path_id", ">"))), lambda k: F.array_join(F.slice(F.split("path_id", ">"), F.lit(1), k), ">"))).alias("prefix"))
    worst = prefixes.join(iq.select(F.col("path_id").alias("prefix"), F.col("iq").alias("q")), "prefix").groupBy("path_id").agg(F.min("q").alias("least"))
    alive = worst.where(F.col("least") >= t_iq).select("path_id")
    scored = pairs.join(iq, "path_id").join(alive, "path_id", "left_semi").join(F.broadcast(fi), "feature_id").withColumn("ug", F.round(F.col("fi") * F.col("iq"), 12))
    return scored.orderBy(F.desc("ug"), "hops", "path_id", "feature_id").limit(heap_size)


def search_greedy(candidates: Sequence[Candidate], budget: int) -> list[Candidate]:
    """By importance alone: for each feature the path with fewest joins (ties by quality), then the first ``budget``."""
    best: dict[str, Candidate] = {}
    for c in sorted(candidates, key=lambda c: (len(c.path.edges), -round(c.iq, 12), c.path.path_id)):
        best.setdefault(c.feature, c)
    return sorted(best.values(), key=lambda c: (-round(c.fi, 12), c.feature))[:budget]


def search_exhaustive(candidates: Sequence[Candidate], budget: int, *, enumerate_up_to: int = 0) -> list[Candidate]:
    """The plan of at most ``budget`` features with the largest summed gain.

    The objective adds up over features, so the best plan takes each feature's best
    path and of those the ``budget`` largest positive gains: exchanging any member for
    one left out cannot raise the sum.  Up to ``enumerate_up_to`` combinations are
    enumerated literally instead.
    """
    best: dict[str, Candidate] = {}
    for c in sorted(candidates, key=Candidate.order):
        best.setdefault(c.feature, c)
    ranked = [c for c in sorted(best.values(), key=Candidate.order) if c.gain > 0]
    if combination_count(len(ranked), 1, min(budget, len(ranked))) <= enumerate_up_to:
        return enumerate_plans(candidates, budget)[0]
    return ranked[:budget]


def enumerate_plans(candidates: Sequence[Candidate], budget: int) -> tuple[list[Candidate], int]:
    """(best plan, plans scored): every choice of at most ``budget`` features with a path each, literally.

    For small repositories: the number of plans explodes.  Ties go to the first in order.
    """
    by_feature: dict[str, list[Candidate]] = {}
    for c in sorted(candidates, key=Candidate.order):
        by_feature.setdefault(c.feature, []).append(c)
    best, value, scored = [], 0.0, 0
    for n in range(1, min(budget, len(by_feature)) + 1):
        for chosen in itertools.combinations(by_feature, n):
            for plan in itertools.product(*[by_feature[f] for f in chosen]):
                scored += 1
                gain = sum(c.gain for c in plan)
                if gain > value + 1e-12:
                    best, value = list(plan), gain
    return best, scored


def refine(candidates: Sequence[Candidate], budget: int, clusters: Mapping[str, int], vectors: Mapping[str, np.ndarray], *, decay: str = "printed", stop_when_nonpositive: bool = False) -> list[tuple[Candidate, float]]:
    """(candidate, gain when taken): repeatedly the largest gain, then less for what is like it.

    After a pick, candidates of its cluster get the importance decayed by the members
    chosen so far: printed, the mean of a chosen member's importance times one minus
    the cosine to it; scaled, their own importance times the mean of one minus cosine.
    """
    unit = {f: np.asarray(v, dtype=float) / (np.linalg.norm(v) or 1.0) for f, v in vectors.items()}
    left = [(c, c.fi) for c in sorted(candidates, key=Candidate.order)]
    chosen: list[tuple[Candidate, float]] = []
    members: dict[int, list[Candidate]] = {}
    while left and len(chosen) < budget:
        k = min(range(len(left)), key=lambda i: (-round(left[i][1] * left[i][0].iq, 12), left[i][0].order()))
        c, fi = left.pop(k)
        if stop_when_nonpositive and fi * c.iq <= 0:
            break
        chosen.append((c, fi * c.iq))
        own = members.setdefault(clusters[c.feature], [])
        own.append(c)
        for i, (d, _) in enumerate(left):
            if clusters[d.feature] == clusters[c.feature]:
                apart = [1 - float(unit[d.feature] @ unit[m.feature]) for m in own]
                left[i] = d, (float(np.mean([m.fi * a for m, a in zip(own, apart, strict=True)])) if decay == "printed" else d.fi * float(np.mean(apart)))
    return chosen

"""Connected components of an edge table, by repeated hooking and contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .frames import Workspace


def _canonical(edges: DataFrame) -> DataFrame:
    return edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _roots(hooks: DataFrame, work: Workspace, name: str) -> DataFrame:
    """Pointers (node, root) followed to their ends by doubling."""
    step = 0
    while True:
        ahead = hooks.select(F.col("node").alias("root"), F.col("root").alias("next"))
        jumped = work.keep(hooks.join(ahead, "root", "left").select("node", F.coalesce("next", "root").alias("root"), F.col("next").isNotNull().alias("moved")), f"{name}-{step}")
        if step:
            work.forget(f"{name}-{step - 1}")
        moved = not jumped.where("moved").isEmpty()
        hooks, step = jumped.select("node", "root"), step + 1
        if not moved:
            return hooks


def connected(edges: DataFrame, work: Workspace, name: str = "cc") -> DataFrame:
    """(node, root) for every node of the edges (a, b); nodes of one component share a root.

    Each round hooks every node to its smallest smaller neighbour, follows the hooks
    to their roots and contracts the edges to roots, which at least halves the
    components that still have edges.  No group is gathered in one place.
    """
    edges = work.keep(_canonical(edges), f"{name}-edges-0")
    labels: DataFrame | None = None
    step = 0
    while not edges.isEmpty():
        hooks = edges.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("root"))
        roots = _roots(work.keep(hooks, f"{name}-hooks-{step}"), work, f"{name}-roots-{step}")
        if labels is None:
            labels = roots
        else:
            moved = labels.join(roots.select(F.col("node").alias("root"), F.col("root").alias("to")), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
            labels = moved.unionByName(roots.join(moved, "node", "left_anti"))
        labels = work.keep(labels, f"{name}-labels-{step}")
        of = lambda c: roots.select(F.col("node").alias(c), F.col("root").alias(f"{c}_root"))  # noqa: B023,E731
        lifted = edges.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("a_root", "a").alias("a"), F.coalesce("b_root", "b").alias("b"))
        step += 1
        edges = work.keep(_canonical(lifted), f"{name}-edges-{step}")
    if labels is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    ends = labels.select("root").distinct().select(F.col("root").alias("node"), "root")
    return labels.unionByName(ends.join(labels, "node", "left_anti"))

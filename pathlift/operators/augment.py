"""Row-preserving augmentation of a base table along join paths.

A path is folded from its far end to the base: the last table is collapsed to one
row a key, then each bridge table is joined with what follows (so bridge rows that
lead nowhere fall away) and collapsed in turn.  Fan-out is removed before every
shuffle, each scan reads two keys and the features only, and the base is joined once.
Plans with several features share the joins of common path prefixes.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.repository import JoinEdge, JoinPath, Repository, as_key

#: Ways of collapsing the matches of a key; ties of mode and first go to the smallest value.
POLICIES = ("first", "mean", "max", "min", "sum", "count", "mode", "latest")


def collapse(column: Column, policy: str, latest_by: Column | None = None) -> Column:
    """An aggregate of a feature's values; all values null gives null (count: 0 becomes null)."""
    if policy == "first":
        return F.min(column)
    if policy in ("mean", "max", "min", "sum"):
        return {"mean": F.avg, "max": F.max, "min": F.min, "sum": F.sum}[policy](column)
    if policy == "count":
        return F.nullif(F.count(column), F.lit(0))
    if policy == "mode":
        return F.mode(column, True)
    if policy == "latest":
        return F.max_by(column, F.when(column.isNotNull(), F.struct(latest_by, column)))
    raise ValueError(f"unknown policy {policy}")


def _fold(repo: Repository, path: Sequence[JoinEdge], features: Mapping[str, Column], policy: str, latest_by: str | None, kind: str | None = None) -> DataFrame:
    """(key, features): what the path leads to from each value of its first edge's right column."""
    edge, rest = path[0], path[1:]
    table = repo.table(edge.right)
    key = as_key(edge.right_col, kind or repo.kind(edge)).alias("key")
    if not rest:
        by = F.col(latest_by) if latest_by else None
        rows = table.where(F.col(edge.right_col).isNotNull())
        out = rows.groupBy(key).agg(*[collapse(c, policy, by).alias(n) for n, c in features.items()])
        return out.where(F.coalesce(*[F.col(n).cast("string") for n in features]).isNotNull())
    ahead = _fold(repo, rest, features, policy, latest_by).withColumnRenamed("key", "onward")
    bridge = table.select(key, as_key(rest[0].left_col, repo.kind(rest[0])).alias("onward")).where("key IS NOT NULL AND onward IS NOT NULL")
    # the bridge row with the smallest onward key that leads to a value
    return bridge.join(ahead, "onward").groupBy("key").agg(*[F.min_by(n, F.when(F.col(n).isNotNull(), F.col("onward"))).alias(n) for n in features])


def augment(repo: Repository, base: DataFrame, path: JoinPath, feature: str, *, name: str | None = None, policy: str = "first", how: str = "left", latest_by: str | None = None) -> DataFrame:
    """The base with one feature carried along a path; missing values are null.

    how: left keeps every base row once; inner drops those without a match; right and
    full also keep far keys that no base row has (their base columns are null).
    """
    name = name or f"{path.last}__{feature}"
    kind = repo.kind(path.edges[0], base)
    frame = _fold(repo, path.edges, {name: F.col(feature)}, policy, latest_by, kind)
    first = path.edges[0].left_col
    joined = base.withColumn("__k", as_key(first, kind)).join(frame.withColumnRenamed("key", "__k"), "__k", how)
    return joined.drop("__k")


def split_augmented(df: DataFrame, feature: str) -> tuple[DataFrame, DataFrame]:
    """Rows with a value and rows without."""
    return df.where(F.col(feature).isNotNull()), df.where(F.col(feature).isNull())


def integrate(repo: Repository, base: DataFrame, plan: Sequence[tuple[JoinPath, str]], *, policy: str = "first") -> tuple[DataFrame, int]:
    """(base with one column a plan entry, joins used): paths with a common prefix share its joins."""
    tree: dict = {}
    for rank, (path, feature) in enumerate(plan, 1):
        node = tree
        for edge in path.edges:
            node = node.setdefault(edge, {})
        node.setdefault("features", []).append((f"{path.last}__{feature}__{rank}", feature))
    joins = 0

    def frame(edge: JoinEdge, node: dict, kind: str) -> tuple[DataFrame, list[str]]:
        nonlocal joins
        own = node.get("features", [])
        children = [(e, n) for e, n in node.items() if e != "features"]
        key = as_key(edge.right_col, kind).alias("key")
        onward = {e: f"__on{i}" for i, (e, _) in enumerate(children)}
        rows = repo.table(edge.right).where(F.col(edge.right_col).isNotNull()).select(key, *[F.col(f).alias(n) for n, f in own], *[as_key(e.left_col, repo.kind(e)).alias(c) for e, c in onward.items()])
        aggregates = [collapse(F.col(n), policy).alias(n) for n, _ in own]
        names = [n for n, _ in own]
        for e, n in children:
            ahead, carried = frame(e, n, repo.kind(e))
            joins += 1
            rows = rows.join(ahead.withColumnRenamed("key", onward[e]), onward[e], "left")
            aggregates += [F.min_by(c, F.when(F.col(c).isNotNull(), F.col(onward[e]))).alias(c) for c in carried]
            names += carried
        return rows.groupBy("key").agg(*aggregates), names

    out = base
    for edge, node in tree.items():
        kind = repo.kind(edge, base)
        ahead, _ = frame(edge, node, kind)
        joins += 1
        out = out.withColumn("__k", as_key(edge.left_col, kind)).join(ahead.withColumnRenamed("key", "__k"), "__k", "left").drop("__k")
    return out, joins


def split_wide(df: DataFrame, key: str, groups: Mapping[str, Sequence[str]]) -> dict[str, DataFrame]:
    """A wide table as a core table and one dimension a group, so that their columns lie one hop further.

    Dimensions hold distinct combinations under a hashed id; the core keeps the key,
    the ungrouped columns and the ids.
    """
    grouped = {c for cols in groups.values() for c in cols}
    ids = {name: F.xxhash64(*cols).alias(f"{name}_id") for name, cols in groups.items()}
    out = {name: df.select(ids[name], *cols).distinct() for name, cols in groups.items()}
    out["core"] = df.select(*[c for c in df.columns if c not in grouped], *ids.values())
    return out

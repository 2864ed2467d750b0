"""The join graph, tables in reach, simple paths and feature-path pairs."""

from __future__ import annotations

from collections.abc import Iterable, Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.repository import JoinEdge, JoinPath, both_ways

_EDGES = "edge_id string, left_table string, left_col string, right_table string, right_col string"


class JoinGraph:
    """Tables as vertices, edges walked either way; several edges between two tables are allowed."""

    def __init__(self, edges: Iterable[JoinEdge]):
        self.edges = both_ways(edges)
        self._from: dict[str, list[JoinEdge]] = {}
        for e in self.edges:
            self._from.setdefault(e.left, []).append(e)

    def neighbours(self, table: str) -> Sequence[JoinEdge]:
        return self._from.get(table, [])

    def tables(self) -> list[str]:
        return sorted(self._from)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(e.edge_id, e.left, e.left_col, e.right, e.right_col) for e in self.edges], _EDGES)

    def khop(self, base: str, k: int) -> dict[str, int]:
        """Fewest joins to every table within k hops."""
        found, frontier = {base: 0}, [base]
        for hop in range(1, k + 1):
            frontier = [e.right for t in frontier for e in self.neighbours(t) if found.setdefault(e.right, hop) == hop]
            frontier = list(dict.fromkeys(frontier))
        return found

    def paths(self, base: str, max_hops: int) -> list[JoinPath]:
        """All simple paths from a base, shorter ones first (metadata sized; see enumerate_paths)."""
        level: list[tuple[JoinEdge, ...]] = [()]
        out: list[JoinPath] = []
        for _ in range(max_hops):
            level = [(*p, e) for p in level for e in self.neighbours(p[-1].right if p else base) if e.right not in {base, *(x.right for x in p)}]
            out += [JoinPath(p) for p in level]
        return out


def enumerate_paths(graph: JoinGraph, spark: SparkSession, base: str, max_hops: int) -> DataFrame:
    """(path_id, hops, tables, last_table): simple paths by a frontier join, level by level.

    The frontier meets the edges, which are metadata (broadcast); visited tables are
    kept out by an array test, so levels stay lazy and distributed.
    """
    edges = F.broadcast(graph.frame(spark))
    level = spark.createDataFrame([("", [base], base)], "path_id string, visited array<string>, last_table string")
    out: DataFrame | None = None
    for hop in range(1, max_hops + 1):
        ahead = level.join(edges, level["last_table"] == edges["left_table"]).where(~F.array_contains("visited", F.col("right_table")))
        level = ahead.select(
            F.when(F.col("path_id") == "", F.col("edge_id")).otherwise(F.concat_ws(">", "path_id", "edge_id")).alias("path_id"), F.array_append("visited", F.col("right_table")).alias("visited"), F.col("right_table").alias("last_table")
        )
        rows = level.select("path_id", F.lit(hop).alias("hops"), F.array_join("visited", ">").alias("tables"), "last_table")
        out = rows if out is None else out.unionByName(rows)
    return out


def enumerate_paths_sql(graph: JoinGraph, spark: SparkSession, base: str, max_hops: int) -> DataFrame:
    """As enumerate_paths, by one recursive query."""
    return spark.sql(
        """WITH RECURSIVE p(path_id, hops, tables, last_table) AS (
            SELECT edge_id, 1, concat(left_table, '>', right_table), right_table FROM {edges} WHERE left_table = {base}
            UNION ALL
            SELECT concat(p.path_id, '>', e.edge_id), p.hops + 1, concat(p.tables, '>', e.right_table), e.right_table
            FROM p JOIN {edges} e ON p.last_table = e.left_table
            WHERE p.hops < {hops} AND NOT array_contains(split(p.tables, '>'), e.right_table))
        SELECT * FROM p""",
        edges=graph.frame(spark), base=base, hops=max_hops,
    )


def make_pairs(paths: DataFrame, features: Mapping[str, Sequence[str]]) -> DataFrame:
    """(feature_id, path_id, hops): every path with every feature of its last table."""
    rows = [(t, f"{t}.{c}") for t, cols in features.items() for c in cols]
    names = F.broadcast(paths.sparkSession.createDataFrame(rows, "table string, feature_id string"))  # columns of the repository
    return paths.join(names, paths["last_table"] == names["table"]).select("feature_id", "path_id", "hops")


def repository_statistics(graph: JoinGraph, base: str, features: Mapping[str, Sequence[str]], max_hops: int) -> dict[str, int]:
    """Tables, columns, and features one hop away or further."""
    hops = graph.khop(base, max_hops)
    width = {t: len(features.get(t, ())) for t in hops}
    return {"tables": len(hops) - 1, "columns": sum(w for t, w in width.items() if t != base), "one_hop": sum(w for t, w in width.items() if hops[t] == 1), "distant": sum(w for t, w in width.items() if hops[t] > 1)}

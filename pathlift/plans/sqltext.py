"""SQL texts for DuckDB that repeat what the operators compute; used as oracles."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

from ..operators.edge_stats import CLIP, SMOOTHING
from ..sources.repository import JoinEdge, JoinPath, view_sql


def frm(name: str) -> str:
    return f"{view_sql(name)} AS {name}" if view_sql(name) != name else name


def edge_ctes(edges: Iterable[JoinEdge]) -> str:
    """CTEs hist, spec, j (joined histogram), t (totals), s (statistics by edge)."""
    edges = list(edges)
    columns = sorted({c for e in edges for c in ((e.left, e.left_col), (e.right, e.right_col))})
    hist = "\nUNION ALL ".join(f"SELECT '{t}.{c}' AS col, {c}::BIGINT AS k, count(*) AS c FROM {frm(t)} WHERE {c} IS NOT NULL GROUP BY {c}" for t, c in columns)
    spec = ", ".join(f"('{e.edge_id}', '{e.left}.{e.left_col}', '{e.right}.{e.right_col}')" for e in edges)
    return f"""hist AS ({hist}),
spec(edge_id, lcol, rcol) AS (VALUES {spec}),
lh AS (SELECT edge_id, k, c AS l FROM hist JOIN spec ON col = lcol),
rh AS (SELECT edge_id, k, c AS r FROM hist JOIN spec ON col = rcol),
j AS (SELECT edge_id, k, coalesce(l, 0) AS l, coalesce(r, 0) AS r, (coalesce(l, 0) * coalesce(r, 0))::DOUBLE AS j FROM lh FULL JOIN rh USING (edge_id, k)),
t AS (SELECT edge_id, sum(j) AS n, sum(r)::DOUBLE AS rr, count(*) FILTER (r > 0) AS rk, count(*) FILTER (l > 0) AS lk, count(*) FILTER (l > 0 AND r > 0) AS mk,
    CASE WHEN sum(j) > 0 THEN sum(j * k) / sum(j) END AS mean, CASE WHEN max(l) = min(l) OR max(r) = min(r) THEN 0.0 ELSE corr(l::DOUBLE, r::DOUBLE) END AS pc FROM j GROUP BY edge_id),
b AS (SELECT j.*, t.* EXCLUDE (edge_id), CASE WHEN n > 0 THEN j / n ELSE 0.0 END AS p, (r / rr + {SMOOTHING}) / (1 + rk * {SMOOTHING}) AS p0,
    (CASE WHEN n > 0 THEN j / n ELSE 0.0 END + {SMOOTHING}) / (CASE WHEN n > 0 THEN 1.0 ELSE 0.0 END + rk * {SMOOTHING}) AS p1 FROM j JOIN t USING (edge_id)),
s AS (SELECT edge_id, any_value(mk)::DOUBLE / any_value(rk) AS transitivity, any_value(mk)::DOUBLE / any_value(lk) AS containment,
    coalesce(sum(p * (k - mean) ** 2) FILTER (j > 0), 0.0) AS variance, coalesce(sum(-p * ln(greatest(1 - p, {CLIP}))) FILTER (j > 0), 0.0) AS entropy_printed,
    coalesce(sum(-p * ln(p)) FILTER (j > 0), 0.0) AS entropy_shannon, coalesce(sum(p0 * ln(p0 / p1)) FILTER (r > 0), 0.0) AS kl,
    any_value(pc) AS pearson_key_counts, any_value(n)::BIGINT AS n_joined FROM b GROUP BY edge_id)"""


def reach(path: JoinPath, feature: str | None) -> str:
    """Distinct keys from which a path reaches a row."""
    out = ""
    for i in range(len(path.edges) - 1, -1, -1):
        e = path.edges[i]
        if not out:
            out = f"SELECT {e.right_col} FROM {frm(e.right)}" + (f" WHERE {feature} IS NOT NULL" if feature else "")
        else:
            out = f"SELECT {e.right_col} FROM {frm(e.right)} WHERE {path.edges[i + 1].left_col} IN ({out})"
    return out


def share(base: str, path: JoinPath, feature: str | None) -> str:
    return f"SELECT '{path.path_id}' AS path_id, avg(CASE WHEN {path.edges[0].left_col} IN ({reach(path, feature)}) THEN 1.0 ELSE 0.0 END) AS iq, count(*) AS n FROM {frm(base)}"


def fold(edges: Sequence[JoinEdge], feature: str, policy: str, latest_by: str | None = None) -> str:
    """(key, v): the collapsed far end of a path by key of its first edge."""
    e, rest = edges[0], edges[1:]
    if not rest:
        rows = f"(SELECT {e.right_col} AS key, {feature} AS x{f', {latest_by} AS moment' if latest_by else ''} FROM {frm(e.right)} WHERE {e.right_col} IS NOT NULL)"
        if policy == "mode":
            return f"(SELECT key, x AS v FROM (SELECT key, x, row_number() OVER (PARTITION BY key ORDER BY count(*) DESC, x) AS place FROM {rows} WHERE x IS NOT NULL GROUP BY key, x) WHERE place = 1)"
        agg = {"first": "min(x)", "mean": "avg(x)", "max": "max(x)", "min": "min(x)", "sum": "sum(x)", "count": "nullif(count(x), 0)", "latest": "arg_max(x, (moment, x))"}[policy]
        return f"(SELECT key, {agg} AS v FROM {rows} GROUP BY key HAVING {agg} IS NOT NULL)"
    return f"(SELECT b.key, arg_min(a.v, b.onward) AS v FROM (SELECT {e.right_col} AS key, {rest[0].left_col} AS onward FROM {frm(e.right)}) b JOIN {fold(rest, feature, policy, latest_by)} a ON b.onward = a.key WHERE b.key IS NOT NULL GROUP BY b.key)"


def augmented(base: str, path: JoinPath, feature: str, columns: str, name: str, policy: str = "first", how: str = "LEFT", latest_by: str | None = None) -> str:
    return f"SELECT {columns}, f.v AS {name} FROM {frm(base)} {how} JOIN {fold(path.edges, feature, policy, latest_by)} f ON {path.edges[0].left_col} = f.key"


def uniform(key: str, seed: int = 0) -> str:
    return f"(('0x' || substr(md5('{seed}:' || {key}::VARCHAR), 1, 8))::BIGINT / 4294967296.0)"


def values(rows: Iterable[Sequence], names: str) -> str:
    cell = lambda x: "NULL" if x is None else f"'{x}'" if isinstance(x, str) else str(x)
    return f"(SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(cell, r)) + ')' for r in rows)}) AS v({names}))"

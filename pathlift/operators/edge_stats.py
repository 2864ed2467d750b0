"""Statistics of join edges, from key histograms: no join is ever expanded.

For an edge, the left and right histograms of the two key columns are joined by
key; a key with l left and r right rows stands for l * r joined rows.  All edges go
through the same three steps at once: one histogram for every key column (one scan
and one partially aggregated shuffle a table), one full join by (edge, key), and
grouped sums by edge.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.repository import JoinEdge, Repository, as_key, key_kind, key_struct
from .quality import LEVELS, least_level

SMOOTHING = 1e-6
CLIP = 1e-12


def _number(column: str, kind: str) -> Column:
    """What a key is in moments: numbers and times as numbers, text as nothing."""
    c = F.col(column)
    if kind == "date":
        return F.unix_date(c.cast("date")).cast("double")
    if kind == "timestamp_ntz":
        return F.unix_seconds(c.cast("timestamp")).cast("double")
    return F.lit(None).cast("double") if kind == "string" else c.cast("double")


def key_histogram(repo: Repository, columns: Iterable[tuple[str, str, str]]) -> DataFrame:
    """(col, key, x, c): rows by value of key columns (table, column, kind); nulls never join and are left out.

    ``key`` is comparable across columns of one kind; ``x`` is its number, if it is one.
    """
    own = sorted(set(columns))
    names = F.array(*[F.lit(f"{table}.{column}:{kind}") for table, column, kind in own])
    parts = []
    for table in dict.fromkeys(t for t, _, _ in own):  # one scan a table, and one shuffle for all
        keys = [(c, [F.lit(n).alias("n"), key_struct(c, kind).alias("key"), _number(c, kind).alias("x")]) for n, (t, c, kind) in enumerate(own) if t == table]
        if len(keys) == 1:
            parts.append(repo.table(table).where(F.col(keys[0][0]).isNotNull()).select(*keys[0][1]))
        else:
            cells = F.array(*[F.when(F.col(c).isNotNull(), F.struct(*cell)) for c, cell in keys])
            parts.append(repo.table(table).select(F.explode(F.filter(cells, lambda e: e.isNotNull())).alias("e")).select("e.*"))
    rows = reduce(DataFrame.unionByName, parts).groupBy("n", "key").agg(F.min("x").alias("x"), F.count(F.lit(1)).alias("c"))
    return rows.select(F.get(names, F.col("n")).alias("col"), "key", "x", "c")


def joined_histogram(repo: Repository, edges: Iterable[JoinEdge]) -> DataFrame:
    """(edge_id, key, x, l, r): left and right rows by key of each edge, 0 where there are none."""
    edges = list(edges)
    kinds = {e: repo.kind(e) for e in edges}
    sides = [(e.edge_id, f"{t}.{c}:{kinds[e]}", left) for e in edges for t, c, left in ((e.left, e.left_col, True), (e.right, e.right_col, False))]
    hist = key_histogram(repo, [c for e in edges for c in ((e.left, e.left_col, kinds[e]), (e.right, e.right_col, kinds[e]))])
    met = hist.join(F.broadcast(repo.spark.createDataFrame(sides, "edge_id string, col string, near boolean")), "col")  # metadata
    own = lambda near, c: F.when(F.col("near") == near, F.col(c))
    return met.groupBy("edge_id", "key").agg(
        F.coalesce(F.min(own(True, "x")), F.min(own(False, "x"))).alias("x"), F.coalesce(F.sum(own(True, "c")), F.lit(0)).alias("l"), F.coalesce(F.sum(own(False, "c")), F.lit(0)).alias("r"),
    )


def edge_statistics(repo: Repository, edges: Iterable[JoinEdge]) -> DataFrame:
    """One row an edge: transitivity, containment, variance, both entropies, KL, Pearson of counts, joined rows.

    transitivity: share of the far side's distinct keys that the near side has.
    variance: population variance of the key in the joined rows.
    entropy: of the key in the joined rows, in the printed form -sum(p ln(1 - p)) and
    in Shannon's.  kl: of the far column before the join against after it, with
    additive smoothing over its values.  pearson_key_counts: correlation of the two
    count vectors over all keys, 0 where a vector is constant.  Keys may be numbers,
    dates, times or text; the variance of text is 0.
    """
    rows = joined_histogram(repo, edges).withColumn("j", (F.col("l") * F.col("r")).cast("double"))
    k = F.col("x")
    met = (F.col("l") > 0) & (F.col("r") > 0)
    l, r = F.col("l").cast("double"), F.col("r").cast("double")  # noqa: E741
    one = lambda c: F.sum(F.when(c, 1.0).otherwise(0.0))
    totals = rows.groupBy("edge_id").agg(
        F.sum("j").alias("n"), F.sum(F.col("r").cast("double")).alias("right_rows"), one(F.col("r") > 0).alias("right_keys"), one(F.col("l") > 0).alias("left_keys"), one(met).alias("met_keys"), F.try_divide(F.sum(F.col("j") * k), F.sum("j")).alias("mean"), F.covar_pop(l, r).alias("cov"), F.var_pop(l).alias("vl"), F.var_pop(r).alias("vr"),
        (F.max("l") == F.min("l")).alias("flat_l"), (F.max("r") == F.min("r")).alias("flat_r"),
    )
    both = rows.join(F.broadcast(totals), "edge_id")  # one row an edge
    p = F.try_divide("j", "n")
    before = (F.coalesce(F.try_divide("r", "right_rows"), F.lit(0.0)) + SMOOTHING) / (1 + F.col("right_keys") * SMOOTHING)
    after = (F.coalesce(F.try_divide("j", "n"), F.lit(0.0)) + SMOOTHING) / (F.when(F.col("n") > 0, 1.0).otherwise(0.0) + F.greatest(F.col("right_keys"), F.lit(1.0)) * SMOOTHING)
    joined = F.col("j") > 0
    stats = both.groupBy("edge_id").agg(
        F.first(F.try_divide("met_keys", "right_keys")).alias("transitivity"),
        F.first(F.try_divide("met_keys", "left_keys")).alias("containment"),
        F.sum(F.when(joined, p * F.pow(k - F.col("mean"), F.lit(2)))).alias("variance"),
        F.sum(F.when(joined, -p * F.log(F.greatest(1 - p, F.lit(CLIP))))).alias("entropy_printed"),
        F.sum(F.when(joined, -p * F.log(p))).alias("entropy_shannon"),
        F.sum(F.when(F.col("r") > 0, before * F.log(before / after))).alias("kl"),
        F.first(F.when(F.col("flat_l") | F.col("flat_r"), 0.0).otherwise(F.try_divide("cov", F.sqrt(F.col("vl") * F.col("vr"))))).alias("pearson_key_counts"),
        F.first("n").cast("long").alias("n_joined"),
    )
    return stats.fillna(0.0)


def passage_statistics(repo: Repository, edge: JoinEdge, out_column: str, out_table: str | None = None) -> DataFrame:
    """(pearson, mutual_info) between the key that enters a table and the column that leaves it.

    Rows of the far table count as often as the near side has their key.  Values of
    the leaving column are the cells; without joined rows both are 0.
    """
    kind = repo.kind(edge)
    near = repo.table(edge.left).where(F.col(edge.left_col).isNotNull()).groupBy(as_key(edge.left_col, kind).alias("x")).agg(F.count(F.lit(1)).cast("double").alias("w"))
    far = repo.table(out_table or edge.right).select(as_key(edge.right_col, kind).alias("x"), F.col(out_column).alias("y")).where("x IS NOT NULL AND y IS NOT NULL")
    cells = far.groupBy("x", "y").count().join(near, "x").select("x", "y", (F.col("w") * F.col("count")).alias("w"))
    total = cells.agg(F.sum("w").alias("n"))
    by_x = cells.groupBy("x").agg(F.sum("w").alias("wx"))
    by_y = cells.groupBy("y").agg(F.sum("w").alias("wy"))
    full = cells.join(by_x, "x").join(by_y, "y").crossJoin(F.broadcast(total))  # one row
    x, y, w = F.expr("try_cast(x AS double)"), F.expr("try_cast(y AS double)"), F.col("w")
    s = lambda e: F.sum(w * e)
    n = F.sum("w")
    cov = s(x * y) / n - s(x) / n * (s(y) / n)
    spread = (s(x * x) / n - F.pow(s(x) / n, F.lit(2))) * (s(y * y) / n - F.pow(s(y) / n, F.lit(2)))
    return full.agg(
        F.coalesce(F.when(spread > 1e-12, cov / F.sqrt(F.greatest(spread, F.lit(1e-300)))), F.lit(0.0)).alias("pearson"),
        F.coalesce(F.sum(w / F.col("n") * F.log(w * F.col("n") / (F.col("wx") * F.col("wy")))), F.lit(0.0)).alias("mutual_info"),
    )


@dataclass(frozen=True)
class Leaving:
    """A way through a table: the edge that enters it and the column that leaves it, or that a path ends in."""

    edge: JoinEdge
    column: str


#: Rows a key beyond which a table's cells are folded before they are shuffled by key.
CROWDED = 32


def _spans(repo: Repository, ways: Iterable[Leaving]) -> dict[tuple[str, str], tuple[int, int, dict[str, tuple]]]:
    """By table and entering column: rows with a key, about how many keys, and (least, largest, about how many values) of numeric columns."""
    asked: dict[tuple[str, str], list[str]] = {}
    for w in ways:
        own = asked.setdefault((w.edge.right, w.edge.right_col), [])
        if w.column not in own and isinstance(repo.table(w.edge.right).schema[w.column].dataType, T.NumericType):
            own.append(w.column)
    parts = []
    for i, ((table, column), numeric) in enumerate(asked.items()):
        ends = [F.struct(F.min(y).alias("low"), F.max(y).alias("high"), F.approx_count_distinct(y).alias("values")) for y in (F.col(c).cast("double") for c in numeric)]
        none = F.array().cast("array<struct<low:double,high:double,values:bigint>>")
        parts.append(repo.table(table).where(F.col(column).isNotNull()).agg(F.lit(i).alias("i"), F.count(F.lit(1)).alias("rows"), F.approx_count_distinct(column).alias("different"), (F.array(*ends) if ends else none).alias("ends")))
    found = {r["i"]: r for r in reduce(DataFrame.unionByName, parts).collect()}  # one row a table and key
    return {at: (found[i]["rows"], found[i]["different"], dict(zip(numeric, map(tuple, found[i]["ends"]), strict=True))) for i, (at, numeric) in enumerate(asked.items())}


def leaving_statistics(repo: Repository, ways: Iterable[Leaving], levels: Sequence[int] = (LEVELS,), bins: int = 20) -> DataFrame:
    """(edge_id, column, level, variance, entropy_printed, entropy_shannon, kl, pearson, mutual_info, transitivity, containment, n_joined).

    The statistics of an edge with the column in place of the join column: it is the
    column of the far table by which a path goes on, or the feature in which it ends.
    Rows of the far table count as often as the near side has their key.  Variance and
    entropies are of the column in the joined rows; kl compares it before and after the
    join; Pearson and mutual information pair it with the entering key.  Numbers of more
    than ``bins`` values are cut into that many equal widths where they stand for
    categories.  A row counts only where the column has a value, so transitivity is the
    share of such far keys that the near side has, and containment the share of near
    keys that find a value.  At a level, the far table holds only the keys that a hash
    puts below it.

    One pass over a far table gives the spans of its columns.  In the next, its rows meet
    the near side's key histogram by key, each with the bins of all its columns.  Bins are
    summed from those rows at once; what needs a key's cells folds them to (key, bin)
    first.  Both sums carry the least level of the key, so all levels come out of one pass.
    """
    ways = list(dict.fromkeys(ways))
    kinds = {w.edge: repo.kind(w.edge) for w in ways}
    near = key_histogram(repo, {(e.left, e.left_col, k) for e, k in kinds.items()})
    edges, numbers = {e: i for i, e in enumerate(kinds)}, {w: i for i, w in enumerate(ways)}
    spec = repo.spark.createDataFrame([(edges[e], f"{e.left}.{e.left_col}:{k}") for e, k in kinds.items()], "edge int, col string")
    near = near.join(F.broadcast(spec), "col").select("edge", "key", F.col("x"), F.col("c").cast("double").alias("w"))  # metadata
    spans = _spans(repo, ways)
    parts = []
    for edge, kind in kinds.items():
        table, (rows, different, ends) = repo.table(edge.right), spans[edge.right, edge.right_col]
        items = []
        for way, column in ((k, w.column) for w, k in numbers.items() if w.edge == edge):
            low, high, values = ends.get(column, (None, None, None))
            numeric = isinstance(table.schema[column].dataType, T.NumericType)
            y = F.col(column).cast("double") if numeric else F.lit(None).cast("double")
            width = (F.lit(high).cast("double") - F.lit(low).cast("double")) / bins
            binned = F.when((F.lit(values) > bins) & (width > 0), F.least(F.lit(bins - 1), F.floor((y - F.lit(low).cast("double")) / width)).cast("string")).otherwise(F.col(column).cast("string"))
            items.append(F.when(F.col(column).isNotNull(), F.struct(F.lit(way).alias("way"), binned.alias("bin"), F.lit(1.0).alias("r"), y.alias("sy"), (y * y).alias("syy"))))
        packed = table.where(F.col(edge.right_col).isNotNull()).select(F.lit(edges[edge]).alias("edge"), key_struct(edge.right_col, kind).alias("key"), F.filter(F.array(*items), lambda x: x.isNotNull()).alias("cells"))
        if rows > CROWDED * different:  # few keys: their cells are folded before rows meet by key
            folded = packed.select("edge", "key", F.explode("cells").alias("p")).groupBy("edge", "key", "p.way", "p.bin").agg(*[F.sum(f"p.{c}").alias(c) for c in ("r", "sy", "syy")])
            packed = folded.select("edge", "key", F.array(F.struct("way", "bin", "r", "sy", "syy")).alias("cells"))
        parts.append(packed)
    way = ["edge", "way"]
    log = lambda c: F.when(c > 0, c * F.log(c)).otherwise(0.0)
    # a row travels once, with the cells of all its columns, and meets the near side before they are taken apart
    met = reduce(DataFrame.unionByName, parts).repartition("edge", "key").join(near, ["edge", "key"], "left")
    met = met.select("edge", "key", "x", F.coalesce("w", F.lit(0.0)).alias("w"), least_level(F.col("key")).alias("least"), F.explode("cells").alias("p")).select("*", "p.*")
    at_levels = lambda df: df.withColumn("level", F.explode(F.array(*[F.lit(x) for x in levels]))).where("least <= level")
    # by key: sums that only need the key, and those over its cells
    cells = met.groupBy(*way, "key", "bin", "least").agg(F.first("x").alias("x"), F.first("w").alias("w"), *[F.sum(c).alias(c) for c in ("r", "sy", "syy")])
    weight = F.col("r") * F.col("w")
    keys = cells.groupBy(*way, "key", "least").agg(F.first("x").alias("x"), F.first("w").alias("w"), F.sum(weight).alias("j"), F.sum(log(weight)).alias("cell_log"), F.sum(F.col("sy") * F.col("w")).alias("jy"), F.sum(F.col("syy") * F.col("w")).alias("jyy"))
    by_key = keys.groupBy(*way, "least").agg(
        F.count(F.lit(1)).alias("far_keys"), F.sum((F.col("w") > 0).cast("long")).alias("met_keys"), F.sum("j").alias("j"), F.sum("cell_log").alias("cell_log"), F.sum(log(F.col("j"))).alias("key_log"),
        F.sum(F.col("j") * F.col("x")).alias("jx"), F.sum(F.col("j") * F.col("x") * F.col("x")).alias("jxx"), F.sum("jy").alias("jy"), F.sum("jyy").alias("jyy"), F.sum(F.col("x") * F.col("jy")).alias("jxy"),
    )
    sums = [c for c in by_key.columns if c not in (*way, "least")]
    totals = at_levels(by_key).groupBy(*way, "level").agg(*[F.sum(c).alias(c) for c in sums])
    # by bin: the column's distribution before and after the join
    bins_at = at_levels(met.groupBy(*way, "bin", "least").agg(F.sum("r").alias("r"), F.sum(weight).alias("j"))).groupBy(*way, "level", "bin").agg(F.sum("r").alias("r"), F.sum("j").alias("j"))
    whole = bins_at.groupBy(*way, "level").agg(F.sum("r").alias("all_r"), F.sum("j").alias("all_j"), F.count(F.lit(1)).alias("n_bins"))
    share = bins_at.join(whole, [*way, "level"])
    p = F.coalesce(F.try_divide("j", "all_j"), F.lit(0.0))
    smooth = 1 + F.col("n_bins") * SMOOTHING
    before = (F.col("r") / F.col("all_r") + SMOOTHING) / smooth
    after = (p + SMOOTHING) / F.when(F.col("all_j") > 0, smooth).otherwise(F.col("n_bins") * SMOOTHING)
    spread = share.groupBy(*way, "level").agg(
        F.sum(F.when(p > 0, -p * F.log(F.greatest(1 - p, F.lit(CLIP)))).otherwise(0.0)).alias("entropy_printed"), F.sum(F.when(p > 0, -p * F.log(p)).otherwise(0.0)).alias("entropy_shannon"),
        F.sum(before * F.log(before / after)).alias("kl"), F.sum(log(F.col("j"))).alias("bin_log"),
    )
    near_keys = near.groupBy("edge").agg(F.count(F.lit(1)).alias("near_keys"))
    named = repo.spark.createDataFrame([(k, w.edge.edge_id, w.column) for w, k in numbers.items()], "way int, edge_id string, column string")
    both = totals.join(spread, [*way, "level"]).join(F.broadcast(near_keys), "edge", "left").join(F.broadcast(named), "way")  # one row an edge, and a way
    mean = lambda c: F.try_divide(c, "j")
    vx, vy = mean("jxx") - mean("jx") * mean("jx"), mean("jyy") - mean("jy") * mean("jy")
    cov = mean("jxy") - mean("jx") * mean("jy")
    # sum p ln(p / (p_x p_y)) over cells, from sums of w ln w
    shared = mean("cell_log") + F.log("j") - mean("key_log") - mean("bin_log")
    out = both.select(
        "edge_id", "column", "level", F.greatest(vy, F.lit(0.0)).alias("variance"), "entropy_printed", "entropy_shannon", F.greatest("kl", F.lit(0.0)).alias("kl"),
        F.when((vx > 1e-12 * F.greatest(F.lit(1.0), mean("jxx"))) & (vy > 1e-12 * F.greatest(F.lit(1.0), mean("jyy"))), cov / F.sqrt(vx * vy)).alias("pearson"), F.when(F.col("j") > 0, F.greatest(shared, F.lit(0.0))).alias("mutual_info"),
        F.try_divide("met_keys", "far_keys").alias("transitivity"), F.try_divide("met_keys", "near_keys").alias("containment"), F.col("j").cast("long").alias("n_joined"),
    )
    return out.fillna(0.0)


def joinable_columns(repo: Repository, tables: Iterable[str], *, most_text: int = 64) -> list[tuple[str, str, str]]:
    """(table, column, kind) of the columns that keys could be: whole numbers, dates and short text."""
    out = []
    for t in tables:
        df = repo.table(t)
        kinds = [(f.name, key_kind(f.dataType)) for f in df.schema.fields if isinstance(f.dataType, T.StringType | T.IntegralType | T.DateType)]
        texts = [c for c, k in kinds if k == "string"]
        longest = df.agg(*[F.max(F.length(c)).alias(c) for c in texts]).first() if texts else {}
        out += [(t, c, k) for c, k in kinds if k != "string" or (longest[c] or 0) <= most_text]
    return out


def _kinded(repo: Repository, columns: Iterable[tuple]) -> list[tuple[str, str, str]]:
    return [c if len(c) == 3 else (*c, key_kind(repo.table(c[0]).schema[c[1]].dataType)) for c in columns]


def _overlapping(hist: DataFrame) -> DataFrame:
    """(col): columns whose range of keys overlaps that of a column of another table; the others can join with nothing."""
    table = lambda c: F.substring_index(c, ".", 1)
    ends = hist.groupBy("col").agg(F.min("key").alias("low"), F.max("key").alias("high"))  # one row a column
    a, b = ends.alias("a"), F.broadcast(ends.alias("b"))
    meet = (table("a.col") != table("b.col")) & (F.col("a.low") <= F.col("b.high")) & (F.col("b.low") <= F.col("a.high"))
    return a.join(b, meet, "left_semi").select("col")


def discover_edges(repo: Repository, columns: Iterable[tuple], min_containment: float = 0.1) -> DataFrame:
    """(lcol, rcol, shared, containment) of column pairs by exact value containment.

    Columns are (table, column[, kind]); keys of one kind meet, whatever the exact type.
    Columns whose range meets that of no other table fall away first.  An inverted index
    groups the columns of each value (their number is bounded by the columns given);
    pairs of columns, not of rows, are counted.
    """
    hist = key_histogram(repo, _kinded(repo, columns))
    hist = hist.join(F.broadcast(_overlapping(hist)), "col")  # one row a column
    sizes = hist.groupBy("col").count()
    index = hist.groupBy("key").agg(F.sort_array(F.collect_set("col")).alias("cols"))
    pairs = index.groupBy("cols").count().select(F.explode("cols").alias("lcol"), "cols", "count").select("lcol", F.explode("cols").alias("rcol"), "count").where("lcol <> rcol")
    shared = pairs.groupBy("lcol", "rcol").agg(F.sum("count").alias("shared"))
    found = shared.join(F.broadcast(sizes), F.col("lcol") == F.col("col")).select("lcol", "rcol", "shared", (F.col("shared") / F.col("count")).alias("containment"))  # one row a column
    bare = lambda c: F.substring_index(c, ":", 1)
    found = found.where((F.col("containment") >= min_containment) & (F.col("shared") >= 2) & (F.substring_index("lcol", ".", 1) != F.substring_index("rcol", ".", 1)))
    return found.select(bare("lcol").alias("lcol"), bare("rcol").alias("rcol"), "shared", "containment")


def discover_edges_sketch(repo: Repository, columns: Iterable[tuple], min_containment: float = 0.1) -> DataFrame:
    """As discover_edges, from one theta sketch a column: mergeable, of fixed size, approximate."""
    hist = key_histogram(repo, _kinded(repo, columns)).groupBy("col").agg(F.expr("theta_sketch_agg(xxhash64(key))").alias("s"))
    bare = lambda c: F.substring_index(c, ":", 1)
    a, b = hist.select(bare("col").alias("lcol"), F.col("s").alias("ls")), hist.select(bare("col").alias("rcol"), F.col("s").alias("rs"))
    both = a.join(b, F.col("lcol") != F.col("rcol"))  # columns, not rows
    shared = F.expr("theta_sketch_estimate(theta_intersection(ls, rs))")
    return both.select("lcol", "rcol", shared.alias("shared"), (shared / F.expr("theta_sketch_estimate(ls)")).alias("containment")).where(F.col("containment") >= min_containment)

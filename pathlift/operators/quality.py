"""Integration quality: the share of base rows that find a value through a path."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.measures import hash_uniform
from ..sources.repository import JoinPath, Repository, as_key, key_struct

#: Far keys are thinned by hash into this many levels, where levels are asked for.
LEVELS = 10


def reachable_keys(repo: Repository, path: JoinPath, feature: str | None = None) -> DataFrame:
    """(key): values of the base's first column from which the path reaches a row (with a value of the feature).

    Key sets walk from the tail to the base by semi joins: distinct keys only, no
    payload, and whatever leads nowhere is gone before the next shuffle.
    """
    keys: DataFrame | None = None
    for i in range(len(path.edges) - 1, -1, -1):
        edge = path.edges[i]
        rows = repo.table(edge.right)
        if keys is None:
            rows = rows.where(F.col(feature).isNotNull()) if feature else rows
        else:
            onward = path.edges[i + 1]
            rows = rows.withColumn("onward", as_key(onward.left_col, repo.kind(onward))).join(keys.withColumnRenamed("key", "onward"), "onward", "left_semi")
        keys = rows.where(F.col(edge.right_col).isNotNull()).select(as_key(edge.right_col, repo.kind(edge)).alias("key")).distinct()
    return keys


def _share(repo: Repository, base: DataFrame, path: JoinPath, keys: DataFrame) -> DataFrame:
    found = base.select(as_key(path.edges[0].left_col, repo.kind(path.edges[0], base)).alias("key")).join(keys.withColumn("hit", F.lit(1.0)), "key", "left")
    return found.agg(F.avg(F.coalesce("hit", F.lit(0.0))).alias("iq"), F.count(F.lit(1)).alias("n"))


def least_level(key: Column) -> Column:
    """The first thinning level (1 to LEVELS) at which a key is there; equal for equal keys."""
    return (F.pmod(F.xxhash64(key), F.lit(LEVELS)) + 1).cast("int")


def _reach(repo: Repository, pairs: Sequence[tuple[JoinPath, str | None]]) -> dict[int, tuple[DataFrame, dict[tuple, int]]]:
    """By path length: (tail, key, least) of all suffixes of the pairs of that length, and the suffixes' numbers.

    All pairs walk from their ends to the base together.  A suffix that several pairs
    share is walked once, and a level is one join of the keys reached so far with the
    distinct key pairs of all bridge tables that the level crosses.
    """
    spark = repo.spark
    suffixes = {n: list(dict.fromkeys((p.edges[len(p.edges) - n :], f) for p, f in pairs if len(p.edges) >= n)) for n in range(1, max(len(p.edges) for p, _ in pairs) + 1)}
    numbers = {n: {s: k for k, s in enumerate(own)} for n, own in suffixes.items()}
    ends = []
    for edge in dict.fromkeys(e[0] for e, _ in suffixes[1]):
        key = key_struct(edge.right_col, repo.kind(edge))
        wanted = [(k, f) for (e, f), k in numbers[1].items() if e[0] == edge]
        tails = F.filter(F.array(*[F.when(F.col(f).isNotNull(), F.lit(k)) if f else F.lit(k) for k, f in wanted]), lambda x: x.isNotNull())
        ends.append(repo.table(edge.right).where(F.col(edge.right_col).isNotNull()).select(F.explode(tails).alias("tail"), key.alias("key")))
    reached = reduce(DataFrame.unionByName, ends).distinct().withColumn("least", least_level(F.col("key")))
    out = {1: (reached, numbers[1])}
    for n in range(2, max(suffixes) + 1):
        crossings: dict[tuple, int] = {}
        steps = []
        for (edges, f), k in numbers[n].items():
            into, onward = edges[0], edges[1]
            crossing = (into.right, into.right_col, repo.kind(into), onward.left_col, repo.kind(onward))
            steps.append((numbers[n - 1][edges[1:], f], crossings.setdefault(crossing, len(crossings)), k))
        bridges = [
            repo.table(t).where(F.col(a).isNotNull() & F.col(b).isNotNull()).select(F.lit(c).alias("bridge"), key_struct(a, ka).alias("key"), key_struct(b, kb).alias("onward"))
            for (t, a, ka, b, kb), c in crossings.items()
        ]
        bridge = reduce(DataFrame.unionByName, bridges).distinct()
        step = F.broadcast(spark.createDataFrame(steps, "tail int, bridge int, next int"))  # metadata
        ahead = reached.withColumnRenamed("key", "onward").join(step, "tail").drop("tail")
        reached = ahead.join(bridge, ["bridge", "onward"]).groupBy(F.col("next").alias("tail"), "key").agg(F.min("least").alias("least"))
        out[n] = reached, numbers[n]
    return out


def exact_iq(repo: Repository, base: DataFrame, pairs: Sequence[tuple[JoinPath, str | None]], levels: Sequence[int] | None = None) -> DataFrame:
    """(path_id, feature, iq, n) of pairs, one plan for all.

    With ``levels`` there is a row for each level too (column ``level``): the quality if
    the far table held only the keys that a hash puts below that level of LEVELS.
    """
    pairs = list(dict.fromkeys(pairs))
    firsts = list(dict.fromkeys((p.edges[0].left_col, repo.kind(p.edges[0], base)) for p, _ in pairs))
    counted = [base.select(F.lit(k).alias("start"), key_struct(c, kind).alias("key")).where("key IS NOT NULL") for k, (c, kind) in enumerate(firsts)]
    starts = reduce(DataFrame.unionByName, counted).groupBy("start", "key").agg(F.count(F.lit(1)).alias("c"))
    hits, spec = [], []
    for n, (reached, numbers) in _reach(repo, pairs).items():
        own = [(numbers[p.edges, f], firsts.index((p.edges[0].left_col, repo.kind(p.edges[0], base))), i) for i, (p, f) in enumerate(pairs) if len(p.edges) == n]
        if own:
            at = F.broadcast(repo.spark.createDataFrame(own, "tail int, start int, pair int"))  # metadata
            hits.append(reached.join(at, "tail").select("start", "pair", "key", "least"))
    spec = repo.spark.createDataFrame([(i, p.path_id, f) for i, (p, f) in enumerate(pairs)], "pair int, path_id string, feature string")
    wanted = list(levels or (LEVELS,))
    found = reduce(DataFrame.unionByName, hits).join(starts, ["start", "key"]).groupBy("pair").agg(*[F.sum(F.when(F.col("least") <= x, F.col("c"))).alias(f"c{x}") for x in wanted])
    total = base.agg(F.count(F.lit(1)).alias("n"))
    rows = spec.join(found, "pair", "left").crossJoin(F.broadcast(total))  # one row
    shares = F.explode(F.array(*[F.struct(F.lit(x).alias("level"), F.try_divide(F.coalesce(f"c{x}", F.lit(0)).cast("double"), "n").alias("iq")) for x in wanted]))
    rows = rows.select("path_id", "feature", shares.alias("x"), "n")
    return rows.select("path_id", "feature", *(["x.level"] if levels else []), "x.iq", "n")


def rowwise_iq(repo: Repository, base: DataFrame, path: JoinPath, feature: str) -> DataFrame:
    """Share of joined rows (fan-out kept) that have a value: the reading by rows instead of base rows."""
    rows = base.select(as_key(path.edges[0].left_col, repo.kind(path.edges[0], base)).alias("key"))
    for i, edge in enumerate(path.edges):
        last = i + 1 == len(path.edges)
        on = as_key(edge.right_col, repo.kind(edge, None if i else base)).alias("key")
        far = repo.table(edge.right).select(on, (F.col(feature) if last else as_key(path.edges[i + 1].left_col, repo.kind(path.edges[i + 1]))).alias("next"))
        rows = rows.join(far, "key", "left").select(F.col("next").alias("key"))
    return rows.agg(F.avg(F.col("key").isNotNull().cast("double")).alias("iq"), F.count(F.lit(1)).alias("n"))


def sampled_iq(repo: Repository, base: DataFrame, path: JoinPath, feature: str | None, *, share: float = 0.1, seed: int = 0) -> DataFrame:
    """(iq, n, half_width): IQ over base rows whose first key hashes below a share, with a 95 % half width."""
    part = base.where(hash_uniform(path.edges[0].left_col, seed) < share)
    out = _share(repo, part, path, reachable_keys(repo, path, feature))
    return out.select("iq", "n", (1.96 * F.sqrt(F.try_divide(F.col("iq") * (1 - F.col("iq")), F.col("n")))).alias("half_width"))


def product_of_transitivity(paths: DataFrame, statistics: DataFrame) -> DataFrame:
    """(path_id, iq_product): the chain estimate that multiplies far-side transitivities."""
    steps = paths.select("path_id", F.explode(F.split("path_id", ">")).alias("edge_id"))
    joined = steps.join(F.broadcast(statistics.select("edge_id", "transitivity")), "edge_id")  # one row an edge
    return joined.groupBy("path_id").agg(F.product("transitivity").alias("iq_product"))


def random_iq(path_id: Column | str, seed: int = 0) -> Column:
    """The estimate that knows nothing: uniform by path."""
    return hash_uniform(path_id, seed)


def iq_error(table: DataFrame, estimate: str, truth: str = "iq") -> DataFrame:
    return table.agg(F.avg(F.pow(F.col(estimate) - F.col(truth), F.lit(2))).alias("mse"), F.count(F.lit(1)).alias("n"))

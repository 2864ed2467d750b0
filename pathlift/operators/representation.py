"""Feature vectors from metadata and sampled values, threshold clustering, estimated importance."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..sources.files import written
from ..sources.repository import Repository


#: Statistics of a column that enter its representation.
STATISTICS = ("null_share", "distinct_share", "mean_length", "digit_share", "mean", "deviation", "lowest", "highest", "median", "skew")


def _semantic_type() -> Column:
    """A guess at what a column means, from its type and statistics."""
    return (
        F.when(F.col("kind").isin("date", "timestamp", "timestamp_ntz"), F.lit("time"))
        .when(F.col("distinct_share") > 0.95, F.when(F.col("kind") == "string", F.lit("text")).otherwise(F.when(F.col("whole"), F.lit("identifier")).otherwise(F.lit("quantity"))))
        .when((F.col("distinct") <= 50) | (F.col("distinct_share") < 0.02), F.lit("category"))
        .when(F.col("kind") == "string", F.lit("text"))
        .otherwise(F.lit("quantity"))
    )


def serialized_columns(repo: Repository, features: Mapping[str, Sequence[str]], sample: int = 64, descriptions: Mapping[str, str] | None = None) -> DataFrame:
    """(feature_id, meta, values, stats): what is known of each column.

    meta has its name, type, semantic type and description, if one is given; values its
    first ``sample`` distinct values by hash; stats the numbers of STATISTICS on a log
    scale.  One pass a table: its columns are unpivoted and folded by value.
    """
    parts = []
    for table, columns in features.items():
        df = repo.table(table)
        kinds = {c: df.schema[c].dataType for c in columns}
        number = lambda c, kinds=kinds: F.col(c).cast("double") if isinstance(kinds[c], T.NumericType) else F.lit(None).cast("double")
        entry = [F.struct(F.lit(f"{table}.{c}").alias("feature_id"), F.lit(kinds[c].simpleString()).alias("kind"), F.substring(F.col(c).cast("string"), 1, 64).alias("v"), number(c).alias("x")) for c in columns]
        parts.append(df.select(F.explode(F.array(*entry)).alias("e")).select("e.*"))
    by_value = reduce(DataFrame.unionByName, parts).groupBy("feature_id", "kind", "v").agg(F.count(F.lit(1)).alias("c"), F.max("x").alias("x"))
    n, c, x = F.sum("c"), F.col("c").cast("double"), F.col("x")
    digits = F.length("v") - F.length(F.regexp_replace("v", "[0-9]", ""))
    log = lambda e: F.coalesce(F.signum(e) * F.log1p(F.abs(e)), F.lit(0.0))
    weighed = F.sum(F.when(x.isNotNull(), c))
    mean = F.try_divide(F.sum(c * x), weighed)
    spread = F.sqrt(F.greatest(F.try_divide(F.sum(c * x * x), weighed) - mean * mean, F.lit(0.0)))
    median = F.percentile_approx("x", 0.5)
    profile = by_value.groupBy("feature_id", "kind").agg(
        n.alias("rows"), F.count("v").alias("distinct"), F.try_divide(F.sum(F.when(F.col("v").isNull(), c)), n.cast("double")).alias("null_share"), F.try_divide(F.count("v").cast("double"), F.sum(F.when(F.col("v").isNotNull(), c))).alias("distinct_share"),
        F.avg(F.length("v")).alias("mean_length"), F.try_divide(F.sum(digits).cast("double"), F.sum(F.length("v"))).alias("digit_share"), mean.alias("mean"), spread.alias("deviation"), F.min("x").alias("lowest"), F.max("x").alias("highest"), median.alias("median"),
        F.try_divide(mean - median, spread).alias("skew"), F.coalesce(F.bool_and(x == F.floor(x)), F.lit(False)).alias("whole"),
    )
    order = Window.partitionBy("feature_id").orderBy(F.xxhash64("v"), "v")
    values = by_value.where("v IS NOT NULL").withColumn("place", F.row_number().over(order)).where(F.col("place") <= sample).groupBy("feature_id").agg(F.sort_array(F.collect_list("v")).alias("values"))  # sample values a column
    described = F.coalesce(F.element_at(F.create_map(*[F.lit(y) for pair in (descriptions or {}).items() for y in pair]), F.col("feature_id")), F.lit("")) if descriptions else F.lit("")
    names = F.concat_ws(" ", F.translate("feature_id", ".", " "), "kind", _semantic_type(), described)
    stats = F.array(*[F.coalesce(F.col(s).cast("double"), F.lit(0.0)) if s.endswith("share") else log(F.col(s).cast("double")) for s in STATISTICS])
    return profile.join(values, "feature_id", "left").select("feature_id", names.alias("meta"), F.coalesce("values", F.array().cast("array<string>")).alias("values"), stats.alias("stats"))


def hashed_ngrams(text: str, dim: int, n: int = 3) -> np.ndarray:
    """Unit vector of hashed character n-grams: stands for a text encoder, which is not available offline."""
    out = np.zeros(dim)
    body = f" {text.lower()} "
    for k in range(max(1, len(body) - n + 1)):
        h = xxhash.xxh3_64_intdigest(body[k : k + n])
        out[h % dim] += 1 if h >> 63 else -1
    norm = np.linalg.norm(out)
    return out / norm if norm else out


def represent(serialized: DataFrame, dim: int = 64, encoder=hashed_ngrams, parts: Sequence[str] = ("meta", "data", "stats")) -> DataFrame:
    """(feature_id, repr): unit vectors of metadata, data and statistics joined and normalised."""
    import pandas as pd

    unit = lambda v: v / (np.linalg.norm(v) or 1.0)

    def run(batches):
        for pdf in batches:
            vectors = []
            for meta, values, stats in zip(pdf["meta"], pdf["values"], pdf["stats"], strict=True):
                own = {"meta": lambda m=meta: encoder(m, dim), "data": lambda v=values: encoder(" ".join(v), dim), "stats": lambda s=stats: unit(np.array(list(s), dtype=float))}
                vectors.append(unit(np.concatenate([own[p]() for p in parts])).astype(np.float32).tolist())
            yield pd.DataFrame({"feature_id": pdf["feature_id"], "repr": vectors})

    return serialized.mapInPandas(run, "feature_id string, repr array<float>")


def dot(a: Column | str, b: Column | str) -> Column:
    """Inner product of two arrays in double precision."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column | str, b: Column | str) -> Column:
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a) * dot(b, b)))


def neighbours(features: DataFrame, eps: float, block_rows: int = 2048) -> DataFrame:
    """(a, b, cos) of features with cosine eps or more, itself included.

    Features are dealt into blocks of about ``block_rows``, however many there are.  Every
    pair of blocks is a key of its own and meets in one matrix product in an Arrow batch;
    only neighbours come out.
    """
    import pandas as pd

    blocks = max(1, -(-features.count() // block_rows))
    packed = features.groupBy(F.pmod(F.xxhash64("feature_id"), F.lit(blocks)).cast("int").alias("block")).agg(F.collect_list("feature_id").alias("ids"), F.collect_list("repr").alias("reprs"))
    left = packed.select("block", F.explode(F.sequence("block", F.lit(blocks - 1))).alias("other"), "ids", "reprs")
    right = packed.select(F.explode(F.sequence(F.lit(0), "block")).alias("block"), F.col("block").alias("other"), F.col("ids").alias("ids2"), F.col("reprs").alias("reprs2"))
    both = left.join(right, ["block", "other"])

    def run(batches):
        for pdf in batches:
            for r in pdf.itertuples():
                x, y = (np.array([list(v) for v in m], dtype=np.float64) for m in (r.reprs, r.reprs2))
                unit = lambda m: m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)
                c = unit(x) @ unit(y).T
                i, j = np.nonzero(c >= eps)
                a, b = np.asarray(r.ids)[i], np.asarray(r.ids2)[j]
                yield pd.DataFrame({"a": a, "b": b, "cos": c[i, j]})
                if r.block != r.other:
                    yield pd.DataFrame({"a": b, "b": a, "cos": c[i, j]})

    return both.mapInPandas(run, "a string, b string, cos double")


def _visit(column: Column | str, seed: int) -> Column:
    """The order in which features are visited: a seeded hash, ties by name."""
    name = F.col(column) if isinstance(column, str) else column
    return F.struct(F.xxhash64(F.lit(f"{seed}:"), name).alias("h"), name.alias("f"))


def threshold_clusters(near: DataFrame, features: DataFrame, least: int = 2, seed: int = 0) -> DataFrame:
    """(feature_id, centroid_id, cos_to_centroid) by seeded visits, without gathering features on the driver.

    Visiting one by one, a feature becomes a centroid if ``least`` features or more lie in
    its neighbourhood and no earlier centroid does.  Rounds decide all of that at once: a
    candidate becomes a centroid when no undecided candidate near it comes earlier, and
    candidates near a new centroid drop out.  Features belong to the earliest centroid
    near them; what none claims stands alone.
    """
    spark = near.sparkSession
    edges = written(near.where("a <> b"), "near-edges")
    degree = edges.groupBy("a").agg((F.count(F.lit(1)) + 1).alias("n"))
    counted = features.select(F.col("feature_id").alias("a")).distinct().join(degree, "a", "left").select("a", F.coalesce("n", F.lit(1)).alias("n"))
    open_ones = written(counted.where(F.col("n") >= least).select(F.col("a").alias("f")), "near-open-0")
    centres = spark.createDataFrame([], "f string")
    step = 0
    while not open_ones.isEmpty():
        rivals = edges.join(open_ones.select(F.col("f").alias("a")), "a").join(open_ones.select(F.col("f").alias("b")), "b")
        earlier = rivals.where(_visit("b", seed) < _visit("a", seed)).select(F.col("a").alias("f")).distinct()
        new = written(open_ones.join(earlier, "f", "left_anti"), f"near-centres-{step}")
        centres = centres.unionByName(new)
        covered = edges.join(new.select(F.col("f").alias("a")), "a").select(F.col("b").alias("f")).unionByName(new).distinct()
        step += 1
        open_ones = written(open_ones.join(covered, "f", "left_anti"), f"near-open-{step}")
    claims = edges.join(centres.select(F.col("f").alias("b")), "b").select(F.col("a").alias("feature_id"), F.col("b").alias("centroid_id"), "cos")
    claims = claims.join(centres.select(F.col("f").alias("feature_id")), "feature_id", "left_anti")
    first = claims.groupBy("feature_id").agg(F.min_by(F.struct("centroid_id", "cos"), _visit("centroid_id", seed)).alias("m")).select("feature_id", "m.*")
    return features.select("feature_id").distinct().join(first, "feature_id", "left").select("feature_id", F.coalesce("centroid_id", "feature_id").alias("centroid_id"), F.coalesce("cos", F.lit(1.0)).alias("cos_to_centroid"))


def threshold_cluster(pairs: Sequence[tuple[str, str, float]], features: Sequence[str], least: int = 2, seed: int = 0) -> list[tuple[str, int, str, float]]:
    """(feature, cluster, centroid, cosine) by seeded visits.

    An unclaimed feature whose neighbourhood (over all features) has ``least`` members
    or more becomes a centroid and claims its unclaimed neighbours; what no centroid
    claims stands alone.  The order of visits, hence the result, follows the seed.
    """
    near: dict[str, list[tuple[str, float]]] = {}
    for a, b, c in pairs:
        near.setdefault(a, []).append((b, c))
    order = sorted(features, key=lambda f: xxhash.xxh3_64_intdigest(f"{seed}:{f}"))
    claimed: dict[str, tuple[int, str, float]] = {}
    cluster = 0
    for f in order:
        around = near.get(f, [(f, 1.0)])
        if f not in claimed and len(around) >= least:
            for g, c in around:
                claimed.setdefault(g, (cluster, f, c))
            claimed[f] = (cluster, f, 1.0) if claimed[f][1] == f else claimed[f]
            cluster += 1
    for f in order:
        if f not in claimed:
            claimed[f] = (cluster, f, 1.0)
            cluster += 1
    return [(f, *claimed[f]) for f in sorted(features)]


def unit_vectors(vectors: DataFrame) -> DataFrame:
    """(feature_id, pos, u): components of the unit vectors; a zero vector has components 0."""
    norm = F.sqrt(dot("repr", "repr"))
    return vectors.select("feature_id", F.posexplode(F.transform("repr", lambda x: F.coalesce(F.try_divide(x.cast("double"), norm), F.lit(0.0)))).alias("pos", "u"))


def estimate_importance(clusters: DataFrame, vectors: DataFrame, known: DataFrame, *, normalise: bool = False, empty: str = "zero") -> DataFrame:
    """(feature_id, fi_est): own importance where known, else the cosine-weighted mean over known members of its cluster.

    The printed form divides by the number of known members; ``normalise`` by the sum
    of cosines.  A cluster without known members gives 0 or the mean of all known.
    A sum of cosines is one inner product with the members' summed unit vectors, so no
    pairs of features are made.
    """
    parts = clusters.join(unit_vectors(vectors), "feature_id")
    told = parts.join(known, "feature_id").groupBy("cluster_id", "pos").agg(F.sum(F.col("fi") * F.col("u")).alias("weighed"), F.sum("u").alias("plain"), F.count(F.lit(1)).alias("members"))
    sums = parts.join(told, ["cluster_id", "pos"]).groupBy("feature_id").agg(F.sum(F.col("u") * F.col("weighed")).alias("top"), F.sum(F.col("u") * F.col("plain")).alias("cosines"), F.max("members").alias("members"))
    means = sums.select("feature_id", F.try_divide("top", F.col("cosines") if normalise else F.col("members").cast("double")).alias("mean"))
    rest = F.lit(0.0) if empty == "zero" else F.col("overall")
    joined = clusters.select("feature_id").join(means, "feature_id", "left").join(known, "feature_id", "left").crossJoin(F.broadcast(known.agg(F.avg("fi").alias("overall"))))  # one row
    return joined.select("feature_id", F.coalesce("fi", "mean", rest).alias("fi_est"))


def sample_features(clusters: DataFrame, vectors: DataFrame, per_cluster: int, method: str, seed: int = 0) -> DataFrame:
    """(feature_id, cluster_id) picked for training: random, centroid (most central) or cover (farthest first)."""
    at = clusters.join(vectors, "feature_id")
    if method == "cover":
        import pandas as pd

        def pick(pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values("feature_id")
            x = np.array([list(v) for v in pdf["repr"]], dtype=np.float64)
            x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
            chosen = [int(np.argmax((x @ x.T).mean(axis=1)))]
            while len(chosen) < min(per_cluster, len(x)):
                far = 1 - (x @ x[chosen].T).max(axis=1)
                far[chosen] = -1
                chosen.append(int(np.argmax(far)))
            return pdf.iloc[chosen][["feature_id", "cluster_id"]]

        return at.groupBy("cluster_id").applyInPandas(pick, "feature_id string, cluster_id int")
    if method == "centroid":
        parts = clusters.join(unit_vectors(vectors), "feature_id")
        centre = parts.groupBy("cluster_id", "pos").agg(F.avg("u").alias("m"))  # its inner product is the mean cosine to all members
        score = parts.join(centre, ["cluster_id", "pos"]).groupBy("feature_id", "cluster_id").agg(F.round(F.sum(F.col("u") * F.col("m")), 9).alias("s"))
        order = Window.partitionBy("cluster_id").orderBy(F.desc("s"), "feature_id")
        return score.withColumn("n", F.row_number().over(order)).where(F.col("n") <= per_cluster).select("feature_id", "cluster_id")
    order = Window.partitionBy("cluster_id").orderBy(F.md5(F.concat(F.lit(f"{seed}:"), "feature_id").cast("binary")), "feature_id")
    return clusters.withColumn("n", F.row_number().over(order)).where(F.col("n") <= per_cluster).select("feature_id", "cluster_id")

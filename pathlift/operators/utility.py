"""Utility of features: closed forms over bins, and trained models."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.measures import METRICS, signed_score


def unpivoted(df: DataFrame, label: str, features: Sequence[str], bins: Column | None = None) -> DataFrame:
    """(feature, bin, y): one row a base row and feature, the missing value being a bin of its own."""
    value = lambda f: F.coalesce(F.col(f).cast("string"), F.lit("(missing)"))
    pairs = F.array(*[F.struct(F.lit(f).alias("feature"), value(f).alias("bin")) for f in features])
    return df.select(F.col(label).alias("y"), F.explode(pairs).alias("p")).select("p.feature", "p.bin", "y")


def equal_width(column: Column, low: float, high: float, bins: int) -> Column:
    """Bin number 0 to bins - 1 of a numeric value; null stays null."""
    width = (high - low) / bins or 1.0
    return F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((column - F.lit(low)) / F.lit(width)))).cast("int")


def majority_accuracy(df: DataFrame, label: str, features: Sequence[str]) -> DataFrame:
    """(feature, score): accuracy of answering each bin's most frequent label; all features in one job."""
    cells = unpivoted(df, label, features).groupBy("feature", "bin", "y").agg(F.count(F.lit(1)).alias("c"))
    bins = cells.groupBy("feature", "bin").agg(F.max("c").alias("top"), F.sum("c").alias("n"))
    return bins.groupBy("feature").agg((F.sum("top") / F.sum("n")).alias("score"))


def binned_f1(df: DataFrame, label: str, features: Sequence[str]) -> DataFrame:
    """(feature, score): F1 of answering 1 in bins whose positive share is a half or more."""
    bins = unpivoted(df, label, features).groupBy("feature", "bin").agg(F.sum("y").cast("double").alias("p"), F.count(F.lit(1)).cast("double").alias("n"))
    said = F.col("p") * 2 >= F.col("n")
    tp, fp, fn = (F.sum(F.when(said, F.col("p")).otherwise(0.0)), F.sum(F.when(said, F.col("n") - F.col("p")).otherwise(0.0)), F.sum(F.when(said, 0.0).otherwise(F.col("p"))))
    return bins.groupBy("feature").agg(F.coalesce(F.try_divide(tp, tp + 0.5 * (fp + fn)), F.lit(0.0)).alias("score"))


def bin_mean_error(df: DataFrame, label: str, features: Sequence[str]) -> DataFrame:
    """(feature, mse, mae): errors of answering each bin's mean."""
    rows = unpivoted(df, label, features)
    means = rows.groupBy("feature", "bin").agg(F.avg("y").alias("m"))
    joined = rows.join(means, ["feature", "bin"])
    return joined.groupBy("feature").agg(METRICS["mse"]("m", "y").alias("mse"), METRICS["mae"]("m", "y").alias("mae"))


def closed_form(df: DataFrame, label: str, features: Sequence[str], metric: str) -> DataFrame:
    """(feature, score): the signed closed-form score of each feature alone for a metric; higher is better."""
    if metric == "accuracy":
        return majority_accuracy(df, label, features)
    if metric == "f1":
        return binned_f1(df, label, features)
    return bin_mean_error(df, label, features).select("feature", (-F.col(metric)).alias("score"))


def linear_error(df: DataFrame, label: str, features: Sequence[str]) -> DataFrame:
    """(feature, mse): error of a straight line on rows with a value and of their mean elsewhere, from moments alone."""
    pairs = F.array(*[F.struct(F.lit(f).alias("feature"), F.col(f).cast("double").alias("x")) for f in features])
    rows = df.select(F.col(label).cast("double").alias("y"), F.explode(pairs).alias("p")).select("p.feature", "p.x", "y")
    has = F.col("x").isNotNull()
    parts = rows.groupBy("feature").agg(
        F.count(F.lit(1)).alias("n"), F.count("x").alias("m"), F.coalesce(F.var_pop(F.when(has, F.col("y"))), F.lit(0.0)).alias("vy"), F.coalesce(F.regr_r2(F.when(has, F.col("y")), F.col("x")), F.lit(0.0)).alias("r2"),
        F.coalesce(F.var_pop(F.when(~has, F.col("y"))), F.lit(0.0)).alias("rest"),
    )
    return parts.select("feature", ((F.col("m") * F.col("vy") * (1 - F.col("r2")) + (F.col("n") - F.col("m")) * F.col("rest")) / F.col("n")).alias("mse"))


def decomposition(df: DataFrame, pred: str, label: str, feature: str) -> DataFrame:
    """(whole, share, matched, unmatched, recombined): a row-averaged score is the weighted mean over the two slices."""
    hit, ok = F.col(feature).isNotNull(), (F.col(pred) == F.col(label)).cast("double")
    out = df.agg(F.avg(ok).alias("whole"), F.avg(hit.cast("double")).alias("share"), F.coalesce(F.avg(F.when(hit, ok)), F.lit(0.0)).alias("matched"), F.coalesce(F.avg(F.when(~hit, ok)), F.lit(0.0)).alias("unmatched"))
    return out.withColumn("recombined", F.col("share") * F.col("matched") + (1 - F.col("share")) * F.col("unmatched"))


def prepared_features(df: DataFrame, features: Sequence[str], numeric: Sequence[str], *, scale: bool = False) -> tuple[list, str]:
    """(pipeline stages, name of the vector column): numbers imputed beside an indicator, strings indexed and one-hot encoded, all standardised if asked."""
    from pyspark.ml.feature import Imputer, OneHotEncoder, StandardScaler, StringIndexer, VectorAssembler

    strings = [f for f in features if f not in numeric]
    stages = [Imputer(inputCols=list(numeric), outputCols=[f"{f}__num" for f in numeric])] if numeric else []
    stages += [StringIndexer(inputCol=f, outputCol=f"{f}__index", handleInvalid="keep") for f in strings]
    if strings:
        stages.append(OneHotEncoder(inputCols=[f"{f}__index" for f in strings], outputCols=[f"{f}__hot" for f in strings], handleInvalid="keep"))
    inputs = [*[f"{f}__num" for f in numeric], *[f"{f}__hot" for f in strings], *[f"{f}__none" for f in numeric]]
    stages.append(VectorAssembler(inputCols=inputs, outputCol="assembled", handleInvalid="keep"))
    if scale:
        stages.append(StandardScaler(inputCol="assembled", outputCol="features", withMean=False))
    return stages, "features" if scale else "assembled"


def fit_models(df: DataFrame, label: str, features: Sequence[str], metric: str, *, families: Sequence[str] = ("linear", "forest", "boosted"), key: str | None = None, seed: int = 3, tune: bool = False, neighbour_rows: int = 5000) -> dict[str, float]:
    """Metric by model family and of their average, on a held-out part split by a hash.

    Families: linear, forest, boosted, network (classes only) of pyspark.ml, whose tree
    aggregates keep rows where they are, and neighbours, whose training rows are bounded by
    ``neighbour_rows`` and travel to the rows that ask.  ``tune`` chooses settings by a
    validation split.  For classes the ensemble averages the families' probabilities and
    answers 1 from a half on; for numbers it averages their answers.
    """
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import GBTClassifier, LogisticRegression, MultilayerPerceptronClassifier, RandomForestClassifier
    from pyspark.ml.evaluation import MulticlassClassificationEvaluator, RegressionEvaluator
    from pyspark.ml.functions import vector_to_array
    from pyspark.ml.regression import GBTRegressor, LinearRegression, RandomForestRegressor
    from pyspark.ml.tuning import ParamGridBuilder, TrainValidationSplit

    numeric = [f for f in features if isinstance(df.schema[f].dataType, T.NumericType)]
    strings = [f for f in features if f not in numeric]
    split = F.xxhash64(*([key] if key else features))
    rows = df.select(
        F.col(label).cast("double").alias("label"), *[F.col(f).cast("double").alias(f) for f in numeric], *[F.coalesce(F.col(f).cast("string"), F.lit("(missing)")).alias(f) for f in strings],
        *[F.col(f).isNull().cast("double").alias(f"{f}__none") for f in numeric], (F.pmod(split, F.lit(10)) < 7).alias("train"), split.alias("place"),
    )
    stages, vector = prepared_features(rows, features, numeric, scale=True)
    classes = metric in ("accuracy", "f1", "precision", "recall")
    prepared = Pipeline(stages=stages).fit(rows.where("train")).transform(rows).select("label", vector, "train", "place").persist()
    train = prepared.where("train")
    width = len(prepared.select(vector).first()[0])
    forest, boosted, linear = (RandomForestClassifier, GBTClassifier, LogisticRegression) if classes else (RandomForestRegressor, GBTRegressor, LinearRegression)
    kinds = {
        "linear": lambda: (linear(maxIter=20), {"regParam": [0.0, 0.1]}), "forest": lambda: (forest(numTrees=20, seed=seed), {"maxDepth": [4, 8]}), "boosted": lambda: (boosted(maxIter=10, seed=seed), {"maxDepth": [2, 4]}),
        "network": lambda: (MultilayerPerceptronClassifier(layers=[width, 8, 2], maxIter=40, seed=seed), {"stepSize": [0.03, 0.3]}),
    }
    scored = prepared.where(~F.col("train")).select("label", vector)
    answers = []
    for name in families:
        if name == "neighbours":
            scored = scored.withColumn("p_neighbours", _neighbours(train, vector, neighbour_rows)(vector_to_array(vector)))
        else:
            estimator, grid = kinds[name]()
            estimator = estimator.setFeaturesCol(vector)
            if tune:
                builder = ParamGridBuilder()
                for parameter, values in grid.items():
                    builder = builder.addGrid(estimator.getParam(parameter), values)
                judge = MulticlassClassificationEvaluator(metricName="accuracy") if classes else RegressionEvaluator(metricName="rmse")
                model = TrainValidationSplit(estimator=estimator, estimatorParamMaps=builder.build(), evaluator=judge, trainRatio=0.75, seed=seed, parallelism=2).fit(train).bestModel
            else:
                model = estimator.fit(train)
            said = vector_to_array("probability")[1] if classes else F.col("prediction")
            scored = model.transform(scored).withColumn(f"p_{name}", said).drop("prediction", "probability", "rawPrediction")
        answers.append(f"p_{name}")
    scored = scored.withColumn("p_ensemble", sum((F.col(a) for a in answers), F.lit(0.0)) / len(answers))
    answer = lambda c: (F.col(c) >= 0.5).cast("double") if classes else F.col(c)
    row = scored.select("label", *[answer(a).alias(a) for a in [*answers, "p_ensemble"]]).agg(*[METRICS[metric](a, "label").alias(a) for a in [*answers, "p_ensemble"]]).first()
    prepared.unpersist()
    return {a[2:]: float(row[a]) if row[a] is not None else float("nan") for a in [*answers, "p_ensemble"]}


def _neighbours(train: DataFrame, vector: str, most: int, k: int = 15):
    """A vectorised function that gives the mean label of the k nearest of at most ``most`` training rows, taken by hash."""
    import numpy as np
    import pandas as pd
    from pyspark.ml.functions import vector_to_array

    sample = train.orderBy("place", "label").limit(most).select(vector_to_array(vector).alias("x"), "label").toPandas()
    points, labels = np.stack(sample["x"].to_numpy()).astype(float), sample["label"].to_numpy(dtype=float)
    norms = (points**2).sum(axis=1)

    @F.pandas_udf("double")
    def nearest(x: pd.Series) -> pd.Series:
        out = []
        for low in range(0, len(x), 1024):
            part = np.stack(x[low : low + 1024].to_numpy()).astype(float)
            far = norms - 2 * part @ points.T
            n = min(k, len(labels))
            out.append(labels[np.argpartition(far, n - 1, axis=1)[:, :n]].mean(axis=1))
        return pd.Series(np.concatenate(out) if out else [])

    return nearest


def utility_gain(metric: str, augmented: float, base: float) -> float:
    return signed_score(metric, augmented) - signed_score(metric, base)

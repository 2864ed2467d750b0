"""Column expressions and closed forms of the measures."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Metrics that are better when lower; their scores are negated.
LOWER_IS_BETTER = ("mae", "mse")


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def accuracy(pred: Column | str, label: Column | str) -> Column:
    return F.avg((_c(pred) == _c(label)).cast("double"))


def _count(condition: Column) -> Column:
    return F.sum(F.when(condition, 1.0).otherwise(0.0))


def f1(pred: Column | str, label: Column | str, positive: int = 1) -> Column:
    """True positives over themselves and half of all errors; null without any positive."""
    p, y = _c(pred) == positive, _c(label) == positive
    return F.try_divide(_count(p & y), _count(p & y) + 0.5 * (_count(p & ~y) + _count(~p & y)))


def precision(pred: Column | str, label: Column | str, positive: int = 1) -> Column:
    p, y = _c(pred) == positive, _c(label) == positive
    return F.try_divide(_count(p & y), _count(p))


def recall(pred: Column | str, label: Column | str, positive: int = 1) -> Column:
    p, y = _c(pred) == positive, _c(label) == positive
    return F.try_divide(_count(p & y), _count(y))


def mae(pred: Column | str, label: Column | str) -> Column:
    return F.avg(F.abs(_c(pred) - _c(label)))


def mse(pred: Column | str, label: Column | str) -> Column:
    return F.avg(F.pow(_c(pred) - _c(label), F.lit(2)))


METRICS = {"accuracy": accuracy, "f1": f1, "precision": precision, "recall": recall, "mae": mae, "mse": mse}


def signed_score(metric: str, value: Column | float):
    """Utility score of a metric's value: negated where lower is better."""
    return -value if metric in LOWER_IS_BETTER else value


def hash_uniform(key: Column | str, seed: int = 0) -> Column:
    """A number in [0, 1) that depends on a key and a seed alone (integer arithmetic, so SQL can repeat it)."""
    mixed = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), _c(key).cast("string")).cast("binary")), 1, 8), 16, 10).cast("double")
    return mixed / F.lit(float(2**32))


def slice_error_bounds(total: int, matched: int, drawn: int) -> dict[str, float]:
    """Moments and bounds of the share error of a random slice.

    Of ``total`` rows ``matched`` are hits; the number of hits among ``drawn`` rows is
    hypergeometric.
    """
    n, m, k = float(total), float(matched), float(drawn)
    mean = k * m / n
    variance = k * m * (n - k) * (n - m) / (n**4 * (n - 1)) if n > 1 else 0.0
    return {"mean": mean, "variance": variance, "variance_bound": 1 / n, "mean_abs_bound": 2 / math.sqrt(n)}


def abs_moment_bounds(eps: float) -> dict[str, float]:
    """Bounds on the mean and variance of |x| for a mean-zero x in (-1, 1) of variance eps at most."""
    return {"mean_abs": 2 * math.sqrt(eps), "var_abs": eps}


def combination_count(n: int, m: int, budget: int) -> int:
    """Plans of up to ``budget`` of n features with m paths: sum of m * C(n, i)."""
    return sum(m * math.comb(n, i) for i in range(1, budget + 1))

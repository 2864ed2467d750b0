"""The ensemble of a plan on all rows: rows come as counts of equal lines (codes, part, label), so none is left out.

``lines`` codes the rows in Arrow batches and counts them in Spark; ``scored`` fits and
scores one plan from its lines alone, in a task of its own.  What is held there grows with
the different lines of a plan, not with its rows.
"""

from __future__ import annotations

from collections.abc import Iterator, Mapping, Sequence
from itertools import combinations
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .joint_models import CLASSES, Coder, Forest, Ridge

#: Parts of the rows: models are tuned on the second, fitted on the first two, scored on the third.
FIT, VALIDATE, OUT = 0, 1, 2
#: Codes that one whole number holds.
WORD = 15
#: Rows in which numbers of a plan's model are made at a time.
CHUNK = 65_536
#: Vectors whose neighbours are counted at a time.
ASKED = 1_000_000


def plain(field: T.StructField) -> Column:
    """A column as coders read it: numbers as doubles, all else as text."""
    c = F.col(f"`{field.name}`")
    return c.cast("double") if isinstance(field.dataType, T.NumericType) else c.cast("string")


def fit_coders(df: DataFrame, names: Sequence[str], bins: int = 12, accuracy: int = 10_000) -> dict[str, Coder]:
    """Coders over all rows: quantile bins for numbers, within a rank of one row in ``accuracy``; the ``bins`` most frequent values for anything else."""
    fields = {n: df.schema[n] for n in names}
    numbers = [n for n in names if isinstance(fields[n].dataType, T.NumericType)]
    texts = [n for n in names if n not in numbers]
    out: dict[str, Coder] = {}
    if numbers:
        finite = {n: F.when(F.abs(x) < float("inf"), x) for n in numbers for x in [plain(fields[n])]}  # NaN is above infinity
        shares = [k / bins for k in range(1, bins)]
        told = df.agg(*[F.struct(F.approx_count_distinct(x).alias("n"), F.percentile_approx(x, shares, accuracy).alias("q")).alias(n) for n, x in finite.items()]).first()
        few = [n for n in numbers if told[n]["n"] <= 2 * bins]
        sets = df.agg(*[F.collect_set(finite[n]).alias(n) for n in few]).first() if few else {}  # a few values each
        for n in numbers:
            values = np.unique(np.array(sets[n], dtype=float)) if n in few else None
            out[n] = Coder(cuts=(values[1:] + values[:-1]) / 2 if values is not None and len(values) <= bins else np.unique(np.array(told[n]["q"], dtype=float)))
    if texts:
        cells = df.select(F.explode(F.array(*[F.struct(F.lit(k).alias("k"), plain(fields[n]).alias("v")) for k, n in enumerate(texts)])).alias("cell")).where("cell.v IS NOT NULL")
        counts = cells.groupBy("cell.k", "cell.v").count()
        place = F.expr("row_number() OVER (PARTITION BY k ORDER BY count DESC, v)")
        top = counts.withColumn("place", place).where(F.col("place") <= bins).collect()  # a dozen rows a column
        for k, n in enumerate(texts):
            out[n] = Coder(values={r["v"]: r["place"] for r in top if r["k"] == k})
    return out


def lines(df: DataFrame, part: Column, label: str, plans: Sequence[Sequence[str]], coders: Mapping[str, Coder]) -> DataFrame:
    """(plan, words, part, y, n): how many rows have these codes, part and label, for every plan; a word holds up to 15 codes."""
    needed = sorted({c for p in plans for c in p})
    words = max([1, *[-(-len(p) // WORD) for p in plans]])
    used = {c: coders[c] for c in needed}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            coded = {c: used[c].code(pdf[c]).astype(np.int64) for c in used}
            made = {"part": pdf["part"], "y": pdf["y"]}
            for k, plan in enumerate(plans):
                for w in range(words):
                    word = np.zeros(len(pdf), dtype=np.int64)
                    for c in plan[w * WORD : (w + 1) * WORD]:
                        word = word * 16 + coded[c]
                    made[f"w{k}_{w}"] = word
            yield pd.DataFrame(made)

    columns = [f"w{k}_{w}" for k in range(len(plans)) for w in range(words)]
    rows = df.select(part.cast("int").alias("part"), F.col(f"`{label}`").cast("double").alias("y"), *[plain(df.schema[c]).alias(c) for c in needed])
    coded = rows.mapInPandas(run, T.StructType([T.StructField("part", T.IntegerType()), T.StructField("y", T.DoubleType()), *[T.StructField(c, T.LongType()) for c in columns]]))
    each = F.array(*[F.struct(F.lit(k).alias("plan"), *[F.col(f"w{k}_{w}").alias(f"w{w}") for w in range(words)]) for k in range(len(plans))])
    own = [f"w{w}" for w in range(words)]
    return coded.select("part", "y", F.explode(each).alias("one")).select("one.*", "part", "y").groupBy("plan", *own, "part", "y").agg(F.count(F.lit(1)).alias("n"))


def unpacked(words: np.ndarray, width: int) -> np.ndarray:
    """Codes by line, from its words."""
    out = np.zeros((len(words), width), dtype=np.int16)
    for w in range(words.shape[1]):
        word, own = words[:, w].copy(), range(w * WORD, min(width, (w + 1) * WORD))
        for c in reversed(own):
            out[:, c] = word % 16
            word //= 16
    return out


def quantiles(values: np.ndarray, n: np.ndarray, shares: np.ndarray) -> np.ndarray:
    """Quantiles of values that occur n times each, between neighbours in a straight line."""
    order = np.argsort(values, kind="stable")
    values, upto = values[order], np.cumsum(n[order])
    at = np.asarray(shares, dtype=float) * (upto[-1] - 1)
    low, high = (values[np.searchsorted(upto, rank, side="right").clip(max=len(values) - 1)] for rank in (np.floor(at), np.ceil(at)))
    return low + (high - low) * (at - np.floor(at))


def fit_ridge(codes: np.ndarray, sizes: Sequence[int], n: np.ndarray, s: np.ndarray) -> Ridge:
    """The Gram matrix of rows given as counts n and sums s of labels by code vector."""
    width = 1 + int(sum(sizes))
    gram, moment = np.zeros((width, width)), np.zeros(width)
    for low in range(0, len(codes), CHUNK):
        x = Ridge.one_hot(codes[low : low + CHUNK], sizes).astype(np.float64)
        gram += x.T @ (x * n[low : low + CHUNK, None])
        moment += x.T @ s[low : low + CHUNK]
    return Ridge(sizes, gram, moment)


def ridge_values(model: Ridge, codes: np.ndarray, penalty: float) -> np.ndarray:
    w = Ridge(model.sizes, model.gram, model.moment, penalty).weights(range(len(model.sizes)))
    return np.concatenate([Ridge.one_hot(codes[low : low + CHUNK], model.sizes) @ w for low in range(0, len(codes), CHUNK)])


def fit_forest(codes: np.ndarray, sizes: Sequence[int], vector: np.ndarray, n: np.ndarray, y: np.ndarray, depth: int) -> Forest:
    """A forest on lines that stand for n rows each: every tree draws each row as often as a Poisson number says."""
    made = Forest(depth=depth)
    rng = np.random.default_rng(made.seed)
    made.importance = np.zeros(codes.shape[1])
    for _ in range(made.trees):
        drawn = rng.poisson(n).astype(float)
        count, total = np.bincount(vector, drawn, len(codes)), np.bincount(vector, drawn * y, len(codes))
        seen = count > 0
        if seen.any():
            made.grow(rng, codes[seen], sizes, count[seen], total[seen])
    return made


def neighbour_values(codes: np.ndarray, sizes: Sequence[int], n: np.ndarray, s: np.ndarray, ks: Sequence[int], asked: np.ndarray) -> list[np.ndarray]:
    """Means over the k nearest rows of all, for every k and asked vector; nearest are those that agree in most codes, and all rows as near as the k-th count.

    No pair of rows is compared.  Rows that agree with a vector on a set of columns are
    counted by grouping; summed over all sets of a size, a row that agrees in m columns is
    counted once for each set within them, which gives the rows that agree in exactly that
    many, from all columns downwards.  Vectors that have their k rows are asked no further.
    """
    known = n > 0
    want = codes[asked]
    parts = [_nearest(codes[known], sizes, n[known].astype(float), s[known], ks, want[low : low + ASKED]) for low in range(0, len(want), ASKED)]
    return [np.concatenate(own) for own in zip(*parts, strict=True)] if parts else [np.zeros(0) for _ in ks]


def _nearest(train: np.ndarray, sizes: Sequence[int], tn: np.ndarray, ts: np.ndarray, ks: Sequence[int], want: np.ndarray) -> list[np.ndarray]:
    width = train.shape[1]
    need = [min(k, tn.sum()) for k in ks]
    found = [np.zeros(len(want)) for _ in ks]
    done = [np.zeros(len(want), dtype=bool) for _ in ks]
    exact_n, exact_s = {}, {}  # rows that agree in exactly m columns
    upto_n, upto_s = np.zeros(len(want)), np.zeros(len(want))
    left = np.arange(len(want))
    for size in range(width, -1, -1):
        sum_n, sum_s = np.zeros(len(left)), np.zeros(len(left))
        for own in combinations(range(width), size):
            at_train, at_left, cells = _cells(train, want[left], sizes, own)
            sum_n += np.bincount(at_train, tn, cells)[at_left]
            sum_s += np.bincount(at_train, ts, cells)[at_left]
        for m in exact_n:
            sum_n -= comb(m, size) * exact_n[m][left]
            sum_s -= comb(m, size) * exact_s[m][left]
        exact_n[size], exact_s[size] = np.zeros(len(want)), np.zeros(len(want))
        exact_n[size][left], exact_s[size][left] = sum_n, sum_s
        upto_n[left] += sum_n
        upto_s[left] += sum_s
        for k, enough in enumerate(need):
            now = left[~done[k][left] & (upto_n[left] >= enough)]
            found[k][now] = upto_s[now] / upto_n[now]
            done[k][now] = True
        left = left[~np.all([d[left] for d in done], axis=0)]
        if not len(left):
            break
    return found


def _cells(train: np.ndarray, want: np.ndarray, sizes: Sequence[int], own: Sequence[int], most: int = 2_000_000) -> tuple[np.ndarray, np.ndarray, int]:
    """Numbers of the cells that vectors share on some columns: of the training vectors, of the asked ones, and how many there are."""
    a, b, cells = np.zeros(len(train), dtype=np.int64), np.zeros(len(want), dtype=np.int64), 1
    for c in own:
        if cells * int(sizes[c]) > most:  # numbered anew, only those that occur; what no training row has is a cell of its own
            values, a = np.unique(a, return_inverse=True)
            at = np.searchsorted(values, b).clip(max=len(values) - 1)
            b, cells = np.where(values[at] == b, at, len(values)), len(values) + 1
        a, b, cells = a * int(sizes[c]) + train[:, c], b * int(sizes[c]) + want[:, c], cells * int(sizes[c])
    if cells > most:
        values, a = np.unique(a, return_inverse=True)
        at = np.searchsorted(values, b).clip(max=len(values) - 1)
        b, cells = np.where(values[at] == b, at, len(values)), len(values) + 1
    return a, b, cells


def fitted_values(codes: np.ndarray, sizes: Sequence[int], vector: np.ndarray, part: np.ndarray, y: np.ndarray, n: np.ndarray, families: Sequence[str]) -> np.ndarray:
    """Mean of one model a family by code vector; settings are chosen by squared error on the validation rows, then the model is fitted on them too."""
    fit, check, both = part == FIT, part == VALIDATE, part != OUT
    size = len(codes)

    def sums(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return np.bincount(vector[rows], n[rows], size), np.bincount(vector[rows], n[rows] * y[rows], size)

    check_n, check_s = sums(check)
    checked = check_n > 0

    def best(tried: list[np.ndarray]) -> int:
        """Squared errors but for the part that is the same for all."""
        return int(np.argmin([np.sum(check_n[checked] * v * v - 2 * check_s[checked] * v) for v in tried]))

    out = []
    for name in families:
        if name == "linear":
            model, penalties = fit_ridge(codes, sizes, *sums(fit)), (1.0, 10.0)
            chosen = penalties[best([ridge_values(model, codes[checked], p) for p in penalties])]
            out.append(ridge_values(fit_ridge(codes, sizes, *sums(both)), codes, chosen))
        elif name == "forest":
            depths = (4, 8)
            chosen = depths[best([fit_forest(codes, sizes, vector[fit], n[fit], y[fit], d).predict(codes[checked]) for d in depths])]
            out.append(fit_forest(codes, sizes, vector[both], n[both], y[both], chosen).predict(codes))
        elif name == "neighbours":
            ks = (7, 25)
            chosen = ks[best(neighbour_values(codes, sizes, *sums(fit), ks, checked))]
            out.append(neighbour_values(codes, sizes, *sums(both), (chosen,), np.ones(size, dtype=bool))[0])
        else:
            raise ValueError(f"no model of counted rows: {name}")
    return np.mean(out, axis=0)


def best_cut(metric: str, said: np.ndarray, y: np.ndarray, n: np.ndarray) -> float:
    """Where to cut fitted values into classes: a half, or for F1 the cut that is best on the training rows."""
    if metric != "f1" or not n.sum():
        return 0.5

    def f1(cut: float) -> float:
        told = said >= cut
        hits, wrong = n[told & (y == 1)].sum(), n[told != (y == 1)].sum()
        return hits / (hits + 0.5 * wrong) if hits else 0.0

    return float(max(np.unique(quantiles(said, n, np.linspace(0.5, 0.995, 40))), key=f1))


def scored(metric: str, families: Sequence[str], sizes: Sequence[int], words: np.ndarray, part: np.ndarray, y: np.ndarray, n: np.ndarray) -> tuple[float, ...]:
    """(rows, right, hits, absolute, squared) over the rows held out, by the ensemble of all other rows."""
    order = np.lexsort([y, part, *words.T])  # as lines come in any order
    words, part, y, n = words[order], part[order], y[order], n[order].astype(float)
    vectors, vector = np.unique(words, axis=0, return_inverse=True) if words.shape[1] > 1 else np.unique(words[:, 0], return_inverse=True)
    vector = vector.reshape(-1)
    codes = unpacked(vectors.reshape(len(vectors), -1), len(sizes))
    learn, out = part != OUT, part == OUT
    if len(sizes) and n[learn].sum() > 20 and n[part == FIT].any() and n[part == VALIDATE].any():
        said = fitted_values(codes, sizes, vector, part, y, n, families)[vector]
    else:
        total = n[learn].sum()
        middle = (quantiles(y[learn], n[learn], np.array([0.5]))[0] if metric == "mae" else np.sum(n[learn] * y[learn]) / total) if total else 0.0
        said = np.full(len(y), float(middle))
    if metric in CLASSES:
        said = (said >= best_cut(metric, said[learn], y[learn], n[learn])).astype(float)
    said, y, n = said[out], y[out], n[out]
    gap = said - y
    return float(n.sum()), float(n[said == y].sum()), float(n[(said == 1) & (y == 1)].sum()), float(np.sum(n * np.abs(gap))), float(np.sum(n * gap * gap))


def score_lines(counted: DataFrame, metric: str, families: Sequence[Sequence[str]], sizes: Sequence[Sequence[int]]) -> DataFrame:
    """(plan, n, right, hits, absolute, squared) from the lines of plans, a plan in a task."""
    words = [c for c in counted.columns if c not in ("plan", "part", "y", "n")]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        k = int(pdf["plan"].iloc[0])
        made = scored(metric, families[k], sizes[k], pdf[words].to_numpy(dtype=np.int64), pdf["part"].to_numpy(), pdf["y"].to_numpy(dtype=float), pdf["n"].to_numpy())
        return pd.DataFrame([(k, *made)], columns=["plan", "n", "right", "hits", "absolute", "squared"])

    # plans differ much in work, so each goes to a task as far as hashes tell them apart
    return counted.repartition(4 * len(sizes), "plan").groupBy("plan").applyInPandas(run, "plan int, n double, right double, hits double, absolute double, squared double")

"""Joint models of several features over coded columns, in NumPy: what searches ask, and what is scored in the end.

A table of candidate columns is coded once: numbers by quantile bins, text by its most
frequent values, the missing value as a code of its own.  Models train on a sample of
rows that is bounded by a parameter; coder and models are small, so Arrow batches of any
number of further rows can be scored with them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Sequence
from dataclasses import dataclass, field
from functools import cached_property, partial

import numpy as np
import pandas as pd

LOWER_IS_BETTER = ("mae", "mse")
CLASSES = ("accuracy", "f1")


@dataclass(frozen=True)
class Coder:
    """Codes of one column: 0 is missing, then bins or values, then (for text) all other values."""

    cuts: np.ndarray | None = None
    values: dict[str, int] | None = None

    @property
    def size(self) -> int:
        return len(self.cuts) + 2 if self.cuts is not None else len(self.values) + 2

    def code(self, column: pd.Series) -> np.ndarray:
        if self.cuts is not None:
            x = pd.to_numeric(column, errors="coerce").to_numpy(dtype=float, na_value=np.nan)
            return np.where(np.isnan(x), 0, 1 + np.searchsorted(self.cuts, x, side="left")).astype(np.int16)
        known = column.map(lambda v: 0 if v is None or v != v else self.values.get(str(v), len(self.values) + 1))
        return known.to_numpy(dtype=np.int16)


def fit_coder(column: pd.Series, bins: int = 12) -> Coder:
    """Quantile bins for numbers, the ``bins`` most frequent values for anything else."""
    if pd.api.types.is_numeric_dtype(column) and not pd.api.types.is_bool_dtype(column):
        x = column.to_numpy(dtype=float, na_value=np.nan)
        x = x[np.isfinite(x)]
        values = np.unique(x)
        if len(values) <= bins:
            return Coder(cuts=(values[1:] + values[:-1]) / 2)
        return Coder(cuts=np.unique(np.quantile(x, np.arange(1, bins) / bins)))
    told = column.dropna().astype(str).value_counts()
    told = told.sort_index().sort_values(ascending=False, kind="stable")
    return Coder(values={v: k + 1 for k, v in enumerate(told.index[:bins])})


def score(metric: str, predicted: np.ndarray, y: np.ndarray) -> float:
    """The signed score: higher is better for every metric."""
    if not len(y):
        return 0.0
    if metric == "accuracy":
        return float(np.mean(predicted == y))
    if metric == "f1":
        tp, wrong = np.sum((predicted == 1) & (y == 1)), np.sum(predicted != y)
        return float(tp / (tp + 0.5 * wrong)) if tp else 0.0
    gap = predicted - y
    return -float(np.mean(np.abs(gap)) if metric == "mae" else np.mean(gap * gap))


def best_threshold(metric: str, said: np.ndarray, y: np.ndarray) -> float:
    """Where to cut a fitted value into classes: a half, or for F1 the cut that is best on the training rows."""
    if metric != "f1" or not len(y):
        return 0.5
    cuts = np.unique(np.quantile(said, np.linspace(0.5, 0.995, 40)))
    return float(max(cuts, key=lambda c: score(metric, (said >= c).astype(int), y)))


@dataclass
class Ridge:
    """Least squares over one-hot codes with a ridge, from the Gram matrix of all columns; any subset of them is one small solve."""

    sizes: Sequence[int]
    gram: np.ndarray
    moment: np.ndarray
    ridge: float = 3.0

    @staticmethod
    def one_hot(codes: np.ndarray, sizes: Sequence[int]) -> np.ndarray:
        starts = np.cumsum([1, *sizes[:-1]]) if len(sizes) else np.zeros(0, np.int64)
        out = np.zeros((len(codes), 1 + int(sum(sizes))), dtype=np.float32)
        out[:, 0] = 1
        rows = np.arange(len(codes))
        for k, a in enumerate(starts):
            out[rows, a + np.minimum(codes[:, k], sizes[k] - 1)] = 1
        return out

    @classmethod
    def of(cls, codes: np.ndarray, sizes: Sequence[int], y: np.ndarray, **settings) -> Ridge:
        x = cls.one_hot(codes, sizes)
        return cls(sizes, (x.T @ x).astype(np.float64), x.T.astype(np.float64) @ y, **settings)

    def places(self, columns: Sequence[int]) -> np.ndarray:
        starts = np.cumsum([1, *self.sizes])
        return np.concatenate([[0], *[np.arange(starts[c], starts[c + 1]) for c in columns]]).astype(np.int64)

    def weights(self, columns: Sequence[int]) -> np.ndarray:
        at = self.places(columns)
        penalty = np.full(len(at), self.ridge)
        penalty[0] = 1e-6
        return np.linalg.solve(self.gram[np.ix_(at, at)] + np.diag(penalty), self.moment[at])


@dataclass
class Forest:
    """Trees over codes, grown level by level from histograms; each sees a random part of rows and columns."""

    trees: int = 30
    depth: int = 6
    least: int = 8
    seed: int = 1
    grown: list = field(default_factory=list)
    importance: np.ndarray | None = None

    def fit(self, codes: np.ndarray, sizes: Sequence[int], y: np.ndarray) -> Forest:
        rng = np.random.default_rng(self.seed)
        n, f = codes.shape
        self.importance = np.zeros(f)
        for _ in range(self.trees):
            rows = rng.integers(0, n, n)
            self.grow(rng, codes[rows], sizes, np.ones(n), y[rows].astype(float))
        self.importance /= max(1e-12, self.importance.sum())
        return self

    def grow(self, rng: np.random.Generator, x: np.ndarray, sizes: Sequence[int], weight: np.ndarray, t: np.ndarray) -> None:
        """One tree more, on code vectors that stand for ``weight`` rows with labels of sum ``t`` each."""
        f = x.shape[1]
        tried = max(1, min(f, int(np.ceil(np.sqrt(f) * 1.5))))
        node = np.zeros(len(x), dtype=np.int64)
        splits: list[dict[int, tuple[int, int]]] = []
        for _ in range(self.depth):
            nodes = int(node.max()) + 1
            count, total = np.bincount(node, weight, nodes), np.bincount(node, t, nodes)
            best = np.zeros(nodes)
            pick: dict[int, tuple[int, int]] = {}
            for c in rng.permutation(f)[:tried]:
                b = int(sizes[c])
                cell = node * b + np.minimum(x[:, c], b - 1)
                left_n = np.cumsum(np.bincount(cell, weight, nodes * b).reshape(nodes, b), axis=1)[:, :-1]
                left_s = np.cumsum(np.bincount(cell, t, nodes * b).reshape(nodes, b), axis=1)[:, :-1]
                right_n, right_s = count[:, None] - left_n, total[:, None] - left_s
                fine = (left_n >= self.least) & (right_n >= self.least)
                gain = np.where(fine, left_s**2 / np.maximum(left_n, 1) + right_s**2 / np.maximum(right_n, 1) - (total**2 / np.maximum(count, 1))[:, None], 0.0)
                if gain.shape[1]:
                    cut = gain.argmax(axis=1)
                    won = gain[np.arange(nodes), cut]
                    for k in np.flatnonzero(won > best + 1e-9):
                        best[k], pick[int(k)] = won[k], (int(c), int(cut[k]))
            if not pick:
                break
            for k, (c, _) in pick.items():
                self.importance[c] += best[k]
            splits.append(pick)
            node = self._step(pick, node, x)
        nodes = int(node.max()) + 1
        count, mean = np.bincount(node, weight, nodes), float(t.sum() / weight.sum())
        leaf = (np.bincount(node, t, nodes) + 2 * mean) / (count + 2)
        self.grown.append((splits, leaf, mean))

    @staticmethod
    def _step(pick: dict[int, tuple[int, int]], node: np.ndarray, x: np.ndarray) -> np.ndarray:
        nodes = int(node.max()) + 1 if len(node) else 1
        column, cut = np.full(max(nodes, max(pick) + 1), -1), np.zeros(max(nodes, max(pick) + 1), dtype=np.int64)
        for k, (c, at) in pick.items():
            column[k], cut[k] = c, at
        own = column[node]
        right = (own >= 0) & (x[np.arange(len(x)), np.maximum(own, 0)] > cut[node])
        return 2 * node + right

    def predict(self, codes: np.ndarray) -> np.ndarray:
        out = np.zeros(len(codes))
        for splits, leaf, mean in self.grown:
            node = np.zeros(len(codes), dtype=np.int64)
            for pick in splits:
                node = self._step(pick, node, codes)
            out += np.where(node < len(leaf), leaf[np.minimum(node, len(leaf) - 1)], mean)
        return out / max(1, len(self.grown))


@dataclass
class Neighbours:
    """The mean of the k training rows that agree in most codes; at most ``most`` training rows are kept."""

    k: int = 15
    most: int = 2000
    rows: np.ndarray | None = None
    y: np.ndarray | None = None

    def fit(self, codes: np.ndarray, sizes: Sequence[int], y: np.ndarray) -> Neighbours:
        step = max(1, -(-len(codes) // self.most))
        self.rows, self.y, self.sizes = codes[::step], y[::step].astype(float), list(sizes)
        return self

    @cached_property
    def hot(self) -> np.ndarray:
        return Ridge.one_hot(self.rows, self.sizes)

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "hot"}  # made of the rest

    def predict(self, codes: np.ndarray) -> np.ndarray:
        k = min(self.k, len(self.y))
        out = np.empty(len(codes))
        for low in range(0, len(codes), 4096):
            agree = Ridge.one_hot(codes[low : low + 4096], self.sizes) @ self.hot.T
            near = np.argpartition(-agree, k - 1, axis=1)[:, :k]
            out[low : low + 4096] = self.y[near].mean(axis=1)
        return out


@dataclass
class Network:
    """One hidden layer over one-hot codes, squared error, Adam in mini-batches; targets are standardised."""

    hidden: int = 16
    epochs: int = 12
    batch: int = 256
    rate: float = 0.01
    seed: int = 2

    def fit(self, codes: np.ndarray, sizes: Sequence[int], y: np.ndarray) -> Network:
        rng = np.random.default_rng(self.seed)
        self.sizes = list(sizes)
        x = Ridge.one_hot(codes, self.sizes).astype(np.float64)
        self.shift, self.scale = float(y.mean()), float(y.std() or 1.0)
        t = (y - self.shift) / self.scale
        w = {"a": rng.normal(0, 0.3, (x.shape[1], self.hidden)), "b": rng.normal(0, 0.3, self.hidden), "c": np.zeros(1)}
        first, second, step = {k: 0.0 for k in w}, {k: 0.0 for k in w}, 0
        for _ in range(self.epochs):
            order = rng.permutation(len(x))
            for low in range(0, len(order), self.batch):
                part = order[low : low + self.batch]
                mid = np.tanh(x[part] @ w["a"])
                error = (mid @ w["b"] + w["c"] - t[part]) / len(part)
                grad = {"a": x[part].T @ (np.outer(error, w["b"]) * (1 - mid**2)) + 1e-4 * w["a"], "b": mid.T @ error, "c": error.sum(keepdims=True)}
                step += 1
                for k, g in grad.items():
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.999 * second[k] + 0.001 * g * g
                    w[k] = w[k] - self.rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
        self.weights = w
        return self

    def predict(self, codes: np.ndarray) -> np.ndarray:
        x = Ridge.one_hot(codes, self.sizes)
        return self.shift + self.scale * (np.tanh(x @ self.weights["a"]) @ self.weights["b"] + self.weights["c"])


@dataclass
class _RidgeModel:
    ridge: float = 3.0

    def fit(self, codes: np.ndarray, sizes: Sequence[int], y: np.ndarray) -> _RidgeModel:
        self.sizes = list(sizes)
        self.w = Ridge.of(codes, self.sizes, y, ridge=self.ridge).weights(range(len(self.sizes)))
        return self

    def predict(self, codes: np.ndarray) -> np.ndarray:
        return Ridge.one_hot(codes, self.sizes) @ self.w


#: Settings of each family that are tried; the best on the validation rows is taken.
FAMILIES = {
    "linear": lambda: [_RidgeModel(r) for r in (1.0, 10.0)],
    "forest": lambda: [Forest(depth=d) for d in (4, 8)],
    "neighbours": lambda: [Neighbours(k) for k in (7, 25)],
    "network": lambda: [Network()],
}


@dataclass
class Ensemble:
    """The mean of the fitted values of one model a family, each tuned on validation rows, cut into classes at the end."""

    metric: str
    families: Sequence[str] = ("linear", "forest", "neighbours", "network")
    found: dict = field(default_factory=dict)  # the models by family
    threshold: float = 0.5
    seed: int = 0
    source: Callable[[], tuple[np.ndarray, Sequence[int], np.ndarray]] | None = None  # what it is to be fitted on

    def ready(self) -> Ensemble:
        """Itself, fitted and without the rows that it was fitted on."""
        if self.source:
            source, self.source = self.source, None
            self.fit(*source())
        return self

    def fit(self, codes: np.ndarray, sizes: Sequence[int], y: np.ndarray) -> Ensemble:
        rng = np.random.default_rng(self.seed)
        y = y.astype(float)
        held = rng.random(len(y)) < 0.25
        for name in self.families if codes.shape[1] and len(y) > 20 else ():
            tried = FAMILIES[name]()
            errors = [np.mean((m.fit(codes[~held], sizes, y[~held]).predict(codes[held]) - y[held]) ** 2) for m in tried] if len(tried) > 1 else [0.0]
            self.found[name] = FAMILIES[name]()[int(np.argmin(errors))].fit(codes, sizes, y)
        self.constant = float(np.median(y) if self.metric == "mae" else y.mean()) if len(y) else 0.0
        self.threshold = best_threshold(self.metric, self.values(codes), y)
        return self

    @property
    def models(self) -> dict:
        return self.ready().found

    def values(self, codes: np.ndarray) -> np.ndarray:
        if not self.models:
            return np.full(len(codes), self.constant)
        return np.mean([m.predict(codes) for m in self.models.values()], axis=0)

    def predict(self, codes: np.ndarray) -> np.ndarray:
        said = self.values(codes)  # before the threshold is read
        return (said >= self.threshold).astype(int) if self.metric in CLASSES else said


@dataclass
class Table:
    """Coded candidate columns of a bounded sample of rows, with what subset searches ask of them.

    ``score`` fits the linear model on the training rows and scores the validation rows;
    every call with a new subset counts as a fit.
    """

    names: list[str]
    coders: list[Coder]
    codes: np.ndarray
    y: np.ndarray
    metric: str
    seed: int = 5
    fits: int = 0
    known: dict = field(default_factory=dict)

    def __post_init__(self):
        rng = np.random.default_rng(self.seed)
        self.validation = rng.random(len(self.y)) < 0.3
        self.sizes = [c.size for c in self.coders]
        self.number = {n: k for k, n in enumerate(self.names)}

    @cached_property
    def model(self) -> Ridge:
        train = ~self.validation
        return Ridge.of(self.codes[train], self.sizes, self.y[train].astype(float))

    @cached_property
    def hot(self) -> np.ndarray:
        return Ridge.one_hot(self.codes, self.sizes)

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("model", "hot")}  # made of the rest

    @classmethod
    def of(cls, rows: pd.DataFrame, label: str, names: Iterable[str], metric: str, bins: int = 12) -> Table:
        names = list(names)
        coders = [fit_coder(rows[n], bins) for n in names]
        codes = np.stack([c.code(rows[n]) for c, n in zip(coders, names, strict=True)], axis=1) if names else np.zeros((len(rows), 0), np.int16)
        return cls(names, coders, codes, rows[label].to_numpy(dtype=float), metric)

    def score(self, columns: Sequence[str]) -> float:
        key = tuple(sorted(columns))
        if key not in self.known:
            self.fits += 1
            at = [self.number[c] for c in key]
            places, w = self.model.places(at), self.model.weights(at)
            said = self.hot[:, places] @ w
            train, y = ~self.validation, self.y
            if self.metric in CLASSES:
                cut = best_threshold(self.metric, said[train], y[train])
                said = (said >= cut).astype(int)
            self.known[key] = score(self.metric, said[self.validation], y[self.validation])
        return self.known[key]

    def importances(self, columns: Sequence[str], noise: int, seed: int) -> tuple[dict[str, float], list[float]]:
        """(importance by column, importances of ``noise`` injected random columns) of one forest over all of them."""
        rng = np.random.default_rng(seed)
        at = [self.number[c] for c in columns]
        injected = rng.integers(1, 13, (len(self.codes), noise)).astype(np.int16)
        train = ~self.validation
        self.fits += 1
        found = Forest(trees=20, depth=6, seed=seed).fit(np.hstack([self.codes[:, at], injected])[train], [*[self.sizes[k] for k in at], *[14] * noise], self.y[train]).importance
        return dict(zip(columns, found[: len(at)].tolist(), strict=True)), found[len(at) :].tolist()

    def part(self, columns: Sequence[str]) -> tuple[np.ndarray, list[int], np.ndarray]:
        """(codes, sizes, labels) of some columns, all rows of the sample."""
        at = [self.number[c] for c in columns]
        return self.codes[:, at], [self.sizes[k] for k in at], self.y

    def final(self, columns: Sequence[str], families: Sequence[str] = ("linear", "forest", "neighbours")) -> tuple[list[Coder], Ensemble]:
        """(coders, ensemble) of a plan, on all rows of the sample; it is fitted when first asked, or by ``ready``, wherever that is."""
        return [self.coders[self.number[c]] for c in columns], Ensemble(self.metric, families, source=partial(self.part, tuple(columns)))

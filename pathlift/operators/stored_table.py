"""Coded candidate columns of all rows in the shared folder, with what searches that query a model ask of them.

The driver holds coders and the Gram matrix; whoever asks for a set of columns reads
those of the files, batch by batch, through ``pyarrow.fs``.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field
from functools import cached_property, partial

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.dataset as pds
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.files import shared_folder
from .counted_models import plain
from .joint_models import CLASSES, Coder, Ensemble, Forest, Ridge, best_threshold, score

#: Rows that are read at a time, and folders of partial sums that reach the driver.
BATCH, PARTS = 262_144, 16


@dataclass
class StoredTable:
    """``score`` answers by the linear model of the training rows over the validation rows; every call with a new subset counts as a fit."""

    folder: str
    names: list[str]
    coders: list[Coder]
    model: Ridge  # of the training rows
    squares: float  # of their labels
    metric: str
    fits: int = 0
    known: dict = field(default_factory=dict)

    def __post_init__(self):
        self.sizes = [c.size for c in self.coders]
        self.number = {n: k for k, n in enumerate(self.names)}
        self.starts = np.cumsum([1, *self.sizes])

    def batches(self, at: Sequence[int]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(codes, y, whether they validate) of some columns, all rows, in order."""
        fs, path = pafs.FileSystem.from_uri(self.folder if "://" in self.folder or self.folder.startswith("file:") else f"file://{self.folder}")
        files = sorted(f.path for f in fs.get_file_info(pafs.FileSelector(path)) if f.path.endswith(".parquet"))
        columns = [f"c{k}" for k in at]
        for f in files:
            for b in pds.dataset(f, filesystem=fs, format="parquet").to_batches(columns=["y", "checked", *columns], batch_size=BATCH, use_threads=False):
                codes = np.stack([b.column(c).to_numpy() for c in columns], axis=1) if columns else np.zeros((len(b), 0), np.int8)
                yield codes, b.column("y").to_numpy(), b.column("checked").to_numpy(zero_copy_only=False)

    @cached_property
    def y(self) -> np.ndarray:
        return np.concatenate([np.zeros(0), *[y for _, y, _ in self.batches([])]])

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "y"}  # read from the files

    def mean_code(self, column: str) -> float:
        k = self.number[column]
        n = self.model.gram[0, self.starts[k] : self.starts[k + 1]]
        return float(n @ np.arange(len(n)) / max(1.0, n.sum()))

    def association(self, column: str) -> float:
        """Absolute correlation of a column's code with the label over all training rows."""
        k, total = self.number[column], self.model.gram[0, 0]
        own = slice(self.starts[k], self.starts[k + 1])
        n, s, x = self.model.gram[0, own], self.model.moment[own], np.arange(self.sizes[k])
        if not total:
            return 0.0
        mean_x, mean_y = n @ x / total, self.model.moment[0] / total
        vx, vy = n @ (x * x) / total - mean_x**2, self.squares / total - mean_y**2
        return float(abs((s @ x) / total - mean_x * mean_y) / np.sqrt(vx * vy)) if vx > 1e-12 and vy > 1e-12 else 0.0

    def score(self, columns: Sequence[str]) -> float:
        key = tuple(sorted(columns))
        if key not in self.known:
            self.fits += 1
            at = [self.number[c] for c in key]
            w = self.model.weights(at)
            starts = np.cumsum([1, *[self.sizes[k] for k in at]])
            said, truth, checks = [np.zeros(0)], [np.zeros(0)], [np.zeros(0, dtype=bool)]
            for codes, y, checked in self.batches(at):
                own = np.full(len(y), w[0])
                for c in range(len(at)):
                    own += w[starts[c] + codes[:, c]]
                keep = np.ones(len(y), dtype=bool) if self.metric == "f1" else checked  # only F1 looks for its cut
                said, truth, checks = [*said, own[keep]], [*truth, y[keep]], [*checks, checked[keep]]
            told, y, checked = np.concatenate(said), np.concatenate(truth), np.concatenate(checks)
            if self.metric in CLASSES:
                told = (told >= best_threshold(self.metric, told[~checked], y[~checked])).astype(int)
            self.known[key] = score(self.metric, told[checked], y[checked])
        return self.known[key]

    def importances(self, columns: Sequence[str], noise: int, seed: int) -> tuple[dict[str, float], list[float]]:
        """(importance by column, importances of ``noise`` injected random columns) of one forest over all training rows."""
        at = [self.number[c] for c in columns]
        parts = [(codes[~checked], y[~checked]) for codes, y, checked in self.batches(at)]
        codes, y = np.concatenate([np.zeros((0, len(at)), np.int8), *[c for c, _ in parts]]), np.concatenate([np.zeros(0), *[y for _, y in parts]])
        injected = np.random.default_rng(seed).integers(1, 13, (len(codes), noise)).astype(np.int8)
        self.fits += 1
        found = Forest(trees=20, depth=6, seed=seed).fit(np.hstack([codes, injected]), [*[self.sizes[k] for k in at], *[14] * noise], y).importance
        return dict(zip(columns, found[: len(at)].tolist(), strict=True)), found[len(at) :].tolist()

    def part(self, columns: Sequence[str]) -> tuple[np.ndarray, list[int], np.ndarray]:
        """(codes, sizes, labels) of some columns, all rows."""
        at = [self.number[c] for c in columns]
        parts = [(codes, y) for codes, y, _ in self.batches(at)]
        return np.concatenate([np.zeros((0, len(at)), np.int8), *[c for c, _ in parts]]), [self.sizes[k] for k in at], np.concatenate([np.zeros(0), *[y for _, y in parts]])

    def final(self, columns: Sequence[str], families: Sequence[str] = ("linear", "forest", "neighbours")) -> tuple[list[Coder], Ensemble]:
        """(coders, ensemble) of a plan; ``counted_models`` fits those families on all rows."""
        return [self.coders[self.number[c]] for c in columns], Ensemble(self.metric, families, source=partial(self.part, tuple(columns)))


def store(df: DataFrame, key: str, label: str, names: Sequence[str], coders: Sequence[Coder], metric: str) -> StoredTable:
    """All rows of a frame, in the order of a hash of the key; three of ten validate.  Apart from the class, which is shipped by value and must not reach a session."""
    names, coders, spark = list(names), list(coders), df.sparkSession
    folder = shared_folder(spark, "coded")

    def code(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield pd.DataFrame({"h": pdf["h"], "y": pdf["y"], "checked": pdf["checked"]} | {f"c{k}": c.code(pdf[f"c{k}"]).astype(np.int8) for k, c in enumerate(coders)})

    own = F.col(key).cast("string")
    rows = df.select(F.xxhash64(own).alias("h"), F.col(label).cast("double").alias("y"), (F.pmod(F.xxhash64(own, F.lit("checked")), F.lit(10)) < 3).alias("checked"), *[plain(df.schema[n]).alias(f"c{k}") for k, n in enumerate(names)])
    schema = ", ".join(["h long, y double, checked boolean", *[f"c{k} tinyint" for k in range(len(names))]])
    rows.mapInPandas(code, schema).orderBy("h", "y").drop("h").write.parquet(folder)
    made = StoredTable(folder, names, coders, Ridge([], np.zeros((0, 0)), np.zeros(0)), 0.0, metric)
    sizes = made.sizes

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pd.DataFrame]:
        width = 1 + sum(sizes)
        gram, moment, squares = np.zeros((width, width)), np.zeros(width), 0.0
        for pdf in batches:
            codes, y = pdf[[f"c{k}" for k in range(len(sizes))]].to_numpy(), pdf["y"].to_numpy(dtype=float)
            x = Ridge.one_hot(codes, sizes)
            gram += x.T @ x
            moment += x.T.astype(np.float64) @ y
            squares += float(y @ y)
        yield pd.DataFrame({"found": [pickle.dumps((gram, moment, squares))]})

    stored = spark.read.schema(schema.removeprefix("h long, ")).parquet(folder).where("NOT checked")
    parts = [pickle.loads(bytes(r["found"])) for r in stored.coalesce(PARTS).mapInPandas(sums, "found binary").collect()]  # one matrix a part
    empty = (np.zeros((1 + sum(sizes),) * 2), np.zeros(1 + sum(sizes)), 0.0)
    gram, moment, made.squares = (sum(own, zero) for own, zero in zip(zip(*parts, strict=True) if parts else ((), (), ()), empty, strict=True))
    made.model = Ridge(sizes, gram, moment)
    return made

"""Toxic documents by a subsequence string kernel and a support vector machine.

Strings are words (letters only, lower case; single letters in a row count as one
spaced-out word too).  The kernel compares gapped runs of four letters within a short
span, each skipped letter costing a factor, so an insult keeps many of its runs when
characters are put in, dropped or set apart.  A Nyström map over landmark words turns
the kernel into a few hundred dimensions, where a linear machine with squared hinge
loss is fitted.  Documents carry the labels: a toxic document needs one toxic word
(its witness), a clean one has none, so the machine alternates between choosing
witnesses and fitting.  A logistic curve over a document's highest word gives its score.

Because the kernel is an inner product over explicit runs, the fitted expansion over
landmarks folds into one weight a run: scoring a word needs no landmark any more.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .frames import add_columns, small_batches, tidied

_BITS = 15
_SPAN = 6
_DECAY = 0.6
_MIX = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], dtype=np.uint64)
_OTHER = re.compile(r"[^\w\s]+|[\d_]+")
_SPACED = re.compile(r"(?<!\S)\w(?:\s\w){2,}(?!\S)")
#: Offsets of the second to fourth letter of all runs within the span.
_RUNS = [(i, j, k) for k in range(3, _SPAN) for j in range(2, k) for i in range(1, j)]


def words_of(text: str | None) -> set[str]:
    """Distinct words of a text for the kernel; words over 64 letters are cut into pieces of 64."""
    if not text:
        return set()
    low = _OTHER.sub("", text.lower())
    found = set(low.split())
    if _SPACED.search(low):
        found |= {"".join(m[0].split()) for m in _SPACED.finditer(low)}
    long = [w for w in found if len(w) > 64]
    for w in long:
        found.discard(w)
        found.update(w[k : k + 64] for k in range(0, len(w), 48))
    return found


def _flat(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the words between boundary marks, and each word's length with its marks."""
    body = "".join(f"^{w}$" for w in words)
    return np.frombuffer(body.encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64), np.fromiter((len(w) + 2 for w in words), np.int64, len(words))


def _runs(words: list[str]):
    """For each choice of offsets: (word numbers, run numbers, weight)."""
    codes, lengths = _flat(words)
    owner = np.repeat(np.arange(len(words)), lengths)
    ends = np.repeat(np.cumsum(lengths), lengths)
    at = np.arange(len(codes))
    for i, j, k in _RUNS:
        start = at[at + k < ends]
        mixed = codes[start] * _MIX[0] + codes[start + i] * _MIX[1] + codes[start + j] * _MIX[2] + codes[start + k] * _MIX[3]
        yield owner[start], ((mixed ^ (mixed >> np.uint64(15))) & np.uint64((1 << _BITS) - 1)).astype(np.int64), _DECAY ** (k - 3)


def _scale(lengths: np.ndarray) -> np.ndarray:
    """Kernel scale of words by length (with marks): the weight that all their runs have."""
    total = np.zeros(len(lengths))
    for _, _, k in _RUNS:
        total += np.maximum(0, lengths - k) * _DECAY ** (2 * (k - 3))
    return np.sqrt(np.maximum(total, 1.0))


def _maps(words: list[str]) -> np.ndarray:
    """Run vectors of a few words, as runs by words."""
    out = np.zeros((1 << _BITS, len(words)), dtype=np.float32)
    for owner, run, weight in _runs(words):
        np.add.at(out, (run, owner), weight)
    out /= _scale(np.array([len(w) + 2 for w in words])).astype(np.float32)
    return out


def kernel(words: list[str], landmarks: np.ndarray) -> np.ndarray:
    """Kernel values of words with landmark vectors (runs by landmarks)."""
    out = np.zeros((len(words), landmarks.shape[1]), dtype=np.float32)
    for low in range(0, len(words), 500):
        part = words[low : low + 500]
        for owner, run, weight in _runs(part):
            rows, first = np.unique(owner, return_index=True)
            out[low + rows] += np.float32(weight) * np.add.reduceat(landmarks[run], first, axis=0)
    return out / _scale(np.array([len(w) + 2 for w in words]))[:, None].astype(np.float32)


@dataclass(frozen=True)
class ToxicityModel:
    """Weights by run, a bias, and the logistic curve (slope, shift) over a document's highest word."""

    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def word_scores(self, words: list[str]) -> np.ndarray:
        total = np.zeros(len(words))
        for owner, run, weight in _runs(words):
            total += weight * np.bincount(owner, self.weights[run], len(words))
        return total / _scale(np.array([len(w) + 2 for w in words])) + self.bias

    def probability(self, highest: float) -> float:
        return float(1.0 / (1.0 + np.exp(-np.clip(self.slope * highest + self.shift, -40, 40))))


def _machine(z: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float) -> tuple[np.ndarray, float]:
    """Squared-hinge support vector machine in the primal, by Newton steps."""
    x = np.hstack([z, np.ones((len(z), 1), z.dtype)]).astype(np.float64)
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    for _ in range(25):
        margin = y * (x @ w)
        on = margin < 1
        rows, c = x[on], weight[on]
        hessian = (rows * c[:, None]).T @ rows + np.diag(penalty)
        new = np.linalg.solve(hessian, (rows * c[:, None]).T @ y[on])
        if np.allclose(new, w, rtol=1e-4, atol=1e-6):
            break
        w = new
    return w[:-1], float(w[-1])


def _changed(words: list[str], rng: np.random.Generator) -> list[str]:
    """Each word with a character put in (four times), doubled, and left out, at random places."""
    letters = "abcdefghijklmnopqrstuvwxyz"
    out = []
    for w in words:
        for _ in range(4):
            a = int(rng.integers(1, max(2, len(w))))
            out.append(w[:a] + letters[int(rng.integers(26))] + w[a:])
        a, b = (int(x) for x in rng.integers(0, len(w), 2))
        out += [w[: a + 1] + w[a:], w[:b] + w[b + 1 :]]
    return [w for w in out if len(w) > 3]


def without_copies(words: list[str], bags: list[np.ndarray]) -> list[np.ndarray]:
    """The bags, one of each group that shares the two least long words under one of four orders."""
    hashes = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in words), np.uint64, len(words))
    long = np.fromiter((len(w) > 7 for w in words), bool, len(words))
    kept, seen = [], set()
    for bag in bags:
        own = hashes[bag[long[bag]]]
        if len(own) > 4:
            marks = {(k, *np.sort(own ^ np.uint64(0x9E3779B97F4A7C15 * k % 2**64))[:2].tolist()) for k in range(4)}
        else:
            marks = {tuple(np.sort(hashes[bag]).tolist())}
        if len(bag) and not marks & seen:
            kept.append(bag)
        seen |= marks
    return kept


def indexed(*groups: list[set[str]]) -> tuple[list[str], list[list[np.ndarray]]]:
    """(distinct words, word numbers of each bag of each group)."""
    words = sorted(set(chain.from_iterable(chain.from_iterable(groups))))
    number = {w: i for i, w in enumerate(words)}
    return words, [[np.fromiter((number[w] for w in sorted(b)), np.int64, len(b)) for b in g] for g in groups]


def train(words: list[str], positive: list[np.ndarray], negative: list[np.ndarray], *, landmarks: int = 256, most_words: int = 5_000, strong_words: int = 4_000, significance: float = 18.0, ridge: float = 0.05, rounds: int = 4, seed: int = 5) -> ToxicityModel:
    """A model from the distinct words and the word numbers of toxic and clean documents.

    Bounds of the fit: ``strong_words`` words that toxic documents prefer may become
    witnesses, the first of them are chosen by how well they tell the labels apart;
    ``most_words`` clean words, and as many hard ones among all words of clean documents,
    stand against them.  With a class missing, the model answers the share of toxic
    documents for all.
    """
    share = (len(positive) + 0.5) / (len(positive) + len(negative) + 1.0)
    constant = ToxicityModel(np.zeros(1 << _BITS, np.float32), 0.0, 0.0, float(np.log(share / (1 - share))))
    positive, negative = without_copies(words, positive), without_copies(words, negative)
    if not positive or not negative:
        return constant
    rng = np.random.default_rng(seed)
    bags = {1: positive, 0: negative}
    df = {k: np.bincount(np.concatenate([*v, np.zeros(0, np.int64)]), minlength=len(words)).astype(float) for k, v in bags.items()}
    n1, n0 = len(positive), len(negative)
    expected = (df[1] + df[0]) * n1 / (n1 + n0)
    gain = 2 * (df[1] * np.log(np.maximum(df[1], 0.5) / np.maximum(expected, 1e-9)) + df[0] * np.log(np.maximum(df[0], 0.5) / np.maximum(df[1] + df[0] - expected, 1e-9)))
    strong = (df[1] > expected) & (gain >= significance) & (df[1] / n1 >= 8 * (df[0] + 0.5) / n0)
    strong = np.flatnonzero(strong)[np.argsort(-gain[strong], kind="stable")][:strong_words].tolist()
    # a word is a witness if it explains toxic documents that stronger words leave open,
    # or is not much weaker than those that explain its documents (words of one copied text are)
    holders: dict[int, list[int]] = {i: [] for i in strong}
    for k, bag in enumerate(bags[1]):
        for i in bag.tolist():
            if i in holders:
                holders[i].append(k)
    by: dict[int, float] = {}  # gain of the strongest witness of a document
    witness: set[int] = set()
    for i in strong:
        rivals = [by[k] for k in holders[i] if k in by]
        if len(holders[i]) - len(rivals) >= 2 or (rivals and gain[i] >= 0.5 * float(np.median(rivals))):
            witness.add(i)
            for k in holders[i]:
                by.setdefault(k, float(gain[i]))
    if not witness:
        return constant
    clean = np.flatnonzero(df[0] > 0)
    order = np.concatenate([clean[np.argsort(-df[0][clean], kind="stable")][: most_words // 3], rng.permutation(clean)])
    clean = order[np.sort(np.unique(order, return_index=True)[1])][:most_words]
    clean = np.array([i for i in clean.tolist() if i not in witness])
    hard = np.zeros(0, np.int64)
    model = constant
    for step in range(rounds):
        ranked = sorted(witness, key=lambda i: (-gain[i], words[i]))
        centre = [words[i] for i in ranked[: landmarks // 2]]
        centre += [words[i] for i in np.concatenate([hard, clean])[: landmarks - len(centre)].tolist()]
        mapped = _maps(centre)
        values, vectors = np.linalg.eigh((mapped.T @ mapped).astype(np.float64))
        fine = values > 1e-6 * values.max()
        root = vectors[:, fine] / np.sqrt(values[fine])
        bad = [words[i] for i in ranked]
        extra = _changed(bad, rng)
        z = kernel(bad + extra + [words[i] for i in np.concatenate([clean, hard]).astype(np.int64).tolist()], mapped).astype(np.float64) @ root
        y = np.where(np.arange(len(z)) < len(bad) + len(extra), 1.0, -1.0)
        weight = np.ones(len(z))
        told = np.array([df[1][i] for i in ranked])
        weight[: len(bad)] = len(clean) * np.maximum(told / told.sum(), 0.3 / len(bad))
        weight[len(bad) : len(bad) + len(extra)] = 0.4 * len(clean) / max(1, len(extra))
        w, bias = _machine(z, y, weight, ridge)
        model = ToxicityModel((mapped @ (root @ w)).astype(np.float32), bias, 1.0, 0.0)
        scores = np.concatenate([model.word_scores(words[low : low + 20_000]) for low in range(0, len(words), 20_000)])
        if step + 1 < rounds:
            witness.update(i for i in strong if scores[i] > 0.5)
            for bag in bags[1]:
                if len(bag) and not witness.intersection(bag.tolist()):
                    best = int(bag[np.argmax(scores[bag])])
                    if scores[best] > 0 and not df[0][best]:
                        witness.add(best)
            near = np.flatnonzero((df[0] > 0) & (scores > -0.8))
            near = np.concatenate([near[np.argsort(-scores[near], kind="stable")], hard])
            near = near[np.sort(np.unique(near, return_index=True)[1])]
            hard = np.array([i for i in near.tolist() if i not in witness][:most_words], dtype=np.int64)
    top = {k: np.array([scores[b].max() if len(b) else model.bias for b in v]) for k, v in bags.items()}
    # documents whose insults are disguised belong to the curve as well
    disguised = {i: float(np.median(model.word_scores(made))) for i in sorted(witness) if (made := _changed([words[i]], rng))}
    hidden = [max((disguised[i] for i in b.tolist() if i in disguised), default=model.bias) for b in bags[1]]
    told = np.concatenate([top[1], np.array(hidden), top[0]])
    slope, shift = _curve(told, np.concatenate([np.ones(2 * len(hidden)), np.zeros(len(top[0]))]))
    return ToxicityModel(model.weights, model.bias, slope, shift)


def _curve(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic slope and shift with a weak prior, by Newton steps."""
    beta = np.zeros(2)
    design = np.stack([x, np.ones_like(x)], axis=1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(design @ beta, -30, 30)))
        gradient = design.T @ (y - p) - np.array([0.02, 0.0]) * beta
        hessian = (design * (p * (1 - p))[:, None]).T @ design + np.diag([0.02, 1e-6])
        step = np.linalg.solve(hessian, gradient)
        beta = beta + np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-6:
            break
    return float(max(beta[0], 0.0)), float(beta[1])


def fit_toxicity(documents: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", per_class: tuple[int, int] = (2000, 3500), **settings) -> ToxicityModel:
    """A model from labelled documents.

    Bounds: at most ``per_class`` toxic and clean documents, taken by a hash of their id,
    are used, and the numbers of words that ``train`` names; of documents that look like
    copies of one another one counts.  Rows with a null label, id or text teach nothing;
    of several labels of one id the largest holds; empty texts have no words; other
    columns, whatever their names, are not read.
    """
    named = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(F.col(label_col).cast("int")).alias("y"))
    chosen = []
    for y, most in ((1, per_class[0]), (0, per_class[1])):
        chosen.append(named.where((F.col("y") > 0) == bool(y)).orderBy(F.xxhash64("id"), "id").limit(most))
    picked = chosen[0].unionByName(chosen[1])  # at most sum(per_class) rows
    texts = documents.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).where("text IS NOT NULL").join(F.broadcast(picked), "id").select("id", "y", "text")

    def sets(batches):
        for batch in batches:
            bags = [sorted(words_of(x.as_py())) for x in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(bags, pa.list_(pa.string()))], names=["id", "y", "words"])

    found = texts.mapInArrow(tidied(sets), T.StructType([T.StructField("id", texts.schema["id"].dataType), T.StructField("y", T.IntegerType()), T.StructField("words", T.ArrayType(T.StringType()))]))
    with small_batches(documents.sparkSession):
        found = found.toArrow()
    lists = found.column("words").combine_chunks()
    coded = lists.flatten().dictionary_encode()
    order = np.argsort(np.asarray(coded.dictionary.to_pylist() or [""], dtype=object), kind="stable")
    words = [coded.dictionary[int(i)].as_py() for i in order] if len(coded.dictionary) else []
    number = np.empty(len(order), dtype=np.int64)
    number[order] = np.arange(len(order))
    codes, ends = number[coded.indices.to_numpy()] if len(coded) else np.zeros(0, np.int64), np.concatenate([[0], np.cumsum([len(x) for x in lists])])
    told, ids = found.column("y").to_pylist(), found.column("id").to_pylist()
    del found, lists, coded
    rows = sorted(range(len(told)), key=lambda r: (ids[r], int(ends[r + 1] - ends[r])))
    bag = lambda r: np.sort(codes[ends[r] : ends[r + 1]])
    return train(words, [bag(r) for r in rows if told[r] > 0], [bag(r) for r in rows if not told[r] > 0], **settings)


def score_toxicity(df: DataFrame, model: ToxicityModel, text_col: str = "text", *, threshold: float = 0.3, cache_words: int = 150_000) -> DataFrame:
    """Adds score (0 to 1) and predicted (1 from the threshold on) from whole texts.

    Null and empty texts get the score of a text without any word; texts of any length
    are read whole.  Columns of these names are replaced, others kept; repeated rows score
    alike; an empty table stays empty.
    """

    known: dict[str, float] = {}  # word scores, kept by each Python worker for its tasks

    def highest_words(column) -> np.ndarray:
        highest = np.empty(len(column))
        for low in range(0, len(column), 256):
            bags = [words_of(x.as_py()) for x in column[low : low + 256]]
            if len(known) > cache_words:
                known.clear()
            new = list(set().union(*bags) - known.keys())
            for part in range(0, len(new), 20_000):
                known.update(zip(new[part : part + 20_000], model.word_scores(new[part : part + 20_000]).tolist(), strict=True))
            for k, bag in enumerate(bags):
                highest[low + k] = max(map(known.__getitem__, bag), default=model.bias)
        return highest

    def make(batch: pa.RecordBatch) -> list:
        highest = highest_words(batch.column(batch.schema.names.index(text_col)))
        scores = np.array([model.probability(h) for h in highest.tolist()])
        return [pa.array(scores, pa.float64()), pa.array((scores >= threshold).astype(np.int32), pa.int32())]

    return add_columns(df, [("score", T.DoubleType()), ("predicted", T.IntegerType())], make)

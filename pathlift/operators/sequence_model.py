"""A small recurrent network that reads a path's join statistics and estimates its quality.

One long short-term memory cell with a sigmoid output, in NumPy, trained on squared
error by Adam over at most a thousand short sequences: the driver's work is fixed by
the training budget, not by the data.  Prediction ships the weights to Arrow batches.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
import pandas as pd

#: Statistics of a join step, in order.
INPUTS = ("variance", "entropy_printed", "kl", "pearson", "mutual_info")
EXTENDED = (*INPUTS, "transitivity", "containment")


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


@dataclass
class SequenceModel:
    hidden: int = 16
    epochs: int = 300
    rate: float = 1e-2
    seed: int = 0
    weights: dict[str, np.ndarray] = field(default_factory=dict)
    shift: np.ndarray | None = None
    scale: np.ndarray | None = None

    def _prepared(self, sequences: Sequence[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Padded (paths, steps, inputs) on a log scale, standardised, and the mask of real steps."""
        steps = max(len(s) for s in sequences)
        x = np.zeros((len(sequences), steps, np.shape(sequences[0])[1]))
        mask = np.zeros((len(sequences), steps))
        for i, s in enumerate(sequences):
            s = np.sign(s) * np.log1p(np.abs(s))
            x[i, : len(s)] = (s - self.shift) / self.scale if self.shift is not None else s
            mask[i, : len(s)] = 1
        return x, mask

    def _forward(self, x: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, list]:
        w, h = self.weights, self.hidden
        state, cell = np.zeros((len(x), h)), np.zeros((len(x), h))
        tape = []
        for t in range(x.shape[1]):
            joined = np.hstack([x[:, t], state])
            gates = joined @ w["gates"] + w["gates_bias"]
            i, f, o = (_sigmoid(gates[:, k * h : (k + 1) * h]) for k in range(3))
            g = np.tanh(gates[:, 3 * h :])
            new_cell = f * cell + i * g
            new_state = o * np.tanh(new_cell)
            m = mask[:, t : t + 1]
            tape.append((joined, i, f, o, g, cell, new_cell, m))
            cell, state = m * new_cell + (1 - m) * cell, m * new_state + (1 - m) * state
        out = _sigmoid(state @ w["out"] + w["out_bias"])[:, 0]
        return out, [*tape, state]

    def _backward(self, out: np.ndarray, slope: np.ndarray, tape: list) -> tuple[dict[str, np.ndarray], np.ndarray]:
        """Gradients of the weights and of the inputs, for the slope of the loss by output."""
        w, h = self.weights, self.hidden
        state = tape[-1]
        d_logit = (slope * out * (1 - out))[:, None]
        grads = {k: np.zeros_like(v) for k, v in w.items()}
        grads["out"], grads["out_bias"] = state.T @ d_logit, d_logit.sum(axis=0)
        d_state, d_cell = d_logit @ w["out"].T, np.zeros_like(state)
        d_x = []
        for joined, i, f, o, g, cell, new_cell, m in reversed(tape[:-1]):
            tanh = np.tanh(new_cell)
            ds, dc = d_state * m, d_cell * m
            dc = dc + ds * o * (1 - tanh**2)
            d_gates = np.hstack([dc * g * i * (1 - i), dc * cell * f * (1 - f), ds * tanh * o * (1 - o), dc * i * (1 - g**2)])
            grads["gates"] += joined.T @ d_gates
            grads["gates_bias"] += d_gates.sum(axis=0)
            d_joined = d_gates @ w["gates"].T
            d_x.append(d_joined[:, : joined.shape[1] - h])
            d_state = d_joined[:, joined.shape[1] - h :] + d_state * (1 - m)
            d_cell = dc * f + d_cell * (1 - m)
        return grads, np.stack(d_x[::-1], axis=1)

    def start(self, inputs: int) -> None:
        rng = np.random.default_rng(self.seed)
        h = self.hidden
        self.weights = {"gates": rng.normal(0, 1 / np.sqrt(inputs + h), (inputs + h, 4 * h)), "gates_bias": np.concatenate([np.zeros(h), np.ones(h), np.zeros(2 * h)]), "out": rng.normal(0, 1 / np.sqrt(h), (h, 1)), "out_bias": np.zeros(1)}

    def fit(self, sequences: Sequence[np.ndarray], quality: Sequence[float]) -> SequenceModel:
        rows = np.vstack([np.sign(s) * np.log1p(np.abs(s)) for s in sequences])
        self.shift, self.scale = rows.mean(axis=0), np.maximum(rows.std(axis=0), 1e-6)
        x, mask = self._prepared(sequences)
        y = np.asarray(quality, dtype=float)
        self.start(x.shape[2])
        first = {k: np.zeros_like(v) for k, v in self.weights.items()}
        second = {k: np.zeros_like(v) for k, v in self.weights.items()}
        for step in range(1, self.epochs + 1):
            out, tape = self._forward(x, mask)
            grads, _ = self._backward(out, 2 * (out - y) / len(y), tape)
            for k, g in grads.items():
                first[k] = 0.9 * first[k] + 0.1 * g
                second[k] = 0.999 * second[k] + 0.001 * g * g
                self.weights[k] -= self.rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
        return self

    def predict(self, sequences: Sequence[np.ndarray]) -> np.ndarray:
        x, mask = self._prepared(sequences)
        return self._forward(x, mask)[0]

    def loss(self, sequences: Sequence[np.ndarray], quality: Sequence[float]) -> float:
        return float(np.mean((self.predict(sequences) - np.asarray(quality)) ** 2))

    def saliency(self, sequences: Sequence[np.ndarray]) -> np.ndarray:
        """Mean absolute slope of the estimate by input, over all real steps."""
        x, mask = self._prepared(sequences)
        out, tape = self._forward(x, mask)
        _, d_x = self._backward(out, np.ones_like(out), tape)
        return np.abs(d_x).sum(axis=(0, 1)) / mask.sum()


def predict_frame(model: SequenceModel, paths, sequence_col: str = "steps"):
    """The frame of paths (with array<array<double>> steps) and iq_lstm, estimated in Arrow batches."""
    from pyspark.sql import functions as F

    @F.pandas_udf("double")
    def estimate(steps: pd.Series) -> pd.Series:
        return pd.Series(model.predict([np.array([list(r) for r in s], dtype=float) for s in steps]))

    return paths.withColumn("iq_lstm", estimate(sequence_col))

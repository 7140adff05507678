"""Follow-the-regularised-leader (proximal) training of sparse linear models, with elastic-net penalties, in numpy."""

from __future__ import annotations

import numpy as np

Rows = list[tuple[np.ndarray, np.ndarray]]


def softmax(s: np.ndarray) -> np.ndarray:
    e = np.exp(s - s.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


class FtrlSoftmax:
    """Multinomial logistic regression; ``l1`` zeroes weights, ``l2`` shrinks them. Rows are (indices, values) pairs."""

    def __init__(self, n_features: int, n_classes: int, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.05, l2: float = 0.05):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z = np.zeros((n_features + 1, n_classes))  # the last row is the intercept
        self.n = np.zeros((n_features + 1, n_classes))

    def _weights(self, at: np.ndarray | slice) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        shrunk = np.sign(z) * np.maximum(np.abs(z) - self.l1, 0.0)
        return -shrunk / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)

    def fit(self, rows: Rows, y: np.ndarray, weight: np.ndarray | None = None, epochs: int = 2, seed: int = 0) -> "FtrlSoftmax":
        rng = np.random.default_rng(seed)
        last, eye = self.z.shape[0] - 1, np.eye(self.z.shape[1])
        for _ in range(epochs):
            for i in rng.permutation(len(rows)):
                at, x = np.append(rows[i][0], last), np.append(rows[i][1], 1.0)
                w = self._weights(at)
                g = np.outer(x, (softmax(x @ w) - eye[y[i]]) * (1.0 if weight is None else weight[i]))
                n = self.n[at]
                square = g * g
                self.z[at] += g - (np.sqrt(n + square) - np.sqrt(n)) / self.alpha * w
                self.n[at] = n + square
        return self

    def weights(self) -> tuple[np.ndarray, np.ndarray]:
        w = self._weights(slice(None))
        return w[:-1], w[-1]


def fit_temperature(scores: np.ndarray, y: np.ndarray) -> float:
    """The temperature in [1/3, 20] with the least negative log-likelihood of held-back rows, by golden-section search on its logarithm."""
    if not len(y):
        return 1.0

    def loss(log_t: float) -> float:
        return -np.log(np.maximum(softmax(scores / np.exp(log_t))[np.arange(len(y)), y], 1e-12)).mean()

    a, b, r = -1.1, 3.0, (5**0.5 - 1) / 2
    for _ in range(40):
        c, d = b - r * (b - a), a + r * (b - a)
        a, b = (a, d) if loss(c) < loss(d) else (c, b)
    return float(np.exp((a + b) / 2))

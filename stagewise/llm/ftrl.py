"""Follow-the-regularised-leader (proximal) for logistic models on sparse rows, with elastic-net penalties."""

from __future__ import annotations

import numpy as np


class FtrlLogistic:
    """Multinomial logistic regression; with one class column it is the binary model.

    Each coordinate has a learning rate of its own, ``alpha / (beta + root of the sum of squared gradients)``. ``l1`` sets weights
    to exact zeros, ``l2`` shrinks the rest. The bias is not penalised.
    """

    def __init__(self, features: int, classes: int = 1, alpha: float = 0.3, beta: float = 1.0, l1: float = 1.0, l2: float = 1.0):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z = np.zeros((features, classes))
        self.n = np.zeros((features, classes))
        self.bias_z, self.bias_n = np.zeros(classes), np.zeros(classes)

    def _solve(self, z: np.ndarray, n: np.ndarray, l1: float, l2: float) -> np.ndarray:
        w = (np.sign(z) * l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + l2)
        return np.where(np.abs(z) <= l1, 0.0, w)

    def weights(self) -> tuple[np.ndarray, np.ndarray]:
        return self._solve(self.z, self.n, self.l1, self.l2), self._solve(self.bias_z, self.bias_n, 0.0, 0.0)

    def probabilities(self, margins: np.ndarray) -> np.ndarray:
        if margins.shape[-1] == 1:
            return 1 / (1 + np.exp(-np.clip(margins, -500, 500)))
        e = np.exp(margins - margins.max(-1, keepdims=True))
        return e / e.sum(-1, keepdims=True)

    def learn(self, at: np.ndarray, x: np.ndarray, target: np.ndarray) -> None:
        """One row: its features' numbers (without repeats) and values, and the target of each class column."""
        z, n = self.z[at], self.n[at]
        w = self._solve(z, n, self.l1, self.l2)
        b = self._solve(self.bias_z, self.bias_n, 0.0, 0.0)
        miss = self.probabilities(x @ w + b) - target
        g = x[:, None] * miss
        more = n + g * g
        self.z[at] = z + g - (np.sqrt(more) - np.sqrt(n)) / self.alpha * w
        self.n[at] = more
        more = self.bias_n + miss * miss
        self.bias_z += miss - (np.sqrt(more) - np.sqrt(self.bias_n)) / self.alpha * b
        self.bias_n = more

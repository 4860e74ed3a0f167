"""A small ridge logistic regression for feature matrices of bounded size."""

from __future__ import annotations

import numpy as np


class Logistic:
    """Standardised features, Newton steps; ``weights`` apply to raw features after folding the scale in."""

    def __init__(self, x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 30):
        width = x.shape[1]
        self.mean = x.mean(0) if len(x) else np.zeros(width)
        self.scale = np.where((s := x.std(0)) > 1e-9, s, 1.0) if len(x) else np.ones(width)
        self.w = np.zeros(width + 1)
        if not len(x) or y.min() == y.max():  # nothing to learn: the prior alone
            p = (y.sum() + 0.5) / (len(y) + 1) if len(x) else 0.5
            self.w[0] = np.log(p / (1 - p))
            return
        z = np.hstack([np.ones((len(x), 1)), np.clip((x - self.mean) / self.scale, -8, 8)])
        pen = np.full(width + 1, ridge)
        pen[0] = 1e-6
        for _ in range(steps):
            p = 1 / (1 + np.exp(-np.clip(z @ self.w, -30, 30)))
            grad = z.T @ (y - p) - pen * self.w
            hess = (z * (p * (1 - p) + 1e-9)[:, None]).T @ z + np.diag(pen)
            step = np.linalg.solve(hess, grad)
            self.w += step
            if np.abs(step).max() < 1e-8:
                break

    def logit(self, x: np.ndarray) -> np.ndarray:
        return self.w[0] + np.clip((x - self.mean) / self.scale, -8, 8) @ self.w[1:]


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))

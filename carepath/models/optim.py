"""Rectified Adam under a look-ahead, on flat weight vectors."""

from __future__ import annotations

import numpy as np


class LookaheadRAdam:
    def __init__(self, rate: float = 1e-3, betas: tuple[float, float] = (0.9, 0.999), epsilon: float = 1e-8, k: int = 6, alpha: float = 0.5):
        self.rate, self.betas, self.epsilon, self.k, self.alpha = rate, betas, epsilon, k, alpha
        self.t = 0
        self.m = self.v = self.slow = None

    def step(self, w: np.ndarray, g: np.ndarray) -> np.ndarray:
        """The weights after one update; every k updates they move from the slow ones by alpha."""
        if self.m is None:
            self.m, self.v, self.slow = np.zeros_like(w), np.zeros_like(w), w.copy()
        self.t += 1
        b1, b2 = self.betas
        self.m *= b1
        self.m += (1 - b1) * g
        self.v *= b2
        self.v += (1 - b2) * g * g
        mean = self.m / (1 - b1**self.t)
        long = 2 / (1 - b2) - 1
        now = long - 2 * self.t * b2**self.t / (1 - b2**self.t)
        if now > 4:  # enough steps for the variance to be known
            r = np.sqrt((now - 4) * (now - 2) * long / ((long - 4) * (long - 2) * now))
            w = w - self.rate * r * mean / (np.sqrt(self.v / (1 - b2**self.t)) + self.epsilon)
        else:
            w = w - self.rate * mean
        if self.t % self.k == 0:
            self.slow = self.slow + self.alpha * (w - self.slow)
            w = self.slow.copy()
        return w

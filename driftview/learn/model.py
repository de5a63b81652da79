"""Linear models: score w.f - b, class +1 where the score is not negative."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Model:
    """Weights and bias of one round."""

    w: np.ndarray
    b: float
    round: int = 0

    @classmethod
    def zero(cls, dim: int) -> Model:
        return cls(np.zeros(dim), 0.0)

    def score(self, f: np.ndarray) -> float:
        """Terms are added from left to right, as an unrolled expression adds them."""
        total = 0.0
        for weight, value in zip(self.w.tolist(), np.asarray(f, float).tolist(), strict=True):
            total += weight * value
        return total - self.b

    def sparse_score(self, idx: np.ndarray, val: np.ndarray) -> float:
        return float(self.w[idx] @ val) - self.b


def sign(x: float) -> int:
    return 1 if x >= 0 else -1

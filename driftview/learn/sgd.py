"""Stochastic gradient steps, one example at a time, for several losses.

The reference names the method and leaves step sizes open; the schedule here is
ours: eta0 / (1 + l2 * eta0 * t), or a constant eta0.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass
from itertools import chain

import numpy as np

from driftview.learn.model import Model

Vector = np.ndarray | tuple[np.ndarray, np.ndarray]


def hinge(y: float, z: float) -> float:
    return -y if y * z < 1 else 0.0


def logistic(y: float, z: float) -> float:
    return -y / (1.0 + math.exp(min(700.0, y * z)))


def squared(y: float, z: float) -> float:
    return z - y


LOSSES = {"hinge": hinge, "logistic": logistic, "squared": squared}


@dataclass(frozen=True)
class SgdTrainer:
    """``l2`` shrinks weights, never the bias; class weights and example weights scale the loss's slope."""

    loss: str = "hinge"
    eta0: float = 0.1
    l2: float = 0.0
    constant: bool = False
    class_weights: tuple[float, float] = (1.0, 1.0)

    def rate(self, t: int) -> float:
        return self.eta0 if self.constant else self.eta0 / (1.0 + self.l2 * self.eta0 * t)

    def step(self, model: Model, f: Vector, y: int, weight: float = 1.0) -> Model:
        """The model after one example; ``f`` is dense, or (indexes, values)."""
        eta = self.rate(model.round)
        sparse = isinstance(f, tuple)
        z = model.sparse_score(*f) if sparse else model.score(f)
        g = LOSSES[self.loss](y, z) * weight * self.class_weights[int(y > 0)]
        w = model.w * (1.0 - eta * self.l2) if self.l2 else model.w.copy()
        if g:
            if sparse:
                np.subtract.at(w, f[0], eta * g * f[1])
            else:
                w = w - eta * g * np.asarray(f, float)
        return Model(w, model.b + eta * g if g else model.b, model.round + 1)

    def run(self, model: Model, batch: Iterable[tuple[Vector, int]]) -> Model:
        """The model after a batch, which is read once and not held; sparse examples take time in proportion to their non-zeros, and the weights are copied once."""
        batch = iter(batch)
        first = next(batch, None)
        if first is None:
            return model
        batch = chain([first], batch)
        if isinstance(first[0], tuple):
            scaled = ScaledSgd(self, model)
            for f, y in batch:
                scaled.step(*f, y)
            return scaled.model()
        for f, y in batch:
            model = self.step(model, f, y)
        return model

    def partial_fit(self, model: Model, batch: Iterable[tuple[Vector, int]]) -> list[Model]:
        """A model for each example of the batch, in order."""
        out = []
        for f, y in batch:
            model = self.step(model, f, y)
            out.append(model)
        return out

    def fit(self, examples: list[tuple[Vector, int]], dim: int, epochs: int = 1) -> Model:
        """Warm training over the examples in the order given."""
        model = Model.zero(dim)
        for _ in range(epochs):
            model = self.run(model, examples)
        return model


class ScaledSgd:
    """Sparse steps in time proportional to an example's non-zeros: weights are scale * v.

    Inner products with the weights of a stored model are carried along, so the
    Euclidean distance to it is known after each step without a pass over d.
    """

    def __init__(self, trainer: SgdTrainer, model: Model) -> None:
        self.trainer, self.t, self.b = trainer, model.round, model.b
        self.scale, self.v = 1.0, model.w.copy()
        self.store()

    def store(self) -> None:
        """Take the present weights as the stored ones."""
        self._fold()
        self.stored = self.v.copy()
        self.ww = self.ws = self.ss = float(self.v @ self.v)

    def _fold(self) -> None:
        self.v *= self.scale
        self.scale = 1.0

    def step(self, idx: np.ndarray, val: np.ndarray, y: int) -> None:
        eta = self.trainer.rate(self.t)
        dot = self.scale * float(self.v[idx] @ val)
        g = LOSSES[self.trainer.loss](y, dot - self.b) * self.trainer.class_weights[int(y > 0)]
        shrink = 1.0 - eta * self.trainer.l2
        self.scale *= shrink
        self.ww *= shrink * shrink
        self.ws *= shrink
        if g:
            step = -eta * g
            self.ww += 2 * step * shrink * dot + step * step * float(val @ val)
            self.ws += step * float(self.stored[idx] @ val)
            np.add.at(self.v, idx, step / self.scale * val)
            self.b += eta * g
        if self.scale < 1e-9:
            self._fold()
        self.t += 1

    def distance(self) -> float:
        return math.sqrt(max(0.0, self.ww - 2 * self.ws + self.ss))

    def model(self) -> Model:
        return Model(self.v * self.scale, self.b, self.t)

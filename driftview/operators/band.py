"""How far margins can have moved since the stored model, and what that settles.

An entity's margin under the current model is its stored margin plus dw.f - db,
and |dw.f| is at most the p-norm of dw times the q-norm of f where 1/p + 1/q = 1.
With M the largest q-norm of all entities, every entity whose stored margin
reaches db + M |dw| has a margin of 0 or more, and every one whose stored margin
is less than db - M |dw| has a negative one.  The low side is strict: a margin
of exactly 0 is in the positive class.
"""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from driftview.learn.model import Model


def norm(x: np.ndarray, p: float) -> float:
    x = np.abs(np.asarray(x, float))
    if not x.size:
        return 0.0
    if math.isinf(p):
        return float(x.max())
    return float(x.sum()) if p == 1 else float((x**p).sum() ** (1.0 / p))


@dataclass(frozen=True)
class HolderPair:
    """``p`` measures the move of the weights, ``q`` the entities."""

    p: float = 2.0
    q: float = 2.0

    def __post_init__(self) -> None:
        if abs(1.0 / self.p + 1.0 / self.q - 1.0) > 1e-9:
            raise ValueError(f"1/{self.p} + 1/{self.q} is not 1")

    @classmethod
    def for_norm(cls, entities: str) -> HolderPair:
        """The pair for entities normalized in ``l1``, ``l2`` or ``linf``."""
        return {"l1": cls(math.inf, 1.0), "l2": cls(2.0, 2.0), "linf": cls(1.0, math.inf)}[entities]


def deviation_interval(stored: Model, current: Model, largest: float, p: float, slack: float = 0.0) -> tuple[float, float]:
    """Stored margins below the first are surely negative now, those from the second on surely positive."""
    if stored is current:
        return 0.0, 0.0
    reach = largest * norm(current.w - stored.w, p)
    shift = current.b - stored.b
    return shift - reach - slack, shift + reach + slack


def float_slack(largest: float, model: Model, p: float) -> float:
    """Room for sums of doubles in another order."""
    return 1e-9 * (1.0 + largest * norm(model.w, p) + abs(model.b))


@dataclass
class WaterMarks:
    """Bounds of the band since the stored model.

    ``cumulative`` keeps the widest bounds so far, which a view that is fixed
    round by round needs; ``pairwise`` covers the last two rounds, which is
    enough if the view was right one round ago; ``current`` covers this round
    alone, and is right only for reads that score the band anew.
    The extremes run along, so a push and a read take constant time; moves are
    kept, so that they can be redone for a larger M.
    """

    kind: str = "cumulative"
    moves: list[tuple[float, float]] = field(default_factory=lambda: [(0.0, 0.0)])
    _extremes: tuple[float, int, float, float] = field(default=(-1.0, 0, math.inf, -math.inf), repr=False)

    def push(self, distance: float, shift: float) -> None:
        self.moves.append((distance, shift))

    def bounds(self, largest: float, slack: float = 0.0) -> tuple[float, float]:
        if self.kind == "cumulative":
            of, seen, low, high = self._extremes
            if of != largest:
                seen, low, high = 0, math.inf, -math.inf
            low, high = self._widened(self.moves[seen:], largest, low, high)
            self._extremes = (largest, len(self.moves), low, high)
            return min(0.0, low - slack), max(0.0, high + slack)
        span = self.moves[-2:] if self.kind == "pairwise" else self.moves[-1:]
        low, high = self._widened(span, largest, math.inf, -math.inf)
        if (0.0, 0.0) in span:
            return min(0.0, low - slack), max(0.0, high + slack)
        return low - slack, high + slack

    @staticmethod
    def _widened(moves: Sequence[tuple[float, float]], largest: float, low: float, high: float) -> tuple[float, float]:
        for d, b in moves:
            if d > 0 or b != 0:
                low, high = min(low, b - largest * d), max(high, b + largest * d)
        return low, high

    def reset(self) -> None:
        self.moves = [(0.0, 0.0)]
        self._extremes = (-1.0, 0, math.inf, -math.inf)


def water_marks(models: Sequence[Model], stored: int, largest: float, p: float, kind: str = "cumulative", slack: float = 0.0) -> list[tuple[int, float, float, float, float]]:
    """(round, low, high, low water, high water) for every round from the stored one on."""
    marks, out = WaterMarks(kind), []
    for j in range(stored, len(models)):
        low, high = deviation_interval(models[stored], models[j], largest, p, slack)
        if j > stored:
            marks.push(norm(models[j].w - models[stored].w, p), models[j].b - models[stored].b)
        out.append((j, low, high, *marks.bounds(largest, slack)))
    return out


def certain_class(eps: Column, low_water: Column | float, high_water: Column | float) -> Column:
    """1, -1, or null where the stored margin alone does not tell."""
    as_column = lambda x: x if isinstance(x, Column) else F.lit(float(x))
    return F.when(eps >= as_column(high_water), 1).when(eps < as_column(low_water), -1)


def in_band(eps: Column, low_water: float, high_water: float) -> Column:
    return (eps >= F.lit(float(low_water))) & (eps < F.lit(float(high_water)))

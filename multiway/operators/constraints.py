"""Constraint sets of a factor, as element-wise projections; they combine with `&` in the order shrink, then clip."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Constraint:
    """threshold: soft threshold; scaled: divide it by the curvature of the column step; clip: no negative entries."""

    threshold: float = 0.0
    scaled: bool = False
    clip: bool = False
    floor: float = 0.0

    def __and__(self, other: Constraint) -> Constraint:
        return Constraint(max(self.threshold, other.threshold), self.scaled or other.scaled, self.clip or other.clip, max(self.floor, other.floor))

    def __call__(self, x: np.ndarray, curvature=1.0) -> np.ndarray:
        if self.threshold:
            c = self.threshold / np.maximum(curvature, 1e-12) if self.scaled else self.threshold
            x = np.sign(x) * np.maximum(np.abs(x) - c, 0.0)
        return np.maximum(x, self.floor) if self.clip else x

    @property
    def free(self) -> bool:
        return not (self.threshold or self.clip)


FREE = Constraint()


def nonneg(floor: float = 0.0) -> Constraint:
    return Constraint(clip=True, floor=floor)


def soft(c: float, scaled: bool = False) -> Constraint:
    return Constraint(threshold=c, scaled=scaled)


def per_mode(constraint: Constraint | dict[int, Constraint] | None, order: int) -> list[Constraint]:
    if isinstance(constraint, dict):
        return [constraint.get(n, FREE) for n in range(order)]
    return [constraint or FREE] * order

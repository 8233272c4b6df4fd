"""The shape and seeds of a sketch."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


class SketchExhausted(RuntimeError):
    """A component still has edges to sample, but the sketch has no unused row left."""


@dataclass(frozen=True)
class SketchSpec:
    """rows: rho; levels: tau; sketches: T independent sketches; family: "portable" (arithmetic that any SQL engine can redo) or "native" (xxhash64)."""

    rows: int = 24
    levels: int = 24
    sketches: int = 1
    seed: int = 1
    family: str = "portable"
    rows_per_round: int = 2

    def copies(self, t: int) -> SketchSpec:
        return replace(self, sketches=t)

    @property
    def words(self) -> int:
        """phi, the words of one dense vertex sketch."""
        return self.sketches * self.rows * self.levels


def size_spec(vertices: int, updates: int, rows_per_round: int = 2, **more) -> SketchSpec:
    """rho = rows a round * (log2 V + 4) rounds, tau = log2 N + 1."""
    rounds = math.ceil(math.log2(max(2, vertices))) + 4
    return SketchSpec(rows=rows_per_round * rounds, levels=math.ceil(math.log2(max(2, updates))) + 1, rows_per_round=rows_per_round, **more)

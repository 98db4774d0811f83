"""Parameters of a voting forest."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil, sqrt


class VectorSchemaError(ValueError):
    """Vectors that are null, hold nulls or NaN, or differ in length."""


@dataclass(frozen=True)
class ForestParams:
    """T trees of depth l, with random directions of a given density.

    density: share of non-zero components, a number in (0, 1] or "1/sqrt(d)".
    components: gaussian; ternary (+1, 0, -1 with 1/6, 2/3, 1/6); very_sparse (+1, 0, -1 with 1/(2 sqrt d) each side).
    nnz: bernoulli (each component on its own) or exact (ceil(a d) non-zeros in every direction).
    direction_scope: level (one direction for all nodes of a level) or node (one for each node).
    split: median, or fractile (a hashed fraction between 1/4 and 3/4 at each node).
    tie: threshold (values at or below the median go left) or rank (the first ceil(n/2) by value and id do).
    build: tree_local, level_exact, level_sketch, sample, or auto: exact medians, by tree or by level as the number of points has it.
    sample: the share of the points that fit the splits of build "sample"; without it, as many as make SAMPLE_ROWS.
    """

    trees: int = 16
    depth: int = 4
    density: float | str = "1/sqrt(d)"
    seed: int = 42
    components: str = "gaussian"
    nnz: str = "bernoulli"
    direction_scope: str = "level"
    split: str = "median"
    tie: str = "threshold"
    build: str = "auto"
    sample: float | None = None

    def share(self, d: int) -> float:
        """The density for d dimensions, rounded to 9 decimals."""
        if self.components == "ternary":
            return round(1 / 3, 9)
        if self.components == "very_sparse" or self.density == "1/sqrt(d)":
            return round(1 / sqrt(d), 9)
        return float(self.density)

    def nonzeros(self, d: int) -> int:
        return ceil(round(self.share(d) * d, 6))

    def validate(self, n: int | None = None, d: int | None = None) -> ForestParams:
        """Raises ValueError on values that make no forest; a tree needs fewer inner nodes than there are points."""
        allowed = {
            "components": ("gaussian", "ternary", "very_sparse"), "nnz": ("bernoulli", "exact"), "direction_scope": ("level", "node"),
            "split": ("median", "fractile"), "tie": ("threshold", "rank"), "build": ("auto", "tree_local", "level_exact", "level_sketch", "sample"),
        }
        for name, values in allowed.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} is one of {', '.join(values)}")
        if self.trees < 1 or not 0 <= self.depth <= 30:
            raise ValueError("a forest has one tree or more, of depth 0 to 30")
        if isinstance(self.density, str) and self.density != "1/sqrt(d)" or not isinstance(self.density, str) and not 0 < self.density <= 1:
            raise ValueError("density is in (0, 1], or 1/sqrt(d)")
        if n is not None and self.depth and 2**self.depth - 1 >= n:
            raise ValueError(f"depth {self.depth} needs more than {2**self.depth - 1} points; there are {n}")
        if d is not None and d < 1:
            raise ValueError("vectors have one dimension or more")
        return self

    def but(self, **changes) -> ForestParams:
        return replace(self, **changes)

"""All constants of the scoring and maintenance formulas, and weight vectors."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    half_life: float = 30.0
    window: str = "closed"  # or "half_open": what counts as inside a validity interval
    outside: float = 0.05  # temporal score outside it
    floor_in_window: bool = False
    age_mode: str = "whole"  # or "fractional"
    libm: bool = False  # decay of trust by the C library's power, to the last bit, where nearly equal trusts are compared
    up: float = 0.03  # trust for each positive, and less for each negative, feedback
    down: float = 0.08
    least: float = 0.01
    access: float = 0.01
    bonus: float = 0.1
    bonus_cap: float = 0.3
    dormant_below: float = 0.15
    ripple: float = 0.15
    hops: int = 2
    ripple_floor: float | None = 0.01
    kappa: float = 10.0  # pseudo-count of the Beta form of trust

    def but(self, **changes) -> Params:
        return replace(self, **changes)


@dataclass(frozen=True)
class Weights:
    """Weights of similarity, temporal validity, trust and relations: not negative, with sum 1."""

    sim: float
    tmp: float = 0.0
    tru: float = 0.0
    rel: float = 0.0

    def __post_init__(self):
        if min(self.as_tuple()) < 0 or abs(sum(self.as_tuple()) - 1) > 1e-9:
            raise ValueError(f"weights must not be negative and sum to 1: {self.as_tuple()}")

    def as_tuple(self) -> tuple[float, float, float, float]:
        return self.sim, self.tmp, self.tru, self.rel

    def without(self, name: str) -> Weights:
        """This vector with one weight at zero and the rest scaled to sum 1."""
        left = {k: (0.0 if k == name else v) for k, v in zip(("sim", "tmp", "tru", "rel"), self.as_tuple(), strict=True)}
        total = sum(left.values())
        return Weights(**{k: v / total for k, v in left.items()})


# The rankers compared, and presets by kind of domain
RANKERS = {
    "m1": Weights(1.0),
    "m2": Weights(0.6, 0.4),
    "m3": Weights(0.6, 0.0, 0.4),
    "m4": Weights(0.35, 0.25, 0.25, 0.15),
    "m5": Weights(0.5, 0.2, 0.0, 0.3),
}
PRESETS = {"default": RANKERS["m4"], "volatile": Weights(0.25, 0.4, 0.2, 0.15), "stable": Weights(0.55, 0.1, 0.2, 0.15)}

# Prior trust by class of source
AUTHORITY = {"official_db": 0.95, "policy": 0.90, "tech_doc": 0.80, "wiki": 0.60, "chat": 0.30}


def grid(step: float = 0.1) -> list[tuple[float, float, float, float]]:
    """All weight vectors on the simplex with the given step, similarity-heavy first."""
    n = round(1 / step)
    return [(a / n, b / n, c / n, (n - a - b - c) / n) for a in range(n, -1, -1) for b in range(n - a, -1, -1) for c in range(n - a - b, -1, -1)]

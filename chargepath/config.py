"""Options of a trip plan. Lengths are in the unit of the edge weights."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction


@dataclass(frozen=True)
class TripOptions:
    """capacity Q; alpha and beta = 1 - alpha share it between the search around
    a base and the distance of bases; n stations are wanted at each base."""

    capacity: int = 10_000
    penalty: int = 2_400
    n: int = 5
    alpha: float = 0.2
    split_rule: str = "greedy"  # or multiples
    split_step: str = "beta"  # or capacity
    tail_rule: str = "beta"  # or capacity: no cut once the rest is within Q
    leg_limit: str = "capacity"  # or beta
    leg_mode: str = "one_to_many"  # or pairwise
    direction: str = "out"  # of the search around a base: out, in, both
    order: str = "network"  # of candidates: network, straight, bins
    penalty_mode: str = "proportional"  # none, flat, proportional_no_last
    max_widen: int = 6
    direct_if_within: bool = True
    mitigation: str = "none"  # or slide: move a base without stations along the path
    slide_steps: int = 8
    widen_factor: float = 1.5  # of the search radius when stations are too few
    plugs: tuple[str, ...] | None = None  # that fit the vehicle; None for all
    final: str = "group"  # or layers, sssp, udtf: how the process graph is solved

    def __post_init__(self) -> None:
        if self.capacity <= 0 or self.n <= 0 or not 0 < self.alpha < 1 or self.penalty < 0 or self.max_widen < 0 or not 0 < self.slide_steps < 10_000 or self.widen_factor <= 1:
            raise ValueError("capacity, n and slide_steps must be positive, alpha between 0 and 1, penalty and max_widen not negative, widen_factor over 1")
        if self.plugs is not None:
            object.__setattr__(self, "plugs", tuple(self.plugs))
        for name, known in (("split_rule", "greedy multiples"), ("split_step", "beta capacity"), ("tail_rule", "beta capacity"), ("leg_limit", "beta capacity"), ("leg_mode", "one_to_many pairwise"), ("direction", "out in both"), ("order", "network straight bins"), ("penalty_mode", "proportional none flat proportional_no_last"), ("mitigation", "none slide"), ("final", "group layers sssp udtf")):
            if getattr(self, name) not in known.split():
                raise ValueError(f"{name} must be one of {known}")

    @property
    def disk(self) -> int:
        return int(self.alpha * self.capacity)

    @property
    def step(self) -> int:
        return self.capacity if self.split_step == "capacity" else self.capacity - self.disk

    @property
    def limit(self) -> int:
        return self.capacity - self.disk if self.leg_limit == "beta" else self.capacity

    def radius(self, k: int) -> int:
        """Search radius after k widenings, each rounded down."""
        r, factor = self.disk, Fraction(self.widen_factor).limit_denominator(1000)
        for _ in range(k):
            r = r * factor.numerator // factor.denominator
        return r

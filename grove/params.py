"""Parameters of the tree solver."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class TreeMisParams:
    """mem_exp: a machine holds about n^mem_exp rows. decay: a reduction step takes the maximum
    degree D to about D^(1 / (1 + decay)). The rest have defaults derived from n and D."""

    mem_exp: float = 0.5
    decay: float = 0.5
    delta_prime: float = 0.01
    delta: float | None = None
    degree_floor: int | None = None
    floor_power: float = 1.0
    shatter_rounds: int | None = None
    singleton: str = "join"
    gather: str = "auto"
    local: str = "greedy"
    seed: int = 7
    max_steps: int = 40
    patience: int = 3
    hub_cleanup: bool | None = None
    diameter: int = 16

    def sampling_exponent(self) -> float:
        """delta with (1 + delta') * delta = 1 / (1 + decay)."""
        return self.delta if self.delta is not None else 1 / ((1 + self.decay) * (1 + self.delta_prime))

    def floor_for(self, n: int) -> int:
        return self.degree_floor if self.degree_floor is not None else max(2, math.ceil(math.log2(max(2, n)) ** self.floor_power))

    def rounds_for(self, max_degree: int) -> int:
        return self.shatter_rounds if self.shatter_rounds is not None else 2 * math.ceil(math.log2(max_degree + 2))

    def hub_degree(self, n: int) -> float:
        """Nodes of this degree are set aside by the hub clean-up."""
        return max(2.0, n ** (self.mem_exp / 2))

"""How a budget is spread over rounds, and when rounds grow.

The annealing rule and the score's noise term are not in the text we have; both are parameters with defaults from published work on
adaptive marginal release. They read released values only.
"""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass
class Schedule:
    """Noise scale and selection epsilon of the current round."""

    sigma: float
    epsilon: float
    measure_share: float = 0.9

    @classmethod
    def initial(cls, rho: float, n_closure: int, measure_share: float = 0.9) -> Schedule:
        """One round costs rho / (2 n_closure), shared between measuring and selecting."""
        return cls(math.sqrt(n_closure / (measure_share * rho)), math.sqrt(4 * (1 - measure_share) * rho / n_closure), measure_share)

    @property
    def round_rho(self) -> float:
        return 1 / (2 * self.sigma**2) + self.epsilon**2 / 8

    def anneal(self, moved_l1: float, cells: int) -> bool:
        """Halve the noise and double epsilon if the chosen estimate moved less than noise alone would move it."""
        if moved_l1 < math.sqrt(2 / math.pi) * self.sigma * cells:
            self.sigma, self.epsilon = self.sigma / 2, self.epsilon * 2
            return True
        return False

    def replay(self, rounds: list[tuple], domain) -> None:
        """Where the schedule stands after the rounds of a trace."""
        for _, gamma, sigma2, epsilon, _, _, _, _, moved, _ in rounds:
            self.sigma, self.epsilon = math.sqrt(sigma2), epsilon
            self.anneal(moved, domain.size(gamma))

    def fit(self, left: float) -> None:
        """Spend all that is left if it is less than two rounds."""
        if left < 2 * self.round_rho:
            self.sigma = 1 / math.sqrt(2 * self.measure_share * left)
            self.epsilon = math.sqrt(8 * (1 - self.measure_share) * left)

"""Parameter rules of the randomized methods and the round bounds they are compared with."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Params:
    """n vertices and the exponent eps in [0, 1] that separates heavy from light (support n^eps)."""

    n: int
    eps: float

    @classmethod
    def for_finding(cls, n: int) -> Params:
        """n^eps = n^(1/3) / (ln n)^(2/3), clamped."""
        return cls(n, cls.clamp(1 / 3 - 2 / 3 * math.log(math.log(n)) / math.log(n)) if n > 2 else 0.0)

    @classmethod
    def for_listing(cls, n: int) -> Params:
        """n^eps = n^(1/2) / (ln n)^2, clamped: 0 below about 5,500 vertices."""
        return cls(n, cls.clamp(1 / 2 - 2 * math.log(math.log(n)) / math.log(n)) if n > 2 else 0.0)

    @staticmethod
    def clamp(eps: float) -> float:
        return min(1.0, max(0.0, eps))

    @property
    def threshold(self) -> float:
        return self.n**self.eps

    @property
    def sample_probability(self) -> float:
        return self.n**-self.eps

    @property
    def sample_cap(self) -> int:
        return math.floor(4 * self.n ** (1 - self.eps) + 1e-9)

    @property
    def buckets(self) -> int:
        return max(1, math.floor(self.n ** (self.eps / 2) + 1e-9))

    @property
    def bucket_cap(self) -> int:
        return math.floor(8 + 4 * self.n / self.buckets + 1e-9)

    @property
    def x_probability(self) -> float:
        return 1 / (9 * self.n**self.eps)

    @property
    def r(self) -> float:
        """Offer limit; the logarithm is natural, as the tail bound behind it needs."""
        return math.sqrt(54 * self.n ** (1 + self.eps) * math.log(max(2, self.n)))

    def budget(self, c: float) -> float:
        return c * (self.n ** (1 - self.eps) + self.n ** ((1 + self.eps) / 2) * math.log(max(2, self.n)))


def find_repetitions(delta: float) -> int:
    """Repetitions of the finding pass until it misses with probability delta, at 0.38 a pass."""
    return max(1, math.ceil(math.log(1 / delta) / -math.log(1 - 0.38)))


def list_repetitions(n: int, c: float = 5.4) -> int:
    return max(1, math.ceil(c * math.log(max(2, n))))


#: Asymptotic round bounds with all constants 1: name, formula in n and d (largest degree), as Python and SQL.
BOUNDS = {
    "find": "pow(n, CAST(2 AS DOUBLE) / 3) * pow(ln(n), CAST(2 AS DOUBLE) / 3)",
    "list": "pow(n, 0.75) * ln(n)",
    "two_hop": "d * 1.0",
    "all_pairs_list": "pow(n, CAST(1 AS DOUBLE) / 3) * pow(ln(n), CAST(2 AS DOUBLE) / 3)",
    "all_pairs_degree_list": "pow(d, 3) / n",
    "all_pairs_algebraic_find": "pow(n, 0.1572)",
    "broadcast_find_lower": "n / (exp(sqrt(ln(n))) * ln(n))",
    "list_lower_earlier": "pow(n, CAST(1 AS DOUBLE) / 3) / pow(ln(n), 3)",
    "list_lower": "pow(n, CAST(1 AS DOUBLE) / 3) / ln(n)",
    "local_list_lower": "n / ln(n)",
}

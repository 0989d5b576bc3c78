"""Parameters and the quantities derived from them."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PprParams:
    """alpha: stop probability; epsilon, delta, p_f: relative error, threshold and failure probability; x = r_max * omega
    is beta / alpha in tuned mode; theta: error split of the lazy baseline."""

    alpha: float = 0.2
    epsilon: float = 0.5
    delta: float = 1e-3
    p_f: float = 1e-3
    beta: float = 1.0
    theta: float = 0.5
    k: int = 500
    seed: int = 7
    fast_hash: bool = False

    @classmethod
    def for_graph(cls, n: int, **over) -> PprParams:
        base = cls(delta=1.0 / n, p_f=1.0 / n, k=min(500, max(1, n // 4)))
        return replace(base, **over)

    @property
    def omega(self) -> float:
        e = self.epsilon
        return (2 * e / 3 + 2) * math.log(2 / self.p_f) / (e * e * self.delta)

    @property
    def x(self) -> float:
        """Walks stored for each out-edge."""
        return self.beta / self.alpha

    def r_max(self, m: int, mode: str = "tuned") -> float:
        if mode == "balanced":
            return math.sqrt(1 / (m * self.omega))
        return {"linear": 1.0, "tuned": self.x}[mode] / self.omega

    def backward_r_max(self, m: int, n: int, undirected: bool) -> float:
        """Times the degree of the target for undirected graphs."""
        return 1 / m if undirected else 1 / n

    def walks_needed(self, residue: Column) -> Column:
        return F.ceil(residue * F.lit(self.omega))

    def walks_stored(self, degree: Column, x: float | None = None) -> Column:
        return F.ceil(degree * F.lit(self.x if x is None else x)).cast("long")

"""What a physical plan of one EM round returns, and the choice between plans."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from relmix.models.families import Family, Params

#: Up to so many sums the fused plan is taken, beyond it Arrow. Measured seconds of one round on 600,000
#: rows and eight cores, fused against Arrow: 6 sums 0.22, 0.38; 24 sums 0.42, 0.20; 60 sums 0.57, 0.39;
#: 84 sums 0.56, 0.26; at 288 sums compiling alone takes over two seconds a round.
FUSED_SUMS = 16


@dataclass
class Round:
    """Row count, log-likelihood of the entering parameters, and the flat statistics under them."""

    n: float
    loglik: float
    stats: np.ndarray

    def __post_init__(self) -> None:
        self.n, self.loglik = float(self.n), float(self.loglik)


def choose(family: Family, params: Params) -> str:
    sums = family.k(params) * family.width() + len(family.extra_sql(params))
    return "fused" if sums <= FUSED_SUMS else "arrow"

"""Parameters of all methods, and the constants that follow from a graph's size."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    alpha_n: float = 0.2
    alpha_r: float = 0.15
    phi_o: float = 0.2
    t_s: float = 2.0
    n_w: int = 10_000
    n_s: int = 200
    t_e: float | None = None
    eps: float | None = None
    eps_t: float = 0.01
    c1: float = 200.0
    log_base: float = 2.0
    floor: float = 0.05
    max_hops: int = 50
    truncate: str = "feedback"  # or output
    stop: str = "l1"  # or mass, fixed
    cut_scope: str = "full"  # or subgraph
    select: str = "best"  # or target
    walk_mode: str = "until_restart"  # or fixed_length
    measure: str = "ratio"  # or classic
    rule: str = "deviation"  # or count
    min_hits: int = 1
    salt: int = 42
    engine: str = "auto"  # or local, relational
    weighted: bool = True

    def but(self, **changes) -> "Params":
        return replace(self, **changes)


EFFECTIVENESS = Params(phi_o=0.05)
FORECAST = Params(t_s=5.0, t_e=0.7)
SWEEP = Params()


@dataclass(frozen=True)
class Derived:
    l: int
    t_last: int
    b: float
    eps: float
    steps: int


def derive_params(m: int, p: Params = Params()) -> Derived:
    """Rank iterations and truncation threshold for a graph of m edges, and the iterations that matter in practice.

    The rank with restart contracts by 1 - alpha a step, so beyond ln(eps_t / 2) / ln(1 - alpha) steps nothing moves by
    more than eps_t in total; `steps` is the smaller of that and the bound.
    """
    m = max(m, 1)
    l = max(1, math.ceil(math.log2(m))) if m > 1 else 1
    t_last = (l + 1) * math.ceil(2 / p.phi_o**2 * math.log(p.c1 * (l + 2) * math.sqrt(m)))
    b = (1 + math.log(m, p.log_base)) / 2
    eps = p.eps if p.eps is not None else 1 / (1800 * (l + 2) * t_last * 2**b)
    enough = math.ceil(math.log(p.eps_t / 2) / math.log(1 - p.alpha_n)) if p.alpha_n > 0 else t_last
    return Derived(l, t_last, b, eps, min(t_last, enough))

"""Parameters of the methods: closed forms, as driver numbers and as columns."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Params:
    """alpha: chance to stop at a step; c: relative error; pf: failure probability."""

    alpha: float = 0.2
    c: float = 0.1
    pf: float = 0.1

    def but(self, **changes: float) -> Params:
        return replace(self, **changes)


def hop_cap(n: int, p: Params) -> int:
    """Hops after which at most c * alpha / (2n) of a walk's mass is left."""
    return math.ceil(math.log(p.c * p.alpha / (2 * n)) / math.log(1 - p.alpha))


def theta_degree(deg: Column | float, n: int, p: Params) -> Column | float:
    return p.alpha * p.c**2 * p.pf / (4 * hop_cap(n, p)) / deg


def theta_edges(n: int, m: int, p: Params) -> float:
    return p.alpha * p.c**2 * p.pf / (4 * hop_cap(n, p)) * math.sqrt(2 * (1 - p.alpha) / m)


def theta_for(deg: Column, n: int, m: int, p: Params, mode: str = "auto") -> Column:
    """Share below which neighbours are sampled: by the target's degree, the edges, or the larger of both."""
    by_degree, by_edges = theta_degree(deg, n, p), F.lit(theta_edges(n, m, p))
    return {"degree": by_degree, "edges": by_edges, "auto": F.greatest(by_degree, by_edges)}[mode]


def theta_oracle(deg: Column, pi: Column, n: int, p: Params) -> Column:
    """The share that a known PageRank allows."""
    return p.c**2 * p.pf * n * pi / (4 * hop_cap(n, p) * deg)


def walk_count(p: Params, pi: float) -> int:
    """Walks that find a PageRank of pi within c."""
    return math.ceil((2 * p.c / 3 + 2) / (p.c**2 * pi) * math.log(1 / p.pf))


def push_eps(n: int, p: Params) -> float:
    return p.c * p.alpha / n


def blanket_r_max(deg: Column, n: int, p: Params) -> Column:
    a = p.alpha
    return p.c * F.sqrt(a * deg * math.log(1 / (1 - a)) / (n * math.log(1 / p.pf) * math.log(n / a)))


def blanket_walks(deg: Column, n: int, p: Params) -> Column:
    a = p.alpha
    return F.ceil(45 * hop_cap(n, p) / p.c * F.sqrt(n * deg * math.log(1 / (1 - a)) * math.log(2 / p.pf) / (a * math.log(n / a))))


def residue_r_max(deg: Column, n: int, p: Params) -> Column:
    return p.c * F.sqrt(p.alpha * deg / (n * math.log(1 / p.pf)))


def residue_walks(r_max: Column, n: int, p: Params) -> Column:
    return F.ceil((2 * p.c / 3 + 2) * r_max * n / (p.c**2 * p.alpha) * math.log(2 / p.pf))


def shared_theta(n: int, p: Params, pi: float | None = None) -> float:
    """Increment below which the randomised reverse push samples."""
    hops = hop_cap(n, p)
    return p.c**2 * (p.alpha / n if pi is None else pi) / (12 * hops)


def subgraph_params(n: int, max_deg: int, avg_deg: float, p: Params) -> tuple[int, int, int]:
    """(walks, explorations, hop cap) of the subgraph-sampling method."""
    a, b = math.log(n / p.pf), math.log(1 / p.pf)
    one = n ** (2 / 3) * max_deg ** (1 / 3) * a ** (1 / 3) * b ** (1 / 3) * p.c ** (-4 / 3)
    two = n ** (4 / 5) * avg_deg ** (1 / 5) * a ** (1 / 5) * b ** (2 / 5) * p.c ** (-6 / 5)
    walks = math.ceil(min(one, two))
    cap = math.ceil(math.log(p.c / n) / math.log(1 - p.alpha))
    return walks, max(1, math.ceil(n * b / (p.c**2 * walks))), cap


def amplification(delta: float) -> int:
    """Replicas whose median fails with at most delta if one fails with a third."""
    return math.ceil(18 * math.log(1 / delta))


def cost_bound(deg: Column, n: int, m: int, p: Params) -> Column:
    """Increments that the main method is expected to need at most, at a failure probability of a third."""
    return 12 * hop_cap(n, p) / (p.alpha**2 * p.c**2) * F.least(deg, F.lit(math.sqrt(m / (2 * (1 - p.alpha)))))


def increment_bound(theta: Column | float, p: Params) -> Column | float:
    return (1 - p.alpha) / (p.alpha * theta)

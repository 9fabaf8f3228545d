"""Parameter settings, the bounds of the theory with constant one, and budgets that are checked before a run."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class HopsetParams:
    """Settings of one build. ``None`` takes the theory's value."""

    k: float = 2
    eps: float = 1.0
    beta: int | None = None
    mu: float = 0.5
    seed: int = 42
    reps: int | None = None
    segments: float | None = None
    ell: int | None = None
    eps0: float = 1.0
    rate: float | None = None  # a: radii have rate a / (rounded reach of a segment)
    weights: str = "exact"
    small: str = "hierarchy"
    local_edge_cap: int = 5_000_000
    scope: str = "cluster"
    clique_scope: str = "all"
    in_task: bool = True  # graphs that fit one task are searched there, with the same rows

    def __post_init__(self) -> None:
        if not 0 < self.eps <= 1:
            raise ValueError("eps must lie in (0, 1]")
        if self.k < 2:
            raise ValueError("k must be at least 2")
        if not 0 < self.mu < 1:
            raise ValueError("mu must lie in (0, 1)")
        if self.weights not in ("exact", "approx") or self.small not in ("hierarchy", "clique", "recursive"):
            raise ValueError("weights: exact or approx; small: hierarchy, clique or recursive")

    def but(self, **changes) -> HopsetParams:
        return replace(self, **changes)


def check_gamma(gamma: float) -> float:
    if not 0 < gamma <= 1:
        raise ValueError("gamma must lie in (0, 1]")
    return gamma


def check_rho(rho: float) -> float:
    if not 0 < rho <= 0.5:
        raise ValueError("rho must lie in (0, 1/2]")
    return rho


def inner_eps(eps: float, n: int, c: float = 1.0) -> float:
    """Per-scale error: scales compound, so eps is shared out over log n of them."""
    return eps / (c * max(1.0, math.log2(max(n, 2))))


def cover_width(params: HopsetParams, n: int, big_r: int) -> float:
    """Length of the path segments that clusters must hold: W."""
    if params.segments is not None:
        return max(1.0, 2 * big_r / params.segments)
    return inner_eps(params.eps, n) * big_r / max(1.0, math.log2(max(n, 2)))


def default_reps(n: int, c: float = 3.0) -> int:
    return max(1, math.ceil(c * math.log2(max(n, 2))))


def reps_for_paths(n: int, eps0: float = 1.0, failures: float = 2.0) -> int:
    """Repetitions after which a path is missed with probability at most n^-failures."""
    p = math.exp(-(1 + eps0 / 2))
    return math.ceil(failures * math.log(max(n, 2)) / -math.log1p(-p))


def padding_bound(r: float, alpha: float) -> float:
    """Least probability that a ball of radius r lies in one cluster."""
    return math.exp(-2 * r * alpha)


def levels(k: float) -> int:
    """Sampled levels of the local hierarchy."""
    return max(1, math.ceil(math.log2(k + 1)) - 1)


#: Bound formulas over logs to base two; L = log n. The SQL text is what DuckDB evaluates for the same row.
BOUNDS = {
    "main_size": "pow(n, 1 + 1/(2*k)) * L + n * L * L",
    "main_hopbound": "(L*L/eps) * pow(L * lg(k) / eps, lg(k+1) - 1)",
    "main_rounds": "((L*L/eps) * pow(L * lg(k) / eps, lg(k+1) - 1)) * L * L",
    "restated_size": "pow(n, 1 + 1/k) * L",
    "restated_hopbound": "(L*L/eps) * pow(L * lg(k) / eps, lg(k+1) - 2)",
    "competitor_hopbound": "pow(L * lg(k) / eps, lg(k) + 2)",
    "competitor_rounds": "pow(n, rho)",
    "claimed_gain": "L * L * pow(lg(k) / eps, 4)",
    "dense_size": "pow(n, 1.5)",
    "dense_hopbound": "L*L/eps",
    "superpoly_hopbound": "pow(2, sqrt(L))",
    "hopbound_lower": "pow(lg(k)/eps, lg(k))",
    "structure_size": "m + pow(n, 1 + 1/(2*k))",
    "many_sources_rounds": "(L*L/eps) * pow(L * lg(k) / eps, lg(k+1) - 1) + s",
    "mssp_rounds": "L*L/eps",
    "detection_rounds": "ell",
    "limited_cover_rounds": "ell * L * L",
    "limited_cover_pipelined": "ell * L",
    "limited_cover_all_rounds": "ell * L * L * lg(w)",
    "unlimited_cover_rounds": "w * L * L",
    "unweighted_cover_rounds": "w * L",
    "partition_diameter": "L / alpha",
    "partition_work": "m",
    "padding": "exp(-2 * r * alpha)",
    "local_size": "pow(sz, 1 + 1/k)",
    "local_total": "pow(n, 0.5 + 1/(2*k))",
    "local_hopbound": "pow(lg(k) * L / eps, lg(k+1) - 1)",
    "bucket_sum": "pow(n, 1 + 1/(2*k))",
    "rich_cover_rounds": "(ell/gamma) * L",
    "rich_cover_memory": "m * L * L",
    "rich_size": "pow(n, 1.5) * L",
    "rich_rounds": "L*L*L / (gamma*eps)",
    "rich_hopbound": "L*L / (gamma*eps)",
    "rich_mssp_rounds": "L*L / (gamma*eps)",
    "rich_memory": "m * sqrt(n)",
    "rich_machines": "m * pow(n, 0.5 - gamma)",
    "rho_hopbound": "pow(L/eps, 3)",
    "rho_memory": "m * pow(n, rho)",
    "older_route_rounds": "(L*L/eps) * L * L * L",
}
ARGUMENTS = {"n": 1500.0, "m": 5000.0, "k": 4.0, "eps": 1.0, "rho": 0.5, "gamma": 0.5, "mu": 0.5, "ell": 16.0, "w": 64.0, "alpha": 0.0625, "r": 4.0, "s": 30.0, "sz": 30.0}


def bounds(name: str, **arguments: float) -> float:
    """One bound with constant one."""
    values = ARGUMENTS | arguments
    space = values | {"L": math.log2(max(values["n"], 2)), "lg": math.log2, "pow": math.pow, "sqrt": math.sqrt, "exp": math.exp}
    return float(eval(BOUNDS[name], {"__builtins__": {}}, space))  # noqa: S307 - formulas of this module only


def bound_expression(name: str) -> str:
    """The bound as SQL over columns named like the arguments, for Spark and DuckDB alike."""
    import re

    text = re.sub(r"\blg\(", "log2(", BOUNDS[name])
    text = re.sub(r"\bL\b", "log2(n)", text)
    return re.sub(r"(?<![\w.])(\d+(?:\.\d+)?)(?![\w.])", r"CAST(\1 AS DOUBLE)", text)


@dataclass(frozen=True)
class Budget:
    """Rows that a run would hold at its widest; raises when they exceed ``max_rows``."""

    max_rows: int = 10**13

    def require(self, what: str, rows: float) -> None:
        if rows > self.max_rows:
            raise ValueError(f"{what}: about {rows:.3g} rows, more than the budget of {self.max_rows:.3g}")

    def search(self, sources: int, nodes: int) -> None:
        self.require("distances from the sources", float(sources) * nodes)

    def cover(self, nodes: int, reps: int, scales: int = 1) -> None:
        self.require("cluster memberships", float(nodes) * reps * scales)

"""Collision probabilities, derived parameters and bounds."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass

WIDTHS = {"static": 2.184, "query": 2.7191}


def _phi(x: float) -> float:
    return 0.5 * (1 + math.erf(x / math.sqrt(2)))


def collision_prob(kind: str, s: float, w: float) -> float:
    """Probability that two points at distance s share a bucket of width w on one projection."""
    if kind == "query":
        return 1 - 2 * _phi(-w / (2 * s))
    return 1 - 2 * _phi(-w / s) - 2 * s / (w * math.sqrt(2 * math.pi)) * (1 - math.exp(-w * w / (2 * s * s)))


def check_family(p1: float, p2: float, c: float) -> None:
    if not (c > 1 and p1 > p2):
        raise ValueError(f"no sensitive family: c={c}, p1={p1}, p2={p2}")


@dataclass(frozen=True)
class Params:
    kind: str
    w: float
    c: int | float
    delta: float
    beta: float
    p1: float
    p2: float
    m: int
    l: int  # noqa: E741


def derive_params(kind: str = "static", w: float | None = None, c: float = 2, delta: float = 0.1, beta: float = 0.25) -> Params:
    """Number of projections m and collision threshold l for the wanted error rates."""
    if kind == "static" and (c != int(c) or c < 2):
        raise ValueError("static buckets nest only for an integer c of at least 2")
    if beta >= 1:
        warnings.warn("beta is clamped below 1", stacklevel=2)
        beta = 0.999
    w = WIDTHS[kind] if w is None else w
    p1, p2 = collision_prob(kind, 1, w), collision_prob(kind, c, w)
    check_family(p1, p2, c)
    z = math.sqrt(math.log(2 / beta) / math.log(1 / delta))
    m = math.ceil(math.log(1 / delta) * (1 + z) ** 2 / (2 * (p1 - p2) ** 2))
    return Params(kind, w, c, delta, beta, p1, p2, m, math.ceil((z * p1 + p2) / (1 + z) * m))


def gamma_min(n_query: float, least_object: float, delta: float, eps: float, beta: float) -> float:
    """The least similarity share for which the guarantee is proven; over 1 it says nothing."""
    bound = math.sqrt(max(math.log(1 / delta) / ((eps - delta) ** 2 * n_query * least_object), 2 * math.log(2 / beta) / (beta**2 * n_query * least_object)))
    if bound > 1:
        warnings.warn(f"the guarantee needs a share of {bound:.3g}", stacklevel=2)
    return bound


def fp_bound(n_objects: int, beta: float, gamma: float, n_query: int, n_object: int) -> float:
    """Upper bound of the expected number of false positives."""
    return n_objects * math.exp(-(beta**2) * gamma**2 * n_query * n_object / 2)


def radius_ladder(c: float, widest: float) -> list[float]:
    """1, c, c squared and so on, up to the first radius that is no less than ``widest``."""
    radii = [1.0]
    while radii[-1] < widest:
        radii.append(radii[-1] * c)
    return radii


def point_error_rates(p: Params) -> tuple[float, float]:
    """(a near pair reaches the threshold, a far pair misses it): the least probabilities that m and l are made for."""
    z = math.sqrt(math.log(2 / p.beta) / math.log(1 / p.delta))
    share = (z * p.p1 + p.p2) / (1 + z)
    return 1 - math.exp(-2 * (p.p1 - share) ** 2 * p.m), 1 - math.exp(-2 * (share - p.p2) ** 2 * p.m)

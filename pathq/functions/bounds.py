"""Closed-form costs on measured sizes, and the inequalities behind them."""

from __future__ import annotations

import math
from collections.abc import Iterable

MATRIX_EXPONENT = 2.37  # of fast matrix multiplication, as the literature states it


def bound_search(v: int, e: int) -> float:
    return float(v) * e


def bound_matrix(v: int) -> float:
    return float(v) ** MATRIX_EXPONENT


def bound_split(v: int, e: int, out: int) -> float:
    return e**1.5 + min(out * math.sqrt(e), v * e)


def bound_star_free(e: int, out: int) -> float:
    return e + e * math.sqrt(out)


def bound_closure(v: int, e: int, out: int) -> float:
    return min(out * math.sqrt(e), float(v) * e)


def floor_combinatorial(v: int, e: int, exponent: float = 0.9) -> float:
    """What no combinatorial method can keep to for all graphs, at any exponent below 1, if Boolean matrix products need cubic work."""
    return (float(v) * e) ** exponent


def floor_any(e: int, out: int, exponent: float = 0.9) -> float:
    """What no method can keep to for all graphs, at any exponent below 1, if sparse matrix products need more than linear work."""
    return float(e + out) ** exponent


def most_heavy_sources(v: int, e: int, out: int) -> float:
    return min(out / math.sqrt(e), v) if e else 0.0


def search_range(e: int) -> tuple[float, float]:
    """The search bound from the densest to the sparsest graph with e edges."""
    return e**1.5, float(e) ** 2


def regime(v: int, e: int, out: int) -> tuple[float | None, float | None]:
    """(alpha, beta) with OUT = (V * sqrt(E)) ** (1 - alpha) and E = V ** (2 - beta). OUT = 0 has alpha 1."""
    alpha = 1.0 if out <= 1 else 1 - math.log(out) / math.log(v * math.sqrt(e)) if v * math.sqrt(e) > 1 else None
    beta = 2 - math.log(e) / math.log(v) if v > 1 and e > 0 else None
    return alpha, beta


def wins(v: int, e: int, out: int) -> bool:
    """Whether the sizes lie where the capped split is strictly cheaper."""
    alpha, beta = regime(v, e, out)
    return alpha is not None and beta is not None and 0 < alpha <= 1 and 0 < beta < 2


def cost_bound(cover: Iterable[tuple[int, float]]) -> float:
    """Product of relation sizes to the powers of a fractional edge cover: a bound on the size of their join."""
    return math.prod(n**w for n, w in cover)


def decomposition_holds(relations: list[tuple[tuple[str, ...], set[tuple], float]], fixed: tuple[str, ...]) -> bool:
    """Checks on data that the bounds of a join restricted to each value of ``fixed`` sum to at most the join's own bound.

    Each relation is (variables, tuples, weight); the weights have to cover every variable at least once.
    """
    variables = {v for r in relations for v in r[0]}
    if any(sum(w for vs, _, w in relations if v in vs) < 1 - 1e-9 for v in variables):
        raise ValueError("the weights are no fractional edge cover")
    domain = {v: sorted({t[vs.index(v)] for vs, ts, _ in relations if v in vs for t in ts}) for v in fixed}
    values = [{}]
    for v in fixed:
        values = [x | {v: y} for x in values for y in domain[v]]
    total = 0.0
    for value in values:
        sizes = [(sum(all(v not in value or t[i] == value[v] for i, v in enumerate(vs)) for t in ts), w) for vs, ts, w in relations]
        total += cost_bound(sizes) if all(n for n, _ in sizes) else 0.0
    return total <= cost_bound((len(ts), w) for _, ts, w in relations) * (1 + 1e-9)

"""Exact fractional vertex covers and edge packings."""

from __future__ import annotations

from collections.abc import Mapping
from fractions import Fraction
from functools import lru_cache
from itertools import combinations

from .query import FullCQ


def simplex(rows: list[list[Fraction]], limits: list[Fraction], gains: list[Fraction]) -> tuple[Fraction, list[Fraction], list[Fraction]]:
    """max gains.x with rows.x <= limits, x >= 0, limits >= 0: value, x and the dual prices (smallest-index pivots)."""
    m, n = len(rows), len(gains)
    t = [list(map(Fraction, r)) + [Fraction(int(i == j)) for j in range(m)] + [Fraction(b)] for i, (r, b) in enumerate(zip(rows, limits))]
    z = [-Fraction(g) for g in gains] + [Fraction(0)] * (m + 1)
    basis = list(range(n, n + m))
    while (enter := next((j for j in range(n + m) if z[j] < 0), None)) is not None:
        choices = [(t[i][-1] / t[i][enter], basis[i], i) for i in range(m) if t[i][enter] > 0]
        if not choices:
            raise ValueError("unbounded")
        leave = min(choices)[2]
        pivot = t[leave][enter]
        t[leave] = [x / pivot for x in t[leave]]
        for row in (*t[:leave], *t[leave + 1 :], z):
            if k := row[enter]:
                row[:] = [a - k * b for a, b in zip(row, t[leave])]
        basis[leave] = enter
    x = [Fraction(0)] * (n + m)
    for i, b in enumerate(basis):
        x[b] = t[i][-1]
    return z[-1], x[:n], z[n : n + m]


def _solve(cq: FullCQ, gain: Mapping[str, float] | None):
    gains = [Fraction(gain[a.name]) if gain else Fraction(1) for a in cq.atoms]
    return simplex([[Fraction(int(v in a.vars)) for a in cq.atoms] for v in cq.vars], [Fraction(1)] * len(cq.vars), gains)


def max_edge_packing(cq: FullCQ, gain: Mapping[str, float] | None = None) -> dict[str, Fraction]:
    """Atom weights, at most 1 in total on each variable, of largest (weighted) total."""
    return dict(zip([a.name for a in cq.atoms], _solve(cq, gain)[1]))


def min_vertex_cover(cq: FullCQ) -> dict[str, Fraction]:
    """Variable weights, at least 1 in total on each atom, of least total: the prices of the packing problem."""
    return dict(zip(cq.vars, _solve(cq, None)[2]))


def is_vertex_cover(cq: FullCQ, v: Mapping[str, Fraction]) -> bool:
    return all(v[x] >= 0 for x in cq.vars) and all(sum(v[x] for x in a.vars) >= 1 for a in cq.atoms)


def is_edge_packing(cq: FullCQ, u: Mapping[str, Fraction]) -> bool:
    return all(u[a.name] >= 0 for a in cq.atoms) and all(sum(u[a.name] for a in cq.having(x)) <= 1 for x in cq.vars)


def duality_gap(cq: FullCQ) -> Fraction:
    return sum(min_vertex_cover(cq).values()) - sum(max_edge_packing(cq).values())


@lru_cache(maxsize=64)
def packing_vertices(cq: FullCQ) -> tuple[tuple[Fraction, ...], ...]:
    """All vertices of the packing polytope, each a weight per atom."""
    n = len(cq.atoms)
    rows = [([Fraction(int(v in a.vars)) for a in cq.atoms], Fraction(1)) for v in cq.vars]
    rows += [([Fraction(int(i == j)) for j in range(n)], Fraction(0)) for i in range(n)]
    found = set()
    for chosen in combinations(rows, n):
        x = _linear([r for r, _ in chosen], [b for _, b in chosen])
        if x and is_edge_packing(cq, dict(zip([a.name for a in cq.atoms], x))):
            found.add(tuple(x))
    return tuple(sorted(found))


def _linear(rows: list[list[Fraction]], right: list[Fraction]) -> list[Fraction] | None:
    t = [list(r) + [b] for r, b in zip(rows, right)]
    n = len(t)
    for c in range(n):
        p = next((i for i in range(c, n) if t[i][c]), None)
        if p is None:
            return None
        t[c], t[p] = t[p], t[c]
        t[c] = [x / t[c][c] for x in t[c]]
        for i in range(n):
            if i != c and t[i][c]:
                t[i] = [a - t[i][c] * b for a, b in zip(t[i], t[c])]
    return [r[-1] for r in t]

"""Upper and lower bounds on the load, in tuples unless a factor for bits is given."""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence

from . import lp
from .cost import CostFunction
from .query import FullCQ


def norm(w: Sequence[float], s: float) -> float:
    top = max(w)
    return top * sum((x / top) ** s for x in w) ** (1 / s)


def upper_uniform(m: float, n: float, w: Sequence[float], v: float) -> float:
    """Load reached, up to a constant, with a cover of total v; linear costs, equal sizes; in bits."""
    return m * math.log2(n) / norm(w, v)


def lower_uniform(m: float, w: Sequence[float], u: float) -> float:
    """Load that no one-round algorithm beats, for a packing of total u; linear costs, equal sizes."""
    return m / norm(w, u)


def tightness(cq: FullCQ, m: float, n: float, w: Sequence[float]) -> float:
    """Upper over lower bound for the best cover and packing: exactly log2 n."""
    return upper_uniform(m, n, w, float(sum(lp.min_vertex_cover(cq).values()))) / lower_uniform(m, w, float(sum(lp.max_edge_packing(cq).values())))


def general_cap(m: int, costs: Sequence[CostFunction]) -> float:
    """The load of sending everything to the machine that takes it best."""
    return min(g(m) for g in costs)


def lower_general(m: int, costs: Sequence[CostFunction], u: float, tol: float = 1e-9) -> float:
    """Least load L with sum over machines of (amount affordable at L)^u at least m^u."""
    low, high = 0.0, general_cap(m, costs)
    enough = lambda load: sum((g.inverse(load, m) / m) ** u for g in costs) >= 1 - 1e-12
    while high - low > tol * high:
        mid = (low + high) / 2
        low, high = (low, mid) if enough(mid) else (mid, high)
    return high


def lower_power(m: float, w: Sequence[float], a: float, u: float) -> float:
    """Closed form of the above for costs x^a / w, amounts not rounded."""
    return m**a / sum(x ** (u / a) for x in w) ** (a / u)


def mixed_bracket(m: Mapping[str, int], w: Sequence[float]) -> tuple[float, float]:
    """The bound for unequal sizes lies between these; their ratio is at most the number of machines."""
    return max(m.values()) / sum(w), max(m.values()) / max(w)


def best_term(cq: FullCQ, m: Mapping[str, int], load: float, weight: float) -> tuple[float, tuple[float, ...]]:
    """Least product over packings of (load * weight / size)^share, and the packing."""
    logs = [math.log(m[a.name] / (load * weight)) for a in cq.atoms]
    if len(cq.atoms) <= 5:
        best = max(lp.packing_vertices(cq), key=lambda u: sum(float(x) * b for x, b in zip(u, logs)))
    else:
        best = tuple(lp.max_edge_packing(cq, {a.name: b for a, b in zip(cq.atoms, logs)}).values())
    return math.exp(-sum(float(x) * b for x, b in zip(best, logs))), tuple(map(float, best))


def coverage(cq: FullCQ, m: Mapping[str, int], w: Sequence[float], load: float) -> float:
    """Share of the answers that all machines together can know at this load; one term per distinct weight."""
    return sum(w.count(x) * best_term(cq, m, load, x)[0] for x in set(w))


def lower_mixed(cq: FullCQ, m: Mapping[str, int], w: Sequence[float], method: str = "bisect", tol: float = 1e-10) -> tuple[float, int]:
    """The least load at which coverage reaches 1, and the steps taken.

    ``double`` starts at the bracket's low end and doubles: at most log2 p steps, within a
    factor of two. ``bisect`` goes on to the tolerance.
    """
    w = list(w)
    low, cap = mixed_bracket(m, w)
    steps, load = 0, low
    while coverage(cq, m, w, load) < 1 - 1e-12 and load < cap:
        load, steps = min(load * 2, cap), steps + 1
    if method == "double" or not steps:
        return load, steps
    if method != "bisect":
        raise ValueError(method)
    low, high = load / 2, load
    while high - low > tol * high:
        mid = (low + high) / 2
        low, high = (low, mid) if coverage(cq, m, w, mid) >= 1 else (mid, high)
        steps += 1
    return high, steps


def expected_output(cq: FullCQ, m: Mapping[str, int], n: int, theta: float | None = None) -> float:
    """Expected answers over random matchings, or over random relations of density theta."""
    k = len(cq.vars)
    if theta is not None:
        return theta ** len(cq.atoms) * n**k
    return n**k * math.prod(m[a.name] / n ** len(a.vars) for a in cq.atoms)


def known_fraction(f: Mapping[str, float], u: Mapping[str, float]) -> float:
    """Most of the expected answers that a machine can know from these fractions of the atoms."""
    return math.prod(f[a] ** float(u[a]) for a in f)


def tail(m: float, w: Sequence[float], v: float, delta: float) -> float:
    """Bound on the chance that some machine gets over 1 + delta times its share of one atom (delta up to 1)."""
    return min(1.0, sum(math.exp(-(delta**2) * m * x / (3 * norm(w, v))) for x in w))

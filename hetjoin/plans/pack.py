"""Boxes into one space: sides become powers of two, equal boxes merge into larger ones until one block is left.

The merge history is a binary tree. Laid out from the root, each machine's box is a range of
grid cells on every variable; the boxes are disjoint and together cover the block, which is
stretched where it is short of the space.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field
from itertools import product

import numpy as np

from .query import FullCQ
from .sides import Sides

GRID_BITS = 20
Shape = tuple[int, ...]
Costs = Sequence[float | Callable[[float], float]]


def cost_of(costs: Costs, machine: int, amount: float) -> float:
    """What ``amount`` costs a machine; a number stands for the weight of a linear cost."""
    c = costs[machine]
    return c(amount) if callable(c) else amount / c


@dataclass
class Node:
    machine: int = -1
    dim: int = -1
    left: Node | None = None
    right: Node | None = None


@dataclass
class Packing:
    vars: tuple[str, ...]
    domain: dict[str, int]
    boxes: dict[int, dict[str, tuple[int, int]]]
    machines: int
    planned: Sides
    root: Node | None = None
    stretch: dict[str, float] = field(default_factory=dict)
    block: dict[str, int] = field(default_factory=dict)
    # Boxes of the last shape before doubling, the volume of one, and of the final block, in parts of the space.
    last: tuple[int, float, float] | None = None

    def used(self) -> list[int]:
        return sorted(c for c, b in self.boxes.items() if all(hi > lo for lo, hi in b.values()))

    def share(self, machine: int, vars: Sequence[str]) -> float:
        """The part of a product of ranges that the machine's box has."""
        if machine not in self.boxes:
            return 0.0
        return math.prod((self.boxes[machine][x][1] - self.boxes[machine][x][0]) / self.domain[x] for x in vars)

    def inflation(self, cq: FullCQ) -> dict[tuple[int, str], float]:
        """Final over planned share, by machine and atom."""
        return {(c, a.name): self.share(c, a.vars) / math.prod(self.planned[c][x] for x in a.vars) for c in self.used() for a in cq.atoms if all(self.planned[c][x] for x in a.vars)}

    def planned_load(self, cq: FullCQ, m: Mapping[str, int], w: Costs) -> float:
        """The worst machine's cost of all that it is to receive."""
        return max(cost_of(w, c, sum(m[a.name] * self.share(c, a.vars) for a in cq.atoms)) for c in self.used())

    def replication(self, cq: FullCQ, m: Mapping[str, int]) -> float:
        return sum(m[a.name] * self.share(c, a.vars) for c in self.used() for a in cq.atoms) / sum(m.values())

    def stats(self) -> dict[str, float]:
        """Figures of the packing. Where boxes were merged, ``block_share`` is over 1/2 and ``last_shapes_share``,
        of the boxes of the last shape and one more of them, over 1; ``stretch`` is at most 2 to the number of variables and one."""
        used = self.used()
        out = {"machines": self.machines, "used": len(used), "volume": sum(self.share(c, self.vars) for c in used), "stretch": math.prod(self.stretch.values()) if self.stretch else 1.0}
        if self.last:
            count, one, block = self.last
            out |= {"block_share": block, "last_shapes_share": (1 + count) * one}
        return out


def round_up(sides: Sides, vars: Sequence[str], bits: int) -> dict[int, Shape]:
    """Exponents on a grid of 2^bits; machines without extent are left out."""
    out = {}
    for c, s in enumerate(sides):
        if all(s[x] > 0 for x in vars):
            out[c] = tuple(min(bits, max(0, math.ceil(math.log2(s[x]) + bits - 1e-9))) for x in vars)
    return out


def buckets(shapes: Mapping[int, Shape]) -> list[tuple[Shape, list[Node]]]:
    """Machines of equal shape together, smaller shapes first; each shape fits into the next."""
    found: dict[Shape, list[Node]] = {}
    for c in sorted(shapes):
        found.setdefault(shapes[c], []).append(Node(machine=c))
    order = sorted(found.items(), key=lambda kv: (sum(kv[0]), kv[0]))
    for (a, _), (b, _) in zip(order, order[1:]):
        if any(x > y for x, y in zip(a, b)):
            raise ValueError("shapes are no chain")
    return order


def _pairs(nodes: list[Node], dim: int) -> list[Node]:
    return [Node(dim=dim, left=a, right=b) for a, b in zip(nodes[::2], nodes[1::2])]


def promote(order: list[tuple[Shape, list[Node]]]) -> tuple[Shape, list[Node]]:
    """Merges boxes of each shape into boxes of the next, small to large; what does not fill one is left over."""
    shape, nodes = order[0][0], list(order[0][1])
    for after, own in order[1:]:
        for dim, (a, b) in enumerate(zip(shape, after)):
            for _ in range(b - a):
                nodes = _pairs(nodes, dim)
        shape, nodes = after, own + nodes
    return shape, nodes


def double(shape: Shape, nodes: list[Node], bits: int, stop_when_covered: bool = True) -> tuple[Shape, Node]:
    """Doubles the block along its shortest side until one is left, or it covers the space."""
    while len(nodes) > 1 and not (stop_when_covered and all(e >= bits for e in shape)):
        dim = min(range(len(shape)), key=lambda i: (shape[i], i))
        nodes = _pairs(nodes, dim)
        shape = tuple(e + (i == dim) for i, e in enumerate(shape))
    return shape, nodes[0]


def stretch(root: Node, shape: Shape, vars: Sequence[str], domain: Mapping[str, int], bits: int, shrink: bool = False) -> tuple[dict[int, dict[str, tuple[int, int]]], dict[str, float]]:
    """Lays the tree out; ranges in which the block is shorter than the space grow in proportion (and shrink, if asked)."""
    boxes: dict[int, dict[str, tuple[int, int]]] = {}
    factor = {x: 2.0**bits / 2.0 ** shape[i] for i, x in enumerate(vars)}
    scaled = [shape[i] <= bits or shrink for i in range(len(vars))]

    def place(node: Node, low: tuple[int, ...], size: Shape) -> None:
        if node.machine >= 0:
            b = {}
            for i, x in enumerate(vars):
                unit = shape[i] if scaled[i] else bits
                lo, hi = (min(domain[x], (p * domain[x]) >> unit) for p in (low[i], low[i] + (1 << size[i])))
                b[x] = (lo, hi)
            boxes[node.machine] = b
            return
        half = tuple(e - (i == node.dim) for i, e in enumerate(size))
        place(node.left, low, half)
        place(node.right, tuple(p + ((1 << half[i]) if i == node.dim else 0) for i, p in enumerate(low)), half)

    place(root, (0,) * len(vars), shape)
    return boxes, {x: max(f, 1.0) if not shrink else f for x, f in factor.items()}


def pack(cq: FullCQ, sides: Sides, domain: Mapping[str, int] | None = None, rounding: str = "up", grid_bits: int = GRID_BITS, stop_when_covered: bool = True, shrink: bool = False, m: Mapping[str, int] | None = None, w: Costs | None = None) -> Packing:
    """``up`` rounds every side up. ``search`` also tries common offsets of each variable with rounding
    down and keeps the packing of least planned load; it is never worse than ``up``."""
    domain = dict(domain or {x: 1 << grid_bits for x in cq.vars})
    base = _packed(cq.vars, sides, round_up(sides, cq.vars, grid_bits), domain, grid_bits, stop_when_covered, shrink)
    if rounding == "up":
        return base
    m, w = m or {a.name: 1 for a in cq.atoms}, w or [1.0] * len(sides)
    best, least = base, base.planned_load(cq, m, w)
    live = {c: s for c, s in enumerate(sides) if all(s[x] > 0 for x in cq.vars)}
    logs = {c: [math.log2(s[x]) + grid_bits for x in cq.vars] for c, s in live.items()}
    groups: dict[tuple, list[int]] = {}
    for c, e in logs.items():
        groups.setdefault(tuple(round(x, 9) for x in e), []).append(c)
    steps = (0, 0.25, 0.5, 0.75) if len(cq.vars) <= 3 else (0, 0.5)
    seen = set()
    for offsets in product(steps, repeat=len(cq.vars)):
        for t in range(20 if len(sides) <= 256 else 6):
            by_group = {g: tuple(min(grid_bits, max(0, math.floor(x + o + t / 10 + 1e-9))) for x, o in zip(g, offsets)) for g in groups}
            key = tuple(by_group.values())
            if key in seen:
                continue
            seen.add(key)
            if sum(len(groups[g]) * 2.0 ** (sum(e) - grid_bits * len(e)) for g, e in by_group.items()) < 1:
                continue
            try:
                tried = _packed(cq.vars, sides, {c: e for g, e in by_group.items() for c in groups[g]}, domain, grid_bits, stop_when_covered, shrink)
            except ValueError:
                continue
            if (load := tried.planned_load(cq, m, w)) < least - 1e-9:
                best, least = tried, load
    return best


def _packed(vars, sides, shapes, domain, bits, stop, shrink) -> Packing:
    last, nodes = promote(buckets(shapes))
    shape, root = double(last, nodes, bits, stop)
    boxes, factors = stretch(root, shape, vars, domain, bits, shrink)
    part = lambda exponents: 2.0 ** (sum(exponents) - bits * len(exponents))
    return Packing(tuple(vars), dict(domain), boxes, len(sides), sides, root, factors, {x: 1 << shape[i] for i, x in enumerate(vars)}, (len(nodes), part(last), part(shape)))


def intervals(cq: FullCQ, sides: Sides, domain: Mapping[str, int] | None = None, grid_bits: int = GRID_BITS) -> Packing:
    """Where only one variable is split: its ranges end to end, without rounding to powers of two."""
    domain = dict(domain or {x: 1 << grid_bits for x in cq.vars})
    split = [x for x in cq.vars if any(s[x] < 1 for s in sides)]
    if len(split) > 1:
        raise ValueError("more than one variable is split")
    if not split:
        return Packing(cq.vars, domain, {0: {x: (0, n) for x, n in domain.items()}}, len(sides), sides, Node(machine=0))
    z = split[0]
    total, at, boxes = sum(s[z] for s in sides), 0.0, {}
    for c, s in enumerate(sides):
        lo, hi = round(at / total * domain[z]), round((at + s[z]) / total * domain[z])
        at += s[z]
        if hi > lo:
            boxes[c] = {x: (lo, hi) if x == z else (0, domain[x]) for x in cq.vars}
    return Packing(cq.vars, domain, boxes, len(sides), sides)


def refine(packing: Packing, cq: FullCQ, m: Mapping[str, int], w: Costs) -> Packing:
    """Gives unused machines a part of the box of the machine with most cost, while that lowers the cost."""
    boxes = {c: dict(b) for c, b in packing.boxes.items()}
    out = Packing(packing.vars, packing.domain, boxes, packing.machines, packing.planned, None, packing.stretch, packing.block, packing.last)
    total = sum(m.values())
    cost = lambda c: cost_of(w, c, sum(m[a.name] * out.share(c, a.vars) for a in cq.atoms))
    for free in sorted(set(range(packing.machines)) - set(packing.used()), key=lambda c: cost_of(w, c, total)):
        worst = max(out.used(), key=cost)
        before, whole, tries = cost(worst), dict(boxes[worst]), []
        for x, (lo, hi) in whole.items():
            low, high = lo, hi
            # The place at which both parts cost the same.
            while high - low > 1:
                cut = (low + high) // 2
                boxes[worst], boxes[free] = whole | {x: (lo, cut)}, whole | {x: (cut, hi)}
                low, high = (cut, high) if cost(worst) <= cost(free) else (low, cut)
            for cut in (low, high):
                if lo < cut < hi:
                    boxes[worst], boxes[free] = whole | {x: (lo, cut)}, whole | {x: (cut, hi)}
                    tries.append((max(cost(worst), cost(free)), boxes[worst], boxes[free]))
        boxes[worst] = whole
        boxes.pop(free, None)
        if tries and (best := min(tries, key=lambda t: t[0]))[0] < before:
            boxes[worst], boxes[free] = best[1], best[2]
    return out


def _primes(n: int) -> list[int]:
    out, k = [], 2
    while n > 1:
        while n % k == 0:
            out.append(k)
            n //= k
        k += 1
    return out[::-1]


def subdivide(packing: Packing, cq: FullCQ, m: Mapping[str, int], parts: int, by: Sequence[str] | None = None) -> Packing:
    """Every box cut into ``parts`` inner boxes, those of machine c numbered from c * parts on.

    Each prime factor of ``parts`` goes to the variable that leaves least in an inner box, or
    only to those in ``by``: variables that few tuples share split heavy values of the others.
    """
    boxes = {}
    for c in packing.used():
        box = packing.boxes[c]
        grid = dict.fromkeys(packing.vars, 1)
        inner = lambda g: sum(m[a.name] * math.prod((box[x][1] - box[x][0]) / packing.domain[x] / g[x] for x in a.vars) for a in cq.atoms)  # noqa: E731, B023
        for prime in _primes(parts):
            room = [x for x in by or packing.vars if (box[x][1] - box[x][0]) // (grid[x] * prime) >= 1]
            if room:
                best = min(room, key=lambda x: (inner(grid | {x: grid[x] * prime}), packing.vars.index(x)))
                grid[best] *= prime
        for number, at in enumerate(product(*[range(grid[x]) for x in packing.vars])):
            boxes[c * parts + number] = {x: tuple(box[x][0] + (box[x][1] - box[x][0]) * (i + k) // grid[x] for k in (0, 1)) for x, i in zip(packing.vars, at)}
    return Packing(packing.vars, packing.domain, boxes, packing.machines * parts, [s for s in packing.planned for _ in range(parts)])


def covers(packing: Packing) -> bool:
    """Every point lies in exactly one box: volumes add up and no two boxes overlap."""
    used = packing.used()
    lo = np.array([[packing.boxes[c][x][0] for x in packing.vars] for c in used])
    hi = np.array([[packing.boxes[c][x][1] for x in packing.vars] for c in used])
    if sum(math.prod(int(h - b) for h, b in zip(hi[i], lo[i])) for i in range(len(used))) != math.prod(packing.domain[x] for x in packing.vars):
        return False
    for i in range(len(used)):
        if ((lo[i] < hi[i + 1 :]) & (lo[i + 1 :] < hi[i])).all(1).any():
            return False
    return True

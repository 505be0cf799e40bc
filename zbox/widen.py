"""Widening a box to cheaper alignment before it is refined."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from math import prod

from .box import Box
from .spec import ZSpec


@dataclass(frozen=True)
class FaceCost:
    """Estimated leaps over one face: num / 2**shift. ``dim`` from 0; ``edge``: it lies on the border of
    the domain and cannot be moved."""

    dim: int
    side: str
    num: int
    shift: int
    edge: bool

    @property
    def value(self) -> Fraction:
        return Fraction(self.num, 1 << self.shift)


def _zeros(v: int, bits: int) -> int:
    """Zero bits that v ends with; all of them for 0."""
    return bits if v == 0 else (v & -v).bit_length() - 1


def face_costs(box: Box, spec: ZSpec) -> list[FaceCost]:
    """Of the 2m faces, dimension by dimension, low side first: the face's cells over the cells that the
    layer it is aligned to takes in one leap."""
    sides = [b - a + 1 for a, b in zip(box.lo, box.hi, strict=True)]
    top, out = (1 << spec.bits) - 1, []
    for d in range(spec.m):
        face = prod(sides[:d] + sides[d + 1 :])
        for side, run, edge in (("lo", _zeros(box.lo[d], spec.bits), box.lo[d] == 0), ("hi", _zeros(~box.hi[d] & top, spec.bits), box.hi[d] == top)):
            out.append(FaceCost(d, side, face, (spec.m - 1) * run + d, edge))
    return out


def total_face_cost(box: Box, spec: ZSpec) -> Fraction:
    return sum((c.value for c in face_costs(box, spec)), Fraction(0))


def widen_face(box: Box, d: int, side: str) -> Box:
    """One bit less precise: the low end loses its lowest one, the high end its lowest zero."""
    lo, hi = list(box.lo), list(box.hi)
    if side == "lo":
        lo[d] &= lo[d] - 1
    else:
        hi[d] |= hi[d] + 1
    return Box(tuple(lo), tuple(hi))


@dataclass(frozen=True)
class Widened:
    box: Box
    steps: int
    total: Fraction


def widen(box: Box, spec: ZSpec, threshold: float = 500) -> Widened:
    """Moves the costliest face, again and again, until the estimates sum to ``threshold`` at most or no
    face can move. All estimates are anew after each step; ties go to the lower dimension, low side
    first. Costs are compared as integers."""
    steps, most = 0, spec.m * (spec.bits + 1)
    limit = None if threshold == float("inf") else Fraction(threshold)
    while True:
        costs = face_costs(box, spec)
        scaled = [c.num << (most - c.shift) for c in costs]
        free = [i for i, c in enumerate(costs) if not c.edge]
        if limit is None or sum(scaled) * limit.denominator <= limit.numerator << most or not free:
            return Widened(box, steps, Fraction(sum(scaled), 1 << most))
        worst = max(free, key=lambda i: (scaled[i], -i))
        box = widen_face(box, costs[worst].dim, costs[worst].side)
        steps += 1

"""Measures of cost and waste of a box of cells."""

from __future__ import annotations

from math import prod
from time import perf_counter

from .box import Box
from .refine import refine
from .spec import ZSpec


def volume(box: Box) -> int:
    """Cells of the box: what leaping in alone has to visit."""
    return prod(b - a + 1 for a, b in zip(box.lo, box.hi, strict=True))


def surface(box: Box) -> int:
    """Cells of the 2m faces: an estimate of the leaps in and out, not a bound."""
    sides = [b - a + 1 for a, b in zip(box.lo, box.hi, strict=True)]
    return 2 * sum(prod(sides[:i] + sides[i + 1 :]) for i in range(len(sides)))


def costs(box: Box, spec: ZSpec, method: str, **options) -> dict:
    """Volume, surface, counters, covered cells and milliseconds of one refinement."""
    began = perf_counter()
    r = refine(box, spec, method, **options)
    ms = (perf_counter() - began) * 1000
    return {"method": method, "volume": volume(box), "surface": surface(box), "visits": r.visits, "leaps": r.leaps, "pieces": len(r.pieces), "covered": r.covered, "ms": ms}

"""Boxes: a closed interval per dimension."""

from __future__ import annotations

from dataclasses import dataclass

from .spec import ZSpec


@dataclass(frozen=True)
class Box:
    """``lo`` and ``hi`` per dimension, both ends in; None leaves an end open (a partial box)."""

    lo: tuple
    hi: tuple

    def __post_init__(self):
        if len(self.lo) != len(self.hi):
            raise ValueError("lo and hi have different numbers of dimensions")

    @classmethod
    def from_conditions(cls, spec: ZSpec, **between) -> Box:
        """``column=(lo, hi)`` for the columns with a condition, None for an open end; the others are
        unconstrained. A column that the key does not hold is an error: it belongs in a filter."""
        names = [d.column for d in spec.dims]
        if unknown := set(between) - set(names):
            raise ValueError(f"not selection columns: {sorted(unknown)}")
        ends = [between.get(n, (None, None)) for n in names]
        return cls(tuple(a for a, _ in ends), tuple(b for _, b in ends))

    def drop(self, d: int) -> Box:
        """The same box without a condition on dimension d (from 0)."""
        put = lambda t: tuple(None if i == d else x for i, x in enumerate(t))
        return Box(put(self.lo), put(self.hi))

    def beyond(self, spec: ZSpec) -> bool:
        """Whether rows without a key may be in the box: where values outside a dimension's range have none
        and the box reaches outside it."""
        ends = zip(self.lo, self.hi, spec.dims, strict=True)
        return not self.empty and any(d.overflow == "null" and (a is None or a < d.lo or b is None or b > d.hi) for a, b, d in ends)

    @property
    def empty(self) -> bool:
        return any(a is not None and b is not None and a > b for a, b in zip(self.lo, self.hi, strict=True))

    def cells(self, spec: ZSpec) -> Box | None:
        """The box in cell coordinates; None if it is empty or lies wholly outside the domain."""
        if len(self.lo) != spec.m:
            raise ValueError(f"a box of {len(self.lo)} dimensions for a key of {spec.m}")
        if self.empty:
            return None
        lo, hi = [], []
        for a, b, d in zip(self.lo, self.hi, spec.dims, strict=True):
            if d.overflow == "wrap" and (a is None or a < d.lo or b is None or b > d.hi):
                lo.append(0)  # values out there may be in any cell
                hi.append((1 << d.bits) - 1)
                continue
            if (a is not None and a > d.hi or b is not None and b < d.lo) and d.overflow != "clamp":
                return None
            clip = lambda v, d=d: min(d.hi, max(d.lo, v))
            lo.append(0 if a is None else d.quantize_value(clip(a)))
            hi.append((1 << d.bits) - 1 if b is None else d.quantize_value(clip(b)))
        return Box(tuple(lo), tuple(hi))

    def envelope(self, spec: ZSpec) -> tuple[int, int]:
        """Least and largest key of a box of cells."""
        return spec.interleave(self.lo), spec.interleave(self.hi)

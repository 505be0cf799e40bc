"""How columns become cells and cells become keys."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field
from functools import cached_property
from math import floor

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class DimSpec:
    """One selection column. Values from ``lo`` to ``hi`` are dealt evenly over 2**bits cells, the
    same monotone way for rows and for box ends, so that a row in a box is in the box's cells.

    ``integer``: exact integer arithmetic (give units as integers: cents, days, ...); else floor on
    doubles. ``overflow``: what becomes of values outside lo..hi: 'clamp' to the end cells, 'null', 'error', or
    'wrap' (whole numbers only): the domain repeats, and a value has the cell of its remainder. A null value has
    no cell."""

    column: str
    lo: float
    hi: float
    bits: int = 10
    integer: bool = True
    overflow: str = "clamp"

    def __post_init__(self):
        if self.hi < self.lo or not 1 <= self.bits <= 62 or self.overflow not in ("clamp", "null", "error", "wrap") or self.overflow == "wrap" and not self.integer:
            raise ValueError(f"bad dimension: {self}")
        if self.integer and not -(1 << 62) <= int(self.lo) <= int(self.hi) <= 1 << 62:
            raise ValueError(f"whole values from -2**62 to 2**62 only: {self}")

    @property
    def wide(self) -> bool:
        """Whether cells of whole numbers need more than long arithmetic."""
        return self.integer and (int(self.hi) - int(self.lo) + 1) << self.bits > (1 << 63) - 1

    def quantize_value(self, v) -> int | None:
        if v is None:
            return None
        if not self.lo <= v <= self.hi:
            if self.overflow == "null":
                return None
            if self.overflow == "error":
                raise ValueError(f"{self.column} = {v} is outside {self.lo}..{self.hi}")
        if self.integer:
            lo, hi = int(self.lo), int(self.hi)
            within = (int(v) - lo) % (hi - lo + 1) if self.overflow == "wrap" else min(hi, max(lo, int(v))) - lo
            cell = within * (1 << self.bits) // (hi - lo + 1)
        else:
            cell = floor((v - self.lo) * (1 << self.bits) / ((self.hi - self.lo) or 1.0))
        return min((1 << self.bits) - 1, max(0, cell))


def quantize(col: Column, d: DimSpec) -> Column:
    """Cell coordinate of a column: built-in functions only. Whole numbers are dealt by whole arithmetic at
    any width, so a row's cell and a box end's cell never differ: in longs where the product fits, else in
    38-digit decimals."""
    top = F.lit((1 << d.bits) - 1).cast("bigint")
    if d.integer:
        lo, hi = int(d.lo), int(d.hi)
        width = hi - lo + 1
        wide = lambda x: x.cast("decimal(38,0)")
        whole = lambda n: F.lit(str(n)).cast("decimal(20,0)")
        narrow = not d.wide
        if d.overflow == "wrap":
            if narrow:
                size = F.lit(width).cast("bigint")
                within = F.pmod(F.pmod(col, size).cast("bigint") - lo % width, size)
            else:
                within = F.pmod(wide(col) - whole(lo), whole(width))
        else:
            clip = lambda x: F.greatest(F.lit(lo).cast("bigint"), F.least(F.lit(hi).cast("bigint"), x))
            # clipped before the cast, which fails on values beyond a long, and after it, as doubles round the ends
            v = clip(clip(col).cast("bigint"))
            within = v - F.lit(lo).cast("bigint") if narrow else wide(v) - whole(lo)
        if narrow:
            cell = _div(within * F.lit(1 << d.bits).cast("bigint"), F.lit(width).cast("bigint"))
        else:
            # up to 2**63 * 2**62 < 10**38
            cell = _div((within.cast("decimal(20,0)") * whole(1 << d.bits)).cast("decimal(38,0)"), whole(width))
    else:
        cell = F.floor((col.cast("double") - d.lo) * float(1 << d.bits) / ((d.hi - d.lo) or 1.0))
    cell = F.when(col.isNull(), F.lit(None).cast("bigint")).otherwise(F.greatest(F.lit(0).cast("bigint"), F.least(top, cell.cast("bigint"))))
    outside = (col < d.lo) | (col > d.hi)
    if d.overflow == "null":
        return F.when(~outside, cell)
    if d.overflow == "error":
        return F.when(outside, F.raise_error(F.lit(f"{d.column} is outside {d.lo}..{d.hi}")).cast("bigint")).otherwise(cell)
    return cell


def _div(a: Column, b: Column) -> Column:
    """Whole quotient."""
    return F.call_function("div", a, b)


@dataclass(frozen=True)
class ZSpec:
    """The selection columns in order; dimension 1 owns the lowest bit of the key."""

    dims: tuple[DimSpec, ...]
    bits: int = field(default=0)

    def __post_init__(self):
        if not self.dims:
            raise ValueError("a key needs a dimension")
        object.__setattr__(self, "bits", self.bits or max(d.bits for d in self.dims))
        if any(d.bits > self.bits for d in self.dims):
            raise ValueError("a dimension has more bits than the key gives it")

    @classmethod
    def grid(cls, m: int, bits: int) -> ZSpec:
        """m dimensions that are cells already, c1 to cm."""
        return cls(tuple(DimSpec(f"c{i + 1}", 0, (1 << bits) - 1, bits) for i in range(m)), bits)

    @property
    def m(self) -> int:
        return len(self.dims)

    @property
    def key_bits(self) -> int:
        return self.m * self.bits

    @property
    def layers(self) -> int:
        """One layer per bit of the key."""
        return self.key_bits

    @cached_property
    def masks(self) -> tuple[int, ...]:
        """Per dimension, its bits within the key."""
        one = sum(1 << (b * self.m) for b in range(self.bits))
        return tuple(one << d for d in range(self.m))

    @property
    def full(self) -> int:
        return (1 << self.key_bits) - 1

    def interleave(self, coords) -> int:
        z = 0
        for d, c in enumerate(coords):
            b = d
            while c:
                z |= (c & 1) << b
                c >>= 1
                b += self.m
        return z

    def deinterleave(self, z: int) -> tuple[int, ...]:
        out = [0] * self.m
        b = 0
        while z:
            out[b % self.m] |= (z & 1) << (b // self.m)
            z >>= 1
            b += 1
        return tuple(out)

    def to_json(self) -> str:
        return json.dumps({"bits": self.bits, "dims": [asdict(d) for d in self.dims]})

    @classmethod
    def from_json(cls, text: str) -> ZSpec:
        x = json.loads(text)
        return cls(tuple(DimSpec(**d) for d in x["dims"]), x["bits"])

"""Keys as column expressions: built-in functions only, so they stay in generated code."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from zbox.box import Box
from zbox.spec import ZSpec, quantize


def _long(v: int) -> Column:
    return F.lit(v).cast("bigint")


def _spread(c: Column, m: int, bits: int) -> Column:
    """Bits of c moved m places apart, by halving blocks: about log2(bits) steps of shift and mask."""
    if m == 1:
        return c
    block = 1
    while block < bits:
        block *= 2
    while block > 1:
        block //= 2
        # blocks of `block` bits end up `block * m` apart
        mask = sum(((1 << block) - 1) << (i * block * m) for i in range((bits + block - 1) // block))
        mask &= (1 << 63) - 1
        c = c.bitwiseOR(F.shiftleft(c, block * (m - 1))).bitwiseAND(_long(mask))
    return c


def _gather(z: Column, m: int, bits: int) -> Column:
    """The inverse of :func:`_spread`."""
    if m == 1:
        return z.bitwiseAND(_long((1 << bits) - 1))
    z = z.bitwiseAND(_long(sum(1 << (b * m) for b in range(bits))))
    block = 1
    while block < bits:
        wide = block * 2
        mask = sum(((1 << wide) - 1) << (i * wide * m) for i in range((bits + wide - 1) // wide)) & ((1 << 63) - 1)
        z = z.bitwiseOR(F.shiftrightunsigned(z, block * (m - 1))).bitwiseAND(_long(mask))
        block = wide
    return z


def z_encode(cols: list[Column], bits: int) -> Column:
    """Key of cell coordinates, as a long: at most 63 bits. Null if any is null."""
    m = len(cols)
    if m * bits > 63:
        raise ValueError(f"{m} dimensions of {bits} bits do not fit a long; use z_encode_wide")
    return reduce(lambda a, b: a.bitwiseOR(b), (F.shiftleft(_spread(c.cast("bigint"), m, bits), d) if d else _spread(c.cast("bigint"), m, bits) for d, c in enumerate(cols)))


def z_decode(z: Column, m: int, bits: int) -> list[Column]:
    """Cell coordinates of a long key."""
    return [_gather(F.shiftrightunsigned(z, d) if d else z, m, bits) for d in range(m)]


def z_encode_wide(cols: list[Column], bits: int) -> Column:
    """Key of any length as big-endian binary, which sorts by bytes as the key does by value."""
    m = len(cols)
    digits = [F.lpad(F.bin(c.cast("bigint")), bits, "0") for c in cols]
    # highest layer first; within a layer the last dimension is the highest bit
    text = F.concat(*(F.substring(digits[d], b + 1, 1) for b in range(bits) for d in reversed(range(m))))
    size = -(-m * bits // 8)
    padded = F.lpad(text, size * 8, "0")
    hexed = F.concat(*(F.lpad(F.conv(F.substring(padded, 8 * i + 1, 8), 2, 16), 2, "0") for i in range(size)))
    null = reduce(lambda a, b: a | b, (c.isNull() for c in cols))
    return F.when(~null, F.unhex(hexed))


def z_of(spec: ZSpec, cols: dict[str, Column] | None = None) -> Column:
    """Key of a row's selection columns."""
    get = lambda d: (cols or {}).get(d.column, F.col(d.column))
    coords = [quantize(get(d), d) for d in spec.dims]
    encode = z_encode if spec.key_bits <= 63 else z_encode_wide
    if not any(d.wide for d in spec.dims):
        return encode(coords, spec.bits)
    # cells in decimals are dear, and spreading names a cell many times: bound, they are worked out once a row
    cells = F.array(F.array(*coords))
    return F.get(F.transform(cells, lambda c: encode([F.get(c, F.lit(d)) for d in range(spec.m)], spec.bits)), F.lit(0))


def cell_start(z: Column, k: int) -> Column:
    """Start of the layer-k cell (k from 1) that holds z."""
    return F.shiftleft(F.shiftrightunsigned(z, k - 1), k - 1)


def next_cell(z: Column, k: int) -> Column:
    return F.shiftleft(F.shiftrightunsigned(z, k - 1) + 1, k - 1)


def z_in_box(z: Column, zs, ze, spec: ZSpec) -> Column:
    """Whether a key lies in the box with corner keys zs and ze, by masked comparison."""
    lit = lambda v: v if isinstance(v, Column) else _long(v)
    zs, ze = lit(zs), lit(ze)
    parts = ((z.bitwiseAND(_long(k)) >= zs.bitwiseAND(_long(k))) & (z.bitwiseAND(_long(k)) <= ze.bitwiseAND(_long(k))) for k in spec.masks)
    return reduce(lambda a, b: a & b, parts)


def in_box(box: Box, cols: list[Column]) -> Column:
    """Membership by the original columns: comparisons that scans can take. Open ends ask nothing but
    that the column is not null."""
    tests = []
    for c, a, b in zip(cols, box.lo, box.hi, strict=True):
        if a is not None:
            tests.append(c >= F.lit(a))
        if b is not None:
            tests.append(c <= F.lit(b))
        if a is None and b is None:
            tests.append(c.isNotNull())
    return reduce(lambda a, b: a & b, tests)


def in_ranges(z: Column, pieces: list[tuple[int, int]]) -> Column:
    """z in any of the intervals, as a balanced tree: a long chain would overflow the planner's stack."""
    if not pieces:
        return F.lit(False)
    if len(pieces) == 1:
        a, b = pieces[0]
        return (z == _long(a)) if a == b else z.between(_long(a), _long(b))
    mid = len(pieces) // 2
    return in_ranges(z, pieces[:mid]) | in_ranges(z, pieces[mid:])


def z_bits(z: Column, width: int) -> Column:
    """The key as text of zeros and ones."""
    return F.lpad(F.bin(z), width, "0")

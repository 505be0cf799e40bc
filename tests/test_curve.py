"""Keys, leaps, refiners and widening against enumeration and worked values."""

import itertools
import random
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from zbox.box import Box
from zbox.leaps import LEAPS_IN, cell_start, inside, leap_in_bits, leap_in_cells, leap_out_exact, leap_out_published, next_cell, slide_candidates
from zbox.measures import costs, surface, volume
from zbox.refine import coalesce_pieces, refine, refine_leaps, refine_none, refine_scan, refine_widened
from zbox.spec import DimSpec, ZSpec
from zbox.widen import face_costs, total_face_cost, widen, widen_face

G = ZSpec.grid(2, 3)


def all_boxes(m, bits):
    ends = [(a, b) for a in range(1 << bits) for b in range(a, 1 << bits)]
    for e in itertools.product(ends, repeat=m):
        yield Box(tuple(a for a, _ in e), tuple(b for _, b in e))


def random_boxes(m, bits, n, seed=3):
    r = random.Random(seed)
    for _ in range(n):
        e = [sorted((r.randrange(1 << bits), r.randrange(1 << bits))) for _ in range(m)]
        yield Box(tuple(a for a, _ in e), tuple(b for _, b in e))


def test_worked_values():
    assert (G.interleave((2, 2)), G.interleave((5, 5))) == (12, 51)
    assert leap_in_bits(28, 12, 51, G) == leap_in_cells(28, 12, 51, G) == 36
    assert slide_candidates(12, 51, G) == [28, 44]
    assert leap_out_exact(12, 12, 51, G) == leap_out_published(12, 12, 51, G) == 16
    assert next_cell(36, 2) == 38 and inside(38, 12, 51, G) and next_cell(36, 4) == 40 and not inside(40, 12, 51, G)
    assert leap_out_exact(36, 12, 51, G) == 40 and cell_start(39, 3) == 36
    assert refine_leaps(Box((2, 2), (5, 5)), G).pieces == [(12, 15), (24, 27), (36, 39), (48, 51)]
    assert refine_none(Box((2, 2), (5, 5)), G).pieces == [(12, 51)]


def test_skipped_bit_rules_differ():
    zs, ze = Box((3, 1), (7, 6)).envelope(G)
    assert leap_out_published(13, zs, ze, G) == 14
    assert leap_out_published(13, zs, ze, G, "one_bits") == 16
    with pytest.raises(ValueError):
        leap_out_published(13, zs, ze, G, "other")


def test_published_exit_misses_and_exact_does_not():
    # the published rule ends at the envelope in both cases (14 and 29), which is None here: no exit
    for box, z, truth, said in ((Box((1, 1), (2, 3)), 11, 13, None), (Box((1, 1), (7, 2)), 22, 26, None)):
        zs, ze = box.envelope(G)
        assert leap_out_exact(z, zs, ze, G) == truth and leap_out_published(z, zs, ze, G) == said


def test_leaps_equal_enumeration_on_all_small_boxes():
    wrong = [0, 0]
    for box in all_boxes(2, 3):
        zs, ze = box.envelope(G)
        cells = {z for z in range(64) if inside(z, zs, ze, G)}
        for z in range(64):
            want = next((y for y in range(z, 64) if y in cells), None)
            assert all(f(z, zs, ze, G) == want for f in LEAPS_IN.values())
        for z in cells:
            want = next((y for y in range(z + 1, ze) if y not in cells), None)
            assert leap_out_exact(z, zs, ze, G) == want
            if z == zs or z - 1 not in cells:
                for k, rule in enumerate(("zero_bits", "one_bits")):
                    said = leap_out_published(z, zs, ze, G, rule)
                    wrong[k] += said != want
                    assert said is None or want is not None and said >= want
    assert wrong == [207, 1263]


@pytest.mark.parametrize(("m", "bits"), [(1, 6), (2, 5), (3, 3), (4, 2)])
def test_refiners_cover_exactly(m, bits):
    spec = ZSpec.grid(m, bits)
    for box in random_boxes(m, bits, 40):
        zs, ze = box.envelope(spec)
        cells = [z for z in range(1 << spec.key_bits) if inside(z, zs, ze, spec)]
        exact = refine_leaps(box, spec)
        assert [z for a, b in exact.pieces for z in range(a, b + 1)] == cells
        assert all(b + 1 < c for (_, b), (c, _) in itertools.pairwise(exact.pieces))
        slow = refine_leaps(box, spec, "exact", "bits", max_leaps=10**9)
        assert (slow.pieces, slow.leaps) == (exact.pieces, exact.leaps)
        scan = refine_scan(box, spec)
        assert scan.pieces == refine_scan(box, spec, "deviation").pieces == exact.pieces
        assert volume(box) - 1 <= scan.visits <= volume(box) + len(scan.pieces)
        for method in ("published", "published_one_bits", "widened"):
            got = refine(box, spec, method, threshold=4)
            assert set(cells) <= {z for a, b in got.pieces for z in range(a, b + 1)}


def test_face_costs_and_widening():
    spec, box = ZSpec.grid(2, 3), Box((3, 1), (7, 6))
    first = face_costs(box, spec)[0]
    assert (first.dim, first.side, first.value) == (0, "lo", 6)
    wider = widen_face(box, 0, "lo")
    assert wider.lo[0] == 2 and face_costs(wider, spec)[0].value == 3
    assert surface(Box((0, 0), (3, 1))) == 2 * (2 + 4)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 4), st.data())
def test_widened_box_holds_the_box(m, data):
    spec = ZSpec.grid(m, 6)
    ends = [sorted(data.draw(st.tuples(st.integers(0, 63), st.integers(0, 63)))) for _ in range(m)]
    box = Box(tuple(a for a, _ in ends), tuple(b for _, b in ends))
    w = widen(box, spec, 10)
    assert all(a <= b for a, b in zip(w.box.lo, box.lo, strict=True)) and all(a >= b for a, b in zip(w.box.hi, box.hi, strict=True))
    assert w.total == total_face_cost(w.box, spec)
    assert w.total <= 10 or all(c.edge for c in face_costs(w.box, spec))
    assert widen(box, spec, float("inf")).steps == 0 and widen(box, spec, Fraction(1, 3)).total >= 0
    z = spec.interleave(box.lo)
    assert spec.deinterleave(z) == box.lo


def test_behaviour_by_length_and_dimension():
    """Leaping in alone costs the volume, leaping both ways the surface, widening a bounded number."""
    spec = ZSpec.grid(2, 10)
    sweep = [Box((101, 203), (100 + s, 202 + s)) for s in (16, 32, 64, 128)]
    scan = [refine_scan(b, spec).visits for b in sweep]
    leap = [refine_leaps(b, spec).leaps for b in sweep]
    assert scan[3] > 50 * scan[0] and 4 * leap[0] < leap[3] < 20 * leap[0]
    for m in (2, 3, 4, 5):
        s = ZSpec.grid(m, 10)
        box = Box(tuple(101 + 7 * d for d in range(m)), tuple(200 + 7 * d for d in range(m)))
        c = costs(box, s, "widened")
        assert c["pieces"] <= 600 and c["leaps"] <= 1200
    assert refine_widened(Box((1,) * 6, (130,) * 6), ZSpec.grid(6, 10)).steps > 0


def test_coalescing_and_edges():
    assert coalesce_pieces([(0, 1), (3, 4), (10, 11), (13, 13)], 2) == [(0, 4), (10, 13)]
    assert coalesce_pieces([(0, 1)], 3) == [(0, 1)]
    with pytest.raises(ValueError):
        coalesce_pieces([(0, 1)], 0)
    assert refine(None, G).pieces == []
    full = Box((0, 0), (7, 7))
    assert refine_leaps(full, G).pieces == refine_widened(full, G).pieces == [(0, 63)]
    one = Box((7, 7), (7, 7))
    assert refine_leaps(one, G).pieces == [(63, 63)] == refine_scan(one, G).pieces
    wide = ZSpec.grid(6, 21)  # 126 bits
    box = Box((5,) * 6, (6,) * 6)
    assert sum(b - a + 1 for a, b in refine_leaps(box, wide).pieces) == 64
    with pytest.raises(ValueError):
        refine_scan(Box((0, 0), (1023, 1022)), ZSpec.grid(2, 10), max_visits=1000)


def test_dimensions():
    d = DimSpec("x", -512, 512)
    assert d.quantize_value(-512) == 0 and d.quantize_value(512) == 1023 and d.quantize_value(9999) == 1023 and d.quantize_value(None) is None
    assert DimSpec("x", 0, 9, overflow="null").quantize_value(10) is None
    with pytest.raises(ValueError):
        DimSpec("x", 0, 9, overflow="error").quantize_value(10)
    for bad in ({"lo": 1, "hi": 0}, {"lo": 0, "hi": 1, "bits": 0}, {"lo": 0, "hi": 1, "overflow": "x"}):
        with pytest.raises(ValueError):
            DimSpec("x", **bad)
    spec = ZSpec((d, DimSpec("y", 0.0, 1.0, 8, integer=False)))
    assert ZSpec.from_json(spec.to_json()) == spec and spec.layers == 20
    assert Box.from_conditions(spec, y=(0.5, None)) == Box((None, 0.5), (None, None))
    with pytest.raises(ValueError):
        Box.from_conditions(spec, w=(1, 2))
    assert Box((5, None), (3, None)).cells(spec) is None
    assert Box((None, 0.5), (0, None)).cells(spec) == Box((0, 128), (511, 255))

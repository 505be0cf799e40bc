"""Choosing how a box query reads.

Planning a disjunction costs more with every range (hundreds of ranges take seconds to plan), so at
most ``PUSHED`` ranges are pushed to the scan. Everything finer is a join on key prefixes, whose cost
does not depend on the number of pieces. A box that covers a large part of the domain is read by a
plain scan: no key order helps there."""

from __future__ import annotations

from zbox.refine import Refined
from zbox.spec import ZSpec

PUSHED = 16
SCAN_SHARE = 0.1
STRATEGIES = ("auto", "scan", "pushed_or", "prefix_join", "range_join", "array_search", "manifest")


def choose(r: Refined, spec: ZSpec, stored: bool, asked: str = "auto") -> str:
    if asked not in STRATEGIES:
        raise ValueError(f"strategy {asked} is not one of {STRATEGIES}")
    if asked == "manifest" and not stored:
        return "prefix_join"
    if asked != "auto":
        return asked
    if not stored or r.covered > SCAN_SHARE * (1 << spec.key_bits):
        return "scan"  # a key that is worked out on the way lets nothing be skipped
    return "manifest"


def choose_threshold(row_group_rows: int, rows: int, piece_cost_rows: int = 2_000) -> float:
    """A threshold for widening from the layout: pieces much finer than a row group skip nothing more,
    so there is no gain in more pieces than row groups, nor in fewer than PUSHED."""
    groups = max(1, rows // max(1, row_group_rows))
    return float(min(5_000, max(4 * PUSHED, min(groups, rows // piece_cost_rows + 1))))

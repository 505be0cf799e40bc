"""The positional index: what its tally guarantees and what it drops."""

from itertools import combinations

from pyspark.sql import functions as F

from zbox.llm import simhash


def test_tally_tells_shared_bytes():
    """For every set of differing positions the shared blocks reach the minimum exactly as they should."""
    assert len(simhash.BLOCKS) == 14
    for d in range(9):
        for lost in combinations(range(8), d):
            shared = sum(not set(b) & set(lost) for b in simhash.BLOCKS)
            assert shared == (14, 7, 3)[d] if d <= 2 else shared <= 1


def test_filter_drops_candidates_before_verification(spark):
    base = 0x0123456789ABCDEF
    rows = [base, base ^ 0b11, base ^ 0x0101, base ^ 0x010101, base ^ 0xFF, base ^ 0x01010101, base ^ 0x0101010101]
    signed = lambda x: (x + 2**63) % 2**64 - 2**63
    posts = simhash.postings(spark.createDataFrame([(signed(x),) for x in rows], "fp bigint"))
    a, b = posts.withColumnRenamed("fp", "u"), posts.withColumnRenamed("fp", "v")
    met = {frozenset((r.u, r.v)) for r in a.join(b, ["slot", "bytes"]).filter("u > v").select("u", "v").distinct().collect()}
    kept = {frozenset((r.u, r.v)): r.shared for r in simhash.tallied_pairs(posts, 2).collect()}
    for x, y in combinations(rows, 2):
        equal = sum((x ^ y) >> 8 * k & 255 == 0 for k in range(8))
        pair = frozenset((signed(x), signed(y)))
        assert (pair in kept) == (equal >= 6)
        assert pair in met or pair not in kept
    assert len(kept) < len(met)
    links = {frozenset((r.u, r.v)) for r in simhash.link_fingerprints(spark.createDataFrame([(signed(x),) for x in rows], "fp bigint")).collect()}
    assert links == {frozenset((signed(x), signed(y))) for x, y in combinations(rows, 2) if (x ^ y).bit_count() <= 2} < set(kept)


def test_odd_rows(spark):
    rows = [(None, "a b c d"), (None, "a b c d"), (3, None), (4, ""), (2, "\t"), (5, "A B c D"), (9, "word " * 1_000_000)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").withColumns({"FP": F.lit(1), "component_id": F.lit("x"), "Least": F.lit(2)})
    got = sorted(((r.doc_id, r.fp, r.component_id) for r in simhash.near_duplicates(docs).collect()), key=str)
    assert len(got) == 7 and [c for d, _, c in got if d is None] == [5, 5]
    assert {c for d, _, c in got if d in (2, 3, 4)} == {2}
    assert simhash.near_duplicates(docs.limit(0)).count() == 0

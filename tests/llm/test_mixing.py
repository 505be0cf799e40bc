"""The mix against the optimum of its dual, worked out source by source."""

import math

import pytest
from pyspark.sql import functions as F

from zbox.llm import mixing


def rate(lam, x):
    t = max(-700.0, min(700.0, lam * x))
    return 2 / (1 + math.exp(-t))


def optimum(sizes, target):
    """lambda, in units of the mean size, by halving."""
    scale, low, high = sum(sizes) / len(sizes), -1e5, 1e5
    for _ in range(300):
        mid = (low + high) / 2
        low, high = (mid, high) if sum(s * rate(mid, s / scale) for s in sizes) < target else (low, mid)
    return (low + high) / 2


def docs_of(spark, sizes):
    rows = [(i, "w " * n if n else None, s) for i, (s, n) in enumerate((s, n) for s, ns in sizes.items() for n in ns)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, source string")


def reshared(sizes):
    """Targets by resharing what is above, again and again."""
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    total, full = 1.5 * sum(map(sum, sizes.values())), set()
    while True:
        rest = total - sum(2 * sum(sizes[s]) for s in full)
        open_ = sum(weight[s] for s in order if s not in full)
        target = {s: 2.0 * sum(sizes[s]) if s in full else rest * weight[s] / open_ for s in order}
        more = {s for s in order if s not in full and target[s] > 2 * sum(sizes[s])}
        if not more:
            return target
        full |= more


CASES = {
    "three": {"a": [2], "b": [2], "c": [2]},
    "tiny": {"a": [1], "b": [1, 1], "c": [3], "d": [0, 0]},
    "mixed": {"a": [5, 7, 7, 30, 400] * 8, "b": list(range(1, 90)), "c": [1000, 3], None: [12] * 50, "z": [0]},
    "one long": {"a": [20_000, 1, 1, 1], "b": [10] * 300, "c": [1, 50_000]},
}


@pytest.mark.parametrize("case", CASES)
def test_targets_and_nearness(spark, case):
    sizes = CASES[case]
    got = mixing.mix(docs_of(spark, sizes), carry=("source",)).collect()
    assert len(got) == sum(map(len, sizes.values()))
    want = reshared(sizes)
    for s, ns in sizes.items():
        mine = [r for r in got if r.source == s]
        assert sorted(r.size for r in mine) == sorted(ns)
        assert all(r.source_size == sum(ns) and 0 <= r.taken <= 2 * r.size for r in mine)
        assert all(r.target == pytest.approx(want[s], rel=1e-12) for r in mine)
        # no single text more or less would bring the source nearer by its whole size
        off = want[s] - sum(r.taken for r in mine)
        room = [r.size for r in mine if r.size and (r.copies < 2 if off > 0 else r.copies > 0)]
        assert not room or min(room) > abs(off) - 1


def test_multipliers_are_the_dual_optimum(spark):
    sizes = CASES["mixed"] | {"y": [3, 9, 27, 81, 243, 729] * 20}
    cells = docs_of(spark, sizes).select(F.coalesce(F.concat(F.lit("="), "source"), F.lit("")).alias("skey"), "source", F.coalesce(F.size(F.split(F.trim("text"), " ")), F.lit(0)).alias("size"))
    cells = cells.withColumn("size", F.when(F.col("size") < 0, 0).otherwise(F.col("size")).cast("bigint")).groupBy("skey", "source", "size").agg(F.count("*").alias("n"))
    sources = cells.groupBy("skey", "source").agg(F.sum(F.col("n") * F.col("size")).alias("source_size"), F.sum("n").alias("docs"))
    state = {r.source: r for r in mixing.balance(cells.drop("source"), mixing.source_targets(sources)).collect()}
    for s, ns in sizes.items():
        if 0 < state[s].target < 2 * sum(ns):
            lam = state[s]["lambda"]
            assert sum(n * rate(lam, n / state[s].scale) for n in ns) == pytest.approx(state[s].target, abs=0.02)
            if sum(1 for n in ns if n):
                assert lam == pytest.approx(optimum([n for n in ns], state[s].target), rel=1e-3, abs=1e-4)
        else:
            assert state[s]["lambda"] == 0


def test_odd_rows(spark):
    docs = docs_of(spark, {"a": [3, 3], None: [2]})
    odd = docs.unionByName(spark.createDataFrame([(None, "x y z", "a"), (None, "x y z", "a"), (7, "", None), (8, "long " * 1_000_000, "b")], docs.schema))
    odd = odd.withColumns({"Size": F.lit("own"), "TAKEN": F.lit(1)})
    got = mixing.mix(odd).collect()
    assert len(got) == 7 and sum(r.doc_id is None for r in got) == 2 and max(r.size for r in got) == 1_000_000
    assert sorted(map(str, mixing.mix(odd).collect())) == sorted(map(str, got))
    taken = mixing.take(odd)
    assert taken.columns == odd.columns and {r.Size for r in taken.collect()} == {"own"}
    assert mixing.mix(odd.limit(0)).count() == 0

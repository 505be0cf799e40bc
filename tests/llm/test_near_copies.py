"""The pipeline's near-duplicate stage against all pairs by brute force."""

import random

import pytest
from pyspark.sql import functions as F

from zbox.llm import shingles

RNG = random.Random(3)
VOCABULARY = [f"w{i}" for i in range(5000)]


def text(n):
    return [RNG.choice(VOCABULARY) for _ in range(n)]


def edited(words, k):
    out = list(words)
    for i in RNG.sample(range(len(out)), k):
        out[i] = RNG.choice(VOCABULARY)
    return out


def grams(t):
    w = t.lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}


def components(texts):
    root, sets = list(range(len(texts))), [grams(t) for t in texts]

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 10 * both >= 8 * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(texts))]


@pytest.mark.parametrize("heap", [0, 150])
def test_near_copies_with_a_few_edits_go(spark, heap):
    import corpus_pipeline as p

    base = [text(n) for n in [300] * 20 + [40] * 20 + [120] * 20]
    some = [*base, *(edited(b, max(1, k * len(b) // 100)) for b in base for k in (1, 2, 4)), ["one", "two"], ["one", "three"]]
    one = text(200)
    some += [edited(one, RNG.choice([1, 2, 3])) for _ in range(heap)]
    some = [" ".join(x) for x in some]
    some.append(some[0].upper().replace(" ", "  "))
    RNG.shuffle(some)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(some)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    want = components(some)
    assert len(set(want)) < len(some) - 60  # the planted copies are within the bound
    kept = [r.doc_id for r in p.keep_one_of_near_copies(spark, docs, "").collect()]
    assert sorted(kept) == sorted(set(want))


def test_candidates_of_a_heap_grow_with_its_size(spark):
    one = text(200)
    some = [(i, [int(x) for x in shingles.bands(shingles.shingles(" ".join(edited(one, 1)))).view("int64")]) for i in range(400)]
    df = spark.createDataFrame(some, "node bigint, bands array<bigint>")
    assert shingles.candidates(df).filter(F.col("u") == F.col("v")).count() == 0
    assert shingles.candidates(df, list_cap=8).count() <= 400 * shingles.BANDS * 4


def linked(spark, some, bands, fps):
    """Links of texts under the given bands and fingerprints, as pairs of texts."""
    docs = spark.createDataFrame([(x,) for x in some], "text string").withColumn("node", F.xxhash64("text"))
    marks = spark.createDataFrame([(x, b, f) for x, b, f in zip(some, bands, fps, strict=True)], "text string, bands array<bigint>, fp bigint")
    distinct = docs.join(marks, "text").select("node", "bands", "fp")
    names = {r.node: r.text for r in docs.collect()}
    return {frozenset((names[r.u], names[r.v])) for r in shingles.links(docs.select("text"), distinct).collect()}, names


def test_links_among_texts_of_one_fingerprint_that_the_least_is_not_similar_to(spark):
    some = [" ".join(text(60)) for _ in range(8)]
    near = [f"{t} more" for t in some]
    both = some + near
    found, _ = linked(spark, both, [[i] for i in range(len(both))], [5] * 8 + [7] * 8)  # linked by two bits or fewer
    assert found == {frozenset(x) for x in zip(some, near, strict=True)}


def test_links_within_a_long_band_that_no_centre_has(spark):
    some = [" ".join(text(60)) for _ in range(60)]
    near = [f"{t} more" for t in some]
    both = some + near
    fps = [(i + 1) * 0x0123_4567_89AB_CDEF % (1 << 62) for i in range(len(both))]
    found, _ = linked(spark, both, [[1, 1000 + i] for i in range(len(both))], fps)
    assert found == {frozenset(x) for x in zip(some, near, strict=True)}
